"""Structured Streaming around a static function.

A function numbers a fixed set; a stream looks keys up, sends unknown ones to a side output, and a batch job
rebuilds the function from time to time under a new version."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from densekeys.operators.filters import SlotFilter, might_contain
from densekeys.plans.build import Artifact, build_two_level
from densekeys.plans.evaluate import lookup
from densekeys.plans.params import Params
from densekeys.shared import shared_path


def event_stream(spark: SparkSession, folder: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Files of events as a stream, with `ts` as an instant that watermarks accept."""
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, label: str, mode: str = "append") -> DataFrame:
    """Run a query until its input ends, into files, and read them."""
    spark = stream.sparkSession
    path = shared_path(spark, label)
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", f"{path}/data").outputMode("append")
    else:
        writer = stream.writeStream.outputMode(mode).foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(f"{path}/data"))
    writer.option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/data")


def lookup_stream(stream: DataFrame, artifact: Artifact, col: str) -> DataFrame:
    """Stream rows with slot and id of their key; the artifact travels once, with the query."""
    return lookup(stream, artifact, col, mode="broadcast")


def split_known(batch: DataFrame, members: SlotFilter, col: str) -> tuple[DataFrame, DataFrame]:
    """Rows whose key may be a member, and rows whose key surely isn't: those wait for a rebuild and are never numbered."""
    probed = might_contain(batch, members, col)
    return probed.where("maybe").drop("maybe"), probed.where("not maybe").drop("maybe")


def windowed_counts(stream: DataFrame, size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.withWatermark("ts", late).groupBy(window, "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def session_counts(stream: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("s.start").alias("start"), "user_id", "n")


def deduplicated(stream: DataFrame, cols: list[str], late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(cols)


def counted_by_user(stream: DataFrame) -> DataFrame:
    """A running count and sum for each user, kept in the state store: one row for each user and batch."""

    def count(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for batch in batches:
            n, total = n + len(batch), total + float(batch["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return stream.groupBy("user_id").applyInPandasWithState(count, "user_id long, n long, total double", "n long, total double", "append", GroupStateTimeout.NoTimeout)


def interval_join(left: DataFrame, right: DataFrame, key: str, within: str, late: str = "1 day") -> DataFrame:
    """Rows of `right` at most `within` after a row of `left` of the same key; both sides are forgotten past their watermark."""
    a = left.withWatermark("ts", late).select(F.col("event_id").alias("first_id"), F.col(key).alias("first_key"), F.col("ts").alias("first_ts"))
    b = right.withWatermark("ts", late).select(F.col("event_id").alias("second_id"), F.col(key).alias("second_key"), F.col("ts").alias("second_ts"))
    near = (F.col("second_ts") >= F.col("first_ts")) & (F.col("second_ts") <= F.col("first_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, (F.col("first_key") == F.col("second_key")) & near)


def rebuild_on_batch(stream: DataFrame, col: str, publish: Callable[[int, Artifact], None], params: Params = Params(hash="xx128")) -> None:
    """After each micro-batch, a function over all keys so far, published under the batch's number."""
    path = shared_path(stream.sparkSession, "keys")

    def rebuild(df: DataFrame, number: int) -> None:
        df.select(col).dropDuplicates().write.mode("append").parquet(f"{path}/keys")
        keys = df.sparkSession.read.parquet(f"{path}/keys").dropDuplicates()
        publish(number, build_two_level(keys, col, params))

    stream.writeStream.foreachBatch(rebuild).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start().awaitTermination()
