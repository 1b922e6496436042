"""Streaming queries over the events, split into files by time; each drains its input and is compared with batch SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densekeys.operators.filters import build_filter
from densekeys.plans.build import build_two_level
from densekeys.plans.evaluate import verify
from densekeys.plans.params import Params
from densekeys.shared import shared_path
from densekeys.streaming import streams
from densekeys.workloads.methods import table


def _events(spark: SparkSession, sf_dir: str, files: int = 3) -> DataFrame:
    """The events as a stream of files in the order of time."""
    path = shared_path(spark, "events")
    events = table(spark, sf_dir, "events")
    events.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(path)
    return streams.event_stream(spark, path, events.schema)


def stream_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of the stream's users are those of the users: as many, and none unknown."""
    users = table(spark, sf_dir, "events").select("user_id")
    found = streams.drained(streams.lookup_stream(_events(spark, sf_dir).select("event_id", "user_id"), build_two_level(users, "user_id", Params(hash="xx128")), "user_id"), "lookup")
    return found.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("id").alias("ids"), F.countDistinct("user_id", "id").alias("pairs"), F.count_if(F.col("id").isNull()).alias("unknown"))


def stream_membership(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Members all pass; what is sent to the side output is no member."""
    members = build_filter(table(spark, sf_dir, "events").select("user_id").where("user_id % 2 = 0"), "user_id", 8)
    path = shared_path(spark, "membership")

    def split(batch: DataFrame, number: int) -> None:
        for name, part in zip(("known", "unknown"), streams.split_known(batch, members, "user_id"), strict=True):
            part.write.mode("overwrite").parquet(f"{path}/{name}/batch={number}")

    stream = _events(spark, sf_dir).select("event_id", "user_id")
    stream.writeStream.foreachBatch(split).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    known, unknown = (spark.read.schema("event_id long, user_id long, batch int").parquet(f"{path}/{name}") for name in ("known", "unknown"))
    return known.agg(F.count_if(F.col("user_id") % 2 == 0).alias("members_known")).crossJoin(unknown.agg(F.count_if(F.col("user_id") % 2 == 0).alias("members_unknown"), (F.count(F.lit(1)) > 0).alias("some_unknown")))


def _closed(found: DataFrame) -> DataFrame:
    return found.select(F.unix_seconds("start").alias("start"), *[c for c in found.columns if c != "start"])


def op_stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _closed(streams.drained(streams.windowed_counts(_events(spark, sf_dir), "1 day"), "tumbling", "complete"))


def op_stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _closed(streams.drained(streams.windowed_counts(_events(spark, sf_dir), "2 days", "1 day"), "sliding", "complete"))


def op_stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = streams.drained(streams.session_counts(_events(spark, sf_dir), "6 hours", "3650 days"), "session", "complete")
    return _closed(found)


def op_stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream that carries every event twice keeps one of each."""
    path = shared_path(spark, "twice")
    events = table(spark, sf_dir, "events")
    events.union(events).repartition(3, "event_id").write.parquet(path)
    stream = streams.event_stream(spark, path, events.schema)
    return streams.drained(streams.deduplicated(stream, ["event_id"], "3650 days").select("event_id"), "dedup")


def op_stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An event older than the watermark of the batch before changes no window; one within it does."""
    path = shared_path(spark, "late")
    rows = [[(1, "2024-01-02 00:00:00"), (2, "2024-01-02 12:00:00")], [(3, "2024-01-05 00:00:00")], [(8, "2024-01-05 12:00:00")], [(4, "2024-01-02 01:00:00"), (5, "2024-01-04 23:00:00")], [(6, "2024-01-09 00:00:00")], [(7, "2024-01-12 00:00:00")]]
    for k, part in enumerate(rows):
        spark.createDataFrame([(i, "x", t) for i, t in part], "event_id long, event_type string, ts string").withColumn("ts", F.to_timestamp_ntz("ts")).coalesce(1).write.mode("append").parquet(f"{path}/part={k}")
    # the files are read in the order in which they were written
    stream = spark.readStream.schema("event_id long, event_type string, ts timestamp_ntz, part int").option("maxFilesPerTrigger", 1).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    found = streams.drained(streams.windowed_counts(stream.select("event_id", "event_type", "ts"), "1 day", late="1 day"), "late")
    return found.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n")


def op_stream_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = streams.drained(streams.counted_by_user(_events(spark, sf_dir).select("user_id", "value")), "state")
    return found.groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max_by("total", "n"), 4).alias("total"))


def op_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    clicks = _events(spark, sf_dir).where("event_type = 'click'")
    buys = _events(spark, sf_dir).where("event_type = 'purchase'")
    return streams.drained(streams.interval_join(clicks, buys, "user_id", "1 HOUR", "3650 days").select("first_id", "second_id"), "join")


def stream_rebuild(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last published function numbers all users."""
    versions: dict[int, object] = {}
    streams.rebuild_on_batch(_events(spark, sf_dir).select("user_id"), "user_id", versions.__setitem__)
    return verify(table(spark, sf_dir, "events").select("user_id"), versions[max(versions)])


QUERIES = {f.__name__: f for f in (stream_lookup, stream_membership, op_stream_tumbling, op_stream_sliding, op_stream_session, op_stream_dedup, op_stream_late, op_stream_state, op_stream_join, stream_rebuild)}
_seconds = "floor(epoch(ts))::BIGINT"
ORACLES = {
    "stream_lookup": "SELECT count(*) AS n, count(DISTINCT user_id) AS ids, count(DISTINCT user_id) AS pairs, 0::BIGINT AS unknown FROM events",
    "stream_membership": "SELECT count(*) FILTER (WHERE user_id % 2 = 0) AS members_known, 0::BIGINT AS members_unknown, true AS some_unknown FROM events",
    "op_stream_tumbling": f"SELECT {_seconds} // 86400 * 86400 AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "op_stream_sliding": f"SELECT s AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([{_seconds} // 86400 * 86400, {_seconds} // 86400 * 86400 - 86400]) AS s FROM events) GROUP BY 1, 2",
    "op_stream_session": """WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT floor(epoch(min(ts)))::BIGINT AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k""",
    "op_stream_dedup": "SELECT event_id FROM events",
    "op_stream_late": "SELECT * FROM (VALUES ('2024-01-02', 2::BIGINT), ('2024-01-04', 1::BIGINT), ('2024-01-05', 2::BIGINT), ('2024-01-09', 1::BIGINT)) t(day, n)",
    "op_stream_state": "SELECT user_id, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY user_id",
    "op_stream_join": "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    "stream_rebuild": "SELECT n, 0::BIGINT AS min_id, n - 1 AS max_id, n AS n_ids FROM (SELECT count(DISTINCT user_id) AS n FROM events)",
}
