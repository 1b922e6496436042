"""Written cuts in the folder that all executors share."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_path(spark: SparkSession, label: str) -> str:
    """A new path under spark.checkpoint.dir, or under the warehouse where that is unset (local tests)."""
    folder = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    folder = folder or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_shared"
    return f"{folder.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str) -> DataFrame:
    spark = df.sparkSession
    path = shared_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def forgotten(*frames: DataFrame) -> None:
    """Delete what `written` made of each, once nothing reads it any more."""
    for frame in frames:
        spark = frame.sparkSession
        for folder in {f.rsplit("/", 1)[0] for f in frame.inputFiles()}:
            place = spark._jvm.org.apache.hadoop.fs.Path(folder)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)
