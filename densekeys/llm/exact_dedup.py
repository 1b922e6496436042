"""Exact deduplication against a persistent digest index, in DataFrame functions only.

The index is a Parquet table bucketed and sorted by the SHA-256 digest of the text without white space.
A batch is digested once, reduced to one row per digest before anything is shuffled by digest, matched
with the index by a sort-merge anti-join, and what is new is appended. Each row then joins the verdict of
its digest; both sides of that join are plain scans, so adaptive execution can split a hot digest.

Defined cases: a null text is empty, and empty texts equal each other and any text of white space only; a
null doc_id loses every tie; rows that repeat a doc_id are one document and share its verdict; an empty
batch gives an empty result; other columns are ignored.

An index outlives its session: `open` registers the table again from the folder alone. `drop` removes it.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densekeys.llm.common import Cuts, deleted, fresh_path, id_and_text

WHITE_SPACE = r"[\x20\x09-\x0D]+"
INDEX_SCHEMA = "digest binary, keep_id long, n_points long, group_size long, batch string"


def digest_of(text: Column) -> Column:
    """The 32-byte digest of the normalised text."""
    return F.unhex(F.sha2(F.regexp_replace(text, WHITE_SPACE, "").cast("binary"), 256))


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, code points of the original text, and the 32-byte digest of the normalised text."""
    rows = id_and_text(docs, id_col, text_col)
    text = F.coalesce(F.col("text"), F.lit(""))
    return rows.select(
        "doc_id",
        F.length(text).cast("long").alias("n_points"),
        digest_of(text).alias("digest"),
    )


class DigestIndex:
    """A persistent table of digests that have been seen, with the document kept for each."""

    def __init__(self, spark: SparkSession, table: str, path: str, buckets: int):
        self.spark, self.table, self.path, self.buckets = spark, table, path, buckets

    @classmethod
    def create(cls, spark: SparkSession, table: str | None = None, path: str | None = None, buckets: int | None = None):
        """An empty index; `path` is by default a new folder in the shared directory."""
        table = table or f"digest_index_{uuid.uuid4().hex}"
        path = path or fresh_path(spark, "digest-index")
        buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
        index = cls(spark, table, path, buckets)
        spark.createDataFrame([(buckets,)], "buckets int").coalesce(1).write.json(index.manifest)
        index._write(spark.createDataFrame([], INDEX_SCHEMA))
        return index

    @classmethod
    def open(cls, spark: SparkSession, path: str, table: str | None = None):
        """The index in the folder `path`, which an earlier session made."""
        index = cls(spark, table or f"digest_index_{uuid.uuid4().hex}", path, 0)
        index.buckets = spark.read.schema("buckets int").json(index.manifest).first()["buckets"]
        spark.sql(f"CREATE TABLE {index.table} ({INDEX_SCHEMA}) USING parquet CLUSTERED BY (digest) SORTED BY (digest) INTO {index.buckets} BUCKETS LOCATION '{path}'")
        return index

    @property
    def manifest(self) -> str:
        return f"{self.path.rstrip('/')}-manifest"

    def drop(self, files: bool = True) -> None:
        """Forget the table and, with `files`, delete what it holds."""
        self.spark.sql(f"DROP TABLE IF EXISTS {self.table}")
        if files:
            deleted(self.spark, self.path)
            deleted(self.spark, self.manifest)

    def _write(self, rows: DataFrame) -> None:
        (
            rows.select("digest", "keep_id", "n_points", "group_size", "batch")
            .repartition(self.buckets, "digest")
            .write.format("parquet")
            .mode("append")
            .bucketBy(self.buckets, "digest")
            .sortBy("digest")
            .option("path", self.path)
            .saveAsTable(self.table)
        )

    def read(self) -> DataFrame:
        return self.spark.table(self.table)

    def dedup(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """Judge a batch and append what is new.

        Of equal texts in the batch the one with most code points stays, then the smallest doc_id; a text that
        the index holds already keeps its earlier document. group_size counts the batch's rows, and the earlier
        ones that the index recorded."""
        batch = uuid.uuid4().hex
        cuts = Cuts(self.spark)
        members = cuts.write(digests(docs, id_col, text_col), "digests")
        # the complement turns the order of ids round, for every long
        best = F.max(F.struct(F.col("n_points"), F.bitwise_not("doc_id").alias("turned")))
        heads = cuts.write(
            members.groupBy("digest")
            .agg(best.alias("best"), F.count(F.lit(1)).alias("n_rows"))
            .select("digest", F.bitwise_not("best.turned").alias("keep_id"), F.col("best.n_points").alias("n_points"), F.col("n_rows").alias("group_size"), F.lit(batch).alias("batch")),
            "digest-heads",
        )
        new = heads.join(self.read().select("digest").hint("merge"), "digest", "left_anti")
        self._write(cuts.write(new, "digest-new"))
        known = self.read().select("digest", F.col("keep_id").alias("kept_id"), F.col("group_size").alias("earlier"), F.col("batch").alias("seen_in"))
        verdicts = cuts.write(
            heads.drop("keep_id", "n_points", "batch")
            .join(known.hint("merge"), "digest")
            .select(
                "digest",
                F.col("kept_id").alias("keep_id"),
                (F.col("group_size") + F.when(F.col("seen_in") == batch, F.lit(0)).otherwise(F.col("earlier"))).alias("group_size"),
            ),
            "digest-verdicts",
        )
        cuts.drop(members, verdicts)
        return members.join(verdicts, "digest").select(
            "doc_id",
            "keep_id",
            "group_size",
            F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
            F.lower(F.hex("digest")).alias("text_sha256"),
        )
