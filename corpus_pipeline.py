"""The corpus pipeline: toxicity, exact dedup, near dedup, shared passages, packing.

Each stage takes the documents that its predecessor kept, and all but the last return the columns of
`documents`. The pipeline writes every stage's result and reads it again for the next."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densekeys.llm import exact_dedup, ngram_join, packing, suffix_dedup, toxicity
from densekeys.llm.common import Cuts, written

VOCABULARY = "word_bpe_49k.json"
#: No SQL can express the classifier; tests/llm checks the stages against brute force.
ORACLE_SQL = None


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, fitted on the labelled documents of the input, rejects go; documents without an id stay only in the clean."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    scored = toxicity.flagged(docs, toxicity.fit_on(docs, labels))
    return scored.where(F.col("score") < 0.5).select(*docs.columns)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str, without_id: bool = False) -> DataFrame:
    """Of equal texts one row stays, found by digest and not by id alone. Documents without an id go first, unless `without_id`."""
    docs = docs if without_id else docs.where("doc_id is not null")
    index = exact_dedup.DigestIndex.create(spark)
    index.dedup(docs)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.struct(*docs.columns).alias("row"), exact_dedup.digest_of(text).alias("digest"), F.length(text).cast("long").alias("n_points"))
    heads = index.read().select(F.col("digest").alias("of"), "keep_id", F.col("n_points").alias("most"))
    is_head = (F.col("digest") == F.col("of")) & (F.col("n_points") == F.col("most")) & F.col("row.doc_id").eqNullSafe(F.col("keep_id"))
    return rows.join(heads, is_head, "left_semi").dropDuplicates(["digest"]).select("row.*")


def drop_copies_of_all(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pipeline's stage: documents without an id stay, too, unless their text is a copy."""
    return drop_copies(spark, docs, sf_dir, without_id=True)


def row_keys(spark: SparkSession, docs: DataFrame, key: str) -> DataFrame:
    """`docs` with a number `key` for each row: its doc_id, or one above all doc_ids if that is null or not its own."""
    repeated = written(docs.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id"), "repeated-ids")
    odd = docs.where("doc_id is null").unionByName(docs.join(repeated, "doc_id", "left_semi").select(*docs.columns))
    odd = written(odd.withColumn(key, F.monotonically_increasing_id()), "odd-rows")
    most = docs.agg(F.max("doc_id")).first()[0] or 0
    last = odd.agg(F.max(key)).first()[0]
    if last is not None and max(most, 0) + 1 + last >= (1 << 63) - 1:
        raise ValueError(f"no numbers are left above doc_id {most}")
    own = docs.where("doc_id is not null").join(repeated, "doc_id", "left_anti").select(*docs.columns, F.col("doc_id").cast("long").alias(key))
    return own.unionByName(odd.withColumn(key, F.col(key) + F.lit(max(most, 0) + 1)))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the smallest document stays; rows without an id of their own count as larger than all others."""
    key = "row_key" + "_" * max(map(len, docs.columns))
    rows = row_keys(spark, docs, key)
    groups = ngram_join.near_groups(rows, id_col=key)
    return rows.join(groups.where("doc_id = component_id").select(F.col("doc_id").alias(key)), key, "left_semi").select(*docs.columns)


def cut_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that a smaller document holds are cut out, to whole characters; a document of which nothing stays keeps its row with an empty text."""
    others = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    cut = suffix_dedup.remove_repeats(docs, carry=others)
    held = {c: F.col(f"carried_{k}") for k, c in enumerate(others)} | {"doc_id": F.col("doc_id"), "text": F.col("kept").cast("string")}
    if "n_chars" in held:
        held["n_chars"] = F.when(F.col("n_removed") > 0, F.length(held["text"]).cast("long")).otherwise(held["n_chars"])
    return cut.select(*(held[c].alias(c) for c in docs.columns))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The kept texts packed into sequences."""
    return packing.pack_documents(docs, public_tokenizers.path(VOCABULARY))


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_copies_of_all),
    ("near_dedup", drop_near_copies),
    ("passages", cut_passages),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, cuts = spark.read.parquet(f"{sf_dir}/documents.parquet"), Cuts(spark)
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = cuts.write(docs, name)
            cuts.drop(docs)  # what the stage read isn't read again
    return docs
