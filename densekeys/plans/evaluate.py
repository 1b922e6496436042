"""Evaluation: slots and ids for the keys of any table.

A small artifact travels to the executors and every probe row is answered where it is. A large one stays
partitioned: probe rows and super-buckets meet by one exchange of each. A non-member gets the slot of some
member, or null where its bucket is empty; `verify` compares with stored signatures."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from densekeys.functions.encode import encode_key
from densekeys.plans.build import Artifact, functions_of
from densekeys.plans.fingerprints import as_longs, as_words, native_words, word_count, words_of
from densekeys.plans.params import Params, family

BROADCAST_BYTES = 256 << 20


def stored_bytes(artifact: Artifact) -> int:
    """An upper estimate of the packed arrays, from counts alone."""
    return artifact.n_slots // 4 + artifact.n // 4 + 80 * min(artifact.n, 1 << artifact.b) + 1024


def _addressed(words: np.ndarray, b: int) -> np.ndarray:
    hi = words[:, 0].astype(np.uint64) << np.uint64(32) | words[:, 1]
    return (hi >> np.uint64(64 - b)).astype(np.int64) if b else np.zeros(len(words), np.int64)


def _answers(functions, words: np.ndarray, b: int, params: Params, attempt: int) -> tuple[np.ndarray, np.ndarray]:
    return functions.evaluate(_addressed(words, b), family(params, attempt).values.sums(words), params.popcount_bits)


def _with_words(df: DataFrame, cols: list[str], artifact: Artifact) -> DataFrame:
    """The table with its key, or for the native family its two fingerprint halves."""
    key = encode_key(df, cols, artifact.params.max_bytes)
    if artifact.params.native:
        hi, lo = native_words(key, artifact.params, artifact.attempt)
        return df.withColumns({"_hi": F.when(key.isNotNull(), hi), "_lo": lo})
    return df.withColumn("_key", key)


def _batch_words(batch: pa.RecordBatch, params: Params, attempt: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows that have a key, and their words."""
    name = "_hi" if params.native else "_key"
    column = batch.column(batch.schema.get_field_index(name))
    some = np.flatnonzero(column.is_valid().to_numpy(zero_copy_only=False))
    if params.native:
        hi, lo = (batch.column(batch.schema.get_field_index(c)).take(pa.array(some)).to_numpy() for c in ("_hi", "_lo"))
        return some, as_words(hi, lo)
    return some, words_of(column.take(pa.array(some)), params, attempt)[:, : word_count(params)]


def lookup(df: DataFrame, artifact: Artifact, cols: str | list[str] | None = None, mode: str = "auto", slot: str = "slot", id: str = "id") -> DataFrame:
    """`df` with a slot (collision-free, below 2 tau over all) and, for a minimal function, an id below n."""
    cols = artifact.cols if cols is None else [cols] if isinstance(cols, str) else list(cols)
    if mode == "auto":
        mode = "broadcast" if stored_bytes(artifact) <= BROADCAST_BYTES else "partitioned"
    params, attempt, b = artifact.params, artifact.attempt, artifact.b
    minimal = params.kind == "mphf"
    fields = [*df.schema.fields, T.StructField(slot, T.LongType()), *([T.StructField(id, T.LongType())] if minimal else [])]
    names = df.columns
    out_schema = T.StructType(fields)

    def answered(batch, functions):
        some, words = _batch_words(batch, params, attempt)
        results = []
        for values in _answers(functions, words, b, params, attempt)[: 1 + minimal]:
            full = np.full(batch.num_rows, -1)
            full[some] = values
            results.append(pa.array(full, mask=full < 0))
        return [*(batch.column(k) for k in range(len(names))), *results]

    probe = _with_words(df, cols, artifact)
    out_names = [f.name for f in fields]
    if mode == "broadcast":
        rows = df.sparkSession.sparkContext.broadcast([r.asDict() for r in artifact.rows.collect()])

        def run(batches):
            functions = functions_of(rows.value, params)
            for batch in batches:
                yield pa.RecordBatch.from_arrays(answered(batch, functions), out_names)

        return probe.mapInArrow(run, out_schema)

    # the super-bucket of a probe row needs its words; they travel instead of the key
    if not params.native:

        def hashed(batches):
            for batch in batches:
                some, words = _batch_words(batch, params, attempt)
                if words.shape[1] == 3:
                    words = np.concatenate([words, np.zeros((len(words), 1), np.uint32)], axis=1)
                halves = []
                for half in as_longs(words):
                    full, known = np.zeros(batch.num_rows, np.int64), np.zeros(batch.num_rows, bool)
                    full[some], known[some] = half, True
                    halves.append(pa.array(full, mask=~known))
                yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(len(names))), *halves], [*names, "_hi", "_lo"])

        probe = probe.mapInArrow(hashed, T.StructType([*df.schema.fields, T.StructField("_hi", T.LongType()), T.StructField("_lo", T.LongType())]))
    top = F.shiftrightunsigned("_hi", 64 - artifact.super_bits) if artifact.super_bits else F.lit(0).cast("long")
    # a null key meets no super-bucket; spread, so that they don't gather in one task
    probe = probe.withColumn("_super", F.when(F.col("_hi").isNotNull(), top).otherwise(-1 - F.pmod(F.monotonically_increasing_id(), F.lit(64))))

    def meet(keys, left, right):
        functions = functions_of(right.to_pylist(), params)
        left = left.combine_chunks()
        hi = left.column("_hi")
        some = np.flatnonzero(hi.is_valid().to_numpy())
        words = as_words(*(left.column(c).take(pa.array(some)).to_numpy() for c in ("_hi", "_lo")), word_count(params))
        results = []
        for values in _answers(functions, words, b, params, attempt)[: 1 + minimal]:
            full = np.full(left.num_rows, -1)
            full[some] = values
            results.append(pa.array(full, mask=full < 0))
        return pa.table([*(left.column(c) for c in names), *results], names=out_names)

    return probe.groupBy("_super").cogroup(artifact.rows.groupBy("super")).applyInArrow(meet, out_schema)


def verify(df: DataFrame, artifact: Artifact) -> DataFrame:
    """n, smallest and largest id, distinct ids over the distinct non-null keys of `df`; for a function of kind phf, of slots."""
    members = df.select(*(F.col(f"`{c}`") for c in artifact.cols)).dropDuplicates()
    found = lookup(members, artifact)
    name = "id" if artifact.params.kind == "mphf" else "slot"
    key = encode_key(members, artifact.cols, artifact.params.max_bytes)
    return found.where(key.isNotNull()).agg(F.count(F.lit(1)).alias("n"), F.min(name).alias("min_id"), F.max(name).alias("max_id"), F.countDistinct(name).alias("n_ids"))
