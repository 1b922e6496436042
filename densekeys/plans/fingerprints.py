"""From key columns to distinct fingerprints. Repeated keys are reduced before anything is exchanged."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from densekeys.functions.encode import encode_key
from densekeys.plans.params import Params, family

SCHEMA = "hi long, lo long, check_word long"


def key_bytes(keys: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a binary column as they lie in its buffers, and where each key begins (and the end)."""
    if keys.type != pa.binary():
        keys = keys.cast(pa.binary())
    _, places, data = keys.buffers()
    ends = np.frombuffer(places, np.int32)[keys.offset : keys.offset + len(keys) + 1].astype(np.int64) if len(keys) else np.zeros(1, np.int64)
    return np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8), ends


def words_of(keys: pa.Array, params: Params, attempt: int) -> np.ndarray:
    """32-bit words of binary keys (no nulls); a 96-bit family leaves the fourth word zero."""
    words = family(params, attempt).fingerprint(*key_bytes(keys))
    if params.gamma < 128:  # narrowed on purpose, to exercise restarts
        for k in range(words.shape[1]):
            keep = min(32, max(0, params.gamma - 32 * k))
            words[:, k] &= np.uint32(((1 << keep) - 1) << (32 - keep) & 0xFFFFFFFF)
    return words if words.shape[1] == 4 else np.concatenate([words, np.zeros((len(words), 1), np.uint32)], axis=1)


def as_longs(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    w = words.astype(np.uint64)
    return (w[:, 0] << np.uint64(32) | w[:, 1]).view(np.int64), (w[:, 2] << np.uint64(32) | w[:, 3]).view(np.int64)


def as_words(hi: np.ndarray, lo: np.ndarray, count: int = 4) -> np.ndarray:
    hi, lo = hi.astype(np.int64).view(np.uint64), lo.astype(np.int64).view(np.uint64)
    out = np.stack([hi >> np.uint64(32), hi & np.uint64(0xFFFFFFFF), lo >> np.uint64(32), lo & np.uint64(0xFFFFFFFF)], axis=1).astype(np.uint32)
    return out[:, :count]


def word_count(params: Params) -> int:
    return 3 if params.hash == "mix96" else 4


def native_words(key: Column, params: Params, attempt: int) -> tuple[Column, Column]:
    """The xx128 family: two seeded 64-bit hashes in generated code, without leaving the JVM."""
    return tuple(F.xxhash64(key, F.lit(params.master_seed * 1000 + 2 * attempt + k)) for k in range(2))


def fingerprint(df: DataFrame, cols: list[str], params: Params, attempt: int) -> DataFrame:
    """A row for each non-null key: 128-bit fingerprint, and a check word that tells a repeated key from a collision."""
    keys = df.select(encode_key(df, cols, params.max_bytes).alias("key")).where("key is not null")
    if params.native:
        hi, lo = native_words(F.col("key"), params, attempt)
        return keys.select(hi.alias("hi"), lo.alias("lo"), F.xxhash64("key", F.lit(71)).alias("check_word"))

    def run(batches):
        for batch in batches:
            hi, lo = as_longs(words_of(batch.column(0), params, attempt))
            # repeated keys of the batch needn't leave the worker; equal ones lie together, but for words that agree in one half
            order = np.argsort(hi, kind="stable")
            rows = [x[order] for x in (hi, lo, batch.column(1).to_numpy())]
            new = np.ones(len(hi), bool)
            new[1:] = np.any([x[1:] != x[:-1] for x in rows], axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(x[new]) for x in rows], ["hi", "lo", "check_word"])

    return keys.select("key", F.xxhash64("key", F.lit(71)).alias("check_word")).mapInArrow(run, SCHEMA)


def distinct_fingerprints(prints: DataFrame) -> DataFrame:
    """One row for each fingerprint; `collided` where two different keys share it. A hot key leaves each task as one row."""
    found = prints.groupBy("hi", "lo").agg(F.min("check_word").alias("low"), F.max("check_word").alias("high"))
    return found.select("hi", "lo", (F.col("low") != F.col("high")).alias("collided"))


def super_bucket(super_bits: int) -> Column:
    """The top bits of a fingerprint."""
    return F.shiftrightunsigned("hi", 64 - super_bits) if super_bits else F.lit(0).cast("long")
