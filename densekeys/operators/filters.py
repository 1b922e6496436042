"""Approximate membership: a signature of a few bits in the slot of each member; and a Bloom filter to compare.

There are no false negatives; a non-member passes with chance about 2**-bits. `semi_reduce` puts the filter
before an exact semi-join."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from densekeys.functions.encode import encode_key
from densekeys.plans.build import Artifact, build_two_level
from densekeys.plans.evaluate import lookup, stored_bytes
from densekeys.plans.params import Params
from densekeys.shared import written

BROADCAST_BYTES = 64 << 20


def signature(df: DataFrame, cols: list[str], bits: int):
    return F.xxhash64(encode_key(df, cols), F.lit(91)).bitwiseAND((1 << bits) - 1)


def signature_of(name: str, bits: int, max_bytes: int) -> str:
    """The signature of a string column as SQL text."""
    key = f"concat(encode({name}, 'UTF-8'), X'01')"
    return f"CAST(xxhash64(CASE WHEN octet_length({key}) > {max_bytes} THEN concat(unhex(sha2({key}, 256)), X'02') ELSE {key} END, 91) & {(1 << bits) - 1} AS INT)"


@dataclass
class SlotFilter:
    artifact: Artifact
    signatures: DataFrame  # id, signature
    bits: int

    @property
    def total_bits(self) -> int:
        return self.bits * self.artifact.n


def build_filter(df: DataFrame, cols: str | list[str], bits: int = 8, params: Params = Params(hash="xx128")) -> SlotFilter:
    artifact = build_two_level(df, cols, params)
    members = df.select(*artifact.cols).dropDuplicates().withColumn("signature", F.lit(0))
    members = members.withColumn("signature", signature(members, artifact.cols, bits))
    found = lookup(members, artifact).where("id is not null and signature is not null").select("id", "signature")
    return SlotFilter(artifact, written(found, "signatures"), bits)


def might_contain(df: DataFrame, members: SlotFilter, cols: str | list[str] | None = None) -> DataFrame:
    """`df` with `maybe`: false only for rows that are surely no members."""
    cols = members.artifact.cols if cols is None else [cols] if isinstance(cols, str) else list(cols)
    probe = lookup(df.withColumn("_signature", signature(df, cols, members.bits)), members.artifact, cols, id="_id", slot="_slot").drop("_slot")
    names = [c for c in df.columns]
    if members.artifact.n * 2 + stored_bytes(members.artifact) <= BROADCAST_BYTES:
        # the signatures as one packed array, of a size that the count of members bounds
        table = members.signatures.toArrow()
        packed = np.zeros(max(1, members.artifact.n), np.int32)
        packed[table.column("id").to_numpy()] = table.column("signature").to_numpy()
        shared = df.sparkSession.sparkContext.broadcast(packed)
        schema = T.StructType([*df.schema.fields, T.StructField("maybe", T.BooleanType())])

        def run(batches):
            for batch in batches:
                ids = batch.column(batch.schema.get_field_index("_id"))
                known = ids.is_valid().to_numpy(zero_copy_only=False)
                at = ids.fill_null(0).to_numpy()
                mine = batch.column(batch.schema.get_field_index("_signature")).fill_null(-1).to_numpy()
                yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(len(names))), pa.array(known & (shared.value[at] == mine))], [*names, "maybe"])

        return probe.mapInArrow(run, schema)
    joined = probe.join(members.signatures.withColumnRenamed("id", "_id"), "_id", "left")
    return joined.select(*names, F.coalesce(F.col("signature") == F.col("_signature"), F.lit(False)).alias("maybe"))


def semi_reduce(fact: DataFrame, keys: DataFrame, fact_col: str, key_col: str, bits: int = 8) -> DataFrame:
    """Rows of `fact` whose key is in `keys`: the filter first, then the exact semi-join on what passes."""
    passed = might_contain(fact, build_filter(keys, key_col, bits), fact_col).where("maybe").drop("maybe")
    return passed.join(keys.select(F.col(key_col).alias(fact_col)), fact_col, "left_semi")


def bloom_parameters(n: int, rate: float) -> tuple[int, int]:
    """Bits and hashes of a Bloom filter for n members."""
    m = max(64, math.ceil(-n * math.log(rate) / math.log(2) ** 2))
    return m, max(1, round(m / max(1, n) * math.log(2)))


def bloom_positions(key, m: int, k: int):
    base = F.pmod(F.xxhash64(key, F.lit(1)), F.lit(m))
    step = F.pmod(F.xxhash64(key, F.lit(2)), F.lit(m - 1)) + 1
    return F.array(*[F.pmod(base + i * step, F.lit(m)) for i in range(k)])


def build_bloom(df: DataFrame, cols: list[str], rate: float) -> tuple[DataFrame, int, int]:
    """The filter as rows of bitmaps, built by bitmap aggregates, with its bits and hashes."""
    n = df.select(*cols).dropDuplicates().count()
    m, k = bloom_parameters(n, rate)
    key = encode_key(df, cols)
    places = df.where(key.isNotNull()).select(F.explode(bloom_positions(key, m, k)).alias("at")).distinct()
    # bitmap rows cover places from one on
    bitmaps = places.select((F.col("at") + 1).alias("at")).groupBy(F.bitmap_bucket_number("at").alias("part")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("at")).alias("bits"))
    return written(bitmaps, "bloom"), m, k


def bloom_contains(df: DataFrame, cols: list[str], bloom: tuple[DataFrame, int, int]) -> DataFrame:
    """`df` with `maybe`; a null key is probed as the empty one."""
    bitmaps, m, k = bloom
    if m > 8 * BROADCAST_BYTES:
        raise ValueError("the bitmap is too large to travel; use a slot filter, which can stay partitioned")
    flat = np.zeros(m // 8 + 4097, np.uint8)
    for row in bitmaps.collect():
        start = (row["part"] - 1) * 4096
        data = np.frombuffer(row["bits"], np.uint8)[: len(flat) - start]
        flat[start : start + len(data)] = data
    shared = df.sparkSession.sparkContext.broadcast(flat)
    schema = T.StructType([*df.schema.fields, T.StructField("maybe", T.BooleanType())])
    names = df.columns
    probe = df.withColumn("_at", bloom_positions(F.coalesce(encode_key(df, cols), F.lit(b"")), m, k))

    def run(batches):
        for batch in batches:
            column = batch.column(batch.num_columns - 1)
            at = column.flatten().to_numpy(zero_copy_only=False).reshape(-1, k).astype(np.int64)
            maybe = (shared.value[at >> 3] >> (at & 7) & 1).all(axis=1)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(len(names))), pa.array(maybe, pa.bool_())], [*names, "maybe"])

    return probe.mapInArrow(run, schema)


def filter_accuracy(probed: DataFrame, is_member: str) -> DataFrame:
    """False negatives, and the rate of false positives, of rows with `maybe` and the true membership."""
    return probed.agg(
        F.count_if(F.col(is_member) & ~F.col("maybe")).alias("false_negatives"),
        F.count_if(~F.col(is_member)).alias("non_members"),
        F.coalesce(F.count_if(~F.col(is_member) & F.col("maybe")) / F.nullif(F.count_if(~F.col(is_member)), F.lit(0)), F.lit(0.0)).alias("rate"),
    )
