"""How many bucket bits, how large the buckets are, and where each bucket's ids begin."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def analytic_bits(n: int, ell: int = 256) -> int:
    """Bits by the analysis: log n - log(ell / log ell), not below 0."""
    return max(0, math.floor(math.log2(max(n, 1)) - math.log2(ell / math.log2(ell)))) if n > ell else 0


def address(hi: Column, b: int) -> Column:
    """The top b bits of the fingerprint; b = 0 is the bucket 0 (a shift by the whole width would do nothing)."""
    return F.shiftrightunsigned(hi, 64 - b) if b else F.lit(0).cast("long")


def bucket_sizes(prints: DataFrame, b: int) -> DataFrame:
    return prints.groupBy(address(F.col("hi"), b).alias("bucket")).agg(F.count(F.lit(1)).alias("size"))


def largest_buckets(prints: DataFrame, levels: list[int]) -> dict[int, int]:
    """Largest bucket for each number of bits, rolled up from the counts at the most bits; a row for each level reaches the driver."""
    most = max(levels)
    fine = bucket_sizes(prints, most)
    steps = F.explode(F.array(*[F.struct(F.lit(b).alias("b"), F.shiftrightunsigned("bucket", most - b).alias("at")) for b in levels]))
    rolled = fine.select("size", steps.alias("s")).groupBy("s.b", "s.at").agg(F.sum("size").alias("size"))
    return {r["b"]: r["most"] for r in rolled.groupBy("b").agg(F.max("size").alias("most")).collect()}


def choose_bits(prints: DataFrame, n: int, ell: int = 256, method: str = "empirical", at_least: int = 0) -> int:
    """The smallest b whose largest bucket holds at most ell keys, sought around the analytic one."""
    guess = max(analytic_bits(n, ell), at_least)
    if method == "analytic" or n <= ell and not at_least:
        return guess
    low = max(at_least, guess - 1)
    while True:
        found = largest_buckets(prints, list(range(low, low + 6)))
        fitting = [b for b, most in found.items() if most <= ell]
        if fitting:
            return min(fitting)
        low += 6
        if low > 56:
            raise RuntimeError("equal fingerprints keep a bucket overfull")


def prefix_sums(df: DataFrame, key: str, value: str, out: str, block: int = 4096) -> DataFrame:
    """Sum of `value` over all smaller keys, in two levels: within blocks of keys, and over block totals.

    Only the block totals, one row for `block` keys, meet in one task."""
    blocked = df.withColumn("_block", F.floor(F.col(key) / block))
    within = F.coalesce(F.sum(value).over(W.partitionBy("_block").orderBy(key).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    totals = blocked.groupBy("_block").agg(F.sum(value).alias("_total"))
    before = totals.select("_block", F.coalesce(F.sum("_total").over(W.orderBy("_block").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    return blocked.withColumn("_within", within).join(before, "_block").withColumn(out, F.col("_within") + F.col("_before")).drop("_block", "_within", "_before")
