"""Joins with one-slot buckets, computed references, identifiers, web graphs, array grouping, basket mining."""

from __future__ import annotations

import math

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from densekeys.operators.filters import build_filter, might_contain
from densekeys.plans.build import Artifact, build_two_level
from densekeys.plans.evaluate import lookup
from densekeys.plans.params import Params
from densekeys.shared import written

FAST = Params(hash="xx128")
#: A dimension of at most so many bytes travels to the probe rows; of a larger one, a task gets so many slots.
SLOT_BYTES = 64 << 20
SLOTS = 1 << 18


def dense_join(fact: DataFrame, dim: DataFrame, on: tuple[str, str], how: str = "inner", artifact: Artifact | None = None, mode: str = "auto") -> DataFrame:
    """Equi-join by slots: the dimension lies in an array by id, one row to a slot, and a probe row reads the one slot of its key.

    There are no chains to follow; the key found is compared with the key sought, as others than members get some slot.
    The dimension key must be unique, which is checked. `how` is inner, left, left_semi or left_anti; both sides keep their
    columns (their names must differ). `mode` is broadcast, partitioned, or auto: by the measured size of the dimension."""
    left, right = on
    if how not in ("inner", "left", "left_semi", "left_anti"):
        raise ValueError(f"unknown join {how}")
    artifact = artifact or build_two_level(dim, right, FAST)
    slots = written(lookup(dim.where(F.col(right).isNotNull()), artifact, right, slot="_slot", id="_slot_id").drop("_slot"), "slots")
    size = slots.agg(F.count(F.lit(1)).alias("n"), F.sum(F.length(F.to_json(F.struct(*dim.columns)))).alias("bytes")).first()
    if size["n"] != artifact.n:
        raise ValueError(f"{size['n']} rows of the dimension have {artifact.n} keys")
    if mode == "auto":
        mode = "broadcast" if (size["bytes"] or 0) <= SLOT_BYTES else "partitioned"
    probe = lookup(fact, artifact, left, slot="_slot", id="_id").drop("_slot")
    names, dim_names, both = fact.columns, dim.columns, how in ("inner", "left")
    schema = T.StructType([*fact.schema.fields, *([T.StructField(f.name, f.dataType, True) for f in dim.schema.fields] if both else [])])

    def met(rows: pa.Table, array: pa.Table, at: pa.Array) -> pa.Table:
        """Probe rows, and the row of the array that each one's slot holds; `at` is null where there is no slot."""
        found = array.select(dim_names).take(at)
        hit = pc.fill_null(pc.equal(rows.column(left), found.column(right)), False)
        rows = rows.select(names)
        if how in ("left_semi", "left_anti"):
            return rows.filter(hit if how == "left_semi" else pc.invert(hit))
        if how == "inner":
            rows, found = rows.filter(hit), found.filter(hit)
        else:
            found = pa.table([pc.if_else(hit, c, pa.scalar(None, c.type)) for c in found.columns], names=found.column_names)
        return pa.table([*rows.columns, *found.columns], names=[*names, *found.column_names])

    if mode == "broadcast":
        shared = fact.sparkSession.sparkContext.broadcast(slots.toArrow().sort_by("_slot_id").combine_chunks())

        def run(batches):
            for batch in batches:
                rows = pa.Table.from_batches([batch])
                yield from met(rows, shared.value, rows.column("_id")).combine_chunks().to_batches()

        return probe.mapInArrow(run, schema)

    def meet(keys, rows, array):
        array = array.sort_by("_slot_id")
        begin = array.column("_slot_id")[0].as_py() if array.num_rows else 0
        at = pc.subtract(rows.column("_id"), begin)
        inside = pc.and_kleene(pc.greater_equal(at, 0), pc.less(at, array.num_rows))
        return met(rows, array, pc.if_else(inside, at, pa.scalar(None, pa.int64())))

    # ids without gaps: a task's stretch of SLOTS ids is an array; a row without an id meets no stretch, and is spread
    spread = F.when(F.col("_id").isNotNull(), F.floor(F.col("_id") / SLOTS)).otherwise(-1 - F.pmod(F.monotonically_increasing_id(), F.lit(64)))
    left_side = probe.withColumn("_part", spread).groupBy("_part")
    return left_side.cogroup(slots.withColumn("_part", F.floor(F.col("_slot_id") / SLOTS)).groupBy("_part")).applyInArrow(meet, schema)


def compress_fk(fact: DataFrame, cols: list[str], artifact: Artifact | None = None, ref: str = "ref") -> DataFrame:
    """The natural columns stay; a dense reference is computed from them, not stored or joined for."""
    artifact = artifact or build_two_level(fact, cols, FAST)
    return lookup(fact, artifact, cols, slot="_slot", id=ref).drop("_slot")


def ref_bits(n: int) -> int:
    return max(1, math.ceil(math.log2(max(2, n))))


def assign_ids(df: DataFrame, col: str) -> DataFrame:
    """Distinct values with ids 0..n-1, by one exchange and without a global sort."""
    values = df.select(col).where(F.col(col).isNotNull()).dropDuplicates()
    return lookup(values, build_two_level(values, col, FAST), slot="_slot").drop("_slot")


def dense_groupby(df: DataFrame, keys: list[str], aggs: list[Column]) -> DataFrame:
    """Group by the dense id of the keys, which come back by `any_value`; null keys form the group that plain grouping gives."""
    return compress_fk(df, keys, ref="_group").groupBy("_group", *[F.col(k).isNull().alias(f"_null_{k}") for k in keys]).agg(*[F.any_value(k).alias(k) for k in keys], *aggs).drop("_group", *[f"_null_{k}" for k in keys])


def page_links(pages: DataFrame) -> DataFrame:
    """An edge for each href of each page."""
    found = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target")
    return pages.select(F.col("url").alias("source"), found)


def label_graph(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges as pairs of vertex labels, and the labels of all vertices."""
    vertices = edges.select(F.col("source").alias("url")).union(edges.select("target")).where("url is not null").dropDuplicates()
    artifact = build_two_level(vertices, "url", FAST)
    labels = lookup(vertices, artifact, slot="_slot", id="vertex").drop("_slot")
    half = lookup(edges, artifact, "source", slot="_s", id="src").drop("_s")
    return lookup(half, artifact, "target", slot="_s", id="dst").select("src", "dst"), labels


def pagerank(edges: DataFrame, labels: DataFrame, iterations: int = 3, damping: float = 0.85) -> DataFrame:
    """Ranks over dense labels; repeated links count once, and what sinks hold goes to all vertices alike."""
    links = written(edges.distinct(), "links")
    n = labels.count()
    out = links.groupBy("src").agg(F.count(F.lit(1)).alias("degree"))
    base = written(labels.select("vertex").join(out, F.col("vertex") == F.col("src"), "left").select("vertex", "degree"), "vertices")
    ranks = base.withColumn("rank", F.lit(1.0 / max(1, n)))
    for _ in range(iterations):
        sunk = ranks.where("degree is null").agg(F.coalesce(F.sum("rank"), F.lit(0.0)).alias("sunk"))
        given = links.join(ranks, F.col("src") == F.col("vertex")).groupBy("dst").agg(F.sum(F.col("rank") / F.col("degree")).alias("given"))
        step = (1 - damping) / n + damping * (F.coalesce("given", F.lit(0.0)) + F.col("sunk") / n)
        ranks = written(base.join(given, F.col("vertex") == F.col("dst"), "left").crossJoin(F.broadcast(sunk)).select("vertex", "degree", step.alias("rank")), "ranks")
    return ranks.select("vertex", "rank")


def adjacency_gaps(edges: DataFrame) -> DataFrame:
    """Sorted neighbours of each vertex as first label and gaps, the form that compresses."""
    lists = edges.distinct().groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("dst"))
    gaps = F.transform("dst", lambda x, i: F.when(i == 0, x).otherwise(x - F.element_at("dst", i)))
    return lists.select("src", F.size("dst").alias("degree"), gaps.alias("gaps"))


def pair_support(rows: DataFrame, basket: str, item: str, min_support: int, bits: int = 8) -> DataFrame:
    """Item pairs of at least min_support baskets.

    Only frequent items can pair. Rows are pruned by a signature filter over these, which keeps all of them and about one in
    2**bits of the others, before the exact check; so no row of an infrequent item is shuffled but those few."""
    items = rows.select(basket, item).where(F.col(basket).isNotNull() & F.col(item).isNotNull()).dropDuplicates()
    frequent = written(items.groupBy(item).count().where(F.col("count") >= min_support).select(item), "frequent-items")
    passed = might_contain(items, build_filter(frequent, item, bits), item).where("maybe").drop("maybe")
    kept = written(passed.join(frequent, item, "left_semi"), "frequent-rows")
    pairs = kept.alias("a").join(kept.alias("b"), (F.col(f"a.{basket}") == F.col(f"b.{basket}")) & (F.col(f"a.{item}") < F.col(f"b.{item}")))
    return pairs.groupBy(F.col(f"a.{item}").alias("first"), F.col(f"b.{item}").alias("second")).agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= min_support)
