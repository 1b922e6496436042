"""Components of a graph in DataFrames, and acyclicity of a whole set's graph by distributed peeling."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.shared import forgotten, written


#: Links that one task joins; more are contracted first.
LOCAL_LINKS = 1 << 20


def joined_here(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vertices of the links and the smallest vertex that each reaches."""
    vertices, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = ends[: len(a)], ends[len(a) :]
    root = np.arange(len(vertices))
    while True:
        p, q = root[x], root[y]
        apart = p != q
        if not apart.any():
            return vertices, vertices[root]
        x, y = x[apart], y[apart]
        np.minimum.at(root, np.maximum(p, q)[apart], np.minimum(p, q)[apart])
        while not np.array_equal(above := root[root], root):
            root = above


def _join_links(batches):
    held = [(x.column(0).to_numpy(), x.column(1).to_numpy()) for x in batches]
    if held:
        vertex, component = joined_here(*(np.concatenate(c) for c in zip(*held, strict=True)))
        yield pa.RecordBatch.from_arrays([pa.array(vertex), pa.array(component)], ["vertex", "component"])


def components(edges: DataFrame) -> DataFrame:
    """vertex, component (smallest vertex reached) for edges a, b.

    Links are contracted: each vertex goes to the one, of itself and its neighbours, of the least random word, drawn anew
    in each round, which leaves at most about three quarters of the vertices whatever their order. Few links are joined in one task."""
    loops = edges.where("a = b").select(F.col("a").cast("long").alias("vertex")).distinct()
    links = written(edges.where("a <> b").select(F.least("a", "b").cast("long").alias("a"), F.greatest("a", "b").cast("long").alias("b")).distinct(), "links")
    moves: list[DataFrame] = []
    while links.limit(LOCAL_LINKS + 1).count() > LOCAL_LINKS:
        word = lambda c: F.xxhash64(c, F.lit(len(moves)))
        ends = links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        near = ends.groupBy("a").agg(F.min_by("b", word("b")).alias("near"))
        move = written(near.select(F.col("a").alias("vertex"), F.when(word("near") < word("a"), F.col("near")).otherwise(F.col("a")).alias("component")), "moves")
        to = lambda c: move.select(F.col("vertex").alias(c), F.col("component").alias(f"to_{c}"))
        met = links.join(to("a"), "a").join(to("b"), "b").where("to_a <> to_b")
        fewer = written(met.select(F.least("to_a", "to_b").alias("a"), F.greatest("to_a", "to_b").alias("b")).distinct(), "links")
        forgotten(links)
        links, moves = fewer, [*moves, move]
    found = links.coalesce(1).mapInArrow(_join_links, "vertex long, component long")
    for move in reversed(moves):
        on = found.select(F.col("vertex").alias("component"), F.col("component").alias("root"))
        found = written(move.join(on, "component", "left").select("vertex", F.coalesce("root", "component").alias("component")), "labels")
    least = found.groupBy("component").agg(F.min("vertex").alias("least"))
    linked = found.join(least, "component").select("vertex", F.col("least").alias("component"))
    alone = loops.join(linked.select("vertex"), "vertex", "left_anti").select("vertex", F.col("vertex").alias("component"))
    out = written(linked.union(alone), "labels")
    forgotten(links, *moves)
    return out


def peel(edges: DataFrame) -> tuple[DataFrame, list[DataFrame]]:
    """Edges (key, a, b) left when no vertex has degree one, and the (key, leaf) removed in each round: a forest leaves none.

    The DataFrame form of the whole-set construction, for sets beyond one task; every round is a shuffle."""
    rest, rounds = written(edges.select("key", "a", "b"), "graph"), []
    while True:
        ends = rest.select("key", F.explode(F.array("a", "b")).alias("vertex"))
        leaves = ends.groupBy("vertex").agg(F.count(F.lit(1)).alias("degree"), F.min("key").alias("key")).where("degree = 1")
        # a lone edge has two leaves; its larger vertex is taken, so that its smaller one is the root
        taken = written(leaves.groupBy("key").agg(F.max("vertex").alias("leaf")), "leaves")
        if not taken.limit(1).count():
            break
        rounds.append(taken)
        rest = written(rest.join(taken, "key", "left_anti"), "graph")
    return rest, rounds


def label(edges: DataFrame, rounds: list[DataFrame], right_from: int) -> DataFrame:
    """vertex, label of all leaves: the parent's label, flipped if the leaf is on the right (vertices from `right_from`)."""
    known: DataFrame | None = None
    for taken in reversed(rounds):
        step = taken.join(edges.select("key", "a", "b"), "key").withColumn("parent", F.col("a") + F.col("b") - F.col("leaf"))
        if known is not None:
            step = step.join(known.select(F.col("vertex").alias("parent"), F.col("label").alias("from")), "parent", "left")
        else:
            step = step.withColumn("from", F.lit(False))
        new = step.select(F.col("leaf").alias("vertex"), (F.coalesce("from", F.lit(False)) != (F.col("leaf") >= right_from)).alias("label"))
        known = written(new if known is None else known.union(new), "known-labels")
    return known


def core_slots(edges: DataFrame, right_from: int) -> DataFrame | None:
    """key, slot of an acyclic graph, or None if it has a cycle (draw again): each key takes the end that its labels tell."""
    rest, rounds = peel(edges)
    if rest.limit(1).count():
        return None
    labels = label(edges, rounds, right_from)
    side = lambda c: labels.select(F.col("vertex").alias(c), F.col("label").alias(f"l{c}"))
    joined = edges.join(side("a"), "a", "left").join(side("b"), "b", "left")
    odd = F.coalesce("la", F.lit(False)) != F.coalesce("lb", F.lit(False))
    return joined.select("key", F.when(odd, F.col("b")).otherwise(F.col("a")).alias("slot"))
