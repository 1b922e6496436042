"""N-gram Jaccard join: groups of documents whose word shingles overlap by at least three quarters.

1. Shingles that only one document holds can't be in an intersection. `sharing` tells every part which of its
   shingles are shared, and by how many documents. A document with fewer shared shingles than three quarters
   of all it has can't link; that leaves the candidates.
2. Candidates with equal sets collapse to one node. Two linked nodes hold a common shingle among the rarest
   of each, of which there are `shared - three quarters of all + 1`; the nodes that hold one form its block.
3. Pairs are found in count-vector R-trees: shingles are hashed to GROUPS groups, the counts of a set are a point,
   boxes hold the largest count of each coordinate and the range of sizes, and the summed minima of query and box
   bound the overlap from above. In a first round each node goes to the block that it shares most shingles with
   the smallest node of, and that node is looked up in the block's tree, so that a group of near copies becomes
   one component by as many checks as it has nodes.
4. In each block that still has several components, the nodes outside its largest component are looked up in
   the block's tree. Blocks are divided by size, as linked sets differ by at most a third, and large ones are split
   among tasks, by the square root of their number of nodes, so that copies of queries and trees grow alike.
5. Pairs that the trees let through are verified on the sets; no link can be lost, since a pair is either
   within one component, or bounded below the threshold, or verified.

Defined cases: null and empty texts and texts without words have no shingles and link with nothing; fewer
words than a shingle are one shingle as a whole; a null id takes part in no link and is its own component
(null); rows with equal ids are one node; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from densekeys.llm.common import Cuts, deleted, fresh_path, give_back, mix64, seeded_words
from densekeys.llm.components import components
from densekeys.llm.sharing import NO_ID, Parts, answered, codes_of
from densekeys.llm.words import blocks, hashed_words

WORDS = 5
GROUPS = 128
LEAF, FAN = 8, 8
BLOCK_NODES = 500
PAIRS_TOGETHER = 5_000
PLACE = seeded_words(23, WORDS) | np.uint64(1)
PREFIX_SCHEMA = "doc_id long, n_shingles long, candidate boolean, print_a long, print_b long, counts binary, shared binary, rarest array<long>"


def shingle_sets(texts: list[bytes]) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of the shingles of each text."""
    out = []
    for a, b in blocks(texts):
        words, bounds = hashed_words(texts[a:b])
        n = np.diff(bounds)
        # positions weigh words before the last mixing, so that order matters
        sums = np.zeros(max(0, len(words) - WORDS + 1), np.uint64)
        for k in range(WORDS):
            sums += words[k : len(words) - WORDS + 1 + k] * PLACE[k]
        prints = mix64(sums)
        for i in range(b - a):
            lo, hi = bounds[i], bounds[i + 1]
            if n[i] >= WORDS:
                out.append(np.unique(prints[lo : hi - WORDS + 1]))
            elif n[i]:
                out.append(mix64(np.array([(words[lo:hi] * PLACE[: n[i]]).sum() + np.uint64(n[i])], np.uint64)))
            else:
                out.append(np.zeros(0, np.uint64))
    return out


def send(ids: np.ndarray, texts: list[bytes], buckets: int):
    sets = shingle_sets(texts)
    codes = np.sort(codes_of(np.concatenate([np.zeros(0, np.uint64), *sets]), buckets))
    first = np.flatnonzero(np.concatenate([[True], codes[1:] != codes[:-1]])) if len(codes) else np.zeros(0, int)
    return codes[first], [np.minimum(np.diff(np.append(first, len(codes))), 255).astype(np.uint8)]


def merge(codes: np.ndarray, arrays: list[np.ndarray]) -> np.ndarray:
    """For a shingle of several documents, one more than the binary logarithm of their number; else zero."""
    order = np.argsort(codes, kind="stable")
    sorted_codes = codes[order]
    first = np.flatnonzero(np.concatenate([[True], sorted_codes[1:] != sorted_codes[:-1]]))
    total = np.add.reduceat(arrays[0][order].astype(np.int64), first)
    rank = np.where(total > 1, np.log2(np.maximum(total, 1)).astype(np.uint64) + np.uint64(1), np.uint64(0))
    answer = np.zeros(len(codes), np.uint64)
    answer[order] = np.repeat(rank, np.diff(np.append(first, len(codes))))
    return answer


merge.kinds = (np.uint8,)


def receive(part: int, ids: np.ndarray, texts: list[bytes], buckets: int, answers_for) -> pa.Table:
    """Each document's size, and for candidates the prints of the set; the set itself only once for equal ones of the part."""
    sets = shingle_sets(texts)
    every = np.concatenate([np.zeros(0, np.uint64), *sets])
    own, back = np.unique(codes_of(every, buckets), return_inverse=True)
    common = answers_for(own)[back]
    rows, seen, at = [], set(), 0
    for doc_id, prints in zip(ids.tolist(), sets, strict=True):
        n = len(prints)
        rank = common[at : at + n]
        at += n
        held = prints[rank > 0]
        least = (3 * n + 3) // 4
        doc = None if doc_id == NO_ID else doc_id
        if not n or len(held) < least or doc is None:
            rows.append((doc, n, False, None, None, None, None, None))
            continue
        mixed = mix64(prints)
        key = (n, int(mixed.sum().astype(np.int64)), int(np.bitwise_xor.reduce(mix64(mixed + np.uint64(1))).astype(np.int64)))
        if key in seen:
            rows.append((doc, n, True, key[1], key[2], None, None, None))
            continue
        seen.add(key)
        order = np.lexsort((held, rank[rank > 0]))
        rarest = held[order[: len(held) - least + 1]].astype(np.int64)
        counts = np.bincount((held % np.uint64(GROUPS)).astype(int), minlength=GROUPS)
        counts = counts.astype(np.uint16 if counts.max() < 1 << 16 else np.uint32)
        rows.append((doc, n, True, key[1], key[2], counts.tobytes(), held.tobytes(), rarest))
    kinds = (pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.int64()))
    return pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 8, kinds, strict=True)], names=[x.split()[0] for x in PREFIX_SCHEMA.split(", ")])


class CountTree:
    """A packed R-tree over count vectors: boxes keep the largest counts and the range of set sizes."""

    def __init__(self, counts: np.ndarray, sizes: np.ndarray):
        self.order = self._split(counts.astype(np.int64), sizes, np.arange(len(sizes)))
        self.counts, self.sizes = counts[self.order].astype(np.int64), sizes[self.order]
        self.levels: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        box, low, high, fan = self.counts, self.sizes, self.sizes, LEAF
        while len(low) > 1:
            first = np.arange(0, len(low), fan)
            box, low, high, fan = np.maximum.reduceat(box, first, axis=0), np.minimum.reduceat(low, first), np.maximum.reduceat(high, first), FAN
            self.levels.append((box, low, high))

    @staticmethod
    def _split(counts: np.ndarray, sizes: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Halve at the median of the size, then of the coordinate that spreads most, until leaves are left."""
        done, todo = [], [rows[np.argsort(sizes[rows], kind="stable")]]
        while todo:
            r = todo.pop()
            if len(r) <= LEAF:
                done.append(r)
                continue
            part = counts[r]
            r = r[np.argsort(part[:, np.argmax(part.max(axis=0) - part.min(axis=0))], kind="stable")] if len(r) <= 64 * LEAF else r
            half = -(-len(r) // 2 // LEAF) * LEAF
            todo += [r[half:], r[:half]]
        return np.concatenate(done)

    def search(self, count: np.ndarray, size: int) -> np.ndarray:
        """Rows (as given) that can overlap enough with a set of this size and these counts."""

        def may(at: np.ndarray, box: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
            at = at[(4 * high[at] >= 3 * size) & (3 * low[at] <= 4 * size)]
            return at[7 * np.minimum(box[at], count).sum(axis=1) >= 3 * (size + low[at])]

        at = np.zeros(1, int) if self.levels else np.arange(len(self.sizes))
        for depth in range(len(self.levels) - 1, -1, -1):
            at = may(at, *self.levels[depth])
            below, fan = (len(self.levels[depth - 1][1]), FAN) if depth else (len(self.sizes), LEAF)
            at = (at[:, None] * fan + np.arange(fan)).reshape(-1)
            at = at[at < below]
        return self.order[may(at, self.counts, self.sizes, self.sizes)]


BLOCK_ROW = ("block", "task", "doc_id", "n_shingles", "component", "counts", "role")
#: What a row of a block is: a point of its tree, a query, or both.
POINT, QUERY = 1, 2


def block_pairs(batches):
    """Pairs of different components that the tree of their block lets through; rows (BLOCK_ROW) come sorted by block and task."""

    def pairs(rows: list[tuple]):
        role = np.array([r[6] for r in rows])
        points, queries = np.flatnonzero(role & POINT), np.flatnonzero(role & QUERY)
        if not len(points) or not len(queries):
            return
        docs, sizes, labels = (np.array([r[k] for r in rows], np.int64) for k in (2, 3, 4))
        counts = np.stack([np.frombuffer(r[5], np.uint16 if len(r[5]) == 2 * GROUPS else np.uint32) for r in rows]).astype(np.uint32)
        tree = CountTree(counts[points], sizes[points])
        for i in queries:
            j = points[tree.search(counts[i].astype(np.int64), int(sizes[i]))]
            j = j[labels[j] != labels[i]]
            if len(j):
                yield np.minimum(docs[j], docs[i]), np.maximum(docs[j], docs[i])

    def emit(found: list):
        a, b = (np.concatenate(x) for x in zip(*found, strict=True))
        kept = np.unique(np.stack([a, b], axis=1), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(kept[:, k])) for k in range(2)], ["a", "b"])

    def blocks_of():
        held: list[tuple] = []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if held and row[:2] != held[0][:2]:
                    yield held
                    held = []
                held.append(row)
        if held:
            yield held

    found, n = [], 0
    for rows in blocks_of():
        for pair in pairs(rows):
            found.append(pair)
            n += len(pair[0])
            if n > 100_000:
                yield emit(found)
                found, n = [], 0
    rows = None
    if found:
        yield emit(found)
    del found
    give_back()


def searched(rows: DataFrame) -> DataFrame:
    """Pairs a < b from rows of blocks, each block's task a tree of its own."""
    return rows.select(*BLOCK_ROW).repartition("block", "task").sortWithinPartitions("block", "task").mapInArrow(block_pairs, "a long, b long").distinct()


def hot_splits(rows: DataFrame, keys: list[str], block_nodes: int, cuts: Cuts, queries: bool) -> DataFrame:
    """Tasks of each block of more than `block_nodes` points; a block that isn't named here is one task.

    One query costs a row in each task, so a block of one is dealt out evenly; where queries are as many as points, copies of
    queries and sizes of trees grow alike."""
    parts = F.count(F.lit(1)) / block_nodes
    split = F.ceil(F.sqrt(parts) if queries else parts).cast("int").alias("split")
    return cuts.write(rows.groupBy(*keys).agg(split).where("split > 1"), "hot-blocks")


def one_task(split) -> Column:
    """The task of a point among as many as its block has."""
    return F.when(split.isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("doc_id"), split).cast("int"))


def all_tasks(split) -> Column:
    return F.explode(F.sequence(F.lit(0), F.coalesce(split, F.lit(1)) - 1))


def star_rows(stars: DataFrame, nodes: DataFrame, block_nodes: int, cuts: Cuts) -> DataFrame:
    """A block for each first node: the nodes that chose it are points, it is the query."""
    hot = hot_splits(stars, ["first"], block_nodes, cuts, queries=False)
    points = stars.join(hot, "first", "left").select(F.col("first").alias("block"), one_task(F.col("split")).alias("task"), "doc_id", F.lit(POINT).alias("role"))
    queries = stars.select("first").distinct().join(hot, "first", "left").select(F.col("first").alias("block"), all_tasks(F.col("split")).alias("task"), F.col("first").alias("doc_id"), F.lit(QUERY).alias("role"))
    return points.unionByName(queries).join(nodes.select("doc_id", "n_shingles", "counts"), "doc_id").withColumn("component", F.col("doc_id"))


def mixed_rows(held: DataFrame, nodes: DataFrame, block_nodes: int, cuts: Cuts) -> DataFrame:
    """Blocks of several components, divided by size: all their nodes are points, those outside the largest component queries.

    `held`: doc_id, n_shingles, component, shingle. Sets that link differ by one size class at most, so a query also goes to both neighbours."""
    by_label = held.groupBy("shingle", "component").agg(F.count(F.lit(1)).alias("n"))
    mixed = cuts.write(by_label.groupBy("shingle").agg(F.count(F.lit(1)).alias("labels"), F.max_by("component", F.struct("n", "component")).alias("major")).where("labels > 1").select("shingle", "major"), "mixed-blocks")
    scale = F.log(F.col("n_shingles").cast("double")) / math.log(4 / 3)
    at = cuts.write(held.join(mixed, "shingle").withColumn("class", F.floor(scale).cast("int")), "mixed-nodes")
    hot = hot_splits(at, ["shingle", "class"], block_nodes, cuts, queries=True)
    block = F.xxhash64("shingle", "class").alias("block")
    points = at.join(hot, ["shingle", "class"], "left").select(block, one_task(F.col("split")).alias("task"), "doc_id", "component", F.lit(POINT).alias("role"))
    near = F.explode(F.sequence(F.floor(scale - 1 - 1e-9).cast("int"), F.floor(scale + 1 + 1e-9).cast("int")))
    queries = at.where("component <> major").withColumn("class", near).join(hot, ["shingle", "class"], "left")
    queries = queries.select(block, all_tasks(F.col("split")).alias("task"), "doc_id", "component", F.lit(QUERY).alias("role"))
    return points.unionByName(queries).join(nodes.select("doc_id", "n_shingles", "counts"), "doc_id")


def verified(pairs: DataFrame, sets: DataFrame, cuts: Cuts) -> DataFrame:
    """The pairs (distinct ones) whose sets overlap by at least three quarters.

    `sets` is bucketed by doc_id, so only pairs travel to it. The set of b goes to its pair; that of a, which may
    be in very many, is copied once for PAIRS_TOGETHER of them."""

    def check(batches):
        for batch in batches:
            a, b, na, nb, sa, sb = (c.to_pylist() for c in batch.columns)
            keep = [k for k in range(len(a)) if 7 * len(np.intersect1d(np.frombuffer(sa[k], np.uint64), np.frombuffer(sb[k], np.uint64), assume_unique=True)) >= 3 * (na[k] + nb[k])]
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for k in keep], pa.int64()) for x in (a, b)], ["a", "b"])
            del batch, sa, sb
            give_back()

    def side(name: str) -> DataFrame:
        return sets.where("shared is not null").select(F.col("doc_id").alias(name), F.col("n_shingles").alias(f"n{name}"), F.col("shared").alias(f"s{name}"))

    copies = F.ceil(F.count(F.lit(1)) / PAIRS_TOGETHER).cast("int")
    often = cuts.write(pairs.groupBy("a").agg(copies.alias("copies")).where("copies > 1"), "pair-heads")
    heads = pairs.select("a").distinct().join(often, "a", "left").join(side("a"), "a")
    heads = heads.withColumn("copy", F.explode(F.sequence(F.lit(0), F.coalesce("copies", F.lit(1)) - 1))).drop("copies")
    told = pairs.join(often, "a", "left").withColumn("copy", F.when(F.col("copies").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("b"), F.col("copies")).cast("int"))).drop("copies")
    fits = (4 * F.col("nb") >= 3 * F.col("na")) & (4 * F.col("na") >= 3 * F.col("nb"))
    joined = told.join(side("b"), "b").join(heads, ["a", "copy"]).where(fits)
    return joined.select("a", "b", "na", "nb", "sa", "sb").mapInArrow(check, "a long, b long")


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_nodes: int = BLOCK_NODES) -> DataFrame:
    """doc_id, n_shingles, component_id of every document."""
    spark = docs.sparkSession
    cuts = Cuts(spark)
    parts = Parts(docs, id_col, text_col)
    table, path = f"shingle_sets_{uuid.uuid4().hex}", fresh_path(spark, "shingle-sets")
    found = answered(parts, send, merge, receive, PREFIX_SCHEMA)
    found.write.format("parquet").bucketBy(parts.files, "doc_id").option("path", path).saveAsTable(table)
    sets = spark.table(table)
    equal = ["n_shingles", "print_a", "print_b"]
    candidates = sets.where("candidate").select("doc_id", *equal)
    # a set is kept once for each part, so the node of equal sets is the smallest id that came with one
    heads = cuts.write(
        sets.where("candidate").groupBy(*equal).agg(F.min(F.when(F.col("shared").isNotNull(), F.col("doc_id"))).alias("node"), F.min("doc_id").alias("least")), "heads"
    )
    is_node = heads.select(F.col("node").alias("doc_id"), F.col("print_a").alias("of_a"), F.col("print_b").alias("of_b"))
    nodes = sets.where("shared is not null").drop("shared", "candidate").join(is_node, "doc_id").where("print_a = of_a and print_b = of_b")
    nodes = cuts.write(nodes.select("doc_id", "n_shingles", "counts", "rarest"), "nodes")
    holders = nodes.select("doc_id", F.explode("rarest").alias("shingle"))
    first = cuts.write(holders.groupBy("shingle").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1"), "block-heads")
    stars = (
        holders.join(first, "shingle")
        .where("doc_id <> first")
        .groupBy("doc_id", "first")
        .count()
        .groupBy("doc_id")
        .agg(F.max_by("first", F.struct("count", F.bitwise_not("first"))).alias("first"))
    )
    stars = cuts.write(stars, "stars")
    pairs = cuts.write(searched(star_rows(stars, nodes, block_nodes, cuts)), "star-pairs")
    links = cuts.write(verified(pairs, sets, cuts), "star-links")
    labels = components(links, cuts)

    held = nodes.join(labels.withColumnRenamed("vertex", "doc_id"), "doc_id", "left").select(
        "doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component"), F.explode("rarest").alias("shingle")
    )
    held = cuts.write(held.join(first.select("shingle"), "shingle", "left_semi"), "holders")
    pairs = cuts.write(searched(mixed_rows(held, nodes, block_nodes, cuts)), "pairs")
    more = cuts.write(verified(pairs, sets, cuts), "links")
    if more.limit(1).count():
        labels = components(links.unionByName(more), cuts)

    # a component's smallest document may be a copy whose set another part's copy stands for
    named = heads.join(labels.withColumnRenamed("vertex", "node"), "node", "left").withColumn("component", F.coalesce("component", "node"))
    least = named.groupBy("component").agg(F.min("least").alias("component_id"))
    groups = cuts.write(named.join(least, "component").select(*equal, "component_id"), "groups")
    known = candidates.join(groups, equal).groupBy("doc_id").agg(F.min("component_id").alias("component_id"))
    out = sets.select("doc_id", "n_shingles").join(known, "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
    out = cuts.write(out, "near-groups")
    cuts.drop(out)
    spark.sql(f"DROP TABLE {table}")
    deleted(spark, path)
    return out
