"""Four classical ways to number a set in memory, a Bloom filter, and what a Spark user would write.

The in-memory ones work on 64-bit key prints of a set that one task can hold; each is a build and an evaluate.
`in_one_task` runs them as a grouped map behind a check of the set's size."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densekeys.functions.encode import encode_key
from densekeys.functions.hashing import splitmix
from densekeys.functions.kernel import peel
from densekeys.shared import written

MAX_KEYS = 2_000_000
TRIES = 200


def hashed(prints: np.ndarray, seed: int, size: int) -> np.ndarray:
    return (splitmix(prints ^ splitmix(np.array([seed], np.uint64))) % np.uint64(max(1, size))).astype(np.int64)


class Groups:
    """Keys by the class that each falls in: number, count and first place in `order` of every class that holds a key."""

    def __init__(self, of: np.ndarray):
        self.order = np.argsort(of, kind="stable")
        self.number, self.count = np.unique(of, return_counts=True)
        self.start = np.cumsum(self.count) - self.count

    def columns(self, column: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
        """The columns of the classes at `at`, all of one size, a row for each."""
        return column[self.order[self.start[at][:, None] + np.arange(size)]]


def placed(groups: Groups, column: np.ndarray, taken: np.ndarray, which: np.ndarray, rng: np.random.Generator, rounds: int = 400) -> tuple[np.ndarray, np.ndarray]:
    """A shift for each class at `which`, larger classes first, that puts its keys on free places, which become taken; and the classes without one.

    Many classes of a size draw at once: each tries to put its first key on free places drawn at random, and of those that
    want a place the first gets it."""
    n = len(taken)
    moves, failed = np.zeros(len(groups.count), np.int64), []
    claim = np.full(n, -1, np.int64)
    for size in np.unique(groups.count[which])[::-1].tolist():
        todo = np.flatnonzero(which & (groups.count == size))
        columns = groups.columns(column, todo, size)
        ordered = np.sort(columns, axis=1)
        distinct = (ordered[:, 1:] != ordered[:, :-1]).all(axis=1)
        failed.append(todo[~distinct])
        todo, columns = todo[distinct], columns[distinct]
        for k in range(rounds):
            if not len(todo):
                break
            if k % 8 == 0:
                free = np.flatnonzero(~taken)
            draws = max(1, min(len(free), (1 << 18) // (size * len(todo))))
            who = np.repeat(np.arange(len(todo)), draws)
            move = (free[rng.integers(0, len(free), len(who))] - columns[who, 0]) % n
            places = (columns[who] + move[:, None]) % n
            fits = ~taken[places].any(axis=1)
            who, move, places = who[fits], move[fits], places[fits]
            first = np.flatnonzero(np.diff(who, prepend=-1))
            who, move, places = who[first], move[first], places[first]
            claim[places[::-1].reshape(-1)] = np.repeat(np.arange(len(who))[::-1], size)
            wins = (claim[places] == np.arange(len(who))[:, None]).all(axis=1)
            moves[todo[who[wins]]] = move[wins]
            taken[places[wins]] = True
            stay = np.ones(len(todo), bool)
            stay[who[wins]] = False
            todo, columns = todo[stay], columns[stay]
        failed.append(todo)
    return moves, np.concatenate(failed) if failed else np.zeros(0, np.int64)


@dataclass
class Displace:
    """value = (column + displacement of the class) mod n; `c` words a key."""

    n: int
    seed: int
    shifts: np.ndarray

    @classmethod
    def build(cls, prints: np.ndarray, c: float = 2.0) -> Displace:
        n = len(prints)
        classes = max(1, round(c * n))
        for seed in range(TRIES):
            column, of = hashed(prints, 2 * seed, n), hashed(prints, 2 * seed + 1, classes)
            groups = Groups(of)
            taken = np.zeros(n, bool)
            # larger classes first; the many classes of one key take the places that are left
            moves, failed = placed(groups, column, taken, groups.count > 1, np.random.default_rng(seed))
            if len(failed):
                continue
            shifts = np.zeros(classes, np.int64)
            shifts[groups.number] = moves
            single = groups.count == 1
            shifts[groups.number[single]] = (np.flatnonzero(~taken) - column[groups.order[groups.start[single]]]) % n
            return cls(n, seed, shifts)
        raise RuntimeError("no displacement found")

    def evaluate(self, prints: np.ndarray) -> np.ndarray:
        return (hashed(prints, 2 * self.seed, self.n) + self.shifts[hashed(prints, 2 * self.seed + 1, len(self.shifts))]) % max(1, self.n)

    @property
    def bits(self) -> int:
        return 32 * len(self.shifts)


def _two_ends(prints: np.ndarray, seed: int, vertices: int) -> tuple[np.ndarray, np.ndarray]:
    half = max(1, vertices // 2)
    return hashed(prints, 2 * seed, half), half + hashed(prints, 2 * seed + 1, half)


@dataclass
class SumGraphAcyclic:
    """value = (g[a] + g[b]) mod n over a forest; any order of the values can be asked for."""

    n: int
    seed: int
    g: np.ndarray

    @classmethod
    def build(cls, prints: np.ndarray, c: float = 2.09, target: np.ndarray | None = None) -> SumGraphAcyclic:
        n = len(prints)
        vertices = 2 * max(1, math.ceil(c * n / 2))
        want = np.arange(n) if target is None else np.asarray(target)
        for seed in range(TRIES):
            a, b = _two_ends(prints, seed, vertices)
            rest, rounds = peel(a, b, vertices)
            if len(rest):
                continue
            g = np.zeros(vertices, np.int64)
            for edge, leaf in reversed(rounds):
                g[leaf] = (want[edge] - g[a[edge] + b[edge] - leaf]) % n
            return cls(n, seed, g)
        raise RuntimeError("no forest found")

    def evaluate(self, prints: np.ndarray) -> np.ndarray:
        a, b = _two_ends(prints, self.seed, len(self.g))
        return (self.g[a] + self.g[b]) % max(1, self.n)

    @property
    def bits(self) -> int:
        return 32 * len(self.g)


@dataclass
class SumGraphDense:
    """value = g[a] + g[b] over about c n vertices; the cyclic core gets distinct sums first, trees the values left."""

    n: int
    seed: int
    g: np.ndarray

    @classmethod
    def build(cls, prints: np.ndarray, c: float = 1.15) -> SumGraphDense:
        n = len(prints)
        vertices = 2 * max(1, math.ceil(c * n / 2))
        for seed in range(TRIES):
            a, b = _two_ends(prints, seed, vertices)
            if len(np.unique(a * vertices + b)) < n:
                continue
            rest, rounds = peel(a, b, vertices)
            g, used = cls._core(a, b, rest, vertices, n)
            if g is None:
                continue
            left = iter(np.flatnonzero(~used).tolist())
            for edge, leaf in reversed(rounds):
                other = a[edge] + b[edge] - leaf
                for o, f in zip(other.tolist(), leaf.tolist(), strict=True):
                    g[f] = next(left) - g[o]
            return cls(n, seed, g)
        raise RuntimeError("no assignment of the core found")

    @staticmethod
    def _core(a, b, rest, vertices, n):
        g, used = np.zeros(vertices, np.int64), np.zeros(n, bool)
        near: dict[int, list[int]] = {}
        for x, y in zip(a[rest].tolist(), b[rest].tolist(), strict=True):
            near.setdefault(x, []).append(y)
            near.setdefault(y, []).append(x)
        # values only grow along a breadth-first walk, so that sums stay below n while the core is small
        done: set[int] = set()
        value = 0
        for root in near:
            if root in done:
                continue
            queue, seen = [root], {root}
            for v in queue:
                fixed = [int(g[w]) for w in near[v] if w in done]
                while fixed:
                    sums = [value + f for f in fixed]
                    if max(sums) >= n:
                        return None, used
                    if len(set(sums)) == len(sums) and not used[sums].any():
                        used[sums] = True
                        break
                    value += 1
                g[v] = value
                value += 1
                done.add(v)
                for w in near[v]:
                    if w not in seen:
                        seen.add(w)
                        queue.append(w)
        return g, used

    def evaluate(self, prints: np.ndarray) -> np.ndarray:
        a, b = _two_ends(prints, self.seed, len(self.g))
        return self.g[a] + self.g[b]

    @property
    def bits(self) -> int:
        return 32 * len(self.g)


@dataclass
class BucketSearch:
    """Most keys go to few large buckets; each bucket, largest first, searches a displacement and a seed."""

    n: int
    seed: int
    g: np.ndarray
    pattern: np.ndarray

    @staticmethod
    def _bucket(prints: np.ndarray, seed: int, buckets: int) -> np.ndarray:
        few = max(1, round(0.3 * buckets))
        skew = hashed(prints, 7 * seed + 1, 1000) < 600
        return np.where(skew, hashed(prints, 7 * seed + 2, few), few + hashed(prints, 7 * seed + 3, max(1, buckets - few)))

    @classmethod
    def count(cls, n: int, c: float) -> int:
        return max(2, math.ceil(c * n / (math.log2(max(n, 2)) + 1)))

    @classmethod
    def build(cls, prints: np.ndarray, c: float = 4.0) -> BucketSearch:
        n = len(prints)
        buckets = cls.count(n, c)
        for seed in range(TRIES):
            groups = Groups(cls._bucket(prints, seed, buckets))
            key_group = np.empty(n, np.int64)
            key_group[groups.order] = np.repeat(np.arange(len(groups.count)), groups.count)
            g, pattern, taken = np.zeros(buckets, np.int64), np.zeros(buckets, np.int64), np.zeros(n, bool)
            drawn, column = np.zeros(len(groups.count), np.int64), np.empty(n, np.int64)
            done = True
            # all buckets of a size are settled, with as many patterns as they need, before smaller ones
            for size in np.unique(groups.count)[::-1].tolist():
                which = groups.count == size
                for bit in range(32):
                    drawn[which] = bit
                    keys = which[key_group]
                    column[keys] = hashed(prints[keys], 1000 + 64 * seed + bit, n)
                    moves, failed = placed(groups, column, taken, which, np.random.default_rng([seed, size, bit]), 400 if size > 1 else 10_000)
                    settled = which.copy()
                    settled[failed] = False
                    g[groups.number[settled]], pattern[groups.number[settled]] = moves[settled], bit
                    which = which & ~settled
                    if not which.any():
                        break
                else:
                    done = False
                    break
            if done:
                return cls(n, seed, g, pattern)
        raise RuntimeError("no assignment found")

    def evaluate(self, prints: np.ndarray) -> np.ndarray:
        of = self._bucket(prints, self.seed, len(self.g))
        x = splitmix(np.asarray(1000 + 64 * self.seed + self.pattern[of], np.uint64))
        return ((splitmix(prints ^ x) % np.uint64(max(1, self.n))).astype(np.int64) + self.g[of]) % max(1, self.n)

    @property
    def bits(self) -> int:
        return 32 * len(self.g)


METHODS = {"displace": Displace, "sumgraph_dense": SumGraphDense, "sumgraph_acyclic": SumGraphAcyclic, "bucket_search": BucketSearch}


def key_prints(df: DataFrame, cols: list[str]) -> DataFrame:
    key = encode_key(df, cols)
    return df.withColumn("print", F.when(key.isNotNull(), F.xxhash64(key, F.lit(5)))).where("print is not null")


def in_one_task(df: DataFrame, cols: str | list[str], method: str, ordered: bool = False, max_keys: int = MAX_KEYS, **options) -> DataFrame:
    """Distinct keys with their id and the method's bits a key; refuses sets that one task can't hold.

    `ordered` asks the acyclic sum graph for ids in the order of the key columns."""
    cols = [cols] if isinstance(cols, str) else list(cols)
    rows = key_prints(df.select(*cols).dropDuplicates(), cols)
    if (n := rows.count()) > max_keys:
        raise ValueError(f"{n} keys exceed {max_keys}; use build_two_level")
    schema = rows.drop("print").schema.add("id", "long").add("bits_per_key", "double")

    def number(table):
        prints = table.column("print").to_numpy().view(np.uint64)
        more = options
        if ordered:
            place = pa.compute.sort_indices(table, [(c, "ascending") for c in cols]).to_numpy()
            target = np.empty(len(prints), np.int64)
            target[place] = np.arange(len(prints))
            more = options | {"target": target}
        built = METHODS[method].build(prints, **more)
        out = table.drop_columns(["print"])
        return out.append_column("id", pa.array(built.evaluate(prints))).append_column("bits_per_key", pa.array(np.full(len(prints), built.bits / max(1, len(prints)))))

    return rows.groupBy().applyInArrow(number, schema)


def sorted_ids(df: DataFrame, col: str) -> DataFrame:
    """Ids by global order: ranges are numbered apart and shifted by the sizes of those before, so no task sees all rows."""
    ranged = written(df.select(col).where(F.col(col).isNotNull()).dropDuplicates().repartitionByRange(col).withColumn("_range", F.spark_partition_id()), "ranges")
    sizes = ranged.groupBy("_range").count()
    before = sizes.select("_range", F.coalesce(F.sum("count").over(W.orderBy("_range").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    within = F.row_number().over(W.partitionBy("_range").orderBy(col)) - 1
    return ranged.withColumn("_within", within).join(F.broadcast(before), "_range").select(col, (F.col("_within") + F.col("_before")).cast("long").alias("id"))


def surrogate_fk(fact: DataFrame, cols: list[str]) -> DataFrame:
    """The design argued against: a stored surrogate id, found by a join on the natural columns."""
    dimension = fact.select(*cols).dropDuplicates().select(*cols, F.xxhash64(*cols).alias("surrogate"))
    return fact.join(dimension, cols)
