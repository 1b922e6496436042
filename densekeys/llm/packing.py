"""Best-fit packing of token pieces into sequences by a grouping genetic algorithm on islands.

Documents are encoded and ended by id 0; only those longer than a sequence are cut. Pieces are dealt by hash
to shards of about SHARD_PIECES, so that no task holds more than a shard, whatever the corpus or its hot
groups. Each shard is a ring of ISLANDS populations, every one a task of its own. An individual is a grouping
of the shard's pieces into bins, at first by best fit in random order; crossover injects whole well-filled bins
of one parent into the other, drops the bins that hold the same pieces, swaps displaced pieces with smaller ones
where that fills a bin better, and puts the rest back by best fit. After each epoch the elite of an island
migrates to the next one. The best elite of a shard wins; its poorly filled bins are opened and evolved again,
together with those of other shards, in one more round.

Defined cases: a null or empty text is the single end token; repeated rows are packed each; a null doc_id is
packed like any other; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.llm.bpe import encoder
from densekeys.llm.common import id_and_text, text_strings, written

CAPACITY = 2048
SHARD_PIECES = 4096
ISLANDS = 2
EPOCHS = 2
POPULATION = 4
GENERATIONS = 6
WELL_FILLED = 0.97
EXCHANGES = 2
PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long"
PIECE_NAMES = [x.split()[0] for x in PIECE_SCHEMA.split(", ")]
PACKED_SCHEMA = PIECE_SCHEMA + ", sequence_id long, offset long"
ISLAND_SCHEMA = "shard long, island int, pieces binary, elite binary, fitness double, crossings long"


def pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every document's ids and the end token, cut only where longer than a sequence."""

    def run(batches):
        words = encoder(vocabulary)
        for batch in batches:
            rows = []
            for doc_id, found in zip(batch.column(0).to_pylist(), words.texts(text_strings(batch.column(1))), strict=True):
                ids = found.astype("<u4").tobytes() + b"\0\0\0\0"
                for k in range(0, len(ids), 4 * capacity):
                    part = ids[k : k + 4 * capacity]
                    rows.append((doc_id, k // (4 * capacity), k // 4, len(part) // 4, zlib.crc32(part)))
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 5, kinds, strict=True)], PIECE_NAMES)

    return id_and_text(docs, id_col, text_col).mapInArrow(run, PIECE_SCHEMA)


def place(sizes: list[int], order: list[int], groups: np.ndarray, room: list[int], capacity: int) -> None:
    """Put each item of `order` into the bin with the least room that still holds it, opening bins as needed.

    A bit for every amount of free room tells the smallest that fits by one lowest-bit search."""
    by_room: dict[int, list[int]] = {}
    mask = 0
    for k, r in enumerate(room):
        if r > 0:
            by_room.setdefault(r, []).append(k)
            mask |= 1 << r
    for item in order:
        size = sizes[item]
        fitting = mask >> size
        if fitting:
            r = size + (fitting & -fitting).bit_length() - 1
            k = by_room[r].pop()
            if not by_room[r]:
                mask ^= 1 << r
        else:
            r, k = capacity, len(room)
            room.append(capacity)
        groups[item] = k
        room[k] = r - size
        if r > size:
            by_room.setdefault(r - size, []).append(k)
            mask |= 1 << (r - size)


class Grouping:
    """Bin of each item, and how full each bin is."""

    def __init__(self, groups: np.ndarray, sizes: np.ndarray, capacity: int):
        self.groups = np.unique(groups, return_inverse=True)[1].astype(np.int32)
        self.fill = np.bincount(self.groups, weights=sizes).astype(np.int64)
        # squares reward a few full bins and one nearly empty over many that are evenly filled
        self.fitness = float(np.mean((self.fill / capacity) ** 2)) if len(self.fill) else 1.0

    @property
    def rank(self) -> tuple[int, float]:
        """Smaller is better."""
        return len(self.fill), -self.fitness


def cross(base: Grouping, donor: Grouping, sizes: np.ndarray, capacity: int, rng: np.random.Generator) -> Grouping:
    """Whole well-filled bins of `donor` go into `base`; bins with doubles, and some of the emptiest, are opened.

    What is displaced first takes the place of smaller items where that fills a bin better, then goes where it fits best."""
    good = np.flatnonzero(donor.fill >= max(capacity * WELL_FILLED, np.quantile(donor.fill, 0.5)))
    chosen = np.zeros(len(donor.fill), bool)
    chosen[good[rng.random(len(good)) < rng.uniform(0.2, 0.6)]] = True
    taken = chosen[donor.groups]
    broken = np.zeros(len(base.fill), bool)
    broken[base.groups[taken]] = True
    broken |= (base.fill < capacity * WELL_FILLED) & (rng.random(len(base.fill)) < rng.uniform(0.1, 0.9))
    groups = np.full(len(sizes), -1, np.int64)
    groups[taken] = donor.groups[taken]
    kept = ~taken & ~broken[base.groups]
    groups[kept] = base.groups[kept] + len(donor.fill)
    for _ in range(EXCHANGES):
        if not exchanged(groups, sizes, capacity):
            break
    return refilled(groups, sizes, capacity, rng)


def exchanged(groups: np.ndarray, sizes: np.ndarray, capacity: int) -> int:
    """Items without a bin swap with smaller ones in bins with room, where most room is filled first, once for each bin; how many did."""
    loose, placed = np.flatnonzero(groups < 0), np.flatnonzero(groups >= 0)
    if not len(loose) or not len(placed):
        return 0
    fill = np.bincount(groups[placed], weights=sizes[placed])
    room = capacity - fill[groups[placed]]
    placed, room = placed[room > 0], room[room > 0]
    loose = loose[np.argsort(sizes[loose], kind="stable")]
    at = np.searchsorted(sizes[loose], sizes[placed] + room, side="right") - 1
    gain = sizes[loose][np.maximum(at, 0)] - sizes[placed]
    gain[at < 0] = 0
    order = np.argsort(-(gain / room), kind="stable")
    order = order[gain[order] > 0]
    done, gone = set(), set()
    for k in order.tolist():
        inside, item = int(placed[k]), int(at[k])
        if item in gone or groups[inside] in done:
            continue
        done.add(int(groups[inside]))
        gone.add(item)
        groups[loose[item]], groups[inside] = groups[inside], -1
    return len(gone)


def refilled(groups: np.ndarray, sizes: np.ndarray, capacity: int, rng: np.random.Generator, noise: float = 0.02) -> Grouping:
    """Best fit of the items without a bin, larger first up to a little noise, or in random order if that is infinite."""
    loose = np.flatnonzero(groups < 0)
    placed = groups >= 0
    out = np.full(len(groups), -1, np.int64)
    out[placed] = np.unique(groups[placed], return_inverse=True)[1]
    room = (capacity - np.bincount(out[placed], weights=sizes[placed])).astype(int).tolist() if placed.any() else []
    order = rng.permutation(loose) if np.isinf(noise) else loose[np.argsort(-sizes[loose] * (1 + noise * rng.random(len(loose))), kind="stable")]
    place(sizes.tolist(), order.tolist(), out, room, capacity)
    return Grouping(out, sizes, capacity)


def evolve(sizes: np.ndarray, elites: list[np.ndarray], capacity: int, seed: int, population: int = POPULATION, generations: int = GENERATIONS) -> tuple[Grouping, int]:
    """Generations on one island, from the elites that it has and received, and best fits in random order; the best, and how many crossings there were.

    It ends early when no grouping can have fewer bins. A shard that no crossing improves has its best fit in random order."""
    rng = np.random.default_rng(seed)
    least = -(-int(sizes.sum()) // capacity)
    people = [Grouping(e, sizes, capacity) for e in elites]
    while len(people) < population:
        people.append(refilled(np.full(len(sizes), -1), sizes, capacity, rng, np.inf))
    crossings = 0
    for _ in range(generations):
        people.sort(key=lambda g: g.rank)
        for _ in range(population - 1):
            if len(people[0].fill) <= least:
                return people[0], crossings
            a, b = rng.integers(0, max(2, population // 2)), rng.integers(0, population)
            child = cross(people[a], people[b], sizes, capacity, rng)
            crossings += 1
            # a child takes the place of the worst
            if child.rank < people[-1].rank:
                people[-1] = child
                people.sort(key=lambda g: g.rank)
    return min(people, key=lambda g: g.rank), crossings


def to_bytes(table: pa.Table) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def from_bytes(data: bytes) -> pa.Table:
    return pa.ipc.open_stream(data).read_all()


def lengths(table: pa.Table) -> np.ndarray:
    return table.column("length").to_numpy().astype(np.int64)


def island_row(shard: int, island: int, data: bytes, evolved: tuple[Grouping, int]) -> pa.Table:
    best, crossings = evolved
    row = {"shard": [shard], "island": [island], "pieces": [data], "elite": [best.groups.tobytes()], "fitness": [best.fitness - len(best.fill)], "crossings": [crossings]}
    kinds = [pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.float64(), pa.int64()]
    return pa.table([pa.array(v, k) for v, k in zip(row.values(), kinds, strict=True)], names=list(row))


def placed_rows(table: pa.Table, groups: np.ndarray, base: int) -> pa.Table:
    """The pieces with their sequence and gapless offsets, in a fixed order in each bin."""
    size = lengths(table)
    order = np.argsort(groups, kind="stable")
    total = np.concatenate([[0], np.cumsum(size[order])])
    first = np.flatnonzero(np.diff(groups[order], prepend=-1))
    begin = np.zeros(len(order), np.int64)
    begin[first] = total[:-1][first]
    offset = total[:-1] - np.maximum.accumulate(begin)
    return table.select(PIECE_NAMES).take(pa.array(order)).append_column("sequence_id", pa.array(groups[order].astype(np.int64) + base)).append_column("offset", pa.array(offset.astype(np.int64)))


def ordered(table: pa.Table) -> pa.Table:
    """Independent of the order in which a shuffle delivers."""
    return table.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending"), ("ids_crc32", "ascending")])


def pack(cut: DataFrame, capacity: int = CAPACITY, shard_pieces: int = SHARD_PIECES, islands: int = ISLANDS, epochs: int = EPOCHS) -> DataFrame:
    """Pack rows of PIECE_SCHEMA (read several times: hand in a written table)."""
    shards = max(1, -(-cut.count() // shard_pieces))
    # by the row's place in the written table, so that rows that repeat are dealt to all shards
    key = F.xxhash64(F.monotonically_increasing_id())
    dealt = cut.withColumn("shard", F.pmod(key, F.lit(shards))).withColumn("island", F.explode(F.array(*[F.lit(k) for k in range(islands)])))

    def begin(keys, table):
        shard, island = (int(k.as_py()) for k in keys)
        table = ordered(table.select(PIECE_NAMES))
        return island_row(shard, island, to_bytes(table), evolve(lengths(table), [], capacity, 2 * shard + island))

    def go_on(keys, table):
        shard, island = (int(k.as_py()) for k in keys)
        table = table.sort_by([("fitness", "descending"), ("elite", "ascending")])
        data = table.column("pieces")[0].as_py()
        elites = [np.frombuffer(e, np.int32) for e in table.column("elite").to_pylist()]
        return island_row(shard, island, data, evolve(lengths(from_bytes(data)), elites, capacity, 7919 * (shard + 1) + island))

    def finish(keys, table):
        shard = int(keys[0].as_py())
        table = table.sort_by([("fitness", "descending"), ("island", "ascending")])
        return placed_rows(from_bytes(table.column("pieces")[0].as_py()), np.frombuffer(table.column("elite")[0].as_py(), np.int32), shard << 24)

    state = dealt.groupBy("shard", "island").applyInArrow(begin, ISLAND_SCHEMA)
    for _ in range(epochs - 1):
        # an elite goes to its own island and to the next one of the ring
        reach = F.explode(F.array_distinct(F.array(F.col("island"), (F.col("island") + 1) % islands)))
        state = state.select("shard", reach.alias("island"), "pieces", "elite", "fitness").groupBy("shard", "island").applyInArrow(go_on, ISLAND_SCHEMA)
    first = written(state.groupBy("shard").applyInArrow(finish, PACKED_SCHEMA), "packed")
    fill = F.sum("length")
    poor = first.groupBy("sequence_id").agg(fill.alias("fill")).where(F.col("fill") < int(capacity * WELL_FILLED))
    poor = written(first.join(poor, "sequence_id").select(*PIECE_NAMES, "sequence_id"), "poorly-filled")
    pools = max(1, -(-poor.count() // shard_pieces))

    def again(keys, table):
        pool = int(keys[0].as_py())
        table = ordered(table.select(PIECE_NAMES))
        return placed_rows(table, evolve(lengths(table), [], capacity, 104729 + pool, generations=2 * GENERATIONS)[0].groups, (shards + pool) << 24)

    repacked = poor.withColumn("pool", F.pmod(F.xxhash64("sequence_id"), F.lit(pools))).groupBy("pool").applyInArrow(again, PACKED_SCHEMA)
    rest = first.join(poor.select("sequence_id").distinct(), "sequence_id", "left_anti").select(*PIECE_NAMES, "sequence_id", "offset")
    return rest.unionByName(repacked)


def pack_documents(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return pack(written(pieces(docs, vocabulary, capacity, id_col, text_col), "pieces"), capacity)
