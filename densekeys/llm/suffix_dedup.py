"""Suffix-array deduplication of long passages that several documents share.

A byte goes if a window of WINDOW bytes that covers it also starts in a document with a smaller id.

Candidates: every window has an anchor, the smallest of its hashed SEED-byte strings, and equal windows
have equal anchors. Anchors that two documents hold are found by `sharing`; only windows of such anchors can
repeat. The answer to an anchor is a route: anchors of few documents go with the first document that holds
them, so that neighbouring windows travel as one segment; frequent ones, and those first seen in a very long
document, go alone, once per part and distinct context. Those of more than HOT documents are taken apart: windows
of STEP neighbouring places around the anchor hold the same bytes in their middle, and go by these, so that one
passage of very many documents is dealt to many tasks, and none gets more than the parts have of one middle.

Suffix arrays: the segments of some routes are put one after another and sorted in two stages. Suffixes
smaller than their successors are sorted directly; the others are induced by one scan over the buckets of
first bytes, each placing its predecessors. Common prefixes of neighbours then delimit runs of equal windows,
and the smallest document of each run decides for all. Order beyond WINDOW bytes isn't needed or computed.

Defined cases: a null text is empty; null ids count as larger than all others and not as smaller than each
other; rows with equal ids never remove from each other; texts shorter than WINDOW stay whole; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from densekeys.llm.common import fresh_path, give_back, giving_back, mix64
from densekeys.llm.sharing import NO_ID, Parts, answered, carried, codes_of, squeezed, table_bytes, unpacked_in_order, unsqueezed
from densekeys.llm.words import blocks, joined, hashes_between, prefix_sums

WINDOW = 50
SEED = 18
FEW = 16
HOT = 256
STEP = 8
LONG_DOCUMENT = 1 << 16
SORT_BYTES = 1 << 19
ALONE = np.uint64(1 << 62)
APART = np.uint64(1 << 61)
SEPARATOR = b"\xff"


def anchors(texts: list[bytes]) -> tuple[np.ndarray, ...]:
    """Of every anchor in order: text, first and last window start, and place, in the text, and hash. Only for one block of texts."""
    data, bounds = joined(texts)
    n = len(data) - WINDOW
    if n < 0:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.int64, np.uint64))
    seeds = np.arange(len(data) - SEED + 1)
    prints = hashes_between(prefix_sums(data), seeds, seeds + SEED)
    # the place in the low bits makes the leftmost of equal ones the smallest
    least = prints >> np.uint64(28) << np.uint64(28) | seeds.astype(np.uint64)
    span, width = WINDOW - SEED + 1, 1
    while width < span:
        step = min(width, span - width)
        least = np.minimum(least[:-step], least[step:])
        width += step
    start = np.arange(len(least))
    text = np.repeat(np.arange(len(texts)), np.diff(bounds))[: len(least)]
    inside = start + WINDOW < bounds[text + 1]
    start, text, owner = start[inside], text[inside], (least[inside] & np.uint64((1 << 28) - 1)).astype(np.int64)
    first = np.flatnonzero((np.diff(owner, prepend=-1) != 0) | (np.diff(text, prepend=-1) != 0))
    last = np.append(first[1:], len(start)) - 1
    begin = bounds[text[first]]
    return text[first], start[first] - begin, start[last] - begin, owner[first] - begin, prints[owner[first]]


def all_anchors(texts: list[bytes]) -> tuple[np.ndarray, ...]:
    found = []
    for a, b in blocks(texts):
        text, *rest = anchors(texts[a:b])
        found.append((text + a, *rest))
    return tuple(np.concatenate(c) for c in zip(*found, strict=True)) if found else anchors([])


def send(ids: np.ndarray, texts: list[bytes], buckets: int):
    """For each anchor of the part: its first document, how many documents hold it, whether that first one is long."""
    text, *_, prints = all_anchors(texts)
    codes = codes_of(prints, buckets)
    order = np.lexsort((text, codes))
    codes, text = codes[order], text[order]
    new = np.diff(codes, prepend=np.uint64(0)) != 0
    if len(new):
        new[0] = True
    first = np.flatnonzero(new)
    docs = np.add.reduceat(new | (np.diff(text, prepend=-1) != 0), first, dtype=np.int64) if len(first) else first
    size = np.array([len(t) for t in texts], np.int64)
    return codes[first], [ids[text[first]], np.minimum(docs, 255).astype(np.uint8), (size[text[first]] > LONG_DOCUMENT).astype(np.uint8)]


def merge(codes: np.ndarray, arrays: list[np.ndarray]) -> np.ndarray:
    """The route of every anchor that two documents hold, else zero."""
    ids, docs, long = arrays
    order = np.lexsort((ids, codes))
    codes_sorted = codes[order]
    first = np.flatnonzero(np.diff(codes_sorted.astype(np.int64), prepend=-1))
    total = np.add.reduceat(docs[order].astype(np.int64), first)
    home = ids[order][first]
    alone = (total > FEW) | (long[order][first] > 0) | (home == NO_ID)
    with np.errstate(over="ignore"):
        along = mix64(home.astype(np.uint64)) >> np.uint64(2) | np.uint64(1)
        own = mix64(codes_sorted[first].astype(np.uint64) + (home.astype(np.uint64) << np.uint64(20))) >> np.uint64(3) | ALONE
    own = np.where(total > HOT, own | APART, own)
    route = np.where(total > 1, np.where(alone, own, along), np.uint64(0))
    answer = np.zeros(len(codes), np.uint64)
    answer[order] = np.repeat(route, np.diff(np.append(first, len(codes))))
    return answer


merge.kinds = (np.int64, np.uint8, np.uint8)
def apart(texts: list[bytes], text: np.ndarray, low: np.ndarray, high: np.ndarray, place: np.ndarray, route: np.ndarray) -> tuple[np.ndarray, ...]:
    """Text, first and last window and route of every segment, where segments of the hottest anchors are taken apart.

    Window starts that lie k STEP to (k + 1) STEP - 1 before the anchor go together; all hold the bytes from the
    last of these starts to the end of the first's window. Equal windows lie alike around their anchor, so they go together."""
    hot = (route & (ALONE | APART)) == (ALONE | APART)
    if not hot.any():
        return text, low, high, route
    stay = ~hot
    t, a, b, p, r = text[hot], low[hot], high[hot], place[hot], route[hot]
    nearest, farthest = (p - b) // STEP, (p - a) // STEP
    count = farthest - nearest + 1
    which = np.repeat(np.arange(len(t)), count)
    k = np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count) + nearest[which]
    first, last = np.maximum(a[which], p[which] - (k + 1) * STEP + 1), np.minimum(b[which], p[which] - k * STEP)
    middle, size = p[which] - k * STEP, WINDOW - STEP + 1
    told = np.zeros(len(which), np.uint64)
    for x, (d, m) in enumerate(zip(t[which].tolist(), middle.tolist(), strict=True)):
        told[x] = xxhash.xxh3_64_intdigest(texts[d][m : m + size])
    with np.errstate(over="ignore"):
        mixed = mix64(told ^ mix64(r[which] + k.astype(np.uint64))) >> np.uint64(3) | ALONE | APART
    out = [np.concatenate(x) for x in ((text[stay], t[which]), (low[stay], first), (high[stay], last), (route[stay], mixed))]
    order = np.lexsort((out[1], out[0]))
    return tuple(x[order] for x in out)


SEGMENT_SCHEMA = "route long, part long, segment int, bytes binary, least long, most long"


def receive(part: int, ids: np.ndarray, texts: list[bytes], buckets: int, answers_for) -> pa.Table:
    """Distinct segments of the part, and one row with route -1 that tells where each occurs."""
    text, low, high, place, prints = all_anchors(texts)
    codes = codes_of(prints, buckets)
    own, back = np.unique(codes, return_inverse=True)
    route = answers_for(own)[back]
    shared = route != 0
    text, low, high, route = apart(texts, text[shared], low[shared], high[shared], place[shared], route[shared])
    joins = np.zeros(len(text), bool)
    joins[1:] = (text[1:] == text[:-1]) & (low[1:] == high[:-1] + 1) & (route[1:] == route[:-1]) & (route[1:] < ALONE)
    first = np.flatnonzero(~joins)
    last = np.append(first[1:], len(text)) - 1 if len(first) else first
    numbers: dict[tuple[int, bytes], int] = {}
    where = np.zeros(len(first), np.uint32)
    docs, starts, ends = text[first], low[first], high[last] + WINDOW
    for k, (d, a, b, r) in enumerate(zip(docs.tolist(), starts.tolist(), ends.tolist(), route[first].tolist(), strict=True)):
        where[k] = numbers.setdefault((r, texts[d][a:b]), len(numbers))
    least = np.full(len(numbers), NO_ID)
    most = np.full(len(numbers), np.iinfo(np.int64).min)
    np.minimum.at(least, where, ids[docs])
    np.maximum.at(most, where, ids[docs])
    places = pa.table({"segment": where, "text": docs.astype(np.uint32), "start": starts.astype(np.int64)})
    keys = list(numbers)
    columns = [[k[0] for k in keys] + [-1], [part] * (len(keys) + 1), list(range(len(keys))) + [0], [k[1] for k in keys] + [table_bytes(places)], np.append(least, 0), np.append(most, 0)]
    kinds = (pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.int64(), pa.int64())
    return pa.table([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["route", "part", "segment", "bytes", "least", "most"])


def words_at(data: np.ndarray) -> np.ndarray:
    """The eight bytes from each place as one big-endian word; `data` has spare bytes at its end."""
    x = data.astype(np.uint64)
    for shift, step in ((8, 1), (16, 2), (32, 4)):
        x = x[:-step] << np.uint64(shift) | x[step:]
    return x


def suffix_array(data: bytes, depth: int = WINDOW) -> np.ndarray:
    """Starts of all suffixes in order of at least their first `depth` bytes, an ended suffix before its extensions.

    A suffix that is smaller than its successor is sorted directly; the rest are induced from left to right."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64)
    x = np.frombuffer(data + bytes(depth + 1), np.uint8)
    text = x[:n]
    # a suffix compares with its successor as the first byte that differs from its neighbour; the last one is larger than the end
    change = np.flatnonzero(text[1:] != text[:-1])
    smaller = np.zeros(n, bool)
    if len(change):
        rising = text[change + 1] > text[change]
        smaller[: change[-1] + 1] = np.repeat(rising, np.diff(np.concatenate([[-1], change])))
    direct = np.flatnonzero(smaller)
    heads = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(x, depth)[direct]).view(f"S{depth}")[:, 0]
    direct = direct[np.argsort(heads, kind="stable")]
    del heads
    direct_end = np.searchsorted(text[direct], np.arange(257))
    size = np.bincount(text, minlength=256)
    top = np.concatenate([[0], np.cumsum(size)])
    out = np.empty(n, np.int64)
    fill = top[:256].copy()

    def induce(batch: np.ndarray) -> None:
        """Predecessors of a stretch of sorted suffixes that aren't smaller than these go to the front of their buckets, in order."""
        before = batch[batch > 0] - 1
        before = before[~smaller[before]]
        byte = text[before]
        order = np.argsort(byte, kind="stable")
        byte, before = byte[order], before[order]
        count = np.bincount(byte, minlength=256)
        at = fill[byte] + np.arange(len(byte)) - (np.cumsum(count) - count)[byte]
        out[at] = before
        fill[:] += count

    # the end of the text comes before everything and induces the last suffix
    induce(np.array([n]))
    for c in np.flatnonzero(size).tolist():
        done = top[c]
        while done < fill[c]:  # a run of equal bytes induces within its own bucket
            upto = fill[c]
            induce(out[done:upto])
            done = upto
        own = direct[direct_end[c] : direct_end[c + 1]]
        out[top[c + 1] - len(own) : top[c + 1]] = own
        induce(own)
    return out


def common_prefixes(data: bytes, order: np.ndarray, depth: int = WINDOW) -> np.ndarray:
    """Equal leading bytes of each suffix and the one before it, up to `depth`; 0 for the first. Ends must be told apart by the caller."""
    word = words_at(np.frombuffer(data + bytes(depth + 16), np.uint8))
    left, right = order[:-1], order[1:]
    out = np.zeros(len(order), np.int64)
    live = np.arange(len(order) - 1)
    for k in range(0, depth, 8):
        differ = word[left[live] + k] ^ word[right[live] + k]
        ended = differ != 0
        bits = differ[ended]
        whole = np.zeros(len(bits), np.int64)
        for b in range(7):
            whole += (bits >> np.uint64(56 - 8 * b)) == 0
        out[live[ended] + 1] = k + whole
        live = live[~ended]
    out[live + 1] = depth
    return np.minimum(out, depth)


def shared_windows(segments: list[bytes], least: np.ndarray, most: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of windows whose smallest document comes before the largest one of their segment: segment, first start, last start, that document."""
    data = SEPARATOR.join(segments) + SEPARATOR
    sizes = np.array([len(s) + 1 for s in segments], np.int64)
    begin = np.concatenate([[0], np.cumsum(sizes)])
    segment = np.repeat(np.arange(len(segments)), sizes)
    order = suffix_array(data)
    order = order[order + WINDOW < begin[segment[order] + 1]]
    if not len(order):
        return tuple(np.zeros(0, np.int64) for _ in range(4))
    first = np.flatnonzero(common_prefixes(data, order) < WINDOW)
    earliest = np.minimum.reduceat(least[segment[order]], first)
    by_start = np.full(len(data), NO_ID)
    by_start[order] = np.repeat(earliest, np.diff(np.append(first, len(order))))
    hit = by_start < most[segment]
    edge = hit.copy()
    edge[1:] = hit[1:] & ~(hit[:-1] & (segment[1:] == segment[:-1]) & (by_start[1:] == by_start[:-1]))
    a = np.flatnonzero(edge)
    stop = hit.copy()
    stop[:-1] = hit[:-1] & (edge[1:] | ~hit[1:])
    b = np.flatnonzero(stop)
    return segment[a], a - begin[segment[a]], b - begin[segment[a]], by_start[a]


RUN_SCHEMA = "part long, segments binary, firsts binary, lasts binary, ids binary"


def sort_segments(batches):
    """Suffix arrays over whole routes, as many at a time as SORT_BYTES holds; rows come sorted by route."""
    held: list[tuple] = []
    size = 0

    def flush(rows):
        part = np.array([r[1] for r in rows], np.int64)
        number = np.array([r[2] for r in rows], np.int64)
        # equal segments of several parts are sorted once
        distinct: dict[bytes, int] = {}
        of = np.array([distinct.setdefault(r[3], len(distinct)) for r in rows], np.int64)
        most = np.array([r[5] for r in rows], np.int64)
        low, high = np.full(len(distinct), NO_ID), np.full(len(distinct), np.iinfo(np.int64).min)
        np.minimum.at(low, of, np.array([r[4] for r in rows], np.int64))
        np.maximum.at(high, of, most)
        one, a, b, ids = shared_windows(list(distinct), low, high)
        begin, count = np.searchsorted(one, of), np.searchsorted(one, of, side="right") - np.searchsorted(one, of)
        seg = np.repeat(np.arange(len(rows)), count)
        at = np.repeat(begin - np.cumsum(count) + count, count) + np.arange(len(seg))
        a, b, ids = a[at], b[at], ids[at]
        told = ids < most[seg]
        seg, a, b, ids = seg[told], a[told], b[told], ids[told]
        out = []
        order = np.argsort(part[seg], kind="stable")
        seg, a, b, ids = seg[order], a[order], b[order], ids[order]
        first = np.flatnonzero(np.diff(part[seg], prepend=-1))
        for x, y in zip(first, [*first[1:], len(seg)], strict=False):  # none without a hit
            out.append((int(part[seg[x]]), squeezed(number[seg[x:y]]), squeezed(a[x:y]), squeezed(b[x:y]), squeezed(ids[x:y])))
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [[]] * 5, (pa.int64(), *[pa.binary()] * 4), strict=True)], ["part", "segments", "firsts", "lasts", "ids"])

    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if size >= SORT_BYTES and row[0] != held[-1][0]:
                yield flush(held)
                held, size = [], 0
            held.append(row)
            size += len(row[3])
    if held:
        yield flush(held)
    del held
    give_back()


REMOVED_SCHEMA = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"


def removing(with_text: bool, carry_names: list[str], carry_kinds: list[pa.DataType]):
    def run(keys, left, right):
        ids, texts, arrived = unpacked_in_order(left)
        size = np.array([len(t) for t in texts], np.int64)
        base = np.concatenate([[0], np.cumsum(size + 1)])
        delta = np.zeros(int(base[-1]) + 1, np.int32)
        places = [pa.ipc.open_stream(x).read_all() for x in right.column("bytes").to_pylist() if x is not None]
        runs = right.filter(pa.compute.is_valid(right.column("segments")))
        if places and runs.num_rows:
            seg, a, b, least = (np.concatenate([unsqueezed(x, np.int64) for x in runs.column(c).to_pylist()]) for c in ("segments", "firsts", "lasts", "ids"))
            place = {c: places[0].column(c).to_numpy() for c in ("segment", "text", "start")}
            order = np.argsort(seg, kind="stable")
            seg, a, b, least = seg[order], a[order], b[order], least[order]
            lo, hi = np.searchsorted(seg, place["segment"]), np.searchsorted(seg, place["segment"], side="right")
            n = hi - lo
            which = np.repeat(np.arange(len(n)), n)
            at = np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)
            text = place["text"].astype(np.int64)[which]
            later = least[at] < ids[text]
            which, at, text = which[later], at[later], text[later]
            start = base[text] + place["start"][which]
            np.add.at(delta, start + a[at], 1)
            np.add.at(delta, start + b[at] + WINDOW, -1)
        out = []
        for k, t in enumerate(texts):
            mark = np.cumsum(delta[base[k] : base[k] + len(t)], dtype=np.int32) > 0
            n_removed = int(mark.sum())
            spans = int((np.diff(mark.astype(np.int8), prepend=0) == 1).sum())
            kept = np.frombuffer(t, np.uint8)[~mark].tobytes() if n_removed else t
            if with_text and n_removed:
                kept_text = without(t, mark)
            else:
                kept_text = kept
            out.append((None if ids[k] == NO_ID else int(ids[k]), len(t), n_removed, spans, hashlib.sha256(kept).hexdigest(), kept_text if with_text else None))
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
        names = [x.split()[0] for x in REMOVED_SCHEMA.split(", ")]
        columns = [pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [[]] * 6, kinds, strict=True)]
        others = carried(left, arrived) if out and carry_names else [pa.array([], k) for k in carry_kinds]
        return pa.table([*columns, *others], names=[*names, *carry_names])

    return lambda keys, left, right: giving_back(run, keys, left, right)


def without(text: bytes, mark: np.ndarray) -> bytes:
    """The text without its marked bytes; a character of which a byte stays, stays whole."""
    data = np.frombuffer(text, np.uint8)
    lead = (data & 0xC0) != 0x80
    character = np.cumsum(lead) - 1
    stays = np.zeros(int(character[-1]) + 2, bool)
    stays[character[~mark]] = True
    return data[stays[character]].tobytes()


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True, carry: tuple[str, ...] = ()) -> DataFrame:
    """What is removed of every document, and with `with_text` the UTF-8 text that is kept; columns in `carry` come back as carried_0, ..."""
    spark = docs.sparkSession
    parts = Parts(docs, id_col, text_col, carry=carry)
    path = fresh_path(spark, "segments")
    answered(parts, send, merge, receive, SEGMENT_SCHEMA).write.option("compression", "zstd").parquet(path)
    segments = spark.read.schema(SEGMENT_SCHEMA).parquet(path)
    runs = segments.where("route >= 0").repartition("route").sortWithinPartitions("route").mapInArrow(sort_segments, RUN_SCHEMA)
    places = segments.where("route = -1").select("part", "bytes", *(F.lit(None).cast("binary").alias(c) for c in ("segments", "firsts", "lasts", "ids")))
    known = runs.select("part", F.lit(None).cast("binary").alias("bytes"), "segments", "firsts", "lasts", "ids").unionByName(places)
    kinds = [docs.schema[c].dataType for c in carry]
    names = [f"carried_{k}" for k in range(len(carry))]
    schema = T.StructType([*T._parse_datatype_string(REMOVED_SCHEMA).fields, *(T.StructField(n, k) for n, k in zip(names, kinds, strict=True))])
    out = parts.laden.groupBy("part").cogroup(known.groupBy("part")).applyInArrow(removing(with_text, names, [to_arrow_type(k) for k in kinds]), schema)
    return out if with_text else out.drop("kept")
