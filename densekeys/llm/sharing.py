"""Which fingerprints do several documents share: the exchange that duplicate search and suffix sorting start from.

Documents are dealt to parts of about PART_BYTES by the hash that Spark's bucketed tables use, of the id, or of
the text where the id is null, so that what a part writes for a document lies in the bucket of its id. A part turns its documents into
sets of 64-bit fingerprints and sends each bucket of the fingerprint space one compressed block: the sorted
32-bit codes that the part holds in the bucket, with whatever is to be merged. The bucket answers every
part with one compressed block in the order of the part's codes. Nothing is exploded to rows, and nothing
reaches the driver but two counts. Two fingerprints whose codes agree by chance only widen the candidates.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.llm.common import give_back, giving_back, id_and_text, text_bytes

PART_BYTES = 4 << 20
PACKED_ROWS = 4000
#: Tables bucketed by document have no more buckets than this, however many parts there are.
MOST_FILES = 8192
NO_ID = np.iinfo(np.int64).max
BLOB_SCHEMA = "part long, ids binary, sizes binary, texts binary, others binary"


def squeezed(values: np.ndarray) -> bytes:
    """Compressed byte planes of an integer array."""
    values = np.ascontiguousarray(values)
    return zstandard.compress(values.view(np.uint8).reshape(len(values), -1).T.tobytes(), 1) if len(values) else b""


def unsqueezed(data: bytes, dtype) -> np.ndarray:
    if not data:
        return np.zeros(0, dtype)
    raw = np.frombuffer(zstandard.decompress(data), np.uint8)
    return np.ascontiguousarray(raw.reshape(np.dtype(dtype).itemsize, -1).T).view(dtype)[:, 0]


def squeezed_sorted(values: np.ndarray) -> bytes:
    return squeezed(np.diff(values, prepend=values.dtype.type(0)))


def unsqueezed_sorted(data: bytes, dtype) -> np.ndarray:
    return np.cumsum(unsqueezed(data, dtype), dtype=dtype)


class Parts:
    """Documents dealt to parts: packed texts, the number of parts, and of buckets; `carry` names columns that travel along.

    `files` divides `parts`, so that a part writes to one bucket of a table bucketed by document into so many."""

    def __init__(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", part_bytes: int = PART_BYTES, carry: tuple[str, ...] = ()):
        rows = id_and_text(docs, id_col, text_col)
        size = rows.agg(F.sum(F.octet_length("text")).alias("size")).first()["size"] or 0
        tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        self.parts = max(tasks, -(-size // part_bytes))
        self.files = min(self.parts, MOST_FILES)
        self.parts = -(-self.parts // self.files) * self.files
        self.buckets = max(tasks, self.parts // 2)
        key = F.pmod(F.hash(F.coalesce("doc_id", F.xxhash64("text"))), F.lit(self.parts)).cast("long")
        self.blobs = rows.withColumn("part", key).mapInArrow(packed, BLOB_SCHEMA)
        self.laden = self.blobs
        if carry:
            others = [F.col(f"`{c}`").alias(f"carried_{k}") for k, c in enumerate(carry)]
            own = [F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text")]
            self.laden = docs.select(*own, *others).withColumn("part", key).select("doc_id", "text", "part", *[f"carried_{k}" for k in range(len(carry))]).mapInArrow(packed, BLOB_SCHEMA)


def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for start in range(0, whole.num_rows, PACKED_ROWS):
            yield packed_rows(whole.slice(start, PACKED_ROWS))
        give_back()


def packed_rows(batch: pa.RecordBatch) -> pa.RecordBatch:
    """A row for each part that has documents in the batch."""
    ids = batch.column(0).fill_null(int(NO_ID)).to_numpy()
    texts = text_bytes(batch.column(1))
    part = batch.column(2).to_numpy()
    order = np.argsort(part, kind="stable")
    first = np.flatnonzero(np.diff(part[order], prepend=-1))
    rows = []
    for a, b in zip(first, [*first[1:], len(order)], strict=True):
        at = order[a:b]
        held = [texts[i] for i in at]
        others = table_bytes(pa.Table.from_batches([batch.select(batch.schema.names[3:]).take(pa.array(at))])) if batch.num_columns > 3 else None
        rows.append((int(part[at[0]]), ids[at].tobytes(), np.array([len(t) for t in held], np.int64).tobytes(), zstandard.compress(b"".join(held), 1), others))
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), *[pa.binary()] * 4), strict=True)], ["part", "ids", "sizes", "texts", "others"])


def table_bytes(table: pa.Table) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def unpacked(table: pa.Table) -> tuple[np.ndarray, list[bytes]]:
    """Ids (NO_ID for null) and texts of a part, sorted by id and then text, however its blocks arrived."""
    ids, texts, _ = unpacked_in_order(table)
    return ids, texts


def unpacked_in_order(table: pa.Table) -> tuple[np.ndarray, list[bytes], np.ndarray]:
    """As unpacked, with the place of each document in the blocks as they arrived."""
    rows: list[tuple[int, bytes, int]] = []
    for ids, sizes, texts in zip(*(table.column(c).to_pylist() for c in ("ids", "sizes", "texts")), strict=True):
        data, at = zstandard.decompress(texts), 0
        for i, n in zip(np.frombuffer(ids, np.int64).tolist(), np.frombuffer(sizes, np.int64).tolist(), strict=True):
            rows.append((i, data[at : at + n], len(rows)))
            at += n
    rows.sort()
    return np.array([r[0] for r in rows], np.int64), [r[1] for r in rows], np.array([r[2] for r in rows], np.int64)


def carried(table: pa.Table, order: np.ndarray) -> list[pa.Array]:
    """The columns that travelled along, in the order of unpacked_in_order."""
    held = [pa.ipc.open_stream(x).read_all() for x in table.column("others").to_pylist() if x is not None]
    return [c.combine_chunks() for c in pa.concat_tables(held).take(pa.array(order)).columns] if held else []


def codes_of(prints: np.ndarray, buckets: int) -> np.ndarray:
    """The bucket of each fingerprint in the high half, its code there in the low half."""
    return ((prints >> np.uint64(32)) * np.uint64(buckets) & np.uint64(0xFFFFFFFF00000000)) | (prints & np.uint64(0xFFFFFFFF))


def bucket_bounds(codes: np.ndarray, buckets: int) -> np.ndarray:
    """Where each bucket begins in sorted codes, and the end."""
    return np.searchsorted(codes, np.arange(buckets + 1, dtype=np.uint64) << np.uint64(32))


def answered(parts: Parts, send: Callable, merge: Callable, receive: Callable, out_schema: str) -> DataFrame:
    """Three steps: send(ids, texts, buckets) -> sorted codes and arrays to merge; merge(all codes of a bucket,
    arrays one after another) -> an answer for each code; receive(part, ids, texts, buckets, answers) -> table.

    Every array that is sent has a value for each code; answers are unsigned 64-bit words, mostly zero."""
    buckets = parts.buckets

    def sending(keys, table):
        part = keys[0].as_py()
        codes, arrays = send(*unpacked(table), buckets)
        bounds = bucket_bounds(codes, buckets)
        low = codes.astype(np.uint32)
        rows = []
        for k in np.flatnonzero(np.diff(bounds)).tolist():
            a, b = bounds[k], bounds[k + 1]
            rows.append((k, part, squeezed_sorted(low[a:b]), [squeezed(x[a:b]) for x in arrays]))
        kinds = (pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.binary()))
        return pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 4, kinds, strict=True)], names=["bucket", "sender", "codes", "extra"])

    def merging(keys, table):
        table = table.sort_by("sender")
        held = [unsqueezed_sorted(c, np.uint32) for c in table.column("codes").to_pylist()]
        extra = table.column("extra").to_pylist()
        codes = np.concatenate(held)
        answers = merge(codes, [np.concatenate([unsqueezed(x[k], merge.kinds[k]) for x in extra]) for k in range(len(merge.kinds))])
        ends = np.cumsum([len(h) for h in held])
        rows = []
        for part, a, b in zip(table.column("sender").to_pylist(), np.concatenate([[0], ends[:-1]]), ends, strict=True):
            some = answers[a:b] != 0
            if some.any():
                rows.append((part, keys[0].as_py(), zstandard.compress(np.packbits(some).tobytes(), 1), squeezed(answers[a:b][some])))
        kinds = (pa.int64(), pa.int64(), pa.binary(), pa.binary())
        return pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 4, kinds, strict=True)], names=["part", "bucket", "bits", "answers"])

    def receiving(keys, left, right):
        ids, texts = unpacked(left)

        def answers_for(codes: np.ndarray) -> np.ndarray:
            bounds = bucket_bounds(codes, buckets)
            out = np.zeros(len(codes), np.uint64)
            for bucket, bits, values in zip(*(right.column(c).to_pylist() for c in ("bucket", "bits", "answers")), strict=True):
                a, b = bounds[bucket], bounds[bucket + 1]
                some = np.unpackbits(np.frombuffer(zstandard.decompress(bits), np.uint8), count=b - a).astype(bool)
                out[a:b][some] = unsqueezed(values, np.uint64)
            return out

        return receive(left.column("part")[0].as_py() if left.num_rows else -1, ids, texts, buckets, answers_for)

    sent = parts.blobs.groupBy("part").applyInArrow(lambda keys, table: giving_back(sending, keys, table), "bucket long, sender long, codes binary, extra array<binary>")
    back = sent.groupBy("bucket").applyInArrow(lambda keys, table: giving_back(merging, keys, table), "part long, bucket long, bits binary, answers binary")
    return parts.blobs.groupBy("part").cogroup(back.groupBy("part")).applyInArrow(lambda keys, left, right: giving_back(receiving, keys, left, right), out_schema)
