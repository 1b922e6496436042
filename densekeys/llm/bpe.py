"""BPE encoding and decoding with contiguous rank arrays.

A short word is a row of part ids with, beside them, the rank of each adjacent pair. The smallest rank is
found by scanning the row, the right-hand boundary of that pair is deleted, the rest of the row moves up,
and only the two neighbouring ranks are looked up again. Rows of many words are held in one matrix, so each
scan and deletion is one array operation for the whole block. Words longer than LONG_WORD bytes use a
heap over linked parts instead, because repeated scans would cost the square of their length.

Texts are taken in blocks. The bounds of all words of a block are found by the classes of its bytes, each word is
known by a hash of 128 bits, and only words that aren't remembered are encoded; ids are gathered by index.

The vocabulary is a `tokenizers` file of the kind: NFC, white space to blanks, lower case, split into
letters, single digits, other signs and English endings, bytes as printable characters, word-end suffix.

Defined cases: a null text is empty and has no tokens; the vocabulary's special strings in a text are their
own tokens; repeated rows are encoded each; an empty table gives an empty result. Code points that Python's
character tables don't know yet count as unassigned signs, whatever a later library makes of them.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import os.path
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from densekeys.llm.common import id_and_text, mix64, seeded_words, text_strings
from densekeys.llm.words import BYTE_WORDS, powers

LONG_WORD = 48
BLOCK_CHARS = 1 << 19
KEPT_WORDS = 300_000
SPACE, LETTER, NUMBER, OTHER = range(4)
OTHER_WORDS = seeded_words(29, 256)
APOSTROPHE = ord("'")
#: Fixed: English endings that are words of their own after an apostrophe.
ENDINGS = (b"s", b"t", b"re", b"ve", b"m", b"ll", b"d")


@lru_cache(maxsize=1)
def classes() -> np.ndarray:
    """The class of every code point: white space, letter, number or other."""
    out = np.full(0x110000, OTHER, np.uint8)
    for k in range(0x110000):
        kind = unicodedata.category(chr(k))[0]
        if kind in "LN":
            out[k] = LETTER if kind == "L" else NUMBER
    for found in regex.finditer(r"\p{White_Space}", "".join(map(chr, range(0x3100)))):
        out[ord(found.group())] = SPACE
    return out


def byte_signs() -> list[str]:
    """The printable character that stands for each byte: itself if printable, else one from 256 on."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(spare)) for b in range(256)]


class WordBpe:
    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        model = spec["model"]
        vocab, end = model["vocab"], model["end_of_word_suffix"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens: dict[int, str] = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}
        self.special_split = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        #: What every special string begins with; a text without it holds none.
        self.special_start = os.path.commonprefix(list(self.special))
        signs = byte_signs()
        # ids and ranks of a small vocabulary take half as much room
        small = max(max(vocab.values()), len(model["merges"])) < 0xFFFF
        self.kind, self.pair_kind, self.shift = (np.uint16, np.uint32, 16) if small else (np.uint32, np.uint64, 32)
        self.no_rank = self.kind(np.iinfo(self.kind).max)
        self.inner = np.array([vocab[s] for s in signs], self.kind)
        self.last = np.array([vocab[s + end] for s in signs], self.kind)
        pairs = np.array([(vocab[a] << self.shift) | vocab[b] for a, b in model["merges"]], self.pair_kind)
        order = np.argsort(pairs, kind="stable")
        self.pairs, self.pair_rank = pairs[order], order.astype(self.kind)
        self.made = np.array([vocab[a + b] for a, b in model["merges"]], self.kind)
        self.ranks = dict(zip(pairs.tolist(), range(len(pairs)), strict=True))

    def rank_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left.astype(self.pair_kind) << self.pair_kind(self.shift) | right
        at = np.minimum(np.searchsorted(self.pairs, key), len(self.pairs) - 1)
        return np.where(self.pairs[at] == key, self.pair_rank[at], self.no_rank)

    def short_words(self, data: np.ndarray, start: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words of at most LONG_WORD bytes that stand in `data`, one after another, and how many each has."""
        order = np.argsort(length, kind="stable")
        found, size = [], np.zeros(len(order), np.int64)
        for a in range(0, len(order), 4096):
            rows = order[a : a + 4096]
            ids, size[rows] = self._block(data, start[rows], length[rows])
            found.append(ids)
        flat = np.concatenate(found) if found else np.zeros(0, np.uint32)
        return flat[ragged(np.cumsum(size[order]) - size[order], size[order], np.argsort(order, kind="stable"))], size

    def _block(self, data: np.ndarray, start: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n, width = len(start), int(lengths.max())
        raw = data[np.minimum(start[:, None] + np.arange(width), len(data) - 1)]
        columns = np.arange(width, dtype=np.int16)
        parts = self.inner[raw]
        parts[np.arange(n), lengths - 1] = self.last[raw[np.arange(n), lengths - 1]]
        ranks = np.full((n, width), self.no_rank, self.kind)
        if width > 1:
            ranks[:, :-1] = np.where(columns[1:] < lengths[:, None], self.rank_of(parts[:, :-1], parts[:, 1:]), self.no_rank)
        size = lengths.copy()
        done_parts, live = parts.copy(), np.arange(n)
        while len(live):
            best = ranks.argmin(axis=1)
            rank = ranks[np.arange(len(live)), best]
            ended = rank == self.no_rank
            if ended.any():
                done_parts[live[ended]] = parts[ended]
                keep = ~ended
                live, parts, ranks, best, rank = live[keep], parts[keep], ranks[keep], best[keep], rank[keep]
                if not len(live):
                    break
            row = np.arange(len(live))
            behind = columns[:-1] >= best[:, None]
            after = ranks.copy()
            np.copyto(after[:, :-1], ranks[:, 1:], where=behind)
            after[:, -1] = self.no_rank
            shorter = parts.copy()
            np.copyto(shorter[:, :-1], parts[:, 1:], where=behind)
            parts = shorter
            parts[row, best] = self.made[rank]
            size[live] -= 1
            has_left, has_right = best > 0, best + 1 < size[live]
            after[row, best] = self.no_rank
            r = row[has_right]
            after[r, best[r]] = self.rank_of(parts[r, best[r]], parts[r, best[r] + 1])
            r = row[has_left]
            after[r, best[r] - 1] = self.rank_of(parts[r, best[r] - 1], parts[r, best[r]])
            ranks = after
        return done_parts[columns < size[:, None]].astype(np.uint32), size

    def long_word(self, word: bytes) -> np.ndarray:
        parts = self.inner[np.frombuffer(word, np.uint8)].tolist()
        parts[-1] = int(self.last[word[-1]])
        n, shift = len(parts), self.shift
        left, right, alive = list(range(-1, n - 1)), list(range(1, n + 1)), [True] * n
        heap = [(r, i, parts[i], parts[i + 1]) for i in range(n - 1) if (r := self.ranks.get(parts[i] << shift | parts[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            rank, i, a, b = heapq.heappop(heap)
            j = right[i]
            if not alive[i] or j >= n or parts[i] != a or parts[j] != b:
                continue
            parts[i], alive[j], right[i] = int(self.made[rank]), False, right[j]
            if right[j] < n:
                left[right[j]] = i
            for x, y in ((left[i], i), (i, right[i])):
                if x >= 0 and y < n and (r := self.ranks.get(parts[x] << shift | parts[y])) is not None:
                    heapq.heappush(heap, (r, x, parts[x], parts[y]))
        return np.array([p for p, a in zip(parts, alive, strict=True) if a], np.uint32)

    def words(self, data: np.ndarray, start: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words of any length, one word after another, and how many each has."""
        short = length <= LONG_WORD
        if short.all():
            return self.short_words(data, start, length)
        flat, size = self.short_words(data, start[short], length[short])
        found = [self.long_word(data[a : a + n].tobytes()) for a, n in zip(start[~short].tolist(), length[~short].tolist(), strict=True)]
        sizes, begins = np.zeros(len(start), np.int64), np.zeros(len(start), np.int64)
        sizes[short], begins[short] = size, np.cumsum(size) - size
        more = np.array([len(f) for f in found], np.int64)
        sizes[~short], begins[~short] = more, len(flat) + np.cumsum(more) - more
        return np.concatenate([flat, *found])[ragged(begins, sizes, np.arange(len(start)))], sizes

    def encode(self, text: str) -> list[int]:
        return next(Encoder(self).texts([text])).tolist()

    def decode(self, ids: list[int]) -> str:
        """The tokens as the vocabulary spells them, joined by blanks (its file names no other decoder)."""
        return " ".join(self.tokens[i] for i in ids)


def ragged(begins: np.ndarray, sizes: np.ndarray, order: np.ndarray) -> np.ndarray:
    """Indices of the elements of the stretches at `order`, one stretch after another."""
    size = sizes[order]
    ends = np.cumsum(size)
    return np.repeat(begins[order] - (ends - size), size) + np.arange(ends[-1] if len(ends) else 0)


def normalised(text: str) -> str:
    if not text.isascii():
        if not unicodedata.is_normalized("NFC", text):
            text = unicodedata.normalize("NFC", text)
        text = text.replace("Σ", "σ")  # lower() would treat a final one apart
    return text.lower()


def word_bounds(text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a normalised text that ends in white space, and where its words begin and end."""
    data = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    if text.isascii():
        kind, lead = classes()[:128][data], None
    else:
        lead = (data & 0xC0) != 0x80
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        kind = classes()[points][np.cumsum(lead) - 1]
    edge = np.ones(len(data), bool)
    edge[1:] = kind[1:] != kind[:-1]
    numbers = kind == NUMBER
    edge |= numbers if lead is None else numbers & lead
    # an apostrophe that begins a run of signs begins an ending, if one follows
    quotes = np.flatnonzero(edge & (data == APOSTROPHE))
    if len(quotes):
        after = [data[np.minimum(quotes + k, len(data) - 1)] for k in (1, 2)]
        for ending in ENDINGS:
            fits = after[0] == ending[0]
            if len(ending) == 2:
                fits &= after[1] == ending[1]
            at = quotes[fits]
            edge[at + 1] = False
            then = at + 1 + len(ending)
            edge[then[kind[then] == LETTER]] = True
    bounds = np.flatnonzero(edge)
    word = kind[bounds] != SPACE
    return data, bounds[word], np.append(bounds[1:], len(data))[word]


class Encoder:
    """Ids of texts. Words are remembered by their hash; when KEPT_WORDS are held, those that weren't met again are given up, so that memory is bounded."""

    def __init__(self, bpe: WordBpe):
        self.bpe = bpe
        self._keep(np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.uint32))

    def _keep(self, key: np.ndarray, check: np.ndarray, size: np.ndarray, flat: np.ndarray) -> None:
        self.row_of: dict[int, int] = dict(zip(key.tolist(), range(len(key)), strict=True))
        self.key, self.check, self.size, self.flat = [key], [check], [size], [flat]
        self.met = np.zeros(2 * KEPT_WORDS, bool)

    def _joined(self, held: list[np.ndarray]) -> np.ndarray:
        if len(held) > 1:
            held[:] = [np.concatenate(held)]
        return held[0]

    def _give_up(self) -> None:
        """Only words met again stay, and none if that were more than half of those allowed."""
        size = self._joined(self.size)
        again = np.flatnonzero(self.met[: len(size)])
        if len(again) > KEPT_WORDS // 2:
            again = again[:0]
        flat = self._joined(self.flat)[ragged(np.cumsum(size) - size, size, again)]
        self._keep(self._joined(self.key)[again], self._joined(self.check)[again], size[again], flat)

    def _rows(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """The remembered row of each word; new words are encoded together."""
        up, down = powers(len(data) + 1)
        length = (end - start).astype(np.uint64)
        prints = []
        for table in (BYTE_WORDS, OTHER_WORDS):
            sums = np.zeros(len(data) + 1, np.uint64)
            np.cumsum(table[data] * up[:-1], out=sums[1:])
            prints.append(mix64((sums[end] - sums[start]) * down[start] + length * table[0]))
        key, check = prints
        distinct, first, back = np.unique(key, return_index=True, return_inverse=True)
        if (check[first][back] != check).any():  # two words of one hash: take them apart by both
            _, first, back = np.unique(np.stack([key, check], axis=1), axis=0, return_index=True, return_inverse=True)
            back, distinct = back.reshape(-1), mix64(key[first] ^ mix64(check[first]))
        if len(self.row_of) + len(distinct) > KEPT_WORDS and len(self.row_of):
            self._give_up()
        names = distinct.tolist()
        rows = np.fromiter(map(self.row_of.get, names, [-1] * len(names)), np.int64, len(names))
        if (self._joined(self.check)[rows[rows >= 0]] != check[first][rows >= 0]).any():
            self._keep(distinct[:0], check[:0], np.zeros(0, np.int64), np.zeros(0, np.uint32))
            rows[:] = -1
        if len(self.row_of) + len(names) > len(self.met):  # a block of very many words
            self.met = np.concatenate([self.met, np.zeros(len(self.row_of) + len(names), bool)])
        self.met[rows[rows >= 0]] = True
        new = np.flatnonzero(rows < 0)
        if len(new):
            at = first[new]
            ids, size = self.bpe.words(data, start[at], end[at] - start[at])
            rows[new] = len(self.row_of) + np.arange(len(new))
            self.row_of.update(zip([names[k] for k in new.tolist()], rows[new].tolist(), strict=True))
            for held, more in ((self.key, distinct[new]), (self.check, check[at]), (self.size, size), (self.flat, ids)):
                held.append(more)
        return rows[back]

    def _together(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of texts without special strings."""
        plain = [normalised(t) for t in texts]
        data, start, end = word_bounds("\n".join(plain) + "\n")
        if not len(start):
            return [np.zeros(0, np.uint32)] * len(texts)
        rows = self._rows(data, start, end)
        size = self._joined(self.size)
        ids = self._joined(self.flat)[ragged(np.cumsum(size) - size, size, rows)]
        of_text = np.cumsum([len(t) + 1 if t.isascii() else len(t.encode("utf-8", "surrogatepass")) + 1 for t in plain])
        words = np.searchsorted(start, of_text)
        ends = np.concatenate([[0], np.cumsum(size[rows])])[words].tolist()
        return [ids[a:b] for a, b in zip([0, *ends], ends, strict=False)]

    def _with_specials(self, text: str) -> np.ndarray:
        parts = self.bpe.special_split.split(text)
        found = self._together(parts[::2])
        out = [found[0]]
        for name, ids in zip(parts[1::2], found[1:], strict=True):
            out += [np.array([self.bpe.special[name]], np.uint32), ids]
        return np.concatenate(out)

    def texts(self, texts: list[str]) -> Iterator[np.ndarray]:
        """Ids of each text, block by block."""
        held, size = [], 0
        for text in texts:
            if self.bpe.special_split is not None and self.bpe.special_start in text:
                yield from self._together(held)
                held, size = [], 0
                yield self._with_specials(text)
                continue
            held.append(text)
            size += len(text)
            if size >= BLOCK_CHARS:
                yield from self._together(held)
                held, size = [], 0
        yield from self._together(held)


@lru_cache(maxsize=2)
def loaded(path: str) -> WordBpe:
    return WordBpe(path)


@lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    """One for each Python worker, so that its tasks share what it remembers."""
    return Encoder(loaded(path))


def encode_documents(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids (array), decoded: every whole text encoded, and its ids decoded again."""

    def run(batches):
        words = encoder(vocabulary)
        for batch in batches:
            ids = [x.tolist() for x in words.texts(text_strings(batch.column(1)))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32())), pa.array([words.bpe.decode(x) for x in ids], pa.string())], ["doc_id", "ids", "decoded"])

    return id_and_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, ids array<int>, decoded string")


def encoding_digests(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Digests of what encode_documents gives, without carrying ids and texts out of the task."""

    def run(batches):
        words = encoder(vocabulary)
        tokens, decimal = words.bpe.tokens, {i: str(i) for i in words.bpe.tokens}
        for batch in batches:
            counts, id_sums, text_sums = [], [], []
            for ids in words.texts(text_strings(batch.column(1))):
                listed = ids.tolist()
                counts.append(len(listed))
                id_sums.append(hashlib.sha256(" ".join(map(decimal.__getitem__, listed)).encode()).hexdigest())
                text_sums.append(hashlib.sha256(" ".join(map(tokens.__getitem__, listed)).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(id_sums, pa.string()), pa.array(text_sums, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return id_and_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
