"""Fingerprint families: linear over GF(2), three-word mixing, and the engine's own 64-bit hash.

A family turns ragged keys into words of 32 bits. Word 0 addresses the bucket by its top bits; the bucket kernel
draws values for each try from all words. `linear` is universal with a proof; the others are heuristic."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Fixed: modulus of the sums, the largest prime below 2**32.
PRIME = np.uint64(4294967291)
MASK32 = np.uint64(0xFFFFFFFF)


def splitmix(x: np.ndarray) -> np.ndarray:
    """Stream of well-mixed 64-bit words from counters."""
    z = (x + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


def random_words(seed: int, n: int, stream: int = 0) -> np.ndarray:
    return splitmix(np.arange(n, dtype=np.uint64) + np.uint64((seed << 40) + (stream << 32) & 0xFFFFFFFFFFFFFFFF))


def ragged(keys: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all keys together, and where each begins (and the end)."""
    ends = np.zeros(len(keys) + 1, np.int64)
    np.cumsum([len(k) for k in keys], out=ends[1:])
    return np.frombuffer(b"".join(keys), np.uint8), ends


class LinearHash:
    """h(x) = A x over GF(2), tabulated by chunks of `sigma` bits: a table row for each chunk's position and value.

    Wider chunks take fewer lookups and larger tables; the map is the same."""

    def __init__(self, seed: int, length: int, words: int = 4, sigma: int = 8):
        if sigma not in (4, 8, 16):
            raise ValueError("chunks have 4, 8 or 16 bits")
        self.seed, self.length, self.words, self.sigma = seed, length, words, sigma
        columns = (random_words(seed, 8 * length * words, 1) >> np.uint64(32)).astype(np.uint32).reshape(length, 8, words)
        # bits of a chunk from its least significant; a key's bytes come most significant first
        chunks = -(-8 * length // sigma)
        padded = np.zeros((chunks * sigma // 8 or 1, 8, words), np.uint32) if sigma >= 8 else columns
        padded[:length] = columns
        bits = padded.reshape(chunks, 2, 8, words)[:, ::-1].reshape(chunks, 16, words) if sigma == 16 else padded if sigma == 8 else padded.reshape(length, 2, 4, words)[:, ::-1].reshape(chunks, 4, words)
        table = np.zeros((chunks, 1 << sigma, words), np.uint32)
        for bit in range(sigma):
            half = 1 << bit
            table[:, half : 2 * half] = table[:, :half] ^ bits[:, bit, None]
        self.columns, self.table = columns, table

    @property
    def table_bytes(self) -> int:
        return self.table.nbytes

    def __call__(self, data: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Words of every key; positions after a key's end contribute nothing."""
        size = np.diff(ends)
        if len(size) and size.max() > self.length:
            raise ValueError(f"a key of {size.max()} bytes exceeds the {self.length} of the table")
        order = np.argsort(-size, kind="stable")
        starts, size = ends[:-1][order], size[order]
        out = np.zeros((len(order), self.words), np.uint32)
        spare = np.append(data, np.uint8(0))
        for position in range(0, int(size[0]) if len(size) else 0, max(1, self.sigma // 8)):
            live = int(np.searchsorted(-size, -position, side="left"))
            value = data[starts[:live] + position]
            if self.sigma == 8:
                out[:live] ^= self.table[position][value]
            elif self.sigma == 4:
                out[:live] ^= self.table[2 * position][value >> 4] ^ self.table[2 * position + 1][value & 15]
            else:  # a last byte alone has zeros after it
                low = np.where(position + 1 < size[:live], spare[np.minimum(starts[:live] + position + 1, len(data))], 0)
                out[:live] ^= self.table[position // 2][value.astype(np.int64) << 8 | low]
        back = np.empty_like(out)
        back[order] = out
        return back

    def rows(self, bits: int) -> list[int]:
        """The matrix by rows for keys of one integer of `bits` bits without terminator: row j of word 0 and 1 as masks."""
        flat = self.columns.reshape(-1, self.words)  # column of byte p, bit k at 8 p + k
        out = []
        for j in range(64):
            word, shift = j // 32, 31 - j % 32
            mask = 0
            for place in range(bits):  # place counted from the most significant bit
                p, k = place // 8, 7 - place % 8
                mask |= int(flat[8 * p + k, word] >> np.uint32(shift) & np.uint32(1)) << (bits - 1 - place)
            out.append(mask)
        return out


def _rotated(x: np.ndarray, k: int) -> np.ndarray:
    return (x << np.uint32(k)) | (x >> np.uint32(32 - k))


class MixingHash:
    """Three 32-bit words of state; twelve key bytes at a time are added, then stirred by reversible steps."""

    STEPS = ((7, 0, 1, 2), (19, 1, 2, 0), (13, 2, 0, 1), (25, 0, 2, 1), (5, 1, 0, 2), (16, 2, 1, 0))

    def __init__(self, seed: int):
        self.seed, self.words = seed, 3
        self.start = (random_words(seed, 3, 2) >> np.uint64(32)).astype(np.uint32)

    table_bytes = 4

    @classmethod
    def stir(cls, state: list[np.ndarray]) -> None:
        for rotate, a, b, c in cls.STEPS:
            state[a] = (state[a] - state[b]) ^ _rotated(state[c], rotate)
            state[b] = state[b] + _rotated(state[a], 32 - rotate)
        for a, b in ((2, 0), (0, 1), (1, 2)):
            state[a] = state[a] * np.uint32(0x9E3779B1) ^ (state[b] >> np.uint32(15))

    def __call__(self, data: np.ndarray, ends: np.ndarray) -> np.ndarray:
        size = np.diff(ends)
        n = len(size)
        order = np.argsort(-size, kind="stable")
        starts, size = ends[:-1][order], size[order]
        blocks = -(-size // 12)
        spare = np.concatenate([data, np.zeros(12, np.uint8)])
        state = [np.full(n, w, np.uint32) for w in self.start]
        for k in range(int(blocks[0]) if n else 0):
            live = int(np.searchsorted(-blocks, -k, side="left"))
            at = starts[:live] + 12 * k
            block = spare[at[:, None] + np.arange(12)]
            block[np.arange(12) >= (size[:live] - 12 * k)[:, None]] = 0
            words = np.ascontiguousarray(block).view("<u4")
            part = [state[w][:live] + words[:, w] for w in range(3)]
            self.stir(part)
            for w in range(3):
                state[w][:live] = part[w]
        state[2] = state[2] + size.astype(np.uint32)
        self.stir(state)
        self.stir(state)
        out = np.empty((n, 3), np.uint32)
        out[order] = np.stack(state, axis=1) if n else out
        return out


@dataclass(frozen=True)
class Sums:
    """What a bucket's values need for each key before the seed of a try is known: value = (a + s b) mod p mod size."""

    a: np.ndarray
    b: np.ndarray

    def values(self, seeds: np.ndarray, size: np.ndarray) -> np.ndarray:
        return ((self.a + seeds * self.b) % PRIME % size).astype(np.int64)


class ChunkTables:
    """Sums of random table entries over 16-bit chunks of the words after the address.

    A chunk's lowest and highest bits are forced to zero; setting the lowest gives the second function without ever
    meeting another key's chunk. Twelve tables of 2**15 entries serve six chunks."""

    BITS = 15

    def __init__(self, seed: int, chunks: int = 6):
        self.chunks = chunks
        self.tables = (random_words(seed, 2 * chunks << self.BITS, 3) % PRIME).reshape(2 * chunks, 1 << self.BITS)

    @property
    def table_bytes(self) -> int:
        return self.tables.size * 4

    def split(self, words: np.ndarray) -> np.ndarray:
        """The last `chunks` 16-bit pieces of the words, masked."""
        halves = np.empty((len(words), 2 * words.shape[1]), np.int64)
        halves[:, 0::2], halves[:, 1::2] = words >> np.uint32(16), words & np.uint32(0xFFFF)
        return halves[:, -self.chunks :] & 0x7FFE

    def sums(self, words: np.ndarray) -> tuple[Sums, Sums]:
        y = self.split(words)
        out = []
        for delta in (0, 1):
            at = y | delta
            a, b = (sum((self.tables[j + k * self.chunks][at[:, j]] for j in range(self.chunks)), np.zeros(len(y), np.uint64)) % PRIME for k in (0, 1))
            out.append(Sums(a, b))
        return out[0], out[1]


class MixedValues:
    """The heuristic families: both sums are mixes of all words, so no table is stored."""

    table_bytes = 0

    def sums(self, words: np.ndarray) -> tuple[Sums, Sums]:
        high = words[:, 0].astype(np.uint64) << np.uint64(32) | words[:, 1]
        low = words[:, -1].astype(np.uint64) << np.uint64(32) | words[:, -2]
        out = []
        for delta in (1, 2):
            x = splitmix(high ^ splitmix(low + np.uint64(delta << 33)))
            out.append(Sums((x >> np.uint64(32)) % PRIME, (x & MASK32) % PRIME))
        return out[0], out[1]


class TabulatedValues:
    """The universal family of the whole set: a 64-bit digest by bytes, each looked up in its own table of 256 random words.

    The entries that the eight bytes pick are combined by exclusive or; either function has a set of tables of its own.
    One half of the result is the sum, the other what a try's seed multiplies."""

    BYTES = 8

    def __init__(self, seed: int):
        self.tables = random_words(seed, 2 * self.BYTES * 256, 4).reshape(2, self.BYTES, 256)

    @property
    def table_bytes(self) -> int:
        return self.tables.nbytes

    def looked_up(self, digest: np.ndarray, which: int) -> np.ndarray:
        out = np.zeros(len(digest), np.uint64)
        for k in range(self.BYTES):
            out ^= self.tables[which, k][(digest >> np.uint64(8 * k) & np.uint64(0xFF)).astype(np.int64)]
        return out

    def sums(self, words: np.ndarray) -> tuple[Sums, Sums]:
        digest = words[:, 0].astype(np.uint64) << np.uint64(32) | words[:, 1]
        out = [self.looked_up(digest, k) for k in range(2)]
        return tuple(Sums((x >> np.uint64(32)) % PRIME, (x & MASK32) % PRIME) for x in out)
