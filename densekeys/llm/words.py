"""Words of many texts at once: positions, 64-bit hashes and document bounds, in array operations."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from densekeys.llm.common import mix64, seeded_words

BLOCK_BYTES = 1 << 19
#: Fixed: white space by the contract of the corpus operators.
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
LOWERED = np.arange(256, dtype=np.uint8)
LOWERED[65:91] += 32
#: Bytes that words of letters and digits are made of; those of non-ASCII characters count as letters.
LETTERS = np.zeros(256, bool)
LETTERS[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True

BYTE_WORDS = seeded_words(11, 256)
RADIX = np.uint64(0x9E3779B97F4A7C55)
RADIX_INVERSE = np.uint64(pow(0x9E3779B97F4A7C55, -1, 1 << 64))
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """RADIX**i and its inverse for i < n."""
    if len(_powers[0]) < n:
        size = 1 << (n - 1).bit_length()
        for k, radix in enumerate((RADIX, RADIX_INVERSE)):
            x = np.full(size, radix, np.uint64)
            x[0] = 1
            _powers[k] = np.multiply.accumulate(x)
    return _powers[0][:n], _powers[1][:n]


def prefix_sums(data: np.ndarray) -> np.ndarray:
    """sums[i] of the hashed bytes before i, each times the radix to its position."""
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(BYTE_WORDS[data] * powers(len(data))[0], out=sums[1:])
    return sums


def hashes_between(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Position-independent hash of the bytes from each start to each end."""
    h = (sums[ends] - sums[starts]) * powers(len(sums))[1][starts]
    return mix64(h + (ends - starts).astype(np.uint64) * np.uint64(0xA24BAED4963EE407))


def blocks(texts: list[bytes], limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about `limit` bytes together; a longer text is a block alone."""
    a = 0
    while a < len(texts):
        b, size = a, 0
        while b < len(texts) and (b == a or size + len(texts[b]) <= limit):
            size += len(texts[b])
            b += 1
        yield a, b
        a = b


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The texts with a blank after each, and where each starts (one bound more than texts)."""
    data = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
    bounds = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) + 1 for t in texts], out=bounds[1:])
    return data, bounds


def spans(inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs where `inside` holds; it must be false at the end."""
    steps = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    if len(inside) and inside[0]:
        steps = np.concatenate([[0], steps])
    return steps[::2], steps[1::2]


def hashed_words(texts: list[bytes], word_bytes: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every lower-cased word in order, and for each text the index of its first word (one more at the end)."""
    data, bounds = joined(texts)
    data = LOWERED[data]
    starts, ends = spans(~SPACE[data] if word_bytes is None else word_bytes[data])
    return hashes_between(prefix_sums(data), starts, ends), np.searchsorted(starts, bounds)


#: Classes for the shape of a run: lower, upper, digit, other letters; signs stand for themselves.
SHAPES = np.arange(256, dtype=np.uint8)
SHAPES[97:123], SHAPES[65:91], SHAPES[48:58], SHAPES[128:] = 97, 65, 48, 97
SHAPES[[9, 11, 12, 13]] = 32


def hashed_shapes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hash of the shape of every run between white space, equal neighbours merged, in order, as hashed_words; line ends are runs of their own."""
    data, bounds = joined(texts)
    data = SHAPES[data]
    keep = np.ones(len(data), bool)
    keep[1:] = (data[1:] != data[:-1]) | (data[1:] == 32) | (data[1:] == 10)
    keep[bounds[1:] - 1] = True
    bounds = np.concatenate([[0], np.cumsum(keep)])[bounds]
    data = data[keep]
    edge = SPACE[data]
    starts, ends = spans(~edge)
    lines = np.flatnonzero(data == 10)
    starts, ends = np.concatenate([starts, lines]), np.concatenate([ends, lines + 1])
    order = np.argsort(starts, kind="stable")
    starts, ends = starts[order], ends[order]
    return hashes_between(prefix_sums(data), starts, ends), np.searchsorted(starts, bounds)
