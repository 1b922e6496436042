"""Bit vectors of many buckets side by side, each padded to whole 64-bit words, and rank over them."""

from __future__ import annotations

import numpy as np

WORD = 64


def words_for(bits: np.ndarray) -> np.ndarray:
    """Words that each bucket's bits take."""
    return -(-np.asarray(bits, np.int64) // WORD)


def packed(flags: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Flags of consecutive buckets of the given sizes, as padded words, lowest bit first."""
    words = words_for(sizes)
    first = np.concatenate([[0], np.cumsum(sizes)[:-1]]) if len(sizes) else np.zeros(0, np.int64)
    base = np.concatenate([[0], np.cumsum(words)[:-1]]) if len(sizes) else np.zeros(0, np.int64)
    out = np.zeros(int(words.sum()) * WORD, bool)
    at = np.arange(len(flags)) - np.repeat(first, sizes) + np.repeat(base * WORD, sizes)
    out[at] = flags
    return np.packbits(out, bitorder="little").view("<u8")


def bit_at(words: np.ndarray, at: np.ndarray) -> np.ndarray:
    return (words[at >> 6] >> (at & 63).astype(np.uint64) & np.uint64(1)).astype(bool)


def popcount(x: np.ndarray, bits: int | str = "native") -> np.ndarray:
    """Set bits of 64-bit words: by the processor, or by a shared table of 2**bits counts."""
    if bits == "native":
        return np.bitwise_count(x).astype(np.int64)
    table = np.bitwise_count(np.arange(1 << int(bits), dtype=np.uint32)).astype(np.int64)
    mask = np.uint64((1 << int(bits)) - 1)
    return sum(table[(x >> np.uint64(s) & mask).astype(np.int64)] for s in range(0, 64, int(bits)))


def below(x: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The lowest n bits of each word, 0 <= n <= 64."""
    n = n.astype(np.uint64)
    full = n >= np.uint64(64)
    mask = (np.uint64(1) << np.where(full, np.uint64(0), n)) - np.uint64(1)
    return np.where(full, x, x & mask)


def theory_steps(tau: np.ndarray, eps_rank: float) -> np.ndarray:
    """The step for which the directory takes about eps_rank tau bits: floor(log2(tau) / eps_rank), at least 1."""
    return np.maximum(1, np.floor(np.log2(np.maximum(2, tau)) / eps_rank)).astype(np.int64)


def directory(flags: np.ndarray, sizes: np.ndarray, kappa: int | np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Set flags of the bucket before every kappa-th place, and where each bucket's entries begin (and the end); kappa may differ by bucket."""
    kappa = np.broadcast_to(np.asarray(kappa, np.int64), sizes.shape)
    entries = -(-sizes // kappa)
    first = np.concatenate([[0], np.cumsum(sizes)])
    begin = np.concatenate([[0], np.cumsum(entries)])
    total = np.concatenate([[0], np.cumsum(flags)])
    bucket = np.repeat(np.arange(len(sizes)), entries)
    at = first[bucket] + (np.arange(begin[-1]) - begin[bucket]) * kappa[bucket]
    return total[at] - total[first[bucket]], begin


def rank(words: np.ndarray, word_base: np.ndarray, entries: np.ndarray, entry_base: np.ndarray, place: np.ndarray, kappa: int | np.ndarray, bits: int | str = "native") -> np.ndarray:
    """Set bits of the bucket before `place`: its directory entry and the bits between. kappa: one, or one for each place."""
    near = place // kappa
    out = entries[entry_base + near].astype(np.int64)
    start = near * kappa
    for k in range(-(-int(np.max(kappa, initial=1)) // WORD) + 1):
        word = (start >> 6) + k
        live = np.flatnonzero(word << 6 < place)
        if not len(live):
            break
        w = word[live]
        x = words[word_base[live] + w]
        upto = below(x, np.minimum(place[live] - (w << 6), 64))
        skip = below(x, np.clip(start[live] - (w << 6), 0, 64))
        out[live] += popcount(upto ^ skip, bits)
    return out
