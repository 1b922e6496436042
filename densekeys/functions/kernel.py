"""The bucket kernel: random acyclic bipartite graphs for many buckets at once, and the functions they give.

A key is an edge between one of tau left and one of tau right vertices of its bucket. Peeling leaves shows
whether all graphs are forests; buckets whose graph isn't draw again. Played backwards, the peeling hands
every edge its leaf: the leaf's label is its parent's, flipped if the leaf is on the right, so that the labels
of an edge tell which of its ends is its own. Peeling never takes a root, whose label stays zero."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from densekeys.functions.hashing import PRIME, Sums, splitmix
from densekeys.functions.rank import bit_at, directory, packed, rank, words_for

MAX_TRIES = 200


class NoForest(RuntimeError):
    """A bucket's graph had a cycle in every try."""


def side_sizes(sizes: np.ndarray, eps: float) -> np.ndarray:
    """tau of each bucket: ceil((1 + eps) size), at least 1."""
    return np.maximum(1, np.ceil((1 + eps) * np.asarray(sizes, np.float64) - 1e-9)).astype(np.int64)


def seeds_for(master: int, buckets: np.ndarray, tries: np.ndarray) -> np.ndarray:
    """Seed of a try in 1..p-1: a function of master seed, bucket and try alone."""
    x = splitmix(splitmix(buckets.astype(np.uint64) + splitmix(np.array([master], np.uint64))) + tries.astype(np.uint64))
    return x % (PRIME - np.uint64(1)) + np.uint64(1)


def peel(left: np.ndarray, right: np.ndarray, vertices: int) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
    """Edges that no peeling removes, and the rounds of (edge, leaf) that it removed."""
    n = len(left)
    ends = np.concatenate([left, right])
    ids = np.concatenate([np.arange(n), np.arange(n)])
    degree = np.bincount(ends, minlength=vertices)
    # with one edge left at a vertex, the sum of its edges is that edge
    total = np.zeros(vertices, np.int64)
    order = np.argsort(ends, kind="stable")
    if n:
        first = np.flatnonzero(np.diff(ends[order], prepend=-1))
        total[ends[order][first]] = np.add.reduceat(ids[order], first)
    rounds = []
    leaves = np.flatnonzero(degree == 1)
    alive = np.ones(n, bool)
    while len(leaves):
        edge = total[leaves]
        # both ends of a lone edge are leaves; the right one is taken, so the left one is the root
        order = np.lexsort((leaves == left[edge], edge))
        edge, leaves = edge[order], leaves[order]
        keep = np.diff(edge, prepend=-1) != 0
        edge, leaves = edge[keep], leaves[keep]
        rounds.append((edge, leaves))
        alive[edge] = False
        other = left[edge] + right[edge] - leaves
        degree[leaves] = 0
        np.subtract.at(degree, other, 1)
        np.subtract.at(total, other, edge)
        near = np.unique(other)
        leaves = near[degree[near] == 1]
    return np.flatnonzero(alive), rounds


def labels_of(left: np.ndarray, right: np.ndarray, rounds: list[tuple[np.ndarray, np.ndarray]], vertices: int) -> np.ndarray:
    label = np.zeros(vertices, bool)
    for edge, leaf in reversed(rounds):
        parent = left[edge] + right[edge] - leaf
        label[leaf] = label[parent] ^ (leaf == right[edge])
    return label


@dataclass
class Buckets:
    """Functions of consecutive buckets: sizes, seeds, tries, labels and occupied slots (flat over 2 tau places each)."""

    numbers: np.ndarray
    sizes: np.ndarray
    seeds: np.ndarray
    tries: np.ndarray
    labels: np.ndarray
    occupied: np.ndarray


def build(numbers: np.ndarray, sizes: np.ndarray, sums: tuple[Sums, Sums], eps: float, master: int, max_tries: int = MAX_TRIES) -> Buckets:
    """Keys come in the order of their buckets. Raises NoForest if a bucket has none in max_tries."""
    tau = side_sizes(sizes, eps)
    base = np.concatenate([[0], 2 * np.cumsum(tau)])
    bucket = np.repeat(np.arange(len(sizes)), sizes)
    seeds, tries = np.zeros(len(sizes), np.uint64), np.zeros(len(sizes), np.int64)
    labels, occupied = np.zeros(base[-1], bool), np.zeros(base[-1], bool)
    open_buckets = np.arange(len(sizes))
    keys = np.arange(len(bucket))
    for k in range(max_tries):
        seeds[open_buckets] = seeds_for(master, numbers[open_buckets], np.full(len(open_buckets), k))
        tries[open_buckets] = k + 1
        of = bucket[keys]
        # vertices of the open buckets only, numbered anew
        place = np.zeros(len(sizes), np.int64)
        starts = np.concatenate([[0], np.cumsum(2 * tau[open_buckets])])
        place[open_buckets] = starts[:-1]
        v = [Sums(s.a[keys], s.b[keys]).values(seeds[of], tau[of].astype(np.uint64)) for s in sums]
        left, right = place[of] + v[0], place[of] + tau[of] + v[1]
        rest, rounds = peel(left, right, int(starts[-1]))
        label = labels_of(left, right, rounds, int(starts[-1]))
        leaf = np.zeros(int(starts[-1]), bool)
        for _, leaves in rounds:
            leaf[leaves] = True
        failed = np.unique(of[rest])
        good = np.setdiff1d(open_buckets, failed, assume_unique=True)
        span = 2 * tau[good]
        source = np.repeat(place[good], span) + np.arange(span.sum()) - np.repeat(np.cumsum(span) - span, span)
        target = np.repeat(base[good], span) + np.arange(span.sum()) - np.repeat(np.cumsum(span) - span, span)
        labels[target], occupied[target] = label[source], leaf[source]
        if not len(failed):
            return Buckets(numbers, sizes, seeds, tries, labels, occupied)
        open_buckets = failed
        again = np.zeros(len(sizes), bool)
        again[failed] = True
        keys = keys[again[of]]
    raise NoForest(f"{len(open_buckets)} buckets have no forest in {max_tries} tries")


class Functions:
    """Packed functions of many buckets, ready to evaluate: slot (into 2 tau) and id (into the bucket's keys)."""

    def __init__(self, numbers: np.ndarray, sizes: np.ndarray, seeds: np.ndarray, offsets: np.ndarray, labels: np.ndarray, occupied: np.ndarray, eps: float, kappa: int | np.ndarray, compressed: bool, slot_offsets: np.ndarray):
        self.numbers, self.sizes, self.seeds, self.offsets, self.eps, self.compressed = numbers, sizes, seeds, offsets, eps, compressed
        self.labels, self.occupied, self.slot_offsets = labels, occupied, slot_offsets
        self.tau = side_sizes(sizes, eps)
        self.kappa = np.broadcast_to(np.asarray(kappa, np.int64), self.tau.shape)
        self.word_base = np.concatenate([[0], np.cumsum(words_for(2 * self.tau))])
        self.label_base = np.concatenate([[0], np.cumsum(words_for(sizes))]) if compressed else self.word_base
        flags = np.unpackbits(occupied.view(np.uint8), bitorder="little").astype(bool)
        span = 2 * self.tau
        at = np.repeat(self.word_base[:-1] * 64, span) + np.arange(span.sum()) - np.repeat(np.cumsum(span) - span, span)
        self.entries, self.entry_base = directory(flags[at], span, self.kappa)

    def find(self, bucket: np.ndarray) -> np.ndarray:
        """Row of each bucket number, or -1 for an empty bucket."""
        at = np.minimum(np.searchsorted(self.numbers, bucket), max(0, len(self.numbers) - 1))
        return np.where(self.numbers[at] == bucket, at, -1) if len(self.numbers) else np.full(len(bucket), -1)

    def ranks(self, row: np.ndarray, slot: np.ndarray, bits: int | str) -> np.ndarray:
        return rank(self.occupied, self.word_base[row], self.entries, self.entry_base[row], slot, self.kappa[row], bits)

    def label(self, row: np.ndarray, slot: np.ndarray, bits: int | str) -> np.ndarray:
        """A compressed label is stored for occupied slots only; the others are zero."""
        if not self.compressed:
            return bit_at(self.labels, self.word_base[row] * 64 + slot)
        held = bit_at(self.occupied, self.word_base[row] * 64 + slot)
        out = np.zeros(len(row), bool)
        if held.any():
            r = row[held]
            out[held] = bit_at(self.labels, self.label_base[r] * 64 + self.ranks(r, slot[held], bits))
        return out

    def evaluate(self, bucket: np.ndarray, sums: tuple[Sums, Sums], bits: int | str = "native") -> tuple[np.ndarray, np.ndarray]:
        """Global slot and id of each key; -1 where the bucket is empty. Others than members get any slot."""
        row = self.find(bucket)
        slot_out, id_out = np.full(len(bucket), -1), np.full(len(bucket), -1)
        some = np.flatnonzero(row >= 0)
        if not len(some):
            return slot_out, id_out
        row = row[some]
        tau = self.tau[row]
        v = [Sums(s.a[some], s.b[some]).values(self.seeds[row], tau.astype(np.uint64)) for s in sums]
        left, right = v[0], tau + v[1]
        slot = np.where(self.label(row, left, bits) ^ self.label(row, right, bits), right, left)
        slot_out[some] = self.slot_offsets[row] + slot
        id_out[some] = self.offsets[row] + np.minimum(self.ranks(row, slot, bits), self.sizes[row] - 1)
        return slot_out, id_out


def packed_bits(built: Buckets, eps: float, compressed: bool) -> tuple[np.ndarray, np.ndarray]:
    """Label words and occupied words of the buckets, the labels of occupied slots only if compressed."""
    span = 2 * side_sizes(built.sizes, eps)
    occupied = packed(built.occupied, span)
    labels = packed(built.labels[built.occupied], built.sizes) if compressed else packed(built.labels, span)
    return labels, occupied
