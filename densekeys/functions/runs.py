"""How a block of fingerprints becomes sorted runs: by radix, by comparisons, or by replacement selection."""

from __future__ import annotations

import heapq

import numpy as np


def radix_runs(values: np.ndarray, memory: int) -> list[np.ndarray]:
    """Blocks of `memory` values, each sorted by 16-bit digits, least significant first."""
    out = []
    for a in range(0, len(values), memory):
        block = values[a : a + memory].astype(np.uint64)
        for shift in range(0, 64, 16):
            digit = (block >> np.uint64(shift)).astype(np.uint16)
            block = block[np.argsort(digit, kind="stable")]
        out.append(block)
    return out


def comparison_runs(values: np.ndarray, memory: int) -> list[np.ndarray]:
    return [np.sort(values[a : a + memory].astype(np.uint64), kind="heapsort") for a in range(0, len(values), memory)]


def replacement_runs(values: np.ndarray, memory: int) -> list[np.ndarray]:
    """The smallest value that can still join the run goes out, and the next of the input takes its place; runs of random input are about twice as long."""
    source = iter(values.astype(np.uint64).tolist())
    heap = [(0, v) for _, v in zip(range(memory), source, strict=False)]
    heapq.heapify(heap)
    runs: list[list[int]] = []
    while heap:
        run, value = heap[0]
        if run == len(runs):
            runs.append([])
        runs[run].append(value)
        new = next(source, None)
        if new is None:
            heapq.heappop(heap)
        else:
            heapq.heapreplace(heap, (run + (new < value), new))
    return [np.array(r, np.uint64) for r in runs]


RUNS = {"radix": radix_runs, "comparison": comparison_runs, "replacement": replacement_runs}
