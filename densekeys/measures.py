"""Cost and accuracy measures: closed forms on the driver, statistics as DataFrame aggregates, and timers."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from statistics import mean, stdev

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.plans.build import Artifact
from densekeys.plans.evaluate import lookup

#: Fixed: 0.975 quantiles of Student's t for 1 to 10 degrees of freedom, then for many.
T_975 = (12.706, 4.303, 3.182, 2.776, 2.571, 2.447, 2.365, 2.306, 2.262, 2.228)


def t_quantile(degrees: int) -> float:
    return T_975[degrees - 1] if degrees <= len(T_975) else 1.96 + 2.4 / degrees


def ci95(sd: float, trials: int) -> float:
    """Half-width of the 95 % confidence interval of a mean."""
    return t_quantile(trials - 1) * sd / math.sqrt(trials)


def required_trials(sd: float, average: float, relative_error: float) -> int:
    return max(1, math.ceil((1.96 * sd / (relative_error * average)) ** 2))


def acyclic_probability(eps: float, model: str = "printed") -> float:
    """Chance that a random graph is a forest: of the ordinary random graph (printed), or the bipartite one that is built."""
    c = 2 * (1 + eps)
    return math.exp(1 / c) * math.sqrt((c - 2) / c) if model == "printed" else math.sqrt(1 - (2 / c) ** 2)


def expected_tries(eps: float, model: str = "printed") -> float:
    return 1 / acyclic_probability(eps, model)


def collision_bound(n: float, b: int, chunks: int = 6, r: int = 15) -> float:
    """Bound on the chance that two of n keys share a fingerprint of b + chunks r bits."""
    return min(1.0, n * (n - 1) / 2 / 2.0 ** (b + chunks * r))


def independence_bound(ell: int, r: int, chunks: int) -> float:
    """Bound on the chance that a key of a bucket of ell finds no chunk of its own."""
    return (ell / 2.0**r) ** chunks


def space_bounds(n: int) -> dict[str, float]:
    """Bits that any minimal function needs, and that fully random functions would."""
    return {"least_bits": n / math.log(2), "random_function_bits": n * math.log2(n) if n > 1 else 0.0}


def fixed_bytes(length_bytes: int = 65, chunks: int = 6, r: int = 15, gamma: int = 128) -> int:
    """Shared tables of the proved family: chunk tables, byte tables, and the bit matrix itself."""
    return 2 * chunks * 2**r * 4 + length_bytes * 256 * gamma // 8 + gamma * 8 * length_bytes // 8


def fixed_bits_per_key(n: int) -> float:
    return 8 * fixed_bytes() / n


def bucket_bits(size: int, eps: float = 0.045, kappa: int = 128, seeds: int = 1, layout: str = "compressed") -> tuple[int, int]:
    """Bits of one bucket as collision-free and as minimal function."""
    tau = max(1, math.ceil((1 + eps) * size - 1e-9))
    header = 32 + 32 * seeds
    return 2 * tau + header, (size if layout == "compressed" else 2 * tau) + 2 * tau + 8 * math.ceil(2 * tau / kappa) + header


def phf_bits_model(n: int, b: int, eps: float = 0.045) -> float:
    """Bits a key of a collision-free function: two sides and a 64-bit header for each of 2**b buckets."""
    return 2 * (1 + eps) + 64 * 2**b / n


def offset_share(n: int, b: int) -> float:
    return 2**b * math.ceil(math.log2(n)) / n


def runs(total_mb: float, memory_mb: float, counters_mb: float = 0) -> int:
    """Blocks that a partitioning pass writes; `counters_mb` of the memory hold bucket counters."""
    return math.ceil(total_mb / (memory_mb - counters_mb))


def io_model(memory_mb: float, files: int, bytes_on_disk: float) -> tuple[float, float]:
    """Buffer of each run in KB, and seeks at worst when they are merged."""
    buffer = memory_mb * 1024 / files
    return buffer, bytes_on_disk / 1024 / buffer


def eval_ops(length_bytes: int, chunks: int = 6, kappa: int = 128, popcount_bits: int = 16) -> dict[str, int]:
    return {"table_xors": length_bytes, "table_reads": 4 * chunks, "label_bits": 2, "popcounts": math.ceil(kappa / popcount_bits)}


def construction_memory_words(files: int, ell: int = 256) -> int:
    """Words the merge needs: heap, positions and buffers of each run, and one bucket."""
    return 3 * files + 4 * ell


def bits_per_key(artifact: Artifact) -> DataFrame:
    """Structure bits a key, fixed tables apart."""
    return artifact.buckets().agg(F.sum("size").alias("n"), (F.sum("bits_phf") / F.sum("size")).alias("phf_bits"), (F.sum("bits_mphf") / F.sum("size")).alias("mphf_bits"))


def tries_stats(artifact: Artifact) -> DataFrame:
    return artifact.buckets().agg(F.count(F.lit(1)).alias("buckets"), F.avg("tries").alias("mean_tries"), F.var_samp("tries").alias("var_tries"), F.max("tries").alias("max_tries"))


def timed(run: Callable[[], object], trials: int) -> dict[str, float]:
    """Mean, deviation and confidence of wall seconds."""
    took = []
    for _ in range(trials):
        began = time.perf_counter()
        run()
        took.append(time.perf_counter() - began)
    sd = stdev(took) if trials > 1 else 0.0
    return {"mean": mean(took), "sd": sd, "ci95": ci95(sd, trials) if trials > 1 else 0.0}


def measure_build(build: Callable[[], Artifact], trials: int = 3) -> dict[str, float]:
    return timed(build, trials)


def measure_lookup(df: DataFrame, artifact: Artifact, trials: int = 3) -> dict[str, float]:
    return timed(lambda: lookup(df, artifact).write.format("noop").mode("overwrite").save(), trials)


def regression(points: DataFrame, y: str, x: str) -> DataFrame:
    """Least squares line of times over sizes."""
    return points.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def is_permutation(ids: np.ndarray, n: int) -> bool:
    return len(ids) == n and bool((np.sort(ids) == np.arange(n)).all())


def artifact_mb(n: int, b: int, eps: float = 0.045) -> float:
    """MB of a collision-free function of n keys."""
    return phf_bits_model(n, b, eps) * n / 8 / 2**20


def disk_bytes(n: int, key_bytes: float, fingerprint_bytes: int = 16) -> float:
    """Bytes read and written by a construction that merges once: keys once, fingerprints out and in."""
    return n * (key_bytes + 2 * fingerprint_bytes)


def build_split(fingerprints: Callable[[], object], build: Callable[[], object]) -> dict[str, float]:
    """Seconds of partitioning (written fingerprints) and of searching, and the share of the first."""
    first, second = timed(fingerprints, 1)["mean"], timed(build, 1)["mean"]
    return {"partition": first, "search": second, "share": first / (first + second)}
