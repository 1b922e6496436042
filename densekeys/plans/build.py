"""Construction of a function over a set of any size, as a table of super-buckets with packed buckets."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densekeys.functions import kernel
from densekeys.functions.kernel import Functions, side_sizes
from densekeys.plans.bucketing import choose_bits, prefix_sums
from densekeys.plans.fingerprints import as_words, distinct_fingerprints, fingerprint, super_bucket, word_count
from densekeys.plans.params import Params, family
from densekeys.shared import forgotten, written

VERSION = 1
BUILT = "super long, n long, n_slots long, buckets binary, sizes binary, seeds binary, tries binary, labels binary, occupied binary"
BUILT_NAMES = [x.split()[0] for x in BUILT.split(", ")]
ARTIFACT = BUILT + ", base long, slot_base long"


@dataclass
class Artifact:
    """A built function: its rows, one for each super-bucket, and what is needed to read them."""

    rows: DataFrame
    params: Params
    n: int
    n_slots: int
    b: int
    super_bits: int
    attempt: int
    restarts: int
    cols: list[str]

    @property
    def manifest(self) -> dict:
        return {"version": VERSION, "n": self.n, "n_slots": self.n_slots, "b": self.b, "super_bits": self.super_bits, "attempt": self.attempt, "restarts": self.restarts, "cols": self.cols, "params": asdict(self.params)}

    def buckets(self) -> DataFrame:
        """One row for each non-empty bucket: number, size, tau, seed, tries, offset, bits of the function."""
        p = self.params

        def run(batches):
            for batch in batches:
                out = []
                for row in batch.to_pylist():
                    number, size, seed, tries = (np.frombuffer(row[k], t) for k, t in (("buckets", np.int64), ("sizes", np.int64), ("seeds", np.uint64), ("tries", np.int64)))
                    tau = side_sizes(size, p.eps)
                    phf, mphf = bucket_bits(size, tau, p)
                    out.append((number, size, tau, seed.astype(np.int64), tries, row["base"] + np.cumsum(size) - size, phf, mphf))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([r[k] for r in out])) for k in range(8)], ["bucket", "size", "tau", "seed", "tries", "offset", "bits_phf", "bits_mphf"])

        return self.rows.mapInArrow(run, "bucket long, size long, tau long, seed long, tries long, offset long, bits_phf long, bits_mphf long")

    def write(self, path: str) -> None:
        """Rows as Parquet, and the manifest as one line of text beside them."""
        self.rows.write.parquet(f"{path}/rows")
        spark = self.rows.sparkSession
        spark.createDataFrame([(json.dumps(self.manifest),)], "value string").coalesce(1).write.text(f"{path}/manifest")

    @classmethod
    def read(cls, spark: SparkSession, path: str) -> Artifact:
        m = json.loads(spark.read.text(f"{path}/manifest").first()[0])
        if m["version"] != VERSION:
            raise ValueError(f"artifact version {m['version']}")
        rows = spark.read.schema(ARTIFACT).parquet(f"{path}/rows")
        return cls(rows, Params(**m["params"]), m["n"], m["n_slots"], m["b"], m["super_bits"], m["attempt"], m["restarts"], m["cols"])


def bucket_bits(size: np.ndarray, tau: np.ndarray, p: Params) -> tuple[np.ndarray, np.ndarray]:
    """Bits of each bucket's function as the collision-free and as the minimal one, headers included."""
    header = 32 + 32 * p.seeds_per_bucket
    labels = size if p.layout == "compressed" else 2 * tau
    return 2 * tau + header, labels + 2 * tau + 8 * -(-2 * tau // p.steps(tau)) + header


def build_super(words: np.ndarray, b: int, params: Params, attempt: int, super_bucket: int) -> dict:
    """Packed buckets of the fingerprints of one super-bucket; the same for any order of rows and any try of the task."""
    order = np.lexsort(tuple(words[:, k] for k in range(words.shape[1] - 1, -1, -1)))
    words = words[order]
    bucket = (words[:, 0].astype(np.int64) << 32 | words[:, 1]) >> (64 - b) if b else np.zeros(len(words), np.int64)
    if b:  # the address is unsigned
        bucket &= (1 << b) - 1
    numbers, sizes = np.unique(bucket, return_counts=True)
    sums = family(params, attempt).values.sums(words)
    built = kernel.build(numbers, sizes.astype(np.int64), sums, params.eps, params.master_seed + attempt, params.max_tries)
    labels, occupied = kernel.packed_bits(built, params.eps, params.layout == "compressed")
    return {
        "super": super_bucket,
        "n": int(sizes.sum()),
        "n_slots": int(2 * side_sizes(sizes, params.eps).sum()),
        "buckets": numbers.astype(np.int64).tobytes(),
        "sizes": sizes.astype(np.int64).tobytes(),
        "seeds": built.seeds.tobytes(),
        "tries": built.tries.tobytes(),
        "labels": labels.tobytes(),
        "occupied": occupied.tobytes(),
    }


def group_builder(params: Params, attempt: int, b: int):
    words = word_count(params)

    def build_group(keys, table):
        w = as_words(table.column("hi").to_numpy(), table.column("lo").to_numpy(), words)
        try:
            row = build_super(w, b, params, attempt, int(keys[0].as_py()))
        except kernel.NoForest:  # told by a size that no super-bucket has
            row = dict.fromkeys(BUILT_NAMES, b"") | {"super": int(keys[0].as_py()), "n": -1, "n_slots": 0}
        return pa.table({k: pa.array([v], pa.binary() if isinstance(v, bytes) else pa.int64()) for k, v in row.items()})

    return build_group


def build_two_level(df: DataFrame, cols: str | list[str], params: Params = Params(), b_method: str = "empirical") -> Artifact:
    """The scalable construction: distinct fingerprints, super-buckets of them, all buckets of a super-bucket at once.

    The keys are read once for each attempt; all counts are taken from the written fingerprints. Driver state is a handful of counts. Two keys with one fingerprint, or a bucket without a forest, start the
    next attempt, which draws new tables, as the attempt is part of every seed."""
    cols = [cols] if isinstance(cols, str) else list(cols)
    rows = df.select(*(F.col(f"`{c}`") for c in cols))
    for attempt in range(params.max_restarts + 1):
        prints = written(distinct_fingerprints(fingerprint(rows, cols, params, attempt)), "fingerprints")
        totals = prints.agg(F.count(F.lit(1)).alias("n"), F.count_if("collided").alias("collided")).first()
        if totals["collided"]:
            forgotten(prints)
            continue
        n = totals["n"]
        super_bits = max(0, math.ceil(math.log2(max(1, n) / params.super_keys)))
        b = choose_bits(prints, n, params.ell, b_method, super_bits) if n > params.ell or super_bits else 0
        dealt = prints.select(super_bucket(super_bits).alias("super"), "hi", "lo")
        built = written(dealt.groupBy("super").applyInArrow(group_builder(params, attempt, b), BUILT), "buckets")
        slots = built.agg(F.sum("n_slots").alias("slots"), F.min("n").alias("least")).first()
        forgotten(prints)
        if (slots["least"] or 0) < 0:
            forgotten(built)
            continue
        placed = prefix_sums(prefix_sums(built, "super", "n", "base"), "super", "n_slots", "slot_base")
        # lookups read what is written, not the two prefix sums again
        rows_out = written(placed.select(*[x.split()[0] for x in ARTIFACT.split(", ")]), "artifact")
        forgotten(built)
        return Artifact(rows_out, params, n, slots["slots"] or 0, b, super_bits, attempt, attempt, cols)
    raise RuntimeError(f"no function found in {params.max_restarts + 1} attempts")


def build_core(df: DataFrame, cols: str | list[str], params: Params = Params(hash="xx128", kappa=256), max_keys: int = 20_000_000) -> Artifact:
    """The whole set as one graph, in memory of one task: the heuristic internal construction, for sets of bounded size."""
    n = df.count()
    if n > max_keys:
        raise ValueError(f"{n} rows exceed the {max_keys} that one task may hold; use build_two_level")
    return build_two_level(df, cols, replace(params, ell=max(n, 1), super_keys=max(n, 1)))


def functions_of(rows: list[dict], params: Params) -> Functions:
    """Evaluator of some super-buckets, given in order."""
    rows = sorted(rows, key=lambda r: r["super"])
    numbers, sizes, seeds = (np.concatenate([np.frombuffer(r[k], t) for r in rows]) if rows else np.zeros(0, t) for k, t in (("buckets", np.int64), ("sizes", np.int64), ("seeds", np.uint64)))
    labels, occupied = (np.concatenate([np.frombuffer(r[k], "<u8") for r in rows]) if rows else np.zeros(0, np.uint64) for k in ("labels", "occupied"))
    offsets, slots = [], []
    for r in rows:
        size = np.frombuffer(r["sizes"], np.int64)
        span = 2 * side_sizes(size, params.eps)
        offsets.append(r["base"] + np.cumsum(size) - size)
        slots.append(r["slot_base"] + np.cumsum(span) - span)
    none = [np.zeros(0, np.int64)]
    return Functions(numbers, sizes, seeds, np.concatenate(offsets or none), labels, occupied, params.eps, params.steps(side_sizes(sizes, params.eps)), params.layout == "compressed", np.concatenate(slots or none))
