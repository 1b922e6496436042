"""The shell of the two-level construction around any way to number the keys of one bucket.

Buckets are small, so the way may favour space, time to build or time to evaluate; KERNELS names them. `core` is the one
that artifacts are built with; the others are the in-memory methods that it is compared with."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.functions import kernel
from densekeys.functions.hashing import splitmix
from densekeys.operators.baselines import METHODS
from densekeys.plans.bucketing import address, bucket_sizes, choose_bits, prefix_sums
from densekeys.plans.build import build_super, functions_of
from densekeys.plans.evaluate import _answers
from densekeys.plans.fingerprints import as_words, distinct_fingerprints, fingerprint, word_count
from densekeys.plans.params import Params
from densekeys.shared import written

Kernel = Callable[[np.ndarray, np.ndarray, np.ndarray, int, Params], tuple[np.ndarray, int]]


def _core(hi: np.ndarray, lo: np.ndarray, bucket: np.ndarray, b: int, params: Params) -> tuple[np.ndarray, int]:
    words = as_words(hi, lo, word_count(params))
    row = build_super(words, b, params, 0, 0) | {"base": 0, "slot_base": 0}
    functions = functions_of([row], params)
    _, ids = _answers(functions, words, b, params, 0)
    offset = functions.offsets[functions.find(bucket)]
    return ids - offset, int(sum(kernel.words_for(x).sum() * 64 for x in (functions.sizes, 2 * functions.tau)))


def _method(name: str) -> Kernel:
    def number(hi, lo, bucket, b, params):
        prints = splitmix(hi.view(np.uint64) ^ splitmix(lo.view(np.uint64)))
        ids, bits = np.empty(len(prints), np.int64), 0
        order = np.argsort(bucket, kind="stable")
        for at in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1):
            if len(at):
                built = METHODS[name].build(prints[at])
                ids[at] = built.evaluate(prints[at])
                bits += built.bits
        return ids, bits

    return number


KERNELS: dict[str, Kernel] = {"core": _core} | {name: _method(name) for name in METHODS}


def numbered(df: DataFrame, cols: str | list[str], kernel_name: str = "core", params: Params = Params(hash="xx128")) -> DataFrame:
    """hi, lo, bucket, id below n of every distinct key, and `bits`, what the key's group of buckets takes over all its keys."""
    cols = [cols] if isinstance(cols, str) else list(cols)
    number = KERNELS[kernel_name]
    prints = written(distinct_fingerprints(fingerprint(df.select(*(F.col(f"`{c}`") for c in cols)), cols, params, 0)), "fingerprints")
    if prints.where("collided").limit(1).count():
        raise RuntimeError("two keys share a fingerprint; choose another master seed")
    n = prints.count()
    b = choose_bits(prints, n, params.ell) if n > params.ell else 0
    group_bits = max(0, b - 6)
    offsets = prefix_sums(bucket_sizes(prints, b), "bucket", "size", "offset").select("bucket", "offset")

    def group(keys, table):
        hi, lo, bucket = (table.column(c).to_numpy() for c in ("hi", "lo", "bucket"))
        # in an order of their own, so that a retried task gives the same
        order = np.lexsort((lo, hi))
        hi, lo, bucket = hi[order], lo[order], bucket[order]
        ids, bits = number(hi, lo, bucket, b, params)
        return pa.table({"hi": hi, "lo": lo, "bucket": bucket, "place": ids, "bits": np.full(len(hi), bits / max(1, len(hi)))})

    dealt = prints.select("hi", "lo", address(F.col("hi"), b).alias("bucket"), address(F.col("hi"), group_bits).alias("group"))
    inside = dealt.groupBy("group").applyInArrow(group, "hi long, lo long, bucket long, place long, bits double")
    return inside.join(offsets, "bucket").select("hi", "lo", "bucket", (F.col("offset") + F.col("place")).cast("long").alias("id"), "bits")
