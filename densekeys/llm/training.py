"""Bounded samples of labelled rows, optimisation and calibration shared by the two classifiers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.llm.common import id_and_text


#: Bytes of the longest text that a sample takes.
LONGEST = 1 << 16


def held_out(id_column, modulus: int, remainder: int):
    """Whether crc32 of the id as text leaves `remainder`; a null id is never held out."""
    return F.coalesce(F.crc32(id_column.cast("string").cast("binary")) % modulus == remainder, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, modulus: int, remainder: int, per_class: int, id_col: str = "doc_id", text_col: str = "text", longest: int = LONGEST) -> tuple[list[bytes], np.ndarray]:
    """At most `per_class` whole texts of either label among the rows that are not held out, in a pseudo-random order that depends on ids alone.

    So that the driver's share is bounded, texts beyond `longest` bytes aren't learnt from, and of rows that repeat an id one is."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("label")).where(
        F.col("label").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), modulus, remainder)
    )
    order = F.xxhash64(F.col("doc_id"), F.lit(label))
    picked = known.where("label = 0").orderBy(order, "doc_id").limit(per_class).unionByName(known.where("label = 1").orderBy(order, "doc_id").limit(per_class))
    ids = {(r["doc_id"], r["label"]) for r in picked.collect()}
    if not ids:
        return [], np.zeros(0, np.int8)
    wanted = docs.sparkSession.createDataFrame(sorted(ids), "doc_id long, label int")
    short = id_and_text(docs, id_col, text_col).where(F.coalesce(F.octet_length("text"), F.lit(0)) <= longest)
    rows = short.join(F.broadcast(wanted), "doc_id").groupBy("doc_id", "label").agg(F.min("text").alias("text")).collect()
    rows.sort(key=lambda r: (mixed(r["doc_id"]), r["label"], r["text"] or ""))
    return [(r["text"] or "").encode("utf-8", "surrogatepass") for r in rows], np.array([r["label"] for r in rows], np.int8)


def mixed(n: int) -> int:
    return (n * 0x9E3779B97F4A7C15 + 0x7F4A7C15) % (1 << 64) >> 11


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


class Adam:
    def __init__(self, params: dict[str, np.ndarray], rate: float):
        self.params, self.rate, self.t = params, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] += 0.1 * (g - self.m[k])
            self.v[k] += 0.001 * (g * g - self.v[k])
            self.params[k] -= self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)


def temperature(logits: np.ndarray, labels: np.ndarray, weights: np.ndarray) -> float:
    """The scale of the logits with the least weighted log loss, by golden-section search over its logarithm."""
    if not len(logits):
        return 1.0

    def loss(log_t: float) -> float:
        z = logits / np.exp(log_t)
        return float(np.mean(weights * (np.logaddexp(0, z) - labels * z)))

    a, b, g = -1.4, 2.5, (5**0.5 - 1) / 2
    for _ in range(40):
        c, d = b - g * (b - a), a + g * (b - a)
        a, b = (a, d) if loss(c) < loss(d) else (c, b)
    return float(np.exp((a + b) / 2))
