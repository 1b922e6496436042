"""Quality classifier: random-indexing vectors pooled per document, then a two-layer network.

Every token (a word, or the shape of a run) has a sparse random index vector that follows from its hash.
A token's context vector is the sum of the index vectors of its neighbours in the training sample, kept in a
table of hashed slots. A document is the mean of both vectors over its tokens, with its logarithmic length.
A numpy network with one hidden layer gives a logit, whose temperature is fitted on rows that the network
did not see; the class weights of the balanced sample are undone by the prior of all labelled rows.

The sample is bounded by `per_class` whole texts of either label. Defined cases: null and empty texts have
the vector zero and get the score that the network gives it; without labels of both kinds every score is the
prior (0.5 without labels); null doc_ids are scored and never held out; repeated rows are scored each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.llm.common import id_and_text, mix64, text_bytes
from densekeys.llm.training import Adam, held_out, labelled_sample, sigmoid, temperature
from densekeys.llm.words import LETTERS, blocks, hashed_shapes, hashed_words

SLOTS = 1 << 14
DIM = 48
NONZERO = 4
WINDOW = 2
HIDDEN = 32
PER_CLASS = 4000
THRESHOLD = 0.7
REPEATED = np.uint64(5)


def index_vectors() -> np.ndarray:
    """The sparse ternary vector of each slot."""
    slot = np.arange(SLOTS, dtype=np.uint64)
    out = np.zeros((SLOTS, DIM), np.float32)
    for k in range(NONZERO):
        h = mix64(slot + np.uint64((k + 1) << 32))
        np.add.at(out, (np.arange(SLOTS), (h % np.uint64(DIM)).astype(int)), np.where(h >> np.uint64(63), 1, -1))
    return out


def token_streams(texts: list[bytes]) -> list[tuple[np.ndarray, np.ndarray]]:
    """Slots and bounds of the words, then of the shapes; the two share the table but not the hashes.

    A word that repeats one of the two before it is the one token REPEATED instead."""
    words, word_bounds = hashed_words(texts, LETTERS)
    again = np.zeros(len(words), bool)
    again[1:] |= words[1:] == words[:-1]
    again[2:] |= words[2:] == words[:-2]
    words[again] = REPEATED
    shapes, shape_bounds = hashed_shapes(texts)
    half = np.uint64(SLOTS // 2)
    return [((words % half).astype(np.int32), word_bounds), ((shapes % half + half).astype(np.int32), shape_bounds)]


def context_vectors(texts: list[bytes], index: np.ndarray) -> np.ndarray:
    table = np.zeros((SLOTS, DIM), np.float32)
    seen = np.zeros(SLOTS, np.float32)
    for a, b in blocks(texts):
        for ids, bounds in token_streams(texts[a:b]):
            doc = np.repeat(np.arange(b - a), np.diff(bounds))
            seen += np.bincount(ids, minlength=SLOTS)
            for d in range(1, WINDOW + 1):
                same = doc[d:] == doc[:-d]
                left, right = ids[:-d][same], ids[d:][same]
                pairs, counts = np.unique(np.concatenate([left.astype(np.int64) * SLOTS + right, right.astype(np.int64) * SLOTS + left]), return_counts=True)
                np.add.at(table, pairs // SLOTS, index[pairs % SLOTS] * counts[:, None].astype(np.float32))
    norm = np.linalg.norm(table, axis=1, keepdims=True)
    return table / np.maximum(norm, 1) * np.minimum(1, seen / 5)[:, None]


def pooled(texts: list[bytes], vectors: np.ndarray) -> np.ndarray:
    """For each text, of words and of shapes: the mean vector and the logarithm of their number."""
    width = vectors.shape[1]
    out = np.zeros((len(texts), 2 * (width + 1)), np.float32)
    for a, b in blocks(texts, 1 << 18):
        for k, (ids, bounds) in enumerate(token_streams(texts[a:b])):
            n = np.diff(bounds)
            some = np.flatnonzero(n)
            part = out[a:b, k * (width + 1) : (k + 1) * (width + 1)]
            if len(some):
                part[some, :width] = np.add.reduceat(vectors[ids], bounds[some], axis=0) / n[some, None]
            part[:, width] = np.log1p(n) / 10
    return out


class QualityModel:
    """Everything needed to score: a few MB, whatever the size of the corpus."""

    def __init__(self, vectors, params, centre, scale, heat, shift, prior):
        self.vectors, self.params, self.centre, self.scale, self.heat, self.shift, self.prior = vectors, params, centre, scale, heat, shift, prior

    def logits(self, x: np.ndarray) -> np.ndarray:
        p = self.params
        return (np.tanh((x - self.centre) / self.scale @ p["a"] + p["b"]) @ p["c"] + p["d"])[:, 0]

    def score(self, texts: list[bytes]) -> np.ndarray:
        if self.params is None:
            return np.full(len(texts), self.prior)
        return sigmoid(self.logits(pooled(texts, self.vectors)) / self.heat + self.shift).astype(np.float64)


def fit(texts: list[bytes], labels: np.ndarray, prior: float, epochs: int = 40) -> QualityModel:
    """Four fifths train the network, the rest its temperature; `prior` is the share of label 1 in all labelled rows."""
    index = index_vectors()
    if len(set(labels.tolist())) < 2:
        return QualityModel(None, None, None, None, 1.0, 0.0, prior)
    rest = np.arange(len(texts)) % 5 == 4
    vectors = np.concatenate([context_vectors([t for t, r in zip(texts, rest, strict=True) if not r], index), index], axis=1)
    x = pooled(texts, vectors)
    centre, scale = x[~rest].mean(axis=0), x[~rest].std(axis=0) + 1e-3
    rng = np.random.default_rng(7)
    width = x.shape[1]
    params = {"a": rng.normal(0, width**-0.5, (width, HIDDEN)).astype(np.float32), "b": np.zeros(HIDDEN, np.float32), "c": rng.normal(0, HIDDEN**-0.5, (HIDDEN, 1)).astype(np.float32), "d": np.zeros(1, np.float32)}
    model = QualityModel(vectors, params, centre, scale, 1.0, 0.0, prior)
    z, y = ((x - centre) / scale)[~rest], labels[~rest].astype(np.float32)
    weight = np.where(y == 1, 0.5 / max(y.mean(), 1e-6), 0.5 / max(1 - y.mean(), 1e-6)).astype(np.float32)
    adam = Adam(params, 0.003)
    for _ in range(epochs):
        order = rng.permutation(len(z))
        for k in range(0, len(z), 64):
            i = order[k : k + 64]
            hidden = np.tanh(z[i] @ params["a"] + params["b"])
            g = ((sigmoid((hidden @ params["c"] + params["d"])[:, 0]) - y[i]) * weight[i] / len(i))[:, None]
            back = g @ params["c"].T * (1 - hidden**2)
            adam.step({"a": z[i].T @ back + 1e-4 * params["a"], "b": back.sum(0), "c": hidden.T @ g + 1e-4 * params["c"], "d": g.sum(0)})
    y = labels[rest].astype(float)
    if 0 < y.sum() < len(y):
        model.heat = temperature(model.logits(x[rest]), y, np.where(y == 1, 0.5 / y.mean(), 0.5 / (1 - y.mean())))
    share = min(max(prior, 0.01), 0.99)
    model.shift = float(np.log(share / (1 - share)))
    return model


def score_documents(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, threshold: float = THRESHOLD, modulus: int = 4, remainder: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fit on the bounded sample and score every whole text."""
    known = labels.where(F.col("quality").isin(0, 1) & ~held_out(F.col("doc_id"), modulus, remainder)).agg(F.avg("quality")).first()[0]
    texts, marks = labelled_sample(docs, labels, "quality", modulus, remainder, per_class, id_col, text_col)
    model = docs.sparkSession.sparkContext.broadcast(fit(texts, marks, 0.5 if known is None else known))

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.value.score(text_bytes(batch.column(1))), pa.float64())], ["doc_id", "score"])

    scored = id_and_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", held_out(F.col("doc_id"), modulus, remainder).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
