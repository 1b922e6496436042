"""Toxicity: a convolutional text classifier in numpy with thresholds calibrated by language.

Words, and their beginnings of four and six bytes, are hashed to rows of an embedding table; a word is the sum
of its rows. Filters of width one, two and three slide over the word
embeddings. Responses are max-pooled over stretches of STRETCH words; for each filter the largest stretch and the
mean of all stretches, rectified, feed a logistic output, so that it sees both what occurs and how often.
For scoring, each filter position is multiplied into the table once, so that a response is a sum of table
rows. The language is guessed from the text alone, by its most frequent function words; for each, a threshold
of the logit is calibrated by cross-fitting (each row's logit from a model that did not see its fold), and the score
is shifted so that 0.5 is it.

The sample is bounded by `per_class` whole texts of either label. Defined cases: null and empty texts have
one padding word and get its score; without labels of both kinds every score is 0; null doc_ids are scored
and never held out; repeated rows are scored each; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from densekeys.llm.common import give_back, id_and_text, mix64, text_bytes
from densekeys.llm.training import Adam, held_out, labelled_sample, sigmoid
from densekeys.llm.words import LETTERS, LOWERED, blocks, hashes_between, joined, prefix_sums, spans

SLOTS = 1 << 16
BEGINNINGS = (4, 6)
PARTS = 1 + len(BEGINNINGS)
DIM = 12
WIDTHS = (1, 2, 3)
FILTERS = 12
STRETCH = 32
PER_CLASS = 2000
FEW_TO_CALIBRATE = 30
FOLDS = 3
LANGUAGES = ("en", "de", "fr", "es")
#: Fixed: frequent function words by which a language is guessed.
FUNCTION_WORDS = (
    "the of and to in that is was for on with as are this be have not by they you",
    "der die und das ist nicht ein eine zu den mit von sich auf für im dem auch es wird",
    "le la les et des est une un du que dans pour pas qui sur au avec ce il ne",
    "el los las y que una por con para del se es como más pero su al lo fue sin",
)


def word_ids(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Slots of each word and its beginnings (one row a word), and the bounds of the texts.

    Each text is padded by at least max(WIDTHS) - 1 rows of slot 0 to whole stretches."""
    data, text_bounds = joined(texts)
    data = LOWERED[data]
    starts, ends = spans(LETTERS[data])
    sums = prefix_sums(data)
    bounds = np.searchsorted(starts, text_bounds)
    n = np.diff(bounds)
    out_bounds = np.concatenate([[0], np.cumsum(-(-(n + max(WIDTHS) - 1) // STRETCH) * STRETCH)])
    ids = np.zeros((out_bounds[-1], PARTS), np.int32)
    rows = np.arange(len(starts)) + np.repeat(out_bounds[:-1] - bounds[:-1], n)
    for k, most in enumerate((None, *BEGINNINGS)):
        h = hashes_between(sums, starts, ends if most is None else np.minimum(ends, starts + most))
        h += np.uint64(k * 0x51ED2701)
        ids[rows, k] = (mix64(h) % np.uint64(SLOTS - 1)).astype(np.int32) + 1
    return ids, out_bounds


def ahead(bounds: np.ndarray, k: int) -> np.ndarray:
    """For each row of the texts that of the word k places on, and one row more than there are where the text has ended: no window reaches into the next text."""
    out = np.arange(bounds[-1]) + k
    for j in range(k):
        out[bounds[1:] - 1 - j] = bounds[-1]
    return out


def language_table() -> np.ndarray:
    """For each slot, one more than the language whose function word it holds; words of two languages count for neither."""
    table, owners = np.zeros(SLOTS, np.int8), {}
    for k, words in enumerate(FUNCTION_WORDS):
        for slot in word_ids([w.encode() for w in words.split()])[0][:, 0]:
            if slot:
                owners.setdefault(int(slot), set()).add(k)
    for slot, of in owners.items():
        if len(of) == 1:
            table[slot] = of.pop() + 1
    return table


def guessed_languages(ids: np.ndarray, bounds: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Index into LANGUAGES, or their number for none."""
    n = len(bounds) - 1
    doc = np.repeat(np.arange(n), np.diff(bounds))
    hits = np.bincount(doc * (len(LANGUAGES) + 1) + table[ids[:, 0]], minlength=n * (len(LANGUAGES) + 1)).reshape(n, -1)[:, 1:]
    return np.where(hits.max(axis=1) > 0, hits.argmax(axis=1), len(LANGUAGES))


class ToxicityModel:
    """The embeddings and filters travel; their products, which are as many times larger as there are filter positions, are made where texts are scored."""

    def __init__(self, embeddings: np.ndarray, filters: list[np.ndarray], bias: np.ndarray, out: np.ndarray, offset: float, thresholds: np.ndarray):
        self.embeddings, self.filters, self.bias, self.out, self.offset, self.thresholds = embeddings, filters, bias, out, offset, thresholds
        self._made: tuple[list[np.ndarray], np.ndarray] | None = None

    def __getstate__(self) -> dict:
        return self.__dict__ | {"_made": None}

    def _tables(self) -> tuple[list[np.ndarray], np.ndarray]:
        if self._made is None:
            tables = [np.ascontiguousarray(self.embeddings @ f[j * DIM : (j + 1) * DIM]) for f in self.filters for j in range(len(f) // DIM)]
            self._made = tables, language_table()
        return self._made

    @property
    def tables(self) -> list[np.ndarray]:
        """What a word's slot adds to the responses at each position of each filter."""
        return self._tables()[0]

    def logits(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        z, lang = np.zeros(len(texts)), np.zeros(len(texts), int)
        tables, languages = self._tables()
        for a, b in blocks(texts, 1 << 18):
            ids, bounds = word_ids(texts[a:b])
            padded = np.concatenate([ids, np.zeros((1, PARTS), np.int32)])
            later = [padded[ahead(bounds, k)] for k in range(max(WIDTHS))]
            stretch, peaks, t = bounds // STRETCH, [], 0
            for w in WIDTHS:
                response = np.zeros((len(ids), FILTERS), np.float32)
                for k in range(w):
                    for part in range(PARTS):
                        response += tables[t + k][later[k][:, part]]
                t += w
                peaks.append(response.reshape(-1, STRETCH, FILTERS).max(axis=1))
            peak = np.maximum(np.concatenate(peaks, axis=1) + self.bias, 0)
            seen = np.concatenate([np.maximum.reduceat(peak, stretch[:-1], axis=0), np.add.reduceat(peak, stretch[:-1], axis=0) / np.diff(stretch)[:, None]], axis=1)
            z[a:b] = seen @ self.out + self.offset
            lang[a:b] = guessed_languages(ids, bounds, languages)
        return z, lang

    def score(self, texts: list[bytes]) -> np.ndarray:
        z, lang = self.logits(texts)
        return sigmoid(z - self.thresholds[lang]).astype(np.float64)


def trained(docs: list[np.ndarray], labels: np.ndarray, train: np.ndarray, epochs: int, steps: int) -> ToxicityModel:
    """The network after training on the documents (rows of word_ids) at `train`, with thresholds of zero."""
    rng = np.random.default_rng(3)
    total = FILTERS * len(WIDTHS)
    params = {"e": rng.normal(0, 0.3, (SLOTS, DIM)).astype(np.float32), "bias": np.zeros(total, np.float32), "out": rng.normal(0, 0.3, 2 * total).astype(np.float32), "offset": np.zeros(1, np.float32)}
    params |= {f"w{w}": rng.normal(0, (w * DIM) ** -0.5, (w * DIM, FILTERS)).astype(np.float32) for w in WIDTHS}
    dense = Adam({k: v for k, v in params.items() if k != "e"}, 0.01)
    squares = np.full(SLOTS, 1e-3, np.float32)
    y = labels.astype(np.float32)
    weight = np.where(y == 1, 0.5 / y[train].mean(), 0.5 / (1 - y[train].mean())).astype(np.float32)
    params["e"][0] = 0
    for _ in range(max(epochs, -(-32 * steps // len(train)))):
        turn = train[rng.permutation(len(train))]
        for k in range(0, len(turn), 32):
            batch = turn[k : k + 32]
            ids = np.concatenate([docs[i] for i in batch])
            bounds = np.concatenate([[0], np.cumsum([len(docs[i]) for i in batch])])
            padded = np.concatenate([ids, np.zeros((1, PARTS), np.int32)])
            e = params["e"][padded].sum(axis=1)
            later = np.stack([ahead(bounds, j) for j in range(max(WIDTHS))], axis=1)
            stretch = bounds // STRETCH
            count = np.diff(stretch)
            peaks, where = [], []
            for w in WIDTHS:
                windows = e[later[:, :w]].reshape(len(ids), w * DIM)
                response = (windows @ params[f"w{w}"]).reshape(-1, STRETCH, FILTERS)
                at = response.argmax(axis=1)
                peaks.append(np.take_along_axis(response, at[:, None], axis=1)[:, 0])
                where.append(at + np.arange(len(at))[:, None] * STRETCH)
            pre = np.concatenate(peaks, axis=1) + params["bias"]
            act = np.maximum(pre, 0)
            top = np.maximum.reduceat(act, stretch[:-1], axis=0)
            seen = np.concatenate([top, np.add.reduceat(act, stretch[:-1], axis=0) / count[:, None]], axis=1)
            error = sigmoid(seen @ params["out"] + params["offset"][0]) - y[batch]
            g = np.where(np.abs(error) < 0.02, 0, error) * weight[batch] / len(batch)
            to_top, to_mean = np.outer(g, params["out"][:total]), np.outer(g, params["out"][total:]) / count[:, None]
            back = (np.repeat(to_top, count, axis=0) * (act == np.repeat(top, count, axis=0)) + np.repeat(to_mean, count, axis=0)) * (pre > 0)
            grads = {"out": seen.T @ g + 1e-4 * params["out"], "offset": np.array([g.sum()], np.float32), "bias": back.sum(0)}
            slots, moves = [], []
            for n, w in enumerate(WIDTHS):
                hit, filt = np.nonzero(back[:, n * FILTERS : (n + 1) * FILTERS])
                d = back[hit, n * FILTERS + filt]
                rows = later[where[n][hit, filt], :w]
                window = e[rows].reshape(len(d), w * DIM)
                grads[f"w{w}"] = np.stack([(window[filt == f] * d[filt == f, None]).sum(axis=0) for f in range(FILTERS)], axis=1) + 1e-4 * params[f"w{w}"]
                slots.append(padded[rows].reshape(-1))
                moves.append(np.repeat((params[f"w{w}"].T[filt] * d[:, None]).reshape(-1, DIM), PARTS, axis=0))
            slots, moves = np.concatenate(slots), np.concatenate(moves)
            order = np.argsort(slots, kind="stable")
            slots = slots[order]
            first = np.flatnonzero(np.diff(slots, prepend=-1))
            slot, move = slots[first], np.add.reduceat(moves[order], first, axis=0) if len(first) else moves
            dense.step(grads)
            squares[slot] += (move**2).mean(axis=1)
            params["e"][slot] -= 0.1 * move / np.sqrt(squares[slot])[:, None]
            params["e"][0] = 0
    return ToxicityModel(params["e"], [params[f"w{w}"] for w in WIDTHS], params["bias"], params["out"], float(params["offset"][0]), np.zeros(len(LANGUAGES) + 1))


def folds_of(labels: np.ndarray, folds: int = FOLDS) -> np.ndarray:
    """A fold for each row; rows of either label are dealt out in turn, so that no fold has more than one above its share."""
    fold = np.zeros(len(labels), int)
    for label in (0, 1):
        fold[labels == label] = np.arange((labels == label).sum()) % folds
    return fold


def fit(texts: list[bytes], labels: np.ndarray, epochs: int = 6, steps: int = 400, each=map) -> ToxicityModel | None:
    """A model of all rows, calibrated at every size by the logits that models without a row's fold give to the row.

    None without labels of both kinds. Small samples get more epochs, for at least `steps` steps. `each` maps a
    function over the trainings, which are independent of each other."""
    if len(set(labels.tolist())) < 2:
        return None
    fold, sizes, packed = folds_of(labels), [len(t) for t in texts], zstandard.compress(b"".join(texts), 3)

    def one(k: int):
        """The model of all rows for k = FOLDS, else rows of fold k with logits and languages: none if the others lack a label."""
        data, ends = zstandard.decompress(packed), np.cumsum(sizes).tolist()
        texts = [data[b - n : b] for b, n in zip(ends, sizes, strict=True)]
        docs = []
        for a, b in blocks(texts):
            ids, bounds = word_ids(texts[a:b])
            docs += [ids[x:y] for x, y in zip(bounds, bounds[1:], strict=False)]
        own, train = np.flatnonzero(fold == k), np.flatnonzero(fold != k)
        if len(own) == 0 and k < FOLDS or len(set(labels[train].tolist())) < 2:
            return own[:0], np.zeros(0), np.zeros(0, int)
        model = trained(docs, labels, train, epochs, steps)
        return (own, *model.logits([texts[i] for i in own])) if k < FOLDS else model

    *unseen, model = each(one, range(FOLDS + 1))
    rows, z, lang = (np.concatenate(x) for x in zip(*unseen, strict=True))
    # the sample is balanced, the corpus is not: thresholds weigh a clean document by the corpus's odds
    model.thresholds = calibrated(z, labels[rows], lang)
    return model


def calibrated(z: np.ndarray, y: np.ndarray, lang: np.ndarray, least: int = FEW_TO_CALIBRATE, clean_weight: float = 2.0) -> np.ndarray:
    """For each language the threshold with the fewest errors, clean documents weighted; languages with few rows take that of all."""

    def best(z: np.ndarray, y: np.ndarray) -> float:
        order = np.argsort(-z)
        z, y = z[order], y[order]
        errors = (y == 1).sum() - np.concatenate([[0], np.cumsum(y == 1)]) + clean_weight * np.concatenate([[0], np.cumsum(y == 0)])
        low = np.flatnonzero(errors == errors.min())
        k = int(low[len(low) // 2])
        edges = np.concatenate([[z[0] + 2], z, [z[-1] - 2]]) if len(z) else np.zeros(2)
        return float((edges[k] + edges[k + 1]) / 2)

    whole = best(z, y)
    return np.array([best(z[of], y[of]) if (y[of := lang == k] == 1).sum() >= least and (y[of] == 0).sum() >= least else whole for k in range(len(LANGUAGES) + 1)])


def fit_on(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, modulus: int = 5, remainder: int = 0, id_col: str = "doc_id", text_col: str = "text") -> ToxicityModel | None:
    context = docs.sparkSession.sparkContext

    def in_tasks(one, which):
        def task(k: int):
            found = one(k)
            give_back()
            return found

        return context.parallelize(which, len(which)).map(task).collect()

    model = fit(*labelled_sample(docs, labels, "toxic", modulus, remainder, per_class, id_col, text_col), each=in_tasks)
    give_back()
    return model


def apply_model(docs: DataFrame, model: ToxicityModel | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and score of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            texts = text_bytes(batch.column(1))
            score = np.zeros(len(texts)) if shared.value is None else shared.value.score(texts)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score, pa.float64())], ["doc_id", "score"])

    return id_and_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, score double")


def flagged(docs: DataFrame, model: ToxicityModel | None, text_col: str = "text", score_col: str = "score") -> DataFrame:
    """All columns of `docs` with the score of the text, in one pass: no join can lose or double rows."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches):
        for batch in batches:
            texts = text_bytes(batch.column(at))
            score = np.zeros(len(texts)) if shared.value is None else shared.value.score(texts)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(score, pa.float64())], [*batch.schema.names, score_col])
        give_back()

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(score_col, T.DoubleType())]))


def score_documents(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, modulus: int = 5, remainder: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    model = fit_on(docs, labels, per_class, modulus, remainder, id_col, text_col)
    scored = apply_model(docs, model, id_col, text_col)
    return scored.select("doc_id", held_out(F.col("doc_id"), modulus, remainder).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
