"""Operators that SQL can't express beside plain loops that follow their definitions word by word."""

from __future__ import annotations

from html.parser import HTMLParser

import numpy as np
import pyarrow.parquet as pq
import pytest

from densekeys.llm import quality, toxicity, warc
from densekeys.llm.words import LETTERS

# --- WARC: pages of the table through a parser that isn't ours


class Reader(HTMLParser):
    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.out, self.links, self.title, self.hidden, self.in_title = [], 0, "", 0, False

    def handle_starttag(self, tag, attrs):
        if tag in warc.BREAKING:
            self.out.append("\n")
        self.hidden += tag in warc.HIDDEN
        self.in_title |= tag == "title"
        self.links += tag == "a" and "href" in dict(attrs)

    def handle_endtag(self, tag):
        if tag in warc.BREAKING:
            self.out.append("\n")
        self.hidden -= tag in warc.HIDDEN
        self.in_title &= tag != "title"

    def handle_data(self, data):
        self.title += data if self.in_title else ""
        if not self.hidden:
            self.out.append(data)

    def handle_comment(self, data):
        self.out.append(" ")


def test_pages_by_another_parser():
    pages = pq.read_table("/root/testdata/sf0.01/pages.parquet").to_pylist()
    assert len(pages) > 200
    for page in pages:
        meta, text = warc.derive(warc.response_of(page["page_id"], page["url"], page["html"]))
        reader = Reader()
        reader.feed(page["html"])
        reader.close()
        lines = (" ".join(x.split()) for x in "".join(reader.out).split("\n"))
        squeezed = lambda t: "".join(t.split())  # noqa: E731  a hidden element is a blank here and nothing there
        assert squeezed(text["content"]) == squeezed("\n".join(x for x in lines if x))
        assert text["n_links"] == reader.links and f"title: {' '.join(reader.title.split())}\r\n" in meta["content"]
        headers, block = warc.parse_record(text["record"])
        assert block.decode() == text["content"] and warc.by_name(headers)["warc-block-digest"] == warc.digest(block)


# --- classifiers: scores by loops over words


def words_of(text: bytes) -> list[bytes]:
    out, held = [], b""
    for byte in text.lower() + b" ":
        if LETTERS[byte]:
            held += bytes([byte])
        elif held:
            out.append(held)
            held = b""
    return out


TEXTS = [b"", b"a", b"you are a bad bad person", b"the quick brown fox " * 40, "Ärger über, straße; été!".encode(), b"word1 word2\nword3   word1"]


@pytest.fixture(scope="module")
def toxic_model():
    rng = np.random.default_rng(5)
    common = [b"the", b"of", b"house", b"tree", b"river", b"stone", b"cloud"]
    bad = [b"awful", b"nasty", b"rotten"]
    texts, labels = [], []
    for k in range(120):
        words = [common[i] for i in rng.integers(0, len(common), 30)]
        if k % 2:
            words[int(rng.integers(0, 30))] = bad[int(rng.integers(0, 3))]
        texts.append(b" ".join(words))
        labels.append(k % 2)
    return toxicity.fit(texts, np.array(labels), epochs=4, steps=60)


def test_convolution_by_loops(toxic_model):
    """Each filter at each place, the largest of each stretch, the largest and the mean of the stretches."""
    m = toxic_model
    z, _ = m.logits(TEXTS)
    for text, got in zip(TEXTS, z, strict=True):
        rows = [toxicity.word_ids([w])[0][0] for w in words_of(text)]
        padded = rows + [np.zeros(toxicity.PARTS, np.int32)] * (-(-(len(rows) + max(toxicity.WIDTHS) - 1) // toxicity.STRETCH) * toxicity.STRETCH - len(rows))
        seen, t = [], 0
        peaks = []
        for width in toxicity.WIDTHS:
            response = np.zeros((len(padded), toxicity.FILTERS))
            for at in range(len(padded)):
                for k in range(width):
                    if at + k < len(padded):
                        for slot in padded[at + k]:
                            response[at] += m.tables[t + k][slot]
            t += width
            peaks.append([response[a : a + toxicity.STRETCH].max(axis=0) for a in range(0, len(padded), toxicity.STRETCH)])
        stretch = [np.maximum(np.concatenate([p[k] for p in peaks]) + m.bias, 0) for k in range(len(peaks[0]))]
        seen = np.concatenate([np.max(stretch, axis=0), np.mean(stretch, axis=0)])
        assert abs(float(seen @ m.out + m.offset) - got) < 1e-3


def test_training_tells_the_classes(toxic_model):
    assert (toxic_model.score([b"the house of the river nasty tree", b"a rotten cloud of stone"]) >= 0.5).all()
    assert (toxic_model.score([b"the house of the river tree", b"cloud of stone"]) < 0.5).all()


def test_thresholds_by_trying_all():
    """No threshold makes fewer weighted errors, over all rows and in a language with enough rows of its own."""
    rng = np.random.default_rng(2)
    z, y, lang = rng.normal(size=300), rng.integers(0, 2, 300), rng.integers(0, 2, 300)
    z += y * 0.8
    found = toxicity.calibrated(z, y, lang, least=30, clean_weight=2.0)
    errors = lambda t, of: ((z[of] < t) & (y[of] == 1)).sum() + 2.0 * ((z[of] >= t) & (y[of] == 0)).sum()
    tried = np.concatenate([z - 1e-9, z + 1e-9, [-9, 9]])
    for k in (0, 1):
        assert errors(found[k], lang == k) == min(errors(t, lang == k) for t in tried)
    assert errors(found[2], lang >= 0) == min(errors(t, lang >= 0) for t in tried)


def test_pooling_and_network_by_loops():
    texts = [b"one two three four five " * 4, b"a b c", b"", b"five four three", b"one one one two"] * 8
    labels = np.array([1, 0, 0, 1, 0] * 8)
    model = quality.fit(texts, labels, 0.5, epochs=3)
    x = quality.pooled(TEXTS, model.vectors)
    for text, row in zip(TEXTS, x, strict=True):
        at = 0
        for ids, _ in quality.token_streams([text]):
            total = np.zeros(model.vectors.shape[1])
            for slot in ids:
                total += model.vectors[slot]
            want = np.append(total / max(1, len(ids)), np.log1p(len(ids)) / 10)
            assert np.abs(row[at : at + len(want)] - want).max() < 1e-4
            at += len(want)
    p = model.params
    for row, got in zip(x, model.score(TEXTS), strict=True):
        hidden = [np.tanh(sum((row[i] - model.centre[i]) / model.scale[i] * p["a"][i, j] for i in range(len(row))) + p["b"][j]) for j in range(quality.HIDDEN)]
        logit = sum(h * c for h, c in zip(hidden, p["c"][:, 0], strict=True)) + p["d"][0]
        assert abs(1 / (1 + np.exp(-(logit / model.heat + model.shift))) - got) < 1e-3


def test_index_vectors_are_sparse_and_contexts_are_sums_of_them():
    index = quality.index_vectors()
    assert (np.abs(index).sum(axis=1) <= quality.NONZERO).all() and len(np.unique(index, axis=0)) > quality.SLOTS // 2
    texts = [b"alpha beta gamma"] * 6
    table = quality.context_vectors(texts, index)
    (ids, _), _ = quality.token_streams([texts[0]])
    a, b, c = ids.tolist()
    want = index[b] * 6 + index[c] * 6
    assert np.abs(table[a] - want / max(np.linalg.norm(want), 1)).max() < 1e-5
