from __future__ import annotations

import hashlib
import random
import re
import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from densekeys.llm import bpe, exact_dedup, ngram_join, packing, quality, suffix_dedup, tiff, toxicity, url_filter, warc
from densekeys.llm.components import components
from densekeys.llm.sharing import unsqueezed

VOCABULARY = public_tokenizers.path("word_bpe_49k.json")
SCHEMA = "doc_id long, text string, part string, route long, bucket int, keep_id long, n_bytes int"
ODD_TEXTS = ["", None, "   ", "a", "A", " a ", "one two three four five", "one two three four five", "é́ Σ ß 日本語 \x1f\x00x", "x" * 120_000, ("lorem ipsum dolor sit amet " * 3000).strip(), "to be or not to be " * 20]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and very long texts, ties, repeated rows, and columns named like inner ones."""
    rows = [(k, t, None, k, None, 5, 6) for k, t in enumerate(ODD_TEXTS)]
    rows += [rows[6], rows[6], (None, "to be or not to be " * 20, "p", None, 1, None, None), (None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def larger() -> str:
    return "/root/testdata/sf0.1"


# --- suffix arrays

WINDOW = suffix_dedup.WINDOW


def removed_by_force(docs: list[tuple[int | None, bytes]]) -> list[tuple]:
    order = lambda i: (1 << 62) if i is None else i
    first: dict[bytes, int] = {}
    for i, t in docs:
        for p in range(len(t) - WINDOW + 1):
            w = t[p : p + WINDOW]
            first[w] = min(first.get(w, 1 << 63), order(i))
    out = []
    for i, t in docs:
        mark = np.zeros(len(t), bool)
        for p in range(len(t) - WINDOW + 1):
            if first[t[p : p + WINDOW]] < order(i):
                mark[p : p + WINDOW] = True
        spans = int((np.diff(mark.astype(int), prepend=0) == 1).sum())
        out.append((i, len(t), int(mark.sum()), spans, hashlib.sha256(np.frombuffer(t, np.uint8)[~mark].tobytes()).hexdigest()))
    return sorted(out, key=str)


@given(st.binary(max_size=60).map(lambda b: bytes(x % 3 + 97 for x in b)))
@settings(max_examples=150, deadline=None)
def test_suffix_array_sorts_all_suffixes(data):
    assert suffix_dedup.suffix_array(data, 80).tolist() == sorted(range(len(data)), key=lambda i: data[i:])


def test_common_prefixes():
    data = b"banana bandana banana"
    order = suffix_dedup.suffix_array(data)
    got = suffix_dedup.common_prefixes(data, order)
    for k in range(1, len(order)):
        a, b = data[order[k - 1] :], data[order[k] :]
        n = next((i for i in range(min(len(a), len(b))) if a[i] != b[i]), min(len(a), len(b)))
        assert got[k] >= n if n == min(len(a), len(b)) else got[k] == n


def test_repeats_against_brute_force(spark, odd, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    rng = random.Random(4)
    words = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 8))) for _ in range(400)]
    passage = " ".join(rng.choice(words) for _ in range(60))
    made = [(1000 + k, " ".join(rng.choice(words) for _ in range(rng.randint(0, 80))) + (passage[rng.randint(0, 100) :] if k % 3 else "") + "ab" * (k % 40)) for k in range(60)]
    docs = docs.union(odd.where("length(text) < 5000 or text is null").select("doc_id", "text")).union(spark.createDataFrame(made, "doc_id long, text string"))
    got = [tuple(r) for r in suffix_dedup.remove_repeats(docs, with_text=False).collect()]
    assert sorted(got, key=str) == removed_by_force([(r["doc_id"], (r["text"] or "").encode()) for r in docs.collect()])


def test_frequent_and_long_sources_go_alone(spark, monkeypatch):
    """Copies beyond FEW, and a first document beyond LONG_DOCUMENT, take the other route to the same result."""
    rng = random.Random(1)
    text = " ".join("".join(rng.choice("abcdefghij") for _ in range(6)) for _ in range(12_000))
    rows = [(0, text), (1, text[5_000:9_000]), *[(k, text[100 * k : 100 * k + 900] + str(k)) for k in range(2, 40)]]
    got = [tuple(r) for r in suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), with_text=False).collect()]
    assert sorted(got, key=str) == removed_by_force([(i, t.encode()) for i, t in rows])


def test_kept_text_keeps_whole_characters(spark):
    text = "é" * 60
    rows = [(1, text, "l"), (2, "x" + text + "y", "m")]
    got = {r["doc_id"]: r for r in suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string, lang string"), carry=("lang",)).collect()}
    assert bytes(got[2]["kept"]).decode() == "xy" and got[2]["carried_0"] == "m" and bytes(got[1]["kept"]).decode() == text


def test_hot_anchors_are_taken_apart(spark, monkeypatch):
    """One passage in every document, after and before texts of their own: dealt to many routes, with the result of brute force."""
    monkeypatch.setattr(suffix_dedup, "HOT", 20)
    rng = random.Random(5)
    passage = "".join(rng.choice("abcdefghij klmnop") for _ in range(160))
    rows = [(k, "".join(rng.choice("qrstuv wxyz") for _ in range(rng.randint(0, 90))) + passage + "".join(rng.choice("qrstuv wxyz") for _ in range(rng.randint(0, 90)))) for k in range(120)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = [tuple(r) for r in suffix_dedup.remove_repeats(docs, with_text=False).collect()]
    assert sorted(got, key=str) == removed_by_force([(i, t.encode()) for i, t in rows])
    text, low, high, place, prints = suffix_dedup.all_anchors([t.encode() for _, t in rows])
    hot = np.full(len(text), suffix_dedup.ALONE | suffix_dedup.APART)
    t, a, b, route = suffix_dedup.apart([x.encode() for _, x in rows], text, low, high, place, hot)
    assert (b - a < suffix_dedup.STEP).all() and (b - a + 1).sum() == (high - low + 1).sum()
    of = {}
    for d, x, y, r in zip(t.tolist(), a.tolist(), b.tolist(), route.tolist(), strict=True):
        for p in range(x, y + 1):
            assert of.setdefault(rows[d][1][p : p + WINDOW], r) == r  # equal windows go together


def test_routes_without_and_with_a_repeat(monkeypatch):
    """Blocks of one route each: segments of different texts give no run, equal ones give the later document's."""
    monkeypatch.setattr(suffix_dedup, "SORT_BYTES", 1)
    a, b = bytes(range(65, 125)), bytes(range(60, 120))[::-1]
    rows = [(1, 0, 0, a, 5, 5), (1, 1, 1, b, 6, 6), (2, 0, 2, a, 3, 3), (2, 1, 3, b"xy" + a, 4, 9)]
    names = ["route", "part", "segment", "bytes", "least", "most"]
    batch = pa.RecordBatch.from_pylist([dict(zip(names, r, strict=True)) for r in rows])
    none, some = suffix_dedup.sort_segments(iter([batch]))
    assert none.num_rows == 0
    assert [(r["part"], *(unsqueezed(r[k], np.int64).tolist() for k in ("segments", "firsts", "lasts", "ids"))) for r in some.to_pylist()] == [(1, [3, 3], [0, 2], [1, 12], [4, 3])]


def test_repeats_of_nothing(none):
    assert suffix_dedup.remove_repeats(none).count() == 0


# --- near duplicates


def groups_by_force(docs):
    lower = {c: c + 32 for c in range(65, 91)}
    sets, root = {}, {}
    for i, t in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(lower))
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
        root[i] = i

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    held = defaultdict(list)
    for i, s in sets.items():
        common = defaultdict(int)
        for x in s:
            for j in held[x]:
                common[j] += 1
            held[x].append(i)
        for j, n in common.items():
            if 100 * n >= 75 * (len(s) + len(sets[j]) - n):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {i: (len(s), find(i)) for i, s in sets.items()}


def near_rows(spark, seed: int, n: int = 150):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(300)]
    base = [[rng.choice(words) for _ in range(rng.choice([3, 5, 8, 40, 90]))] for _ in range(6)]
    rows = []
    for k in range(n):
        text = list(rng.choice(base))
        for _ in range(rng.choice([0, 0, 1, 1, 2, 3, 6])):
            text[rng.randrange(len(text))] = rng.choice(words)
        if rng.random() < 0.2:
            text = text[rng.randrange(len(text)) :]
        rows.append((k, " ".join(text).upper() if k % 7 == 0 else " ".join(text)))
    return spark.createDataFrame(rows, "doc_id long, text string")


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_near_groups_against_brute_force(spark, seed):
    docs = near_rows(spark, seed)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.near_groups(docs).collect()}
    assert got == groups_by_force([tuple(r) for r in docs.collect()])


def test_split_blocks_and_copied_sets_lose_nothing(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "PAIRS_TOGETHER", 3)
    docs = near_rows(spark, 5)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.near_groups(docs, block_nodes=7).collect()}
    assert got == groups_by_force([tuple(r) for r in docs.collect()])


def test_near_groups_of_odd_rows(odd, none):
    got = ngram_join.near_groups(odd).collect()
    assert len(got) == odd.count()
    by_id = {r["doc_id"]: r for r in got}
    assert by_id[7]["component_id"] == 6 and by_id[0]["n_shingles"] == 0 and by_id[None]["component_id"] is None
    assert by_id[4]["component_id"] == 3 == by_id[5]["component_id"]
    assert ngram_join.near_groups(none).count() == 0


def test_trees_hand_every_pair_to_verification(spark, monkeypatch):
    """With the tree made blind no link is found: pairs come from it in every block, and from nowhere else."""
    docs = near_rows(spark, 8)
    seen = []
    kept = ngram_join.searched
    monkeypatch.setattr(ngram_join, "searched", lambda rows: seen.append(kept(rows)) or seen[-1])
    linked = {r["doc_id"]: r["component_id"] for r in ngram_join.near_groups(docs).collect()}
    assert len(seen) == 2 and any(k != v for k, v in linked.items())
    monkeypatch.setattr(ngram_join, "searched", lambda rows: kept(rows).where("false"))
    sets = docs.select("doc_id", F.lower("text").alias("t")).collect()
    equal = {r["t"]: min(x["doc_id"] for x in sets if x["t"] == r["t"]) for r in sets}
    blind = {r["doc_id"]: r["component_id"] for r in ngram_join.near_groups(docs).collect()}
    assert all(v == k or equal[next(x["t"] for x in sets if x["doc_id"] == k)] == v for k, v in blind.items())


def test_blocks_find_pairs_by_bound_alone():
    """Rows of two blocks: pairs of one component, and pairs whose minima can't reach, aren't handed on."""
    def counts(*held):
        x = np.zeros(ngram_join.GROUPS, np.uint16)
        x[list(held)] = 10
        return x.tobytes()

    rows = [(1, 0, 5, 40, 5, counts(0, 1, 2, 3), 3), (1, 0, 6, 40, 6, counts(0, 1, 2, 3), 1), (1, 0, 7, 40, 7, counts(0, 1, 2, 9), 1), (1, 0, 8, 40, 8, counts(4, 5, 6, 7), 1), (1, 0, 9, 40, 5, counts(0, 1, 2, 3), 1)]
    rows += [(2, 0, 1, 40, 1, counts(0, 1, 2, 3), 1), (2, 0, 2, 40, 2, counts(0, 1, 2, 3), 1)]
    batch = pa.RecordBatch.from_pylist([dict(zip(ngram_join.BLOCK_ROW, r, strict=True)) for r in rows])
    found = [tuple(r.values()) for b in ngram_join.block_pairs(iter([batch])) for r in b.to_pylist()]
    assert found == [(5, 6)]


@given(st.lists(st.lists(st.integers(0, 6), min_size=8, max_size=8), min_size=1, max_size=60))
@settings(max_examples=40, deadline=None)
def test_tree_loses_no_pair_within_the_bound(rows):
    counts = np.zeros((len(rows), ngram_join.GROUPS), np.int64)
    counts[:, :8] = rows
    sizes = counts.sum(axis=1)
    tree = ngram_join.CountTree(counts, sizes)
    for i in range(len(rows)):
        n, m = sizes[i], sizes
        want = np.flatnonzero((4 * m >= 3 * n) & (3 * m <= 4 * n) & (7 * np.minimum(counts, counts[i]).sum(axis=1) >= 3 * (n + m)))
        assert sorted(tree.search(counts[i], int(n)).tolist()) == want.tolist()


def test_components_of_a_chain(spark):
    links = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(100, 101)], "a long, b long")
    assert {r["component"] for r in components(links).collect()} == {0, 100}


# --- exact duplicates


def test_index_across_batches(spark):
    index = exact_dedup.DigestIndex.create(spark)
    first = spark.createDataFrame([(5, "a b"), (3, "ab"), (9, "c")], "doc_id long, text string")
    got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"]) for r in index.dedup(first).collect()}
    assert got == {5: (5, 2, True), 3: (5, 2, False), 9: (9, 1, True)}
    second = spark.createDataFrame([(1, "a  b"), (2, "d")], "doc_id long, text string")
    got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"]) for r in index.dedup(second).collect()}
    assert got == {1: (5, 3, False), 2: (2, 1, True)}
    assert index.read().count() == 3


def test_exact_dedup_of_odd_rows(spark, odd, none):
    got = exact_dedup.DigestIndex.create(spark).dedup(odd).collect()
    assert len(got) == odd.count()
    empty = [r for r in got if r["doc_id"] in (0, 1, 2) or r["doc_id"] is None and r["text_sha256"] == hashlib.sha256(b"").hexdigest()]
    assert {r["keep_id"] for r in empty} == {2} and {r["group_size"] for r in empty} == {4}
    assert exact_dedup.DigestIndex.create(spark).dedup(none).count() == 0


def test_index_is_opened_again_and_dropped(spark, tmp_path):
    path = f"file:{tmp_path}/index"
    index = exact_dedup.DigestIndex.create(spark, path=path, buckets=3)
    index.dedup(spark.createDataFrame([(5, "a b")], "doc_id long, text string"))
    index.drop(files=False)
    again = exact_dedup.DigestIndex.open(spark, path)
    assert again.buckets == 3 and again.read().count() == 1
    got = {r["doc_id"]: (r["keep_id"], r["kept"]) for r in again.dedup(spark.createDataFrame([(1, "ab"), (2, "c")], "doc_id long, text string")).collect()}
    assert got == {1: (5, False), 2: (2, True)} and again.read().count() == 2
    again.drop()
    assert not list(tmp_path.iterdir()) and not spark.catalog.tableExists(again.table)


def test_extreme_ids_keep_their_order(spark):
    least, most = -(1 << 63), (1 << 63) - 1
    docs = spark.createDataFrame([(most, "x"), (0, "x"), (least, "x"), (None, "x")], "doc_id long, text string")
    assert {r["keep_id"] for r in exact_dedup.DigestIndex.create(spark).dedup(docs).collect()} == {least}


# --- URLs


def test_rules_by_rarest_token_equal_all_rules():
    index = url_filter.RuleIndex(url_filter.RULES, {"org": 9, "example": 1, "com": 2})
    every = url_filter.RuleIndex(tuple(url_filter.Rule(r.name, r.verdict, r.pattern, (), r.by_host) for r in url_filter.RULES), {})
    urls = [None, "", "x", "http://", "HTTP://A.EXAMPLE.org/en/12", "http://example.org/en/1", "http://example.org/es", "http://badexample.org/es/x", "http://example.org/es/x?utm_source=1", "ftp://org/", "http://b.com/de/?q", "http://c.com#/de/", "http://d.net/x.zip"]
    for u in urls:
        assert index.judge(u, "allow") == every.judge(u, "allow")
    assert index.judge("HTTP://A.EXAMPLE.org/en/12", "allow") == ("a.example.org", "/en/12", "example.org/en/1", "block")
    assert index.judge("http://badexample.org/es/x", "block")[2:] == ("org/", "allow")
    assert index.judge("http://example.org", "allow") == ("example.org", "", None, "allow")
    assert index.judge(None, "allow") == ("", "", None, "allow")


def test_thousands_of_rules_run_few_expressions():
    """A URL runs the expressions filed under its own tokens, however many rules there are; the verdicts are those of running all."""
    rng = random.Random(6)
    words = [f"w{k}x" for k in range(400)]
    rules = [url_filter.host_rule(rng.choice(["allow", "block"]), f"{rng.choice(words)}.{rng.choice(words)}.org/{rng.choice(words)}/") for _ in range(4000)]
    rules += [url_filter.free_rule(f"free{k}", "block", rf"/{w}-[0-9]+/", (w,)) for k, w in enumerate(words)]
    rules = tuple({r.name: r for r in (*rules, *url_filter.RULES[:5])}.values())
    assert all(r.tokens for r in (*rules, *url_filter.RULES))
    urls = [f"http://{rng.choice(words)}.{rng.choice(words)}.org/{rng.choice(words)}/{rng.choice(words)}-7/" for _ in range(150)]
    urls += [f"http://sub.{r.name}page" for r in rng.sample(rules[:4000], 50)]
    counts = defaultdict(int)
    for u in urls:
        for t in set(re.findall("[a-z0-9]+", u)):
            counts[t] += 1
    index = url_filter.RuleIndex(rules, counts)
    every = url_filter.RuleIndex(tuple(url_filter.Rule(r.name, r.verdict, r.pattern, (), r.by_host) for r in rules), {})
    for u in urls:
        assert index.judge(u, "allow") == every.judge(u, "allow")
    run = [len(index.candidates(u)) for u in urls]
    assert not index.always and np.mean(run) < len(rules) / 50 and any(index.judge(u, "allow")[2] for u in urls)


def test_url_table(spark):
    pages = spark.createDataFrame([(1, None), (2, "http://x.org/a"), (2, "http://x.org/a")], "page_id long, url string")
    assert [r["verdict"] for r in url_filter.filter_urls(pages).collect()] == ["allow"] * 3
    assert url_filter.filter_urls(pages.limit(0)).count() == 0


# --- media


@pytest.mark.parametrize("compression", tiff.SCHEMES)
@pytest.mark.parametrize("predictor", [1, 2])
@pytest.mark.parametrize("tile", [None, (32, 16)])
def test_tiff_round_trip(compression, predictor, tile):
    rng = np.random.default_rng(5)
    for high in (2, 256):
        pages = [rng.integers(0, high, (int(rng.integers(1, 150)), 64, 3)).astype(np.uint8) for _ in range(3)]
        back = tiff.read_tiff(tiff.write_tiff(pages, compression, predictor, 40, tile))
        assert len(back) == 3 and all((a == b).all() for a, b in zip(pages, back, strict=True))


@given(st.binary(max_size=9000))
@settings(max_examples=30, deadline=None)
def test_lzw_and_packbits(data):
    assert tiff.lzw_decode(tiff.lzw_encode(data), len(data)) == data
    assert tiff.packbits_decode(tiff.packbits_encode(data), len(data)) == data


def test_lzw_over_a_full_table():
    data = np.random.default_rng(2).integers(0, 256, 60_000).astype(np.uint8).tobytes()
    assert tiff.lzw_decode(tiff.lzw_encode(data), len(data)) == data


def test_media_of_odd_rows(spark, odd, none):
    for r in tiff.text_media(odd).collect():
        text = b"" if r["doc_id"] is None and r["n_bytes"] == 0 else None
        if r["doc_id"] is not None:
            text = (ODD_TEXTS[r["doc_id"]] or "").encode()
        if text is not None:
            payload = text.ljust(max(192, -(-len(text) // 192) * 192), b" ")
            assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(text), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
    assert tiff.text_media(none).count() == 0


def test_broken_media_is_told(spark):
    good = tiff.write_tiff([np.zeros((2, 64, 3), np.uint8), np.ones((1, 64, 3), np.uint8)])
    media = spark.createDataFrame([(1, good), (2, good[:20]), (3, None), (4, b"II*\0\x08\0\0\0\x00\x00\x08\0\0\0")], "media_id long, data binary")
    rows = tiff.explode_pages(media).collect()
    assert sorted((r["media_id"], r["page"], r["error"] is None) for r in rows if r["media_id"] < 4) == [(1, 0, True), (1, 1, True), (2, -1, False), (3, -1, False)]
    assert any(r["error"] for r in rows if r["media_id"] == 4)


# --- WARC


def test_derivatives_link_to_their_response():
    page = "<html><head><title>A &amp; B</title><script>x()</script></head><body><p>One<br>two</p><a href='/x'>l</a><!-- c --></body></html>"
    data = warc.response_of(7, "http://a.b/c", page)
    meta, text = warc.derive(data)
    headers, block = warc.parse_record(text["record"])
    headers, source = warc.by_name(headers), warc.by_name(warc.parse_record(data)[0])
    assert headers["warc-refers-to"] == source["warc-record-id"] == meta["refers_to"] and headers["warc-target-uri"] == "http://a.b/c"
    assert block.decode() == "A & B\nOne\ntwo\nl" and text["block_digest"] == warc.digest(block) and headers["warc-date"] == source["warc-date"]
    assert "title: A & B\r\n" in meta["content"] and "outlinks: 1\r\n" in meta["content"] and meta["source_digest"] == source["warc-payload-digest"]


def test_coded_bodies():
    import gzip

    body = gzip.compress("<p>café</p>".encode("latin-1"))
    chunked = b"%x\r\n" % len(body[:9]) + body[:9] + b"\r\n" + b"%x;e=1\r\n" % len(body[9:]) + body[9:] + b"\r\n0\r\n\r\n"
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html;\r\n charset=ISO-8859-1\r\nTransfer-Encoding: chunked\r\nContent-Encoding: gzip\r\n\r\n" + chunked
    data = warc.record([("WARC-Type", "response"), ("WARC-Record-ID", "<urn:uuid:1>")], http)
    assert warc.derive(data)[1]["content"] == "café"


def test_warc_tables(spark):
    pages = spark.createDataFrame([(1, None, None), (2, "http://x", "<p>t</p>"), (2, "http://x", "<p>t</p>")], "page_id long, url string, html string")
    rows = warc.derive_pages(pages).collect()
    assert len(rows) == 6 and {r["content"] for r in rows if r["record_type"] == "conversion"} == {"", "t"}
    broken = spark.createDataFrame([(1, b"nonsense"), (2, None)], "page_id long, record binary")
    assert [r["record_type"] for r in warc.derive_records(broken).collect()] == ["error", "error"]
    assert warc.derive_pages(pages.limit(0)).count() == 0


# --- BPE and packing

PIECES = ["a", "th", "E", "é", "é", " ", "\n", "'s", "'LL", "7", "²", "!?", "ß", "ﬁ", "Σ", "\x1d", "　", "日", "😀", "́", "ǅ", "<|endoftext|>", "<|", "word", ",", "x" * 60]


@given(st.lists(st.sampled_from(PIECES), max_size=60).map("".join))
@settings(max_examples=200, deadline=None)
def test_encoding_equals_the_library(text):
    library, own = Tokenizer.from_file(VOCABULARY) if not LIBRARY else LIBRARY[0], bpe.loaded(VOCABULARY)
    LIBRARY[:] = [library]
    ids = library.encode(text, add_special_tokens=False).ids
    assert own.encode(text) == ids and own.decode(ids) == library.decode(ids, skip_special_tokens=False)


LIBRARY: list = []


def test_special_strings_are_found_by_what_they_share(tmp_path):
    """Whatever the vocabulary calls special, its own start tells whether a text can hold it."""
    import json

    spec = json.load(open(VOCABULARY))
    for t in spec["added_tokens"]:
        t["content"] = "[[" + t["content"].strip("<|>") + "]]"
    path = tmp_path / "v.json"
    path.write_text(json.dumps(spec))
    own, content = bpe.WordBpe(str(path)), spec["added_tokens"][0]["content"]
    assert own.special_start.startswith("[[") and own.encode(f"a {content} b") == [*own.encode("a"), spec["added_tokens"][0]["id"], *own.encode("b")]


def test_long_and_short_words_agree():
    own = bpe.loaded(VOCABULARY)
    words = [b"internationalization", b"x", bytes(range(97, 123)) * 1, "été".encode()]
    data, size = np.frombuffer(b"".join(words), np.uint8), np.array([len(w) for w in words])
    ids, n = own.short_words(data, np.cumsum(size) - size, size)
    assert [x.tolist() for x in np.split(ids, np.cumsum(n)[:-1])] == [own.long_word(w).tolist() for w in words]


def test_memory_given_up_changes_nothing(monkeypatch, spark, small):
    monkeypatch.setattr(bpe, "KEPT_WORDS", 300)
    monkeypatch.setattr(bpe, "BLOCK_CHARS", 2000)
    library = Tokenizer.from_file(VOCABULARY)
    texts = [r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").select("text").limit(60).collect()] + ["x" * 200 + " a " + "y" * 90 + "<|endoftext|>b"]
    for t, ids in zip(texts, bpe.Encoder(bpe.loaded(VOCABULARY)).texts(texts), strict=True):
        assert ids.tolist() == library.encode(t, add_special_tokens=False).ids


def test_words_of_one_hash_are_told_apart(monkeypatch):
    """Both tables of byte hashes made to agree for two letters: the second print tells, else nothing could."""
    table = bpe.BYTE_WORDS.copy()
    table[ord("b")] = table[ord("a")]
    monkeypatch.setattr(bpe, "BYTE_WORDS", table)
    own, encoder = bpe.loaded(VOCABULARY), bpe.Encoder(bpe.loaded(VOCABULARY))
    library = Tokenizer.from_file(VOCABULARY)
    for text in ("bat", "aat", "aat bat cab caa", "caa"):
        assert next(encoder.texts([text])).tolist() == library.encode(text, add_special_tokens=False).ids
    assert own is encoder.bpe


def test_digests_follow_ids_and_texts(spark, odd, none):
    whole = bpe.encode_documents(odd, VOCABULARY).collect()
    digests = bpe.encoding_digests(odd, VOCABULARY).collect()
    want = sorted((r["doc_id"] or -1, len(r["ids"]), hashlib.sha256(" ".join(map(str, r["ids"])).encode()).hexdigest(), hashlib.sha256(r["decoded"].encode()).hexdigest()) for r in whole)
    assert sorted((r["doc_id"] or -1, r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in digests) == want
    assert bpe.encoding_digests(none, VOCABULARY).count() == 0


def test_packing_is_gapless_whole_and_tight(spark, odd, none, small):
    library = Tokenizer.from_file(VOCABULARY)
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").union(odd.select(F.col("doc_id") + 10_000, "text"))
    cut = packing.written(packing.pieces(docs, VOCABULARY), "pieces")
    rows = packing.pack(cut, shard_pieces=100).collect()
    want = []
    for r in docs.collect():
        ids = [*library.encode(r["text"] or "", add_special_tokens=False).ids, 0]
        want += [(r["doc_id"], k // 2048, k, len(ids[k : k + 2048]), zlib.crc32(np.array(ids[k : k + 2048], "<u4").tobytes())) for k in range(0, len(ids), 2048)]
    assert sorted((tuple(r)[:5] for r in rows), key=str) == sorted(want, key=str)
    bins = defaultdict(list)
    for r in rows:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for placed in bins.values():
        at = 0
        for offset, length in sorted(placed):
            assert offset == at
            at += length
        assert at <= 2048
    total = sum(r["length"] for r in rows)
    assert len(bins) <= 1.02 * total / 2048 + 1
    assert packing.pack_documents(none, VOCABULARY).count() == 0


def triplets(n: int, seed: int) -> np.ndarray:
    """Sizes that three by three fill n bins, which best fit doesn't find."""
    rng = np.random.default_rng(seed)
    a = rng.integers(780, 1000, n)
    b = np.array([rng.integers(512, (2048 - x) // 2 + 1) for x in a])
    return np.concatenate([a, b, 2048 - a - b])


def best_fit_bins(sizes: np.ndarray) -> int:
    return len(packing.refilled(np.full(len(sizes), -1), sizes, 2048, np.random.default_rng(0), 0.0).fill)


@pytest.mark.parametrize("sizes", [triplets(60, 1), triplets(300, 2), np.random.default_rng(0).integers(300, 1100, 400), np.random.default_rng(4).integers(200, 1000, 1500)])
def test_crossing_packs_what_best_fit_cannot(sizes):
    """Fewer bins than best fit of the largest first, and than without crossings. Nothing is handed in."""
    begun, none = packing.evolve(sizes, [], 2048, 1, generations=0)
    best, crossings = packing.evolve(sizes, [], 2048, 1, population=8, generations=20)
    assert none == 0 and crossings > 0 and len(best.fill) < min(best_fit_bins(sizes), len(begun.fill))
    assert best.fill.max() <= 2048 and best.fill.sum() == sizes.sum() and len(best.groups) == len(sizes)


def test_real_shards_are_packed_by_crossings(spark, larger):
    """On the lengths of real documents, crossings reach what can't be beaten by more than a bin, from begins that are several away."""
    sizes = np.array([min(2048, 1 + len(r["text"].split())) for r in spark.read.parquet(f"{larger}/documents.parquet").select("text").collect()])
    for shard in np.array_split(sizes, 3):
        least = -(-int(shard.sum()) // 2048)
        begun, _ = packing.evolve(shard, [], 2048, 3, generations=0)
        best, crossings = packing.evolve(shard, [], 2048, 3)
        assert crossings > 0 and len(best.fill) <= least + 1 < len(begun.fill)


def test_elites_migrate_and_win():
    sizes = triplets(60, 3)
    good, _ = packing.evolve(sizes, [], 2048, 1, population=8, generations=20)
    other, _ = packing.evolve(sizes, [good.groups], 2048, 2, generations=0)
    assert (other.groups == good.groups).all()


def test_repeated_rows_are_dealt_to_all_shards(spark):
    rows = packing.pack(packing.written(spark.createDataFrame([(None, 0, 0, 700, 5)] * 400, packing.PIECE_SCHEMA).repartition(4), "pieces"), shard_pieces=50).collect()
    assert len(rows) == 400 and len({r["sequence_id"] >> 24 for r in rows}) >= 6 and len({r["sequence_id"] for r in rows}) <= 210


# --- classifiers


def held_out(doc_id: int, modulus: int, remainder: int) -> bool:
    return zlib.crc32(str(doc_id).encode()) % modulus == remainder


@pytest.mark.parametrize("operator,label,modulus,remainder,least", [(quality, "quality", 4, 2, 0.95), (toxicity, "toxic", 5, 0, 0.9)])
def test_held_out_accuracy(spark, larger, operator, label, modulus, remainder, least):
    docs, labels = (spark.read.parquet(f"{larger}/{t}.parquet") for t in ("documents", "labels"))
    rows = operator.score_documents(docs, labels).join(labels, "doc_id").collect()
    assert all(r["held_out"] == held_out(r["doc_id"], modulus, remainder) and 0 <= r["score"] <= 1 for r in rows)
    rows = [r for r in rows if r["held_out"]]
    assert np.mean([r["predicted"] == r[label] for r in rows]) >= least
    clean = [r for r in rows if r[label] == (1 if label == "quality" else 0)]
    assert np.mean([r["predicted"] == r[label] for r in clean]) >= 0.97


@pytest.mark.parametrize("folder,recall", [("sf0.01", 0.15), ("sf0.1", 0.7)])
def test_toxic_recall_at_every_size(spark, folder, recall):
    docs, labels = (spark.read.parquet(f"/root/testdata/{folder}/{t}.parquet") for t in ("documents", "labels"))
    rows = [r for r in toxicity.score_documents(docs.join(labels.select("doc_id"), "doc_id", "left_semi"), labels).join(labels, "doc_id").collect() if r["held_out"]]
    toxic = [r["predicted"] for r in rows if r["toxic"] == 1]
    assert np.mean(toxic) >= recall
    assert np.mean([r["predicted"] for r in rows if r["toxic"] == 0]) <= 0.01


@pytest.mark.parametrize("operator,label", [(quality, "quality"), (toxicity, "toxic")])
def test_classifiers_of_odd_rows(spark, odd, none, operator, label):
    few = spark.createDataFrame([(6, 1), (8, 0), (None, 1), (3, None)], f"doc_id long, {label} int")
    for labels in (few, few.limit(0)):
        rows = operator.score_documents(odd, labels).collect()
        assert len(rows) == odd.count() and all(0 <= r["score"] <= 1 for r in rows)
        assert not any(r["held_out"] for r in rows if r["doc_id"] is None)
    assert operator.score_documents(none, few).count() == 0


def test_labels_of_held_out_rows_are_not_learnt(spark, small):
    docs, labels = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("documents", "labels"))
    turned = labels.withColumn("toxic", F.when(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = ({r["doc_id"]: r["score"] for r in toxicity.score_documents(docs, x).collect()} for x in (labels, turned))
    assert a == b


def test_memory_is_returned_once_a_step_has_ended(monkeypatch):
    """Idle workers kept what their last group had taken, beside those of the next stage."""
    import weakref

    from densekeys.llm import common

    class Held:
        pass

    refs, gone = [], []

    def step(x):
        held = Held()
        refs.append(weakref.ref(held))
        return x + 1

    monkeypatch.setattr(common, "give_back", lambda: gone.append(refs[0]() is None))
    assert common.giving_back(step, 1) == 2
    assert gone == [True]
