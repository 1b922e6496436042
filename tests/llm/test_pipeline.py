from __future__ import annotations

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from densekeys.llm.common import written
from tests.llm.test_operators import groups_by_force, removed_by_force


@pytest.fixture(scope="module")
def stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    held = [docs]
    for name, stage in corpus_pipeline.STAGES:
        held.append(written(stage(spark, held[-1], small), name))
    return held


def test_stages_keep_columns_and_all_but_the_rejected(spark, stages):
    docs, clean, single, apart, cut, packed = stages
    for d in (clean, single, apart, cut):
        assert d.columns == docs.columns
    assert clean.count() > 0.8 * docs.count()
    texts = {"".join(r["text"].split()) for r in clean.collect()}
    assert single.count() == len(texts)
    groups = groups_by_force([(r["doc_id"], r["text"]) for r in single.collect()])
    assert {r["doc_id"] for r in apart.collect()} == {i for i, (_, g) in groups.items() if i == g}


def test_cut_passages_follow_the_operator(stages):
    apart, cut = stages[3], stages[4]
    want = {r[0]: r for r in removed_by_force([(r["doc_id"], r["text"].encode()) for r in apart.collect()])}
    before = {r["doc_id"]: r for r in apart.collect()}
    assert apart.count() == cut.count()
    for r in cut.collect():
        if not want[r["doc_id"]][2]:
            assert r == before[r["doc_id"]]
        else:
            assert want[r["doc_id"]][1] - want[r["doc_id"]][2] <= len(r["text"].encode()) < want[r["doc_id"]][1] and r["n_chars"] == len(r["text"])
        assert (r["lang"], r["source"]) == (before[r["doc_id"]]["lang"], before[r["doc_id"]]["source"])


def test_everything_kept_is_packed(stages):
    cut, packed = stages[4], stages[5]
    assert {r["doc_id"] for r in packed.select("doc_id").distinct().collect()} == {r["doc_id"] for r in cut.collect()}


def test_pipeline_of_odd_and_no_rows(spark, small):
    schema = "doc_id long, text string, lang string, source string, n_chars long, kept string, carried_0 int"
    rows = [(1, None, None, None, None, "k", 1), (1, None, None, None, None, "k", 1), (None, "x", None, None, None, None, None), (2, "some words that stay", "en", None, 20, None, 2), (3, "", "en", "s", 0, None, 3)]
    docs = spark.createDataFrame(rows, schema)
    for d in (docs, docs.limit(0)):
        for name, stage in corpus_pipeline.STAGES:
            d = written(stage(spark, d, small), name)
            if name != "packing":
                assert d.columns == docs.columns
    kept = corpus_pipeline.drop_copies(spark, docs, small)
    assert sorted(r["doc_id"] for r in kept.select(F.col("doc_id")).collect()) == [1, 2]


def test_rows_are_judged_by_their_own_text(spark, small):
    """Unique texts without an id, or of an id that another text has too, stay; copies go whatever the id."""
    stages = dict(corpus_pipeline.STAGES)
    rows = [(1, "p q"), (5, "p q"), (5, "r s"), (None, "x"), (None, "x"), (None, "y"), (None, "p q"), (6, "u v"), (None, "u   v"), (7, "w z"), (7, "w z"), (7, "wz")]
    for extra in ("doc_id long, text string", "doc_id long, text string, row_key long"):
        docs = spark.createDataFrame([(*r, 3) if "row_key" in extra else r for r in rows], extra)
        kept = written(stages["exact_dedup"](spark, docs, small), "exact_dedup")
        assert kept.columns == docs.columns
        key = lambda r: (r[0] is None, r[0] or 0, r[1])
        assert sorted(((r["doc_id"], r["text"]) for r in kept.collect()), key=key) == [(1, "p q"), (5, "r s"), (7, "w z"), (None, "u   v"), (None, "x"), (None, "y")]
    words = [" ".join(f"{w}{k}" for k in range(60)) for w in "abcd"]
    near = [(1, words[0]), (5, words[0] + " more"), (5, words[1]), (None, words[2]), (None, words[1] + " end"), (None, words[0] + " other"), (8, words[3]), (9, words[3] + " again")]
    left = stages["near_dedup"](spark, spark.createDataFrame(near, "doc_id long, text string"), small).collect()
    assert {r["text"] for r in left} >= {words[0], words[2], words[3]} and len(left) == 4
    assert len({r["text"] for r in left} & {words[1], words[1] + " end"}) == 1


def test_run_equals_its_stages(spark, small, stages):
    key = lambda d: sorted((r["doc_id"], r["piece"], r["ids_crc32"]) for r in d.select("doc_id", "piece", "ids_crc32").collect())
    found = key(corpus_pipeline.run(spark, small))
    assert len(found) > 100 and found == key(stages[5])
