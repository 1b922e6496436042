from __future__ import annotations

import heapq
import math
import random
import re
from concurrent.futures import ThreadPoolExecutor

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from densekeys.functions.encode import encode_key, encoded_string
from densekeys.operators import graphs
from densekeys.operators.apps import dense_join
from densekeys.plans.build import build_core, build_two_level
from densekeys.plans.evaluate import lookup, verify
from densekeys.plans.params import Params, family
from densekeys.workloads import registry, relational
from densekeys.workloads.relational import TABLES

@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def canonical(df: pd.DataFrame) -> list[tuple]:
    df = df[sorted(df.columns)].astype(object)

    def plain(x):
        if x is None or x is pd.NA or isinstance(x, float) and math.isnan(x):
            return None
        return round(float(x), 6) if isinstance(x, (int, float)) and not isinstance(x, bool) else str(x)

    return sorted((tuple(map(plain, r)) for r in df.itertuples(index=False)), key=str)


@pytest.fixture(scope="module")
def results(spark, small):
    """Every query, several at a time, as most wait for small tasks."""

    def run(name: str):
        try:
            return registry.QUERIES[name](spark, small).toPandas()
        except Exception as e:  # noqa: BLE001  told by the query's own test
            return e

    with ThreadPoolExecutor(6) as pool:
        return dict(zip(registry.QUERIES, pool.map(run, registry.QUERIES), strict=True))


@pytest.mark.parametrize("name", registry.QUERIES)
def test_query_equals_sql(results, duck, name):
    got, want = results[name], duck.execute(registry.ORACLES[name]).df()
    if isinstance(got, Exception):
        raise got
    assert sorted(got.columns) == sorted(want.columns)
    assert canonical(got) == canonical(want)


def test_every_query_has_sql():
    assert set(registry.QUERIES) == set(registry.ORACLES)


def test_entry(spark):
    rows = __spark_entry__.entry(spark).collect()
    assert sorted(r["id"] for r in rows) == list(range(50))


@pytest.mark.parametrize("hash", ["linear", "mix96", "xx128"])
@pytest.mark.parametrize("n", [0, 1, 255, 256, 257])
def test_sizes_at_the_edges(spark, hash, n):
    df = spark.range(n).withColumnRenamed("id", "k")
    row = verify(df, build_two_level(df, "k", Params(hash=hash))).first()
    assert (row["n"], row["min_id"], row["max_id"], row["n_ids"]) == ((n, 0, n - 1, n) if n else (0, None, None, 0))


def test_nulls_and_repeats_are_no_members(spark):
    df = spark.createDataFrame([(None,), ("a",), ("a",), ("b",), ("",)], "k string")
    artifact = build_two_level(df, "k")
    assert artifact.n == 3
    for mode in ("broadcast", "partitioned"):
        rows = lookup(df, artifact, mode=mode).collect()
        assert {r["k"]: r["id"] for r in rows}.keys() == {None, "a", "b", ""} and {r["id"] for r in rows if r["k"] is None} == {None}


def test_encoding_is_injective(spark):
    df = spark.createDataFrame([("1", "23"), ("12", "3"), ("", "123")], "a string, b string")
    assert df.select(encode_key(df, ["a", "b"])).distinct().count() == 3
    nul = spark.createDataFrame([("",), ("\0",), ("a",), ("a\0",)], "a string")
    assert nul.select(encode_key(nul, ["a"])).distinct().count() == 4
    zeros = spark.createDataFrame([(0.0,), (-0.0,)], "a double")
    assert zeros.select(encode_key(zeros, ["a"])).distinct().count() == 1
    with pytest.raises(TypeError):
        encode_key(spark.createDataFrame([({"a": 1},)], "m map<string,int>"), ["m"])


@pytest.mark.parametrize("hash", ["linear", "mix96", "xx128"])
def test_repeated_keys_are_reduced_before_the_exchange(spark, small, hash):
    """One exchange, a partial aggregate below it, and only the key column read."""
    from densekeys.plans.fingerprints import distinct_fingerprints, fingerprint

    df = spark.read.parquet(f"{small}/orders.parquet")
    plan = distinct_fingerprints(fingerprint(df, ["o_orderkey"], Params(hash=hash), 0))._jdf.queryExecution().toString()
    physical = plan[plan.index("== Physical Plan ==") :]
    assert physical.count("Exchange ") == 1
    exchange = physical.index("Exchange ")
    assert "partial_min" in physical[exchange:] and "partial_min" not in physical[:exchange]
    assert re.search(r"ReadSchema: struct<o_orderkey:bigint>", physical)


def test_the_build_reads_its_keys_once(spark):
    from pyspark.sql.functions import udf

    rows = spark.sparkContext.accumulator(0)

    @udf("long")
    def told(x):
        rows.add(1)
        return x

    df = spark.range(500, numPartitions=3).select(told.asNondeterministic()("id").alias("k"))
    assert build_two_level(df, "k", Params(hash="xx128", super_keys=64)).n == 500 and rows.value == 500


def test_same_artifact_for_other_partitionings(spark):
    a, b = (build_two_level(spark.range(3000).repartition(p).withColumnRenamed("id", "k"), "k", Params(super_keys=500)).rows.orderBy("super").collect() for p in (1, 7))
    assert a == b


def test_whole_set_is_refused_beyond_its_bound(spark):
    with pytest.raises(ValueError):
        build_core(spark.range(100), "id", max_keys=10)


@pytest.mark.parametrize("build", [build_core, build_two_level])
def test_universal_is_a_family_of_its_own(spark, build):
    df = spark.range(700).withColumnRenamed("id", "k")
    artifact = build(df, "k", Params(hash="universal"))
    assert artifact.params.hash == "universal"
    tables = family(artifact.params, artifact.attempt).values.tables
    assert tables.shape == (2, 8, 256) and len(np.unique(tables)) == tables.size
    row = verify(df, artifact).first()
    assert (row["n"], row["min_id"], row["max_id"], row["n_ids"]) == (700, 0, 699, 700)
    other = build(df, "k", Params(hash="xx128"))
    assert sorted(bytes(r["labels"]) for r in artifact.rows.collect()) != sorted(bytes(r["labels"]) for r in other.rows.collect())


def test_tabulated_values_by_force():
    values, words = family(Params(hash="universal"), 0).values, np.array([[0x01020304, 0xA0B0C0D0, 5, 6], [0, 0xFF, 7, 8]], np.uint32)
    for which, sums in enumerate(values.sums(words)):
        for row, key in enumerate(words.tolist()):
            x = 0
            for k, byte in enumerate(reversed((key[0] << 32 | key[1]).to_bytes(8, "big"))):
                x ^= int(values.tables[which, k, byte])
            assert (int(sums.a[row]), int(sums.b[row])) == ((x >> 32) % 4294967291, x % (1 << 32) % 4294967291)


def test_unknown_keys_get_a_slot_or_null_but_never_fail(spark):
    artifact = build_two_level(spark.range(1000), "id", Params(hash="xx128"))
    found = lookup(spark.range(5000, 6000), artifact, slot="s", id="i")
    assert found.where((F.col("i") < 0) | (F.col("i") >= 1000)).count() == 0


@pytest.mark.parametrize("how", ["inner", "left", "left_semi", "left_anti"])
@pytest.mark.parametrize("mode", ["broadcast", "partitioned"])
def test_one_slot_joins_equal_joins(spark, monkeypatch, how, mode):
    """Nulls, unknown keys and repeated probe keys, over several stretches of slots."""
    from densekeys.operators import apps

    monkeypatch.setattr(apps, "SLOTS", 16)
    rng = random.Random(2)
    fact = spark.createDataFrame([(rng.choice([None, *range(150)]), k) for k in range(400)], "k long, v long")
    dim = spark.createDataFrame([(k, f"n{k}") for k in range(100)] + [(None, "none")], "d long, name string")
    got = dense_join(fact, dim, ("k", "d"), how, mode=mode).collect()
    want = fact.join(dim, F.col("k") == F.col("d"), how).collect()
    assert sorted(got, key=str) == sorted(want, key=str)


def test_one_slot_joins_refuse_repeated_dimension_keys(spark):
    dim = spark.createDataFrame([(1, "a"), (1, "b")], "d long, name string")
    with pytest.raises(ValueError):
        dense_join(spark.createDataFrame([(1,)], "k long"), dim, ("k", "d"))


def test_long_keys_are_encoded_alike(spark):
    texts = ["", "a", "x" * 63, "x" * 64, "x" * 65, "x" * 66, "é" * 200, "\0"]
    df = spark.createDataFrame([(t,) for t in texts], "k string")
    assert [bytes(r[0]) for r in df.select(encode_key(df, ["k"])).collect()] == [encoded_string(t.encode()) for t in texts]


def test_buckets_by_a_merge_of_runs(spark):
    """The reference way to read buckets: sorted runs merged by a heap hand over the buckets that the engine's exchange does."""
    from densekeys.plans.fingerprints import distinct_fingerprints, fingerprint

    artifact = build_two_level(spark.range(3000), "id", Params(hash="xx128"))
    prints = distinct_fingerprints(fingerprint(spark.range(3000), ["id"], artifact.params, artifact.attempt))
    values = [r["hi"] % (1 << 64) for r in prints.collect()]
    runs = [sorted(values[a : a + 400]) for a in range(0, len(values), 400)]
    sizes: dict[int, int] = {}
    last = -1
    for value in heapq.merge(*runs):
        bucket = value >> (64 - artifact.b)
        assert bucket >= last
        last = bucket
        sizes[bucket] = sizes.get(bucket, 0) + 1
    assert sizes == {r["bucket"]: r["size"] for r in artifact.buckets().collect()}


def test_runs_hold_all_values_in_order():
    from densekeys.functions.runs import RUNS

    values = np.random.default_rng(3).integers(0, 1 << 63, 5000).astype(np.uint64)
    lengths = {}
    for name, form in RUNS.items():
        runs = form(values, 256)
        assert sorted(np.concatenate(runs).tolist()) == sorted(values.tolist()) and all((r[1:] >= r[:-1]).all() for r in runs)
        lengths[name] = len(runs)
    assert lengths["radix"] == lengths["comparison"] == 20 and lengths["replacement"] < 14


def test_a_large_side_is_sent_in_pieces(spark, small, duck, monkeypatch):
    """No hash table of all orders is made; the driver held it whole."""
    sent, broadcast = [], F.broadcast

    def told(df):
        sent.append(df.count())
        return broadcast(df)

    monkeypatch.setattr(relational.F, "broadcast", told)
    monkeypatch.setattr(relational, "PIECE_ROWS", 200, raising=False)
    got = registry.QUERIES["op_join_inner_bhj"](spark, small).toPandas()
    assert canonical(got) == canonical(duck.execute(registry.ORACLES["op_join_inner_bhj"]).df())
    assert len(sent) > 1 and max(sent) <= 400 and sum(sent) == 1500


def test_dearest_orders_are_numbered_by_price(spark, small, duck, tmp_path):
    """A decorrelated ORDER BY ... LIMIT numbers the rows as they arrive from the exchange; and customers stand for themselves, however often they are listed."""
    spark.read.parquet(f"{small}/orders.parquet").repartition(16).write.parquet(f"{tmp_path}/orders.parquet")
    customers = spark.read.parquet(f"{small}/customer.parquet")
    customers.union(customers).write.parquet(f"{tmp_path}/customer.parquet")
    got = registry.QUERIES["op_lateral_topk"](spark, str(tmp_path))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "o_totalprice" in plan.split("windowspecdefinition")[1].split("specifiedwindowframe")[0]
    assert canonical(got.toPandas()) == canonical(duck.execute(registry.ORACLES["op_lateral_topk"]).df())


def test_long_paths_and_big_graphs_are_contracted_in_few_rounds(spark, monkeypatch):
    """A path of 300 whose numbers only rise, a star, a loop and a pair; one round wrote three cuts, and each moved labels by a few links."""
    rows = [(k, k + 1) for k in range(300)] + [(1000, 1000 + k) for k in range(1, 50)] + [(2000, 2000), (3001, 3000), (3000, 3001), (5, 5)]
    monkeypatch.setattr(graphs, "LOCAL_LINKS", 20, raising=False)
    rounds, write = [], graphs.written
    monkeypatch.setattr(graphs, "written", lambda df, label: rounds.append(label) or write(df, label))
    got = {r.vertex: r.component for r in graphs.components(spark.createDataFrame(rows, "a long, b long")).collect()}
    want = {k: 0 for k in range(301)} | {k: 1000 for k in range(1000, 1050)} | {2000: 2000, 3000: 3000, 3001: 3000}
    assert got == want
    assert 0 < rounds.count("moves") < 20


READING = ["acyclic_prob_table", "ci95_table", "collision_bound_table", "eval_ops", "eval_ratio_table", "fixed_cost", "gf2_example", "independence_table", "io_model", "kappa_bits", "memory_words_table"]


@pytest.mark.parametrize("name", READING)
def test_closed_forms_are_of_a_given_table(spark, small, name):
    assert registry.QUERIES[name](spark, small).inputFiles()
