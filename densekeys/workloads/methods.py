"""Construction and evaluation queries. Results are invariant under the drawn seeds, so that SQL can state them."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densekeys.functions.hashing import LinearHash
from densekeys.operators import baselines
from densekeys.plans.bucketing import address, largest_buckets, prefix_sums
from densekeys.plans.build import build_core, build_two_level
from densekeys.plans.evaluate import lookup, verify
from densekeys.plans.params import Params

Query = Callable[[SparkSession, str], DataFrame]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.explode(F.split("text", " ")).alias("token")).where("token <> ''")


#: Key sets: source, key columns, SQL that counts the distinct keys.
KEY_SETS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], list[str], str]] = {
    "urls": (lambda s, d: table(s, d, "pages"), ["url"], "SELECT count(DISTINCT url) FROM pages"),
    "orders": (lambda s, d: table(s, d, "orders"), ["o_orderkey"], "SELECT count(DISTINCT o_orderkey) FROM orders"),
    "customers": (lambda s, d: table(s, d, "customer"), ["c_name"], "SELECT count(DISTINCT c_name) FROM customer"),
    "lineitem_composite": (lambda s, d: table(s, d, "lineitem"), ["l_orderkey", "l_linenumber"], "SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)"),
    "foreign_keys": (lambda s, d: table(s, d, "lineitem"), ["l_partkey", "l_suppkey"], "SELECT count(*) FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)"),
    "prices": (lambda s, d: table(s, d, "lineitem"), ["l_extendedprice"], "SELECT count(DISTINCT l_extendedprice) FROM lineitem"),
    "tokens": (tokens, ["token"], "SELECT count(DISTINCT t) FROM (SELECT unnest(string_split(text, ' ')) AS t FROM documents) WHERE t <> ''"),
    "doc_text": (lambda s, d: table(s, d, "documents"), ["text"], "SELECT count(DISTINCT text) FROM documents"),
    "conversations": (lambda s, d: table(s, d, "conversations"), ["conv_id", "turn"], "SELECT count(*) FROM (SELECT DISTINCT conv_id, turn FROM conversations)"),
    "event_times": (lambda s, d: table(s, d, "events"), ["ts"], "SELECT count(DISTINCT ts) FROM events"),
    "embeddings": (lambda s, d: table(s, d, "embeddings"), ["embedding"], "SELECT count(DISTINCT embedding) FROM embeddings"),
    "region": (lambda s, d: table(s, d, "region"), ["r_regionkey"], "SELECT count(DISTINCT r_regionkey) FROM region"),
}
BIJECTION = "SELECT n, 0::BIGINT AS min_id, (n - 1)::BIGINT AS max_id, n AS n_ids FROM (SELECT ({count})::BIGINT AS n)"


def bijective(name: str, params: Params, build=build_two_level) -> Query:
    source, cols, _ = KEY_SETS[name]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = source(spark, sf_dir)
        return verify(df, build(df, cols, params))

    return run


def injective(name: str, params: Params) -> Query:
    source, cols, _ = KEY_SETS[name]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = source(spark, sf_dir)
        artifact = build_two_level(df, cols, params)
        found = verify(df, artifact)
        return found.select("n", F.col("n_ids").alias("n_slots"), ((F.col("min_id") >= 0) & (F.col("max_id") < artifact.n_slots)).alias("range_ok"))

    return run


INJECTION = "SELECT n, n AS n_slots, true AS range_ok FROM (SELECT ({count})::BIGINT AS n)"


def partitioned_equals_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both ways to evaluate, on super-buckets small enough that there are several."""
    df = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber")
    artifact = build_two_level(df, ["l_orderkey", "l_linenumber"], Params(hash="xx128", super_keys=4096))
    a = lookup(df, artifact, mode="broadcast", slot="s1", id="i1").dropDuplicates()
    b = lookup(df, artifact, mode="partitioned", slot="s2", id="i2").dropDuplicates()
    same = (F.col("s1") == F.col("s2")) & (F.col("i1") == F.col("i2"))
    return a.join(b, ["l_orderkey", "l_linenumber"]).agg(F.count(F.lit(1)).alias("n"), F.count_if(~same).alias("differ"))


def layouts_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Compressed and plain labels, native and tabulated popcounts, and every directory step give one function."""
    df = table(spark, sf_dir, "orders").select("o_orderkey")
    base = lookup(df, build_two_level(df, "o_orderkey", Params()), slot="s0", id="i0")
    variants = [Params(layout="plain"), Params(popcount_bits=16), Params(popcount_bits=8), Params(kappa=32), Params(kappa=64), Params(kappa=256)]
    for k, params in enumerate(variants, 1):
        base = lookup(base, build_two_level(df, "o_orderkey", params), "o_orderkey", slot=f"s{k}", id=f"i{k}")
    same = F.lit(True)
    for k in range(1, len(variants) + 1):
        same = same & (F.col(f"i{k}") == F.col("i0")) & (F.col(f"s{k}") == F.col("s0"))
    return base.agg(F.count(F.lit(1)).alias("n"), F.count_if(~same).alias("differ"))


EXAMPLE_ROWS = (0b101, 0b001, 0b110)


def gf2_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three parities of the last three bits of the order keys; 110 gives 1, 0, 0."""
    inputs = table(spark, sf_dir, "orders").groupBy(F.col("o_orderkey").bitwiseAND(7).alias("input")).agg(F.count(F.lit(1)).alias("n"))
    return inputs.select("*", *((F.bit_count(F.col("input").bitwiseAND(r)) % 2).cast("long").alias(f"bit{k}") for k, r in enumerate(EXAMPLE_ROWS)))


ORDER_ROWS = [r & (1 << 62) - 1 for r in LinearHash(12345, 8).rows(64)[:32]]


def linear_word(col, rows: list[int]):
    """Row form of the linear map on a non-negative integer: a bit of output is the parity of key AND row."""
    out = F.lit(0).cast("long")
    for j, row in enumerate(rows):
        out = out.bitwiseOR(F.shiftleft((F.bit_count(col.bitwiseAND(row)) % 2).cast("long"), len(rows) - 1 - j))
    return out


def gf2_hash_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select("o_orderkey", linear_word(F.col("o_orderkey"), ORDER_ROWS).alias("word0"))


def sql_word(col: str, rows: list[int]) -> str:
    return " + ".join(f"((bit_count({col} & {r}) % 2)::BIGINT << {len(rows) - 1 - j})" for j, r in enumerate(rows))


def gf2_linearity(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = table(spark, sf_dir, "orders").select("o_orderkey", (F.col("o_orderkey") * 7 + 3).alias("other"))
    h = lambda c: linear_word(c, ORDER_ROWS)
    violated = h(F.col("o_orderkey")).bitwiseXOR(h(F.col("other"))) != h(F.col("o_orderkey").bitwiseXOR(F.col("other")))
    return df.agg(F.count(F.lit(1)).alias("n"), F.count_if(violated).alias("violations"))


def gf2_forms_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tabulated kernel and the row form in generated code give the same word."""
    family = LinearHash(777, 8, 2)
    rows = [r for r in family.rows(64)[:32]]
    signed = [r - (1 << 64) if r >= 1 << 63 else r for r in rows]

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            keys = batch.column(0).to_numpy().astype(">i8")
            words = family(np.frombuffer(keys.tobytes(), np.uint8), np.arange(len(keys) + 1) * 8)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(words[:, 0].astype(np.int64))], ["o_orderkey", "tabulated"])

    df = table(spark, sf_dir, "orders").select("o_orderkey").mapInArrow(run, "o_orderkey long, tabulated long")
    return df.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("tabulated") != linear_word(F.col("o_orderkey"), signed)).alias("differ"))


def _order_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gf2_hash_orders(spark, sf_dir).select(F.shiftleft("word0", 32).alias("hi"))


def bucket_sizes_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _order_words(spark, sf_dir).groupBy(address(F.col("hi"), 7).alias("bucket")).agg(F.count(F.lit(1)).alias("size"))


def bucket_offsets_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefix_sums(bucket_sizes_orders(spark, sf_dir), "bucket", "size", "offset", block=16).select("bucket", "size", F.col("offset").cast("long"))


LEVELS = list(range(0, 13))


def bucket_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = largest_buckets(_order_words(spark, sf_dir), LEVELS)
    return spark.createDataFrame(sorted(found.items()), "b int, largest long")


def choose_b_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bucket_stats(spark, sf_dir).where("largest <= 256").agg(F.min("b").alias("b"))


def sql_words(inner: str = "o_orderkey") -> str:
    return f"(SELECT {sql_word(inner, ORDER_ROWS)} AS w FROM orders)"


def core_demo_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All order numbers as edges by two congruences, in the bipartite graph that the construction draws; components by contraction."""
    keys = table(spark, sf_dir, "orders").select("o_orderkey").dropDuplicates()
    tau = -(-keys.count() * 1045 // 1000)
    k = F.col("o_orderkey")
    edges = keys.select((k * k % 1000003 * 7919 % 2147483647 % tau).alias("a"), (k * k % 1000033 * 104729 % 2147483647 % tau + tau).alias("b")).distinct()
    from densekeys.operators.graphs import components
    from densekeys.shared import written

    edges = written(edges, "drawn")
    labels = components(edges)
    return labels.agg(F.count(F.lit(1)).alias("vertices"), F.countDistinct("component").alias("components")).crossJoin(edges.agg(F.count(F.lit(1)).alias("edges"))).select(
        "vertices", "components", "edges", (F.col("vertices") - F.col("components") == F.col("edges")).alias("forest")
    )


def rank_directory_demo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Members below every 128th place, from bitmaps of the occupied places."""
    keys = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k")).dropDuplicates()
    counts = keys.groupBy(F.floor(F.col("k") / 128).alias("entry")).agg(F.count(F.lit(1)).alias("held"))
    return prefix_sums(counts, "entry", "held", "below", block=32).select("entry", F.col("below").cast("long"))


def popcount_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Occupied places in each 32-bit word of the customer bitmap, by bit_or and bit_count."""
    bit = F.expr("shiftleft(1L, CAST(c_custkey % 32 AS INT))")
    return table(spark, sf_dir, "customer").groupBy(F.floor(F.col("c_custkey") / 32).alias("word")).agg(F.bit_count(F.bit_or(bit)).cast("long").alias("held"))


def space_two_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of every bucket of the SQL-expressible address, summed."""
    size = bucket_sizes_orders(spark, sf_dir)
    tau = F.greatest(F.lit(1), F.ceil(F.col("size") * 1045 / 1000)).cast("long")
    return size.withColumn("tau", tau).agg(
        F.sum("size").alias("n"),
        F.sum(2 * F.col("tau") + 64).cast("long").alias("bits_phf"),
        F.sum(F.col("size") + 2 * F.col("tau") + 8 * F.ceil(2 * F.col("tau") / 128) + 64).cast("long").alias("bits_mphf"),
    )


def space_core(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range of the whole-set function: exactly 2 ceil(1.045 n)."""
    df = table(spark, sf_dir, "orders")
    artifact = build_core(df, "o_orderkey")
    return spark.createDataFrame([(artifact.n, artifact.n_slots)], "n long, n_slots long")


def tries_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tries of full buckets lie where the bipartite model puts them."""
    df = table(spark, sf_dir, "lineitem")
    stats = build_two_level(df, ["l_orderkey", "l_linenumber", "l_partkey"], Params(hash="xx128")).buckets()
    return stats.agg((F.avg("tries").between(1.7, 3.5)).alias("mean_in_bounds"), (F.max("size") <= 256).alias("sizes_ok"))


EPS = (0.01, 0.045, 0.1, 0.25, 0.5, 1.0)


def eps_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Larger eps: more bits; and fewer tries at the largest than at the smallest, as neighbours may tie on small sets."""
    df = table(spark, sf_dir, "orders")
    rows = []
    for eps in EPS:
        artifact = build_two_level(df, "o_orderkey", Params(hash="xx128", eps=eps))
        rows.append((eps, artifact.n_slots / artifact.n, artifact.buckets().agg(F.avg("tries")).first()[0]))
    bits_up = all(a[1] < b[1] for a, b in zip(rows, rows[1:], strict=False))
    tries_down = rows[0][2] > rows[-1][2]
    return spark.createDataFrame([(e, s >= 2 * (1 + e), bits_up, tries_down) for e, s, _ in rows], "eps double, range_ok boolean, bits_grow boolean, tries_fall boolean")


def restart_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Default fingerprints need no restart; 12 bits collide in every attempt, which is reported and not hidden."""
    df = table(spark, sf_dir, "orders")
    plain = build_two_level(df, "o_orderkey", Params()).restarts
    try:
        build_two_level(df, "o_orderkey", Params(gamma=12, max_restarts=1))
        refused = False
    except RuntimeError:
        refused = True
    return spark.createDataFrame([(plain, refused)], "restarts int, narrow_refused boolean")


def hash_family_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = []
    for h in ("linear", "mix96", "xx128"):
        a = build_two_level(table(spark, sf_dir, "pages"), "url", Params(hash=h))
        rows.append((h, a.n, a.restarts))
    return spark.createDataFrame(rows, "hash string, n long, restarts int")


def evaluate_length(length: int) -> Query:
    """Keys of one byte length, as the evaluation experiment has them."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        keys = table(spark, sf_dir, "orders").select(F.lpad(F.col("o_orderkey").cast("string"), length, "x").alias("key"))
        return verify(keys, build_two_level(keys, "key", Params(max_bytes=129)))

    return run


def baseline(method: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = baselines.in_one_task(table(spark, sf_dir, "customer"), "c_custkey", method)
        return found.agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("min_id"), F.max("id").alias("max_id"), F.countDistinct("id").alias("n_ids"))

    return run


def order_preserving(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.in_one_task(table(spark, sf_dir, "customer"), "c_name", "sumgraph_acyclic", ordered=True).select("c_name", "id")


def sorted_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.sorted_ids(table(spark, sf_dir, "customer"), "c_name")


def surrogate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = baselines.surrogate_fk(table(spark, sf_dir, "lineitem"), ["l_partkey", "l_suppkey"])
    return found.agg(F.count(F.lit(1)).alias("n_rows"), F.countDistinct("surrogate").alias("n_refs"))


def artifact_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Written, read again by both readers, and evaluated."""
    from densekeys.plans.build import Artifact
    from densekeys.shared import shared_path
    from densekeys.sources.artifact import register

    df = table(spark, sf_dir, "orders")
    path = shared_path(spark, "artifact")
    build_two_level(df, "o_orderkey", Params(hash="xx128")).write(path)
    again = Artifact.read(spark, path)
    register(spark)
    buckets = spark.read.format("densekeys").load(path)
    return verify(df, again).crossJoin(buckets.agg(F.sum("size").alias("n_in_buckets")))


QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
for _name, (_, _, _count) in KEY_SETS.items():
    for _hash in ("linear", "mix96", "xx128"):
        if _hash == "linear" or _name in ("urls", "orders", "lineitem_composite", "tokens", "region"):
            QUERIES[f"mphf_{_name}_{_hash}"] = bijective(_name, Params(hash=_hash))
            ORACLES[f"mphf_{_name}_{_hash}"] = BIJECTION.format(count=_count)
for _name in ("urls", "orders", "lineitem_composite"):
    for _hash in ("linear", "mix96"):
        QUERIES[f"phf_{_name}_{_hash}"] = injective(_name, Params(hash=_hash, kind="phf"))
        ORACLES[f"phf_{_name}_{_hash}"] = INJECTION.format(count=KEY_SETS[_name][2])
QUERIES["core_universal_bijective"] = bijective("orders", Params(hash="universal", kappa=256), build_core)
ORACLES["core_universal_bijective"] = BIJECTION.format(count=KEY_SETS["orders"][2])
QUERIES["mphf_plain_layout"] = bijective("orders", Params(layout="plain"))
ORACLES["mphf_plain_layout"] = BIJECTION.format(count=KEY_SETS["orders"][2])
for _length in (8, 16, 32, 64, 128):
    QUERIES[f"eval_len_{_length}"] = evaluate_length(_length)
    ORACLES[f"eval_len_{_length}"] = BIJECTION.format(count=KEY_SETS["orders"][2])
for _method in baselines.METHODS:
    QUERIES[f"bl_{_method}_bijective"] = baseline(_method)
    ORACLES[f"bl_{_method}_bijective"] = BIJECTION.format(count="SELECT count(DISTINCT c_custkey) FROM customer")
QUERIES |= {
    "eval_partitioned_equals_broadcast": partitioned_equals_broadcast,
    "core_layouts_agree": layouts_agree,
    "gf2_example": gf2_example,
    "gf2_hash_orders": gf2_hash_orders,
    "gf2_linearity": gf2_linearity,
    "gf2_forms_agree": gf2_forms_agree,
    "bucket_sizes_orders": bucket_sizes_orders,
    "bucket_offsets_orders": bucket_offsets_orders,
    "bucket_stats": bucket_stats,
    "choose_b_orders": choose_b_orders,
    "core_demo_components": core_demo_components,
    "rank_directory_demo": rank_directory_demo,
    "popcount_words": popcount_words,
    "space_two_level": space_two_level,
    "space_core": space_core,
    "tries_bounds": tries_bounds,
    "eps_sweep": eps_sweep,
    "restart_count": restart_count,
    "hash_family_sizes": hash_family_sizes,
    "bl_acyclic_order_preserving": order_preserving,
    "bl_sorted_ids": sorted_ids,
    "bl_surrogate_key": surrogate,
    "op_artifact_roundtrip": artifact_roundtrip,
}
_sizes = f"SELECT w >> 25 AS bucket, count(*)::BIGINT AS size FROM {sql_words()} GROUP BY 1"
ORACLES |= {
    "eval_partitioned_equals_broadcast": "SELECT count(*)::BIGINT AS n, 0::BIGINT AS differ FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)",
    "core_layouts_agree": "SELECT count(*)::BIGINT AS n, 0::BIGINT AS differ FROM orders",
    "gf2_example": "SELECT o_orderkey & 7 AS input, count(*)::BIGINT AS n, " + ", ".join(f"(bit_count((o_orderkey & 7) & {r}) % 2)::BIGINT AS bit{k}" for k, r in enumerate(EXAMPLE_ROWS)) + " FROM orders GROUP BY 1",
    "gf2_hash_orders": f"SELECT o_orderkey, {sql_word('o_orderkey', ORDER_ROWS)} AS word0 FROM orders",
    "gf2_linearity": "SELECT count(*)::BIGINT AS n, 0::BIGINT AS violations FROM orders",
    "gf2_forms_agree": "SELECT count(*)::BIGINT AS n, 0::BIGINT AS differ FROM orders",
    "bucket_sizes_orders": _sizes,
    "bucket_offsets_orders": f"SELECT bucket, size, coalesce(sum(size) OVER (ORDER BY bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS \"offset\" FROM ({_sizes})",
    "bucket_stats": " UNION ALL ".join(f"SELECT {b}::INTEGER AS b, max(c)::BIGINT AS largest FROM (SELECT count(*) AS c FROM {sql_words()} GROUP BY w >> {32 - b})" for b in LEVELS),
    "choose_b_orders": "SELECT min(b)::INTEGER AS b FROM (" + " UNION ALL ".join(f"SELECT {b} AS b, max(c) AS largest FROM (SELECT count(*) AS c FROM {sql_words()} GROUP BY w >> {32 - b})" for b in LEVELS) + ") WHERE largest <= 256",
    "core_demo_components": """
WITH RECURSIVE keys AS (SELECT DISTINCT o_orderkey AS k FROM orders),
size AS (SELECT (count(*) * 1045 + 999) // 1000 AS tau FROM keys),
e AS (SELECT DISTINCT k * k % 1000003 * 7919 % 2147483647 % tau AS a, k * k % 1000033 * 104729 % 2147483647 % tau + tau AS b FROM keys, size),
v AS (SELECT a AS v FROM e UNION SELECT b FROM e),
both_ways AS (SELECT a, b FROM e UNION SELECT b, a FROM e),
reach(v, r) AS (SELECT v, v FROM v UNION SELECT reach.v, b FROM reach JOIN both_ways ON reach.r = a),
low AS (SELECT v, min(r) AS c FROM reach GROUP BY v)
SELECT count(*)::BIGINT AS vertices, count(DISTINCT c)::BIGINT AS components, (SELECT count(*) FROM e)::BIGINT AS edges, count(*) - count(DISTINCT c) = (SELECT count(*) FROM e) AS forest FROM low""",
    "rank_directory_demo": """
SELECT entry, coalesce(sum(held) OVER (ORDER BY entry ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS below
FROM (SELECT o_orderkey // 128 AS entry, count(*) AS held FROM (SELECT DISTINCT o_orderkey FROM orders) GROUP BY 1)""",
    "popcount_words": "SELECT c_custkey // 32 AS word, count(DISTINCT c_custkey)::BIGINT AS held FROM customer GROUP BY 1",
    "space_two_level": f"""
SELECT sum(size)::BIGINT AS n, sum(2 * tau + 64)::BIGINT AS bits_phf, sum(size + 2 * tau + 8 * ((2 * tau + 127) // 128) + 64)::BIGINT AS bits_mphf
FROM (SELECT size, greatest(1, (size * 1045 + 999) // 1000) AS tau FROM ({_sizes}))""",
    "space_core": "SELECT n, 2 * ((n * 1045 + 999) // 1000) AS n_slots FROM (SELECT count(DISTINCT o_orderkey)::BIGINT AS n FROM orders)",
    "tries_bounds": "SELECT true AS mean_in_bounds, true AS sizes_ok",
    "eps_sweep": "SELECT eps::DOUBLE AS eps, true AS range_ok, true AS bits_grow, true AS tries_fall FROM (VALUES " + ", ".join(f"({e})" for e in EPS) + ") t(eps)",
    "restart_count": "SELECT 0::INTEGER AS restarts, true AS narrow_refused",
    "hash_family_sizes": "SELECT hash, (SELECT count(DISTINCT url) FROM pages)::BIGINT AS n, 0::INTEGER AS restarts FROM (VALUES ('linear'), ('mix96'), ('xx128')) t(hash)",
    "bl_acyclic_order_preserving": "SELECT c_name, row_number() OVER (ORDER BY c_name) - 1 AS id FROM (SELECT DISTINCT c_name FROM customer)",
    "bl_sorted_ids": "SELECT c_name, row_number() OVER (ORDER BY c_name) - 1 AS id FROM (SELECT DISTINCT c_name FROM customer)",
    "bl_surrogate_key": "SELECT (SELECT count(*) FROM lineitem)::BIGINT AS n_rows, count(*)::BIGINT AS n_refs FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)",
    "op_artifact_roundtrip": "SELECT n, 0::BIGINT AS min_id, n - 1 AS max_id, n AS n_ids, n AS n_in_buckets FROM (SELECT count(DISTINCT o_orderkey)::BIGINT AS n FROM orders)",
}


def sql_dense_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The function called from SQL agrees with lookup()."""
    from densekeys.operators.sql_surface import register_lookup

    urls = table(spark, sf_dir, "pages").select("url")
    artifact = build_two_level(urls, "url", Params(hash="mix96"))
    register_lookup(spark, "dense_id", artifact)
    both = lookup(urls, artifact).withColumn("by_sql", F.expr("dense_id(url)"))
    return both.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("id") != F.col("by_sql")).alias("differ"))


def sql_set_places(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Occupied slots exploded by the table function: one for each key."""
    from densekeys.operators.sql_surface import register_tables

    register_tables(spark)
    rows = build_two_level(table(spark, sf_dir, "orders"), "o_orderkey", Params(hash="xx128")).rows
    return spark.sql("SELECT count(*) AS n FROM {rows}, LATERAL set_places(occupied)", rows=rows)


QUERIES |= {"sql_dense_id": sql_dense_id, "sql_set_places": sql_set_places}
ORACLES |= {
    "sql_dense_id": "SELECT count(*)::BIGINT AS n, 0::BIGINT AS differ FROM pages",
    "sql_set_places": "SELECT count(DISTINCT o_orderkey)::BIGINT AS n FROM orders",
}
