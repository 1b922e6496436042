"""Application queries: filters, joins, references, identifiers, graphs, grouping, mining."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densekeys.operators import apps, filters, graphs
from densekeys.workloads.methods import table


def membership(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every member passes; the share of others that pass is near 2**-8. Members: even order keys."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey")
    members = filters.build_filter(orders.where("o_orderkey % 2 = 0"), "o_orderkey", 8)
    probed = filters.might_contain(orders, members).withColumn("member", F.col("o_orderkey") % 2 == 0)
    return filters.filter_accuracy(probed, "member").select("false_negatives", "non_members", (F.col("rate") <= 4 / 256).alias("rate_ok"))


def bloom(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey")
    built = filters.build_bloom(orders.where("o_orderkey % 2 = 0"), ["o_orderkey"], 1 / 256)
    probed = filters.bloom_contains(orders, ["o_orderkey"], built).withColumn("member", F.col("o_orderkey") % 2 == 0)
    return filters.filter_accuracy(probed, "member").select("false_negatives", "non_members", (F.col("rate") <= 4 / 256).alias("rate_ok"))


def semi_reduce(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "value")
    rich = table(spark, sf_dir, "customer").where("c_acctbal > 5000").select("c_custkey")
    return filters.semi_reduce(events, rich, "user_id", "c_custkey")


def _join(how: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        fact = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity")
        dim = table(spark, sf_dir, "orders").where("o_totalprice > 100000").select("o_orderkey", "o_custkey").dropDuplicates(["o_orderkey"])
        joined = apps.dense_join(fact, dim, ("l_orderkey", "o_orderkey"), how)
        extra = [F.count("o_orderkey").alias("n_matched"), F.sum("o_custkey").alias("cust_sum")] if how in ("inner", "left") else []
        return joined.agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"), *extra)

    return run


def fk_compress(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey")
    found = apps.compress_fk(lines, ["l_partkey", "l_suppkey"])
    return found.agg(F.count(F.lit(1)).alias("n_rows"), F.countDistinct("ref").alias("n_refs"), (F.max("ref") + 1).alias("range"), F.countDistinct("l_partkey", "l_suppkey", "ref").alias("n_pairs"))


def dense_groupby(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem")
    return apps.dense_groupby(lines, ["l_partkey", "l_suppkey"], [F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("revenue")])


def assign_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids decode to the values they came from."""
    pages = table(spark, sf_dir, "pages").select("url")
    ids = apps.assign_ids(pages, "url")
    back = pages.join(ids, "url").join(ids.select("id", F.col("url").alias("decoded")), "id")
    return back.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("url") != F.col("decoded")).alias("differ"))


def graph_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges, labels = apps.label_graph(apps.page_links(table(spark, sf_dir, "pages")))
    return edges.agg(F.count(F.lit(1)).alias("links"), F.countDistinct("src").alias("sources"), F.countDistinct("dst").alias("targets")).crossJoin(labels.agg(F.count(F.lit(1)).alias("vertices"), F.countDistinct("vertex").alias("labels")))


def pagerank(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges, labels = apps.label_graph(apps.page_links(table(spark, sf_dir, "pages")))
    return apps.pagerank(edges, labels).join(labels, "vertex").select("url", F.round("rank", 9).alias("rank"))


def adjacency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gaps add up to the last neighbour, and neighbours number the distinct links."""
    edges, labels = apps.label_graph(apps.page_links(table(spark, sf_dir, "pages")))
    gaps = apps.adjacency_gaps(edges).join(labels, F.col("src") == F.col("vertex"))
    positive = F.forall(F.slice("gaps", 2, 1_000_000), lambda g: g > 0)
    return gaps.select("url", F.col("degree").cast("long").alias("degree"), positive.alias("gaps_positive"))


def association_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of parts that at least two orders hold together."""
    return apps.pair_support(table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", 2)


def core_df_bijective(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole-set construction by distributed peeling: distinct slots for all keys, from the first seed whose graph is a forest."""
    keys = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("key")).dropDuplicates()
    n = keys.count()
    tau = -(-1045 * n // 1000)
    for seed in range(40):
        edges = keys.select("key", F.pmod(F.xxhash64("key", F.lit(2 * seed)), F.lit(tau)).alias("a"), (F.pmod(F.xxhash64("key", F.lit(2 * seed + 1)), F.lit(tau)) + tau).alias("b"))
        slots = graphs.core_slots(edges, tau)
        if slots is not None:
            return slots.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("slot").alias("n_slots"))
    raise RuntimeError("no forest in 40 seeds")


QUERIES = {
    "app_membership": membership,
    "bl_bloom_membership": bloom,
    "app_semi_reduce": semi_reduce,
    **{f"app_dense_join_{how}": _join(how) for how in ("inner", "left", "left_semi", "left_anti")},
    "app_fk_compress": fk_compress,
    "app_dense_groupby": dense_groupby,
    "app_assign_ids": assign_ids,
    "app_graph_labels": graph_labels,
    "app_pagerank": pagerank,
    "app_adjacency_gaps": adjacency,
    "app_association_pairs": association_pairs,
    "core_df_bijective": core_df_bijective,
}
_DIM = "(SELECT DISTINCT o_orderkey, o_custkey FROM orders WHERE o_totalprice > 100000)"
_LINKS = "(SELECT url AS source, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS target FROM pages)"
_member = "SELECT 0::BIGINT AS false_negatives, count(*)::BIGINT AS non_members, true AS rate_ok FROM orders WHERE o_orderkey % 2 <> 0"
_rank_steps = "\n".join(
    f"""r{k} AS (SELECT v.url, 0.15 / (SELECT n FROM size) + 0.85 * (coalesce(g.given, 0) + (SELECT coalesce(sum(r{k - 1}.rank), 0) FROM r{k - 1} LEFT JOIN deg ON r{k - 1}.url = deg.source WHERE degree IS NULL) / (SELECT n FROM size)) AS rank
  FROM v LEFT JOIN (SELECT target, sum(r{k - 1}.rank / degree) AS given FROM e JOIN r{k - 1} ON e.source = r{k - 1}.url JOIN deg ON deg.source = e.source GROUP BY target) g ON v.url = g.target){',' if k < 3 else ''}"""
    for k in (1, 2, 3)
)
ORACLES = {
    "app_membership": _member,
    "bl_bloom_membership": _member,
    "app_semi_reduce": "SELECT event_id, user_id, value FROM events WHERE user_id IN (SELECT c_custkey FROM customer WHERE c_acctbal > 5000)",
    "app_dense_join_inner": f"SELECT count(*)::BIGINT AS n, sum(l_quantity) AS quantity, count(o_orderkey)::BIGINT AS n_matched, sum(o_custkey)::BIGINT AS cust_sum FROM lineitem JOIN {_DIM} ON l_orderkey = o_orderkey",
    "app_dense_join_left": f"SELECT count(*)::BIGINT AS n, sum(l_quantity) AS quantity, count(o_orderkey)::BIGINT AS n_matched, sum(o_custkey)::BIGINT AS cust_sum FROM lineitem LEFT JOIN {_DIM} ON l_orderkey = o_orderkey",
    "app_dense_join_left_semi": f"SELECT count(*)::BIGINT AS n, sum(l_quantity) AS quantity FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM {_DIM})",
    "app_dense_join_left_anti": f"SELECT count(*)::BIGINT AS n, sum(l_quantity) AS quantity FROM lineitem WHERE l_orderkey NOT IN (SELECT o_orderkey FROM {_DIM})",
    "app_fk_compress": "SELECT (SELECT count(*) FROM lineitem)::BIGINT AS n_rows, n AS n_refs, n AS range, n AS n_pairs FROM (SELECT count(*)::BIGINT AS n FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem))",
    "app_dense_groupby": "SELECT l_partkey, l_suppkey, count(*)::BIGINT AS n, round(sum(l_extendedprice), 2) AS revenue FROM lineitem GROUP BY 1, 2",
    "app_assign_ids": "SELECT count(*)::BIGINT AS n, 0::BIGINT AS differ FROM pages",
    "app_graph_labels": f"SELECT count(*)::BIGINT AS links, count(DISTINCT source)::BIGINT AS sources, count(DISTINCT target)::BIGINT AS targets, (SELECT count(*) FROM (SELECT source FROM {_LINKS} UNION SELECT target FROM {_LINKS}))::BIGINT AS vertices, (SELECT count(*) FROM (SELECT source FROM {_LINKS} UNION SELECT target FROM {_LINKS}))::BIGINT AS labels FROM {_LINKS}",
    "app_pagerank": f"""WITH e AS (SELECT DISTINCT source, target FROM {_LINKS}), v AS (SELECT source AS url FROM e UNION SELECT target FROM e), size AS (SELECT count(*)::DOUBLE AS n FROM v),
deg AS (SELECT source, count(*) AS degree FROM e GROUP BY source), r0 AS (SELECT url, 1.0 / (SELECT n FROM size) AS rank FROM v),
{_rank_steps}
SELECT url, round(rank, 9) AS rank FROM r3""",
    "app_adjacency_gaps": f"SELECT source AS url, count(DISTINCT target)::BIGINT AS degree, true AS gaps_positive FROM {_LINKS} GROUP BY source",
    "app_association_pairs": """WITH i AS (SELECT DISTINCT l_orderkey, l_partkey AS item FROM lineitem)
SELECT a.item AS first, b.item AS second, count(*)::BIGINT AS support FROM i a JOIN i b ON a.l_orderkey = b.l_orderkey AND a.item < b.item GROUP BY 1, 2 HAVING count(*) >= 2""",
    "core_df_bijective": "SELECT count(DISTINCT c_custkey)::BIGINT AS n, count(DISTINCT c_custkey)::BIGINT AS n_slots FROM customer",
}
