"""The relational surface around the methods, on the given tables: each query with its SQL.

Most entries are one SQL text that both engines run; where the dialects or the API differ, both are given."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from densekeys.shared import shared_path
from densekeys.workloads.methods import table

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def sql_query(text: str, *names: str) -> Callable[[SparkSession, str], DataFrame]:
    """Run on the tables given by name in the call, not on shared views, so that queries can't disturb each other."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(text, **{n: table(spark, sf_dir, n) for n in names})

    return run


def _both(text: str) -> tuple[Callable, str]:
    names = [n for n in TABLES if f"{{{n}}}" in text]
    return sql_query(text, *names), text.format(**{n: n for n in names})


SQL: dict[str, str] = {
    "op_scan_prune": "SELECT o_orderkey, o_totalprice FROM {orders} WHERE o_orderdate >= TIMESTAMP '1995-01-01 00:00:00'",
    "op_project_expr": "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM {lineitem}",
    "op_cast": "SELECT o_orderkey, CAST(o_orderkey AS VARCHAR(20)) AS key_text, CAST(CAST(o_totalprice AS DECIMAL(18, 2)) AS DOUBLE) AS price FROM {orders}",
    "op_case": "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS class, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS segment FROM {customer}",
    "op_filter_cmp": "SELECT p_partkey FROM {part} WHERE p_size > 25 AND p_retailprice <= 1500",
    "op_filter_between": "SELECT l_orderkey, l_linenumber FROM {lineitem} WHERE l_quantity BETWEEN 10 AND 20",
    "op_filter_in": "SELECT c_custkey FROM {customer} WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')",
    "op_filter_like": "SELECT url FROM {pages} WHERE url LIKE 'https://%example%'",
    "op_filter_null": "SELECT count(*) AS n FROM {documents} WHERE text IS NOT NULL AND lang IS NOT NULL",
    "op_filter_bool": "SELECT o_orderkey FROM {orders} WHERE NOT (o_orderstatus = 'F' OR o_totalprice < 100000)",
    "op_distinct": "SELECT DISTINCT l_orderkey, l_linenumber FROM {lineitem}",
    "op_join_left": "SELECT c_custkey, o_orderkey FROM {customer} LEFT JOIN {orders} ON c_custkey = o_custkey",
    "op_join_right": "SELECT c_custkey, o_orderkey FROM {orders} RIGHT JOIN {customer} ON c_custkey = o_custkey",
    "op_join_full": "SELECT c_custkey, o_orderkey FROM {customer} FULL OUTER JOIN {orders} ON c_custkey = o_custkey AND o_totalprice > 200000",
    "op_join_semi": "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)",
    "op_join_anti": "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)",
    "op_join_cross": "SELECT r_name, n_name FROM {region} CROSS JOIN {nation}",
    "op_join_theta": "SELECT a.n_name AS first, b.n_name AS second FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
    "op_join_nullsafe": "SELECT count(*) AS n FROM {customer} JOIN {nation} ON nullif(c_nationkey, 3) IS NOT DISTINCT FROM nullif(n_nationkey, 3)",
    "op_star_revenue": "SELECT r_name, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {customer} ON o_custkey = c_custkey JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name",
    "op_exists": "SELECT s_suppkey FROM {supplier} WHERE EXISTS (SELECT 1 FROM {lineitem} WHERE l_suppkey = s_suppkey AND l_quantity > 45)",
    "op_scalar_subquery": "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM {orders})",
    "op_agg_global": "SELECT count(*) AS n, min(l_orderkey) AS low, max(l_orderkey) AS high, round(avg(l_quantity), 6) AS mean, CAST(sum(l_linenumber) AS BIGINT) AS total FROM {lineitem}",
    "op_agg_grouped": "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount FROM {lineitem} GROUP BY l_returnflag, l_linestatus",
    "op_agg_string_max": "SELECT c_nationkey, max(c_name) AS last, min(c_mktsegment) AS first FROM {customer} GROUP BY c_nationkey",
    "op_agg_distinct": "SELECT l_returnflag, count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts, CAST(sum(DISTINCT l_linenumber) AS BIGINT) AS numbers FROM {lineitem} GROUP BY l_returnflag",
    "op_agg_having": "SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey HAVING count(*) >= 12",
    "op_agg_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "op_agg_cube": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {orders} GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "op_agg_gsets": "SELECT o_orderstatus, o_orderpriority, grouping(o_orderstatus) AS g, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())",
    "op_agg_stats": "SELECT round(stddev_samp(l_quantity), 6) AS sd, round(var_samp(l_quantity), 6) AS var, round(corr(l_quantity, l_extendedprice), 6) AS r, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM {lineitem}",
    "op_agg_filter": "SELECT l_returnflag, count(*) FILTER (WHERE l_quantity > 25) AS large FROM {lineitem} GROUP BY l_returnflag",
    "op_agg_max_by": "SELECT o_orderstatus, max_by(o_orderkey, o_totalprice * 1000000 + o_orderkey) AS dearest FROM {orders} GROUP BY o_orderstatus",
    "op_agg_bits": "SELECT l_returnflag, bit_xor(l_orderkey) AS x, bit_or(l_partkey) AS o, bit_and(l_suppkey) AS a FROM {lineitem} GROUP BY l_returnflag",
    "op_win_prefix_sum": "SELECT o_orderkey, o_custkey, CAST(coalesce(sum(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before FROM {orders}",
    "op_win_row_number": "SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM {orders}",
    "op_win_rank_dense": "SELECT p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS d FROM {part}",
    "op_win_lag_lead": "SELECT o_orderkey, lag(o_orderkey, 1) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS prev, lead(o_orderkey, 1) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS next FROM {orders}",
    "op_win_moving_avg": "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean FROM {events}",
    "op_win_ntile": "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS q FROM {customer}",
    "op_win_first_last": "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "op_win_pct": "SELECT p_partkey, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_retailprice), 9) AS p, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_retailprice), 9) AS c FROM {part}",
    "op_topk": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "op_topk_per_group": "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM {orders}) t WHERE k <= 2",
    "op_limit_offset": "SELECT c_custkey FROM {customer} ORDER BY c_custkey LIMIT 10 OFFSET 5",
    "op_sort_multi": "SELECT s_suppkey, s_nationkey FROM {supplier} ORDER BY s_nationkey DESC, s_suppkey",
    "op_sort_nulls": "SELECT c_custkey, nullif(c_nationkey, 5) AS k FROM {customer} ORDER BY k DESC NULLS LAST, c_custkey",
    "op_union_all": "SELECT c_nationkey AS k FROM {customer} UNION ALL SELECT s_nationkey FROM {supplier}",
    "op_union": "SELECT c_nationkey AS k FROM {customer} UNION SELECT s_nationkey FROM {supplier}",
    "op_intersect": "SELECT l_suppkey AS k FROM {lineitem} INTERSECT SELECT s_suppkey FROM {supplier}",
    "op_intersect_all": "SELECT c_nationkey AS k FROM {customer} INTERSECT ALL SELECT s_nationkey FROM {supplier}",
    "op_except": "SELECT c_custkey AS k FROM {customer} EXCEPT SELECT o_custkey FROM {orders}",
    "op_except_all": "SELECT c_nationkey AS k FROM {customer} EXCEPT ALL SELECT s_nationkey FROM {supplier}",
    "op_fn_string": "SELECT p_partkey, length(p_name) AS n, upper(p_name) AS u, lower(p_brand) AS l, substr(p_name, 2, 4) AS s, concat(p_brand, '-', p_type) AS c, lpad(p_brand, 12, '*') AS lp, rpad(p_brand, 12, '*') AS rp, trim(concat(' ', p_brand, ' ')) AS t, replace(p_name, 'a', 'b') AS r, reverse(p_brand) AS rev FROM {part}",
    "op_fn_math": "SELECT l_orderkey, l_linenumber, abs(l_discount - 0.05) AS a, CAST(ceil(l_quantity / 7) AS BIGINT) AS c, CAST(floor(l_quantity / 7) AS BIGINT) AS f, round(sqrt(l_quantity), 9) AS s, round(ln(l_quantity), 9) AS l, greatest(l_tax, l_discount) AS g, least(l_tax, l_discount) AS m, round(power(l_tax, 2), 9) AS p FROM {lineitem}",
    "op_fn_hash": "SELECT doc_id, md5(text) AS m FROM {documents}",
    "op_fn_conditional": "SELECT c_custkey, coalesce(nullif(c_nationkey, 1), -1) AS n, CASE c_mktsegment WHEN 'BUILDING' THEN 1 ELSE 0 END AS b FROM {customer}",
    "op_cte": "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS total FROM {orders} GROUP BY o_custkey) SELECT c_custkey, round(total, 2) AS total FROM big JOIN {customer} ON o_custkey = c_custkey WHERE total > 500000",
}
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
for _name, _text in SQL.items():
    QUERIES[_name], ORACLES[_name] = _both(_text)


def _inner(strategy: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity")
        orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
        return lines.join(orders.hint(strategy), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))

    return run


#: Rows whose hash table is sent whole; a larger side is sent in pieces.
PIECE_ROWS = 1 << 20


def broadcast_pieces(left: DataFrame, right: DataFrame, on: tuple[str, str], each: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """`each` of the broadcast hash join. A right side above PIECE_ROWS is sent piece after piece: both sides are written
    once by a hash of their keys, of one type, every piece meets its own rows only, and what `each` makes of the pieces is written and read as one."""
    spark = left.sparkSession
    joined = lambda a, b: each(a.join(F.broadcast(b), F.col(on[0]) == F.col(on[1])))
    pieces = -(-right.count() // PIECE_ROWS)
    if pieces <= 1:
        return joined(left, right)
    if left.schema[on[0]].dataType != right.schema[on[1]].dataType:
        raise ValueError("keys of two types do not hash alike")

    def dealt(side: DataFrame, key: str) -> list[DataFrame]:
        path = shared_path(spark, "side")
        side = side.withColumn("_piece", F.pmod(F.xxhash64(key), F.lit(pieces)).cast("int"))
        side.write.partitionBy("_piece").parquet(path)
        kept = spark.read.schema(side.schema).parquet(path)
        return [kept.where(F.col("_piece") == k).drop("_piece") for k in range(pieces)]

    path, schema = shared_path(spark, "joined"), None
    for a, b in zip(dealt(left, on[0]), dealt(right, on[1]), strict=True):
        part = joined(a, b)
        part.write.mode("append").parquet(path)
        schema = part.schema
    return spark.read.schema(schema).parquet(path)


def op_join_inner_bhj(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    found = broadcast_pieces(lines, orders, ("l_orderkey", "o_orderkey"), lambda df: df.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity")))
    return found.groupBy("o_custkey").agg(F.sum("n").alias("n"), F.sum("quantity").alias("quantity"))


QUERIES["op_join_inner_bhj"] = op_join_inner_bhj
for _short, _hint in (("shj", "shuffle_hash"), ("smj", "merge")):
    QUERIES[f"op_join_inner_{_short}"] = _inner(_hint)
for _short in ("bhj", "shj", "smj"):
    ORACLES[f"op_join_inner_{_short}"] = "SELECT o_custkey, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey"


def range_join(points: DataFrame, intervals: DataFrame, value: str, low: str, high: str, width: int) -> DataFrame:
    """Points in [low, high): intervals are entered in every bin of `width` they touch, points meet them there."""
    bins = F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width)))
    return points.withColumn("_bin", F.floor(F.col(value) / width)).join(intervals.withColumn("_bin", bins), "_bin").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_bin")


def op_join_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = table(spark, sf_dir, "part").select("p_partkey", F.floor("p_retailprice").alias("price"))
    intervals = table(spark, sf_dir, "supplier").select("s_suppkey", (F.col("s_suppkey") * 13 % 900 + 900).alias("low")).withColumn("high", F.col("low") + 25)
    return range_join(points, intervals, "price", "low", "high", 32).select("p_partkey", "s_suppkey")


def asof_join(left: DataFrame, right: DataFrame, by: str, time: str, value: str) -> DataFrame:
    """For each left row the last right value of its key at or before its time: one union, one window, no pairs."""
    a = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("_side"))
    b = right.select(by, time, value, F.lit(0).alias("_side"))
    order = W.partitionBy(by).orderBy(time, "_side").rowsBetween(W.unboundedPreceding, 0)
    return a.unionByName(b, allowMissingColumns=True).withColumn(value, F.last(value, ignorenulls=True).over(order)).where("_side = 1").drop("_side")


def op_join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events")
    clicks = events.where("event_type = 'click'").select("event_id", "user_id", "ts")
    others = events.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("last_value"))
    return asof_join(clicks, others, "user_id", "ts", "last_value").select("event_id", "last_value")


def op_agg_percentile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_quantity", 0.25), 6).alias("q1"), F.round(F.median("l_quantity"), 6).alias("q2"))


def op_agg_collect(spark: SparkSession, sf_dir: str) -> DataFrame:
    grouped = table(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_sort(F.collect_set("n_name")).alias("names"))
    return grouped.select("n_regionkey", F.array_join("names", ",").alias("names"), F.size("names").cast("long").alias("n"))


def op_agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The estimate that could choose b lies within a tenth of the count."""
    exact, near = F.countDistinct("l_partkey"), F.approx_count_distinct("l_partkey", 0.02)
    return table(spark, sf_dir, "lineitem").agg((F.abs(exact - near) <= exact / 10).alias("near"))


def op_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().select("o_orderpriority", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("F", "O", "P")))


def op_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").unpivot(["l_orderkey", "l_linenumber", "l_partkey"], ["l_tax", "l_discount"], "kind", "rate")


def op_lateral_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dearest orders of each customer, by a correlated subquery that Catalyst decorrelates.

    They are numbered in it: a decorrelated ORDER BY ... LIMIT takes any orders once a customer's come from several tasks."""
    text = """SELECT c_custkey, o_orderkey FROM (SELECT DISTINCT c_custkey FROM {customer}), LATERAL (
        SELECT o_orderkey FROM (SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS k FROM {orders} WHERE o_custkey = c_custkey) WHERE k <= 2)"""
    return sql_query(text, "customer", "orders")(spark, sf_dir)


def op_fn_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.col("o_orderkey")
    return table(spark, sf_dir, "orders").select(
        "o_orderkey", k.bitwiseAND(255).alias("a"), k.bitwiseOR(256).alias("o"), k.bitwiseXOR(37).alias("x"), F.shiftleft(k, 3).alias("l"), F.shiftright(k, 2).alias("r"), F.bit_count(k).cast("int").alias("c")
    )


def op_fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


def op_fn_regexp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", r"://([^/]+)", 1).alias("host"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'))).cast("long").alias("links"))


def op_fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = F.col("embedding")
    return table(spark, sf_dir, "embeddings").select("vec_id", F.size(e).cast("long").alias("n"), F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 6).alias("norm2"), F.round(F.array_max(e).cast("double"), 6).alias("most"))


def op_fn_datetime(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_format("o_orderdate", "yyyy-MM-dd").alias("d"))


def op_win_range_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp"))
    frame = W.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return table(spark, sf_dir, "events").select("event_id", "user_id", seconds.alias("s")).select("event_id", F.count(F.lit(1)).over(frame).alias("n"))


def _roundtrip(fmt: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Written in another format and read with the schema given."""
        pages = table(spark, sf_dir, "pages").select("page_id", "url")
        path = shared_path(spark, fmt)
        if fmt == "text":
            pages.select(F.concat_ws("\t", "page_id", "url").alias("value")).write.text(path)
            parts = F.split("value", "\t")
            return spark.read.text(path).select(parts[0].cast("long").alias("page_id"), parts[1].alias("url"))
        writer = pages.write.option("header", True) if fmt == "csv" else pages.write
        writer.format(fmt).save(path)
        from densekeys.sources.artifact import read_keys

        return read_keys(spark, path, ["page_id", "url"], fmt, "page_id long, url string")

    return run


_EXTRA = (op_join_range, op_join_asof, op_agg_percentile, op_agg_collect, op_agg_approx_distinct, op_pivot, op_unpivot, op_lateral_topk, op_fn_bits, op_fn_json, op_fn_regexp, op_fn_array, op_fn_datetime, op_win_range_frame)
QUERIES |= {f.__name__: f for f in _EXTRA} | {f"op_fmt_roundtrip_{fmt}": _roundtrip(fmt) for fmt in ("csv", "json", "orc", "text")}
ORACLES |= {f"op_fmt_roundtrip_{fmt}": "SELECT page_id, url FROM pages" for fmt in ("csv", "json", "orc", "text")}
ORACLES |= {
    "op_join_range": "SELECT p_partkey, s_suppkey FROM part JOIN (SELECT s_suppkey, s_suppkey * 13 % 900 + 900 AS low FROM supplier) ON floor(p_retailprice) >= low AND floor(p_retailprice) < low + 25",
    "op_join_asof": "SELECT event_id, last_value FROM (SELECT event_id, user_id, ts FROM events WHERE event_type = 'click') c ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS last_value FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) p ON c.user_id = p.user_id AND c.ts >= p.ts",
    "op_agg_percentile": "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.25), 6) AS q1, round(median(l_quantity), 6) AS q2 FROM lineitem GROUP BY 1",
    "op_agg_collect": "SELECT n_regionkey, string_agg(DISTINCT n_name, ',' ORDER BY n_name) AS names, count(DISTINCT n_name) AS n FROM nation GROUP BY 1",
    "op_agg_approx_distinct": "SELECT true AS near",
    "op_pivot": "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"O\", count(*) FILTER (WHERE o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1",
    "op_unpivot": "SELECT l_orderkey, l_linenumber, l_partkey, 'l_tax' AS kind, l_tax AS rate FROM lineitem UNION ALL SELECT l_orderkey, l_linenumber, l_partkey, 'l_discount', l_discount FROM lineitem",
    "op_lateral_topk": "SELECT o_custkey AS c_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer)) WHERE k <= 2",
    "op_fn_bits": "SELECT o_orderkey, o_orderkey & 255 AS a, o_orderkey | 256 AS o, xor(o_orderkey, 37) AS x, o_orderkey << 3 AS l, o_orderkey >> 2 AS r, bit_count(o_orderkey)::INTEGER AS c FROM orders",
    "op_fn_json": "SELECT event_id, json_extract(props, '$.k')::INTEGER AS k FROM events",
    "op_fn_regexp": "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS links FROM pages",
    "op_fn_array": "SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm2, round(list_max(embedding)::DOUBLE, 6) AS most FROM embeddings",
    "op_fn_datetime": "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, strftime(o_orderdate, '%Y-%m-%d') AS d FROM orders",
    "op_win_range_frame": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM (SELECT event_id, user_id, floor(epoch(ts))::BIGINT AS s FROM events)",
}
