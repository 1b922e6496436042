"""Variants of the method, its measures and experiments at the size of the tables, and functions called from SQL."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densekeys import measures
from densekeys.functions.hashing import LinearHash
from densekeys.functions.runs import RUNS
from densekeys.operators import baselines, filters, sql_surface
from densekeys.plans.bucketing import address
from densekeys.plans.build import build_core, build_two_level
from densekeys.plans.evaluate import lookup, verify
from densekeys.plans.fingerprints import distinct_fingerprints, fingerprint
from densekeys.plans.kernels import KERNELS, numbered
from densekeys.plans.params import Params
from densekeys.shared import shared_path, written
from densekeys.workloads.methods import BIJECTION, EXAMPLE_ROWS, _order_words, sql_words, table
from densekeys.workloads.tables import BUILD_TIMES, MEMORY, FILES_SQL, SPACE, _values, cases, run_files

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str):
    def keep(f):
        QUERIES[f.__name__], ORACLES[f.__name__] = f, sql
        return f

    return keep


AGREE = "SELECT count(*)::BIGINT AS n, 0::BIGINT AS differ FROM {}"


def _agree(df: DataFrame, key: str, variants: list[Params]) -> DataFrame:
    """Ids by the first variant and by the others, row by row."""
    base = lookup(df, build_two_level(df, key, variants[0]), slot="s0", id="i0")
    differ = F.lit(False)
    for k, params in enumerate(variants[1:], 1):
        base = lookup(base, build_two_level(df, key, params), key, slot=f"s{k}", id=f"i{k}")
        differ = differ | (F.col(f"i{k}") != F.col("i0"))
    return base.agg(F.count(F.lit(1)).alias("n"), F.count_if(differ).alias("differ"))


# --- variants of the method


@query(AGREE.format("orders"))
def gf2_chunk_widths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tables of 4-, 8- and 16-bit chunks give the words of one linear map."""
    families = [LinearHash(777, 8, 2, sigma) for sigma in (8, 4, 16)]

    def run(batches):
        for batch in batches:
            keys = np.frombuffer(batch.column(0).to_numpy().astype(">i8").tobytes(), np.uint8)
            first, *rest = (f(keys, np.arange(batch.num_rows + 1) * 8) for f in families)
            yield pa.RecordBatch.from_arrays([pa.array(np.any([(first != w).any(axis=1) for w in rest], axis=0))], ["differs"])

    found = table(spark, sf_dir, "orders").select("o_orderkey").mapInArrow(run, "differs boolean")
    return found.agg(F.count(F.lit(1)).alias("n"), F.count_if("differs").alias("differ"))


@query(AGREE.format("customer"))
def mphf_chunk_widths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _agree(table(spark, sf_dir, "customer").select("c_name"), "c_name", [Params(sigma=s) for s in (8, 4, 16)])


@query(AGREE.format("orders"))
def rank_theory_directory(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directories whose step grows with log tau answer as the fixed one does."""
    variants = [Params(hash="xx128"), *(Params(hash="xx128", kappa="theory", eps_rank=e) for e in (0.05, 0.1, 1.0))]
    return _agree(table(spark, sf_dir, "orders").select("o_orderkey"), "o_orderkey", variants)


def _kernel(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """The two-level shell with another way to number the keys of a bucket."""
        found = numbered(table(spark, sf_dir, "customer"), "c_custkey", name)
        return found.agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("min_id"), F.max("id").alias("max_id"), F.countDistinct("id").alias("n_ids"))

    return run


for _name in KERNELS:
    QUERIES[f"kernel_{_name}"] = _kernel(_name)
    ORACLES[f"kernel_{_name}"] = BIJECTION.format(count="SELECT count(DISTINCT c_custkey) FROM customer")


@query("SELECT method, (SELECT count(DISTINCT o_orderkey) FROM orders)::BIGINT AS n, 0::BIGINT AS unsorted FROM (VALUES ('radix'), ('comparison'), ('replacement')) t(method)")
def ab_run_formation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sorted runs of the fingerprints by each way to form them: all values, and none out of order in its run."""
    prints = written(distinct_fingerprints(fingerprint(table(spark, sf_dir, "orders").select("o_orderkey"), ["o_orderkey"], Params(hash="xx128"), 0)).select("hi"), "fingerprints")

    def run(batches):
        for batch in batches:
            values = batch.column(0).to_numpy().view(np.uint64)
            for name, form in RUNS.items():
                runs = form(values, 512)
                yield pa.RecordBatch.from_pydict({"method": [name], "n": [sum(map(len, runs))], "unsorted": [sum(int((r[1:] < r[:-1]).sum()) for r in runs)]})

    return prints.mapInArrow(run, "method string, n long, unsorted long").groupBy("method").agg(F.sum("n").alias("n"), F.sum("unsorted").alias("unsorted"))


# --- measures as closed forms


def _rows(spark: SparkSession, schema: str, rows) -> DataFrame:
    return spark.createDataFrame(list(rows), schema)


@query(f"SELECT a::BIGINT AS n, greatest(1, ceil(pow(1.96 * c / (0.05 * b), 2)))::BIGINT AS trials FROM (VALUES {_values(BUILD_TIMES)}) t(a, b, c)")
def trials_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trials that a mean within a twentieth needs."""
    return _rows(spark, "n long, trials long", ((n, measures.required_trials(sd, mean, 0.05)) for n, mean, sd in BUILD_TIMES))


@query(f"SELECT n::BIGINT AS n, round(pow(2.0, b) * ceil(log2(n)) / n, 9) AS share FROM (VALUES {_values(SPACE)}) t(n, b, p, m)")
def offset_share_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rows(spark, "n long, share double", ((n, round(measures.offset_share(n, b), 9)) for n, b, *_ in SPACE))


TOTAL_MB, COUNTERS_MB = 16_630, 32


@query(f"SELECT m::BIGINT AS memory_mb, ceil({TOTAL_MB}.0 / (m - {COUNTERS_MB}))::BIGINT AS files, f::BIGINT AS printed FROM (VALUES {_values(MEMORY)}) t(m, f, b, s)")
def runs_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rows(spark, "memory_mb long, files long, printed long", ((m, measures.runs(TOTAL_MB, m, COUNTERS_MB), f) for m, f, *_ in MEMORY))


#: Bits and number of chunks.
INDEPENDENCE = tuple((r, k) for r in (14, 15) for k in (4, 6, 8))


@query(f"""SELECT ell, buckets, r::BIGINT AS r, k::BIGINT AS chunks, CASE k WHEN 4 THEN q * q * (q * q) WHEN 6 THEN q * q * (q * q) * (q * q) ELSE q * q * (q * q) * (q * q * (q * q)) END * 1e9::DOUBLE AS bound_e9
    FROM (SELECT *, ell / pow(2.0, r) AS q FROM (SELECT ell, count(*)::BIGINT AS buckets FROM (SELECT count(*)::BIGINT AS ell FROM {sql_words()} GROUP BY w >> 20) GROUP BY 1), (VALUES {_values(INDEPENDENCE)}) t(r, k))""")
def independence_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bound for each size that 4,096 buckets of order keys have; products, as powers differ in their last bits between engines."""
    sizes = _order_words(spark, sf_dir).groupBy(address(F.col("hi"), 12)).agg(F.count(F.lit(1)).alias("ell")).groupBy("ell").agg(F.count(F.lit(1)).alias("buckets"))
    q = F.col("ell") / F.pow(F.lit(2.0), F.col("r"))
    square = q * q
    fourth = square * square
    bound = F.when(F.col("chunks") == 4, fourth).when(F.col("chunks") == 6, fourth * square).otherwise(fourth * fourth)
    return sizes.select("*", cases("r chunks", INDEPENDENCE)).select("ell", "buckets", F.col("r").cast("long").alias("r"), F.col("chunks").cast("long").alias("chunks"), (bound * 1e9).alias("bound_e9"))


@query(f"SELECT m::BIGINT AS memory_mb, f AS files, 3 * f + 1024 AS words FROM {FILES_SQL}")
def memory_words_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words that merging the runs of the line items' keys needs."""
    return run_files(spark, sf_dir).select("memory_mb", "files", measures.construction_memory_words(F.col("files")).alias("words"))


@query(f"SELECT n::BIGINT AS n, round((2.09 + 64 * pow(2.0, b) / n) * n / 8 / 1048576, 4) AS mb, (n::BIGINT * 96) AS disk_bytes FROM (VALUES {_values(SPACE)}) t(n, b, p, m)")
def size_and_disk_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """MB of the function, and bytes that its construction moves over keys of 64 bytes."""
    return _rows(spark, "n long, mb double, disk_bytes long", ((n, round(measures.artifact_mb(n, b), 4), int(measures.disk_bytes(n, 64))) for n, b, *_ in SPACE))


# --- experiments at the size of the tables; bench.py --paper times them at the published ones

SIZES = (1 << 10, 1 << 12, 1 << 14, 1 << 16)


def url_like(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.concat(F.lit("http://"), F.substring(F.sha2(F.col("id").cast("string"), 256), 1, 57)).alias("url"))


@query(f"SELECT n::BIGINT AS n, n::BIGINT AS n_ids, true AS range_ok, true AS space_ok FROM (VALUES {_values((s,) for s in SIZES)}) t(n)")
def scale_build_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Growing sets: ids without gaps, a range just over twice the keys, and bits a key below 4.4."""
    rows = []
    for n in SIZES:
        df = url_like(spark, n)
        artifact = build_two_level(df, "url")
        bits = measures.bits_per_key(artifact).first()["mphf_bits"]
        rows.append((n, verify(df, artifact).first()["n_ids"], 2.09 <= artifact.n_slots / n < 2.13, bits < 4.4))
    return _rows(spark, "n long, n_ids long, range_ok boolean, space_ok boolean", rows)


BUILDS = {f"two_level_{h}_{kind}": (build_two_level, Params(hash=h, kind=kind)) for h in ("linear", "mix96") for kind in ("phf", "mphf")}
BUILDS |= {f"core_universal_{kind}": (build_core, Params(hash="universal", kappa=256, kind=kind)) for kind in ("phf", "mphf")}


@query(f"SELECT method, (SELECT count(DISTINCT c_custkey) FROM customer)::BIGINT AS n, (SELECT count(DISTINCT c_custkey) FROM customer)::BIGINT AS n_values FROM (VALUES {_values((m,) for m in [*BUILDS, *(f'bl_{b}' for b in baselines.METHODS)])}) t(method)")
def build_compare(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every method and baseline on one set: as many values as keys."""
    keys = table(spark, sf_dir, "customer").select("c_custkey")
    found = None
    for name, (build, params) in BUILDS.items():
        one = verify(keys, build(keys, "c_custkey", params)).select(F.lit(name).alias("method"), "n", F.col("n_ids").alias("n_values"))
        found = one if found is None else found.unionByName(one)
    for name in baselines.METHODS:
        ids = baselines.in_one_task(keys, "c_custkey", name)
        found = found.unionByName(ids.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("id").alias("n_values")).select(F.lit(f"bl_{name}").alias("method"), "n", "n_values"))
    return found


PARTITIONS = (2, 4, 8, 16)


@query(f"SELECT p::BIGINT AS partitions, (SELECT count(DISTINCT o_orderkey) FROM orders)::BIGINT AS n, 1::BIGINT AS artifacts FROM (VALUES {_values((p,) for p in PARTITIONS)}) t(p)")
def memory_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Smaller and more numerous shares of the keys, as less memory would have them, give one and the same function."""
    keys, rows, seen = table(spark, sf_dir, "orders").select("o_orderkey"), [], set()
    for p in PARTITIONS:
        artifact = build_two_level(keys.repartition(p), "o_orderkey", Params(hash="xx128", super_keys=4096))
        told = artifact.rows.select("super", F.sha2(F.concat("buckets", "sizes", "seeds", "labels", "occupied"), 256).alias("h")).groupBy().agg(F.array_join(F.array_sort(F.collect_list(F.concat_ws(":", "super", "h"))), ",").alias("h"))
        seen.add(hashlib.sha256(told.first()["h"].encode()).hexdigest())
        rows.append((p, artifact.n, len(seen)))
    return _rows(spark, "partitions long, n long, artifacts long", rows)


@query("SELECT count(DISTINCT o_orderkey)::BIGINT AS n, true AS both_take_time FROM orders")
def split_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Time goes to partitioning and to searching; bench.py --paper records the shares."""
    keys, params = table(spark, sf_dir, "orders").select("o_orderkey"), Params()
    held = {}
    split = measures.build_split(
        lambda: held.update(prints=written(distinct_fingerprints(fingerprint(keys, ["o_orderkey"], params, 0)), "fingerprints")),
        lambda: held.update(artifact=build_two_level(keys, "o_orderkey", params)),
    )
    return _rows(spark, "n long, both_take_time boolean", [(held["artifact"].n, 0 < split["share"] < 1)])


# --- functions called from SQL


@query("SELECT count(text)::BIGINT AS n, 0::BIGINT AS differ FROM documents")
def sql_long_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys of any length are encoded alike by functions and by lookups."""
    texts = table(spark, sf_dir, "documents").select("text").where("text IS NOT NULL")
    both, differ = texts, F.lit(False)
    for h in ("linear", "mix96"):
        artifact = build_two_level(texts, "text", Params(hash=h))
        sql_surface.register_lookup(spark, f"text_id_{h}", artifact)
        both = lookup(both, artifact, "text", slot=f"s_{h}", id=f"i_{h}").withColumn(f"f_{h}", F.expr(f"text_id_{h}(text)"))
        differ = differ | ~F.col(f"i_{h}").eqNullSafe(F.col(f"f_{h}"))
    return both.agg(F.count(F.lit(1)).alias("n"), F.count_if(differ).alias("differ"))


@query(AGREE.format("pages"))
def sql_dense_slot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Slots, and ids by the form that reads the artifact once for each task."""
    urls = table(spark, sf_dir, "pages").select("url")
    artifact = build_two_level(urls, "url", Params(hash="mix96"))
    sql_surface.register_lookup(spark, "dense_slot", artifact, slot=True)
    sql_surface.register_iterator_lookup(spark, "dense_id_of_batches", artifact)
    both = lookup(urls, artifact).withColumns({"by_slot": F.expr("dense_slot(url)"), "by_id": F.expr("dense_id_of_batches(url)")})
    return both.agg(F.count(F.lit(1)).alias("n"), F.count_if((F.col("slot") != F.col("by_slot")) | (F.col("id") != F.col("by_id"))).alias("differ"))


@query("SELECT 0::BIGINT AS false_negatives, count(*)::BIGINT AS non_members, true AS rate_ok FROM customer WHERE c_custkey % 2 <> 0")
def sql_might_contain(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = table(spark, sf_dir, "customer").select("c_name", (F.col("c_custkey") % 2 == 0).alias("member"))
    members = filters.build_filter(names.where("member"), "c_name", 8, Params(hash="mix96"))
    sql_surface.register_membership(spark, "known_customer", members)
    probed = names.withColumn("maybe", F.expr("known_customer(c_name)"))
    return filters.filter_accuracy(probed, "member").select("false_negatives", "non_members", (F.col("rate") <= 4 / 256).alias("rate_ok"))


@query("SELECT count(DISTINCT url)::BIGINT AS n, 0::BIGINT AS unknown FROM pages")
def sql_key_fp128(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints by the function are those that a build starts from."""
    params = Params()
    sql_surface.register_hashes(spark, params)
    urls = table(spark, sf_dir, "pages").select("url").dropDuplicates()
    known = fingerprint(urls, ["url"], params, 0).select("hi", "lo")
    found = urls.select(F.expr("key_fp128(url)").alias("f")).select("f.hi", "f.lo")
    return found.agg(F.count(F.lit(1)).alias("n")).crossJoin(found.join(known, ["hi", "lo"], "left_anti").agg(F.count(F.lit(1)).alias("unknown")))


@query("SELECT o_orderkey, " + ", ".join(f"(bit_count(o_orderkey & {r * 1237}) % 2)::BIGINT AS p{k}" for k, r in enumerate(EXAMPLE_ROWS)) + " FROM orders")
def op_udf_parity(spark: SparkSession, sf_dir: str) -> DataFrame:
    sql_surface.register_hashes(spark)
    return table(spark, sf_dir, "orders").select("o_orderkey", *(F.expr(f"gf2_parity(o_orderkey, CAST({r * 1237} AS BIGINT))").alias(f"p{k}") for k, r in enumerate(EXAMPLE_ROWS)))


@query("""SELECT c_nationkey, (m + 2 * tau + 8 * ((2 * tau + 127) // 128) + 64)::BIGINT AS bits
FROM (SELECT c_nationkey, m, greatest(1, (1045 * m + 999) // 1000) AS tau FROM (SELECT c_nationkey, count(DISTINCT c_custkey) AS m FROM customer GROUP BY 1))""")
def op_udaf_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    sql_surface.register_bucket_bits(spark)
    return table(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.expr("bits_of_bucket(c_custkey)").alias("bits"))


@query("SELECT count(DISTINCT o_orderkey)::BIGINT AS n, true AS sizes_ok FROM orders")
def sql_artifact_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    sql_surface.register_tables(spark)
    rows = build_two_level(table(spark, sf_dir, "orders"), "o_orderkey", Params(hash="xx128")).rows
    return spark.sql("SELECT sum(t.held) AS n, max(t.held) <= 256 AND min(t.tried) >= 1 AS sizes_ok FROM {rows}, LATERAL artifact_buckets(buckets, sizes, tries) AS t(number, held, tried)", rows=rows)


@query("SELECT n_regionkey, count(*)::BIGINT AS taken, 1::BIGINT AS rounds FROM nation GROUP BY 1")
def sql_peel_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each region and its nations are a star, which one round takes apart."""
    sql_surface.register_tables(spark)
    stars = table(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.collect_list("n_nationkey").alias("l"), F.collect_list(F.col("n_regionkey") + 100).alias("r"))
    return spark.sql("SELECT n_regionkey, count(*) AS taken, count(DISTINCT round) AS rounds FROM {stars}, LATERAL peel_trace(l, r) GROUP BY n_regionkey", stars=stars)


@query("SELECT count(DISTINCT o_orderkey)::BIGINT AS n, true AS sizes_ok, 0::BIGINT AS repeated FROM orders")
def op_artifact_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A written artifact as a data source of its own."""
    from densekeys.sources.artifact import register

    path = shared_path(spark, "artifact")
    build_two_level(table(spark, sf_dir, "orders"), "o_orderkey", Params(hash="xx128", super_keys=4096)).write(path)
    register(spark)
    rows = spark.read.format("densekeys").load(path)
    return rows.agg(F.sum("size").alias("n"), (F.max("size") <= 256).alias("sizes_ok"), (F.count(F.lit(1)) - F.countDistinct("bucket")).alias("repeated"))


# --- what was missing of the relational surface


@query("SELECT page_id, url FROM pages WHERE regexp_matches(url, '^https?://[a-z0-9.-]+/(en|de)/')")
def op_filter_rlike(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").where(F.col("url").rlike("^https?://[a-z0-9.-]+/(en|de)/")).select("page_id", "url")


@query("SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def op_join_inner_bnlj(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nested loop that the hash and merge joins are compared with, on a pair of small tables."""
    nations = table(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    return table(spark, sf_dir, "supplier").hint("shuffle_replicate_nl").join(nations, F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT a.event_id AS event_id, b.event_id AS later FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def op_join_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Later events of a user within six hours: each event meets those of its own and the next stretch of six hours, not all of its user."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts")).withColumn("stretch", F.floor(F.unix_seconds("ts") / 21_600))
    early = events.withColumn("stretch", F.explode(F.array("stretch", F.col("stretch") + 1)))
    late = events.select(F.col("event_id").alias("later"), "user_id", F.col("ts").alias("late_ts"), "stretch")
    near = (F.col("late_ts") > F.col("ts")) & (F.col("late_ts") <= F.col("ts") + F.expr("INTERVAL 6 HOURS"))
    return early.join(late, ["user_id", "stretch"]).where(near).select("event_id", "later")


@query("SELECT lpad(i::VARCHAR, 32, 'x') AS key FROM range(5000) t(i)")
def op_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Synthetic keys of one length."""
    return spark.range(5000).select(F.lpad(F.col("id").cast("string"), 32, "x").alias("key"))


@query("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def op_sql_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Views and the catalog, under names that no other query uses."""
    for name in ("customer", "nation"):
        table(spark, sf_dir, name).createOrReplaceTempView(f"densekeys_view_{name}")
    return spark.table("densekeys_view_customer").join(spark.sql("SELECT n_nationkey, n_name FROM densekeys_view_nation"), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))
