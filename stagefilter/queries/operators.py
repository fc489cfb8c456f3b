"""One query for each operator around the methods: joins, aggregates, windows, sorts, sets, scalar functions, sources, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stagefilter.functions import udfs
from stagefilter.functions.hashing import BLOCK_BITS, element_hash, hash_sql, position_sql
from stagefilter.operators.bloom import BloomFilter, bitmaps
from stagefilter.operators.flow import measure_flow
from stagefilter.operators.joins import asof_version, interval_version, prefilter_join, region_join
from stagefilter.queries.base import BINS, THETAS, flow_sql, scored, scored_sql
from stagefilter.queries.method import Q as METHOD
from stagefilter.queries.method import SQL as METHOD_SQL
from stagefilter.queries.method import _GRID_SQL, _K, _REGIONS, _SETS_SQL, _staged_sql, _grid, _key_sets, fixed_staged, with_ideal_bits, with_sizes
from stagefilter.sources import store
from stagefilter.sources.scratch import scratch
from stagefilter.sources.workloads import table
from stagefilter.streaming import service

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        Q[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


# --- sources --------------------------------------------------------------------------


@query("SELECT l_returnflag, round(sum(l_quantity), 2) AS qty FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' GROUP BY 1")
def scan_pruned_lineitem(spark: SparkSession, sf: str) -> DataFrame:
    t = table(spark, sf, "lineitem").filter(F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp_ntz"))
    return t.groupBy("l_returnflag").agg(F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("SELECT r_regionkey, r_name FROM region")
def roundtrip_formats(spark: SparkSession, sf: str) -> DataFrame:
    """Keys through CSV, JSON, ORC and text with declared schemas; what is common to all."""
    r, path = table(spark, sf, "region").select("r_regionkey", "r_name"), scratch(spark, "formats")
    schema, out = "r_regionkey int, r_name string", None
    for kind in ("csv", "json", "orc"):
        r.write.format(kind).save(f"{path}/{kind}")
        back = spark.read.schema(schema).format(kind).load(f"{path}/{kind}")
        out = back if out is None else out.intersect(back)
    r.select(F.concat_ws("|", "r_regionkey", "r_name").alias("value")).write.text(f"{path}/text")
    lines = spark.read.text(f"{path}/text").select(F.split_part("value", F.lit("|"), F.lit(1)).cast("int").alias("r_regionkey"), F.split_part("value", F.lit("|"), F.lit(2)).alias("r_name"))
    return out.intersect(lines)


@query("SELECT 2 AS depth, 5::BIGINT AS filters, true AS same")
def filter_store_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    _, f = fixed_staged(spark, sf)
    path = scratch(spark, "store")
    store.write(spark, f, path, 3)
    g = store.read(spark, path)
    same = store.fingerprint(f.plan) == store.fingerprint(g.plan) and all((f.filters[k].bits == g.filters[k].bits).all() for k in f.filters)
    return spark.createDataFrame([(g.plan.depth, len(g.filters), bool(same))], "depth int, filters long, same boolean")


@query("SELECT 2 AS depth, 5::BIGINT AS filters, true AS same")
def roundtrip_plan_json(spark: SparkSession, sf: str) -> DataFrame:
    _, f = fixed_staged(spark, sf)
    text = store.plan_json(f.plan)
    df = spark.createDataFrame([(text,)], "plan string").select(F.from_json("plan", "depth int, gates array<int>, exit_fpr array<double>, leaf_fpr array<double>").alias("p"))
    return df.select("p.depth", (F.size("p.gates") + F.size("p.exit_fpr") + F.size("p.leaf_fpr")).cast("long").alias("filters"), F.lit(store.plan_json(store.plan_from_json(text)) == text).alias("same"))


@query("SELECT * FROM (VALUES ('g1'), ('e1'), ('g2'), ('l0'), ('l1')) v(name)")
def datasource_filter_rows(spark: SparkSession, sf: str) -> DataFrame:
    _, f = fixed_staged(spark, sf)
    path = scratch(spark, "store")
    store.write(spark, f, path)
    return store.data_source_rows(spark, path).select("name")


@query(f"WITH {scored_sql()} SELECT count(*) AS n FROM q WHERE is_key AND s4 >= 0.7")
def sql_entry_membership(spark: SparkSession, sf: str) -> DataFrame:
    q = scored(spark, sf)
    f = BloomFilter.build(q.filter("is_key"), "h", 0.01, 6)
    udfs.register(spark, bloom=f, prefix="entry_")
    q.createOrReplaceTempView("stagefilter_examples")
    return spark.sql("SELECT count(*) AS n FROM stagefilter_examples WHERE entry_bloom_has(h) AND is_key AND s[3] >= :least", args={"least": 0.7})


# --- predicates -----------------------------------------------------------------------


@query("SELECT count(*) AS keys, count(*) AS found FROM orders WHERE o_orderpriority = '1-URGENT'")
def maybe_in_superset(spark: SparkSession, sf: str) -> DataFrame:
    o = table(spark, sf, "orders").filter("o_orderpriority = '1-URGENT'").select(element_hash(F.col("o_orderkey")).alias("h"))
    f = BloomFilter.build(o, "h", 0.01)
    return o.agg(F.count("*").alias("keys"), F.count_if(f.contains(F.col("h"))).alias("found"))


@query(
    "SELECT page_id, length(url) AS n, len(regexp_extract_all(url, '[0-9]')) AS digits, len(regexp_extract_all(url, '[.]')) AS dots, len(regexp_extract_all(url, '/')) AS slashes, CAST(starts_with(url, 'https') AS INTEGER) AS https FROM pages"
)
def url_lexical_features(spark: SparkSession, sf: str) -> DataFrame:
    from stagefilter.sources.workloads import url_features

    x = url_features(F.col("url"))
    return table(spark, sf, "pages").select("page_id", x[0].alias("n"), x[1].alias("digits"), x[3].alias("dots"), x[4].alias("slashes"), x[6].alias("https"))


@query(f"WITH {scored_sql()} SELECT eid FROM q WHERE CASE WHEN s1 >= 0.4 THEN is_key WHEN s2 >= 0.3 THEN h % 2 = 0 ELSE false END")
def lazy_predicate_order(spark: SparkSession, sf: str) -> DataFrame:
    s = lambda i: F.get("s", F.lit(i))
    return scored(spark, sf).filter(F.when(s(0) >= 0.4, F.col("is_key")).when(s(1) >= 0.3, F.col("h") % 2 == 0).otherwise(False)).select("eid")


@query("SELECT count(*) AS n FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#22', 'Brand#33') OR p_name LIKE '%a%' AND regexp_matches(p_type, '^[A-M]') AND p_retailprice IS NOT DISTINCT FROM p_retailprice")
def predicate_mix(spark: SparkSession, sf: str) -> DataFrame:
    p = table(spark, sf, "part")
    one = F.col("p_size").between(5, 20) & F.col("p_brand").isin("Brand#11", "Brand#22", "Brand#33")
    return p.filter(one | (F.col("p_name").like("%a%") & F.col("p_type").rlike("^[A-M]") & F.col("p_retailprice").eqNullSafe(F.col("p_retailprice")))).agg(F.count("*").alias("n"))


# --- joins ----------------------------------------------------------------------------

_URGENT = "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT')"
_UNSHIPPED = "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)"


def _lines(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey")


def _urgent(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "orders").filter("o_orderpriority = '1-URGENT'").select("o_orderkey")


@query(_URGENT)
def exact_semi_urgent(spark: SparkSession, sf: str) -> DataFrame:
    return _lines(spark, sf).join(_urgent(spark, sf), F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")


@query(_UNSHIPPED)
def exact_anti_unshipped(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "orders").select("o_orderkey").join(_lines(spark, sf), F.col("l_orderkey") == F.col("o_orderkey"), "left_anti")


@query(_URGENT)
def prefilter_semi_join(spark: SparkSession, sf: str) -> DataFrame:
    return prefilter_join(_lines(spark, sf), _urgent(spark, sf), "l_orderkey", "o_orderkey")


@query(_UNSHIPPED)
def prefilter_anti_join(spark: SparkSession, sf: str) -> DataFrame:
    return prefilter_join(table(spark, sf, "orders").select("o_orderkey"), _lines(spark, sf).select("l_orderkey"), "o_orderkey", "l_orderkey", "left_anti")


@query("SELECT p_brand, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size > 45 GROUP BY 1")
def prefilter_star_join(spark: SparkSession, sf: str) -> DataFrame:
    p = table(spark, sf, "part").filter("p_size > 45").select("p_partkey", "p_brand")
    fact = table(spark, sf, "lineitem").select("l_partkey", "l_extendedprice")
    return prefilter_join(fact, p, "l_partkey", "p_partkey", "inner").groupBy("p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size > 45 GROUP BY 1")
def runtime_bloom_parity(spark: SparkSession, sf: str) -> DataFrame:
    """The built-in runtime filter may act here; the answer is the same."""
    p = table(spark, sf, "part").filter("p_size > 45")
    return table(spark, sf, "lineitem").join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n"))


@query("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_hints_parity(spark: SparkSession, sf: str) -> DataFrame:
    c, n, out = table(spark, sf, "customer"), table(spark, sf, "nation"), None
    for hint in ("broadcast", "shuffle_hash", "merge", "shuffle_replicate_nl"):
        part = c.join(n.hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))
        out = part if out is None else out.intersect(part)
    return out


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey AND o_totalprice > 400000 GROUP BY 1")
def left_outer_counts(spark: SparkSession, sf: str) -> DataFrame:
    o = table(spark, sf, "orders").filter("o_totalprice > 400000")
    return table(spark, sf, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT coalesce(a, b) AS k, a IS NOT NULL AS in_orders, b IS NOT NULL AS in_lines FROM (SELECT DISTINCT o_orderkey AS a FROM orders WHERE o_orderpriority = '1-URGENT') FULL JOIN (SELECT DISTINCT l_orderkey AS b FROM lineitem WHERE l_returnflag = 'R') ON a = b")
def full_outer_keysets(spark: SparkSession, sf: str) -> DataFrame:
    """Keys of urgent orders against keys of orders with returned lines."""
    a = table(spark, sf, "orders").filter("o_orderpriority = '1-URGENT'").select(F.col("o_orderkey").alias("a")).distinct()
    b = table(spark, sf, "lineitem").filter("l_returnflag = 'R'").select(F.col("l_orderkey").alias("b")).distinct()
    return a.join(b, F.col("a") == F.col("b"), "full").select(F.coalesce("a", "b").alias("k"), F.col("a").isNotNull().alias("in_orders"), F.col("b").isNotNull().alias("in_lines"))


@query("WITH g AS (SELECT DISTINCT CAST(least(floor(o_totalprice / 100000), 3) AS BIGINT) AS i FROM orders) SELECT a.i AS i, b.i AS j, c.i AS k FROM g a, g b, g c WHERE a.i + b.i + c.i <= 3")
def cross_config_grid(spark: SparkSession, sf: str) -> DataFrame:
    """Gate exponents of three learners whose sum stays on a grid of four: the price levels that orders have."""
    level = F.least(F.floor(F.col("o_totalprice") / 100000), F.lit(3)).cast("long")
    g = lambda n: table(spark, sf, "orders").select(level.alias(n)).distinct()
    return g("i").crossJoin(g("j")).crossJoin(g("k")).filter("i + j + k <= 3")


@query(METHOD_SQL["bloom_sharded_probe"])
def block_probe_join(spark: SparkSession, sf: str) -> DataFrame:
    return METHOD["bloom_sharded_probe"](spark, sf)


@query(f"WITH {scored_sql()} SELECT region, count(*) AS n FROM (SELECT CASE WHEN s4 < 0.3 THEN 0 WHEN s4 < 0.7 THEN 1 ELSE 2 END AS region FROM q) GROUP BY region")
def range_region_join(spark: SparkSession, sf: str) -> DataFrame:
    r = spark.createDataFrame(_REGIONS, "region int, lo double, hi double")
    return region_join(scored(spark, sf).select(F.get("s", F.lit(3)).alias("score")), "score", r).groupBy("region").agg(F.count("*").alias("n"))


_VERSIONS = "(SELECT date_trunc('day', ts) AS vts, row_number() OVER (ORDER BY date_trunc('day', ts)) AS version FROM events GROUP BY 1)"


def _versions(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    e = table(spark, sf, "events").select("event_id", "ts")
    days = e.select(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("ts")).distinct()
    return e, days.withColumn("version", F.row_number().over(Window.orderBy("ts")).cast("long"))


_ASOF = f"SELECT event_id, version FROM events ASOF JOIN {_VERSIONS} v ON events.ts >= v.vts"


@query(_ASOF)
def asof_filter_version(spark: SparkSession, sf: str) -> DataFrame:
    return asof_version(*_versions(spark, sf)).select("event_id", "version")


@query(_ASOF)
def interval_filter_version(spark: SparkSession, sf: str) -> DataFrame:
    return interval_version(*_versions(spark, sf)).select("event_id", "version")


# --- aggregates -----------------------------------------------------------------------


@query("SELECT count(DISTINCT l_orderkey) AS exact, true AS near FROM lineitem")
def distinct_ids_exact_vs_approx(spark: SparkSession, sf: str) -> DataFrame:
    t = table(spark, sf, "lineitem").agg(F.count_distinct("l_orderkey").alias("exact"), F.approx_count_distinct("l_orderkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("b"))
    return t.select("exact", ((F.abs(F.col("a") / F.col("exact") - 1) < 0.1) & (F.abs(F.col("b") / F.col("exact") - 1) < 0.1)).alias("near"))


_V = f"WITH {_staged_sql()} SELECT split, CAST(learners AS INTEGER) AS learners, count(*) AS n, count(*) FILTER (WHERE found) AS found FROM w GROUP BY "


def _verdicts(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    return f.lookup(e, ("split",)).select("split", F.col("learners_run").alias("learners"), "found")


def _tally(g) -> DataFrame:
    return g.agg(F.count("*").alias("n"), F.count_if("found").alias("found"))


@query(_V + "CUBE (split, learners)")
def verdict_cube(spark: SparkSession, sf: str) -> DataFrame:
    return _tally(_verdicts(spark, sf).cube("split", "learners"))


@query(_V + "ROLLUP (split, learners)")
def verdict_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _tally(_verdicts(spark, sf).rollup("split", "learners"))


@query(_V + "GROUPING SETS ((split), (learners), ())")
def verdict_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    return _tally(_verdicts(spark, sf).groupingSets([["split"], ["learners"], []], "split", "learners"))


@query("SELECT t, count(*) AS n, min(o_totalprice) AS low, max(o_totalprice) AS high FROM (SELECT o_totalprice, ntile(8) OVER (ORDER BY o_totalprice, o_orderkey) AS t FROM orders) GROUP BY t")
def equal_depth_hist(spark: SparkSession, sf: str) -> DataFrame:
    o = table(spark, sf, "orders").select("o_totalprice", F.ntile(8).over(Window.orderBy("o_totalprice", "o_orderkey")).alias("t"))
    return o.groupBy("t").agg(F.count("*").alias("n"), F.min("o_totalprice").alias("low"), F.max("o_totalprice").alias("high"))


_POS = f"SELECT DISTINCT {position_sql('h', 2, 'i', 100000)} AS p FROM q CROSS JOIN generate_series(0, 3) g(i) WHERE is_key"


def _points(spark: SparkSession, sf: str, where: str = "is_key") -> DataFrame:
    from stagefilter.functions.hashing import positions

    return scored(spark, sf).filter(where).select(F.explode(positions(F.col("h"), 2, 4, 100000)).alias("p"))


@query(f"WITH {scored_sql()} SELECT p // {BLOCK_BITS} AS block, count(*) AS ones FROM ({_POS}) GROUP BY 1")
def bitmap_block_popcount(spark: SparkSession, sf: str) -> DataFrame:
    return bitmaps(_points(spark, sf)).select("block", F.bitmap_count("bits").alias("ones"))


@query(f"WITH {scored_sql()} SELECT p // {BLOCK_BITS} AS block, count(*) AS ones FROM ({_POS}) GROUP BY 1")
def union_filter_bits(spark: SparkSession, sf: str) -> DataFrame:
    """Two halves of the keys built apart and united are the filter of all."""
    halves = bitmaps(_points(spark, sf, "is_key and h % 2 = 0")).unionAll(bitmaps(_points(spark, sf, "is_key and h % 2 = 1")))
    return halves.groupBy("block").agg(F.bitmap_count(F.bitmap_or_agg("bits")).alias("ones"))


_SIZES = f"SELECT n, fpr, round(1.4426950408889634 * n * log2(1 / fpr), 3) AS bits FROM {_SETS_SQL} WHERE fpr IN (0.1, 0.01, 0.001)"


def _sizes(spark: SparkSession, sf: str) -> DataFrame:
    return with_ideal_bits(_key_sets(spark, sf)).filter("fpr in (0.1D, 0.01D, 0.001D)")


@query(f"SELECT n, max(bits) FILTER (WHERE fpr = 0.1) AS a, max(bits) FILTER (WHERE fpr = 0.01) AS b, max(bits) FILTER (WHERE fpr = 0.001) AS c FROM ({_SIZES}) GROUP BY n")
def frontier_pivot(spark: SparkSession, sf: str) -> DataFrame:
    t = _sizes(spark, sf).groupBy("n").pivot("fpr", [0.1, 0.01, 0.001]).agg(F.max("bits"))
    return t.toDF("n", "a", "b", "c")


@query(_SIZES)
def frontier_unpivot(spark: SparkSession, sf: str) -> DataFrame:
    t = frontier_pivot(spark, sf).unpivot("n", ["a", "b", "c"], "k", "bits")
    return t.select("n", F.when(F.col("k") == "a", 0.1).when(F.col("k") == "b", 0.01).otherwise(0.001).alias("fpr"), "bits")


@query("SELECT o_orderstatus, round(avg(o_totalprice), 4) AS mean, min(o_totalprice) AS low, max(o_totalprice) AS high, count(*) FILTER (WHERE o_totalprice > 300000) AS big FROM orders GROUP BY 1")
def two_phase_aggregates(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "orders").groupBy("o_orderstatus").agg(F.round(F.avg("o_totalprice"), 4).alias("mean"), F.min("o_totalprice").alias("low"), F.max("o_totalprice").alias("high"), F.count_if(F.col("o_totalprice") > 300000).alias("big"))


# --- windows --------------------------------------------------------------------------

_BINS = f"{flow_sql()}, r AS (SELECT cls, bin, cnt FROM f WHERE theta_id = 0 AND depth = 4 AND bin >= 0)"


def _bins(spark: SparkSession, sf: str) -> DataFrame:
    return measure_flow(scored(spark, sf), [THETAS[0]], BINS).filter("depth = 4 and bin >= 0").select("cls", "bin", "cnt")


@query(f"WITH {_BINS} SELECT cls, bin, CAST(sum(cnt) OVER (PARTITION BY cls ORDER BY bin DESC) AS BIGINT) AS over_it FROM r")
def tail_share(spark: SparkSession, sf: str) -> DataFrame:
    return _bins(spark, sf).select("cls", "bin", F.sum("cnt").over(Window.partitionBy("cls").orderBy(F.desc("bin"))).alias("over_it"))


@query(f"WITH {_BINS} SELECT cls, bin, lag(bin) OVER w AS before, lead(bin) OVER w AS after FROM r WINDOW w AS (PARTITION BY cls ORDER BY bin)")
def region_neighbours(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("cls").orderBy("bin")
    return _bins(spark, sf).select("cls", "bin", F.lag("bin").over(w).alias("before"), F.lead("bin").over(w).alias("after"))


@query(f"WITH {flow_sql()}, t AS (SELECT theta_id, sum(cnt) FILTER (WHERE cls = 1 AND bin < 0) AS keys, sum(cnt) FILTER (WHERE cls = 0 AND bin < 0) AS others FROM f GROUP BY theta_id) SELECT theta_id, CAST(rank() OVER (ORDER BY coalesce(keys, 0) DESC, theta_id) AS INTEGER) AS place FROM t")
def best_theta_per_lambda(spark: SparkSession, sf: str) -> DataFrame:
    f = measure_flow(scored(spark, sf), THETAS, BINS)
    t = f.groupBy("theta_id").agg(F.coalesce(F.sum(F.when((F.col("cls") == 1) & (F.col("bin") < 0), F.col("cnt"))), F.lit(0)).alias("keys"))
    return t.select("theta_id", F.rank().over(Window.orderBy(F.desc("keys"), "theta_id")).alias("place"))


@query("SELECT c_custkey, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS d, round(percent_rank() OVER w, 9) AS p, round(cume_dist() OVER w, 9) AS c FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_nationkey)")
def rank_family(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("c_mktsegment").orderBy("c_nationkey")
    return table(spark, sf, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.round(F.percent_rank().over(w), 9).alias("p"), F.round(F.cume_dist().over(w), 9).alias("c"))


@query("SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def drift_range_frame(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("event_type").orderBy("s").rangeBetween(-3600, 0)
    return table(spark, sf, "events").withColumn("s", F.unix_seconds(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("n"))


@query("SELECT DISTINCT user_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id, nth_value(event_id, 2) OVER w AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def first_last_version(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf, "events").select("user_id", F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(w).alias("last_id"), F.nth_value("event_id", 2).over(w).alias("second_id")).distinct()


# --- sorts, limits, sets --------------------------------------------------------------


@query(f"SELECT n, fpr, {_K} AS k FROM {_GRID_SQL} ORDER BY fpr, n")
def sorted_plan(spark: SparkSession, sf: str) -> DataFrame:
    return with_sizes(_grid(spark)).select("n", "fpr", "k").orderBy("fpr", "n")


@query("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10")
def topk_configs(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").limit(10)


@query("SELECT p_brand, p_partkey FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def topk_per_group(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(spark, sf, "part").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("p_brand", "p_partkey")


@query("SELECT p_partkey FROM part ORDER BY p_retailprice, p_partkey LIMIT 20 OFFSET 40")
def paged_configs(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "part").orderBy("p_retailprice", "p_partkey").select("p_partkey").offset(40).limit(20)


def _two(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    e = table(spark, sf, "events")
    return e.filter("event_type = 'error'").select("user_id"), e.filter("value > 60").select("user_id")


_A, _B = "SELECT user_id FROM events WHERE event_type = 'error'", "SELECT user_id FROM events WHERE value > 60"


@query(f"{_A} UNION {_B}")
def set_union_keys(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _two(spark, sf)
    return a.unionByName(b).distinct()


@query(f"{_A} INTERSECT {_B}")
def set_intersect_keys(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _two(spark, sf)
    return a.intersect(b)


@query(f"{_B} EXCEPT {_A}")
def set_except_keys(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _two(spark, sf)
    return b.subtract(a)


@query(f"SELECT user_id, count(*) AS n FROM (({_B}) EXCEPT ALL ({_A})) GROUP BY 1 UNION ALL SELECT -user_id - 1, count(*) FROM (({_A}) INTERSECT ALL ({_B})) GROUP BY 1")
def set_ops_multiset(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _two(spark, sf)
    n = lambda t: t.groupBy("user_id").agg(F.count("*").alias("n"))
    return n(b.exceptAll(a)).unionAll(n(a.intersectAll(b)).select((-F.col("user_id") - 1).alias("user_id"), "n"))


# --- scalar functions -----------------------------------------------------------------


@query("SELECT c_custkey, length(c_name) AS n, lower(c_mktsegment) AS seg, replace(c_name, '#', '-') AS dashed, split_part(c_name, '#', 2) AS num, instr(c_name, '#') AS at, sha256(c_name) AS sha, md5(c_name) AS md, trim('  x ') AS t, levenshtein(c_mktsegment, 'BUILDING') AS lev FROM customer")
def string_features(spark: SparkSession, sf: str) -> DataFrame:
    n = F.col("c_name")
    return table(spark, sf, "customer").select(
        "c_custkey", F.length(n).alias("n"), F.lower("c_mktsegment").alias("seg"), F.regexp_replace(n, "#", "-").alias("dashed"), F.split_part(n, F.lit("#"), F.lit(2)).alias("num"), F.instr(n, "#").alias("at"),
        F.sha2(n, 256).alias("sha"), F.md5(n.cast("binary")).alias("md"), F.trim(F.lit("  x ")).alias("t"), F.levenshtein("c_mktsegment", F.lit("BUILDING")).alias("lev"),
    )


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, regexp_matches(url, '[?]') AS has_query FROM pages")
def url_parts(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("QUERY")).isNotNull().alias("has_query"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofyear(o_orderdate) AS d, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS w, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def date_features(spark: SparkSession, sf: str) -> DataFrame:
    d = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.dayofyear(d).alias("d"), F.dayofweek(d).alias("w"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).alias("days"))


@query(f"SELECT n, fpr, {_K} AS k, round(pow(1 - exp(-{_K} * n / (10.0 * n)), {_K}), 9) AS at_ten, CAST(floor(log2(n)) AS INTEGER) AS lg, n >> 2 AS quarter, CAST(n % 7 AS INTEGER) AS rest FROM {_GRID_SQL}")
def math_sizing(spark: SparkSession, sf: str) -> DataFrame:
    from stagefilter.functions.sizing import hashes_col

    n, k = F.col("n"), hashes_col(F.col("fpr"))
    return _grid(spark).select("n", "fpr", k.alias("k"), F.round(F.pow(1 - F.exp(-k * n / (10.0 * n)), k), 9).alias("at_ten"), F.floor(F.log2(n)).cast("int").alias("lg"), F.shiftright(n, 2).alias("quarter"), F.pmod(n, F.lit(7)).cast("int").alias("rest"))


@query("SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(embedding[1]::DOUBLE, 6) AS first, list_sum(list_transform(embedding[1:3], lambda x: CASE WHEN x > 0 THEN 1 ELSE 0 END))::INTEGER AS head FROM embeddings")
def array_ops(spark: SparkSession, sf: str) -> DataFrame:
    v = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, sf, "embeddings").select(
        "vec_id", F.size("embedding").alias("n"), F.round(F.aggregate(F.zip_with(v, v, lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"),
        F.round(F.element_at(v, 1), 6).alias("first"), F.size(F.filter(F.slice("embedding", 1, 3), lambda x: x > 0)).alias("head"),
    )


@query("SELECT fpr, round(max(CASE WHEN n = 1000 THEN 1.4426950408889634 * n * log2(1 / fpr) END) / 1000, 6) AS small, 2 AS entries FROM " + _GRID_SQL + " GROUP BY fpr")
def map_measures(spark: SparkSession, sf: str) -> DataFrame:
    """Measures as a map from size to bits."""
    m = with_ideal_bits(_grid(spark)).groupBy("fpr").agg(F.map_from_entries(F.collect_list(F.struct("n", (F.lit(1.4426950408889634) * F.col("n") * F.log2(1 / F.col("fpr"))).alias("b")))).alias("m"))
    part = F.transform_values(F.map_filter("m", lambda k, v: k == 1000), lambda k, v: v / k)
    return m.select("fpr", F.round(F.element_at(part, F.lit(1000).cast("long")), 6).alias("small"), F.size("m").alias("entries"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def json_features(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k"))


@query(f"SELECT n, fpr, {_K} AS k, 'plain' AS role FROM {_GRID_SQL}")
def struct_plan(spark: SparkSession, sf: str) -> DataFrame:
    t = with_sizes(_grid(spark)).select(F.struct("n", "fpr", "k", "m").alias("p")).select(F.col("p").withField("role", F.lit("plain")).dropFields("m").alias("p"))
    return t.select("p.n", "p.fpr", "p.k", "p.role")


@query(f"SELECT shard, count(*) AS n FROM (SELECT {hash_sql('CAST(o_orderkey AS VARCHAR)')} % 16 AS shard FROM orders) GROUP BY shard")
def hash_buckets_md5(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "orders").groupBy((element_hash(F.col("o_orderkey")) % 16).alias("shard")).agg(F.count("*").alias("n"))


@query("SELECT * FROM (VALUES (1, 'a', 0.5::DOUBLE, true), (2, NULL, 1.0, false), (3, 'c', 0.0, false), (4, '', NULL, false)) v(i, eid, x, known)")
def null_policy(spark: SparkSession, sf: str) -> DataFrame:
    rows = spark.createDataFrame([(1, "a", 0.5), (2, None, 1.0), (3, "c", float("nan")), (4, "", None)], "i int, eid string, x double")
    f = BloomFilter.empty(4, 1e-6)
    import numpy as np

    f.insert(np.array([r.h for r in rows.filter("i = 1").select(element_hash(F.col("eid")).alias("h")).collect()]))
    return rows.select("i", "eid", F.nanvl(F.col("x"), F.lit(0.0)).alias("x"), f.contains(element_hash(F.col("eid"))).alias("known"))


# --- functions ------------------------------------------------------------------------


@query(f"WITH {_staged_sql()} SELECT split, count(*) FILTER (WHERE found) AS found FROM w GROUP BY split")
def udf_maybe_in(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    udfs.register(spark, staged=f, prefix="q1_")
    e.createOrReplaceTempView("stagefilter_udf")
    return spark.sql("SELECT split, count_if(q1_maybe_in(h, x)) AS found FROM stagefilter_udf GROUP BY split")


@query(f"WITH {scored_sql()} SELECT eid, round(s3, 9) AS s3 FROM q")
def udf_score_prefix(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    udfs.register(spark, staged=f, prefix="q2_")
    e.createOrReplaceTempView("stagefilter_udf2")
    return spark.sql("SELECT eid, round(q2_score_prefix(x)[2], 9) AS s3 FROM stagefilter_udf2")


@query(f"WITH {_staged_sql()} SELECT count(*) AS keys, count(*) FILTER (WHERE found) AS accepted FROM w WHERE split = 'key'")
def udtf_filter_path(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    udfs.register(spark, staged=f, prefix="q3_")
    e.filter("split = 'key'").createOrReplaceTempView("stagefilter_udf3")
    return spark.sql("SELECT count(*) AS keys, count_if(ok) AS accepted FROM (SELECT eid, bool_and(p.found) AS ok FROM stagefilter_udf3, LATERAL q3_filter_path(h, x) p GROUP BY eid)")


@query(f"SELECT CAST(i AS INTEGER) AS i, {position_sql('(987654321987654321::BIGINT)', 5, 'i', 1000)} AS p FROM generate_series(0, 3) g(i)")
def udtf_bloom_positions(spark: SparkSession, sf: str) -> DataFrame:
    udfs.register(spark, prefix="q4_")
    return spark.sql("SELECT i, p FROM q4_bloom_positions(987654321987654321, 5, 4, 1000)")


@query("SELECT * FROM (VALUES ('q5_bloom_has'), ('q5_maybe_in'), ('q5_score_prefix')) v(name)")
def sql_registered_functions(spark: SparkSession, sf: str) -> DataFrame:
    _, f = fixed_staged(spark, sf)
    names = udfs.register(spark, staged=f, bloom=BloomFilter.empty(10, 0.01), prefix="q5_")
    have = [n for n in names if spark.catalog.functionExists(n) and n not in ("q5_filter_path", "q5_bloom_positions")]
    return spark.createDataFrame([(n,) for n in have], "name string")


@query("SELECT c_mktsegment, count(*) AS n, 0::BIGINT AS missed FROM customer GROUP BY 1")
def grouped_filter_build(spark: SparkSession, sf: str) -> DataFrame:
    """A filter per group, built and checked where the group's rows are."""
    import numpy as np
    import pandas as pd

    def build(rows: pd.DataFrame) -> pd.DataFrame:
        f = BloomFilter.empty(len(rows), 0.01)
        h = rows.h.to_numpy(np.int64)
        f.insert(h)
        return pd.DataFrame({"c_mktsegment": [rows.c_mktsegment.iloc[0]], "n": [len(rows)], "missed": [int((~f.contains_np(h)).sum())]})

    c = table(spark, sf, "customer").select("c_mktsegment", element_hash(F.col("c_custkey")).alias("h"))
    return c.groupBy("c_mktsegment").applyInPandas(build, "c_mktsegment string, n long, missed long")


# --- streams --------------------------------------------------------------------------


def _stream(spark: SparkSession, sf: str) -> tuple[DataFrame, str]:
    # a file source wants a folder: the table through the shared scratch folder
    path = scratch(spark, "stream")
    e = table(spark, sf, "events")
    e.write.parquet(f"{path}/in")
    return service.event_stream(spark, f"{path}/in", e.schema), path


def _users(spark: SparkSession, sf: str) -> tuple[DataFrame, BloomFilter]:
    users = table(spark, sf, "events").filter("event_type = 'error'").select(element_hash(F.col("user_id")).alias("h")).distinct()
    return users, BloomFilter.build(users, "h", 1e-6, 1)


def _sink(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    import uuid

    return service.run_to_end(stream, f"s{uuid.uuid4().hex[:12]}", f"{path}/check", mode)


_ERR = "user_id IN (SELECT user_id FROM events WHERE event_type = 'error')"


@query(f"SELECT count(*) AS n, count(*) FILTER (WHERE {_ERR}) AS found FROM events")
def stream_lookup_batch(spark: SparkSession, sf: str) -> DataFrame:
    _, f = _users(spark, sf)
    s, path = _stream(spark, sf)
    out = _sink(service.lookup_stream(s, f, F.col("user_id")).select("event_id", "found"), path)
    return out.agg(F.count("*").alias("n"), F.count_if("found").alias("found"))


@query("SELECT count(DISTINCT user_id) AS keys, 0::BIGINT AS missed FROM events")
def stream_insert_batch(spark: SparkSession, sf: str) -> DataFrame:
    s, path = _stream(spark, sf)
    keys = s.select(element_hash(F.col("user_id")).alias("h"))
    shape = BloomFilter.empty(20_000, 0.01, 2)
    service.insert_stream(keys, shape, f"{path}/bits", f"{path}/check")
    f = service.live_filter(spark, shape, f"{path}/bits")
    users = table(spark, sf, "events").select("user_id").distinct()
    return users.agg(F.count("*").alias("keys"), F.count_if(~f.contains(element_hash(F.col("user_id")))).alias("missed"))


def _windowed(spark: SparkSession, sf: str, length: str, slide: str | None) -> DataFrame:
    _, f = _users(spark, sf)
    s, path = _stream(spark, sf)
    rows = service.lookup_stream(s, f, F.col("user_id")).select("ts", "found")
    out = _sink(service.windowed_rate(rows, length, slide), path, "complete")
    return out.select(F.unix_seconds("start").alias("start"), "n", "hits")


_WIN = f"epoch_us(ts) // 1000000 AS s, {_ERR} AS found FROM events"


@query(f"SELECT s // 86400 * 86400 AS start, count(*) AS n, count(*) FILTER (WHERE found) AS hits FROM (SELECT {_WIN}) GROUP BY 1")
def windowed_fpr_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return _windowed(spark, sf, "1 day", None)


@query(f"SELECT (s // 43200 - k) * 43200 AS start, count(*) AS n, count(*) FILTER (WHERE found) AS hits FROM (SELECT {_WIN}) CROSS JOIN generate_series(0, 1) g(k) GROUP BY 1")
def windowed_fpr_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return _windowed(spark, sf, "1 day", "12 hours")


@query(
    "WITH e AS (SELECT user_id, epoch_us(ts) AS t, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events), g AS (SELECT user_id, t, sum(CASE WHEN p IS NULL OR t - p >= 86400000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS g FROM e) SELECT user_id, count(*) AS n FROM g GROUP BY user_id, g"
)
def session_paths(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return service.sessions(e, "1 day", "user_id").select("user_id", "n")


@query("SELECT count(*) AS n FROM events")
def late_insert_count(spark: SparkSession, sf: str) -> DataFrame:
    """Keys are inserted whatever the watermark says: all rows arrive, late ones too."""
    s, path = _stream(spark, sf)
    out = _sink(s.withWatermark("ts", "1 hour").select("event_id"), path)
    return out.agg(F.count("*").alias("n"))


@query("SELECT count(DISTINCT user_id) AS n FROM events")
def stream_first_seen(spark: SparkSession, sf: str) -> DataFrame:
    s, path = _stream(spark, sf)
    return _sink(service.first_seen(s, "user_id", "4000 days").select("user_id"), path).agg(F.count("*").alias("n"))


@query("SELECT count(*) AS rows, true AS few_lost FROM events")
def stream_filter_state(spark: SparkSession, sf: str) -> DataFrame:
    """First-seen test by filter state: at most as many firsts as users, and nearly all of them."""
    s, path = _stream(spark, sf)
    out = _sink(service.keyed_filter_state(s.select(element_hash(F.col("user_id")).alias("h")), 4, 20_000, 0.001), path)
    users = table(spark, sf, "events").select("user_id").distinct().count()
    return out.agg(F.count("*").alias("rows"), F.count_if("new").between(int(0.98 * users), users).alias("few_lost"))


@query("SELECT a.event_type, b.event_type AS other_type, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.user_id IN (SELECT user_id FROM events WHERE event_type = 'error') AND a.event_id <> b.event_id GROUP BY ALL")
def stream_stream_join(spark: SparkSession, sf: str) -> DataFrame:
    """Two streams of events behind one filter, joined by user within an hour; watermarks bound the state of both sides."""
    users, f = _users(spark, sf)
    sides = []
    for name in ("a", "b"):
        s, path = _stream(spark, sf)
        known = service.lookup_stream(s, f, F.col("user_id")).filter("found")
        sides.append(known.select(F.col("event_id").alias(f"{name}_id"), F.col("user_id").alias(f"{name}_user"), F.col("ts").cast("timestamp").alias(f"{name}_ts"), F.col("event_type").alias(f"{name}_type")).withWatermark(f"{name}_ts", "2 hours"))
    on = F.expr("a_user = b_user AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL 1 HOUR AND a_id <> b_id")
    out = _sink(sides[0].join(sides[1], on), path)
    exact = out.withColumn("h", element_hash(F.col("a_user"))).join(users, "h", "left_semi")
    return exact.groupBy(F.col("a_type").alias("event_type"), F.col("b_type").alias("other_type")).agg(F.count("*").alias("n"))


@query("SELECT c_nationkey, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(spark: SparkSession, sf: str) -> DataFrame:
    s, path = _stream(spark, sf)
    c = table(spark, sf, "customer").select("c_custkey", "c_nationkey")
    out = _sink(s.join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_nationkey"), path)
    return out.groupBy("c_nationkey").agg(F.count("*").alias("n"))


@query("SELECT * FROM (VALUES (0.05::DOUBLE, false), (0.2, true)) v(share, rebuild)")
def rebuild_trigger(spark: SparkSession, sf: str) -> DataFrame:
    _, f = fixed_staged(spark, sf)
    n = f.plan.flow.n_keys
    rows = [(x, service.needs_rebuild(service.health(f, int(x * n)) | {"estimated_fpr": 0.0}, 0.01)) for x in (0.05, 0.2)]
    return spark.createDataFrame(rows, "share double, rebuild boolean")
