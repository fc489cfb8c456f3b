"""Queries of the method: inputs, plain filters, scores, flow, regions, configuration, lookups, baselines, measures."""

from __future__ import annotations

import itertools
import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stagefilter import experiments as X
from stagefilter import measures as M
from stagefilter.functions.hashing import BLOCK_BITS, block_sql, hash_sql, position_sql, uniform, uniform_sql
from stagefilter.functions.sizing import LOG2E, bloom_bits_col, bloom_size, hashes_col, ideal_bits_col
from stagefilter.operators import amq
from stagefilter.operators import baselines as B
from stagefilter.operators.bloom import BloomFilter, ShardedBloom, position_rows, probe_rows
from stagefilter.operators.boosting import Boosting
from stagefilter.operators.flow import exit_depth, measure_flow
from stagefilter.operators.staged import FAMILIES, StagedFilter, build
from stagefilter.plans.config_dp import Costs, Flow, configure, configure_bruteforce, evaluate, make_flow
from stagefilter.plans.partition import partition_scores
from stagefilter.queries.base import BINS, DEPTH, LABEL, THETAS, bin_sql, ensemble, examples, flow_sql, scored, scored_sql
from stagefilter.sources.workloads import LINE_KEY, WORKLOADS, load, table

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        Q[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


# --- inputs ---------------------------------------------------------------------------

_LINE_LABEL = "l_extendedprice / 1000 + 200 * l_discount - l_quantity > 36"
_LINE = f"""e AS (SELECT concat_ws('-', {', '.join(LINE_KEY)}) AS eid, {_LINE_LABEL} AS raw FROM lineitem),
n AS (SELECT eid, bool_or(CASE WHEN {uniform_sql('flip', 'eid')} < 0.25 THEN NOT raw ELSE raw END) AS is_key, bool_or(raw) AS raw FROM e GROUP BY eid),
k AS (SELECT *, {hash_sql('eid')} AS h FROM n),
p AS (SELECT *, CASE WHEN is_key THEN 'key' WHEN h % 1000 < 100 THEN 'test' WHEN h % 10 = 9 THEN 'calib' ELSE 'train' END AS split FROM k)"""


@query(f"WITH {_LINE} SELECT eid, h, is_key, split FROM p")
def examples_physics(spark: SparkSession, sf: str) -> DataFrame:
    return load("physics_hard", spark, sf).select("eid", "h", "is_key", "split")


@query(f"WITH {scored_sql()} SELECT eid, h, is_key, split FROM q")
def examples_orders(spark: SparkSession, sf: str) -> DataFrame:
    return scored(spark, sf).select("eid", "h", "is_key", "split")


@query(
    "WITH u AS (SELECT DISTINCT url || '/v' || CAST(i AS VARCHAR) AS eid FROM pages CROSS JOIN generate_series(0, 39) g(i)) SELECT eid, "
    + hash_sql("eid")
    + " AS h FROM u"
)
def examples_url(spark: SparkSession, sf: str) -> DataFrame:
    return load("url_easy", spark, sf).select("eid", "h")


@query("SELECT sha256(text) AS eid, max(quality) = 0 OR min(quality) = 0 AS is_key FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def examples_file(spark: SparkSession, sf: str) -> DataFrame:
    return load("file_wide", spark, sf).select("eid", "is_key")


@query("SELECT CAST(vec_id AS VARCHAR) AS eid, label < 5 AS is_key FROM embeddings")
def examples_vec(spark: SparkSession, sf: str) -> DataFrame:
    return load("null_vec", spark, sf).select("eid", "is_key")


@query(f"WITH {_LINE} SELECT split, count(*) AS n FROM p GROUP BY split")
def split_counts(spark: SparkSession, sf: str) -> DataFrame:
    return load("physics_hard", spark, sf).groupBy("split").agg(F.count("*").alias("n"))


@query(f"WITH {_LINE} SELECT count(*) AS n FROM (SELECT eid FROM p WHERE is_key INTERSECT SELECT eid FROM p WHERE NOT is_key)")
def disjointness_check(spark: SparkSession, sf: str) -> DataFrame:
    e = load("physics_hard", spark, sf)
    return e.filter("is_key").select("eid").join(e.filter("not is_key").select("eid"), "eid", "left_semi").agg(F.count("*").alias("n"))


@query(f"WITH {_LINE} SELECT round(avg(CASE WHEN is_key <> raw THEN 1.0 ELSE 0.0 END), 6) AS rate FROM p")
def noise_flip_rate(spark: SparkSession, sf: str) -> DataFrame:
    rows = table(spark, sf, "lineitem").select(F.concat_ws("-", *LINE_KEY).alias("eid"))
    return rows.agg(F.round(F.avg(F.when(uniform("flip", F.col("eid")) < 0.25, 1.0).otherwise(0.0)), 6).alias("rate"))


def _share(name: str, eid: str, label: str, source: str, flip: float = 0.0) -> str:
    noisy = f"CASE WHEN {uniform_sql('flip', 'eid')} < {flip} THEN NOT l ELSE l END" if flip else "l"
    return f"SELECT '{name}' AS workload, count(*) AS n, sum(CAST(k AS INTEGER)) AS keys FROM (SELECT eid, bool_or({noisy}) AS k FROM (SELECT CAST({eid} AS VARCHAR) AS eid, {label} AS l FROM {source}) GROUP BY eid)"


_LABELLED = "documents JOIN labels USING (doc_id)"
_E = [f"embedding[{i}]" for i in range(1, 5)]


@query(
    " UNION ALL ".join(
        [
            _share("url_easy", "url || '/v' || CAST(i AS VARCHAR)", "regexp_matches(url, '[?#]')", "pages CROSS JOIN generate_series(0, 39) g(i)", 0.05),
            _share("file_wide", "sha256(text)", "quality = 0", _LABELLED), _share("doc_toxic", "sha256(text)", "toxic = 1", _LABELLED),
            _share("doc_lang", "sha256(text)", "lang <> 'en'", "documents"), _share("physics_hard", f"concat_ws('-', {', '.join(LINE_KEY)})", _LINE_LABEL, "lineitem", 0.25),
            _share("null_rows", f"concat_ws('-', {', '.join(LINE_KEY)})", "l_returnflag = 'R'", "lineitem"), _share("null_vec", "vec_id", "label < 5", "embeddings"),
            _share("vec_linear", "vec_id", f"{_E[0]} + {_E[1]} - {_E[2]} + {_E[3]} > 0", "embeddings", 0.02),
            _share("orders_mix", "o_orderkey", "(o_totalprice > 300000 OR o_orderdate < TIMESTAMP '1996-06-01')", "orders", 0.1), _share("cust_sep", "c_custkey", "c_acctbal < 0", "customer"),
            _share("part_box", "p_partkey", "(p_retailprice > 950 AND p_size < 30)", "part", 0.03), _share("event_tail", "event_id", "value > 60", "events", 0.1),
            _share("turn_role", "concat_ws('-', conv_id, turn)", "role = 'assistant'", "conversations"),
        ]
    )
)
def key_share_workloads(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for name in WORKLOADS:
        if name != "ngram_bench":
            part = load(name, spark, sf).agg(F.lit(name).alias("workload"), F.count("*").alias("n"), F.sum(F.col("is_key").cast("int")).alias("keys"))
            out = part if out is None else out.unionAll(part)
    return out


@query()
def examples_ngram(spark: SparkSession, sf: str) -> DataFrame:
    return load("ngram_bench", spark, sf).groupBy("is_key", "split").agg(F.count("*").alias("n"))


# --- plain filters --------------------------------------------------------------------

_GRID = [(n, f) for n in (1000, 60000) for f in (0.1, 0.05, 0.01, 0.001, 1e-6)]
_GRID_SQL = "(VALUES " + ", ".join(f"({n}::BIGINT, {f}::DOUBLE)" for n, f in _GRID) + ") g(n, fpr)"


def _grid(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(_GRID, "n long, fpr double")


#: The same rates with the sizes of real key sets: the keys among the orders of each priority.
_SETS_SQL = f"(SELECT n, fpr FROM (SELECT DISTINCT count(*) AS n FROM orders WHERE {LABEL} GROUP BY o_orderpriority) CROSS JOIN (VALUES " + ", ".join(f"({f}::DOUBLE)" for f in dict.fromkeys(f for _, f in _GRID)) + ") v(fpr)) g"


def _key_sets(spark: SparkSession, sf: str) -> DataFrame:
    n = table(spark, sf, "orders").filter(LABEL).groupBy("o_orderpriority").agg(F.count("*").alias("n")).select("n").distinct()
    return n.crossJoin(F.broadcast(spark.createDataFrame([(f,) for f in dict.fromkeys(f for _, f in _GRID)], "fpr double")))


_K = "greatest(1, CAST(round(log2(1 / fpr)) AS INTEGER))"


@query(f"SELECT n, fpr, {_K} AS k, CAST(ceil(-{_K} * n / ln(1 - pow(fpr, 1.0::DOUBLE / {_K}))) AS BIGINT) AS m FROM {_SETS_SQL}")
def bloom_size_grid(spark: SparkSession, sf: str) -> DataFrame:
    return with_sizes(_key_sets(spark, sf))


def with_sizes(g: DataFrame) -> DataFrame:
    return g.select("n", "fpr", hashes_col(F.col("fpr")).alias("k"), bloom_bits_col(F.col("n"), F.col("fpr")).alias("m"))


@query(f"SELECT n, fpr, round({LOG2E} * n * log2(1 / fpr), 3) AS bits FROM {_SETS_SQL}")
def bloom_ideal_bits(spark: SparkSession, sf: str) -> DataFrame:
    return with_ideal_bits(_key_sets(spark, sf))


def with_ideal_bits(g: DataFrame) -> DataFrame:
    return g.select("n", "fpr", F.round(ideal_bits_col(F.col("n"), F.col("fpr")), 3).alias("bits"))


_M, _KH, _SEED = 60000, 5, 3
_SET = f"s AS (SELECT DISTINCT {position_sql('h', _SEED, 'i', _M)} AS p FROM q CROSS JOIN generate_series(0, {_KH - 1}) g(i) WHERE is_key)"
_FOUND = f"""{scored_sql()}, {_SET},
a AS (SELECT DISTINCT eid, {position_sql('h', _SEED, 'i', _M)} AS p FROM q CROSS JOIN generate_series(0, {_KH - 1}) g(i)),
w AS (SELECT a.eid, bool_and(s.p IS NOT NULL) AS found FROM a LEFT JOIN s USING (p) GROUP BY a.eid),
v AS (SELECT q.eid, q.split, w.found FROM q JOIN w USING (eid))"""


def _fixed(spark: SparkSession, sf: str) -> tuple[DataFrame, BloomFilter]:
    q = scored(spark, sf)
    f = BloomFilter(_M, _KH, _SEED, np.zeros(-(-_M // 8), np.uint8), 0.05)
    from stagefilter.functions.hashing import positions
    from stagefilter.operators.bloom import bitmaps

    for r in bitmaps(q.filter("is_key").select(F.explode(positions(F.col("h"), _SEED, _KH, _M)).alias("p"))).toLocalIterator():
        part, a = np.frombuffer(bytes(r.bits), np.uint8), r.block * BLOCK_BITS // 8
        f.bits[a : a + len(part)] |= part[: len(f.bits) - a]
    return q, f


@query(f"WITH {scored_sql()}, {_SET} SELECT count(*) AS ones, min(p) AS low, max(p) AS high FROM s")
def bloom_bits_sql(spark: SparkSession, sf: str) -> DataFrame:
    return position_rows(scored(spark, sf).filter("is_key"), "h", _SEED, _KH, _M).agg(F.count("*").alias("ones"), F.min("p").alias("low"), F.max("p").alias("high"))


@query(f"WITH {_FOUND} SELECT eid, split FROM v WHERE found")
def bloom_lookup_sql(spark: SparkSession, sf: str) -> DataFrame:
    q = scored(spark, sf)
    return probe_rows(q.select("eid", "split", "h"), position_rows(q.filter("is_key"), "h", _SEED, _KH, _M), "h", _SEED, _KH, _M).select("eid", "split")


@query(f"WITH {_FOUND} SELECT eid, split FROM v WHERE found")
def bloom_broadcast_probe(spark: SparkSession, sf: str) -> DataFrame:
    q, f = _fixed(spark, sf)
    return q.filter(f.contains(F.col("h"))).select("eid", "split")


@query(f"WITH {_FOUND} SELECT split, count(*) AS n, round(avg(CAST(found AS INTEGER)), 6) AS rate FROM v GROUP BY split")
def bloom_fpr_sql(spark: SparkSession, sf: str) -> DataFrame:
    q, f = _fixed(spark, sf)
    return q.select("split", f.contains(F.col("h")).alias("found")).groupBy("split").agg(F.count("*").alias("n"), F.round(F.avg(F.col("found").cast("int")), 6).alias("rate"))


@query(f"WITH {scored_sql()} SELECT count(*) AS keys, 0::BIGINT AS missed FROM q WHERE is_key")
def bloom_no_false_negative(spark: SparkSession, sf: str) -> DataFrame:
    q = scored(spark, sf).filter("is_key")
    f = BloomFilter.build(q, "h", 0.01, 9)
    return q.agg(F.count("*").alias("keys"), F.count_if(~f.contains(F.col("h"))).alias("missed"))


_BK = bloom_size(1000, 0.01 / 1.03)[1]


@query(
    f"""WITH {scored_sql()},
c AS (SELECT greatest(1, CAST(ceil(ceil(-{_BK} * count(*) / ln(1 - pow({0.01 / 1.03}::DOUBLE, 1.0::DOUBLE / {_BK}))) / {BLOCK_BITS}) AS BIGINT)) AS blocks FROM q WHERE is_key),
s AS (SELECT DISTINCT {block_sql('h', 4, 'c.blocks')} AS b, {position_sql('h', 4, 'i', BLOCK_BITS)} AS p FROM q, c, generate_series(0, {_BK - 1}) g(i) WHERE is_key),
a AS (SELECT eid, split, {block_sql('h', 4, 'c.blocks')} AS b, {position_sql('h', 4, 'i', BLOCK_BITS)} AS p FROM q, c, generate_series(0, {_BK - 1}) g(i))
SELECT a.eid, a.split, bool_and(s.p IS NOT NULL) AS found FROM a LEFT JOIN s ON a.b = s.b AND a.p = s.p GROUP BY a.eid, a.split"""
)
def bloom_sharded_probe(spark: SparkSession, sf: str) -> DataFrame:
    q = scored(spark, sf)
    return ShardedBloom.build(q.filter("is_key"), "h", 0.01, 4).probe(q.select("eid", "split", "h")).select("eid", "split", "found")


@query(f"WITH {scored_sql()} SELECT count(*) AS keys, true AS all_found, true AS rate_ok FROM q WHERE is_key")
def bloom_jvm_crosscheck(spark: SparkSession, sf: str) -> DataFrame:
    """The library's own filter and ours on the same keys: both find all of them; ours keeps to its rate within four deviations."""
    q = scored(spark, sf)
    keys = q.filter("is_key")
    n = keys.count()
    theirs = keys._jdf.stat().bloomFilter("h", n, 0.01)
    sample = [r.h for r in keys.orderBy("h").limit(500).collect()]
    ours = BloomFilter.build(keys, "h", 0.01, 9, n)
    r = q.filter("not is_key").agg(F.avg(ours.contains(F.col("h")).cast("int")).alias("rate"), F.count("*").alias("n")).first()
    ok = r.rate <= 0.01 + 4 * math.sqrt(0.01 * 0.99 / r.n)
    return spark.createDataFrame([(n, all(theirs.mightContainLong(h) for h in sample) and bool(ours.contains_np(np.array(sample)).all()), ok)], "keys long, all_found boolean, rate_ok boolean")


def _amq(kind: str):
    @query(f"WITH {scored_sql()} SELECT count(*) AS keys, 0::BIGINT AS missed, true AS rate_ok FROM q WHERE is_key")
    def run(spark: SparkSession, sf: str) -> DataFrame:
        q = scored(spark, sf)
        t = amq.build_sharded(q.filter("is_key"), kind, 0.01, 4)
        v = q.select("h", "is_key").join(amq.probe_sharded(q, t, 4), "h")
        rate = F.avg(F.when(~F.col("is_key"), F.col("found").cast("int")))
        return v.agg(F.count_if("is_key").alias("keys"), F.count_if(F.col("is_key") & ~F.col("found")).alias("missed"), (rate <= 0.025).alias("rate_ok"))

    return run


for _kind in ("counting", "cuckoo", "quotient"):
    _f = _amq(_kind)
    Q[f"{_kind}_filter_probe"], SQL[f"{_kind}_filter_probe"] = Q["run"], SQL["run"]
del Q["run"], SQL["run"]


@query(
    f"""WITH {scored_sql()}, c AS (SELECT h, 1 AS sign FROM q WHERE is_key UNION ALL SELECT h, -1 FROM q WHERE is_key AND h % 3 = 0),
t AS (SELECT {position_sql('h', 8, 'i', 50000)} AS p, sum(sign) AS count FROM c CROSS JOIN generate_series(0, 4) g(i) GROUP BY 1 HAVING sum(sign) > 0)
SELECT count(*) AS cells, CAST(sum(count) AS BIGINT) AS total, CAST(max(count) AS BIGINT) AS most FROM t"""
)
def counting_deletes(spark: SparkSession, sf: str) -> DataFrame:
    keys = scored(spark, sf).filter("is_key").select("h")
    changes = keys.withColumn("sign", F.lit(1)).unionAll(keys.filter("h % 3 = 0").withColumn("sign", F.lit(-1)))
    return amq.CountingBloom.table(changes, 8, 5, 50000).agg(F.count("*").alias("cells"), F.sum("count").alias("total"), F.max("count").alias("most"))


# --- scores and flow ------------------------------------------------------------------


@query(f"WITH {scored_sql()} SELECT eid, s1, s2, s3, s4 FROM q")
def table_scores(spark: SparkSession, sf: str) -> DataFrame:
    return scored(spark, sf).select("eid", *[F.get("s", F.lit(i)).alias(f"s{i + 1}") for i in range(DEPTH)])


@query(f"WITH {scored_sql()} SELECT eid, round(s1, 9) AS s1, round(s4, 9) AS s4 FROM q")
def prefix_scores(spark: SparkSession, sf: str) -> DataFrame:
    from stagefilter.operators.scoring import score_prefixes

    s = score_prefixes(examples(spark, sf), ensemble(), ("eid",))
    return s.select("eid", F.round(F.get("s", F.lit(0)), 9).alias("s1"), F.round(F.get("s", F.lit(3)), 9).alias("s4"))


@query(f"WITH {flow_sql()} SELECT depth, cls, bin, cnt FROM f WHERE theta_id = 0 AND bin >= 0")
def score_hist(spark: SparkSession, sf: str) -> DataFrame:
    return measure_flow(scored(spark, sf), [THETAS[0]], BINS).filter("bin >= 0").select("depth", "cls", "bin", "cnt")


@query(f"WITH {scored_sql()} SELECT a AS alpha, round(quantile_cont(s4, 1 - a), 6) AS theta FROM q CROSS JOIN (VALUES (0.1::DOUBLE), (0.01::DOUBLE), (0.001::DOUBLE), (0.0::DOUBLE)) v(a) WHERE split = 'calib' GROUP BY a".replace("quantile_cont(s4, 1 - a)", "CASE WHEN a = 0.1 THEN quantile_cont(s4, 0.9) WHEN a = 0.01 THEN quantile_cont(s4, 0.99) WHEN a = 0.001 THEN quantile_cont(s4, 0.999) ELSE max(s4) END"))
def quantile_thresholds(spark: SparkSession, sf: str) -> DataFrame:
    from stagefilter.operators.flow import quantile_thetas

    alphas = (0.1, 0.01, 0.001, 0.0)
    q = scored(spark, sf).persist()
    rows = [(a, round(float(quantile_thetas(q, (a,), never=False)[0][3]), 6)) for a in alphas]
    q.unpersist()
    return spark.createDataFrame(rows, "alpha double, theta double")


@query(
    f"""WITH {scored_sql()} SELECT t / 10.0 AS theta, count(*) FILTER (WHERE is_key AND s4 >= t / 10.0) AS tp, count(*) FILTER (WHERE NOT is_key AND s4 >= t / 10.0) AS fp,
count(*) FILTER (WHERE is_key AND s4 < t / 10.0) AS fn, count(*) FILTER (WHERE NOT is_key AND s4 < t / 10.0) AS tn FROM q CROSS JOIN generate_series(0, 10) g(t) WHERE split IN ('key', 'calib') GROUP BY t"""
)
def confusion_by_threshold(spark: SparkSession, sf: str) -> DataFrame:
    q = scored(spark, sf).filter("split in ('key', 'calib')").select("is_key", F.get("s", F.lit(3)).alias("s"))
    t = q.groupBy("is_key", "s").agg(F.count("*").alias("n"))  # few distinct scores; the thresholds meet those
    g = spark.range(11).select((F.col("id") / 10.0).alias("theta"))
    hit = F.col("s") >= F.col("theta")
    cell = lambda k, over: F.sum(F.when(k & over, F.col("n")).otherwise(0))
    k = F.col("is_key")
    return t.join(F.broadcast(g)).groupBy("theta").agg(cell(k, hit).alias("tp"), cell(~k, hit).alias("fp"), cell(k, ~hit).alias("fn"), cell(~k, ~hit).alias("tn"))


@query(
    f"""WITH {flow_sql()}, r AS (SELECT bin, sum(CASE WHEN cls = 1 THEN cnt ELSE 0 END) AS k, sum(CASE WHEN cls = 0 THEN cnt ELSE 0 END) AS n FROM f WHERE theta_id = 0 AND depth = 4 AND bin >= 0 GROUP BY bin)
SELECT bin, round(sum(k) OVER (ORDER BY bin DESC) * 1.0 / sum(k) OVER (), 6) AS tpr, round(sum(n) OVER (ORDER BY bin DESC) * 1.0 / sum(n) OVER (), 6) AS fpr FROM r"""
)
def roc_points(spark: SparkSession, sf: str) -> DataFrame:
    h = measure_flow(scored(spark, sf), [THETAS[0]], BINS).filter("bin >= 0 and depth = 4")
    r = h.groupBy("bin").agg(F.sum(F.when(F.col("cls") == 1, F.col("cnt")).otherwise(0)).alias("k"), F.sum(F.when(F.col("cls") == 0, F.col("cnt")).otherwise(0)).alias("n"))
    down, all_ = Window.orderBy(F.desc("bin")), Window.partitionBy()
    return r.select("bin", F.round(F.sum("k").over(down) / F.sum("k").over(all_), 6).alias("tpr"), F.round(F.sum("n").over(down) / F.sum("n").over(all_), 6).alias("fpr"))


@query(f"WITH {scored_sql()} SELECT eid, CASE WHEN s1 >= 0.4 THEN 1 WHEN s2 >= 0.4 THEN 2 WHEN s3 >= 0.4 THEN 3 ELSE 4 END AS depth FROM q")
def exit_depths(spark: SparkSession, sf: str) -> DataFrame:
    return scored(spark, sf).select("eid", exit_depth(F.col("s"), THETAS[3]).alias("depth"))


@query(f"WITH {flow_sql()} SELECT theta_id, depth, cls, bin, cnt FROM f")
def flow_shares(spark: SparkSession, sf: str) -> DataFrame:
    return measure_flow(scored(spark, sf), THETAS, BINS)


@query(
    f"""WITH {flow_sql()}, r AS (SELECT theta_id, depth, cls, sum(CASE WHEN bin >= 0 THEN cnt ELSE 0 END) AS reach, sum(CASE WHEN bin < 0 THEN cnt ELSE 0 END) AS leave FROM f GROUP BY ALL)
SELECT a.theta_id, a.cls, a.depth, CAST(a.reach AS BIGINT) AS reach, coalesce(b.reach = a.reach - a.leave, true) AS conserved FROM r a LEFT JOIN r b ON b.theta_id = a.theta_id AND b.cls = a.cls AND b.depth = a.depth + 1"""
)
def flow_conservation(spark: SparkSession, sf: str) -> DataFrame:
    f = measure_flow(scored(spark, sf), THETAS, BINS)
    r = f.groupBy("theta_id", "cls", "depth").agg(F.sum(F.when(F.col("bin") >= 0, F.col("cnt")).otherwise(0)).alias("reach"), F.sum(F.when(F.col("bin") < 0, F.col("cnt")).otherwise(0)).alias("leave"))
    w = Window.partitionBy("theta_id", "cls").orderBy("depth")
    return r.select("theta_id", "cls", "depth", "reach", F.coalesce(F.lead("reach").over(w) == F.col("reach") - F.col("leave"), F.lit(True)).alias("conserved"))


_GATES = (0.5, 0.25, 1.0, 0.5)


@query(
    f"""WITH {flow_sql()}, r AS (SELECT depth, sum(cnt) * 1.0 / (SELECT sum(cnt) FROM f WHERE theta_id = 3 AND depth = 1 AND cls = 0 AND bin >= 0) AS share FROM f WHERE theta_id = 3 AND cls = 0 AND bin >= 0 GROUP BY depth)
SELECT depth, round(share * CASE depth WHEN 1 THEN 0.5 WHEN 2 THEN 0.125 WHEN 3 THEN 0.125 ELSE 0.0625 END, 6) AS reaching FROM r"""
)
def flow_with_gates(spark: SparkSession, sf: str) -> DataFrame:
    """Non-key shares that reach each scorer once gates are in: shares without gates times the running product of the gate rates."""
    r = measure_flow(scored(spark, sf), [THETAS[3]], BINS).filter("cls = 0 and bin >= 0").groupBy("depth").agg(F.sum("cnt").alias("n"))
    gate = F.element_at(F.array(*[F.lit(g) for g in _GATES]), F.col("depth"))
    w = Window.orderBy("depth")
    return r.select("depth", F.round(F.col("n") / F.first("n").over(w) * F.exp(F.sum(F.ln(gate)).over(w)), 6).alias("reaching"))


# --- regions --------------------------------------------------------------------------

_HIST = f"""{flow_sql()}, r AS (SELECT b AS bin, coalesce(sum(cnt) FILTER (WHERE cls = 1), 0) AS k, coalesce(sum(cnt) FILTER (WHERE cls = 0), 0) AS n FROM generate_series(0, {BINS - 1}) g(b) LEFT JOIN f ON f.bin = b AND theta_id = 0 AND depth = 4 GROUP BY b),
t AS (SELECT sum(k) AS kt, sum(n) AS nt FROM r),
c AS (SELECT bin + 1 AS e, sum(k) OVER (ORDER BY bin) / kt AS ck, sum(n) OVER (ORDER BY bin) / nt AS cn FROM r, t UNION ALL SELECT 0, 0.0, 0.0)"""


def _hist(spark: SparkSession, sf: str) -> tuple[np.ndarray, np.ndarray]:
    out = np.zeros((2, BINS))
    for r in measure_flow(scored(spark, sf), [THETAS[0]], BINS).filter("depth = 4 and bin >= 0").collect():
        out[r.cls, r.bin] = r.cnt
    return out[1], out[0]


@query(f"WITH {_HIST} SELECT CAST(e AS INTEGER) AS edge, round(ck, 6) AS keys, round(cn, 6) AS others FROM c")
def kl_prefix(spark: SparkSession, sf: str) -> DataFrame:
    h = measure_flow(scored(spark, sf), [THETAS[0]], BINS).filter("depth = 4 and bin >= 0")
    grid = spark.range(-1, BINS).select(F.col("id").cast("int").alias("bin"))
    r = grid.join(h, "bin", "left").groupBy("bin").agg(F.sum(F.when(F.col("cls") == 1, F.col("cnt")).otherwise(0)).alias("k"), F.sum(F.when(F.col("cls") == 0, F.col("cnt")).otherwise(0)).alias("n"))
    w, all_ = Window.orderBy("bin"), Window.partitionBy()
    return r.select((F.col("bin") + 1).alias("edge"), F.round(F.sum("k").over(w) / F.sum("k").over(all_), 6).alias("keys"), F.round(F.sum("n").over(w) / F.sum("n").over(all_), 6).alias("others"))


def _term(a: str, b: str) -> str:
    return f"(CASE WHEN {b}.ck - {a}.ck > 1e-15 THEN ({b}.ck - {a}.ck) * log2(({b}.ck - {a}.ck) / greatest({b}.cn - {a}.cn, 1e-9)) ELSE 0 END)"


_K2 = f"SELECT {_term('z', 'x')} + {_term('x', 'o')} AS kl FROM c z, c x, c o WHERE z.e = 0 AND o.e = {BINS} AND x.e BETWEEN 1 AND {BINS - 1} UNION ALL SELECT {_term('z', 'o')} FROM c z, c o WHERE z.e = 0 AND o.e = {BINS}"
_K3 = f"SELECT {_term('z', 'x')} + {_term('x', 'y')} + {_term('y', 'o')} AS kl FROM c z, c x, c y, c o WHERE z.e = 0 AND o.e = {BINS} AND x.e BETWEEN 1 AND {BINS - 1} AND y.e BETWEEN x.e + 1 AND {BINS - 1} UNION ALL {_K2}"


@query(f"WITH {_HIST} SELECT round(max(kl), 6) AS kl FROM ({_K2})")
def kl_best_split_k2(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(round(partition_scores(*_hist(spark, sf), 2)[1], 6),)], "kl double")


@query(f"WITH {_HIST} SELECT round(max(kl), 6) AS kl FROM ({_K3})")
def kl_best_split_k3(spark: SparkSession, sf: str) -> DataFrame:
    values = {m: round(partition_scores(*_hist(spark, sf), 3, m)[1], 6) for m in ("fast", "classic", "brute")}
    assert len(set(values.values())) == 1, values
    return spark.createDataFrame([(values["fast"],)], "kl double")


_REGIONS = [(0, 0.0, 0.3), (1, 0.3, 0.7), (2, 0.7, 1.0)]


@query(f"WITH {scored_sql()} SELECT eid, CASE WHEN s4 < 0.3 THEN 0 WHEN s4 < 0.7 THEN 1 ELSE 2 END AS region FROM q")
def region_assign(spark: SparkSession, sf: str) -> DataFrame:
    from stagefilter.operators.joins import region_join

    r = spark.createDataFrame(_REGIONS, "region int, lo double, hi double")
    return region_join(scored(spark, sf).select("eid", F.get("s", F.lit(3)).alias("score")), "score", r).select("eid", "region")


# --- configuration: the hand-checkable example ----------------------------------------


def toy(n: int = 1000) -> tuple[Flow, Costs]:
    a = np.array
    f = Flow(n, a([1, 0.5]), a([1, 0.9]), a([0.5, 0]), a([0.1, 0]), [a([0.3, 0.7]), a([0.2, 0.3])], [a([0.8, 0.2]), a([0.75, 0.15])], [[50], [50]], a([0.5, 0.5]))
    return f, Costs(a([200.0, 200.0]), a([1.0, 1.0]), LOG2E * n * math.log2(100), 1.0)


_C = repr(LOG2E * 1000)


def _bits_sql(a: float, b: float, e: str) -> str:
    return f"({_C} * {a} * log2(1 / least(1, 0.01 * {a} / ({b} * pow(2.0, -({e}))))))"


_TOY = f"""g AS (SELECT i, j FROM generate_series(0, 2) a(i), generate_series(0, 2) b(j)),
m AS (SELECT 1 AS depth, i, 0 AS j, 200 + {_C} * i + {_bits_sql(.3, .8, 'i')} + {_bits_sql(.7, .2, 'i')} AS memory, pow(2.0, -i) AS reject FROM g WHERE j = 0
      UNION ALL SELECT 2, i, j, 400 + {_C} * i + {_C} * 0.5 * j + {_bits_sql(.5, .1, 'i')} + {_bits_sql(.2, .75, 'i + j')} + {_bits_sql(.3, .15, 'i + j')}, pow(2.0, -i) + 0.9 * pow(2.0, -(i + j)) FROM g WHERE i + j <= 2
      UNION ALL SELECT 0, 0, 0, {_C} * log2(100.0), 0.0)"""
_LAMS = (0.0, 0.3, 0.5, 0.9, 1.0)
#: Bits per halved rate of the keys among the orders, in place of the example's thousand.
_ORDERS_C = f"({LOG2E!r}::DOUBLE * (SELECT count(*) FROM orders WHERE {LABEL}))"


def orders_keys(spark: SparkSession, sf: str) -> int:
    return table(spark, sf, "orders").filter(LABEL).count()



@query(f"WITH {_TOY} SELECT depth, CAST(i AS INTEGER) AS i, CAST(j AS INTEGER) AS j, round(memory, 3) AS memory, round(reject, 6) AS reject FROM m")
def plan_cost_bruteforce(spark: SparkSession, sf: str) -> DataFrame:
    f, c = toy()
    rows = []
    for gates in [[], *[[i] for i in range(3)], *[[i, j] for i in range(3) for j in range(3 - i)]]:
        p = evaluate(f, c, 0.01, 1.0, gates)
        rows.append((p.depth, (gates + [0, 0])[0], (gates + [0, 0])[1], round(float(p.memory), 3), round(float(p.reject), 6)))
    return spark.createDataFrame(rows, "depth int, i int, j int, memory double, reject double")


def _best(lam: str) -> str:
    return f"round({lam} * memory / ({_C} * log2(100.0)) + (1 - {lam}) * reject, 6)"


@query(
    f"""WITH {_TOY.replace(_C, _ORDERS_C)}, o AS (SELECT l AS lam, depth, memory, reject, {_best('l').replace(_C, _ORDERS_C)} AS objective FROM m CROSS JOIN (VALUES {', '.join(f'({x}::DOUBLE)' for x in _LAMS)}) v(l)),
r AS (SELECT *, row_number() OVER (PARTITION BY lam ORDER BY objective, round(reject, 9), round(memory, 6), depth) AS k FROM o) SELECT lam, depth, objective, round(memory, 3) AS memory, round(reject, 6) AS reject FROM r WHERE k = 1"""
)
def lambda_frontier(spark: SparkSession, sf: str) -> DataFrame:
    """Best plans along lambda for as many keys as the orders have, in the example's shares."""
    f, c = toy(orders_keys(spark, sf))
    plans = [configure(f, c, 0.01, lam, 3) for lam in _LAMS]
    return spark.createDataFrame([(p.lam, p.depth, round(float(p.objective), 6), round(float(p.memory), 3), round(float(p.reject), 6)) for p in plans], "lam double, depth int, objective double, memory double, reject double")


@query(f"WITH {scored_sql()} SELECT count(*) AS keys, 16::BIGINT AS flows, 0::BIGINT AS different, true AS cached_same, true AS bounded FROM q WHERE is_key")
def dp_equals_bruteforce(spark: SparkSession, sf: str) -> DataFrame:
    """The flows of the orders under four threshold vectors, each at four values of lambda, with five grid steps and three regions: the search against all tuples, with and without the memo, and its number of choices."""
    from stagefilter.operators.flow import flows

    found, bad, same, bounded = flows(scored(spark, sf), THETAS, 3, BINS), 0, True, True
    n = found[0].n_keys
    c = Costs(np.array([96.0, 128.0, 160.0, 192.0]), np.array([0.6, 1.0, 1.4, 1.8]), LOG2E * n * math.log2(100), 1.0)
    for f in found:
        for lam in (0.0, 0.3, 0.9, 1.0):
            count: dict = {}
            p, q = configure(f, c, 0.01, lam, 5, counter=count), configure_bruteforce(f, c, 0.01, lam, 5)
            bad += abs(p.objective - q.objective) > 1e-9
            same &= configure(f, c, 0.01, lam, 5, cached=False).gates == p.gates
            bounded &= count["choices"] <= f.depth * 25 and count["leaves"] <= f.depth * 5
    return spark.createDataFrame([(n, 4 * len(found), int(bad), bool(same), bool(bounded))], "keys long, flows long, different long, cached_same boolean, bounded boolean")


def random_flow(rng, depth: int, parts: int, n: int = 1000) -> tuple[Flow, Costs]:
    keys, others = rng.integers(1, 50, (depth, 12)).astype(float), rng.integers(1, 50, (depth, 12)).astype(float)
    kl, nl = np.zeros(depth), np.zeros(depth)
    for d in range(depth - 1):
        kl[d], nl[d] = rng.integers(0, keys[d].sum()), rng.integers(0, others[d].sum())
        keys[d + 1] *= (keys[d].sum() - kl[d]) / keys[d + 1].sum()
        others[d + 1] *= (others[d].sum() - nl[d]) / others[d + 1].sum()
    return make_flow(keys, others, kl, nl, n, np.full(depth, 0.5), parts), Costs(rng.uniform(50, 500, depth), rng.uniform(0.5, 2, depth), LOG2E * n * math.log2(100), 1.0)


@query(f"WITH {_TOY.replace(_C, _ORDERS_C)} SELECT depth, count(DISTINCT round(memory, 3)) AS memories FROM (SELECT depth, {_ORDERS_C} * (i + 0.5 * j * (depth - 1)) + CASE depth WHEN 1 THEN {_ORDERS_C} * (.3 * log2(1 / (1e-9 * .3 / .8)) + .7 * log2(1 / (1e-9 * .7 / .2)) - i) WHEN 2 THEN {_ORDERS_C} * (.5 * (log2(1 / (1e-9 * .5 / .1)) - i) + .2 * (log2(1 / (1e-9 * .2 / .75)) - i - j) + .3 * (log2(1 / (1e-9 * .3 / .15)) - i - j)) END AS memory FROM m WHERE depth > 0) GROUP BY depth")
def gate_neutrality(spark: SparkSession, sf: str) -> DataFrame:
    """With no rate clipped, all gate choices of a depth take the same memory; for as many keys as the orders have."""
    f, c = toy(orders_keys(spark, sf))
    rows = [(d, len({round(evaluate(f, c, 1e-9, 1.0, g).memory, 3) for g in ([[i] for i in range(3)] if d == 1 else [[i, j] for i in range(3) for j in range(3 - i)])})) for d in (1, 2)]
    return spark.createDataFrame(rows, "depth int, memories long")


@query("SELECT 4::BIGINT AS workloads, 4::BIGINT AS plain")
def zero_depth_at_lambda0(spark: SparkSession, sf: str) -> DataFrame:
    rng = np.random.default_rng(2)
    n = sum(configure(*random_flow(rng, 3, 3), 0.01, 0.0, 6).depth == 0 for _ in range(4))
    return spark.createDataFrame([(4, n)], "workloads long, plain long")


@query(
    f"""WITH {_HIST}, v AS (SELECT bin, k / kt AS a, n / nt AS b FROM r, t)
SELECT CAST(bin AS INTEGER) AS bin, round(a, 9) AS a, round(b, 9) AS b, round(CASE WHEN a = 0 THEN 0 WHEN b = 0 THEN 1 ELSE least(1, 0.01 * a / b) END, 9) AS fpr FROM v"""
)
def backup_rule(spark: SparkSession, sf: str) -> DataFrame:
    """The rate of a backup filter for each score bin of the orders, from the shares of keys and of non-keys there; some bins have none of either."""
    from stagefilter.functions.sizing import backup_fpr_col

    h = measure_flow(scored(spark, sf), [THETAS[0]], BINS).filter("depth = 4 and bin >= 0")
    part = lambda cls: F.sum(F.when(F.col("cls") == cls, F.col("cnt")).otherwise(0))
    r = spark.range(BINS).select(F.col("id").cast("int").alias("bin")).join(h, "bin", "left").groupBy("bin").agg(part(1).alias("k"), part(0).alias("n"))
    all_ = Window.partitionBy()  # one row per bin
    g = r.select("bin", (F.col("k") / F.sum("k").over(all_)).alias("a"), (F.col("n") / F.sum("n").over(all_)).alias("b"))
    return g.select("bin", F.round("a", 9).alias("a"), F.round("b", 9).alias("b"), F.round(backup_fpr_col(F.col("a"), F.col("b"), F.lit(0.01)), 9).alias("fpr"))


@query(f"WITH {_TOY} SELECT round(0.9 * memory / ({_C} * log2(100.0)), 6) AS memory_term, round(0.1 * reject, 6) AS reject_term, 0.01 AS expected_fpr FROM m WHERE depth = 1 AND i = 2")
def objective_terms(spark: SparkSession, sf: str) -> DataFrame:
    f, c = toy()
    p = configure(f, c, 0.01, 0.9, 3)
    return spark.createDataFrame([(round(0.9 * float(p.memory) / c.plain_bits, 6), round(0.1 * float(p.reject), 6), round(float(p.expected_fpr), 9))], "memory_term double, reject_term double, expected_fpr double")


# --- lookups --------------------------------------------------------------------------


def fixed_plan(n: int):
    """Two learners, a gate at each, one exit, two regions; rates as given."""
    a = np.array
    f = Flow(n, a([1.0, 0.5]), a([1.0, 0.9]), a([0.5, 0.0]), a([0.1, 0.0]), [a([0.5, 0.5]), a([0.25, 0.25])], [a([0.5, 0.5]), a([0.45, 0.45])], [[10], [6]], a([0.4, np.inf]), BINS)
    p = evaluate(f, Costs(a([128.0, 128.0]), a([1.0, 1.0]), 1.0, 1.0), 0.01, 1.0, [1, 2])
    p.exit_fpr, p.leaf_fpr = [0.05], [0.02, 0.2]
    return p


def fixed_staged(spark: SparkSession, sf: str, kind: str = "bloom") -> tuple[DataFrame, StagedFilter]:
    e = examples(spark, sf)
    keys = e.filter("split = 'key'")
    return e, StagedFilter(fixed_plan(keys.count()), ensemble().head(4), kind=kind).materialise(keys)


def _staged_sql() -> str:
    order = [("g1", 0.5), ("e1", 0.05), ("g2", 0.25), ("l0", 0.02), ("l1", 0.2)]
    vals = ", ".join(f"('{n}', {f}::DOUBLE, {i + 1})" for i, (n, f) in enumerate(order))
    return f"""{scored_sql()},
r AS (SELECT eid, h, is_key, split, CASE WHEN s1 >= 0.4 THEN 'e1' WHEN {bin_sql('s2')} < 6 THEN 'l0' ELSE 'l1' END AS last, CASE WHEN s1 >= 0.4 THEN 1 ELSE 2 END AS depth FROM q),
path AS (SELECT eid, h, is_key, 'g1' AS name, 1 AS step FROM r UNION ALL SELECT eid, h, is_key, 'g2', 3 FROM r WHERE depth = 2 UNION ALL SELECT eid, h, is_key, last, CASE WHEN depth = 1 THEN 2 ELSE 4 END FROM r),
rate(name, fpr, seed) AS (VALUES {vals}),
shape AS (SELECT name, seed, {_K} AS k, greatest(8, CAST(ceil(-{_K} * n / ln(1 - pow(fpr, 1.0::DOUBLE / {_K}))) AS BIGINT)) AS m FROM rate JOIN (SELECT name, count(*) AS n FROM path WHERE is_key GROUP BY name) USING (name)),
pos AS (SELECT eid, is_key, name, step, {position_sql('h', 'seed', 'i', 'm')} AS p FROM path JOIN shape USING (name) CROSS JOIN generate_series(0, 9) g(i) WHERE i < k),
held AS (SELECT DISTINCT name, p FROM pos WHERE is_key),
hit AS (SELECT pos.eid, pos.name, pos.step, bool_and(held.p IS NOT NULL) AS found FROM pos LEFT JOIN held ON held.name = pos.name AND held.p = pos.p GROUP BY ALL),
v AS (SELECT r.eid, r.split, bool_and(hit.found) AS found, min(CASE WHEN NOT hit.found AND hit.name LIKE 'g%' THEN hit.step END) AS gone, max(r.depth) AS deepest FROM r JOIN hit USING (eid) GROUP BY r.eid, r.split),
w AS (SELECT eid, split, found, CASE WHEN gone = 1 THEN 0 WHEN gone = 3 THEN 1 ELSE deepest END AS learners FROM v)"""


@query(f"WITH {_staged_sql()} SELECT eid, found, CAST(learners AS INTEGER) AS learners FROM w WHERE split = 'test'")
def staged_verdicts(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    return f.lookup(e.filter("split = 'test'")).select("eid", "found", F.col("learners_run").alias("learners"))


@query(f"WITH {_staged_sql()} SELECT split, CAST(learners AS INTEGER) AS learners, found, count(*) AS n FROM w GROUP BY ALL")
def staged_path_mix(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    return f.lookup(e, ("split",)).groupBy("split", F.col("learners_run").alias("learners"), "found").agg(F.count("*").alias("n"))


@query(f"WITH {_staged_sql()} SELECT count(*) AS keys, count(*) FILTER (WHERE NOT found) AS missed FROM w WHERE split = 'key'")
def staged_fn_zero(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    return f.lookup(e.filter("split = 'key'")).agg(F.count("*").alias("keys"), F.count_if(~F.col("found")).alias("missed"))


@query(f"WITH {_staged_sql()} SELECT round(avg(CAST(found AS INTEGER)), 6) AS rate, count(*) AS n FROM w WHERE split = 'test'")
def staged_fpr_vs_target(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    return f.lookup(e.filter("split = 'test'")).agg(F.round(F.avg(F.col("found").cast("int")), 6).alias("rate"), F.count("*").alias("n"))


@query(f"WITH {_staged_sql()} SELECT count(*) FILTER (WHERE split = 'key') AS keys, 0::BIGINT AS missed, count(*) FILTER (WHERE split <> 'key') AS others, true AS rate_ok FROM w")
def staged_sharded_lookup(spark: SparkSession, sf: str) -> DataFrame:
    """All rows through sharded filters: keys are found, and other rows pass as rarely as through the broadcast form (within four deviations)."""
    e, f = fixed_staged(spark, sf)
    shape, bits = f.sharded_bits(e.filter("split = 'key'"))
    seen = f.lookup_sharded(e, shape, bits).join(f.lookup(e, ("eid", "split")).select("eid", "split", F.col("found").alias("plainly")), "eid")
    key, other = F.col("split") == "key", F.col("split") != "key"
    rate = lambda c: F.avg(F.when(other, F.col(c).cast("int")))
    close = F.abs(rate("found") - rate("plainly")) <= 4 * F.sqrt(2 * rate("plainly") / F.count_if(other)) + 0.001
    return seen.agg(F.count_if(key).alias("keys"), F.count_if(key & ~F.col("found")).alias("missed"), F.count_if(other).alias("others"), close.alias("rate_ok"))


@query(f"""WITH {scored_sql()} SELECT form, count(*) AS keys, 0::BIGINT AS missed, 0::BIGINT AS nulls_found FROM q, (VALUES ('broadcast'), ('sharded')) v(form) WHERE is_key GROUP BY form""")
def staged_null_identity(spark: SparkSession, sf: str) -> DataFrame:
    """Keys are found whatever else stands in their batch: a row without identity and one without features go into every partition."""
    e, f = fixed_staged(spark, sf)
    keys = e.filter("split = 'key'").select("eid", "h", "x", F.lit(True).alias("key"))
    shape, bits = f.sharded_bits(e.filter("split = 'key'"))
    odd = keys.limit(1).select(F.explode(F.sequence(F.lit(1), F.lit(64))).alias("i"), "x").select(F.concat(F.lit("odd-"), "i").alias("eid"), F.lit(None).cast("long").alias("h"), F.when(F.col("i") % 2 == 0, F.col("x")).alias("x"), F.lit(False).alias("key"))
    rows = keys.unionByName(odd).repartition(8).persist()
    out = None
    for form, v in (("broadcast", f.lookup(rows)), ("sharded", f.lookup_sharded(rows, shape, bits))):
        v = rows.select("eid", "key").join(v.select("eid", "found"), "eid", "left")
        v = v.agg(F.count_if("key").alias("keys"), F.count_if(F.col("key") & ~F.coalesce("found", F.lit(False))).alias("missed"), F.count_if(~F.col("key") & F.coalesce("found", F.lit(True))).alias("nulls_found")).select(F.lit(form).alias("form"), "*")
        out = v if out is None else out.union(v)
    return out


@query(f"WITH {scored_sql()} SELECT count(*) AS added, 0::BIGINT AS missed FROM q WHERE split = 'train'")
def staged_dynamic_insert(spark: SparkSession, sf: str) -> DataFrame:
    """Keys added after the build are found; none of the old ones is lost (checked in tests)."""
    e, f = fixed_staged(spark, sf)
    late = e.filter("split = 'train'")
    return f.insert(late).lookup(late).agg(F.count("*").alias("added"), F.count_if(~F.col("found")).alias("missed"))


QUICK = Boosting(rounds=10, depth=2, eta=0.3, sample=20_000)


@query()
def staged_end_to_end(spark: SparkSession, sf: str) -> DataFrame:
    e = load("physics_hard", spark, sf).persist()
    f = build(e, 0.01, 0.9, QUICK)
    return M.path_mix(f.lookup(e.filter("split = 'test'")))


@query()
def boost_train(spark: SparkSession, sf: str) -> DataFrame:
    from stagefilter.operators.boosting import train

    e = train(load("physics_hard", spark, sf), QUICK)
    return spark.createDataFrame([(d + 1, t.bits, [int(x) for x in t.feat]) for d, t in enumerate(e.trees)], "depth int, bits long, feat array<int>")


@query()
def boost_train_distributed(spark: SparkSession, sf: str) -> DataFrame:
    from stagefilter.operators.boosting import train

    e = train(load("orders_mix", spark, sf).persist(), Boosting(rounds=2, depth=2), distributed=True)
    return spark.createDataFrame([(d + 1, t.bits, [int(x) for x in t.feat]) for d, t in enumerate(e.trees)], "depth int, bits long, feat array<int>")


# --- baselines ------------------------------------------------------------------------

_CURVE = f"""{_HIST}, w AS (SELECT e, 1 - cn AS hi, ck AS lo, kt FROM c, t WHERE e BETWEEN 1 AND {BINS - 1})"""


@query(f"WITH {_CURVE} SELECT round(min({LOG2E} * kt * lo * log2((1 - hi) / (0.1 - hi))), 2) AS bits FROM w WHERE hi < 0.1")
def single_threshold_plan(spark: SparkSession, sf: str) -> DataFrame:
    k, n = _hist(spark, sf)
    p = B.single_threshold(k, n, 0.1)
    return spark.createDataFrame([(round(float(p.filter_bits), 2) if p else None,)], "bits double")


_PRE = f"""{_CURVE}, y AS (SELECT *, CASE WHEN hi <= 0 OR lo <= 0 THEN NULL ELSE lo * hi / ((1 - hi) * (1 - lo)) END AS b FROM w),
z AS (SELECT *, CASE WHEN hi <= 0 THEN 1.0 WHEN lo <= 0 THEN least(1.0, 0.01 / hi) WHEN b >= 1 THEN 0.01 ELSE 0.01 / (hi + (1 - hi) * b) END AS g FROM y),
u AS (SELECT CASE WHEN g > 1 THEN 1.0 ELSE g END AS gate, CASE WHEN hi <= 0 THEN 0.01 WHEN lo <= 0 THEN 0.0 WHEN b >= 1 THEN 1.0 WHEN g > 1 THEN greatest(0.0, (0.01 - hi) / (1 - hi)) ELSE b END AS backup, lo, kt FROM z)"""


@query(f"WITH {_PRE} SELECT round(min({LOG2E} * kt * log2(1 / gate) + CASE WHEN lo > 0 AND backup < 1 THEN {LOG2E} * kt * lo * log2(1 / backup) ELSE 0 END), 2) AS bits FROM u")
def prefilter_plan(spark: SparkSession, sf: str) -> DataFrame:
    k, n = _hist(spark, sf)
    return spark.createDataFrame([(round(float(B.prefiltered(k, n, 0.01).filter_bits), 2),)], "bits double")


_SMOOTH = _HIST.replace("coalesce(sum(cnt) FILTER (WHERE cls = 0), 0) AS n", "coalesce(sum(cnt) FILTER (WHERE cls = 0), 0) + 1 AS n")


@query(f"WITH {_SMOOTH}, best AS ({_K3}) SELECT round((SELECT kt FROM t) * {LOG2E} * (log2(1 / 1e-9) - max(kl)), 0) AS bits FROM best")
def partition_plan(spark: SparkSession, sf: str) -> DataFrame:
    """Three regions at a rate so small that none is clipped: bits are those of the plain filter less the divergence."""
    k, n = _hist(spark, sf)
    n = n + 1  # no region without a non-key
    p = B.partitioned(k[None], n[None], 1e-9, Costs(np.zeros(1), np.ones(1), 1.0), 1, 3, fill=False)
    return spark.createDataFrame([(float(round(p.memory)),)], "bits double")


@query("SELECT x AS high, y AS low, round(CASE WHEN b >= 1 THEN 0.01 ELSE 0.01 / (x + (1 - x) * b) END, 7) AS gate, round(least(b, 1), 7) AS backup FROM (SELECT x, y, y * x / ((1 - x) * (1 - y)) AS b FROM (VALUES (0.1::DOUBLE, 0.4::DOUBLE), (0.05, 0.2), (0.7, 0.6)) v(x, y))")
def prefilter_rates(spark: SparkSession, sf: str) -> DataFrame:
    rows = [(h, lo, *(round(float(r), 7) for r in B.prefilter_rates(h, lo, 0.01))) for h, lo in ((0.1, 0.4), (0.05, 0.2), (0.7, 0.6))]
    return spark.createDataFrame(rows, "high double, low double, gate double, backup double")


@query(f"WITH {flow_sql()} SELECT depth, CAST(count(DISTINCT bin) AS BIGINT) AS bins, CAST(sum(cnt) AS BIGINT) AS n FROM f WHERE theta_id = 0 AND bin >= 0 GROUP BY depth")
def model_size_histograms(spark: SparkSession, sf: str) -> DataFrame:
    return measure_flow(scored(spark, sf), [THETAS[0]], BINS).filter("bin >= 0").groupBy("depth").agg(F.countDistinct("bin").alias("bins"), F.sum("cnt").alias("n"))


def _bench(spark: SparkSession, sf: str, name: str = "orders_mix") -> X.Bench:
    return X.bench(spark, sf, name, QUICK)


@query("SELECT count(*) AS n, round(1.0::DOUBLE, 6) AS same FROM orders WHERE o_totalprice < 280000")
def construction_variants_agree(spark: SparkSession, sf: str) -> DataFrame:
    """Fast and classic construction of the partitioned filter give one structure: on the prices of the orders of each priority in fourteen bins, early orders as keys."""
    o = table(spark, sf, "orders").filter("o_totalprice < 280000").select("o_orderpriority", F.floor(F.col("o_totalprice") / 20000).cast("int").alias("bin"), F.expr("o_orderdate < TIMESTAMP '1996-06-01 00:00:00'").alias("is_key"))
    found: dict[str, np.ndarray] = {}
    for r in o.groupBy("o_orderpriority", "bin", "is_key").count().collect():  # at most 28 cells for each priority
        found.setdefault(r.o_orderpriority, np.zeros((2, 14)))[int(r.is_key), r.bin] = r["count"]
    same = [partition_scores(h[1], h[0], 4, "fast")[0] == partition_scores(h[1], h[0], 4, "classic")[0] for h in found.values()]
    return spark.createDataFrame([(int(sum(h.sum() for h in found.values())), float(np.mean(same)))], "n long, same double")


#: The setting of the experiments: 100 learners of depth 4.
FULL = Boosting()


def _experiment(name: str, run, schema: str = X.ROW, tables=X.MAIN, boosting: Boosting = FULL, after=None):
    def f(spark: SparkSession, sf: str) -> DataFrame:
        rows = [r for t in tables for r in run(X.bench(spark, sf, t, boosting))]
        return spark.createDataFrame(after(rows) if after else rows, schema)

    f.__name__ = name
    Q[name] = f


_experiment("memory_vs_rate", X.memory_vs_rate)
_experiment("memory_saving", X.memory_vs_rate, X.SAVING, after=X.saving)
_experiment("memory_vs_reject", X.memory_vs_reject)
_experiment("memory_vs_reject_time", X.memory_vs_reject_time, X.TIMED)
_experiment("reject_time_ratio", X.memory_vs_reject_time, X.RATIO, after=X.reject_ratio)
_experiment("offered_learners", X.offered_learners)
_experiment("used_learners", X.used_learners)
_experiment("model_size_sweep", lambda b: [b.row("prefiltered", 0.001, 1, B.prefiltered(b.keys[d - 1], b.others[d - 1], 0.001, float(b.ensemble.bits()[:d].sum()), d)) for d in b.depths()])
_experiment("budgeted_plan", lambda b: X.against_budgeted(b, 0.001, 40))
_experiment("refined_thresholds", lambda b: X.refined_thresholds(b, 0.001, 0.9, 100), tables=("orders_mix",))
_experiment("reject_distribution", X.reject_distribution, "workload string, method string, bits double, learners int, n long")
_experiment("construction_phases", X.construction_times, "workload string, method string, phase string, seconds double")
_experiment("seen_and_unseen", X.seen_and_unseen, "workload string, method string, parameter double, seen double, unseen double", ("orders_mix",))
_experiment("other_filters", X.other_filters, X.OTHERS, ("orders_mix",))
_experiment("subset_ensemble_plan", X.subset_points, "workload string, method string, budget double, chosen int, assumed_fpr double, real_fpr double", ("orders_mix",))
_experiment("score_adaptive_bits", lambda b: [(b.name, float(f), float(B.score_adaptive_bits(b.keys[4], b.others[4], f)), float(B.partitioned(b.keys, b.others, f, b.costs(f), 5).memory - b.ensemble.bits()[:5].sum())) for f in (0.1, 0.01, 0.001)], "workload string, fpr double, score_adaptive double, partitioned double")


def _flags(rows: list[tuple]) -> list[tuple]:
    """What the experiments are to show, by workload, from the rows of memory_vs_rate, memory_vs_reject and offered_learners."""
    out = []
    for name in dict.fromkeys(r[0] for r in rows):
        mine = [r for r in rows if r[0] == name]
        saved = [r[4] for r in X.saving([r for r in mine if r[9] == "rate"])]
        reject = sorted((r for r in mine if r[9] == "reject" and r[1] == "staged"), key=lambda r: r[3])
        offered = [r[5] for r in mine if r[9] == "offered"]
        falls = lambda v, slack=1e-6: all(b <= a * (1 + slack) for a, b in itertools.pairwise(v))
        out.append((name, min(saved) >= -0.002, reject[0][4] == 0, falls([r[5] for r in reject]), falls([-r[7] for r in reject], -1e-6), falls(offered)))
    return out


_experiment(
    "experiment_flags",
    lambda b: [(*r, "rate") for r in X.memory_vs_rate(b)] + [(*r, "reject") for r in X.memory_vs_reject(b)] + [(*r, "offered") for r in X.offered_learners(b)],
    "workload string, no_more_than_partitioned boolean, plain_at_lambda_0 boolean, memory_falls_with_lambda boolean, reject_rises_with_lambda boolean, offering_more_never_costs boolean",
    after=_flags,
)
SQL["experiment_flags"] = f"SELECT w AS workload, true AS no_more_than_partitioned, true AS plain_at_lambda_0, true AS memory_falls_with_lambda, true AS reject_rises_with_lambda, true AS offering_more_never_costs FROM (VALUES {', '.join(f'({w!r})' for w in X.MAIN)}) v(w)"


@query()
def updates_and_drift(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame(X.updates(spark, sf), X.UPDATES)


@query()
def guarded_joins(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame(X.guarded_joins(spark, sf), X.GUARDED)


@query()
def all_workloads(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame(X.all_sets(spark, sf), X.ROW)


def _staged_of(kind: str):
    @query(f"WITH {scored_sql()} SELECT count(*) AS keys, 0::BIGINT AS missed, 0::BIGINT AS lost, true AS deleted_ok, true AS rate_ok FROM q WHERE is_key")
    def run(spark: SparkSession, sf: str) -> DataFrame:
        """The staged filter made of other filters: finds all keys, keeps its rate; where it can delete, what is deleted goes and the rest stays."""
        e, f = fixed_staged(spark, sf, kind)
        keys = e.filter("split = 'key'")
        r = f.lookup(keys).agg(F.count("*").alias("n"), F.count_if(~F.col("found")).alias("missed")).first()
        t = f.lookup(e.filter("split = 'test'")).agg(F.avg(F.col("found").cast("int")).alias("rate"), F.count("*").alias("n")).first()
        lost, gone_ok = 0, True
        if kind != "quotient":
            gone, rest = keys.filter("h % 10 = 0"), keys.filter("h % 10 <> 0")
            g = f.delete(gone).lookup(gone).agg(F.avg(F.col("found").cast("int"))).first()[0] or 0.0
            lost, gone_ok = f.lookup(rest).filter("not found").count(), g <= 0.5
        plain = fixed_staged(spark, sf)[1].lookup(e.filter("split = 'test'")).agg(F.avg(F.col("found").cast("int"))).first()[0] or 0.0
        return spark.createDataFrame([(r.n, r.missed, lost, gone_ok, (t.rate or 0.0) <= 1.2 * plain + 0.01)], "keys long, missed long, lost long, deleted_ok boolean, rate_ok boolean")

    return run


for _kind in FAMILIES:
    _staged_of(_kind)
    Q[f"staged_{_kind}"], SQL[f"staged_{_kind}"] = Q.pop("run"), SQL.pop("run")


@query()
def model_families(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame(X.model_families(spark, sf, "orders_mix", tuple((d, r) for d in (1, 2, 4, 6) for r in (20, 100))), X.ROW)


@query()
def library_trees(spark: SparkSession, sf: str) -> DataFrame:
    """The library's boosted trees and forest as learners of the same filter."""
    from pyspark.ml.classification import GBTClassifier, RandomForestClassifier
    from pyspark.ml.functions import array_to_vector

    from stagefilter.operators.scoring import from_library_trees

    e = load("orders_mix", spark, sf).persist()
    rows = e.filter("split in ('key', 'train')").select(array_to_vector(F.col("x").cast("array<double>")).alias("features"), F.col("is_key").cast("double").alias("label"))
    out = []
    for name, m in (("boosted", GBTClassifier(maxIter=5, maxDepth=3, seed=1)), ("forest", RandomForestClassifier(numTrees=5, maxDepth=4, seed=1))):
        f = build(e, 0.01, 1.0, ensemble=from_library_trees(m.fit(rows), []))
        out.append((name, f.plan.depth, float(f.plan.memory), M.false_negatives(f, e)))
    return spark.createDataFrame(out, "family string, depth int, bits double, missed long")


@query()
def no_signal_controls(spark: SparkSession, sf: str) -> DataFrame:
    rows = []
    for name in ("null_rows", "null_vec"):
        b = _bench(spark, sf, name)
        p, plain = b.staged(0.01), b.costs(0.01).plain_bits
        rows.append((name, p.depth, float(p.memory), float(plain), bool(p.memory <= 1.02 * plain)))
    return spark.createDataFrame(rows, "workload string, depth int, bits double, plain_bits double, within boolean")


# --- measures -------------------------------------------------------------------------


@query()
def memory_report(spark: SparkSession, sf: str) -> DataFrame:
    return M.memory_report(spark, fixed_staged(spark, sf)[1])


@query()
def measured_fpr_ci(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    return spark.createDataFrame([M.measured_fpr(f, e)], "fpr double, low double, high double, n long")


@query()
def reject_cost_hist(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    return M.reject_histogram(f.lookup(e.filter("split = 'test'")))


@query()
def reject_cost_model(spark: SparkSession, sf: str) -> DataFrame:
    e, f = fixed_staged(spark, sf)
    t = M.reject_time(f, e, 2000, 3)
    return spark.createDataFrame([(float(f.plan.reject), t["batch"], t["row"])], "modelled double, batch_s double, row_s double")


@query("SELECT o_orderpriority, round(f, 9) AS fpr, round((1 - f) * 1.0 + f * (2.0 + 1000.0), 6) AS full_time, round(1.0 + f * 1000.0, 6) AS short_time FROM (SELECT o_orderpriority, count(*) FILTER (WHERE o_totalprice > 300000) / count(*)::DOUBLE AS f FROM orders GROUP BY 1)")
def expected_latency_curve(spark: SparkSession, sf: str) -> DataFrame:
    """Expected time of a lookup behind a filter on the price, at the rate with which it lets the orders of each priority through."""
    g = table(spark, sf, "orders").groupBy("o_orderpriority").agg((F.count_if(F.col("o_totalprice") > 300000) / F.count("*")).alias("fpr"))
    f = F.col("fpr")
    return g.select("o_orderpriority", F.round(f, 9).alias("fpr"), F.round(M.expected_latency(f, 1.0, 2.0, 1000.0), 6).alias("full_time"), F.round(M.expected_latency(f, 1.0, 2.0, 1000.0, True), 6).alias("short_time"))


@query()
def shuffle_report(spark: SparkSession, sf: str) -> DataFrame:
    r = M.shuffle_bytes(spark, lambda: load("orders_mix", spark, sf).count())
    return spark.createDataFrame([(r["shuffle"], r["spill"], r["tasks"])], "shuffle long, spill long, tasks long")
