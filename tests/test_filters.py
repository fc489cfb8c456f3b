import numpy as np
import pytest
from pyspark.sql import functions as F

from stagefilter import experiments as X
from stagefilter import measures as M
from stagefilter.functions.hashing import element_hash, positions, positions_np
from stagefilter.operators.amq import CountingBloom, CuckooFilter, QuotientFilter
from stagefilter.operators.baselines import HashAdaptive, ProjectionHash, histograms
from stagefilter.operators.bloom import BloomFilter, ShardedBloom
from stagefilter.operators.boosting import Boosting
from stagefilter.operators.staged import build
from stagefilter.queries.method import fixed_staged
from stagefilter.sources import store
from stagefilter.sources.workloads import WORKLOADS, load

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def hashes():
    rng = np.random.default_rng(0)
    h = rng.integers(0, 1 << 60, 40_000)
    return h[:5000], h[5000:]


def test_columns_and_arrays_give_the_same_positions(spark):
    df = spark.range(300).select(element_hash(F.col("id")).alias("h")).withColumn("p", positions(F.col("h"), 9, 5, 777))
    rows = df.collect()
    want = positions_np(np.array([r.h for r in rows]), 9, 5, 777)
    assert [r.p for r in rows] == want.tolist()


def test_filters_keep_their_rate_and_miss_nothing(hashes):
    keys, others = hashes
    for f in (BloomFilter.empty(5000, 0.01, 1), CountingBloom(5000, 0.01, 1), CuckooFilter(5000, 0.01, 1), QuotientFilter(5000, 0.01, 1)):
        f.insert(keys)
        assert f.contains_np(keys).all()
        assert f.contains_np(others).mean() < 0.013, type(f)
    for f in (CountingBloom(5000, 0.01), CuckooFilter(5000, 0.01)):
        f.insert(keys)
        f.delete(keys[:1000])
        assert f.contains_np(keys[1000:]).all() and f.contains_np(keys[:1000]).mean() < 0.03


def test_seeds_are_independent(hashes):
    keys, others = hashes
    a, b = BloomFilter.empty(5000, 0.1, 1), BloomFilter.empty(5000, 0.1, 2)
    a.insert(keys)
    b.insert(keys)
    x, y = a.contains_np(others), b.contains_np(others)
    assert abs((x & y).mean() - x.mean() * y.mean()) < 0.004


def test_built_forms_agree(spark):
    keys = spark.range(2000).select(element_hash(F.col("id")).alias("h"))
    f = BloomFilter.build(keys, "h", 0.01, 3)
    g = BloomFilter.empty(2000, 0.01, 3)
    g.insert(np.array([r.h for r in keys.collect()]))
    assert (f.bits == g.bits).all()
    queries = spark.range(6000).select("id", element_hash(F.col("id")).alias("h"))
    s = ShardedBloom.build(keys, "h", 0.01, 3).probe(queries)
    assert s.filter("id < 2000 and not found").count() == 0
    assert s.filter("id >= 2000 and found").count() < 4000 * 0.02
    assert f.merge(g).n == 4000 and f.ones == g.ones


def test_workloads_have_distinct_elements_and_fixed_splits(spark):
    for name in WORKLOADS:
        e = load(name, spark, SF)
        r = e.agg(F.count("*").alias("n"), F.count_distinct("eid").alias("d"), F.count_if(F.col("is_key") != (F.col("split") == "key")).alias("bad"), F.count_distinct(F.size("x")).alias("w")).first()
        assert r.n == r.d > 0 and r.bad == 0 and r.w == 1, name


def test_staged_filter_end_to_end(spark, tmp_path):
    e = load("physics_hard", spark, "/root/testdata/sf0.01").persist()
    f = build(e, 0.02, 0.9, Boosting(rounds=6, depth=2, sample=15_000))
    assert M.false_negatives(f, e) == 0
    rate, low, high, n = M.measured_fpr(f, e)
    assert n > 1000 and rate <= 0.02 + 4 * (0.02 * 0.98 / n) ** 0.5
    assert low <= rate <= high
    shape, bits = f.sharded_bits(e.filter("split = 'key'"))
    assert f.lookup_sharded(e.filter("split = 'key'"), shape, bits).filter("not found").count() == 0
    store.write(spark, f, str(tmp_path / "s"))
    g = store.read(spark, str(tmp_path / "s"))
    probe = e.filter("split = 'test'")
    assert sorted(map(tuple, f.lookup(probe).collect())) == sorted(map(tuple, g.lookup(probe).collect()))
    assert f.lookup(spark.createDataFrame([("a", None, [0.0] * 28)], "eid string, h long, x array<float>")).first().found is False
    plan = f.lookup(probe)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan.split("MapInArrow")[0]


def test_inserted_keys_are_found_and_none_is_lost(spark):
    e, f = fixed_staged(spark, SF)
    f.insert(e.filter("split = 'train'"))
    assert f.lookup(e.filter("split in ('key', 'train')")).filter("not found").count() == 0


def test_shapes_of_the_experiments(spark):
    b = X.Bench(spark, "/root/testdata/sf0.01", "orders_mix", Boosting(rounds=8, depth=2, sample=10_000))
    for fpr in (0.1, 0.01, 0.001):
        rows = {r[1]: r for r in X.memory_vs_rate(b, (fpr,))}
        assert rows["staged"][5] <= min(r[5] for k, r in rows.items() if k.startswith("partitioned")) * 1.002
        assert rows["staged"][5] <= rows["plain"][5]
    rows = X.memory_vs_reject(b)
    staged = [r for r in rows if r[1] == "staged"]
    assert staged[0][4] == 0
    assert all(x[5] >= y[5] - 1e-6 and x[7] <= y[7] + 1e-9 for x, y in zip(staged, staged[1:], strict=False))
    offered = [r[5] for r in X.offered_learners(b)]
    assert all(x >= y - 1e-6 for x, y in zip(offered, offered[1:], strict=False))
    b.close()


def test_no_signal_means_no_more_memory_than_plain(spark):
    b = X.Bench(spark, SF, "null_rows", Boosting(rounds=4, depth=2))
    p = b.staged(0.01)
    assert p.memory <= 1.0 * b.costs(0.01).plain_bits + 1e-6
    b.close()


def test_learning_baselines_miss_no_key(hashes):
    keys, others = hashes
    f = HashAdaptive(6).fit(keys[:2000], others[:4000])
    assert f.contains_np(keys[:2000]).all() and f.moved > 0
    assert f.contains_np(others[:4000]).mean() < f.contains_np(others[4000:]).mean()
    rng = np.random.default_rng(1)
    kx, nx = rng.normal(1, 1, (400, 6)), rng.normal(-1, 1, (400, 6))
    p = ProjectionHash(k=8, m=4000).fit(kx, nx)
    assert p.contains_x(kx).all()
    assert (p.contains_x(nx, "row") == p.contains_x(nx, "batch")).all()


def test_nulls_in_a_batch_lose_no_key(spark):
    """A null identity or null features beside keys: hashes keep all their bits, nulls are never found, nothing fails."""
    e, f = fixed_staged(spark, SF)
    keys = e.filter("split = 'key'").select("eid", "h", "x").limit(300)
    odd = keys.limit(4).selectExpr("concat('odd-', eid) as eid", "cast(null as bigint) as h", "if(eid > '1', x, cast(null as array<float>)) as x")
    rows = keys.unionByName(odd).coalesce(1).persist()
    blank = keys.limit(3).selectExpr("eid", "h", "cast(null as array<float>) as x").coalesce(1)
    shape, bits = f.sharded_bits(e.filter("split = 'key'"))
    for form in (f.lookup, lambda df: f.lookup_sharded(df, shape, bits)):
        got = {r.eid: r.found for r in form(rows).collect()}
        assert len(got) == 304 and all(found != eid.startswith("odd-") for eid, found in got.items())
        assert form(blank).count() == 3
    assert f.routed(rows).filter("h is null").count() == 0


def test_registered_functions_with_nulls(spark):
    from stagefilter.functions.udfs import register

    e, f = fixed_staged(spark, SF)
    keys = e.filter("split = 'key'").select("h", "x").limit(200)
    bloom = BloomFilter.build(keys, "h", 0.01)
    register(spark, staged=f, bloom=bloom, prefix="tn_")
    keys.unionByName(keys.limit(1).selectExpr("cast(null as bigint) as h", "x")).coalesce(1).createOrReplaceTempView("tn_rows")
    r = spark.sql("select count_if(tn_bloom_has(h) and tn_maybe_in(h, x)) as hits, count_if(h is null and (tn_bloom_has(h) or tn_maybe_in(h, x))) as wrong from tn_rows").first()
    assert r.hits == 200 and r.wrong == 0

def test_exact_quantiles_hold_no_values(spark):
    """Equal to the library's percentile on scores with ties, negative values and both zeros; tasks hand on counts of digits, not values."""
    from pyspark.sql import functions as F

    from stagefilter.operators import flow

    rows = spark.range(0, 20_011, 1, 5).select(F.array(F.rand(3), F.round(F.rand(4), 1), F.randn(5), F.lit(0.25), F.round(F.randn(6)) * F.lit(-0.0), F.rand(7) * 1e-300).alias("s"), F.lit("calib").alias("split")).persist()
    shares = [1 - a for a in (0.1, 0.01, 0.001, 0.0001)] + [1.0, 0.0, 0.5]
    want = rows.select(F.posexplode("s").alias("d", "s")).groupBy("d").agg(*[F.percentile("s", F.lit(q)).alias(f"q{i}") for i, q in enumerate(shares)]).orderBy("d").collect()
    assert flow.exact_quantiles(rows, shares).tolist() == [[r[f"q{i}"] for i in range(len(shares))] for r in want]
    assert flow.exact_quantiles(rows.filter("false"), shares).shape == (0, len(shares))
    counts = flow._digit_counts(rows.select("s"), [], 52, 12)
    assert len(counts) == 6 and all(c.sum() == 20_011 for c in counts.values())


def test_bench_keeps_nothing_in_the_cache(spark):
    before = spark.sparkContext._jsc.getPersistentRDDs().size()
    b = X.Bench(spark, SF, "orders_mix", Boosting(rounds=3, depth=2))
    assert spark.sparkContext._jsc.getPersistentRDDs().size() == before
    scored = b.scored.cache()
    keys, others = histograms(scored)
    assert (keys == b.keys).all() and (others == b.others).all() and b.n == scored.filter("is_key").count()
    scored.unpersist()
