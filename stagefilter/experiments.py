"""The experiment workloads: each returns rows of one table of measures."""

from __future__ import annotations

import time
from dataclasses import replace
from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stagefilter import measures as M
from stagefilter.functions.hashing import smallest
from stagefilter.operators import baselines as B
from stagefilter.operators import joins
from stagefilter.operators.bloom import BloomFilter
from stagefilter.operators.boosting import Boosting, train
from stagefilter.operators.flow import flow_cube, flows, flows_of, quantile_thetas
from stagefilter.operators.scoring import Ensemble, matrix, score_prefixes
from stagefilter.operators.staged import StagedFilter, best_plan, build, plain_costs, refine
from stagefilter.plans.config_dp import Plan, configure, refill
from stagefilter.sources.scratch import kept
from stagefilter.sources.workloads import WORKLOADS, load, table
from stagefilter.streaming import service

RATES = (0.1, 0.05, 0.02, 0.01, 0.005, 0.002, 0.001)
LAMBDAS = (0.0, 0.3, 0.5, 0.7, 0.9, 0.99, 1.0)
ROW = "workload string, method string, fpr double, lam double, depth int, bits double, model_bits double, reject double, expected_fpr double"


#: What the paper's three main sets stand for: short strings, wide rows, many rows of few features.
MAIN = ("url_easy", "file_wide", "physics_hard")
TIMED = "workload string, method string, fpr double, lam double, depth int, bits double, reject_us double, plain_us double"
_KEPT: dict[tuple, "Bench"] = {}


def bench(spark: SparkSession, sf_dir: str, name: str, boosting: Boosting = Boosting(), most: int = 4) -> "Bench":
    """The bench of a workload; the last few of a session are kept, so that experiments share their training."""
    key = (spark.sparkContext.applicationId, sf_dir, name, boosting)
    if key not in _KEPT:
        while len(_KEPT) >= most:
            _KEPT.pop(next(iter(_KEPT))).close()
        _KEPT[key] = Bench(spark, sf_dir, name, boosting)
    return _KEPT[key]


class Bench:
    """One workload, trained and scored once; all plans come from its flows."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, boosting: Boosting = Boosting()):
        self.spark, self.name = spark, name
        self.examples = kept(load(name, spark, sf_dir), "examples")
        began = time.perf_counter()
        self.ensemble: Ensemble = train(self.examples, boosting)
        self.training = time.perf_counter() - began
        began = time.perf_counter()
        # thresholds read the calibration scores a few times, so those are written; keys, which are many, are scored on the way into the counts
        self.scored = score_prefixes(self.examples.filter("split in ('key', 'calib')"), self.ensemble)
        self.thetas = quantile_thetas(kept(score_prefixes(self.examples.filter("split = 'calib'"), self.ensemble), "scores")) or [np.full(self.ensemble.depth, np.inf)]
        cube = flow_cube(self.scored, self.thetas)
        self.calibration = time.perf_counter() - began
        self.flows = flows_of(cube, self.thetas)
        self.n = self.flows[0].n_keys
        self.keys, self.others = cube[-1, :, 1, :-1], cube[-1, :, 0, :-1]  # the last vector lets nothing exit

    def costs(self, fpr: float, timed: bool = False):
        c = plain_costs(self.ensemble, self.n, fpr)
        return replace(c, time=self.times[0], plain_time=self.times[1]) if timed else c

    @cached_property
    def times(self) -> tuple[np.ndarray, float]:
        """Measured seconds per element of each learner and of one filter probe, on at most 10,000 unseen non-keys."""
        t = self.examples.filter("split = 'test'").select("h", "x").limit(10_000).toArrow()
        h, x = t["h"].to_numpy(), matrix(t["x"], self.ensemble.width)
        rows = max(1, len(h))
        plain = BloomFilter.empty(max(1, self.n), 0.001)
        return np.array([M.median_time(lambda t=t: t.predict(x), 3) / rows for t in self.ensemble.trees]), M.median_time(lambda: plain.contains_np(h), 9) / rows

    def staged(self, fpr: float, lam: float = 1.0, deepest: int | None = None, timed: bool = False) -> Plan:
        """The best of the searched plans and of their special case without gates and exits, which is the partitioned filter; backup filters take what clipping leaves, as there."""
        c = self.costs(fpr, timed)
        found = [_head(f, deepest) for f in self.flows] if deepest else list(self.flows)
        plans = [configure(f, c, fpr, lam) for f in found]
        plans += [replace(B.partitioned(self.keys, self.others, fpr, c, d, fill=False), lam=lam) for d in self.depths() if d <= (deepest or d)]
        cost = lambda p: lam * p.memory / c.plain_bits + (1 - lam) * p.reject / c.plain_time if p.depth else lam
        plans = [replace(q, objective=cost(q)) for q in map(refill, plans)]
        return min(plans, key=lambda p: (round(p.objective, 12), p.reject, p.memory, p.depth))

    def depths(self) -> list[int]:
        return [d for d in (1, 2, 5, 10, 20, 50, 100) if d <= self.ensemble.depth]

    def row(self, method: str, fpr: float, lam: float, p) -> tuple:
        model = float(self.ensemble.bits()[: p.depth].sum())
        return (self.name, method, float(fpr), float(lam), int(p.depth), float(p.memory), model, float(p.reject), float(p.expected_fpr))
    def close(self) -> None:
        """Nothing is held in the cache; the written files stay in the shared folder, as all scratch files do."""
        self.examples = self.scored = None


def _head(f, deepest: int):
    d = min(deepest, f.depth)
    return replace(f, key_reach=f.key_reach[:d], non_reach=f.non_reach[:d], key_leave=f.key_leave[:d], non_leave=f.non_leave[:d], key_leaf=f.key_leaf[:d], non_leaf=f.non_leaf[:d], cuts=f.cuts[:d], theta=f.theta[:d])


def memory_vs_rate(b: Bench, rates=RATES) -> list[tuple]:
    out = []
    for fpr in rates:
        c = b.costs(fpr)
        out += [b.row("plain", fpr, 1, configure(b.flows[0], c, fpr, 0.0)), b.row("staged", fpr, 1, b.staged(fpr))]
        for d in [x for x in (1, 10, 100) if x <= b.ensemble.depth]:
            bits = float(b.ensemble.bits()[:d].sum())
            out += [b.row(f"partitioned_{d}", fpr, 1, B.partitioned(b.keys, b.others, fpr, c, d)), b.row(f"prefiltered_{d}", fpr, 1, B.prefiltered(b.keys[d - 1], b.others[d - 1], fpr, bits, d))]
            if s := B.single_threshold(b.keys[d - 1], b.others[d - 1], fpr, bits, d):
                out.append(b.row(f"single_{d}", fpr, 1, s))
    return out


def memory_vs_reject(b: Bench, fpr: float = 0.001, lams=LAMBDAS) -> list[tuple]:
    c = b.costs(fpr)
    out = [b.row("staged", fpr, lam, b.staged(fpr, lam)) for lam in lams]
    for d in b.depths():
        out += [b.row("partitioned", fpr, 1, B.partitioned(b.keys, b.others, fpr, c, d)), b.row("prefiltered", fpr, 1, B.prefiltered(b.keys[d - 1], b.others[d - 1], fpr, float(b.ensemble.bits()[:d].sum()), d))]
    return out


def memory_vs_reject_time(b: Bench, fpr: float = 0.001, lams=LAMBDAS) -> list[tuple]:
    """The same in measured time: seconds of learners enter the plans, reject_us is what they add up to, in microseconds per non-key."""
    c = b.costs(fpr, True)
    row = lambda method, lam, p: (b.name, method, float(fpr), float(lam), int(p.depth), float(p.memory), 1e6 * float(p.reject), 1e6 * c.plain_time)
    out = [row("staged", lam, b.staged(fpr, lam, timed=True)) for lam in lams]
    for d in b.depths():
        out += [row("partitioned", 1, B.partitioned(b.keys, b.others, fpr, c, d)), row("prefiltered", 1, _timed(B.prefiltered(b.keys[d - 1], b.others[d - 1], fpr, float(b.ensemble.bits()[:d].sum()), d), float(c.time[:d].sum())))]
    if plan := B.budgeted(b.keys, b.others, c, b.staged(fpr).memory, 40)[0]:
        out.append(row("budgeted", 1, plan))
    return out


def _timed(plan, seconds: float):
    """A baseline that runs all its learners for whatever passes its gate."""
    return replace(plan, reject=seconds * (plan.reject / plan.depth if plan.depth else 0.0))


def reject_ratio(rows: list[tuple]) -> list[tuple]:
    """(workload, method, least bits, its reject_us, reject_us of the staged plan that takes no more bits, ratio)."""
    out = []
    for name in dict.fromkeys(r[0] for r in rows):
        staged = [r for r in rows if r[0] == name and r[1] == "staged"]
        for method in ("partitioned", "prefiltered", "budgeted"):
            others = [r for r in rows if r[0] == name and r[1] == method]
            if others:
                least = min(others, key=lambda r: r[5])
                fits = [r for r in staged if r[5] <= least[5] * (1 + 1e-9)]
                mine = min(fits, key=lambda r: r[6]) if fits else min(staged, key=lambda r: r[5])
                out.append((name, method, least[5], least[6], mine[5], mine[6], least[6] / mine[6] if mine[6] > 0 else None))
    return out


RATIO = "workload string, method string, bits double, reject_us double, staged_bits double, staged_reject_us double, ratio double"


def saving(rows: list[tuple]) -> list[tuple]:
    """(workload, rate, staged bits, least bits of a partitioned filter, share saved) from the rows of memory_vs_rate."""
    out = []
    for name, fpr in dict.fromkeys((r[0], r[2]) for r in rows):
        here = [r for r in rows if (r[0], r[2]) == (name, fpr)]
        staged = next(r[5] for r in here if r[1] == "staged")
        best = min(r[5] for r in here if r[1].startswith("partitioned"))
        out.append((name, fpr, staged, best, 1 - staged / best))
    return out


SAVING = "workload string, fpr double, staged_bits double, partitioned_bits double, saved double"


def other_filters(b: Bench, bits_per_key=tuple(range(1, 16)), most: int = 20_000) -> list[tuple]:
    """(workload, method, parameter, bits per key, unseen rate, seconds per query one by one, and in a batch) of the subset ensemble, the projection hash in both forms, and the hash-adaptive filter; on at most `most` rows a side."""
    part = lambda split: smallest(b.examples.filter(F.col("split") == split), most).select("h", "x").toArrow()
    (kh, kx), (nh, nx), (th, tx) = ((t["h"].to_numpy(), np.nan_to_num(matrix(t["x"]))) for t in map(part, ("key", "train", "test")))
    out = []
    for bits in bits_per_key:
        f = B.HashAdaptive(float(bits)).fit(kh, nh)
        out.append((b.name, "hash_adaptive", float(bits), f.memory / len(kh), float(f.contains_np(th).mean()), M.row_time(lambda h, _, f=f: f.contains_np(h), th, tx, 100), M.median_time(lambda f=f: f.contains_np(th), 3) / len(th)))
    for cells in (5, 10, 20):
        p = B.ProjectionHash(m=cells * len(kh)).fit(kx, nx)
        out.append((b.name, "projection_hash", float(cells), p.bits / len(kh), float(p.contains_x(tx).mean()), M.median_time(lambda p=p: p.contains_x(tx[:500], "row"), 1) / min(500, len(tx)), M.median_time(lambda p=p: p.contains_x(tx), 3) / len(tx)))
    ks, ns = B.learner_outcomes(b.examples, b.ensemble)
    for share in (0.3, 0.5, 0.8, 1.0):
        r = B.subset_ensemble(ks, ns, b.ensemble.bits(), b.n, share * b.costs(0.001).plain_bits)
        out.append((b.name, "subset_ensemble", share, r["total_bits"] / max(1, b.n), r["real_fpr"], float(b.times[0][r["chosen"]].sum()), float(b.times[0][r["chosen"]].sum())))
    return out


OTHERS = "workload string, method string, parameter double, bits_per_key double, unseen_rate double, row_s double, batch_s double"


def updates(spark: SparkSession, sf_dir: str, periods: int = 6, fpr: float = 0.01, boosting: Boosting = Boosting(rounds=20), kind: str = "counting") -> list[tuple]:
    """(period, keys before, inserted, missed, rate on the period's non-keys, estimated rate, rebuilt, deleted and still found).

    The first period of `events` is built; the keys of each later one are inserted and its non-keys asked, until
    the rules call for a rebuild from everything seen so far. At the end of a period a tenth of its keys is deleted.
    """
    span = table(spark, sf_dir, "events").select(F.col("event_id").cast("string").alias("eid"), F.ntile(periods).over(Window.orderBy(F.to_date("ts"))).alias("period"))
    e = load("event_tail", spark, sf_dir).join(span, "eid").persist()
    out, f, base, late = [], None, 0, 0
    for p in range(1, periods + 1):
        now, keys = e.filter(F.col("period") == p), e.filter((F.col("period") == p) & F.col("is_key"))
        n, rebuilt = keys.count(), f is None
        if f is not None:
            f.insert(keys)
            late += n
        else:
            f, base, late = build(e.filter(F.col("period") <= p), fpr, 0.9, boosting, kind=kind), n, 0
        ask = lambda: f.lookup(now.filter(~F.col("is_key"))).agg(F.count_if("found").alias("hits"), F.count("*").alias("n")).first()  # noqa: B023, E731
        r = ask()
        state = {"inserted_share": late / max(1, base), "estimated_fpr": r.hits / max(1, r.n), "measured_fpr": r.hits / max(1, r.n)}
        if p > 1 and service.needs_rebuild(state, fpr, 0.5):
            f, rebuilt = build(e.filter(F.col("period") <= p), fpr, 0.9, boosting, kind=kind), True
            base, late = base + late, 0
        missed = f.lookup(keys).filter("not found").count()
        gone = keys.filter("h % 10 = 0")
        f.delete(gone)
        still = f.lookup(gone).filter("found").count()
        lost = f.lookup(keys.filter("h % 10 <> 0")).filter("not found").count()
        f.insert(gone)
        out.append((p, base + late - n, n, missed, r.hits / max(1, r.n), rebuilt, gone.count(), still, lost))
    e.unpersist()
    return out


UPDATES = "period int, held long, inserted long, missed long, rate_before_rebuild double, rebuilt boolean, deleted long, still_found long, lost_by_deletion long"


def guarded_joins(spark: SparkSession, sf_dir: str, fpr: float = 0.01) -> list[tuple]:
    """(join, rows, passed, matched, seconds exact, seconds behind the filter, mean latency by the model) of exact lookups behind a filter: orders of the urgent kind, orders without items, parts of a size."""
    orders, items, parts = (table(spark, sf_dir, t) for t in ("orders", "lineitem", "part"))
    cases = {
        "semi_urgent": (items, orders.filter("o_orderpriority = '1-URGENT'"), "l_orderkey", "o_orderkey", "left_semi"),
        "anti_items": (orders, items.select("l_orderkey").distinct(), "o_orderkey", "l_orderkey", "left_anti"),
        "star_part": (items, parts.filter("p_size < 5").select("p_partkey", "p_size"), "l_partkey", "p_partkey", "inner"),
    }
    out = []
    for name, (fact, keys, a, b, how) in cases.items():
        run = lambda df: M.median_time(lambda: df.write.format("noop").mode("overwrite").save(), 3)
        exact = run(fact.join(keys.hint("merge"), F.col(a) == F.col(b), how))
        guarded = run(joins.prefilter_join(fact, keys.hint("merge"), a, b, how, fpr))
        rows, passed = fact.count(), joins.prefilter(fact, keys, a, b, fpr).count()
        matched = fact.join(keys.select(F.col(b).alias("_k")).distinct(), F.col(a) == F.col("_k"), "left_semi").count()
        rate = (passed - matched) / max(1, rows - matched)
        probe = M.median_time(lambda: joins.prefilter(fact, keys, a, b, fpr).select(a).write.format("noop").mode("overwrite").save(), 3)
        out.append((name, rows, passed, matched, exact, guarded, M.expected_latency(rate, probe / max(1, rows), probe / max(1, rows), exact / max(1, rows))))
    return out


GUARDED = "name string, fact_rows long, passed long, matched long, exact_s double, guarded_s double, latency_s double"


def all_sets(spark: SparkSession, sf_dir: str, fpr: float = 0.01, boosting: Boosting = Boosting(rounds=20)) -> list[tuple]:
    """Plain, partitioned and staged filters of all fourteen workloads."""
    out = []
    for name in WORKLOADS:
        b = Bench(spark, sf_dir, name, boosting)
        c = b.costs(fpr)
        out += [b.row("plain", fpr, 1, configure(b.flows[0], c, fpr, 0.0)), b.row("staged", fpr, 1, b.staged(fpr))]
        out.append(b.row("partitioned", fpr, 1, min((B.partitioned(b.keys, b.others, fpr, c, d) for d in b.depths()), key=lambda p: p.memory)))
    return out


def offered_learners(b: Bench, fpr: float = 0.001) -> list[tuple]:
    return [b.row(f"offered_{d}", fpr, 1, b.staged(fpr, 1.0, d)) for d in b.depths()]


def used_learners(b: Bench, fpr: float = 0.001) -> list[tuple]:
    c = b.costs(fpr)
    return [b.row("partitioned", fpr, 1, B.partitioned(b.keys, b.others, fpr, c, d)) for d in b.depths()] + [b.row("staged", fpr, 1, b.staged(fpr))]


def refined_thresholds(b: Bench, fpr: float = 0.001, lam: float = 0.9, steps: int = 100) -> list[tuple]:
    scored = kept(b.scored, "scores")
    began = time.perf_counter()
    plan, tried = refine(scored, b.thetas, b.costs(fpr), fpr, lam, steps)
    seconds = time.perf_counter() - began
    began = time.perf_counter()
    quick = best_plan(flows(scored, b.thetas), b.costs(fpr), fpr, lam)
    return [b.row(f"refined_{tried}_tried_{seconds:.1f}s", fpr, lam, plan), b.row(f"quantile_{time.perf_counter() - began:.1f}s", fpr, lam, quick)]


def against_budgeted(b: Bench, fpr: float = 0.001, steps: int = 40) -> list[tuple]:
    mine = b.staged(fpr)
    plan, _, _ = B.budgeted(b.keys, b.others, b.costs(fpr), mine.memory, steps)
    return [b.row("staged", fpr, 1, mine)] + ([b.row("budgeted", plan.fpr, 1, plan)] if plan else [])


def reject_distribution(b: Bench, fpr: float = 0.001) -> list[tuple]:
    """(workload, method, bits, learners run, test non-keys): the partitioned filter of the least memory, and the staged one that rejects soonest within that memory; both built."""
    test = b.examples.filter("split = 'test'")
    part = min((B.partitioned(b.keys, b.others, fpr, b.costs(fpr), d) for d in b.depths()), key=lambda p: p.memory)
    mine = [b.staged(fpr, lam) for lam in (0.3, 0.5, 0.7, 0.8, 0.9, 0.95, 0.99, 1.0)]
    fits = [p for p in mine if p.memory <= part.memory * 1.001]
    plans = {"staged": min(fits, key=lambda p: p.reject) if fits else min(mine, key=lambda p: p.memory), "partitioned": part}
    out = []
    for name, p in plans.items():
        f = StagedFilter(p, b.ensemble.head(max(1, p.depth))).materialise(b.examples.filter("split = 'key'"))
        out += [(b.name, name, float(p.memory), int(r.learners_run), int(r["count"])) for r in f.lookup(test).groupBy("learners_run").count().collect()]
    return out


def construction_times(b: Bench, fpr: float = 0.001, lam: float = 1.0) -> list[tuple]:
    """(workload, method, phase, seconds). The calibration's one pass over the scores also counts the flow and the histograms that the configurations start from."""
    keys = b.examples.filter("split = 'key'")
    began = time.perf_counter()
    plan = best_plan(b.flows, b.costs(fpr), fpr, lam)
    config = time.perf_counter() - began
    f = StagedFilter(plan, b.ensemble.head(max(1, plan.depth))).materialise(keys)
    d = b.ensemble.depth
    began = time.perf_counter()
    B.prefiltered(b.keys[d - 1], b.others[d - 1], fpr, 0.0, d)
    pre = time.perf_counter() - began
    began = time.perf_counter()
    BloomFilter.build(keys, "h", fpr)
    plain = time.perf_counter() - began
    began = time.perf_counter()
    B.budgeted(b.keys, b.others, b.costs(fpr), plan.memory, 20)
    black = time.perf_counter() - began
    rows = []
    for method, c in (("staged", config), ("prefiltered", pre), ("budgeted", black)):
        rows += [(b.name, method, "training", b.training), (b.name, method, "calibration", b.calibration), (b.name, method, "configuration", c), (b.name, method, "insertion", f.report.insertion)]
    return [*rows, (b.name, "plain", "insertion", plain)]


def seen_and_unseen(b: Bench, bits_per_key=(1, 5, 10, 15)) -> list[tuple]:
    """(workload, method, parameter, seen rate, unseen rate) of the filters that learn from known non-keys; on a bounded sample of 20,000 rows a side."""

    def part(split: str, n: int = 20_000):
        t = smallest(b.examples.filter(F.col("split") == split), n).select("h", "x").toArrow()
        return t["h"].to_numpy(), matrix(t["x"].combine_chunks())

    (kh, kx), (nh, nx), (th, tx) = part("key"), part("train"), part("test")
    out = []
    for bits in bits_per_key:
        f = B.HashAdaptive(bits).fit(kh, nh)
        assert f.contains_np(kh).all()
        out.append((b.name, "hash_adaptive", float(bits), float(f.contains_np(nh).mean()), float(f.contains_np(th).mean())))
    p = B.ProjectionHash(m=10 * len(kh)).fit(kx, nx)
    assert p.contains_x(kx).all()
    return [*out, (b.name, "projection_hash", 10.0, float(p.contains_x(nx).mean()), float(p.contains_x(tx).mean()))]


def subset_points(b: Bench, shares=(0.3, 0.5, 0.8)) -> list[tuple]:
    ks, ns = B.learner_outcomes(b.examples, b.ensemble)
    plain = b.costs(0.001).plain_bits
    rows = [B.subset_ensemble(ks, ns, b.ensemble.bits(), b.n, s * plain) for s in shares]
    return [(b.name, "subset_ensemble", float(s), len(r["chosen"]), r["assumed_fpr"], r["real_fpr"]) for s, r in zip(shares, rows, strict=True)]


def model_families(spark: SparkSession, sf_dir: str, name: str, grid=((1, 20), (2, 20), (4, 20)), fpr: float = 0.001) -> list[tuple]:
    """Other boosting settings and the library's trees in place of ours."""
    out = []
    for depth, rounds in grid:
        b = Bench(spark, sf_dir, name, Boosting(rounds=rounds, depth=depth))
        out.append(b.row(f"depth_{depth}_rounds_{rounds}", fpr, 1, b.staged(fpr)))
    return out


def run_all(spark: SparkSession, sf_dir: str, names=("url_easy", "file_wide", "physics_hard"), boosting: Boosting = Boosting()) -> dict[str, DataFrame]:
    rows: dict[str, list] = {k: [] for k in ("memory_vs_rate", "memory_vs_reject", "offered_learners", "used_learners", "against_budgeted")}
    for name in names:
        b = Bench(spark, sf_dir, name, boosting)
        for k in rows:
            rows[k] += globals()[k](b)
    return {k: spark.createDataFrame(v, ROW) for k, v in rows.items()}


def build_and_measure(spark: SparkSession, sf_dir: str, name: str, fpr: float, lam: float, boosting: Boosting) -> dict:
    e = load(name, spark, sf_dir).persist()
    f = build(e, fpr, lam, boosting)
    rate = M.measured_fpr(f, e)
    out = {"fpr": rate[0], "low": rate[1], "high": rate[2], "tests": rate[3], "missed": M.false_negatives(f, e), "bits": M.total_bits(f), **M.construction(f), "depth": f.plan.depth}
    e.unpersist()
    return out


__all__ = [k for k in globals() if not k.startswith("_")]
