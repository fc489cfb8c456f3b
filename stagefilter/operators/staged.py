"""The staged filter: gates and scorers in turn, exits for confident scores, a filter for each score region at the end."""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagefilter.functions.hashing import positions, smallest
from stagefilter.functions.sizing import bloom_size, ideal_bits
from stagefilter.operators.amq import CountingBloom, CuckooFilter, QuotientFilter
from stagefilter.operators.bloom import BLOCK_BITS, MOST_BROADCAST, AcceptAll, BloomFilter, RejectAll, bit_is_set, bitmaps, block_of
from stagefilter.operators.boosting import Boosting, train
from stagefilter.operators.flow import ALPHAS, bin_of, flows, quantile_thetas
from stagefilter.operators.scoring import Ensemble, identities, matrix, score_prefixes
from stagefilter.plans.config_dp import Costs, Plan, configure, refill
from stagefilter.plans.thresholds import DensitySampler, knots_to_alphas, thetas_from_sketch

#: Filters that can stand in for Bloom filters, and what a cell of theirs takes in memory beside a bit.
FAMILIES = {"counting": CountingBloom, "cuckoo": CuckooFilter, "quotient": QuotientFilter}
CELL_BITS = {"counting": 32}
VERDICT = "found boolean, exit_depth int, exit_role string, region int, learners_run int, probes int"


@dataclass
class Report:
    """Seconds of the four phases of a build, and what was tried."""

    training: float = 0.0
    calibration: float = 0.0
    configuration: float = 0.0
    insertion: float = 0.0
    tried: int = 0

    @property
    def total(self) -> float:
        return self.training + self.calibration + self.configuration + self.insertion


@dataclass
class StagedFilter:
    plan: Plan
    ensemble: Ensemble
    filters: dict[str, object] = field(default_factory=dict)
    report: Report = field(default_factory=Report)
    seed: int = 0
    kind: str = "bloom"  # or counting, cuckoo, quotient: what every gate, exit and leaf is made of
    hook: object = None  # called as hook(depth, rows, scores) with the scores after each learner of a walk

    # --- the walk -------------------------------------------------------------------

    def names(self) -> list[tuple[str, float, float]]:
        """(name, rate, key share) of every filter, in path order."""
        p = self.plan
        if not p.depth:
            return [("plain", p.fpr, 1.0)]
        return [({"gate": f"g{d}", "exit": f"e{d}", "leaf": f"l{k}"}[role], fpr, share) for d, role, k, fpr, share, _, _ in p.rows()]

    def walk(self, h: np.ndarray, x: np.ndarray, probe: bool = True):
        """Path of each element: found, depth, role (0 plain, 1 gate, 2 exit, 3 leaf), region, learners run, probes. With probe off gates and backups let all through."""
        n, p = len(h), self.plan
        found, role = np.zeros(n, bool), np.zeros(n, np.int8)
        depth, region = np.zeros(n, np.int32), np.full(n, -1, np.int32)
        learners, probes = np.zeros(n, np.int32), np.zeros(n, np.int32)

        def ask(name: str, rows: np.ndarray) -> np.ndarray:
            f = self.filters.get(name)
            if not probe or f is None or isinstance(f, AcceptAll) and not isinstance(f, RejectAll):
                return np.ones(len(rows), bool)
            probes[rows] += 1
            return f.contains_np(h[rows])

        if not p.depth:
            found[:] = ask("plain", np.arange(n))
            return found, depth, role, region, learners, probes
        rows, margin = np.arange(n), np.full(n, self.ensemble.base)
        for d in range(p.depth):
            if p.gates[d]:
                ok = ask(f"g{d + 1}", rows)
                gone = rows[~ok]
                depth[gone], role[gone] = d + 1, 1
                rows = rows[ok]
            margin[rows] += self.ensemble.trees[d].predict(x[rows])
            learners[rows] += 1
            s = self.ensemble.margin_to_score(margin[rows], d + 1)
            if self.hook is not None:
                self.hook(d + 1, rows, s)
            depth[rows] = d + 1
            if d + 1 < p.depth:
                out = s >= p.flow.theta[d]
                leave = rows[out]
                role[leave] = 2
                found[leave] = ask(f"e{d + 1}", leave)
                rows = rows[~out]
            else:
                k = np.searchsorted(np.array(p.flow.cuts[d]), bin_of(s, p.flow.bins), side="right")
                role[rows], region[rows] = 3, k
                for i in np.unique(k):
                    part = rows[k == i]
                    found[part] = ask(f"l{i}", part)
        return found, depth, role, region, learners, probes

    def path_names(self, depth: np.ndarray, role: np.ndarray, region: np.ndarray) -> list[list[str]]:
        """Names of the filters that hold each key."""
        if not self.plan.depth:
            return [["plain"]] * len(depth)
        gates = [[f"g{i + 1}" for i in range(d) if self.plan.gates[i]] for d in range(self.plan.depth + 1)]
        return [[*gates[d], f"e{d}" if r == 2 else f"l{k}"] for d, r, k in zip(depth, role, region, strict=True)]

    # --- distributed use ------------------------------------------------------------

    def routed(self, keys: DataFrame) -> DataFrame:
        """(filter, h): each key once for every filter on its path. Rows without an identity are no keys."""
        held = keys.sparkSession.sparkContext.broadcast(self)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                h = b.column(0).to_numpy()
                _, depth, role, region, _, _ = held.value.walk(h, matrix(b.column(1), held.value.ensemble.width), probe=False)
                paths = held.value.path_names(depth, role, region)
                yield pa.RecordBatch.from_arrays([pa.array([f for p in paths for f in p], pa.string()), pa.array(np.repeat(h, [len(p) for p in paths]))], names=["filter", "h"])

        return keys.select("h", "x").filter("h is not null").mapInArrow(run, "filter string, h long")

    def materialise(self, keys: DataFrame) -> StagedFilter:
        """Sizes every filter from exact key counts, then sets all bits in the JVM, one bitmap per filter and block."""
        began = time.perf_counter()
        rates = {name: fpr for name, fpr, _ in self.names()}
        routed = self.routed(keys)
        counts = {r["filter"]: r["count"] for r in routed.groupBy("filter").count().collect()}
        self.filters, shapes = {}, []
        for i, (name, fpr) in enumerate(rates.items()):
            n = counts.get(name, 0)
            if name[0] == "g" and fpr >= 1:
                continue
            if n == 0:
                self.filters[name] = RejectAll()
            elif fpr >= 1:
                self.filters[name] = AcceptAll()
            else:
                f = self._empty(n, fpr, self.seed + 1 + i)
                self.filters[name] = f
                shapes.append((name, f.m * CELL_BITS.get(self.kind, 1)))
        if sum(m for _, m in shapes) // 8 > MOST_BROADCAST:
            raise ValueError("filters are over the broadcast limit; use sharded_bits")
        self._fill(routed, [name for name, _ in shapes], counts)
        self.report.insertion += time.perf_counter() - began
        return self

    def lookup(self, df: DataFrame, keep: tuple[str, ...] = ("eid",)) -> DataFrame:
        """keep columns and the verdict. Needs h and x. A null identity is never found; null features count as missing values."""
        held = df.sparkSession.sparkContext.broadcast(self)
        roles = np.array(["plain", "gate", "exit", "leaf"])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                h, known = identities(b.column("h"))
                found, depth, role, region, learners, probes = held.value.walk(h, matrix(b.column("x"), held.value.ensemble.width))
                yield pa.RecordBatch.from_arrays([*[b.column(c) for c in keep], pa.array(found & known), pa.array(depth), pa.array(roles[role]), pa.array(region), pa.array(learners), pa.array(probes)], names=[*keep, *[x.split()[0] for x in VERDICT.split(", ")]])

        rows = df.select(*dict.fromkeys([*keep, "h", "x"]))
        types = "".join(f"{c} {rows.schema[c].dataType.simpleString()}, " for c in keep)
        return rows.mapInArrow(run, types + VERDICT)

    def insert(self, keys: DataFrame) -> StagedFilter:
        """Adds keys to the live filters along their paths. A filter that rejected all becomes a small real one. Counts and bitmaps reach the driver, never hashes."""
        routed = self.routed(keys)
        counts = {r["filter"]: r["count"] for r in routed.groupBy("filter").count().collect()}
        for name, n in counts.items():
            if isinstance(self.filters.get(name), RejectAll):
                self.filters[name] = self._empty(max(64, 2 * n), self.plan.fpr, self.seed + 997)
        self._fill(routed, [name for name in counts if not isinstance(self.filters.get(name), AcceptAll | None)], counts)
        return self

    def delete(self, keys: DataFrame) -> StagedFilter:
        """Takes keys out along their paths; needs counting or cuckoo filters, and keys that are in (proven by the exact table)."""
        if self.kind not in ("counting", "cuckoo"):
            raise ValueError(f"{self.kind} filters can't delete")
        routed = self.routed(keys)
        counts = {r["filter"]: r["count"] for r in routed.groupBy("filter").count().collect()}
        self._fill(routed, [name for name in counts if not isinstance(self.filters.get(name), AcceptAll | None)], counts, -1)
        return self

    def _empty(self, n: int, fpr: float, seed: int):
        return BloomFilter.empty(n, fpr, seed) if self.kind == "bloom" else FAMILIES[self.kind](n, fpr, seed)

    def _fill(self, routed: DataFrame, names: list[str], counts: dict[str, int], sign: int = 1) -> None:
        """Puts the routed keys into filters of these names, or takes them out. Bitmaps and counters are summed up in the JVM; filters of fingerprints get their hashes in blocks."""
        if self.kind == "bloom":
            self._set_bits(routed, names)
            for name in names:
                self.filters[name].n += counts.get(name, 0)
        elif self.kind == "counting" and names:
            shapes = [(n, f.m, f.k, f.seed) for n in names if (f := self.filters[n])]
            shape = F.broadcast(routed.sparkSession.createDataFrame(shapes, "filter string, m long, k long, seed long"))  # one row per filter of the plan
            points = routed.join(shape, "filter").select("filter", F.explode(positions(F.col("h"), F.col("seed"), F.col("k"), F.col("m"))).alias("p"))
            # no more cells than the filters have counters, and those are under the broadcast limit
            cells = points.groupBy("filter", "p").count().groupBy("filter", F.floor(F.col("p") / BLOCK_BITS).alias("block")).agg(F.collect_list("p").alias("p"), F.collect_list("count").alias("c"))
            for r in cells.toLocalIterator():
                self.filters[r["filter"]].counts[np.array(r.p)] += sign * np.array(r.c, np.int32)
            for name in names:
                self.filters[name].n += sign * counts.get(name, 0)
        else:
            for name in names:
                held: list[int] = []
                put = self.filters[name].insert if sign > 0 else self.filters[name].delete
                for r in routed.filter(F.col("filter") == name).select("h").toLocalIterator():
                    held.append(r.h)
                    if len(held) == 100_000:
                        put(np.array(held, np.int64))
                        held = []
                if held:
                    put(np.array(held, np.int64))

    def _set_bits(self, routed: DataFrame, names: list[str]) -> None:
        """Sets the bits of the routed keys in the JVM, one bitmap per filter and block, and joins them to the filters."""
        if not names:
            return
        shapes = [(n, f.m, f.k, f.seed) for n in names if (f := self.filters[n])]
        shape = F.broadcast(routed.sparkSession.createDataFrame(shapes, "filter string, m long, k long, seed long"))  # one row per filter of the plan
        points = routed.join(shape, "filter").select("filter", F.explode(positions(F.col("h"), F.col("seed"), F.col("k"), F.col("m"))).alias("p"))
        for r in bitmaps(points, "filter").toLocalIterator():
            f, part = self.filters[r["filter"]], np.frombuffer(bytes(r.bits), np.uint8)
            a = r.block * BLOCK_BITS // 8
            f.bits[a : a + len(part)] |= part[: len(f.bits) - a]

    def sharded_bits(self, keys: DataFrame) -> tuple[DataFrame, DataFrame]:
        """The filters as tables: shapes (filter, blocks, k, seed) and bits (filter, block, bits). Nothing but counts is collected."""
        spark = keys.sparkSession
        routed = self.routed(keys)
        counts = {r["filter"]: r["count"] for r in routed.groupBy("filter").count().collect()}
        shapes = []
        for i, (name, fpr, _) in enumerate(self.names()):
            if 0 < fpr < 1 and counts.get(name):
                m, k = bloom_size(counts[name], fpr / 1.03)
                shapes.append((name, max(1, -(-m // BLOCK_BITS)), k, self.seed + 1 + i))
        shape = spark.createDataFrame(shapes, "filter string, blocks long, k long, seed long")
        rows = routed.join(F.broadcast(shape), "filter")
        h = F.col("h")
        points = rows.select("filter", block_of(h, F.col("seed"), F.col("blocks")).alias("block"), F.explode(positions(h, F.col("seed"), F.col("k"), F.lit(BLOCK_BITS))).alias("at"))
        return shape, points.groupBy("filter", "block").agg(F.bitmap_construct_agg("at").alias("bits"))

    def _advance(self, df: DataFrame, first: int, last: int) -> DataFrame:
        """Runs learners first + 1 .. last for the rows that are still under way (asked is null). A row that leaves at an exit, or after the last learner, names its filter and drops its features."""
        held = df.sparkSession.sparkContext.broadcast(self)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            f, p = held.value, held.value.plan
            for b in batches:
                margin, asked = b.column("margin").to_numpy().copy(), np.array(b.column("asked").to_pylist(), object)
                rows = np.flatnonzero([a is None for a in asked])
                x = matrix(b.column("x"), f.ensemble.width)
                for d in range(first, last):
                    margin[rows] += f.ensemble.trees[d].predict(x[rows])
                    s = f.ensemble.margin_to_score(margin[rows], d + 1)
                    if d + 1 < p.depth:
                        out = s >= p.flow.theta[d]
                        asked[rows[out]] = f"e{d + 1}"
                        rows = rows[~out]
                    else:
                        k = np.searchsorted(np.array(p.flow.cuts[d]), bin_of(s, p.flow.bins), side="right")
                        asked[rows] = [f"l{i}" for i in k]
                done = pa.array(asked, pa.string())
                yield pa.RecordBatch.from_arrays([b.column("eid"), b.column("h"), pc.if_else(done.is_null(), b.column("x"), pa.scalar(None, b.column("x").type)), pa.array(margin), done], names=["eid", "h", "x", "margin", "asked"])

        return df.select("eid", "h", "x", "margin", "asked").mapInArrow(run, f"eid string, h long, x {df.schema['x'].dataType.simpleString()}, margin double, asked string")

    def lookup_sharded(self, df: DataFrame, shape: DataFrame, bits: DataFrame, spread: int = 64) -> DataFrame:
        """(eid, found) against sharded filters, one row for each row of df.

        Learners up to a gate run in one Arrow pass, the gate is one join on (filter, block), and only
        rows that it lets through go on; the exits and leaves of all rows are one last join. A filter
        of few blocks is copied until it has `spread` of them, and rows are dealt over the copies, so
        that no block draws all rows to one task. Rows that ask nothing meet no block and spread by hash.
        """
        spark, p = df.sparkSession, self.plan
        shapes = {r["filter"]: r for r in shape.collect()}  # one row per filter of the plan
        rates = {n: fpr for n, fpr, _ in self.names()}
        copies = F.greatest(F.lit(1), F.floor(F.lit(spread) / F.col("blocks"))).cast("int")
        table = bits.join(F.broadcast(shape), "filter").select(F.col("filter").alias("_f"), F.col("block").alias("_b"), "bits", F.explode(F.sequence(F.lit(0), copies - 1)).alias("_copy"))
        shape = F.broadcast(spark.createDataFrame([(n, bool(fpr >= 1), *((s.blocks, s.k, s.seed) if (s := shapes.get(n)) else (None,) * 3)) for n, fpr in rates.items()], "_n string, open boolean, blocks long, k long, seed long"))
        h = F.col("h")

        def probe(rows: DataFrame, name) -> DataFrame:
            """rows with `hit`: whether the filter named by the column `name` has the row; null where that is null."""
            known = rows.withColumn("_name", name).join(shape, F.col("_name") == F.col("_n"), "left")
            some = F.col("_n").isNotNull() & ~F.col("open") & F.col("k").isNotNull()
            known = known.withColumn("_block", F.when(some, block_of(h, F.col("seed"), F.col("blocks"))).otherwise(-1 - F.abs(F.xxhash64("eid") % 1_000_003)))
            known = known.withColumn("_part", F.when(some, F.pmod(F.xxhash64("h", "eid"), copies)).otherwise(0).cast("int"))
            met = known.join(table, (F.col("_name") == F.col("_f")) & (F.col("_block") == F.col("_b")) & (F.col("_part") == F.col("_copy")), "left") if shapes else known.withColumn("bits", F.lit(None).cast("binary"))
            inside = F.forall(positions(h, F.col("seed"), F.col("k"), F.lit(BLOCK_BITS)), lambda at: bit_is_set(F.col("bits"), at))
            hit = F.when(F.col("_n").isNull(), None).when(F.col("open"), True).when(F.col("bits").isNull(), False).otherwise(inside)
            return met.select(*[F.col(c) for c in rows.columns], hit.alias("hit"))

        none = "-"  # asks no filter: rejected
        rows = df.select(F.col("eid").cast("string").alias("eid"), "h", "x", F.lit(float(self.ensemble.base)).alias("margin"), F.when(h.isNull(), none).otherwise("plain" if not p.depth else F.lit(None)).cast("string").alias("asked"))
        at = 0
        for d in range(p.depth):
            if p.gates[d] and rates.get(f"g{d + 1}", 1.0) < 1:
                rows = self._advance(rows, at, d) if d > at else rows
                at = d
                passed = probe(rows, F.when(F.col("asked").isNull(), f"g{d + 1}"))
                rows = passed.select("eid", "h", "x", "margin", F.when(F.col("hit") | F.col("hit").isNull(), F.col("asked")).otherwise(none).alias("asked"))
        rows = self._advance(rows, at, p.depth) if p.depth else rows
        return probe(rows.select("eid", "h", "asked"), F.col("asked")).select("eid", F.coalesce("hit", F.lit(False)).alias("found"))

    def memory(self) -> list[tuple[str, float, int]]:
        """(part, ideal bits, actual bits)."""
        p = self.plan
        n = p.flow.n_keys if p.flow else 0
        out = [("learners", float(self.ensemble.bits()[: p.depth].sum()), int(self.ensemble.bits()[: p.depth].sum()))]
        for name, fpr, share in self.names():
            f = self.filters.get(name)
            out.append((name, ideal_bits(n * share, fpr) if share > 0 else 0.0, int(f.m) if f is not None else 0))
        return out


def plain_costs(ensemble: Ensemble, n: int, fpr: float, unit_time: float = 1.0, plain_time: float = 1.0) -> Costs:
    return Costs(ensemble.bits(), np.full(ensemble.depth, unit_time), max(1.0, ideal_bits(n, fpr)), plain_time)


def best_plan(candidates: list, costs: Costs, fpr: float, lam: float, grid: int = 20) -> Plan:
    plans = [configure(f, costs, fpr, lam, grid) for f in candidates]
    return min(plans, key=lambda p: (round(p.objective, 12), p.reject, p.memory, p.depth))


def refine(scored: DataFrame, seeds: list[np.ndarray], costs: Costs, fpr: float, lam: float, steps: int = 100, block: int = 10, grid: int = 20, parts: int = 8, knots: int = 5, seed: int = 7, sample: int = 20_000) -> tuple[Plan, int]:
    """Thresholds refined by sequential sampling, started from the quantile candidates; never worse than the best of those.

    Candidates are measured a block at a time in one scan. Their quantiles come from a bounded sample of calibration scores.
    """
    warm = flows(scored, seeds, parts)
    plans = [configure(f, costs, fpr, lam, grid) for f in warm]
    best = min(plans, key=lambda p: p.objective)
    sampler = DensitySampler([-4.5] * knots, [-0.3] * knots, seed)
    for a, p in zip(ALPHAS, plans, strict=False):
        sampler.tell([math.log10(max(a, 10**-4.5))] * knots, p.objective)
    rows = smallest(scored.filter("split = 'calib'"), sample).select("s").toArrow()
    table = np.sort(matrix(rows["s"].combine_chunks()), axis=0)
    for _ in range(0, steps, block):
        points = [sampler.ask() for _ in range(block)]
        thetas = [thetas_from_sketch(table, knots_to_alphas(x, table.shape[1])) for x in points]
        for x, f in zip(points, flows(scored, thetas, parts), strict=True):
            p = configure(f, costs, fpr, lam, grid)
            sampler.tell(x, p.objective)
            best = min(best, p, key=lambda q: q.objective)
    return best, len(sampler.values)


def build(examples: DataFrame, fpr: float = 0.01, lam: float = 0.9, boosting: Boosting = Boosting(), grid: int = 20, parts: int = 8, refined: int = 0, fill: bool = False, smooth: float = 0.0, ensemble: Ensemble | None = None, insert: bool = True, kind: str = "bloom") -> StagedFilter:
    """Train, calibrate, configure, insert. kind: what the filters are made of. examples: eid, h, is_key, split, x. refined: steps of threshold refinement; fill: rescale unclipped rates; smooth: added to non-key bins."""
    report, clock = Report(), time.perf_counter
    began = clock()
    ensemble = ensemble or train(examples, boosting)
    report.training = clock() - began
    began = clock()
    scored = score_prefixes(examples.filter("split in ('key', 'calib')"), ensemble).persist()
    n = scored.filter("split = 'key'").count()
    report.calibration = clock() - began
    began = clock()
    costs = plain_costs(ensemble, n, fpr)
    thetas = quantile_thetas(scored) or [np.full(ensemble.depth, math.inf)]
    if refined:
        plan, report.tried = refine(scored, thetas, costs, fpr, lam, refined, grid=grid, parts=parts)
    else:
        plan, report.tried = best_plan(flows(scored, thetas, parts, smooth=smooth), costs, fpr, lam, grid), len(thetas)
    if fill:
        plan = refill(plan)
    scored.unpersist()
    report.configuration = clock() - began
    out = StagedFilter(plan, ensemble.head(max(1, plan.depth)), report=report, kind=kind)
    return out.materialise(examples.filter("split = 'key'")) if insert else out


__all__ = ["StagedFilter", "build", "best_plan", "plain_costs", "refine"]
