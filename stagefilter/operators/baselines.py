"""The filters that the staged filter is compared with."""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagefilter.functions.hashing import positions_np, smallest
from stagefilter.functions.sizing import LOG2E, bloom_size, ideal_bits
from stagefilter.operators.flow import measure_flow
from stagefilter.operators.scoring import Ensemble, matrix
from stagefilter.plans.config_dp import Costs, Plan, make_flow, preset, refill
from stagefilter.plans.thresholds import DensitySampler


def histograms(scored: DataFrame, bins: int = 100) -> tuple[np.ndarray, np.ndarray]:
    """Counts [depth, bin] of keys and calibration non-keys, nothing exiting early."""
    depth = len(scored.select("s").first().s)
    out = np.zeros((2, depth, bins))
    for r in measure_flow(scored, [np.full(depth, math.inf)], bins).filter("bin >= 0").collect():
        out[r.cls, r.depth - 1, r.bin] = r.cnt
    return out[1], out[0]


@dataclass
class LearnedPlan:
    """A baseline's plan: rates by role, bits of filters and of the model, expected rate, expected learners run per non-key."""

    kind: str
    depth: int
    threshold: float
    rates: dict[str, float]
    filter_bits: float
    model_bits: float
    expected_fpr: float
    reject: float

    @property
    def memory(self) -> float:
        return self.filter_bits + self.model_bits


def single_threshold(keys: np.ndarray, others: np.ndarray, fpr: float, model_bits: float = 0.0, depth: int = 1) -> LearnedPlan | None:
    """One threshold: above it found, below it a backup filter. keys, others: histograms at one depth. None if no threshold is feasible."""
    n, best = keys.sum(), None
    for i in range(1, len(keys)):
        high, low = others[i:].sum() / max(others.sum(), 1), keys[:i].sum() / max(n, 1)
        if high >= fpr:
            continue
        backup = (fpr - high) / (1 - high)
        bits = ideal_bits(n * low, backup)
        if best is None or bits < best.filter_bits - 1e-9:
            best = LearnedPlan("single", depth, i / len(keys), {"backup": backup}, bits, model_bits, high + (1 - high) * backup, float(depth))
    return best


def prefilter_rates(high: float, low: float, fpr: float) -> tuple[float, float]:
    """(gate, backup) rates of least memory for the non-key share over the threshold and the key share under it."""
    if high <= 0:
        return 1.0, fpr
    if low <= 0:
        return min(1.0, fpr / high), 0.0
    backup = low * high / ((1 - high) * (1 - low)) if high < 1 and low < 1 else 1.0
    if backup >= 1:
        return fpr, 1.0
    gate = fpr / (high + (1 - high) * backup)
    if gate > 1:
        return 1.0, max(0.0, (fpr - high) / (1 - high))
    return gate, backup


def prefiltered(keys: np.ndarray, others: np.ndarray, fpr: float, model_bits: float = 0.0, depth: int = 1) -> LearnedPlan:
    """A gate, then one threshold with a backup filter: the best of all bin edges."""
    n, best = keys.sum(), None
    for i in range(1, len(keys)):
        high, low = others[i:].sum() / max(others.sum(), 1), keys[:i].sum() / max(n, 1)
        gate, backup = prefilter_rates(high, low, fpr)
        bits = ideal_bits(n, gate) + (ideal_bits(n * low, backup) if low > 0 else 0.0)
        if best is None or bits < best.filter_bits - 1e-9:
            best = LearnedPlan("prefiltered", depth, i / len(keys), {"gate": gate, "backup": backup}, bits, model_bits, gate * (high + (1 - high) * backup), gate * depth)
    return best


def partitioned(keys: np.ndarray, others: np.ndarray, fpr: float, costs: Costs, depth: int, parts: int = 8, fill: bool = True, method: str = "fast") -> Plan:
    """Score regions with a filter each after `depth` learners. keys, others: histograms [depth, bin]."""
    zero = np.zeros(depth)
    flow = make_flow(keys[:depth], others[:depth], zero, zero, int(keys[0].sum()), np.full(depth, math.inf), parts)
    if method != "fast":
        from stagefilter.plans.partition import partition_scores, region_sums

        cuts, _ = partition_scores(keys[depth - 1], others[depth - 1], parts, method, 1 / (2 * max(1, others[0].sum())))
        flow.cuts[depth - 1] = cuts
        flow.key_leaf[depth - 1] = region_sums(keys[depth - 1], cuts) / max(1, keys[0].sum())
        flow.non_leaf[depth - 1] = region_sums(others[depth - 1], cuts) / max(1, others[0].sum())
    plan = preset("partitioned", flow, costs, fpr, 1.0, depth)
    return refill(plan) if fill else plan


def budgeted(keys: np.ndarray, others: np.ndarray, costs: Costs, total_bits: float, steps: int = 40, parts: int = 8, seed: int = 3) -> tuple[Plan | None, float, int]:
    """Black-box search of the number of learners for the least rate within total_bits; a partitioned filter is built for each trial, its rate found by bisection."""
    deepest = len(keys)

    def rate(depth: int) -> tuple[float, Plan | None]:
        if costs.bits[:depth].sum() >= total_bits:
            return 1.0, None
        low, high, found = -7.0, 0.0, None
        for _ in range(22):
            mid = (low + high) / 2
            p = partitioned(keys, others, 10**mid, costs, depth, parts)
            if p.memory <= total_bits:
                high, found = mid, p
            else:
                low = mid
        return (10**high if found else 1.0), found

    sampler, known = DensitySampler([0.0], [math.log(deepest + 0.999)], seed), {}
    for _ in range(steps):
        x = sampler.ask()
        depth = min(deepest, max(1, int(math.exp(x[0]))))
        if depth not in known:
            known[depth] = rate(depth)
        sampler.tell(x, known[depth][0])
    best = min(known.values(), key=lambda v: v[0])
    return best[1], best[0], steps


def sample_size(eps: float, conf: float) -> int:
    """Rows from which a share is known to within eps with probability 1 - conf."""
    return math.ceil(math.log(2 / conf) / (2 * eps * eps))


def learner_outcomes(examples: DataFrame, ensemble: Ensemble, eps: float = 0.01, conf: float = 0.01) -> tuple[np.ndarray, np.ndarray]:
    """Scores of each learner alone on a bounded sample of keys and of calibration non-keys."""
    out = []
    for part in ("key", "calib"):
        x = matrix(smallest(examples.filter(F.col("split") == part), sample_size(eps, conf)).select("x").toArrow()["x"].combine_chunks())
        out.append(np.stack([1 / (1 + np.exp(-t.predict(x))) for t in ensemble.trees], axis=1) if len(x) else np.zeros((0, ensemble.depth)))
    return out[0], out[1]


def subset_ensemble(key_scores: np.ndarray, non_scores: np.ndarray, bits: np.ndarray, n: int, total_bits: float, delta: float = 0.1, exhaustive: bool = False) -> dict:
    """Learners as independent oracles: each accepts over a fixed threshold (the grid point of step delta with the best gain); the chosen subset accepts what any of them accepts, a backup filter holds the rest.

    Rates of a subset are products, as if oracles were independent. Returns the choice, its assumed and real rates.
    """
    grid, m = np.quantile(non_scores, np.clip(np.arange(1 - delta, 1.0001, delta / 10), 0, 1), axis=0) if len(non_scores) else np.ones((1, key_scores.shape[1])), key_scores.shape[1]
    threshold, fp, miss = np.ones(m), np.zeros(m), np.ones(m)
    for j in range(m):
        options = [((non_scores[:, j] > t).mean(), (key_scores[:, j] <= t).mean(), t) for t in np.unique(grid[:, j])]
        fp[j], miss[j], threshold[j] = min(options, key=lambda o: (o[0] + o[1], o[0]))

    def overall(chosen: tuple[int, ...]) -> float:
        left = total_bits - bits[list(chosen)].sum()
        if left < 0:
            return math.inf
        pass_, missed = 1 - np.prod(1 - fp[list(chosen)]), np.prod(miss[list(chosen)])
        backup = 2 ** (-left / (LOG2E * n * missed)) if n * missed > 0 else 0.0
        return float(pass_ + (1 - pass_) * backup)

    if exhaustive:
        best = min((c for k in range(m + 1) for c in itertools.combinations(range(m), k)), key=lambda c: (overall(c), len(c), c))
    else:
        best, value = (), overall(())
        while True:
            options = [(overall(tuple(sorted((*best, j)))), j) for j in range(m) if j not in best]
            if not options or min(options)[0] >= value - 1e-12:
                break
            value, j = min(options)
            best = tuple(sorted((*best, j)))
    chosen = list(best)
    real_pass = (non_scores[:, chosen] > threshold[chosen]).any(axis=1).mean() if chosen and len(non_scores) else 0.0
    real_miss = (key_scores[:, chosen] <= threshold[chosen]).all(axis=1).mean() if chosen else 1.0
    left = total_bits - bits[chosen].sum()
    backup = 2 ** (-left / (LOG2E * n * real_miss)) if n * real_miss > 0 else 0.0
    return {"chosen": chosen, "assumed_fpr": overall(best), "real_fpr": float(real_pass + (1 - real_pass) * backup), "model_bits": float(bits[chosen].sum()), "total_bits": float(total_bits)}


@dataclass
class ProjectionHash:
    """Hash values from projections of the features; all k cells of an element must be set."""

    k: int = 30
    sampling: int = 100
    m: int = 30_000
    seed: int = 5
    vectors: np.ndarray | None = None
    low: np.ndarray | None = None
    width: np.ndarray | None = None
    cells: np.ndarray | None = None

    def fit(self, keys: np.ndarray, others: np.ndarray) -> ProjectionHash:
        """Directions are differences of sampled keys and non-keys; of `sampling` draws the one that overlaps least is kept."""
        rng, per = np.random.default_rng(self.seed), self.m // self.k
        keys, others = np.nan_to_num(keys), np.nan_to_num(others)
        spread = np.concatenate([keys, others]).std(axis=0) + 1e-9
        self.vectors = np.empty((keys.shape[1], self.k))
        a_sample, b_sample = keys[rng.permutation(len(keys))[:200]], others[rng.permutation(len(others))[:200]]
        for j in range(self.k):
            draws = (keys[rng.integers(len(keys), size=self.sampling)] - others[rng.integers(len(others), size=self.sampling)]).T / (spread**2)[:, None]
            draws /= np.linalg.norm(draws, axis=0) + 1e-12
            a, b = a_sample @ draws, b_sample @ draws
            gap = np.abs(a.mean(axis=0) - b.mean(axis=0)) / (a.std(axis=0) + b.std(axis=0) + 1e-9)
            self.vectors[:, j] = draws[:, int(gap.argmax())]
        p = keys @ self.vectors
        self.low, self.width = p.min(axis=0), np.maximum((p.max(axis=0) - p.min(axis=0)) / per, 1e-12)
        self.cells = np.zeros((self.k, per + 1), bool)
        self.cells[np.arange(self.k)[None], self._cell(keys)] = True
        return self

    def _cell(self, x: np.ndarray) -> np.ndarray:
        at = np.floor((np.nan_to_num(x) @ self.vectors - self.low) / self.width)
        per = self.m // self.k
        return np.where((at < 0) | (at > per), per, np.clip(at, 0, per - 1)).astype(np.int64)

    def contains_x(self, x: np.ndarray, mode: str = "batch") -> np.ndarray:
        """row: one element at a time; batch: all at once. Same answers."""
        if mode == "row":
            return np.array([bool(self.cells[np.arange(self.k), self._cell(r[None])[0]].all()) for r in x], bool)
        return self.cells[np.arange(self.k)[None], self._cell(x)].all(axis=1)

    @property
    def bits(self) -> int:
        return self.m + self.vectors.size * 32


@dataclass
class HashAdaptive:
    """A Bloom filter that re-picks the hash family of some keys so that known non-keys stop colliding; picks live in a small cell table."""

    bits_per_key: float = 10.0
    families: int = 6
    seed: int = 17
    m: int = 0
    k: int = 1
    bits: np.ndarray | None = None
    table: np.ndarray | None = None
    moved: int = 0
    stats: dict = field(default_factory=dict)

    def _pos(self, h: np.ndarray, family) -> np.ndarray:
        if np.isscalar(family):
            return positions_np(h, self.seed + 100 * int(family), self.k, self.m)
        out = np.empty((len(h), self.k), np.int64)
        for f in np.unique(family):
            out[family == f] = positions_np(h[family == f], self.seed + 100 * int(f), self.k, self.m)
        return out

    def _cells(self, h: np.ndarray) -> np.ndarray:
        return positions_np(h, self.seed + 55_555, 1, len(self.table))[:, 0]

    def fit(self, keys: np.ndarray, known: np.ndarray) -> HashAdaptive:
        self.m, self.k = max(8, int(self.bits_per_key * len(keys))), max(1, round(0.693 * self.bits_per_key * 0.8))
        self.table = np.zeros(max(8, len(keys)), np.uint8)
        family = np.zeros(len(keys), np.int64)
        pos = self._pos(keys, 0)
        count = np.bincount(pos.ravel(), minlength=self.m)
        owner = np.full(self.m, -1)
        owner[pos.ravel()] = np.repeat(np.arange(len(keys)), self.k)
        cell = self._cells(keys)
        members = np.bincount(cell, minlength=len(self.table))
        for q, spots in zip(known, self._pos(known, 0), strict=True):
            if not (count[spots] > 0).all():
                continue
            for s in spots:
                i = owner[s]
                # only a key that alone sets the bit and alone has its cell can be moved
                if count[s] != 1 or i < 0 or family[i] or members[cell[i]] != 1:
                    continue
                options = [(int((count[self._pos(keys[i : i + 1], f)[0]] == 0).sum()), f) for f in range(1, self.families)]
                new, f = min(options)
                np.subtract.at(count, pos[i], 1)
                pos[i] = self._pos(keys[i : i + 1], f)[0]
                np.add.at(count, pos[i], 1)
                owner[pos[i]] = i
                family[i], self.table[cell[i]] = f, f
                self.moved += 1
                break
        self.bits = count > 0
        return self

    def contains_np(self, h: np.ndarray) -> np.ndarray:
        """Plain picks first, then the pick of the element's cell."""
        first = self.bits[self._pos(h, 0)].all(axis=1)
        pick = self.table[self._cells(h)].astype(np.int64)
        second = np.zeros(len(h), bool)
        if (pick > 0).any():
            second[pick > 0] = self.bits[self._pos(h[pick > 0], pick[pick > 0])].all(axis=1)
        return first | second

    @property
    def memory(self) -> int:
        return self.m + 3 * len(self.table)


def score_adaptive_bits(keys: np.ndarray, others: np.ndarray, fpr: float, groups: int = 4) -> float:
    """Bits of the disjoint score-adaptive filter: equal-width score groups, rates falling by a constant ratio, the best ratio of a grid."""
    n, edges = keys.sum(), np.linspace(0, len(keys), groups + 1).astype(int)
    a = np.array([keys[x:y].sum() for x, y in itertools.pairwise(edges)]) / max(n, 1)
    b = np.array([others[x:y].sum() for x, y in itertools.pairwise(edges)]) / max(others.sum(), 1)
    best = math.inf
    for ratio in np.linspace(1, 12, 45):
        shape = ratio ** np.arange(groups)
        low, high = -12.0, 0.0
        for _ in range(40):
            mid = (low + high) / 2
            if (b * np.minimum(1, 10**mid * shape)).sum() > fpr:
                high = mid
            else:
                low = mid
        best = min(best, sum(ideal_bits(n * x, min(1.0, 10**low * s)) for x, s in zip(a, shape, strict=True)))
    return best


def plain_bits(n: int, fpr: float) -> tuple[float, int]:
    return ideal_bits(n, fpr), bloom_size(n, fpr)[0]
