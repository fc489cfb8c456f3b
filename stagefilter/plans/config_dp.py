"""Choosing depth and filter rates of a staged filter.

State: depth and the exponent e of the product 2^-e of the gate rates above. At a state a
gate exponent is chosen and then either the chain ends there (score regions with a backup
filter each) or goes on (one exit with a backup filter, then the next state). Given the
product, backup rates follow from the flow shares alone, so the state is sufficient.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass, field

import numpy as np

from stagefilter.functions.sizing import LOG2E, backup_fpr, ideal_bits
from stagefilter.plans.partition import partition_scores, region_sums


@dataclass
class Flow:
    """Shares of keys and non-keys, gates left out. reach, leave: by depth; leaf: by depth the shares of each region. cuts: region borders in bins."""

    n_keys: int
    key_reach: np.ndarray
    non_reach: np.ndarray
    key_leave: np.ndarray
    non_leave: np.ndarray
    key_leaf: list[np.ndarray]
    non_leaf: list[np.ndarray]
    cuts: list[list[int]]
    theta: np.ndarray
    bins: int = 100

    @property
    def depth(self) -> int:
        return len(self.key_reach)


@dataclass
class Costs:
    """Bits and time of each learner, and what the plain filter takes."""

    bits: np.ndarray
    time: np.ndarray
    plain_bits: float
    plain_time: float = 1.0


@dataclass
class Plan:
    depth: int
    gates: list[int]
    exit_fpr: list[float]
    leaf_fpr: list[float]
    fpr: float
    lam: float
    objective: float
    memory: float
    reject: float
    expected_fpr: float
    flow: Flow | None = field(default=None, repr=False)

    def rows(self) -> list[tuple]:
        """(depth, role, region, fpr, key share, lo, hi) of every filter."""
        if not self.depth:
            return [(0, "plain", 0, self.fpr, 1.0, None, None)]
        f, out = self.flow, []
        for d in range(self.depth):
            out.append((d + 1, "gate", 0, 2.0 ** -self.gates[d], float(f.key_reach[d]), None, None))
            if d + 1 < self.depth:
                out.append((d + 1, "exit", 0, self.exit_fpr[d], float(f.key_leave[d]), float(f.theta[d]), None))
        edges = [0, *f.cuts[self.depth - 1], f.bins]
        for k, x in enumerate(self.leaf_fpr):
            out.append((self.depth, "leaf", k, x, float(f.key_leaf[self.depth - 1][k]), edges[k] / f.bins, edges[k + 1] / f.bins))
        return out


def make_flow(key_hist, non_hist, key_leave, non_leave, n_keys, theta, parts=8, smooth=0.0, floor=None) -> Flow:
    """From counts: hist[d, bin] of what reaches depth d, leave[d] of what exits there. smooth is added to non-key bins."""
    key_hist, non_hist = np.asarray(key_hist, float), np.asarray(non_hist, float) + smooth
    nk, nn = max(key_hist[0].sum(), 1), max(non_hist[0].sum(), 1)
    cuts = [partition_scores(a, b, parts, floor=floor or 1 / (2 * nn))[0] for a, b in zip(key_hist, non_hist, strict=True)]
    return Flow(
        n_keys, key_hist.sum(axis=1) / nk, non_hist.sum(axis=1) / nn, np.asarray(key_leave) / nk, np.asarray(non_leave) / nn,
        [region_sums(h, c) / nk for h, c in zip(key_hist, cuts, strict=True)], [region_sums(h, c) / nn for h, c in zip(non_hist, cuts, strict=True)],
        cuts, np.asarray(theta, float), key_hist.shape[1],
    )


def _bits(f: Flow, keys: float, fpr: float) -> float:
    return ideal_bits(f.n_keys * keys, fpr) if keys > 0 else 0.0


def leaf_bits(f: Flow, d: int, product: float, fpr: float) -> float:
    return sum(_bits(f, a, backup_fpr(a, b * product, fpr)) for a, b in zip(f.key_leaf[d], f.non_leaf[d], strict=True))


def evaluate(f: Flow, c: Costs, fpr: float, lam: float, gates: list[int]) -> Plan:
    """The plan with these gate exponents (its depth is their number), fully costed."""
    if not gates:
        return Plan(0, [], [], [], fpr, lam, lam, c.plain_bits, 0.0, fpr, f)
    product, memory, reject, expected, exits = 1.0, 0.0, 0.0, 0.0, []
    for d, j in enumerate(gates):
        product *= 2.0**-j
        memory += c.bits[d] + LOG2E * f.n_keys * f.key_reach[d] * j
        reject += c.time[d] * f.non_reach[d] * product
        if d + 1 < len(gates):
            x = backup_fpr(f.key_leave[d], f.non_leave[d] * product, fpr)
            exits.append(x)
            memory += _bits(f, f.key_leave[d], x)
            expected += f.non_leave[d] * product * x
    last = len(gates) - 1
    leaves = [backup_fpr(a, b * product, fpr) for a, b in zip(f.key_leaf[last], f.non_leaf[last], strict=True)]
    memory += leaf_bits(f, last, product, fpr)
    expected += sum(b * product * x for b, x in zip(f.non_leaf[last], leaves, strict=True))
    objective = lam * memory / c.plain_bits + (1 - lam) * reject / c.plain_time
    return Plan(len(gates), list(gates), exits, leaves, fpr, lam, objective, memory, reject, expected, f)


def configure(f: Flow, c: Costs, fpr: float, lam: float, grid: int = 20, gates: bool = True, exits: bool = True, depth: int | None = None, plain: bool = True, cached: bool = True, counter: dict | None = None) -> Plan:
    """The best plan. gates, exits, depth and plain switch parts off, which gives the special cases.

    Ties (the gates are neutral for memory until a backup rate is clipped) go to the shorter
    reject time, then the smaller memory, then fewer learners, then smaller exponents.
    """
    deepest = depth or f.depth
    count = counter if counter is not None else {}
    count["states"] = count["leaves"] = count["choices"] = 0
    memo: dict[tuple[int, int], float] = {}

    def leaves(d: int, e: int) -> float:
        if not cached or (d, e) not in memo:
            count["leaves"] += 1
            memo[d, e] = leaf_bits(f, d, 2.0**-e, fpr)
        return memo[d, e]

    exponents = range(grid) if gates else range(1)
    # value: objective, reject, memory, learners, gate exponents below
    below: dict[int, tuple] = {}
    for d in range(deepest - 1, -1, -1):
        here: dict[int, tuple] = {}
        for i in exponents:
            count["states"] += 1
            options = []
            for j in range(len(exponents) - i):
                count["choices"] += 1
                e = i + j
                memory, reject = c.bits[d] + LOG2E * f.n_keys * f.key_reach[d] * j, c.time[d] * f.non_reach[d] * 2.0**-e
                if depth is None or d + 1 == depth:
                    m = memory + leaves(d, e)
                    options.append((m, reject, 1, (j,)))
                if d + 1 < deepest and (exits or f.key_leave[d] == f.non_leave[d] == 0):
                    x = backup_fpr(f.key_leave[d], f.non_leave[d] * 2.0**-e, fpr)
                    _, r2, m2, n2, js = below[e]
                    options.append((memory + _bits(f, f.key_leave[d], x) + m2, reject + r2, 1 + n2, (j, *js)))
            scored = [(lam * m / c.plain_bits + (1 - lam) * r / c.plain_time, r, m, n, js) for m, r, n, js in options]
            if scored:
                least = min(s[0] for s in scored)
                here[i] = min((s for s in scored if s[0] <= least + 1e-12 * max(1.0, abs(least))), key=lambda s: s[1:])
        below = here
    best = evaluate(f, c, fpr, lam, list(below[0][4]))
    if plain and lam <= best.objective + 1e-12:
        return evaluate(f, c, fpr, lam, [])
    return best


def configure_bruteforce(f: Flow, c: Costs, fpr: float, lam: float, grid: int, plain: bool = True) -> Plan:
    """Every depth and tuple of gate exponents whose product stays on the grid."""
    plans = [evaluate(f, c, fpr, lam, list(g)) for d in range(1, f.depth + 1) for g in itertools.product(range(grid), repeat=d) if sum(g) < grid]
    if plain:
        plans.append(evaluate(f, c, fpr, lam, []))
    return min(plans, key=lambda p: (round(p.objective, 11), p.reject, p.memory, p.depth, p.gates))


def refill(plan: Plan) -> Plan:
    """Rates of unclipped backup filters scaled by one factor until the expected rate is the target; memory falls."""
    if not plan.depth:
        return plan
    f, product, filters = plan.flow, 1.0, []
    for d in range(plan.depth):
        product *= 2.0 ** -plan.gates[d]
        if d + 1 < plan.depth:
            filters.append([f.key_leave[d], f.non_leave[d] * product, plan.exit_fpr[d]])
    filters += [[a, b * product, x] for a, b, x in zip(f.key_leaf[plan.depth - 1], f.non_leaf[plan.depth - 1], plan.leaf_fpr, strict=True)]
    while True:
        fixed = sum(b for a, b, x in filters if x >= 1)
        free = [x for x in filters if x[2] < 1 and x[0] > 0 and x[1] > 0]
        used = sum(b * x for _, b, x in free)
        if not free or used <= 0 or plan.fpr - fixed <= used * (1 + 1e-12):
            break
        factor = (plan.fpr - fixed) / used
        for x in free:
            x[2] = min(1.0, x[2] * factor)
    exits = [x[2] for x in filters[: plan.depth - 1]]
    leaves = [x[2] for x in filters[plan.depth - 1 :]]
    saved = sum(_bits(f, a, old) - _bits(f, a, new) for (a, _, new), old in zip(filters, [*plan.exit_fpr, *plan.leaf_fpr], strict=True))
    expected = sum(b * x for _, b, x in filters)
    return Plan(plan.depth, plan.gates, exits, leaves, plan.fpr, plan.lam, plan.objective, plan.memory - saved, plan.reject, expected, f)


def preset(name: str, f: Flow, c: Costs, fpr: float, lam: float = 1.0, depth: int | None = None, grid: int = 20) -> Plan:
    """The classical structures as restrictions of the same search."""
    if name == "plain":
        return evaluate(f, c, fpr, lam, [])
    if name == "partitioned":
        return configure(f, c, fpr, lam, 1, gates=False, depth=depth or f.depth, plain=False)
    if name == "no_gates":
        return configure(f, c, fpr, lam, grid, gates=False, plain=False)
    if name == "no_exits":
        return configure(f, c, fpr, lam, grid, exits=False, plain=False)
    raise ValueError(name)
