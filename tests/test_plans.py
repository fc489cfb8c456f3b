import itertools
import math

import numpy as np
import pytest

from stagefilter.functions.sizing import backup_fpr, bloom_fpr, bloom_size, ideal_bits
from stagefilter.operators.baselines import prefilter_rates, sample_size, score_adaptive_bits, single_threshold, subset_ensemble
from stagefilter.plans.config_dp import configure, configure_bruteforce, evaluate, preset, refill
from stagefilter.plans.partition import partition_scores
from stagefilter.plans.thresholds import DensitySampler, knots_to_alphas, thetas_from_sketch
from stagefilter.queries.method import random_flow, toy


def test_sizes():
    assert ideal_bits(1000, 0.01) == pytest.approx(9585.058, abs=1e-3)
    assert ideal_bits(1000, 0.001) == pytest.approx(14377.588, abs=1e-3)
    assert ideal_bits(60000, 0.001) == pytest.approx(862655.254, abs=1e-3)
    for n, f in itertools.product((10, 1000, 10**6), (0.5, 0.1, 0.01, 1e-6)):
        m, k = bloom_size(n, f)
        assert bloom_fpr(n, m, k) <= f * 1.001
    assert backup_fpr(0, 0.5, 0.01) == 0 and backup_fpr(0.5, 0, 0.01) == 1 and backup_fpr(0.9, 0.001, 0.01) == 1


@pytest.mark.parametrize(
    ("lam", "depth", "objective", "memory", "reject"),
    [(1.0, 2, 0.879238, 8427.545, 0.475), (0.9, 1, 0.829904, 8572.275, 0.25), (0.5, 0, 0.5, 9585.058, 0), (0.0, 0, 0, 9585.058, 0)],
)
def test_toy(lam, depth, objective, memory, reject):
    f, c = toy()
    p = configure(f, c, 0.01, lam, 3)
    assert (p.depth, round(p.objective, 6), round(p.memory, 3)) == (depth, objective, memory) and p.reject == pytest.approx(reject)
    assert p.expected_fpr == pytest.approx(0.01)


def test_search_equals_enumeration_and_is_bounded():
    rng = np.random.default_rng(0)
    for t in range(40):
        f, c = random_flow(rng, 1 + t % 4, 3)
        lam, count = (0.0, 0.5, 0.9, 1.0)[t % 4], {}
        p, q = configure(f, c, 0.02, lam, 4, counter=count), configure_bruteforce(f, c, 0.02, lam, 4)
        assert p.objective == pytest.approx(q.objective, abs=1e-9)
        assert count["choices"] <= f.depth * 16
        assert p.expected_fpr <= 0.02 + 1e-12
        assert configure(f, c, 0.02, lam, 6).objective <= p.objective + 1e-12


def test_gates_do_not_change_memory_unless_clipped():
    f, c = toy()
    values = {round(evaluate(f, c, 1e-9, 1, [i, j]).memory, 6) for i in range(3) for j in range(3)}
    assert len(values) == 1


def test_refill_uses_the_whole_rate():
    rng = np.random.default_rng(4)
    for _ in range(20):
        f, c = random_flow(rng, 3, 4)
        p = configure(f, c, 0.2, 1.0, 4, plain=False)
        r = refill(p)
        assert r.memory <= p.memory + 1e-9 and r.expected_fpr <= 0.2 + 1e-9 and r.expected_fpr >= p.expected_fpr - 1e-12


def test_presets():
    f, c = toy()
    assert preset("plain", f, c, 0.01).depth == 0
    assert all(g == 0 for g in preset("no_gates", f, c, 0.01).gates)
    assert preset("no_exits", f, c, 0.01).depth == 1


def test_partition_methods_agree():
    rng = np.random.default_rng(2)
    for _ in range(15):
        a, b = rng.integers(0, 40, 9), rng.integers(0, 40, 9)
        values = [partition_scores(a + (a.sum() == 0), b + (b.sum() == 0), 3, m)[1] for m in ("fast", "classic", "brute")]
        assert max(values) - min(values) < 1e-9


def test_prefilter_rates_golden_number():
    gate, backup = prefilter_rates(0.1, 0.4, 0.01)
    assert (round(gate, 7), round(backup, 7)) == (0.06, 0.0740741)
    bits = ideal_bits(1000, gate) + ideal_bits(400, backup)
    assert bits == pytest.approx(8022.609, abs=1e-3)
    for g in np.linspace(0.02, 1, 60):
        b = (0.01 / g - 0.1) / 0.9
        if 0 < b <= 1:
            assert ideal_bits(1000, g) + ideal_bits(400, b) >= bits - 1e-6


def test_baseline_plans():
    keys, others = np.array([5, 5, 10, 80.0]), np.array([90, 8, 2, 0.0])
    p = single_threshold(keys, others, 0.01)
    assert p.expected_fpr == pytest.approx(0.01)
    assert sample_size(0.01, 0.01) == 26492
    rng = np.random.default_rng(1)
    ks, ns = rng.uniform(0.3, 1, (500, 5)), rng.uniform(0, 0.7, (500, 5))
    greedy, best = (subset_ensemble(ks, ns, np.full(5, 50.0), 1000, 6000, exhaustive=x) for x in (False, True))
    assert best["assumed_fpr"] <= greedy["assumed_fpr"] + 1e-12
    assert score_adaptive_bits(keys, others, 0.01) > 0


def test_sampler_and_sketch():
    s = DensitySampler([-1, -1], [1, 1], seed=1)
    x, v = s.minimise(lambda p: float(((p - 0.3) ** 2).sum()), 80)
    assert v < 0.05 and ((x >= -1) & (x <= 1)).all()
    assert knots_to_alphas(np.array([-1.0, -3.0]), 3) == pytest.approx([0.1, 0.01, 0.001])
    t = thetas_from_sketch(np.sort(np.arange(100.0)[:, None] @ np.ones((1, 2)), axis=0), np.array([0.1, 0.5]))
    assert list(t) == [90.0, 50.0]
    assert math.isfinite(t[0])
