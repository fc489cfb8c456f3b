"""Cutting a score histogram into regions so that the Kullback-Leibler divergence of keys from non-keys is largest."""

from __future__ import annotations

import itertools

import numpy as np


def _gain_table(keys: np.ndarray, others: np.ndarray, floor: float) -> np.ndarray:
    """gain[i, j]: contribution of a region of bins i .. j-1."""
    p, r = np.concatenate([[0.0], np.cumsum(keys)]), np.concatenate([[0.0], np.cumsum(others)])
    a = p[None, :] - p[:, None]
    b = np.maximum(r[None, :] - r[:, None], floor)
    with np.errstate(divide="ignore", invalid="ignore"):
        g = np.where(a > 1e-15, a * np.log2(np.maximum(a, 1e-300) / b), 0.0)
    return np.where(np.triu(np.ones_like(g, bool), 1), g, -np.inf)


def _tables(gain: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """best[k, j]: best value of bins 0 .. j-1 in k regions, and the last region's start."""
    n = gain.shape[0]
    best, start = np.full((parts + 1, n), -np.inf), np.zeros((parts + 1, n), int)
    best[0, 0] = 0
    for k in range(1, parts + 1):
        value = best[k - 1][:, None] + gain
        start[k], best[k] = value.argmax(axis=0), value.max(axis=0)
    return best, start


def _walk(start: np.ndarray, parts: int, end: int) -> list[int]:
    cuts = []
    for k in range(parts, 0, -1):
        end = int(start[k, end])
        cuts.append(end)
    return cuts[::-1][1:]


def partition_scores(keys, others, parts: int, method: str = "fast", floor: float = 1e-9) -> tuple[list[int], float]:
    """Inner cuts (bin numbers) and the divergence in bits of the best split into at most `parts` regions.

    fast: one table for all ends. classic: the last region's start is tried one by one, each
    with a table of its own (same result). brute: all cuts.
    """
    keys, others = np.asarray(keys, float), np.asarray(others, float)
    keys, others = keys / max(keys.sum(), 1e-300), others / max(others.sum(), 1e-300)
    n, parts = len(keys), min(parts, len(keys))
    gain = _gain_table(keys, others, floor)
    if method == "brute":
        best = max(
            ((sum(gain[a, b] for a, b in itertools.pairwise((0, *c, n))), c) for k in range(parts) for c in itertools.combinations(range(1, n), k)),
            key=lambda x: (round(x[0], 12), -len(x[1])),
        )
        return list(best[1]), float(best[0])
    if method == "classic":
        top, cuts = gain[0, n], []
        for last in range(1, n):
            best, start = _tables(gain[: last + 1, : last + 1], parts - 1)
            for k in range(1, parts):
                if best[k, last] + gain[last, n] > top + 1e-12:
                    top, cuts = best[k, last] + gain[last, n], [*_walk(start, k, last), last]
        return cuts, float(top)
    best, start = _tables(gain, parts)
    k = int(np.argmax(np.round(best[1:, n], 12))) + 1
    return _walk(start, k, n), float(best[k, n])


def region_sums(hist: np.ndarray, cuts: list[int]) -> np.ndarray:
    c = np.concatenate([[0], np.cumsum(hist)])
    edges = np.array([0, *cuts, len(hist)])
    return c[edges[1:]] - c[edges[:-1]]
