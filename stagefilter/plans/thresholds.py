"""Refining thresholds by sequential sampling: good past trials against the rest, by kernel densities."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


class DensitySampler:
    """Minimises a function of a box. Each step draws proposals near the better quarter of past trials and takes the one that is likeliest there and unlikeliest among the rest."""

    def __init__(self, low, high, seed: int = 7, proposals: int = 24, good: float = 0.25):
        self.low, self.high = np.asarray(low, float), np.asarray(high, float)
        self.rng, self.proposals, self.good = np.random.default_rng(seed), proposals, good
        self.points: list[np.ndarray] = []
        self.values: list[float] = []

    def tell(self, point, value: float) -> None:
        self.points.append(np.asarray(point, float))
        self.values.append(float(value))

    def _density(self, x: np.ndarray, centres: np.ndarray) -> np.ndarray:
        width = (self.high - self.low) / max(2.0, len(centres) ** 0.5)
        z = (x[:, None] - centres[None]) / width
        return np.log(np.exp(-0.5 * (z * z).sum(axis=2)).sum(axis=1) + 1e-300) - np.log(len(centres))

    def ask(self) -> np.ndarray:
        if len(self.points) < 4:
            return self.rng.uniform(self.low, self.high)
        order = np.argsort(self.values, kind="stable")
        n = max(2, int(np.ceil(self.good * len(order))))
        p = np.array(self.points)
        best, rest = p[order[:n]], p[order[n:]] if len(order) > n else p
        width = (self.high - self.low) / max(2.0, n**0.5)
        x = np.clip(best[self.rng.integers(n, size=self.proposals)] + self.rng.standard_normal((self.proposals, len(self.low))) * width, self.low, self.high)
        return x[np.argmax(self._density(x, best) - self._density(x, rest))]

    def minimise(self, f: Callable[[np.ndarray], float], steps: int) -> tuple[np.ndarray, float]:
        for _ in range(steps):
            x = self.ask()
            self.tell(x, f(x))
        i = int(np.argmin(self.values))
        return self.points[i], self.values[i]


def knots_to_alphas(knots: np.ndarray, depth: int) -> np.ndarray:
    """log10 shares at a few depths, interpolated to all."""
    return 10.0 ** np.interp(np.linspace(0, 1, max(depth, 1)), np.linspace(0, 1, len(knots)), knots)


def thetas_from_sketch(sorted_scores: np.ndarray, alphas: np.ndarray) -> np.ndarray:
    """Per depth the value that a share alpha of the (sorted ascending, column per depth) non-key scores reaches."""
    n = len(sorted_scores)
    at = np.clip(np.ceil((1 - alphas) * (n - 1)).astype(int), 0, n - 1)
    return sorted_scores[at, np.arange(sorted_scores.shape[1])]
