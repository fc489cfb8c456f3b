"""Ordered ensembles of weak learners and the scores of their prefixes."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bits of a tree's parts: an inner node holds a feature and a threshold, a leaf a value.
INNER_BITS, LEAF_BITS = 64, 32


@dataclass
class Tree:
    """A binary tree in heap order; feat is -1 at leaves. A value above thr goes to the right; missing values go left."""

    feat: np.ndarray
    thr: np.ndarray
    value: np.ndarray

    def predict(self, x: np.ndarray) -> np.ndarray:
        at = np.zeros(len(x), np.int64)
        rows = np.arange(len(x))
        while True:
            f = self.feat[at]
            inner = f >= 0
            if not inner.any():
                return self.value[at]
            right = x[rows, np.maximum(f, 0)] > self.thr[at]
            at = np.where(inner, 2 * at + 1 + right, at)

    @property
    def bits(self) -> int:
        inner = int((self.feat >= 0).sum())
        return inner * INNER_BITS + (inner + 1) * LEAF_BITS


@dataclass
class Ensemble:
    trees: list[Tree]
    base: float = 0.0
    features: list[str] = field(default_factory=list)
    link: str = "logistic"  # or "mean": scores are running means of the trees' values; "share": of the sum of all

    @property
    def depth(self) -> int:
        return len(self.trees)

    @property
    def width(self) -> int:
        """Values of a row that the trees look at."""
        return 1 + max((int(t.feat.max(initial=-1)) for t in self.trees), default=-1)

    def bits(self) -> np.ndarray:
        return np.array([t.bits for t in self.trees], float)

    def margin_to_score(self, margin: np.ndarray, d: int) -> np.ndarray:
        """Score in [0, 1] of the prefix 1..d from the sum of its values."""
        if self.link == "logistic":
            return 1 / (1 + np.exp(-np.clip(margin, -60, 60)))
        if self.link == "mean":
            return np.clip(margin / d, 0, 1)
        return np.clip(margin / max(1e-12, sum(float(t.value.max()) for t in self.trees)), 0, 1)

    def prefixes(self, x: np.ndarray) -> np.ndarray:
        """Scores after 1 .. depth learners, one row per element."""
        margin = np.full(len(x), self.base)
        out = np.empty((len(x), self.depth), np.float64)
        for d, t in enumerate(self.trees):
            margin = margin + t.predict(x)
            out[:, d] = self.margin_to_score(margin, d + 1)
        return out

    def head(self, depth: int) -> Ensemble:
        return Ensemble(self.trees[:depth], self.base, self.features, self.link)


def matrix(column: pa.Array, width: int = 0) -> np.ndarray:
    """Rows of an array column; a null row is all missing values. width: least number of values in a row."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros((0, max(1, width)))
    known = ~column.is_null().to_numpy(zero_copy_only=False)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    rows = flat.reshape(int(known.sum()), -1) if known.any() else np.zeros((0, width))
    if known.all() and rows.shape[1] >= width:
        return rows
    out = np.full((len(column), max(1, width, rows.shape[1])), np.nan)
    out[known, : rows.shape[1]] = rows
    return out


def identities(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of a batch, 0 for nulls, and which are known. Never by way of floats: those lose the low bits of 60-bit hashes."""
    return pc.fill_null(column, 0).to_numpy(), column.is_valid().to_numpy(zero_copy_only=False)


def score_prefixes(df: DataFrame, ensemble: Ensemble, keep: tuple[str, ...] = ("eid", "h", "is_key", "split")) -> DataFrame:
    """keep columns and s, the array of prefix scores. One Arrow pass, no shuffle."""
    held = df.sparkSession.sparkContext.broadcast(ensemble)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = held.value.prefixes(matrix(b.column("x"), held.value.width))
            offsets = pa.array(np.arange(0, s.size + 1, max(1, s.shape[1]))[: len(s) + 1].astype(np.int32))
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in keep], pa.ListArray.from_arrays(offsets, pa.array(s.ravel()))], names=[*keep, "s"])

    rows = df.select(*keep, "x")
    types = ", ".join(f"{c} {rows.schema[c].dataType.simpleString()}" for c in keep)
    return rows.mapInArrow(run, f"{types}, s array<double>")


@dataclass(frozen=True)
class TableScorer:
    """Fixed integer stumps over native columns: (condition in SQL, weight). Score d is the share of the total weight met by the first d."""

    stumps: tuple[tuple[str, int], ...]

    @property
    def total(self) -> int:
        return sum(w for _, w in self.stumps)

    def prefix_columns(self) -> list[Column]:
        out, running = [], F.lit(0)
        for cond, w in self.stumps:
            running = running + F.when(F.expr(cond), w).otherwise(0)
            out.append(running / F.lit(self.total))
        return out

    def scores(self) -> Column:
        return F.array(*self.prefix_columns())

    def sql(self) -> list[str]:
        """The same prefix scores as SQL expressions."""
        terms = [f"(CASE WHEN {c} THEN {w} ELSE 0 END)" for c, w in self.stumps]
        return [f"(({' + '.join(terms[: d + 1])}) / {self.total}.0)" for d in range(len(terms))]


def from_library_trees(model, features: list[str], link: str = "logistic") -> Ensemble:
    """Trees of the library's boosted or random-forest classifier in their order, as one of our ensembles.

    Boosted trees predict margins with weights; forest trees give class-1 shares, averaged.
    """
    trees, weights = model.trees, list(model.treeWeights)
    boosted = "GBT" in type(model).__name__
    out = []
    for tree, w in zip(trees, weights, strict=True):
        root = tree._call_java("rootNode")

        def depth_of(node) -> int:
            return 0 if node.getClass().getSimpleName() == "LeafNode" else 1 + max(depth_of(node.leftChild()), depth_of(node.rightChild()))

        n = 2 ** (depth_of(root) + 1) - 1
        t = Tree(np.full(n, -1), np.zeros(n), np.zeros(n))

        def fill(node, i: int, t=t, w=w) -> None:
            if node.getClass().getSimpleName() == "LeafNode":
                if boosted:
                    t.value[i] = 2 * w * node.prediction()
                else:
                    stats = list(node.impurityStats().stats())
                    t.value[i] = stats[1] / max(1e-12, sum(stats))
                return
            t.feat[i], t.thr[i] = node.split().featureIndex(), node.split().threshold()
            fill(node.leftChild(), 2 * i + 1)
            fill(node.rightChild(), 2 * i + 2)

        fill(root, 0)
        out.append(t)
    return Ensemble(out, 0.0, features, "logistic" if boosted else "mean")
