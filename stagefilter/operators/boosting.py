"""Second-order boosted trees over quantile bins, on all rows of the splits `key` and `train`.

The learner only asks for histograms of gradients. `LocalData` answers from arrays on the
driver, `SparkData` for tables of more rows than that, from blocks of rows that stay on the
executors' disks: one job a level, whose result is one histogram. Gradients are rounded to
2**-24, so that their sums are exact in any order and trees don't depend on how rows are dealt.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from operator import add
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagefilter.operators.scoring import Ensemble, Tree, matrix

#: Bytes of blocks that one task reads in a pass, about.
TASK_BYTES = 64 << 20


@dataclass(frozen=True)
class Boosting:
    """rounds and depth of the trees, step eta, ridge reg, bins per feature; sample: most rows that are trained on the driver, more are where they lie."""

    rounds: int = 100
    depth: int = 4
    eta: float = 0.3
    reg: float = 1.0
    bins: int = 64
    sample: int = 60_000


def bin_edges(x: np.ndarray, bins: int) -> list[np.ndarray]:
    return [np.unique(np.quantile(c[np.isfinite(c)], np.linspace(0, 1, bins + 1)[1:-1])) if np.isfinite(c).any() else np.zeros(0) for c in x.T]


def to_bins(x: np.ndarray, edges: list[np.ndarray]) -> np.ndarray:
    """Bin numbers; a bin holds values above the edge before it, missing values are in bin 0."""
    out = np.empty(x.shape, np.uint8)
    for j, e in enumerate(edges):
        c = np.where(np.isnan(x[:, j]), -np.inf, x[:, j])
        out[:, j] = np.searchsorted(e, c, side="left")
    return out


def slopes(margin: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gradients and curvatures of the logistic loss, as whole multiples of 2**-24."""
    p = 1 / (1 + np.exp(-margin))
    return np.rint((p - y) * 2**24) / 2**24, np.maximum(np.rint(p * (1 - p) * 2**24), 1) / 2**24


def node_histograms(b: np.ndarray, node: np.ndarray, g: np.ndarray, h: np.ndarray, nodes: int, bins: int) -> np.ndarray:
    """[2, node, feature, bin] sums of gradients and curvatures of the bins b [feature, row]; node -1 takes no part."""
    ok = np.flatnonzero(node >= 0)
    whole = len(ok) == len(node)
    first, g, h = (v if whole else v[ok] for v in (node * bins, g, h))
    out = np.zeros((2, nodes, len(b), bins))
    for j, c in enumerate(b):
        at = first + (c if whole else c[ok])
        out[0, :, j] = np.bincount(at, g, nodes * bins).reshape(nodes, bins)
        out[1, :, j] = np.bincount(at, h, nodes * bins).reshape(nodes, bins)
    return out


def places(tree: Tree, b: np.ndarray) -> np.ndarray:
    """Place in heap order of the leaf of each row. Nodes are gone through, not rows: comparing bytes of a whole column is far cheaper than a look-up a row."""
    kind = np.uint8 if len(tree.feat) < 256 else np.int64
    at = np.zeros(b.shape[1], kind)
    for k in np.flatnonzero(tree.feat >= 0):
        right = b[tree.feat[k]] > kind(tree.thr[k])
        at += (at == k) * (right + kind(k + 1))
    return at


class LocalData:
    def __init__(self, x: np.ndarray, y: np.ndarray, cfg: Boosting):
        self.edges = bin_edges(x, cfg.bins)
        self.b, self.y, self.cfg = np.ascontiguousarray(to_bins(x, self.edges).T), y.astype(float), cfg
        self.margin = np.zeros(len(y))

    def class_share(self) -> float:
        return float(self.y.mean()) if len(self.y) else 0.5

    def start(self, base: float) -> None:
        self.margin[:] = base

    def histograms(self, tree: Tree, level: int) -> np.ndarray:
        low = 2**level - 1
        at = places(tree, self.b).astype(np.int64) - low
        return node_histograms(self.b, np.where(at >= 0, at, -1), *slopes(self.margin, self.y), 2**level, self.cfg.bins)

    def add(self, tree: Tree) -> None:
        self.margin += tree.value[places(tree, self.b)]

    def close(self) -> None:
        pass


class SparkData:
    """All rows (x, is_key) of a table as blocks of 8-bit bins [feature, row], labels and margins.

    Blocks are kept on the executors' disks by Spark, not in memory, and are made again from the
    table where an executor is lost. A pass adds the trees grown since the blocks were made; they
    are made anew every `fold` trees, so the work of a pass does not grow with the rounds, and the
    older ones go. Of two nodes under a split only the lighter one is counted, the other is what
    is left of the node above. Bins are cut at quantiles of all rows, to a two-thousandth of them.
    """

    def __init__(self, df: DataFrame, cfg: Boosting, n: int | None = None, fold: int = 8):
        self.cfg, self.trees, self.base, self.fold = cfg, [], 0.0, fold
        rows = df.select("x", F.col("is_key").cast("double").alias("y"))
        n, width = df.count() if n is None else n, df.agg(F.max(F.size("x"))).first()[0]
        probs = [float(q) for q in np.linspace(0, 1, cfg.bins + 1)[1:-1]]
        value = [F.get("x", F.lit(j)).cast("double") for j in range(width)]
        finite = [F.when(~F.isnan(v) & (F.abs(v) < float("inf")), v) for v in value]
        found = df.agg(*[F.percentile_approx(v, probs, 2000).alias(f"c{j}") for j, v in enumerate(finite)]).first()
        self.edges = edges = [np.unique(np.array(c if c is not None else [], float)) for c in found]

        def binned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    b = to_bins(matrix(batch.column(0), width), edges)
                    yield pa.RecordBatch.from_arrays([pa.array([b.T.tobytes()], pa.binary()), pa.array([batch.column(1).to_numpy().astype(np.uint8).tobytes()], pa.binary())], names=["b", "y"])

        def block(r) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            y = np.frombuffer(bytes(r.y), np.uint8)
            return np.frombuffer(bytes(r.b), np.uint8).reshape(width, len(y)), y, np.zeros(len(y))

        blocks = rows.mapInArrow(binned, "b binary, y binary").rdd
        tasks = max(blocks.context.defaultParallelism, math.ceil(n * (width + 9) / TASK_BYTES))
        self.blocks, self.older = blocks.coalesce(tasks).map(block).persist(StorageLevel.DISK_ONLY), None

    def class_share(self) -> float:
        keys, n = self.blocks.map(lambda r: (int(r[1].sum()), len(r[1]))).fold((0, 0), lambda a, b: (a[0] + b[0], a[1] + b[1]))
        return keys / n if n else 0.5

    def start(self, base: float) -> None:
        self.base = base

    def histograms(self, tree: Tree, level: int) -> np.ndarray:
        trees, base, width, bins = list(self.trees), self.base, len(self.edges), self.cfg.bins
        low, ask = 2**level - 1, np.zeros(1, np.int64)
        if level:
            feat, thr = tree.feat[low // 2 : low], tree.thr[low // 2 : low]
            split = np.flatnonzero(feat >= 0)
            weight = self.above[1, split, feat[split]]
            left = (weight * (np.arange(bins) <= thr[split][:, None])).sum(axis=1)
            ask = 2 * split + (left > weight.sum(axis=1) - left)
        slot = np.full(len(tree.feat), -1)
        slot[low + ask] = np.arange(len(ask))

        def run(blocks: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[tuple[int, np.ndarray]]:
            total = np.zeros((2, int(slot.max()) + 1, width, bins))
            for b, y, margin in blocks:
                margin = base + margin
                for t in trees:
                    margin += t.value[places(t, b)]
                total += node_histograms(b, slot[places(tree, b)], *slopes(margin, y), total.shape[1], bins)
            for k in range(total.shape[1]):
                yield k, total[:, k]

        # one task adds the tasks' histograms up, several where those are many or wide
        adders = min(len(ask), 1 + self.blocks.getNumPartitions() * len(ask) * width * bins * 16 // TASK_BYTES)
        found = dict(self.blocks.mapPartitions(run).reduceByKey(add, adders).collect())
        if self.older is not None:
            self.older, _ = None, self.older.unpersist()
        out = np.zeros((2, 2**level, width, bins))
        for k, node in enumerate(ask):
            out[:, node] = found.get(k, 0)
            if level:
                out[:, node ^ 1] = self.above[:, node // 2] - out[:, node]
        self.above = out
        return out

    def add(self, tree: Tree) -> None:
        self.trees.append(tree)
        if len(self.trees) < self.fold:
            return
        trees = list(self.trees)

        def grown(r: tuple[np.ndarray, np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            b, y, margin = r
            return b, y, sum((t.value[places(t, b)] for t in trees), margin)

        self.older, self.blocks, self.trees = self.blocks, self.blocks.map(grown).persist(StorageLevel.DISK_ONLY), []

    def close(self) -> None:
        for blocks in (self.blocks, self.older):
            if blocks is not None:
                blocks.unpersist()


def best_splits(hist: np.ndarray, reg: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per node feature, bin (rows with a higher bin go right) and gain of the best split."""
    left = hist.cumsum(axis=3)
    total = left[:, :, :1, -1:]
    right = total - left
    score = lambda s: s[0] ** 2 / (s[1] + reg)
    gain = score(left) + score(right) - score(total)
    gain[(left[1] <= 1e-9) | (right[1] <= 1e-9)] = -np.inf
    flat = gain.reshape(gain.shape[0], -1)
    at = flat.argmax(axis=1)
    return at // hist.shape[3], at % hist.shape[3], flat[np.arange(len(at)), at]


def boost(data: LocalData | SparkData, cfg: Boosting, features: list[str] | None = None) -> Ensemble:
    share = min(max(data.class_share(), 1e-6), 1 - 1e-6)
    base = float(np.log(share / (1 - share)))
    data.start(base)
    leaf = lambda sums: -cfg.eta * sums[0] / (sums[1] + cfg.reg)
    out = []
    for _ in range(cfg.rounds):
        n = 2 ** (cfg.depth + 1) - 1
        by_bin = Tree(np.full(n, -1), np.zeros(n), np.zeros(n))
        for level in range(max(1, cfg.depth)):
            low = 2**level - 1
            if level and (by_bin.feat[low // 2 : low] < 0).all():
                break
            hist = data.histograms(by_bin, level)
            sums = hist[:, :, 0].sum(axis=2)
            if not level:
                by_bin.value[0] = leaf(sums)[0]
            if not cfg.depth:
                break
            feat, at, gain = best_splits(hist, cfg.reg)
            ok = gain > 1e-9
            by_bin.feat[low : 2 * low + 1] = np.where(ok, feat, -1)
            by_bin.thr[low : 2 * low + 1] = at
            # what goes left and right of a split is known from its histogram
            left = (hist[:, np.arange(len(feat)), feat] * (np.arange(cfg.bins) <= at[:, None])).sum(axis=2)
            by_bin.value[2 * low + 1 : 4 * low + 3] = leaf(np.stack([left * ok, (sums - left) * ok], axis=2).reshape(2, -1))
        data.add(by_bin)
        thr = np.array([data.edges[f][min(int(b), len(data.edges[f]) - 1)] if f >= 0 else 0.0 for f, b in zip(by_bin.feat, by_bin.thr, strict=True)])
        out.append(Tree(by_bin.feat, thr, by_bin.value))
    return Ensemble(out, base, features or [])


def train(df: DataFrame, cfg: Boosting = Boosting(), distributed: bool = False) -> Ensemble:
    """On all keyed rows of the splits `key` and `train`: on the driver if they are no more than cfg.sample, else, or if so asked, where they lie."""
    rows = df.filter(F.col("split").isin("key", "train")).select("x", "is_key")
    n = rows.count()
    if n and (distributed or n > cfg.sample):
        data = SparkData(rows, cfg, n)
    else:
        part = rows.toArrow()
        x = matrix(part["x"]) if part.num_rows else np.zeros((0, 1))
        data = LocalData(x, part["is_key"].to_numpy().astype(float), cfg)
    try:
        return boost(data, cfg)
    finally:
        data.close()
