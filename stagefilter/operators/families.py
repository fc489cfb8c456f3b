"""Other families of weak learners for the same filter: stumps boosted in DataFrame functions, and small modules fitted to residuals."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stagefilter.functions.hashing import smallest
from stagefilter.operators.scoring import INNER_BITS, Ensemble, Tree, matrix

# --- stumps -----------------------------------------------------------------------------


def bin_column(x: Column, edges: list[float]) -> Column:
    """Bin of a value: how many edges lie below it. Missing values are in bin 0."""
    return F.coalesce(F.size(F.filter(F.array(*[F.lit(float(e)) for e in edges]), lambda e: e < x)) if edges else F.lit(0), F.lit(0))


def best_stump(rows: DataFrame, reg: float = 1.0) -> DataFrame:
    """One row: feature, bin (higher bins go right), gain, lo, hi (Newton steps of the sides). rows: y, margin, b (bins by feature).

    Gradients are summed per feature and bin, map-side first; everything after runs on that small table.
    """
    p = 1 / (1 + F.exp(-F.col("margin")))
    cells = rows.select((p - F.col("y")).alias("g"), F.greatest(p * (1 - p), F.lit(1e-12)).alias("h"), F.posexplode("b").alias("feature", "bin"))
    cells = cells.groupBy("feature", "bin").agg(F.sum("g").alias("g"), F.sum("h").alias("h"))
    to_here, all_ = Window.partitionBy("feature").orderBy("bin"), Window.partitionBy("feature")
    sums = cells.select("feature", "bin", *[F.sum(c).over(w).alias(f"{c}{n}") for c in "gh" for n, w in (("l", to_here), ("t", all_))])
    score = lambda g, h: g * g / (h + reg)
    gr, hr = F.col("gt") - F.col("gl"), F.col("ht") - F.col("hl")
    gain = score(F.col("gl"), F.col("hl")) + score(gr, hr) - score(F.col("gt"), F.col("ht"))
    found = sums.filter((F.col("hl") > 1e-9) & (hr > 1e-9)).select("feature", "bin", gain.alias("gain"), (-F.col("gl") / (F.col("hl") + reg)).alias("lo"), (-gr / (hr + reg)).alias("hi"))
    return found.orderBy(F.desc("gain"), "feature", "bin").limit(1)


def boost_stumps(rows: DataFrame, edges: list[list[float]], rounds: int = 20, eta: float = 0.3, reg: float = 1.0) -> Ensemble:
    """Stumps boosted over a whole table, each round one small aggregation and one row for the driver. rows: is_key, x."""
    share = rows.agg(F.avg(F.col("is_key").cast("double"))).first()[0]
    share = min(max(0.5 if share is None else share, 1e-6), 1 - 1e-6)
    base = float(np.log(share / (1 - share)))
    binned = rows.select(F.col("is_key").cast("double").alias("y"), F.array(*[bin_column(F.get("x", F.lit(j)), e) for j, e in enumerate(edges)]).alias("b")).persist()
    margin, trees = F.lit(base), []
    for _ in range(rounds):
        s = best_stump(binned.withColumn("margin", margin), reg).first()
        if s is None or s.gain <= 1e-9:
            break
        margin = margin + F.when(F.get("b", F.lit(s.feature)) > s.bin, eta * s.hi).otherwise(eta * s.lo)
        trees.append(Tree(np.array([s.feature, -1, -1]), np.array([edges[s.feature][s.bin], 0.0, 0.0]), np.array([0.0, eta * s.lo, eta * s.hi])))
    binned.unpersist()
    return Ensemble(trees, base)


# --- modules fitted to residuals --------------------------------------------------------


@dataclass
class Module:
    """A linear map, or one hidden layer, of scaled features; missing values count as the mean. Stands where a tree does."""

    mean: np.ndarray
    scale: np.ndarray
    hidden: np.ndarray | None
    out: np.ndarray

    def layer(self, x: np.ndarray) -> np.ndarray:
        z = np.nan_to_num((x[:, : len(self.mean)] - self.mean) / self.scale)
        z = np.clip(np.column_stack([z, np.ones(len(z))]), -8, 8)
        return z if self.hidden is None else np.column_stack([np.tanh(z @ self.hidden), np.ones(len(z))])

    def predict(self, x: np.ndarray) -> np.ndarray:
        return self.layer(x) @ self.out

    @property
    def feat(self) -> np.ndarray:
        return np.arange(len(self.mean))

    @property
    def value(self) -> np.ndarray:
        return np.abs(self.out).sum(keepdims=True)

    @property
    def bits(self) -> int:
        return 32 * (self.out.size + (self.hidden.size if self.hidden is not None else 0) + self.mean.size) + INNER_BITS


def grow_modules(x: np.ndarray, y: np.ndarray, rounds: int = 20, units: int = 0, eta: float = 0.5, reg: float = 1.0, seed: int = 1) -> Ensemble:
    """Each module is the ridge solution of the Newton step on the residuals of those before. units: size of the hidden layer, 0 for linear modules, which see a random half of the features."""
    rng = np.random.default_rng(seed)
    mean = np.nan_to_num(np.nanmean(x, axis=0)) if len(x) else np.zeros(x.shape[1])
    scale = np.nan_to_num(np.nanstd(x, axis=0), nan=1.0) + 1e-9 if len(x) else np.ones(x.shape[1])
    share = min(max(float(y.mean()) if len(y) else 0.5, 1e-6), 1 - 1e-6)
    base = float(np.log(share / (1 - share)))
    margin, out = np.full(len(x), base), []
    for _ in range(rounds):
        wide = len(mean) + 1
        if units:
            m = Module(mean, scale, rng.normal(0, 1.5 / np.sqrt(wide), (wide, units)), np.zeros(units + 1))
            seen = np.ones(units + 1, bool)
        else:
            m = Module(mean, scale, None, np.zeros(wide))
            seen = np.r_[rng.random(wide - 1) < 0.5, True]
        a = m.layer(x)[:, seen]
        p = 1 / (1 + np.exp(-np.clip(margin, -60, 60)))
        h = np.maximum(p * (1 - p), 1e-6)
        m.out[seen] = eta * np.linalg.solve(a.T @ (a * h[:, None]) + reg * np.eye(a.shape[1]), a.T @ (y - p))
        margin += m.predict(x)
        out.append(m)
    return Ensemble(out, base)


def train_modules(examples: DataFrame, rounds: int = 20, units: int = 0, sample: int = 60_000, seed: int = 1) -> Ensemble:
    """Modules fitted on at most `sample` rows of the splits key and train, those of the smallest hash."""
    rows = smallest(examples.filter(F.col("split").isin("key", "train")).select("h", "x", "is_key"), sample).toArrow()
    return grow_modules(matrix(rows["x"]), rows["is_key"].to_numpy().astype(float), rounds, units, seed=seed)


# --- projections at any size ------------------------------------------------------------


def projection_cells(rows: DataFrame, values: Column, vectors: list[list[int]]) -> DataFrame:
    """rows with one row per vector: k and dot, the projection of the whole-number values on it."""
    dots = F.array(*[sum((F.get(values, F.lit(j)) * w for j, w in enumerate(v)), F.lit(0)).cast("long") for v in vectors])
    return rows.select("*", F.posexplode(dots).alias("k", "dot"))


def projection_filter(keys: DataFrame, values: Column, vectors: list[list[int]], per: int) -> tuple[DataFrame, DataFrame]:
    """(bounds by k, set cells (k, cell)): the projection hash as two tables; only one row per vector is broadcast."""
    dots = projection_cells(keys, values, vectors)
    bounds = dots.groupBy("k").agg(F.min("dot").alias("low"), F.greatest(F.lit(1).cast("long"), F.ceil((F.max("dot") - F.min("dot") + 1) / per)).alias("width"))
    cells = dots.select("k", "dot").join(F.broadcast(bounds), "k").select("k", F.floor((F.col("dot") - F.col("low")) / F.col("width")).alias("cell")).distinct()
    return bounds, cells


def projection_probe(rows: DataFrame, by: str, values: Column, vectors: list[list[int]], bounds: DataFrame, cells: DataFrame) -> DataFrame:
    """(by, found): whether all cells of an element are set."""
    at = projection_cells(rows.select(by, values.alias("_v")), F.col("_v"), vectors).join(F.broadcast(bounds), "k")
    at = at.select(by, "k", F.floor((F.col("dot") - F.col("low")) / F.col("width")).alias("cell"))
    met = at.join(cells.withColumn("hit", F.lit(True)), ["k", "cell"], "left")
    return met.groupBy(by).agg(F.bool_and(F.coalesce("hit", F.lit(False))).alias("found"))
