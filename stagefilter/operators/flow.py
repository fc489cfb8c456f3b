"""How keys and non-keys travel through the scorers, gates left out; measured for all threshold vectors in one scan."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stagefilter.operators.scoring import matrix
from stagefilter.plans.config_dp import Flow, make_flow

ALPHAS = (0.1, 0.01, 0.001, 0.0001, 0.0)


def bin_of(s: np.ndarray, bins: int) -> np.ndarray:
    return np.clip((np.nan_to_num(s, nan=0.0) * bins).astype(np.int64), 0, bins - 1)


#: Bits of a score that one pass of the exact quantiles settles, from the highest on.
DIGITS = (12, 13, 13, 13, 13)


def _ordered(s: np.ndarray) -> np.ndarray:
    """Scores as unsigned integers of the same order; both zeros are one value, missing values stand last."""
    at = (np.ascontiguousarray(s, np.float64) + 0.0).view(np.int64)
    return np.where(at < 0, ~at, at ^ np.int64(-(2**63))).view(np.uint64)


def _value(at: int) -> float:
    return float(np.array([at ^ (1 << 63) if at >> 63 else at ^ (2**64 - 1)], np.uint64).view(np.float64)[0])


def _digit_counts(rows: DataFrame, begun: list[np.ndarray], shift: int, bits: int) -> dict[tuple[int, int], np.ndarray]:
    """By depth and digits so far (`begun`, by depth): how many scores go on with each value of the next `bits` bits, which stand `shift` bits above the lowest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[int, int], np.ndarray] = {}
        for b in batches:
            at = _ordered(matrix(b.column(0))) >> np.uint64(shift) if b.num_rows else np.zeros((0, 0), np.uint64)
            for d in range(at.shape[1]):
                digit, above = (at[:, d] & np.uint64(2**bits - 1)).astype(np.int64), at[:, d] >> np.uint64(bits)
                for p in begun[d] if begun else np.zeros(1, np.uint64):
                    part = np.bincount(digit[above == p], minlength=2**bits)
                    k = (d, int(p))
                    total[k] = total[k] + part if k in total else part
        for (d, p), n in total.items():
            i = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(i), d, np.int32)), pa.array(np.full(len(i), p, np.int64)), pa.array(i.astype(np.int32)), pa.array(n[i])], names=["d", "p", "i", "n"])

    t = rows.mapInArrow(run, "d int, p long, i int, n long").groupBy("d", "p", "i").agg(F.sum("n").alias("n")).toArrow()
    d, p, i, n = (t[c].to_numpy() for c in ("d", "p", "i", "n"))
    out: dict[tuple[int, int], np.ndarray] = {}
    for k in sorted(set(zip(d.tolist(), p.tolist(), strict=True))):
        out[k] = np.zeros(2**bits, np.int64)
    for d_, p_, i_, n_ in zip(d.tolist(), p.tolist(), i.tolist(), n.tolist(), strict=True):
        out[d_, p_][i_] = n_
    return out


def exact_quantiles(rows: DataFrame, shares: list[float]) -> np.ndarray:
    """[depth, share] quantiles of the arrays in column s, interpolated between neighbours as by `percentile`.

    `percentile` holds every distinct value of every depth in one buffer. Here each pass counts one
    more digit of the values whose ranks are asked for, so tasks and driver hold no more than
    depths * ranks * 2**13 counts, whatever the rows.
    """
    rows = rows.select("s")
    counts = _digit_counts(rows, [], 64 - DIGITS[0], DIGITS[0])
    depth = 1 + max((d for d, _ in counts), default=-1)
    if not depth:
        return np.zeros((0, len(shares)))
    n = int(counts[0, 0].sum())
    places = [q * (n - 1) for q in shares]
    ranks = sorted({r for x in places for r in (math.floor(x), math.ceil(x))})
    found, left = {(d, r): 0 for d in range(depth) for r in ranks}, {(d, r): r for d in range(depth) for r in ranks}
    shift = 64
    for bits in DIGITS:
        shift -= bits
        if shift < 64 - DIGITS[0]:
            counts = _digit_counts(rows, [np.unique(np.array([found[d, r] for r in ranks], np.uint64)) for d in range(depth)], shift, bits)
        upto = {k: np.cumsum(v) for k, v in counts.items()}
        for d, r in found:
            c = upto[d, found[d, r]]
            i = int(np.searchsorted(c, left[d, r], side="right"))
            left[d, r] -= int(c[i - 1]) if i else 0
            found[d, r] = found[d, r] << bits | i
    out = np.zeros((depth, len(shares)))
    for d in range(depth):
        for j, x in enumerate(places):
            low, high = _value(found[d, math.floor(x)]), _value(found[d, math.ceil(x)])
            out[d, j] = low if low == high or math.isnan(low) else (math.ceil(x) - x) * low + (x - math.floor(x)) * high
    return out


def quantile_thetas(scored: DataFrame, alphas=ALPHAS, never: bool = True, exact: bool = True) -> list[np.ndarray]:
    """Distinct threshold vectors: per depth the value that a share alpha of calibration non-keys reaches; alpha 0 is the maximum.

    The share is taken from above, so that no more than alpha reach it unless values tie. `never` adds the vector that lets nothing exit.
    """
    calib = scored.filter("split = 'calib' and s is not null")
    if exact:
        cells = exact_quantiles(calib, [1 - a if a > 0 else 1.0 for a in alphas])
    else:
        found = calib.select(F.posexplode("s").alias("d", "s")).groupBy("d").agg(*[(F.max("s") if a <= 0 else F.percentile_approx("s", F.lit(1 - a))).alias(f"a{i}") for i, a in enumerate(alphas)]).orderBy("d").collect()
        cells = np.array([[r[f"a{i}"] for i in range(len(alphas))] for r in found], float)
    out: list[np.ndarray] = []
    for theta in cells.T if len(cells) else ():
        if not any(np.array_equal(theta, t) for t in out):
            out.append(theta)
    if never and len(cells):
        out.append(np.full(len(cells), math.inf))
    return out


def measure_flow(scored: DataFrame, thetas: list[np.ndarray], bins: int = 100) -> DataFrame:
    """(theta_id, depth, cls, bin, cnt): what reaches each depth by score bin, and with bin -1 what exits there. Splits key and calib count."""
    held = np.array(thetas)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            if not b.num_rows:
                continue
            s, cls = matrix(b.column(1)), np.asarray(b.column(0).to_numpy(zero_copy_only=False)).astype(int)
            n, depth = s.shape
            if total is None:
                total = np.zeros((len(held), depth, 2, bins + 1), np.int64)
            at = bin_of(s, bins)
            for t, theta in enumerate(held):
                out = s[:, : depth - 1] >= theta[None, : depth - 1]
                left = np.where(out.any(axis=1), out.argmax(axis=1), depth - 1) if depth > 1 else np.zeros(n, int)
                for d in range(depth):
                    here = left >= d
                    total[t, d, :, :bins] += np.bincount(cls[here] * bins + at[here, d], minlength=2 * bins).reshape(2, bins)
                    if d < depth - 1:
                        gone = left == d
                        total[t, d, :, bins] += np.bincount(cls[gone], minlength=2)
        if total is not None:
            t, d, c, i = np.nonzero(total)
            i2 = np.where(i == bins, -1, i)
            yield pa.RecordBatch.from_arrays([pa.array(v.astype(np.int32)) for v in (t, d + 1, c, i2)] + [pa.array(total[t, d, c, i])], names=["theta_id", "depth", "cls", "bin", "cnt"])

    rows = scored.filter("split in ('key', 'calib')").select("is_key", "s").mapInArrow(run, "theta_id int, depth int, cls int, bin int, cnt long")
    return rows.groupBy("theta_id", "depth", "cls", "bin").agg(F.sum("cnt").alias("cnt"))


def flow_cube(scored: DataFrame, thetas: list[np.ndarray], bins: int = 100) -> np.ndarray:
    """[threshold vector, depth, class, bin], the last bin what exits; the collected counts are at most thetas * depths * 2 * (bins + 1)."""
    cube = np.zeros((len(thetas), len(thetas[0]), 2, bins + 1))
    for r in measure_flow(scored, thetas, bins).collect():
        cube[r.theta_id, r.depth - 1, r.cls, r.bin] = r.cnt  # bin -1 is the last cell
    return cube


def flows_of(cube: np.ndarray, thetas: list[np.ndarray], parts: int = 8, smooth: float = 0.0) -> list[Flow]:
    bins = cube.shape[3] - 1
    n = int(cube[0, 0, 1, :bins].sum())
    return [make_flow(c[:, 1, :bins], c[:, 0, :bins], c[:, 1, bins], c[:, 0, bins], n, t, parts, smooth) for c, t in zip(cube, thetas, strict=True)]


def flows(scored: DataFrame, thetas: list[np.ndarray], parts: int = 8, bins: int = 100, smooth: float = 0.0) -> list[Flow]:
    """The flow of each threshold vector."""
    return flows_of(flow_cube(scored, thetas, bins), thetas, parts, smooth)


def exit_depth(s: Column, thetas) -> Column:
    """First depth (from 1) whose score reaches its threshold, else the last, as a column over an array column of scores."""
    depth = len(thetas)
    out = F.lit(depth)
    for d in range(depth - 1, 0, -1):
        out = F.when(F.get(s, F.lit(d - 1)) >= F.lit(float(thetas[d - 1])), d).otherwise(out)
    return out
