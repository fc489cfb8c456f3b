"""Operator 8: nearest neighbours by collision counting over single projections.

Vectors are dealt into shards of bounded size. A shard keeps one sorted array per random
projection. A query's window on a projection is centred on the query's own value; at
radius r two vectors collide on a projection if their values differ by at most width * r
("virtual rehashing": a growing radius widens the windows and nothing is hashed again).
A vector that collides on at least `threshold` projections is verified by its exact
cosine. The radius grows until the k-th best verified distance is within the radius: by
then every true neighbour was verified with the probability that the threshold was chosen
for, so recall is set by `miss` and not by the data.

Unit vectors are compared, so the largest cosine is the least distance and the radius ends
at 2, where everything has been seen. Each query is sent to each shard (a stated query set
in blocks), shards answer with their k best, and the k best of those stand.

Edge cases: vectors that are null, empty, zero or hold null or non-finite components take
no part, as query or candidate; vectors of another length are never compared; a query gets
fewer rows if there are fewer candidates; ties go to the smaller vec_id; repeated vec_ids
are candidates each, but never of a query with the same id; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class CollisionIndex:
    """projections: sorted arrays per shard; width: half width of a window at radius 1; miss: chance that a vector within the radius stays under the threshold; growth: factor between radii; shard: most vectors in a shard; least_shards: shards at any size."""

    projections: int = 96
    width: float = 1.0
    miss: float = 0.02
    growth: float = 1.2
    start: float = 0.15
    shard: int = 32_768
    least_shards: int = 12
    block: int = 64
    seed: int = 11

    @property
    def threshold(self) -> int:
        """Largest count that a vector at exactly the radius reaches with probability 1 - miss (binomial tail)."""
        p = math.erf(self.width / math.sqrt(2))
        tail, m = 0.0, self.projections
        for c in range(m + 1):
            tail += math.comb(m, c) * p**c * (1 - p) ** (m - c)
            if tail > self.miss:
                return max(1, c)
        return m


class Shard:
    """Sorted projections of some unit vectors and the search over them."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, cfg: CollisionIndex):
        self.cfg, self.ids, self.vectors = cfg, ids, vectors
        norms = np.linalg.norm(vectors, axis=1, keepdims=True)
        self.unit = vectors / norms
        # orthogonal groups of directions: closer to independent views than plain random ones
        rng, dim = np.random.default_rng(cfg.seed), vectors.shape[1]
        parts = [np.linalg.qr(rng.standard_normal((dim, dim)))[0] * math.sqrt(dim) for _ in range(-(-cfg.projections // dim))]
        self.lines = np.concatenate(parts, axis=1)[:, : cfg.projections]
        shades = (self.unit @ self.lines).T
        self.order = np.argsort(shades, axis=1, kind="stable").astype(np.int32)
        self.sorted = np.take_along_axis(shades, self.order, axis=1)
        self.norms = norms[:, 0]

    def search(self, ids: np.ndarray, queries: np.ndarray, k: int) -> Iterator[tuple[int, int, float]]:
        cfg, n = self.cfg, len(self.ids)
        unit = queries / np.linalg.norm(queries, axis=1, keepdims=True)
        shades = unit @ self.lines
        radii = [cfg.start]
        while radii[-1] * cfg.growth < 2:
            radii.append(radii[-1] * cfg.growth)
        reach = cfg.width * np.array([-r for r in radii[::-1]] + radii)
        # the ends of every window of every query of the block: one binary search a projection
        ends = np.stack([np.searchsorted(s, shades[:, j, None] + reach) for j, s in enumerate(self.sorted)], axis=1)
        for q, qid in enumerate(ids):
            counts = np.zeros(n, np.int64)
            cosines = np.full(n, -np.inf)
            open_ = self.ids != qid
            best = -np.inf
            for level in range(len(radii) + 1):
                if level == len(radii):
                    fresh = np.flatnonzero(open_)
                else:
                    low, high = ends[q, :, len(radii) - 1 - level], ends[q, :, len(radii) + level]
                    if level:
                        inner, outer = ends[q, :, len(radii) - level], ends[q, :, len(radii) + level - 1]
                        parts = [o[a:b] for o, a, b in zip(self.order, low, inner, strict=True)] + [o[a:b] for o, a, b in zip(self.order, outer, high, strict=True)]
                    else:
                        parts = [o[a:b] for o, a, b in zip(self.order, low, high, strict=True)]
                    counts += np.bincount(np.concatenate(parts), minlength=n)
                    fresh = np.flatnonzero(open_ & (counts >= cfg.threshold))
                if len(fresh):
                    open_[fresh] = False
                    cosines[fresh] = self.unit[fresh] @ unit[q]
                    seen = cosines[cosines > -np.inf]
                    if len(seen) >= k:
                        best = np.partition(seen, len(seen) - k)[len(seen) - k]
                if level < len(radii) and math.sqrt(max(0.0, 2 - 2 * best)) <= radii[level]:
                    break
            got = np.flatnonzero(cosines > -np.inf)
            if len(got) > k:  # all near ties of the k-th stay, so that the exact measure below decides
                got = got[cosines[got] >= np.partition(cosines[got], len(got) - k)[len(got) - k] - 1e-9]
            exact = (self.vectors[got] * queries[q]).sum(axis=1) / (self.norms[got] * math.sqrt((queries[q] * queries[q]).sum()))
            for i in np.lexsort((self.ids[got], -exact))[:k]:
                yield int(qid), int(self.ids[got[i]]), float(exact[i])


def _searcher(cfg: CollisionIndex, k: int):
    def matrix(column: pa.Array) -> np.ndarray:
        return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)

    def answers(shard: Shard | None, held: list[tuple[int, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        if shard is None or not held:
            return
        rows = list(shard.search(np.array([i for i, _ in held]), np.array([v for _, v in held]), k))
        if rows:
            q, v, s = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(q, pa.int64()), pa.array(v, pa.int64()), pa.array(s, pa.float64())], names=["query_id", "vec_id", "score"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by shard, a shard's vectors before its queries; only one shard is held."""
        now, ids, rows, shard, held = None, [], [], None, []
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.stack([batch.column(c).to_numpy() for c in (0, 1, 2)], axis=1)
            cuts = np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1
            for a, b in zip([0, *cuts], [*cuts, len(keys)], strict=True):
                key, part = tuple(keys[a][:2]), batch.slice(a, b - a)
                if key != now:
                    yield from answers(shard, held)
                    now, ids, rows, shard, held = key, [], [], None, []
                vec_ids, vectors = part.column(3).to_numpy(), matrix(part.column(4))
                if not keys[a][2]:
                    ids.append(vec_ids)
                    rows.append(vectors)
                    continue
                if shard is None and ids:
                    shard = Shard(np.concatenate(ids), np.concatenate(rows), cfg)
                    ids, rows = [], []
                held += zip(vec_ids, vectors, strict=True)
                if len(held) >= cfg.block:
                    yield from answers(shard, held)
                    held = []
        yield from answers(shard, held)

    return run


def usable(table: DataFrame) -> DataFrame:
    """The vectors that take part: vec_id, embedding (doubles)."""
    v = F.transform("embedding", lambda x: x.cast("double"))
    bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    ok = F.col("vec_id").isNotNull() & F.col("v").isNotNull() & (F.size("v") > 0) & ~bad & F.exists("v", lambda x: x != 0)
    return table.select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v")).filter(ok)


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 5, cfg: CollisionIndex = CollisionIndex()) -> DataFrame:
    """The k nearest vectors of each query by cosine: query_id, rank, vec_id, score."""
    data, asked = usable(vectors), usable(queries)
    shards = max(cfg.least_shards, -(-data.count() // cfg.shard))
    of = lambda c: F.pmod(F.xxhash64(F.lit(cfg.seed), c), F.lit(shards)).cast("int")
    dealt = data.select(F.size("v").alias("dim"), of(F.struct("vec_id", "v")).alias("shard"), F.lit(0).alias("asks"), "vec_id", "v")
    sent = asked.select(F.size("v").alias("dim"), F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.lit(1).alias("asks"), "vec_id", "v")
    # by range, so that two shards never meet in one task while another task has none
    rows = dealt.unionByName(sent).repartitionByRange(shards, "shard", "dim").sortWithinPartitions("dim", "shard", "asks")
    found = rows.mapInArrow(_searcher(cfg, k), "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
