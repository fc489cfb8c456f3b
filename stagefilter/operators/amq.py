"""Other membership filters that can stand in for the Bloom filter: counting, cuckoo and quotient. All answer contains_np and never miss a key."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagefilter.functions.hashing import block_np, positions, positions_np
from stagefilter.functions.sizing import bloom_size


class CountingBloom:
    """Counters in place of bits, so that keys can be deleted."""

    def __init__(self, n: int, fpr: float, seed: int = 0):
        self.m, self.k = bloom_size(n, fpr)
        self.seed, self.fpr, self.n = seed, fpr, 0
        self.counts = np.zeros(self.m, np.int32)

    def insert(self, h: np.ndarray, by: int = 1) -> None:
        p = positions_np(np.asarray(h, np.int64), self.seed, self.k, self.m)
        np.add.at(self.counts, p.ravel(), by)
        self.n += by * len(p)

    def delete(self, h: np.ndarray) -> None:
        """Only for keys that are in (proven by the exact table)."""
        self.insert(h, -1)

    def contains_np(self, h: np.ndarray) -> np.ndarray:
        return (self.counts[positions_np(np.asarray(h, np.int64), self.seed, self.k, self.m)] > 0).all(axis=1)

    @staticmethod
    def table(changes: DataFrame, seed: int, k: int, m: int) -> DataFrame:
        """(p, count) of inserts and deletes, columns h and sign, at any scale."""
        rows = changes.select("sign", F.explode(positions(F.col("h"), seed, k, m)).alias("p"))
        return rows.groupBy("p").agg(F.sum("sign").alias("count")).filter("count > 0")


class CuckooFilter:
    """Fingerprints in buckets of four with two possible buckets each."""

    SLOTS = 4

    def __init__(self, n: int, fpr: float, seed: int = 0):
        self.bits = max(4, int(np.ceil(np.log2(2 * self.SLOTS / fpr))))
        self.buckets = 1 << max(1, int(np.ceil(np.log2(max(1, n) / self.SLOTS / 0.9))))
        self.seed, self.fpr, self.n = seed, fpr, 0
        self.table = np.zeros((self.buckets, self.SLOTS), np.int64)
        self.rest: list[tuple[int, int]] = []  # what found no room

    @property
    def m(self) -> int:
        return self.buckets * self.SLOTS * self.bits

    def _places(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        h = np.asarray(h, np.int64)
        print_ = positions_np(h, self.seed + 7919, 1, (1 << self.bits) - 1)[:, 0] + 1
        a = block_np(h, self.seed, self.buckets)
        return print_, a, a ^ (block_np(print_, self.seed + 1, self.buckets))

    def _other(self, at: int, print_: int) -> int:
        return int(at ^ block_np(np.array([print_], np.int64), self.seed + 1, self.buckets)[0])

    def insert(self, h: np.ndarray) -> None:
        rng = np.random.default_rng(self.seed)
        for f, a, b in zip(*self._places(h), strict=True):
            self.n += 1
            at = a
            for i in (a, b):
                if (free := np.flatnonzero(self.table[i] == 0)).size:
                    self.table[i, free[0]] = f
                    break
            else:
                for _ in range(500):
                    slot = rng.integers(self.SLOTS)
                    f, self.table[at, slot] = self.table[at, slot], f
                    at = self._other(int(at), int(f))
                    if (free := np.flatnonzero(self.table[at] == 0)).size:
                        self.table[at, free[0]] = f
                        break
                else:
                    self.rest.append((int(f), int(at)))

    def contains_np(self, h: np.ndarray) -> np.ndarray:
        f, a, b = self._places(h)
        out = (self.table[a] == f[:, None]).any(axis=1) | (self.table[b] == f[:, None]).any(axis=1)
        for g, at in self.rest:
            out |= (f == g) & ((a == at) | (b == at))
        return out

    def delete(self, h: np.ndarray) -> None:
        for f, a, b in zip(*self._places(h), strict=True):
            for i in (a, b):
                if (held := np.flatnonzero(self.table[i] == f)).size:
                    self.table[i, held[0]] = 0
                    self.n -= 1
                    break
            else:
                self.rest = [x for x in self.rest if x[0] != f or x[1] not in (a, b)]


class QuotientFilter:
    """Sorted remainders by quotient, kept as one sorted array: the compact form for build once, probe often."""

    def __init__(self, n: int, fpr: float, seed: int = 0):
        self.remainder = max(1, int(np.ceil(np.log2(1 / fpr))))
        self.quotients = 1 << max(1, int(np.ceil(np.log2(max(1, n) / 0.75))))
        self.seed, self.fpr = seed, fpr
        self.codes = np.zeros(0, np.int64)

    @property
    def m(self) -> int:
        return self.quotients * (self.remainder + 3)

    @property
    def n(self) -> int:
        return len(self.codes)

    def _codes(self, h: np.ndarray) -> np.ndarray:
        h = np.asarray(h, np.int64)
        return block_np(h, self.seed, self.quotients) * (1 << self.remainder) + positions_np(h, self.seed + 104729, 1, 1 << self.remainder)[:, 0]

    def insert(self, h: np.ndarray) -> None:
        self.codes = np.sort(np.concatenate([self.codes, self._codes(h)]))

    def delete(self, h: np.ndarray) -> None:
        codes, drop = list(self.codes), self._codes(h)
        at = np.searchsorted(self.codes, drop)
        for i in sorted({int(i) for i, c in zip(at, drop, strict=True) if i < len(codes) and codes[i] == c}, reverse=True):
            codes.pop(i)
        self.codes = np.array(codes, np.int64)

    def contains_np(self, h: np.ndarray) -> np.ndarray:
        c = self._codes(h)
        at = np.searchsorted(self.codes, c)
        return (at < len(self.codes)) & (self.codes[np.minimum(at, max(0, len(self.codes) - 1))] == c) if len(self.codes) else np.zeros(len(c), bool)


KINDS = {"counting": CountingBloom, "cuckoo": CuckooFilter, "quotient": QuotientFilter}


def build_sharded(keys: DataFrame, kind: str, fpr: float, shards: int, seed: int = 0) -> DataFrame:
    """(shard, n, bits, filter): one filter per hash shard, each built in a task of its own."""
    import pickle

    import pandas as pd

    made = KINDS[kind]

    def build(rows: pd.DataFrame) -> pd.DataFrame:
        f = made(len(rows), fpr, seed)
        f.insert(rows.h.to_numpy(np.int64))
        return pd.DataFrame({"shard": [int(rows.shard.iloc[0])], "n": [len(rows)], "bits": [int(f.m)], "filter": [pickle.dumps(f)]})

    dealt = keys.select("h", F.pmod(F.xxhash64("h"), F.lit(shards)).cast("int").alias("shard"))
    return dealt.groupBy("shard").applyInPandas(build, "shard int, n long, bits long, filter binary")


def probe_sharded(queries: DataFrame, table: DataFrame, shards: int) -> DataFrame:
    """(h, found): queries meet their shard's filter."""
    import pickle

    import pandas as pd

    def probe(rows: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        found = pickle.loads(held["filter"].iloc[0]).contains_np(rows.h.to_numpy(np.int64)) if len(held) else np.zeros(len(rows), bool)
        return pd.DataFrame({"h": rows.h, "found": found})

    dealt = queries.select("h", F.pmod(F.xxhash64("h"), F.lit(shards)).cast("int").alias("shard"))
    return dealt.groupBy("shard").cogroup(table.select("shard", "filter").groupBy("shard")).applyInPandas(probe, "h long, found boolean")
