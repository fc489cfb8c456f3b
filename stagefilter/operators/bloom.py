"""Bloom filters in three forms: held by the driver and broadcast, sharded into a table of blocks, and as rows of positions."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stagefilter.functions.hashing import BLOCK_BITS, block_of, positions, positions_np
from stagefilter.functions.sizing import MOST_BROADCAST, bloom_size

#: The uneven load of blocks raises the rate by up to this factor at the rates in use; sharded filters are sized for it.
BLOCK_LOAD = 1.03


@dataclass
class BloomFilter:
    """m bits (little end first in each byte), k hash functions, the seed of its hash family, n keys in it."""

    m: int
    k: int
    seed: int
    bits: np.ndarray
    fpr: float
    n: int = 0

    @classmethod
    def empty(cls, n: int, fpr: float, seed: int = 0) -> BloomFilter:
        m, k = bloom_size(n, fpr)
        return cls(m, k, seed, np.zeros(-(-m // 8), np.uint8), fpr, 0)

    @classmethod
    def build(cls, keys: DataFrame, col: str = "h", fpr: float = 0.01, seed: int = 0, n: int | None = None) -> BloomFilter:
        """Of the hashes in col. Positions are set in the JVM, one bitmap per 32768 of them; only bitmaps reach the driver."""
        n = keys.count() if n is None else n
        out = cls.empty(n, fpr, seed)
        if out.m // 8 > MOST_BROADCAST:
            raise ValueError(f"{out.m // 8} bytes are over the broadcast limit; use ShardedBloom")
        out.n = n
        for r in bitmaps(keys.select(F.explode(positions(F.col(col), seed, out.k, out.m)).alias("p"))).toLocalIterator():
            part = np.frombuffer(bytes(r.bits), np.uint8)
            a = r.block * BLOCK_BITS // 8
            out.bits[a : a + len(part)] |= part[: len(out.bits) - a]
        return out

    def insert(self, h: np.ndarray) -> None:
        p = positions_np(np.asarray(h, np.int64), self.seed, self.k, self.m).ravel()
        np.bitwise_or.at(self.bits, p >> 3, (1 << (p & 7)).astype(np.uint8))
        self.n += len(h)

    def contains_np(self, h: np.ndarray) -> np.ndarray:
        if not len(h):
            return np.zeros(0, bool)
        p = positions_np(np.asarray(h, np.int64), self.seed, self.k, self.m)
        return ((self.bits[p >> 3] >> (p & 7).astype(np.uint8)) & 1).all(axis=1)

    def contains(self, h: Column) -> Column:
        """Whether the hash may be in the filter, by an Arrow function over the broadcast bits; a null hash is not."""
        from pyspark.sql import SparkSession

        held = SparkSession.active().sparkContext.broadcast(self)

        @F.pandas_udf("boolean")
        def probe(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for s in batches:
                ok = s.notna().to_numpy()
                out = np.zeros(len(s), bool)
                out[ok] = held.value.contains_np(s[ok].to_numpy(np.int64))
                yield pd.Series(out)

        return probe(h)

    def merge(self, other: BloomFilter) -> BloomFilter:
        if (self.m, self.k, self.seed) != (other.m, other.k, other.seed):
            raise ValueError("only filters of one shape and seed can be united")
        return BloomFilter(self.m, self.k, self.seed, self.bits | other.bits, self.fpr, self.n + other.n)

    @property
    def ones(self) -> int:
        return int(np.unpackbits(self.bits).sum())

    def estimated_fpr(self) -> float:
        return (self.ones / self.m) ** self.k


def bitmaps(points: DataFrame, *by: str) -> DataFrame:
    """(by.., block, bits) of positions in column p."""
    rows = points.select(*by, F.expr(f"p div {BLOCK_BITS}").alias("block"), (F.col("p") % BLOCK_BITS).alias("at"))
    return rows.groupBy(*by, "block").agg(F.bitmap_construct_agg("at").alias("bits"))


class AcceptAll:
    """Rate 1: no bits."""

    fpr, m, k, n, seed = 1.0, 0, 0, 0, 0

    def contains_np(self, h: np.ndarray) -> np.ndarray:
        return np.ones(len(h), bool)

    def insert(self, h: np.ndarray) -> None: ...


class RejectAll(AcceptAll):
    """A filter that no key reaches. A key inserted later turns it into a small real filter."""

    fpr = 0.0

    def contains_np(self, h: np.ndarray) -> np.ndarray:
        return np.zeros(len(h), bool)


def bit_is_set(bits: Column, at: Column) -> Column:
    byte = F.conv(F.hex(F.substring(bits, (at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    return F.call_function("shiftright", byte, (at % 8).cast("int")).bitwiseAND(1) == 1


@dataclass
class ShardedBloom:
    """A table (filter_id, block, bits) in which an element's positions all lie in one block. Build and probe shuffle by block; nothing is collected."""

    bits: DataFrame
    blocks: int
    k: int
    seed: int

    @classmethod
    def build(cls, keys: DataFrame, col: str = "h", fpr: float = 0.01, seed: int = 0, n: int | None = None) -> ShardedBloom:
        n = keys.count() if n is None else n
        m, k = bloom_size(n, fpr / BLOCK_LOAD)
        blocks = max(1, -(-m // BLOCK_BITS))
        h = F.col(col)
        points = keys.select(block_of(h, seed, blocks).alias("block"), F.explode(positions(h, seed, k, BLOCK_BITS)).alias("at"))
        return cls(points.groupBy("block").agg(F.bitmap_construct_agg("at").alias("bits")), blocks, k, seed)

    def probe(self, queries: DataFrame, col: str = "h") -> DataFrame:
        """queries with column found."""
        h = F.col(col)
        asked = queries.withColumn("_block", block_of(h, self.seed, self.blocks))
        joined = asked.join(self.bits.select(F.col("block").alias("_b"), F.col("bits").alias("_bits")), F.col("_block") == F.col("_b"), "left")
        hit = F.forall(positions(h, self.seed, self.k, BLOCK_BITS), lambda p: bit_is_set(F.col("_bits"), p))
        return joined.withColumn("found", F.coalesce(hit, F.lit(False))).drop("_block", "_b", "_bits")


def position_rows(keys: DataFrame, col: str, seed: int, k: int, m: int) -> DataFrame:
    """The filter as a table of its set positions."""
    return keys.select(F.explode(positions(F.col(col), seed, k, m)).alias("p")).distinct()


def probe_rows(queries: DataFrame, filter_rows: DataFrame, col: str, seed: int, k: int, m: int) -> DataFrame:
    """The queries all of whose distinct positions are set."""
    asked = queries.select("*", F.explode(F.array_distinct(positions(F.col(col), seed, k, m))).alias("p"))
    hits = asked.join(filter_rows, "p", "left_semi").groupBy(*queries.columns).count()
    want = F.size(F.array_distinct(positions(F.col(col), seed, k, m)))
    return hits.filter(F.col("count") == want).select(*queries.columns)
