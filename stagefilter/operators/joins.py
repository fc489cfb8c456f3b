"""Joins behind a membership filter, and joins that locate a region or a filter version."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stagefilter.functions.hashing import element_hash
from stagefilter.operators.bloom import BloomFilter, ShardedBloom
from stagefilter.functions.sizing import bloom_size

#: Keys up to this many bits are broadcast; more go through the sharded form.
BROADCAST_BITS = 8 * (64 << 20)


def prefilter(fact: DataFrame, keys: DataFrame, fact_key: str, key: str, fpr: float = 0.01) -> DataFrame:
    """The rows of fact whose key may be among keys: all that are, and a share fpr of the others. The filter's size decides its form."""
    hashed = keys.select(element_hash(F.col(key)).alias("h")).distinct()
    n = hashed.count()
    if bloom_size(n, fpr)[0] <= BROADCAST_BITS:
        return fact.filter(BloomFilter.build(hashed, "h", fpr, n=n).contains(element_hash(F.col(fact_key))))
    probed = ShardedBloom.build(hashed, "h", fpr, n=n).probe(fact.withColumn("_h", element_hash(F.col(fact_key))), "_h")
    return probed.filter("found").drop("_h", "found")


def prefilter_join(fact: DataFrame, keys: DataFrame, fact_key: str, key: str, how: str = "left_semi", fpr: float = 0.01) -> DataFrame:
    """An exact join whose probe side is thinned before it is shuffled. Semi and inner joins only drop rows that can't match; an anti join keeps what the filter rejects and checks the rest."""
    if how == "left_anti":
        near = prefilter(fact, keys, fact_key, key, fpr)
        matched = near.join(keys.select(F.col(key).alias("_k")).distinct(), F.col(fact_key) == F.col("_k"), "left_semi").select(F.col(fact_key).alias("_m")).distinct()
        return fact.join(matched, F.col(fact_key) == F.col("_m"), "left_anti")
    return prefilter(fact, keys, fact_key, key, fpr).join(keys, F.col(fact_key) == F.col(key), how)


def region_join(scored: DataFrame, score: str, regions: DataFrame) -> DataFrame:
    """Rows with the region (lo <= score < hi; the last also takes its upper end) they fall in. regions: region, lo, hi, one row per region of a plan."""
    s = F.col(score)
    last = regions.agg(F.max("hi")).first()[0]
    return scored.join(F.broadcast(regions), (s >= F.col("lo")) & ((s < F.col("hi")) | ((F.col("hi") == last) & (s == last))))


def asof_version(queries: DataFrame, versions: DataFrame, time: str = "ts", by: str | None = None) -> DataFrame:
    """queries with the version that was live at their time: the last one not later. versions: `time` and version. One sorted pass over the union."""
    keep = [c for c in queries.columns if c != time]
    both = queries.select(time, *keep, F.lit(None).cast("long").alias("version"), F.lit(1).alias("_ask")).unionByName(
        versions.select(time, "version", *([by] if by else []), F.lit(0).alias("_ask")), allowMissingColumns=True
    )
    w = (Window.partitionBy(by) if by else Window.partitionBy()).orderBy(time, "_ask").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("version", F.last("version", ignorenulls=True).over(w)).filter("_ask = 1").select(time, *keep, "version")


def interval_version(queries: DataFrame, versions: DataFrame, time: str = "ts") -> DataFrame:
    """The same by an interval join against the few versions, each live until the next starts; scales with the queries alone."""
    w = Window.orderBy(time)
    spans = versions.select("version", F.col(time).alias("_from"), F.lead(time).over(w).alias("_to"))
    return queries.join(F.broadcast(spans), (F.col(time) >= F.col("_from")) & (F.col("_to").isNull() | (F.col(time) < F.col("_to"))), "left").drop("_from", "_to")
