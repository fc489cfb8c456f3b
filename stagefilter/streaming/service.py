"""Filters over streams: lookups, inserts with versions, monitoring, rebuild rules."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stagefilter.functions.hashing import BLOCK_BITS, element_hash, positions
from stagefilter.operators.bloom import BloomFilter


def event_stream(spark, path: str, schema) -> DataFrame:
    """A file stream; ts becomes a timestamp, as a watermark needs."""
    return spark.readStream.schema(schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def lookup_stream(stream: DataFrame, f: BloomFilter, key: Column) -> DataFrame:
    """Stateless: the stream with `found`."""
    return stream.withColumn("found", f.contains(element_hash(key)))


def run_to_end(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """All that is available. Appended rows go to Parquet files beside the checkpoint, so none of them pass the driver; a complete result, which is one row per group, goes through a memory sink."""
    out = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if mode != "append":
        out.format("memory").queryName(name).start().awaitTermination()
        return stream.sparkSession.table(name)
    out.format("parquet").queryName(name).start(f"{checkpoint}-{name}").awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{checkpoint}-{name}")


def insert_stream(keys: DataFrame, shape: BloomFilter, path: str, checkpoint: str) -> int:
    """Streamed inserts: each micro-batch's bitmaps go to a version of their own under path. The live filter is the union of all versions, so a batch that is written twice changes nothing, and no key is ever dropped for being late. Returns the number of versions."""
    spark = keys.sparkSession

    def write(batch: DataFrame, version: int) -> None:
        points = batch.select(F.explode(positions(F.col("h"), shape.seed, shape.k, shape.m)).alias("p"))
        rows = points.groupBy(F.expr(f"p div {BLOCK_BITS}").alias("block")).agg(F.bitmap_construct_agg(F.col("p") % BLOCK_BITS).alias("bits"))
        rows.withColumn("version", F.lit(version).cast("long")).write.mode("overwrite").parquet(f"{path}/batch={version}")

    q = keys.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(path).select("batch").distinct().count()


def live_filter(spark, shape: BloomFilter, path: str) -> BloomFilter:
    out = BloomFilter(shape.m, shape.k, shape.seed, np.zeros_like(shape.bits), shape.fpr)
    for r in spark.read.parquet(path).groupBy("block").agg(F.bitmap_or_agg("bits").alias("bits")).toLocalIterator():
        part, a = np.frombuffer(bytes(r.bits), np.uint8), r.block * BLOCK_BITS // 8
        out.bits[a : a + len(part)] |= part[: len(out.bits) - a]
    return out


def windowed_rate(verdicts: DataFrame, length: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """Share of accepted queries in tumbling or sliding windows of ts; late rows are let in until the watermark."""
    rows = verdicts.withWatermark("ts", late) if late and verdicts.isStreaming else verdicts
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return rows.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.count_if("found").alias("hits")).select(F.col("w.start").alias("start"), "n", "hits")


def sessions(verdicts: DataFrame, gap: str, by: str) -> DataFrame:
    return verdicts.groupBy(F.session_window("ts", gap).alias("w"), by).agg(F.count("*").alias("n")).select(by, F.col("w.start").alias("start"), "n")


def first_seen(rows: DataFrame, key: str, late: str) -> DataFrame:
    """One row per key within the watermark."""
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def keyed_filter_state(stream: DataFrame, shards: int, n: int, fpr: float) -> DataFrame:
    """(shard, h, new): state is one Bloom filter per hash shard; `new` says whether the filter had not seen the key."""
    empty = BloomFilter.empty(n, fpr)

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        f = BloomFilter(empty.m, empty.k, 0, np.frombuffer(state.get[0], np.uint8).copy() if state.exists else np.zeros_like(empty.bits), fpr)
        for rows in batches:
            h = rows.h.to_numpy(np.int64)
            # a key is new where it stands first in the batch and the filter had not seen it
            new = ~f.contains_np(h) & ~rows.h.duplicated().to_numpy()
            f.insert(h[new])
            yield pd.DataFrame({"shard": key[0], "h": rows.h, "new": new})
        state.update((f.bits.tobytes(),))

    dealt = stream.select("h", F.pmod(F.xxhash64("h"), F.lit(shards)).cast("int").alias("shard"))
    return dealt.groupBy("shard").applyInPandasWithState(step, "shard int, h long, new boolean", "bits binary", "append", "NoTimeout")


def health(f, inserted: int, window_hits: int = 0, window_n: int = 0) -> dict[str, float]:
    """Inserted share and estimated rate of a staged filter's parts, with the measured rate of a window."""
    live = [x for x in f.filters.values() if isinstance(x, BloomFilter)]
    planned = max(1, f.plan.flow.n_keys if f.plan.flow else 1)
    worst = max((x.estimated_fpr() / x.fpr for x in live if x.fpr), default=1.0)
    return {"inserted_share": inserted / planned, "estimated_fpr": f.plan.expected_fpr * worst, "measured_fpr": window_hits / window_n if window_n else 0.0}


def needs_rebuild(state: dict[str, float], target: float, most_inserted: float = 0.1, slack: float = 0.5) -> bool:
    return state["inserted_share"] > most_inserted or state["estimated_fpr"] > (1 + slack) * target or state["measured_fpr"] > (1 + slack) * target


__all__ = [k for k, v in list(globals().items()) if isinstance(v, Callable) and not k.startswith("_")]
