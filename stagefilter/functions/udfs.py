"""Filters as SQL functions and table functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from stagefilter.functions.hashing import positions_np
from stagefilter.functions.sizing import MOST_BROADCAST
from stagefilter.operators.scoring import identities, matrix


def register(spark: SparkSession, staged=None, bloom=None, prefix: str = "") -> list[str]:
    """maybe_in(h, x) and score_prefix(x) of a staged filter, bloom_has(h) of a Bloom filter, and the table functions bloom_positions and filter_path. Returns the names. Filters are broadcast, so their bits are checked first; null identities are never found, null features count as missing values."""
    names = []
    held_bits = (bloom.m if bloom is not None else 0) + sum(int(f.m) for f in (staged.filters.values() if staged is not None else ()))
    if held_bits // 8 > MOST_BROADCAST:
        raise ValueError(f"{held_bits // 8} bytes are over the broadcast limit; join with the sharded form")
    if bloom is not None:
        held = spark.sparkContext.broadcast(bloom)

        @F.arrow_udf("boolean")
        def bloom_has(h: pa.Array) -> pa.Array:
            hashes, known = identities(h)
            return pa.array(held.value.contains_np(hashes) & known)

        spark.udf.register(f"{prefix}bloom_has", bloom_has)
        names.append(f"{prefix}bloom_has")
    if staged is not None:
        kept = spark.sparkContext.broadcast(staged)

        @F.arrow_udf("boolean")
        def maybe_in(h: pa.Array, x: pa.Array) -> pa.Array:
            hashes, known = identities(h)
            return pa.array(kept.value.walk(hashes, matrix(x, kept.value.ensemble.width))[0] & known)

        @F.arrow_udf("array<double>")
        def score_prefix(x: pa.Array) -> pa.Array:
            s = kept.value.ensemble.prefixes(matrix(x, kept.value.ensemble.width))
            return pa.ListArray.from_arrays(pa.array((np.arange(len(s) + 1) * s.shape[1]).astype(np.int32)), pa.array(s.ravel()))

        @F.udtf(returnType="step int, component string, found boolean")
        class FilterPath:
            def eval(self, h: int, x: list):
                f = kept.value
                found, depth, role, region, _, _ = f.walk(np.array([h], np.int64), np.array([x], float))
                last, n = int(depth[0]), 0
                for d in range(1, last + 1):
                    if f.plan.gates[d - 1]:
                        n += 1
                        yield n, f"g{d}", not (role[0] == 1 and d == last)
                if role[0] != 1:
                    yield n + 1, {0: "plain", 2: f"e{last}", 3: f"l{int(region[0])}"}[int(role[0])], bool(found[0])

        spark.udf.register(f"{prefix}maybe_in", maybe_in)
        spark.udf.register(f"{prefix}score_prefix", score_prefix)
        spark.udtf.register(f"{prefix}filter_path", FilterPath)
        names += [f"{prefix}{n}" for n in ("maybe_in", "score_prefix", "filter_path")]

    @F.udtf(returnType="i int, p long")
    class BloomPositions:
        def eval(self, h: int, seed: int, k: int, m: int):
            for i, p in enumerate(positions_np(np.array([h], np.int64), seed, k, m)[0]):
                yield i, int(p)

    spark.udtf.register(f"{prefix}bloom_positions", BloomPositions)
    return [*names, f"{prefix}bloom_positions"]
