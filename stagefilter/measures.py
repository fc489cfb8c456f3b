"""Memory, rates, reject times and build times of filters."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stagefilter.operators.scoring import matrix
from stagefilter.operators.staged import StagedFilter


def memory_report(spark: SparkSession, f: StagedFilter) -> DataFrame:
    return spark.createDataFrame([(a, float(b), int(c)) for a, b, c in f.memory()], "part string, ideal_bits double, actual_bits long")


def total_bits(f: StagedFilter, actual: bool = False) -> float:
    return float(sum(x[2 if actual else 1] for x in f.memory()))


def interval(hits: int, n: int, z: float = 1.96) -> tuple[float, float]:
    """Wilson interval of a share."""
    if not n:
        return 0.0, 1.0
    p, d = hits / n, 1 + z * z / n
    half = z * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / d
    centre = (p + z * z / (2 * n)) / d
    return max(0.0, centre - half), min(1.0, centre + half)


def measured_fpr(f: StagedFilter, test: DataFrame) -> tuple[float, float, float, int]:
    """Share of unseen non-keys accepted, its interval, their number."""
    r = f.lookup(test.filter("split = 'test'")).agg(F.count_if("found").alias("hits"), F.count("*").alias("n")).first()
    return (r.hits / r.n if r.n else 0.0, *interval(r.hits, r.n), r.n)


def false_negatives(f: StagedFilter, keys: DataFrame) -> int:
    return f.lookup(keys.filter("split = 'key'")).filter("not found").count()


def path_mix(verdicts: DataFrame) -> DataFrame:
    return verdicts.groupBy("exit_depth", "exit_role").agg(F.count("*").alias("n"), F.count_if("found").alias("found"), F.avg("learners_run").alias("learners"))


def reject_histogram(verdicts: DataFrame) -> DataFrame:
    """Learners run per query, in powers of two."""
    return verdicts.groupBy(F.floor(F.log2(F.greatest("learners_run", F.lit(1)))).alias("log2_learners")).agg(F.count("*").alias("n"), F.avg("learners_run").alias("mean"))


def reject_time(f: StagedFilter, test: DataFrame, rows: int = 10_000, repeats: int = 5) -> dict[str, float]:
    """Seconds per query, measured on a bounded sample of non-keys: median of repeats in one batch, and one row at a time."""
    part = test.filter("split = 'test'").select("h", "x").limit(rows).toArrow()
    h, x = part["h"].to_numpy(), matrix(part["x"].combine_chunks())
    return {"batch": median_time(lambda: f.walk(h, x), repeats) / max(1, len(h)), "row": row_time(lambda a, b: f.walk(a, b), h, x)}


def median_time(run: Callable[[], object], repeats: int) -> float:
    out = []
    for _ in range(repeats):
        began = time.perf_counter()
        run()
        out.append(time.perf_counter() - began)
    return float(np.median(out))


def row_time(run, h: np.ndarray, x: np.ndarray, rows: int = 300) -> float:
    began, n = time.perf_counter(), min(rows, len(h))
    for i in range(n):
        run(h[i : i + 1], x[i : i + 1])
    return (time.perf_counter() - began) / max(1, n)


def expected_latency(fpr: float, reject: float, accept: float, exact: float, approx: bool = False) -> float:
    """Mean time of a non-key query that is followed by an exact check if it is accepted."""
    return reject + fpr * exact if approx else (1 - fpr) * reject + fpr * (accept + exact)


def construction(f: StagedFilter) -> dict[str, float]:
    r = f.report
    return {"training": r.training, "calibration": r.calibration, "configuration": r.configuration, "insertion": r.insertion, "total": r.total}


def balance(f: StagedFilter) -> dict[str, float]:
    rows = f.memory()
    return {"depth": f.plan.depth, "model_bits": rows[0][1], "filter_bits": sum(r[1] for r in rows[1:])}


def slack(f: StagedFilter, test_fpr: float) -> dict[str, float]:
    return {"plan": f.plan.fpr - f.plan.expected_fpr, "test": f.plan.fpr - test_fpr}


def divergence(keys: np.ndarray, others: np.ndarray, cuts: list[int]) -> float:
    from stagefilter.plans.partition import region_sums

    a, b = region_sums(keys, cuts) / keys.sum(), np.maximum(region_sums(others, cuts) / others.sum(), 1e-300)
    return float((a[a > 0] * np.log2(a[a > 0] / b[a > 0])).sum())


def shuffle_bytes(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """Shuffled and spilled bytes and tasks of what run starts, from the status store."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def now() -> dict[str, int]:
        out = {"shuffle": 0, "spill": 0, "tasks": 0}
        stages = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
        for i in range(stages.size()):
            s = stages.apply(i)
            out["shuffle"] += s.shuffleWriteBytes()
            out["spill"] += s.diskBytesSpilled()
            out["tasks"] += s.numCompleteTasks()
        return out

    before = now()
    run()
    after = now()
    return {k: after[k] - before[k] for k in after}
