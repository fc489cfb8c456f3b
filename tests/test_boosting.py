"""Training takes every row of its splits, on the driver and where the rows lie."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from stagefilter.functions.hashing import element_hash
from stagefilter.operators import boosting
from stagefilter.operators.boosting import Boosting, train
from stagefilter.operators.scoring import matrix


@pytest.fixture(scope="module")
def rows(spark):
    """4,000 rows of whole numbers, some missing; the rare value 9 of the second feature decides alone."""
    v = lambda salt, n: F.pmod(F.xxhash64(F.col("id"), F.lit(salt)), F.lit(n))
    rare = F.col("id") % 400 == 7
    e = spark.range(0, 4000, 1, 5).select(
        element_hash(F.col("id")).alias("h"),
        F.when(F.col("id") == 3, None).otherwise(F.array(F.when(v(1, 50) == 0, float("nan")).otherwise(v(1, 5)).cast("float"), F.when(rare, 9).otherwise(v(2, 3)).cast("float"), v(3, 7).cast("float"))).alias("x"),
        (rare | (v(1, 5) + v(4, 4) > 5)).alias("is_key"),
    )
    return e.withColumn("split", F.when(F.col("is_key"), "key").otherwise("train")).persist()


def test_all_rows_are_trained_on(spark, rows):
    """As many rows as are taken on the driver, or forty times that: the classes' shares, and so the base, are those of all rows, and so are the trees."""
    n, keys = rows.count(), rows.filter("is_key").count()
    held = spark.sparkContext._jsc.getPersistentRDDs().size()
    few, whole = train(rows, Boosting(rounds=10, depth=3, sample=100)), train(rows, Boosting(rounds=10, depth=3, sample=n))
    assert few.base == whole.base == pytest.approx(np.log(keys / (n - keys)))
    t = rows.toArrow()
    x, y = matrix(t["x"], 3), t["is_key"].to_numpy(zero_copy_only=False).astype(float)
    loss = [-(y * np.log(p) + (1 - y) * np.log(1 - p)).mean() for p in (m.prefixes(x)[:, -1] for m in (few, whole))]
    assert loss[0] == pytest.approx(loss[1], rel=0.01)
    # ten rows of 4,000 alone have a 9, a sample of 100 would hardly hold one; each model tells them
    assert all((m.prefixes(x[x[:, 1] == 9])[:, -1] > m.prefixes(np.where(x == 9, 2, x)[x[:, 1] == 9])[:, -1]).all() for m in (few, whole))
    assert spark.sparkContext._jsc.getPersistentRDDs().size() == held


def test_trees_do_not_depend_on_where_rows_lie(spark, rows):
    """The same splits and values, bit by bit, from arrays and from tasks, however rows are dealt, also after blocks are made anew."""
    cfg = Boosting(rounds=10, depth=3, bins=16)
    t = rows.toArrow()
    x, y = matrix(t["x"], 3), t["is_key"].to_numpy(zero_copy_only=False).astype(float)
    found = []
    for parts, fold in ((0, 0), (1, 8), (7, 3)):
        data = boosting.SparkData(rows.repartition(parts), cfg, fold=fold) if parts else boosting.LocalData(x, y, cfg)
        if not parts:
            data.edges = boosting.SparkData(rows, cfg).edges
            data.b = np.ascontiguousarray(boosting.to_bins(x, data.edges).T)
        found.append(boosting.boost(data, cfg))
        data.close()
    for m in found[1:]:
        assert m.base == found[0].base
        for a, b in zip(m.trees, found[0].trees, strict=True):
            assert (a.feat == b.feat).all() and (a.thr == b.thr).all() and (a.value == b.value).all()
