"""The small fixed workload that the SQL twins can follow: orders, four stumps with whole weights, fixed thresholds."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stagefilter.functions.hashing import element_hash, hash_sql
from stagefilter.operators.scoring import Ensemble, TableScorer, Tree
from stagefilter.sources.workloads import split_of, table

LABEL = "(o_totalprice > 300000 OR o_orderdate < TIMESTAMP '1996-06-01 00:00:00')"
SCORER = TableScorer(
    (
        ("CAST(o_totalprice AS FLOAT) > 250000", 4),
        ("o_orderdate < TIMESTAMP '1996-01-01 00:00:00'", 3),
        ("CAST(o_totalprice AS FLOAT) > 350000", 2),
        ("o_orderdate < TIMESTAMP '1997-01-01 00:00:00'", 1),
    )
)
DEPTH, BINS = 4, 20
#: Threshold vectors by number: no exits, then exits at a score for every depth.
THETAS = [np.full(4, np.inf), np.full(4, 0.9), np.full(4, 0.7), np.full(4, 0.4)]


def scored(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders")
    rows = o.select(F.col("o_orderkey").cast("string").alias("eid"), F.expr(LABEL).alias("is_key"), SCORER.scores().alias("s"), F.col("o_totalprice").alias("price"), F.col("o_orderdate").alias("day"))
    rows = rows.withColumn("h", element_hash(F.col("eid")))
    return rows.withColumn("split", split_of(F.col("h"), F.col("is_key")))


def examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with features for the tree form of the scorer: price, days."""
    return scored(spark, sf_dir).withColumn("x", F.array(F.col("price").cast("float"), F.unix_date(F.col("day").cast("date")).cast("float")))


def ensemble() -> Ensemble:
    """The stumps as trees; dates are days since 1970."""
    price = lambda t, w: Tree(np.array([0, -1, -1]), np.array([t, 0.0, 0.0]), np.array([0.0, 0.0, w]))
    before = lambda t, w: Tree(np.array([1, -1, -1]), np.array([t - 0.5, 0.0, 0.0]), np.array([0.0, w, 0.0]))
    return Ensemble([price(250000.0, 4.0), before(9496.0, 3.0), price(350000.0, 2.0), before(9862.0, 1.0)], 0.0, ["price", "day"], "share")


def scored_sql() -> str:
    """CTE `q`: eid, h, is_key, split, s1 .. s4."""
    s = ", ".join(f"{e} AS s{i + 1}" for i, e in enumerate(SCORER.sql()))
    return f"""b AS (SELECT CAST(o_orderkey AS VARCHAR) AS eid, {LABEL} AS is_key, {s} FROM orders),
hh AS (SELECT *, {hash_sql('eid')} AS h FROM b),
q AS (SELECT *, CASE WHEN is_key THEN 'key' WHEN h % 1000 < 100 THEN 'test' WHEN h % 10 = 9 THEN 'calib' ELSE 'train' END AS split FROM hh)"""


def bin_sql(s: str, bins: int = BINS) -> str:
    return f"CAST(least(floor({s} * {bins}), {bins - 1}) AS INTEGER)"


def long_sql() -> str:
    """CTE `d`: one row per element of splits key and calib and depth, with exit depth under each threshold vector."""
    exits = []
    for t in THETAS:
        arms = " ".join(f"WHEN s{i + 1} >= {t[i]} THEN {i + 1}" for i in range(DEPTH - 1)) if np.isfinite(t[0]) else ""
        exits.append(f"CASE {arms} ELSE {DEPTH} END" if arms else str(DEPTH))
    union = " UNION ALL ".join(f"SELECT eid, is_key, {t} AS theta_id, {x} AS ex, s1, s2, s3, s4 FROM q WHERE split IN ('key', 'calib')" for t, x in enumerate(exits))
    return f"""{scored_sql()},
x AS ({union}),
d AS (SELECT theta_id, dep AS depth, CAST(is_key AS INTEGER) AS cls, ex, CASE dep WHEN 1 THEN s1 WHEN 2 THEN s2 WHEN 3 THEN s3 ELSE s4 END AS s
      FROM x CROSS JOIN (VALUES (1), (2), (3), (4)) v(dep) WHERE ex >= dep)"""


def flow_sql() -> str:
    """CTE `f`: theta_id, depth, cls, bin, cnt; bin -1 is what exits."""
    return f"""{long_sql()},
f AS (SELECT theta_id, depth, cls, {bin_sql('s')} AS bin, count(*) AS cnt FROM d GROUP BY ALL
      UNION ALL SELECT theta_id, depth, cls, -1 AS bin, count(*) AS cnt FROM d WHERE ex = depth AND depth < {DEPTH} GROUP BY ALL)"""
