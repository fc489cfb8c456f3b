"""Queries of other learner families, of the unrolled search and of the projection hash, with their SQL twins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stagefilter import measures as M
from stagefilter.functions.sizing import LOG2E
from stagefilter.operators.families import best_stump, boost_stumps, projection_cells, projection_filter, projection_probe, train_modules
from stagefilter.operators.staged import build
from stagefilter.plans.config_dp import Costs, Flow, configure
from stagefilter.queries.base import LABEL
from stagefilter.queries.method import _ORDERS_C, orders_keys
from stagefilter.sources.workloads import load, table

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        Q[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


_BINS = ("CAST(floor(o_totalprice / 25000) AS INTEGER)", "CAST(substr(o_orderpriority, 1, 1) AS INTEGER)", "month(o_orderdate)", "year(o_orderdate)")
_CELLS = " UNION ALL ".join(f"SELECT {j} AS feature, {e} AS bin, y FROM o" for j, e in enumerate(_BINS))


@query(
    f"""WITH o AS (SELECT *, CASE WHEN {LABEL} THEN 1.0 ELSE 0.0 END::DOUBLE AS y FROM orders), z AS ({_CELLS}),
c AS (SELECT feature, bin, sum(0.5 - y) AS g, count(*) * 0.25::DOUBLE AS h FROM z GROUP BY ALL),
w AS (SELECT feature, bin, sum(g) OVER a AS gl, sum(g) OVER (PARTITION BY feature) AS gt, sum(h) OVER a AS hl, sum(h) OVER (PARTITION BY feature) AS ht FROM c WINDOW a AS (PARTITION BY feature ORDER BY bin)),
s AS (SELECT feature, bin, gl * gl / (hl + 1) + (gt - gl) * (gt - gl) / (ht - hl + 1) - gt * gt / (ht + 1) AS gain, -gl / (hl + 1) AS lo, -(gt - gl) / (ht - hl + 1) AS hi FROM w WHERE hl > 1e-9 AND ht - hl > 1e-9)
SELECT CAST(feature AS INTEGER) AS feature, bin, round(gain, 4) AS gain, round(lo, 6) AS lo, round(hi, 6) AS hi FROM s ORDER BY s.gain DESC, feature, bin LIMIT 1"""
)
def boost_round_one(spark: SparkSession, sf: str) -> DataFrame:
    """The first stump of a boosting from margin 0."""
    o = table(spark, sf, "orders")
    rows = o.select(F.expr(f"CASE WHEN {LABEL} THEN 1D ELSE 0D END").alias("y"), F.lit(0.0).alias("margin"), F.array(*[F.expr(e) for e in _BINS]).alias("b"))
    return best_stump(rows).select("feature", "bin", F.round("gain", 4).alias("gain"), F.round("lo", 6).alias("lo"), F.round("hi", 6).alias("hi"))


def _edges(e: DataFrame, bins: int = 32) -> list[list[float]]:
    width = len(e.select("x").first().x)
    probs = [i / bins for i in range(1, bins)]
    found = e.agg(*[F.percentile_approx(F.get("x", F.lit(j)).cast("double"), probs, 2000).alias(f"c{j}") for j in range(width)]).first()
    return [sorted(set(c or [])) for c in found]


@query()
def family_filters(spark: SparkSession, sf: str) -> DataFrame:
    """Filters whose learners are stumps boosted in DataFrame functions, linear modules, and modules of one hidden layer."""
    e = load("orders_mix", spark, sf).persist()
    trained = e.filter("split in ('key', 'train')").select("is_key", "x")
    made = {"stumps_sql": boost_stumps(trained, _edges(trained), 20), "linear": train_modules(e, 20), "hidden_8": train_modules(e, 20, 8)}
    out = []
    for name, ensemble in made.items():
        f = build(e, 0.01, 1.0, ensemble=ensemble)
        out.append((name, f.plan.depth, float(f.plan.memory), M.false_negatives(f, e), M.measured_fpr(f, e)[0]))
    e.unpersist()
    return spark.createDataFrame(out, "family string, depth int, bits double, missed long, rate double")


def _held(a: float, b: float, product: str) -> str:
    """Bits of a backup filter in SQL: key share a, non-key share b, what the gates above let through."""
    return f"(CASE WHEN 0.01 * {a} >= {b} * {product} THEN 0 ELSE {_ORDERS_C} * {a} * log2({b} * {product} / (0.01 * {a})) END)"


@query(
    f"""WITH l(lam) AS (VALUES (1.0::DOUBLE), (0.9), (0.5), (0.0)), e(i) AS (VALUES (0), (1), (2)),
last AS (SELECT a.i AS i, a.i + b.i AS t, b.i AS k FROM e a, e b WHERE a.i + b.i <= 2),
two AS (SELECT i, 200 + {_ORDERS_C} * 0.5 * k + {_held(0.2, 0.75, 'pow(0.5, t)')} + {_held(0.3, 0.15, 'pow(0.5, t)')} AS m, 0.9 * pow(0.5, t) AS r FROM last),
one AS (SELECT i, {_held(0.3, 0.8, 'pow(0.5, i)')} + {_held(0.7, 0.2, 'pow(0.5, i)')} AS m, 0.0 AS r FROM e),
rest AS (SELECT * FROM one UNION ALL SELECT i, m + {_held(0.5, 0.1, 'pow(0.5, i)')}, r FROM two),
val AS (SELECT lam, lam * (200 + {_ORDERS_C} * i + m) / ({_ORDERS_C} * log2(100)) + (1 - lam) * (pow(0.5, i) + r) AS v FROM l, rest)
SELECT lam, round(least(lam, min(v)), 6) AS value FROM val GROUP BY lam"""
)
def dp_value_chain(spark: SparkSession, sf: str) -> DataFrame:
    """The value of the search on the worked example with as many keys as the orders have, its two levels unrolled in SQL."""
    a = np.array
    n = orders_keys(spark, sf)
    f = Flow(n, a([1.0, 0.5]), a([1.0, 0.9]), a([0.5, 0.0]), a([0.1, 0.0]), [a([0.3, 0.7]), a([0.2, 0.3])], [a([0.8, 0.2]), a([0.75, 0.15])], [[50], [50]], a([0.9, np.inf]))
    c = Costs(a([200.0, 200.0]), a([1.0, 1.0]), LOG2E * n * np.log2(100))
    return spark.createDataFrame([(lam, round(float(configure(f, c, 0.01, lam, 3).objective), 6)) for lam in (1.0, 0.9, 0.5, 0.0)], "lam double, value double")


_VECTORS = [[3, -2, 5], [1, 4, -7], [-2, 1, 11]]
_VALUES = ("CAST(floor(o_totalprice / 1000) AS BIGINT)", "CAST(o_custkey AS BIGINT)", "CAST(month(o_orderdate) AS BIGINT)")
_DOTS = f"""o AS (SELECT o_orderkey, {LABEL} AS is_key, {', '.join(f'{e} AS v{j}' for j, e in enumerate(_VALUES))} FROM orders),
p AS ({' UNION ALL '.join('SELECT o_orderkey, is_key, ' + str(k) + ' AS k, ' + ' + '.join(f'v{j} * {w}' for j, w in enumerate(v)) + ' AS dot FROM o' for k, v in enumerate(_VECTORS))}),
b AS (SELECT k, min(dot) AS low, greatest(1, CAST(ceil((max(dot) - min(dot) + 1) / 200.0) AS BIGINT)) AS width FROM p WHERE is_key GROUP BY k),
c AS (SELECT o_orderkey, is_key, k, CAST(floor((dot - low) / CAST(width AS DOUBLE)) AS BIGINT) AS cell FROM p JOIN b USING (k))"""


def _projected(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "orders").select("o_orderkey", F.expr(LABEL).alias("is_key"), F.array(*[F.expr(e) for e in _VALUES]).alias("v"))


@query(f"WITH {_DOTS} SELECT CAST(k AS INTEGER) AS k, cell, count(*) AS n FROM c WHERE is_key GROUP BY ALL")
def projection_positions(spark: SparkSession, sf: str) -> DataFrame:
    rows = _projected(spark, sf).filter("is_key")
    bounds, _ = projection_filter(rows, F.col("v"), _VECTORS, 200)
    at = projection_cells(rows, F.col("v"), _VECTORS).join(F.broadcast(bounds), "k")
    return at.groupBy("k", F.floor((F.col("dot") - F.col("low")) / F.col("width")).alias("cell")).agg(F.count("*").alias("n"))


@query(f"WITH {_DOTS}, s AS (SELECT DISTINCT k, cell FROM c WHERE is_key), f AS (SELECT o_orderkey, is_key, bool_and(s.k IS NOT NULL) AS found FROM c LEFT JOIN s USING (k, cell) GROUP BY ALL) SELECT is_key, found, count(*) AS n FROM f GROUP BY ALL")
def projection_fpr(spark: SparkSession, sf: str) -> DataFrame:
    """The projection hash as tables: all keys are found, and how many others."""
    rows = _projected(spark, sf)
    bounds, cells = projection_filter(rows.filter("is_key"), F.col("v"), _VECTORS, 200)
    found = projection_probe(rows, "o_orderkey", F.col("v"), _VECTORS, bounds, cells)
    return rows.select("o_orderkey", "is_key").join(found, "o_orderkey").groupBy("is_key", "found").agg(F.count("*").alias("n"))
