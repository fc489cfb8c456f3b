"""Writing and reading built filters: plan, learners and bits as Parquet under versions, and a pointer to the live one."""

from __future__ import annotations

import hashlib
import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stagefilter.operators.bloom import AcceptAll, BloomFilter, RejectAll
from stagefilter.operators.scoring import Ensemble, Tree
from stagefilter.operators.staged import StagedFilter
from stagefilter.plans.config_dp import Flow, Plan

FILTERS = "name string, kind string, m long, k int, seed long, n long, fpr double, bits binary, checksum string"
LEARNERS = "depth int, size_bits long, feat array<int>, thr array<double>, value array<double>"


def plan_json(p: Plan) -> str:
    f = p.flow
    body = {k: getattr(p, k) for k in ("depth", "gates", "exit_fpr", "leaf_fpr", "fpr", "lam", "objective", "memory", "reject", "expected_fpr")}
    body["theta"] = [None if not np.isfinite(t) else float(t) for t in f.theta[: p.depth]] if f else []
    body |= {"cuts": [list(map(int, c)) for c in f.cuts[: p.depth]] if f else [], "bins": f.bins if f else 100, "n_keys": f.n_keys if f else 0}
    for k in ("key_reach", "non_reach", "key_leave", "non_leave"):
        body[k] = [float(x) for x in getattr(f, k)[: p.depth]] if f else []
    for k in ("key_leaf", "non_leaf"):
        body[k] = [[float(y) for y in x] for x in getattr(f, k)[: p.depth]] if f else []
    return json.dumps(body, sort_keys=True, default=float)


def plan_from_json(text: str) -> Plan:
    b = json.loads(text)
    arr = lambda k: np.array(b[k], float)
    theta = np.array([np.inf if t is None else t for t in b["theta"]], float)
    flow = Flow(b["n_keys"], arr("key_reach"), arr("non_reach"), arr("key_leave"), arr("non_leave"), [np.array(x) for x in b["key_leaf"]], [np.array(x) for x in b["non_leaf"]], b["cuts"], theta, b["bins"])
    return Plan(*(b[k] for k in ("depth", "gates", "exit_fpr", "leaf_fpr", "fpr", "lam", "objective", "memory", "reject", "expected_fpr")), flow=flow)


def fingerprint(p: Plan) -> str:
    return hashlib.sha256(plan_json(p).encode()).hexdigest()


def tables(spark: SparkSession, f: StagedFilter) -> dict[str, DataFrame]:
    rows = []
    for name, x in f.filters.items():
        kind = type(x).__name__
        bits = bytes(getattr(x, "bits", b"")) if isinstance(x, BloomFilter) else b""
        rows.append((name, kind, int(x.m), int(x.k), int(x.seed), int(x.n), float(x.fpr), bytearray(bits), hashlib.sha256(bits).hexdigest()))
    learners = [(d + 1, t.bits, [int(v) for v in t.feat], [float(v) for v in t.thr], [float(v) for v in t.value]) for d, t in enumerate(f.ensemble.trees)]
    e = f.ensemble
    plan = [(plan_json(f.plan), fingerprint(f.plan), float(e.base), e.link, list(e.features), f.seed)]
    return {
        "filters": spark.createDataFrame(rows, FILTERS),
        "learners": spark.createDataFrame(learners, LEARNERS),
        "plan": spark.createDataFrame(plan, "plan string, fingerprint string, base double, link string, features array<string>, seed long"),
    }


def write(spark: SparkSession, f: StagedFilter, path: str, version: int = 0) -> None:
    """A new version; the pointer is written last, so readers see a whole version or the one before."""
    for name, t in tables(spark, f).items():
        t.write.mode("overwrite").parquet(f"{path}/v{version}/{name}")
    spark.createDataFrame([(version,)], "version long").coalesce(1).write.mode("append").json(f"{path}/live")


def live_version(spark: SparkSession, path: str) -> int:
    return spark.read.schema("version long").json(f"{path}/live").agg(F.max("version")).first()[0]


def read(spark: SparkSession, path: str, version: int | None = None) -> StagedFilter:
    at = f"{path}/v{live_version(spark, path) if version is None else version}"
    p = spark.read.parquet(f"{at}/plan").first()
    trees = [Tree(np.array(r.feat), np.array(r.thr), np.array(r.value)) for r in spark.read.parquet(f"{at}/learners").orderBy("depth").toLocalIterator()]
    filters: dict[str, object] = {}
    for r in spark.read.parquet(f"{at}/filters").toLocalIterator():
        if hashlib.sha256(bytes(r.bits)).hexdigest() != r.checksum:
            raise ValueError(f"filter {r.name} is damaged")
        filters[r.name] = BloomFilter(r.m, r.k, r.seed, np.frombuffer(bytes(r.bits), np.uint8).copy(), r.fpr, r.n) if r.kind == "BloomFilter" else {"AcceptAll": AcceptAll, "RejectAll": RejectAll}[r.kind]()
    return StagedFilter(plan_from_json(p.plan), Ensemble(trees, p.base, list(p.features), p.link), filters, seed=p.seed)


def register_data_source(spark: SparkSession) -> None:
    """Format `filter_store`: one row per filter of a stored version, without its bits. Read through Spark's own file readers on the driver's session."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Reader(DataSourceReader):
        def __init__(self, options):
            self.rows = json.loads(options["rows"])

        def partitions(self):
            return [InputPartition(i) for i in range(len(self.rows))]

        def read(self, partition):
            yield tuple(self.rows[partition.value])

    class FilterStore(DataSource):
        @classmethod
        def name(cls):
            return "filter_store"

        def schema(self):
            return "name string, kind string, m long, k int, n long, fpr double"

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(FilterStore)


def data_source_rows(spark: SparkSession, path: str, version: int | None = None) -> DataFrame:
    register_data_source(spark)
    at = f"{path}/v{live_version(spark, path) if version is None else version}"
    rows = [list(r) for r in spark.read.parquet(f"{at}/filters").select("name", "kind", "m", "k", "n", "fpr").collect()]
    return spark.read.format("filter_store").option("rows", json.dumps(rows)).load()
