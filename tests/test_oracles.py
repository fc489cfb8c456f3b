"""Queries against their SQL twins on the smallest tables that all hold for."""

import duckdb
import pytest

from stagefilter import registry

SF = "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = (
    "examples_physics", "bloom_lookup_sql", "bloom_sharded_probe", "flow_shares", "flow_with_gates", "kl_best_split_k3", "lambda_frontier", "dp_equals_bruteforce", "staged_verdicts",
    "prefilter_anti_join", "asof_filter_version", "verdict_cube", "stream_lookup_batch", "windowed_fpr_sliding", "udtf_filter_path", "null_policy",
    "staged_null_identity", "boost_round_one", "dp_value_chain", "projection_fpr", "staged_counting",
)


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def norm(v):
    return round(float(v), 6) if isinstance(v, float) or hasattr(v, "as_tuple") else v


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, db, name):
    df = registry.queries()[name](spark, SF)
    cols = sorted(df.columns)
    r = db.sql(registry.oracle_sql()[name])
    assert sorted(r.columns) == cols
    at = [r.columns.index(c) for c in cols]
    assert sorted((tuple(norm(x[c]) for c in cols) for x in df.collect()), key=repr) == sorted((tuple(norm(x[i]) for i in at) for x in r.fetchall()), key=repr)


def test_every_twin_has_a_query():
    assert set(registry.oracle_sql()) <= set(registry.queries())
    assert len(registry.queries()) > 120
