"""Queries that once made their data up: they read orders, and give their SQL twins' results."""

import duckdb
import pytest
from conftest import SF
from pyspark.errors import AnalysisException

from stagefilter import registry

READING = (
    "backup_rule", "bloom_ideal_bits", "bloom_size_grid", "construction_variants_agree", "cross_config_grid", "dp_equals_bruteforce", "dp_value_chain", "expected_latency_curve", "frontier_pivot", "frontier_unpivot", "gate_neutrality", "lambda_frontier",
)


def close(rows):
    return sorted(tuple(round(float(v), 6) if isinstance(v, float) or hasattr(v, "as_tuple") else v for v in r) for r in rows)


@pytest.mark.parametrize("name", READING)
def test_reads_orders(spark, name, tmp_path):
    con = duckdb.connect()
    con.sql(f"create view orders as select * from '{SF}/orders.parquet'")
    r = con.sql(registry.oracle_sql()[name])
    df = registry.queries()[name](spark, SF)
    assert sorted(df.columns) == sorted(r.columns)
    assert close(tuple(x[c] for c in r.columns) for x in df.collect()) == close(r.fetchall())
    with pytest.raises(AnalysisException):
        registry.queries()[name](spark, str(tmp_path)).collect()
