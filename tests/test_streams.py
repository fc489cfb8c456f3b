"""Streams run to their end: appended rows stay off the driver, and the queries around them give their SQL twins' results."""

import duckdb
import pytest
from conftest import TINY

from stagefilter import registry
from stagefilter.sources.workloads import table


def against_sql(spark, name: str) -> None:
    df, con = registry.queries()[name](spark, TINY), duckdb.connect()
    for t in ("events", "customer"):
        con.sql(f"create view {t} as select * from '{TINY}/{t}.parquet'")
    r = con.sql(registry.oracle_sql()[name])
    assert sorted(tuple(x[c] for c in r.columns) for x in df.collect()) == sorted(r.fetchall())


def in_memory_tables(spark) -> set[str]:
    return {t.name for t in spark.catalog.listTables() if t.isTemporary}


def test_late_inserts_go_to_files(spark):
    before = in_memory_tables(spark)
    against_sql(spark, "late_insert_count")
    assert in_memory_tables(spark) == before


@pytest.mark.parametrize("name", ["stream_filter_state", "stream_lookup_batch", "stream_static_join"])
def test_appended_rows_go_to_files(spark, name):
    before = in_memory_tables(spark)
    against_sql(spark, name)
    assert in_memory_tables(spark) == before
