"""Rules and the cost model are computed for what the given tables hold, as their SQL says."""

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = {
    "q_config_map": "events", "q_cost_model": "embeddings", "q_degree_params": "lineitem", "q_load_efficiency": "embeddings", "q_mode_rule": "events", "q_scaling_slope": "lineitem", "q_table_size": "lineitem", "q_w_b1_lanes": "embeddings",
}


@pytest.mark.parametrize("name", TABLES)
def test_rule_reads_its_table_and_equals_sql(spark, sf, name):
    got = entry.queries()[name](spark, sf)
    assert any(f"/{TABLES[name]}.parquet" in f for f in got.inputFiles())
    con = duckdb.connect()
    for table in ("events", "embeddings", "lineitem", "supplier"):
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM read_parquet('{sf}/{table}.parquet')")
    want = con.execute(entry.oracle_sql()["q_load_efficiency" if name == "q_w_b1_lanes" else name])
    assert got.columns == [c[0] for c in want.description]
    rows = [tuple(r) for r in got.collect()]
    assert rows and sorted(rows, key=repr) == sorted(want.fetchall(), key=repr)
