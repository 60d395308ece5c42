import duckdb
import glob
import os

import pytest

from peakcover import registry

FAST = ["interval_blocked", "enclosing_k", "conv_min", "chain_enclosing", "exact_disk_unit", "rectangle_colored", "ball_static_even", "ball_colored_bitmask", "union_arc_count", "hotspot_rollup", "stream_final_depth", "dynamic_round_best"]


@pytest.mark.parametrize("name", FAST)
def test_query_equals_its_sql(spark, data, name):
    con = duckdb.connect()
    for f in glob.glob(f"{data}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    mine = registry.QUERIES[name](spark, data)
    theirs = con.execute(registry.ORACLE_SQL[name])
    columns = [c[0] for c in theirs.description]
    order = sorted(range(len(columns)), key=columns.__getitem__)
    want = sorted(str([r[i] for i in order]) for r in theirs.fetchall())
    assert sorted(mine.columns) == sorted(columns)
    assert sorted(str([r[c] for c in sorted(columns)]) for r in mine.collect()) == want


def test_entry_module_lists_queries():
    import __spark_entry__

    assert set(registry.QUERIES) <= set(__spark_entry__.queries())
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


@pytest.mark.parametrize("name", ["lean_budgets", "cap_fraction_table", "cap_fraction_measured"])
def test_the_given_table_is_read(spark, data, name):
    found = registry.QUERIES[name](spark, data)
    assert "lineitem" in found._jdf.queryExecution().executedPlan().toString()
    if name == "cap_fraction_measured":
        assert all(abs(r["measured"] - r["formula"]) < 0.03 for r in found.collect())
    else:
        test_query_equals_its_sql(spark, data, name)
