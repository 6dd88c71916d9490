"""Measures and rules whose inputs come from a given table."""

import duckdb
import pytest

from tensorlane import queries, queries_models, queries_tables

SF = "/root/testdata/sf0.001"
QUERIES = {**queries.QUERIES, **queries_tables.QUERIES, **queries_models.QUERIES}
ORACLES = {**queries.ORACLES, **queries_tables.ORACLES}
CHECKED: list[str] = ["cost_per_prediction", "coverage_summary", "op_count_table", "speedup_summary", "strategy_choice_grid", "strategy_cost_table", "w18_diagnostics"]
TIMED: list[str] = ["w6_memory", "w8_conversion_time"]


@pytest.mark.parametrize("name", CHECKED + TIMED)
def test_there_is_no_result_without_the_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("name", CHECKED)
def test_equals_its_sql(spark, name):
    con = duckdb.connect()
    for table in ("lineitem", "orders", "events", "part", "customer", "supplier", "nation", "region"):
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{SF}/{table}.parquet'")
    rows = sorted(tuple(r) for r in QUERIES[name](spark, SF).collect())
    assert rows and rows == sorted(con.execute(ORACLES[name]).fetchall())


@pytest.mark.parametrize("name", TIMED)
def test_gives_a_row_for_each_size_and_strategy(spark, name):
    assert QUERIES[name](spark, SF).count() == 9
