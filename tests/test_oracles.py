"""Every registered query with SQL against DuckDB on the smallest tables."""

import os

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry

SQL = {k: v for k, v in entry.oracle_sql().items() if k.startswith("q_")}


def normal(df: pd.DataFrame) -> list:
    def one(v):
        if v is None or v is pd.NaT or v is pd.NA or (isinstance(v, float) and v != v):
            return ""
        if type(v).__name__ in ("float", "float64", "float32", "Decimal"):
            return f"{float(v):.6g}"
        return str(pd.Timestamp(v)) if "date" in type(v).__name__.lower() or "time" in type(v).__name__.lower() else str(v)

    cols = sorted(df.columns)
    return [cols, sorted(tuple(one(v) for v in row) for row in df[cols].itertuples(index=False))]


@pytest.fixture(scope="module")
def duck(tiny):
    c = duckdb.connect()
    for f in os.listdir(tiny):
        c.execute(f"create view {f.split('.')[0]} as select * from read_parquet('{tiny}/{f}')")
    return c


@pytest.mark.parametrize("name", sorted(SQL))
def test_query(spark, tiny, duck, name):
    assert normal(entry.queries()[name](spark, tiny).toPandas()) == normal(duck.execute(SQL[name]).df())


def test_rows_only_queries(spark, tiny):
    for name, f in entry.queries().items():
        if name.startswith("q_") and name not in SQL:
            assert f(spark, tiny).count() >= 0


def test_entry(spark):
    assert entry.entry(spark).count() == 6000


@pytest.mark.parametrize("name", ["q_cost_block_transfers", "q_cost_branch_proxy", "q_cost_comparisons", "q_cost_extra_space", "q_cost_io_volume", "q_level_plan", "q_speedup_model"])
def test_models_are_of_the_given_table(spark, tiny, name):
    """Costs are those of rows that tasks have read."""
    out = entry.queries()[name](spark, tiny)
    assert any("lineitem" in f for f in out.inputFiles())
    n = spark.read.parquet(f"{tiny}/lineitem.parquet").count()
    assert sum(r.n for r in out.select("l_returnflag", "l_linenumber", "n").distinct().collect()) == n
