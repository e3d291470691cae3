"""Every query with SQL against DuckDB on the smallest tables; results must agree row by row."""

import glob
import math
import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
SQL = {n: s for n, s in entry.oracle_sql().items() if n in entry.core.SQL}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else float(f"{v:.12g}")
    return v


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, duck, name):
    df = entry.queries()[name](spark, SF)
    want = duck.sql(SQL[name])
    columns = list(want.columns)
    assert sorted(columns) == sorted(df.columns)
    rows = [tuple(plain(r[c]) for c in columns) for r in df.collect()]
    assert sorted(rows, key=repr) == sorted((tuple(map(plain, r)) for r in want.fetchall()), key=repr)


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert {r["step"] for r in rows} == {1, 2} and all(r["n"] == 6000 and r["bits"] == 5 and r["n_exact"] == 0 for r in rows)


def test_queries_need_no_llm_subpackage():
    assert set(entry.core.QUERIES) <= set(entry.queries()) and not any(n.startswith("op") for n in entry.core.QUERIES)


def test_densify_all_returns_every_point(spark):
    rows = entry.queries()["o_densify_all"](spark, "/root/testdata/sf0.01").collect()
    assert len({r["pos"] for r in rows}) == 750 and len(rows) == 30 * 750


@pytest.mark.parametrize("name, series", [("m_choose_bits_measured", "part_volume"), ("m_log_scale_centres", "part_volume"), ("m_kmeans", "supplier_month"), ("b_strategies_fixed", "part_volume")])
def test_method_queries_take_every_step(spark, name, series):
    steps = {r["step"] for r in entry.core.change_ratios(entry.load_series(spark, SF, series)).where("ratio IS NOT NULL AND ratio <> 0").select("step").distinct().collect()}
    assert len(steps) > 2 and steps <= {r["step"] for r in entry.queries()[name](spark, SF).collect()}


@pytest.mark.parametrize("name, table", [("c_predicted_cr", "part"), ("o_size_estimate_rows", "part"), ("w_dp_memory", "customer"), ("w_partial_blocks", "part"), ("w_speedup", "lineitem")])
def test_queries_read_given_tables(spark, tmp_path, name, table):
    for path in glob.glob(f"{SF}/*.parquet"):
        os.symlink(path, tmp_path / os.path.basename(path))
    os.unlink(tmp_path / f"{table}.parquet")
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        entry.queries()[name](spark, str(tmp_path)).collect()
