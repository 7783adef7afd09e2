"""Registered queries against their SQL in DuckDB, at the smallest scale."""

import duckdb
import pandas as pd
import pytest

from ordering_engine import experiments, method_queries, operator_queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES = method_queries.QUERIES | operator_queries.QUERIES | experiments.QUERIES
ORACLE = method_queries.ORACLE | operator_queries.ORACLE | experiments.ORACLE
#: Methods that test_methods covers on other inputs; their SQL is held against them at the driver.
SLOW = {n for n in ORACLE if n.startswith("sort_") and n not in ("sort_cube_robust", "sort_cube_ternary", "sort_bitonic", "sort_direct", "sort_direct_given", "sort_exact_split", "sort_global_multi", "sort_grid_robust", "sort_descending", "sort_within_pe")} | {"shuffle_cube", "cube_route"}


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def plain(frame: pd.DataFrame) -> list[tuple]:
    def value(v):
        if v is None or v is pd.NaT or v is pd.NA or isinstance(v, float) and v != v:
            return "none"
        if isinstance(v, pd.Timestamp):
            return str(v)
        return repr(float(v)) if isinstance(v, (int, float)) and not isinstance(v, bool) or hasattr(v, "dtype") and v.dtype.kind in "iuf" else str(v)

    return sorted(tuple(value(v) for v in row) for row in frame[sorted(frame.columns)].itertuples(index=False))


@pytest.mark.parametrize("name", sorted(set(ORACLE) - SLOW))
def test_query_matches_sql(spark, duck, small, name):
    got, want = QUERIES[name](spark, small).toPandas(), duck.execute(ORACLE[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert plain(got) == plain(want)


def test_entry_imports_without_corpus_operators(tmp_path):
    import os
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    repo = Path(__file__).resolve().parent.parent
    shutil.copytree(repo / "ordering_engine", tmp_path / "ordering_engine", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(repo / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 150 and not any(n.startswith('op1') for n in q) and 'pipeline' not in q; print(len(q), len(e.oracle_sql()))"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=os.environ | {"PYTHONPATH": str(tmp_path)}, check=True)


def test_every_customer_is_a_pe(spark):
    """On more customers than the first 1,024."""
    larger, name = "/root/testdata/sf0.01", "sort_one_per_pe"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW customer AS SELECT * FROM '{larger}/customer.parquet'")
    got, want = QUERIES[name](spark, larger).toPandas(), con.execute(ORACLE[name]).df()
    assert len(got) == 1500 and plain(got) == plain(want)


@pytest.mark.parametrize("name", ["cost_bound", "cost_formulas", "cost_rank_methods", "exp_median_fit", "median_quality", "udtf_bitonic_schedule"])
def test_query_needs_its_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()


def test_small_sort_keeps_the_method_of_its_sql(spark, duck, small, monkeypatch):
    """Where the load is in the range of another method, as it is from 262,145 orders on."""
    from ordering_engine.plans import selector

    monkeypatch.setattr(selector, "PUBLISHED", ((float("inf"), "multilevel_samplesort"),))
    got, want = QUERIES["sort_adaptive_small"](spark, small).toPandas(), duck.execute(ORACLE["sort_adaptive_small"]).df()
    assert plain(got) == plain(want)


def test_theta_join_of_prices(spark, tmp_path):
    """Every pair of parts whose prices are less than 15 cents apart, in their order; equal, missing and odd prices too."""
    prices = [900.0, 900.0, 900.1, 900.1, 900.14, 900.15, 900.2, 901.0, -0.05, 0.0, -0.0, 0.1, float("nan"), float("inf"), None]
    spark.createDataFrame(list(enumerate(prices)), "p_partkey bigint, p_retailprice double").write.parquet(str(tmp_path / "part.parquet"))
    got, con = QUERIES["join_theta_price"](spark, str(tmp_path)).collect(), duckdb.connect()
    con.execute(f"CREATE VIEW part AS SELECT * FROM '{tmp_path}/part.parquet/*.parquet'")
    real = [(k, v) for k, v in enumerate(prices) if v is not None]
    want = [(a, b) for a, v in real for b, w in real if v < w < v + 0.15]
    assert sorted(map(tuple, got)) == sorted(want) == sorted(con.execute(ORACLE["join_theta_price"]).fetchall())
