"""Every registered query with SQL gives the rows that DuckDB gives, on the smallest tables."""

import glob
import numbers
import os

import duckdb
import pandas as pd
import pytest

from apcube import queries as registered

NAMES = sorted(registered.oracle_sql())
QUERIES, ORACLES = registered.queries(), registered.oracle_sql()
#: Statements about errors and recall hold on tables of some size; the smallest is a smoke test only.
LARGER = {"w10", "w16", "d_qu", "d_iq", "d_cd", "d_mo", "d_di", "w18", "b_gl", "h_ov", "q_pr", "q_un", "w20", "q_bi", "agg_", "p_he", "q_le", "w15", "w13", "b_rt", "w11", "p_di", "b_sa"}


@pytest.fixture(scope="module")
def tables():
    con = duckdb.connect()
    out = {}
    for sf in ("sf0.001", "sf0.01"):
        out[sf] = con.cursor()
        for f in glob.glob(f"/root/testdata/{sf}/*.parquet"):
            out[sf].execute(f"create or replace temp view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return out


def canon(df):
    def one(v):
        if v is None or v is pd.NA or v is pd.NaT or (isinstance(v, float) and v != v):
            return ""
        if type(v).__name__ in ("bool", "bool_"):
            return str(bool(v))
        return repr(float(v)) if isinstance(v, numbers.Number) else str(v)

    return sorted(tuple(map(one, r)) for r in df[sorted(df.columns)].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", NAMES)
def test_against_sql(spark, tables, name):
    sf = "sf0.01" if name[:4] in LARGER or name[:3] in LARGER else "sf0.001"
    got, want = QUERIES[name](spark, f"/root/testdata/{sf}").toPandas(), tables[sf].execute(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert canon(got) == canon(want)


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_runs_without_the_training_data_operators():
    """Nothing outside the subpackage and the guard imports it."""
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    for path in glob.glob(f"{root}/apcube/**/*.py", recursive=True):
        if f"{os.sep}llm{os.sep}" not in path:
            assert "apcube.llm" not in open(path).read(), path
