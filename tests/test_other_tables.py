"""Queries on tables unlike the given ones: records beyond the points' usual domain, and other records than theirs."""

import os

import duckdb
import pytest

from apcube import queries as registered
from test_queries import canon

QUERIES, ORACLES = registered.queries(), registered.oracle_sql()
BEYOND = ["d_combo", "d_cov_corr", "d_distinct", "d_mean_var_std", "d_minmax_interval", "i_cat_axis", "p_rstar_counts_area", "p_rstar_counts_density", "p_rstar_counts_density_n", "p_rstar_reinsert", "q_linked", "q_multi_range", "str_ingest_cells"]
READING = ["h_overlap_probe", "h_verify", "join_box_overlap", "join_cross_grid", "join_self_overlap", "m_coincidence", "m_dense_size", "m_op_count", "q_slider_steps"]


def copied(sf, folder, **changed):
    """A copy of the tables in which some are replaced by the rows of an SQL over the others."""
    con = duckdb.connect()
    for f in sorted(os.listdir(sf)):
        con.execute(f"create view {f[:-8]} as select * from '{sf}/{f}'")
        if f[:-8] not in changed:
            os.symlink(f"{sf}/{f}", f"{folder}/{f}")
    for table, sql in changed.items():
        con.execute(f"copy ({sql}) to '{folder}/{table}.parquet' (format parquet)")
    return str(folder)


def against_sql(spark, folder, name):
    con = duckdb.connect()
    for f in os.listdir(folder):
        con.execute(f"create view {f[:-8]} as select * from '{folder}/{f}'")
    got, want = QUERIES[name](spark, folder).toPandas(), con.execute(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert canon(got) == canon(want)
    return canon(got)


@pytest.fixture(scope="module")
def wide(sf, tmp_path_factory):
    """Values up to four times as high: coordinates pass 57600."""
    return copied(sf, tmp_path_factory.mktemp("wide"), events="select * replace (round(value * (1 + event_id % 4), 2)::double as value) from events")


@pytest.mark.parametrize("name", BEYOND)
def test_records_beyond_the_domain(spark, wide, name):
    against_sql(spark, wide, name)


@pytest.mark.parametrize("name", READING)
def test_answers_follow_the_table(spark, sf, wide, name):
    """Other records, other answers."""
    assert against_sql(spark, wide, name) != against_sql(spark, sf, name)


@pytest.mark.parametrize("name", ["p_rstar_counts_density"])
def test_leaves_over_equal_points(spark, sf, tmp_path, name):
    """Three values make nine points: most leaves have the box of another one."""
    against_sql(spark, copied(sf, tmp_path, events="select * replace ((event_id % 3 * 40)::double as value) from events"), name)


@pytest.mark.parametrize("name", ["p_rstar_counts_density_n"])
def test_records_without_coordinates(spark, sf, tmp_path, name):
    against_sql(spark, copied(sf, tmp_path, events="select * replace (case when event_id % 7 > 0 then value end as value) from events"), name)


@pytest.mark.parametrize("name", ["p_rstar_reinsert"])
@pytest.mark.parametrize("users", [0, 1])
def test_hardly_any_records(spark, sf, tmp_path, name, users):
    """None, and two."""
    against_sql(spark, copied(sf, tmp_path, events=f"select * from events where user_id < {users} order by event_id limit 3"), name)


@pytest.mark.parametrize("name", ["p_rstar_reinsert"])
def test_tree_of_every_record(spark, sf, tmp_path, monkeypatch, name):
    """Also of more records than a driver grows a tree on."""
    from apcube.operators import index as core
    from apcube.queries import methods

    seen, indexed = [], methods.indexed
    monkeypatch.setattr(core, "MOST_SAMPLE", 100)
    monkeypatch.setattr(methods, "indexed", lambda *a, **k: seen.append(indexed(*a, **k)) or seen[-1])
    against_sql(spark, copied(sf, tmp_path), name)
    assert [ix.nodes.count[ix.leaves].sum() for ix in seen] == [985]


@pytest.mark.parametrize("name", ["p_rstar_counts_density"])
def test_a_tree_of_a_sample_shows(spark, sf, tmp_path, monkeypatch, name):
    """Leaves of a tree that was grown on fewer records are told, however many there are."""
    from apcube.operators import index as core
    from apcube.queries import methods

    indexed = methods.indexed
    monkeypatch.setattr(core, "MOST_SAMPLE", 100)
    monkeypatch.setattr(methods, "indexed", lambda *a, whole, **k: indexed(*a, **k))
    row = QUERIES[name](spark, copied(sf, tmp_path)).first()
    assert row["records"] == 985 and not row["whole_sample"]


def test_mode_at_the_edge_of_the_data(spark, sf, tmp_path):
    """Evenly spread totals, the lowest a little denser: the densest bin is the first, half an average bin from the edge."""
    every = "select i * 12 + m as o_orderkey, 0::bigint as o_custkey, 'O' as o_orderstatus, (1000 + i % 2000 * 249.5)::double as o_totalprice, make_timestamp(1995, m::bigint + 1, 1 + i::bigint % 28, 0, 0, 0.0) as o_orderdate, '1-URGENT' as o_orderpriority from range(2012) t(i), range(12) u(m)"
    against_sql(spark, copied(sf, tmp_path, orders=every), "d_mode_of_index")
