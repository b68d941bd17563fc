"""Queries of the baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from apcube.operators import baselines as base, index as core, measures, partitioners as parts
from apcube.plans.spec import Bins, Chart
from apcube.queries.methods import DENSE, HEAT, PLANE, PLANE_X, XY, _flat, on
from apcube.queries.registry import indexed, query
from apcube.sources.tables import VIEWS, view

CHECKIN = VIEWS["checkin"]

for _agg in ("count", "sum", "mean", "min", "max"):
    query(f"b_scan_{_agg}", on(HEAT, _agg).sql(PLANE_X))(lambda s, d, a=_agg: base.scan(view(s, d, "plane"), on(HEAT, a), "x"))


_PUSHED = Chart([Bins.width("qty", 10, 0, 60)], {"disc": (2, 6), "price": (20000, 60000)}, "sum")
query("b_scan_pushed", _PUSHED.sql(f"select *, ext as m from ({VIEWS['splom'].sql})"))(lambda s, d: base.scan(view(s, d, "splom", _PUSHED.where), _PUSHED, "ext"))
_PUSHED_HAIL = Chart([Bins.width("month", 1, 0, 12)], {"price": (50000, 200000), "cust": (1, 500)})
query("b_scan_pushed_orders", _PUSHED_HAIL.sql(VIEWS["hail"].sql))(lambda s, d: base.scan(view(s, d, "hail", _PUSHED_HAIL.where), _PUSHED_HAIL))


def _tree(spark, sf_dir):
    return base.tree_cube(view(spark, sf_dir, "checkin"), XY, 16, 8, "event_type", "hr", 6)


for _level in (2, 4, 6):
    query(f"b_tree_cube_level_{_level}", base.tree_cube_sql(PLANE.sql, XY, 16, _level, "hr", 6))(lambda s, d, level=_level: base.tree_cube_counts(_tree(s, d), level, 2))
query("b_tree_cube_category", base.tree_cube_sql(f"select * from ({PLANE.sql}) where event_type = 'view'", XY, 16, 3, "hr", 6))(lambda s, d: base.tree_cube_counts(_tree(s, d), 3, 2, "view"))


@query("b_pivot_cube", " union all ".join(f"select {level} as level, prefix, value from (select prefix, sum(value)::bigint as value from ({base.tree_cube_sql(PLANE.sql, XY, 16, level, 'hr', 24)}) group by all)" for level in range(5)))
def _(spark, sf_dir):
    """Counts of nodes as differences of places in the sorted array."""
    cube = base.pivot_cube(view(spark, sf_dir, "plane"), XY, 16, 4, ("event_id",))
    return cube.select("level", "prefix", (F.col("last") - F.col("first") + 1).cast("long").alias("value"))


query("b_tiles", base.tiles_sql(CHECKIN.sql, ("x", "y", "hr"), CHECKIN.widths, 24, 3))(lambda s, d: base.tiles(view(s, d, "checkin"), ("x", "y", "hr"), CHECKIN.widths, 24, 3))
_GROUPS, _BRUSHES = {"wd": 1, "hr": 1, "x": 7200, "t": 86400}, {"x": (7200, 14400), "wd": (0, 5), "hr": (6, 18)}
query("b_crossfilter", base.crossfilter_sql(CHECKIN.sql, _GROUPS, _BRUSHES))(lambda s, d: base.crossfilter(view(s, d, "checkin"), _GROUPS, _BRUSHES))


@query("b_data_cube", f"select region, nation, segment, grouping_id(region, nation, segment)::bigint as gid, count(*) as n, sum(total)::bigint as total from ({VIEWS['geo'].sql}) group by cube (region, nation, segment)")
def _(spark, sf_dir):
    g = view(spark, sf_dir, "geo")
    return g.cube("region", "nation", "segment").agg(F.grouping_id().cast("long").alias("gid"), F.count("*").alias("n"), F.sum("total").alias("total"))


@query("b_data_cube_lookup", f"select region, count(*) as n from ({VIEWS['geo'].sql}) where segment = 'BUILDING' group by all")
def _(spark, sf_dir):
    """A range answer from the conventional cube: all covered cells are read and added."""
    cube = view(spark, sf_dir, "geo").cube("region", "nation", "segment").agg(F.grouping_id().alias("gid"), F.count("*").alias("n"))
    return cube.where("gid = 0 and segment = 'BUILDING'").groupBy("region").agg(F.sum("n").alias("n"))


query("b_sat_fine", DENSE.sql(PLANE.sql))(lambda s, d: _flat(s, d, 100).chart(DENSE))


@query("b_sat_same_size", "select true as coarser_than_fine, true as same_size")
def _(spark, sf_dir):
    """A plain table with as many entries as the index's dense arrays; its error is the larger where data are dense."""
    ix = indexed(spark, sf_dir, "plane")
    n = max(2, round(ix.dense_entries() ** 0.5))
    cell = -(-57600 // n)
    flat = _flat(spark, sf_dir, cell)
    truth = base.scan(view(spark, sf_dir, "plane"), DENSE)
    a = measures.are(flat.chart(DENSE), truth, DENSE.names, 16).withColumnRenamed("are", "a")
    b = measures.are(_flat(spark, sf_dir, 100).chart(DENSE), truth, DENSE.names, 16).withColumnRenamed("are", "b")
    same = abs(flat.dense_entries() - ix.dense_entries()) <= 0.1 * ix.dense_entries()
    return a.crossJoin(b).select((F.col("a") >= F.col("b")).alias("coarser_than_fine"), F.lit(bool(same)).alias("same_size"))  # one row each


query("b_sample", base.sample_sql(PLANE.sql, HEAT, "event_id", 0.1))(lambda s, d: base.sample_chart(view(s, d, "plane"), HEAT, "event_id", 0.1))
query("b_haar", base.haar_sql(PLANE.sql, "x", 57600, 6, 12))(lambda s, d: base.haar(view(s, d, "plane"), "x", 57600, 6, 12))
_ODD = Chart([Bins.width("x", 5000, 0, 60000), Bins.width("y", 5000, 0, 60000)])
query("b_bucket_hist", base.bucket_spread_sql(PLANE.sql, _ODD, 7200))(lambda s, d: base.bucket_spread(view(s, d, "plane"), _ODD, 7200))
query("b_compressed_sat", f"select r.t::bigint as t, count(x) as value from range(8) r(t) left join ({PLANE.sql}) p on p.x // 7200 = r.t group by all")(lambda s, d: base.compressed_answers(base.compressed_prefix(view(s, d, "plane"), "x", 57600, 64), list(range(0, 65, 8))))
query("b_compressed_sat_rows", f"select count(distinct x * 64 // 57600) as stored from ({PLANE.sql})")(lambda s, d: base.compressed_prefix(view(s, d, "plane"), "x", 57600, 64).agg(F.count("*").alias("stored")))


def _chart_on(kind: str):
    def run(spark, sf_dir):
        from apcube.queries.methods import partition

        return indexed(spark, sf_dir, "plane", nodes=partition(spark, sf_dir, "plane", XY, kind), tag=kind).chart(HEAT)

    return run


for _kind in ("kd", "kdb", "quad", "uniform", "str", "area"):
    query(f"b_chart_{_kind}", HEAT.sql(PLANE.sql))(_chart_on(_kind))


@query("b_rtree_heights", " union all ".join(f"select {h} as height, * from ({HEAT.sql(PLANE.sql)})" for h in (1, 2, 3)))
def _(spark, sf_dir):
    """Tree descent without hashing, stopped at each height."""
    out = None
    for h in (1, 2, 3):
        level = indexed(spark, sf_dir, "plane").at_depth(h)
        one = level.chart(HEAT, leaves=level.candidates(HEAT)).select(F.lit(h).alias("height"), *HEAT.names, "value")
        out = one if out is None else out.union(one)
    return out


@query("b_global_bins", f"select month::bigint as t1, true as close from ({VIEWS['hail'].sql}) group by all")
def _(spark, sf_dir):
    from apcube.operators import histograms
    from apcube.queries.methods import MONTHS, _hist_index

    est = histograms.quantile(histograms.masses(_hist_index(spark, sf_dir, "global"), MONTHS, 32), 0.5, "t1")
    exact = view(spark, sf_dir, "hail").groupBy(F.col("month").alias("t1")).agg(F.expr("percentile(total, 0.5)").alias("e"))
    return exact.join(est, "t1", "left").select("t1", F.coalesce(F.abs(F.col("value") - F.col("e")) <= 3_000_000, F.lit(False)).alias("close"))


query("b_equi_width", Chart([Bins.width("x", 7200, 0, 57600)]).sql(PLANE.sql))(lambda s, d: _flat(s, d, 7200).chart(Chart([Bins.width("x", 7200, 0, 57600)])))
query("b_full_tree", HEAT.sql(PLANE.sql))(lambda s, d: core.build(view(s, d, "plane"), XY, PLANE.widths, "event_id", rate=1.0, grid_widths={"x": 7200, "y": 7200}).chart(HEAT))
query("b_uniform_counts", f"select part, count(*) as n from ({parts.uniform_sql(PLANE.sql, XY, PLANE.widths, 8)}) group by all")(lambda s, d: parts.uniform_parts(view(s, d, "plane"), XY, PLANE.widths, 8).groupBy("part").agg(F.count("*").alias("n")))
