"""Operators that a user of the index needs around it: sources, sinks, joins, aggregates, windows, sets and functions."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from apcube.functions.scale import morton
from apcube.operators import index as core, measures, prefix
from apcube.operators.baselines import scan
from apcube.operators.boxtree import Nodes
from apcube.plans.spec import Bins, Chart
from apcube.queries.methods import _MEET, BOXES, HEAT, LEAF4, LINE, PLANE, QBOXES, XY, _flat, _literal, _snap_sql, _values, tight, tight_sql
from apcube.queries.registry import indexed, query
from apcube.sources import store
from apcube.sources.tables import VIEWS, load, view


_SCRATCH: dict[str, str] = {}


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder that driver and executors share: in that of checkpoints where one is set, else in a temporary one in
    local mode (deleted when the process ends), else in the warehouse."""
    base, app = spark.conf.get("spark.checkpoint.dir", None), spark.sparkContext.applicationId
    if not base:
        if app not in _SCRATCH:
            if spark.sparkContext.master.startswith("local["):
                _SCRATCH[app] = tempfile.mkdtemp(prefix="apcube-")
                atexit.register(shutil.rmtree, _SCRATCH[app], True)
            else:
                _SCRATCH[app] = spark.conf.get("spark.sql.warehouse.dir")
        base = _SCRATCH[app]
    return f"{base.rstrip('/')}/apcube-scratch/{name}-{uuid.uuid4().hex[:10]}"


# ---- sources and sinks -------------------------------------------------------------------------------------------

query("src_parquet", "select o_orderstatus, count(*) as n from orders where o_totalprice > 100000 group by all")(lambda s, d: load(s, d, "orders").where("o_totalprice > 100000").groupBy("o_orderstatus").agg(F.count("*").alias("n")))
query("src_ntz_cast", "select event_id, floor(epoch(ts))::bigint as sec from events")(lambda s, d: load(s, d, "events").select("event_id", F.unix_timestamp("ts").alias("sec")))


@query("src_csv_json_orc", "select f.name as format, count(*) as n, sum(o_orderkey)::bigint as k, sum(round(o_totalprice * 100)::bigint)::bigint as cents from orders, (values ('csv'), ('json'), ('orc')) as f(name) group by all")
def _(spark, sf_dir):
    """Round trips through other formats with an explicit schema."""
    o, out = load(spark, sf_dir, "orders"), None
    for kind in ("csv", "json", "orc"):
        path = scratch(spark, kind)
        (o.write.option("header", True) if kind == "csv" else o.write).format(kind).save(path)
        back = spark.read.schema(o.schema).option("header", True).format(kind).load(path)
        one = back.agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("k"), F.sum(F.round(F.col("o_totalprice") * 100).cast("long")).alias("cents")).select(F.lit(kind).alias("format"), "n", "k", "cents")
        out = one if out is None else out.union(one)
    return out


@query("src_index_save_load", HEAT.sql(PLANE.sql))
def _(spark, sf_dir):
    path = scratch(spark, "index")
    store.save(indexed(spark, sf_dir, "plane"), path)
    return store.load(spark, path).chart(HEAT)


@query("src_datasource", LINE.sql(PLANE.sql))
def _(spark, sf_dir):
    """The saved index as a readable source: bins and ranges are options."""
    path = scratch(spark, "index")
    store.save(indexed(spark, sf_dir, "plane"), path)
    spark.dataSource.register(store.ChartSource)
    got = spark.read.format("apcube_chart").option("path", path).option("bins", "x:7200:0:57600").option("where", "y:0:7200").load()
    return got.groupBy("t1").agg(F.sum("value").cast("long").alias("value"))


@query("src_cache", HEAT.sql(PLANE.sql))
def _(spark, sf_dir):
    ix = indexed(spark, sf_dir, "plane")
    ix.cells.persist()
    return ix.chart(HEAT)


@query("snk_json_payload", f"select '{{\"t1\":' || t1 || ',\"value\":' || value || '}}' as json from ({LINE.sql(PLANE.sql)})")
def _(spark, sf_dir):
    return indexed(spark, sf_dir, "plane").chart(LINE).select(F.to_json(F.struct("t1", "value")).alias("json"))


@query("snk_partitioned", f"select x // 7200 as t1, count(*) as n from ({PLANE.sql}) where x < 28800 group by all")
def _(spark, sf_dir):
    """Cells partitioned by slab; an overwrite of two slabs leaves the others."""
    path = scratch(spark, "cells")
    cells = view(spark, sf_dir, "plane").where("x < 28800").groupBy(F.floor(F.col("x") / 7200).alias("t1"), F.floor(F.col("y") / 7200).alias("t2")).agg(F.count("*").alias("n"))
    cells.write.partitionBy("t1").parquet(path)
    cells.where("t1 in (0, 1)").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("t1").parquet(path)
    return spark.read.parquet(path).groupBy(F.col("t1").cast("long").alias("t1")).agg(F.sum("n").alias("n"))


# ---- projections and filters -------------------------------------------------------------------------------------

query("prj_scale_coords", "select event_id, round(value * 100)::bigint // 25 as s from events")(lambda s, d: load(s, d, "events").select("event_id", F.floor(F.round(F.col("value") * 100) / 25).cast("long").alias("s")))
query("prj_calendar", "select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, day(o_orderdate)::int as d, (isodow(o_orderdate) - 1)::int as wd, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as first from orders")(lambda s, d: load(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofmonth("o_orderdate").alias("d"), F.weekday("o_orderdate").alias("wd"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("first")))
query("flt_box", f"select event_id from ({PLANE.sql}) where x between 1000 and 5000 and y between 0 and 3000 and hr between 6 and 11")(lambda s, d: view(s, d, "plane").where("x between 1000 and 5000 and y between 0 and 3000 and hr between 6 and 11").select("event_id"))
query("flt_half_open", "select event_id from events where value >= 5 and value < 60")(lambda s, d: load(s, d, "events").where("value >= 5 and value < 60").select("event_id"))
query("flt_in_category", "select o_orderkey from orders where o_orderpriority in ('1-URGENT', '2-HIGH')")(lambda s, d: load(s, d, "orders").where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH")).select("o_orderkey"))
query("flt_multi_range", "select event_id from events where value < 5 or (value >= 50 and value < 60)")(lambda s, d: load(s, d, "events").where("value < 5 or (value >= 50 and value < 60)").select("event_id"))
query("flt_null_dim", "select count(*) filter (q is null) as null_rows, count(*) filter (q is not null) as in_range from (select quality as q from documents left join labels using (doc_id))")(lambda s, d: view(s, d, "docs").agg(F.count_if(F.col("quality").isNull()).alias("null_rows"), F.count_if(F.col("quality").isNotNull()).alias("in_range")))
query("flt_like_regex", "select p_partkey from part where p_name like '%a%' and regexp_matches(p_type, '^[A-Z]+')")(lambda s, d: load(s, d, "part").where(F.col("p_name").like("%a%") & F.col("p_type").rlike("^[A-Z]+")).select("p_partkey"))
query("flt_json_key", "select event_id from events where json_extract_string(props, '$.k')::int >= 90")(lambda s, d: load(s, d, "events").where(F.get_json_object("props", "$.k").cast("int") >= 90).select("event_id"))
query("flt_case_group", "select case when o_totalprice < 100000 then 'low' when o_totalprice < 300000 then 'mid' else 'high' end as g, count(*) as n from orders group by all")(lambda s, d: load(s, d, "orders").groupBy(F.when(F.col("o_totalprice") < 100000, "low").when(F.col("o_totalprice") < 300000, "mid").otherwise("high").alias("g")).agg(F.count("*").alias("n")))
query("prj_try_divide", "select event_type, round(sum(round(value * 100)::bigint) filter (value > 400)::double / nullif(count(*) filter (value > 400), 0), 4) as mean from events group by all")(lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.round(F.try_divide(F.sum(F.when(F.col("value") > 400, F.round(F.col("value") * 100).cast("long"))).cast("double"), F.count_if(F.col("value") > 400)), 4).alias("mean")))

# ---- joins -------------------------------------------------------------------------------------------------------

_STAR = "select r_name, c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by all"


@query("join_hash_star", _STAR)
def _(spark, sf_dir):
    o, c, n, r = (load(spark, sf_dir, t) for t in ("orders", "customer", "nation", "region"))
    j = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return j.groupBy("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


def _lines(hint: str):
    def run(spark, sf_dir):
        li, o = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders")
        return li.join(o.hint(hint), li.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"))

    return run


for _key, _hint in (("join_sort_merge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    query(_key, "select o_orderpriority, count(*) as n from lineitem join orders on l_orderkey = o_orderkey group by all")(_lines(_hint))
query("join_corner_lookup", HEAT.sql(PLANE.sql))(lambda s, d: prefix.corner_chart(prefix.sat(view(s, d, "plane"), {"x": 7200, "y": 7200}, {"x": 8, "y": 8}), XY, 1, 8))

_IN_BOX = f"select b.id as box, count(*) as n from ({PLANE.sql}), {_values(LEAF4, 'b')} where x between lo_x and hi_x and y between lo_y and hi_y group by all"


@query("join_box_contains", _IN_BOX)
def _(spark, sf_dir):
    """A theta join; the 16 literal boxes are broadcast."""
    b = F.broadcast(_literal(spark, LEAF4))
    return view(spark, sf_dir, "plane").join(b, (F.col("x") >= F.col("lo_x")) & (F.col("x") <= F.col("hi_x")) & (F.col("y") >= F.col("lo_y")) & (F.col("y") <= F.col("hi_y"))).groupBy(F.col("id").alias("box")).agg(F.count("*").alias("n"))


@query("join_box_contains_cell", _IN_BOX)
def _(spark, sf_dir):
    """The same as an equi-join on coarse cells: boxes are laid out over the cells that they cover."""
    cell = 3600
    b = _literal(spark, LEAF4)
    for d in XY:
        b = b.withColumn(f"g_{d}", F.explode(F.sequence(F.floor(F.col(f"lo_{d}") / cell), F.floor(F.col(f"hi_{d}") / cell))))
    p = view(spark, sf_dir, "plane").select("x", "y", *(F.floor(F.col(d) / cell).alias(f"g_{d}") for d in XY))
    return p.join(b, ["g_x", "g_y"]).where("x between lo_x and hi_x and y between lo_y and hi_y").groupBy(F.col("id").alias("box")).agg(F.count("*").alias("n"))


@query("join_box_overlap", f"select q.id as query, count(*) as n from {tight_sql(1800)} b, {tight_sql(9000)} q where {_MEET} group by all")
def _(spark, sf_dir):
    """A theta join of the boxes of records in small squares with those in large ones, which are few and broadcast."""
    b, q = tight(spark, sf_dir, 1800).alias("b"), F.broadcast(tight(spark, sf_dir, 9000).alias("q"))
    return b.join(q, F.expr(_MEET)).groupBy(F.col("q.id").alias("query")).agg(F.count("*").alias("n"))


_EDGES = [(0, 0, 500), (1, 500, 2000), (2, 2000, 8000), (3, 8000, 144000)]


@query("join_interval_bins", f"select e.t as t, count(*) as n from documents, (values {', '.join(map(str, _EDGES))}) as e(t, lo, hi) where n_chars >= lo and n_chars < hi group by all")
def _(spark, sf_dir):
    e = F.broadcast(spark.createDataFrame(_EDGES, "t int, lo bigint, hi bigint"))
    return load(spark, sf_dir, "documents").select("n_chars").join(e, (F.col("n_chars") >= F.col("lo")) & (F.col("n_chars") < F.col("hi"))).groupBy("t").agg(F.count("*").alias("n"))


_NEAREST = f"select box, count(*) as n from (select event_id, arg_min(b.id, (pow(greatest(lo_x - x, x - hi_x, 0)::bigint, 2) + pow(greatest(lo_y - y, y - hi_y, 0)::bigint, 2)) * 100 + b.id) as box from ({PLANE.sql}), {_values(LEAF4, 'b')} group by event_id) group by all"


@query("join_nearest", _NEAREST)
def _(spark, sf_dir):
    """The nearest of 16 literal boxes per point: the boxes are one array, no join is made."""
    boxes = F.array(*(F.struct(*(F.lit(v).alias(n) for v, n in zip(b, ("id", "lx", "ly", "hx", "hy")))) for b in LEAF4))
    gap = lambda b: F.pow(F.greatest(b["lx"] - F.col("x"), F.col("x") - b["hx"], F.lit(0)), 2.0) + F.pow(F.greatest(b["ly"] - F.col("y"), F.col("y") - b["hy"], F.lit(0)), 2.0)
    best = F.array_min(F.transform(boxes, lambda b: F.struct(gap(b).alias("d"), b["id"].alias("id"))))
    return view(spark, sf_dir, "plane").select(best["id"].alias("box")).groupBy("box").agg(F.count("*").alias("n"))


@query("join_asof", "select e.event_id, o.o_orderkey from (select *, date '1998-01-01' + (user_id % 500)::int as day from events) e asof left join (select o_orderkey, o_custkey, o_orderdate::date as day from (select *, row_number() over (partition by o_custkey, o_orderdate::date order by o_orderkey desc) as r from orders) where r = 1) o on e.user_id = o.o_custkey and e.day >= o.day")
def _(spark, sf_dir):
    """The customer's last order on or before a day: one window over the union, ordered by day with orders first."""
    e = load(spark, sf_dir, "events").select(F.col("user_id").alias("k"), F.date_add(F.lit("1998-01-01").cast("date"), (F.col("user_id") % 500).cast("int")).alias("day"), F.lit(1).alias("side"), "event_id", F.lit(None).cast("long").alias("o"))
    o = load(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").cast("date").alias("day"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("event_id"), F.col("o_orderkey").alias("o"))
    w = Window.partitionBy("k").orderBy("day", "side", "o").rowsBetween(Window.unboundedPreceding, 0)
    return e.union(o).withColumn("o_orderkey", F.last("o", True).over(w)).where("side = 1").select("event_id", "o_orderkey")


query("join_semi", "select count(*) as n from customer where c_custkey in (select o_custkey from orders where o_totalprice > 400000)")(lambda s, d: load(s, d, "customer").join(load(s, d, "orders").where("o_totalprice > 400000").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi").agg(F.count("*").alias("n")))
query("join_anti", "select count(*) as n from customer where c_custkey not in (select o_custkey from orders)")(lambda s, d: load(s, d, "customer").join(load(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").agg(F.count("*").alias("n")))
query("join_full_outer_are", measures.are_sql(_snap_sql(HEAT, 1700, "outer"), HEAT.sql(PLANE.sql), ["t1", "t2"], 64))(lambda s, d: measures.are(_flat(s, d, 1700).chart(HEAT, "outer"), scan(view(s, d, "plane"), HEAT), ["t1", "t2"], 64))


@query("join_cross_grid", f"with p as ({PLANE.sql}) select t1, t2, t1 * 7200 as lo_x, t2 * 7200 as lo_y from (select distinct x // 7200 as t1 from p where x is not null), (select distinct y // 7200 as t2 from p)")
def _(spark, sf_dir):
    """Every grid of the bins that hold records along x and along y, also those that hold none together."""
    p = view(spark, sf_dir, "plane")
    a, b = (p.select(F.expr(f"{d} div 7200").alias(t)).dropna().distinct() for d, t in (("x", "t1"), ("y", "t2")))
    return a.crossJoin(b).select("t1", "t2", (F.col("t1") * 7200).alias("lo_x"), (F.col("t2") * 7200).alias("lo_y"))  # bins x bins


@query("join_lateral", f"select query, t1, t2, value from (select q.id as query, c.*, row_number() over (partition by q.id order by value desc, t1, t2) as r from {_values(QBOXES, 'q')}, ({HEAT.sql(PLANE.sql)}) c where t1 * 7200 <= q.hi_x and t1 * 7200 + 7199 >= q.lo_x and t2 * 7200 <= q.hi_y and t2 * 7200 + 7199 >= q.lo_y) where r <= 2")
def _(spark, sf_dir):
    """The two fullest grids of each query box, by a lateral join."""
    _literal(spark, QBOXES).createOrReplaceTempView("apcube_q")
    indexed(spark, sf_dir, "plane").chart(HEAT).createOrReplaceTempView("apcube_c")
    return spark.sql("select q.id as query, c.* from apcube_q q join lateral (select t1, t2, value from apcube_c where t1 * 7200 <= q.hi_x and t1 * 7200 + 7199 >= q.lo_x and t2 * 7200 <= q.hi_y and t2 * 7200 + 7199 >= q.lo_y order by value desc, t1, t2 limit 2) c")


_BANDS = f"(select (x // 9000) * 7 + wd as id, min(x) as lo_x, min(y) as lo_y, max(x) as hi_x, max(y) as hi_y from ({PLANE.sql}) where x is not null group by 1)"
_BOTH = "a.id < b.id and a.lo_x <= b.hi_x and a.hi_x >= b.lo_x and a.lo_y <= b.hi_y and a.hi_y >= b.lo_y"


@query("join_self_overlap", f"select count(*) as pairs from {_BANDS} a, {_BANDS} b where {_BOTH}")
def _(spark, sf_dir):
    """Pairs of meeting boxes among those of the records of each band of x on each day of the week."""
    records = view(spark, sf_dir, "plane").where("x is not null").withColumn("id", F.expr("(x div 9000) * 7 + wd"))
    boxes = records.groupBy("id").agg(*(f(d).alias(f"{p}_{d}") for p, f in (("lo", F.min), ("hi", F.max)) for d in XY))
    return boxes.alias("a").join(F.broadcast(boxes.alias("b")), F.expr(_BOTH)).agg(F.count("*").alias("pairs"))

# ---- aggregates --------------------------------------------------------------------------------------------------

query("agg_hash_partial_final", f"select x // 1800 as q1, y // 1800 as q2, count(*) as n, sum(x)::bigint as s from ({PLANE.sql}) group by all")(lambda s, d: view(s, d, "plane").groupBy(F.floor(F.col("x") / 1800).cast("long").alias("q1"), F.floor(F.col("y") / 1800).cast("long").alias("q2")).agg(F.count("*").alias("n"), F.sum("x").alias("s")))
query("agg_sort", "select user_id, array_to_string(list_sort(list(distinct event_type)), ',') as kinds from events group by all")(lambda s, d: load(s, d, "events").groupBy("user_id").agg(F.array_join(F.sort_array(F.collect_set("event_type")), ",").alias("kinds")))
query("agg_distinct", "select event_type, count(distinct user_id) as users from events group by all")(lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users")))
query("agg_approx_distinct", "select event_type, true as close from events group by all")(lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("n"), F.approx_count_distinct("user_id", 0.02).alias("a")).select("event_type", (F.abs(F.col("a") - F.col("n")) <= 0.1 * F.col("n") + 1).alias("close")))
_GEO = VIEWS["geo"].sql
query("agg_grouping_sets", f"select region, segment, grouping_id(region, segment)::bigint as gid, count(*) as n from ({_GEO}) group by grouping sets ((region, segment), (region), ())")(lambda s, d: _grouping(s, d))


def _grouping(spark, sf_dir):
    view(spark, sf_dir, "geo").createOrReplaceTempView("apcube_geo")
    return spark.sql("select region, segment, cast(grouping_id() as bigint) as gid, count(*) as n from apcube_geo group by grouping sets ((region, segment), (region), ())")


query("agg_cube", f"select region, segment, grouping_id(region, segment)::bigint as gid, sum(total)::bigint as s from ({_GEO}) group by cube (region, segment)")(lambda s, d: view(s, d, "geo").cube("region", "segment").agg(F.grouping_id().cast("long").alias("gid"), F.sum("total").alias("s")))
query("agg_rollup", f"select region, nation, grouping_id(region, nation)::bigint as gid, count(*) as n, sum(total)::bigint as s from ({_GEO}) group by rollup (region, nation)")(lambda s, d: view(s, d, "geo").rollup("region", "nation").agg(F.grouping_id().cast("long").alias("gid"), F.count("*").alias("n"), F.sum("total").alias("s")))
query("agg_filter_clause", "select o_orderstatus, count(*) filter (o_totalprice > 250000) as big, count(*) as n from orders group by all")(lambda s, d: load(s, d, "orders").groupBy("o_orderstatus").agg(F.count_if(F.col("o_totalprice") > 250000).alias("big"), F.count("*").alias("n")))
query("agg_pivot", "select l_returnflag, count(*) filter (l_linestatus = 'F') as f, count(*) filter (l_linestatus = 'O') as o from lineitem group by all")(lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o")))
query("agg_stddev_var_corr", "select o_orderstatus, round(stddev_samp(o_totalprice), 2) as sd, round(corr(o_totalprice, o_custkey), 4) as c from orders group by all")(lambda s, d: load(s, d, "orders").groupBy("o_orderstatus").agg(F.round(F.stddev_samp("o_totalprice"), 2).alias("sd"), F.round(F.corr("o_totalprice", "o_custkey"), 4).alias("c")))
query("agg_percentile_exact", "select o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) as med, round(quantile_cont(o_totalprice, 0.9), 4) as p90 from orders group by all")(lambda s, d: load(s, d, "orders").groupBy("o_orderstatus").agg(F.round(F.expr("percentile(o_totalprice, 0.5)"), 4).alias("med"), F.round(F.expr("percentile(o_totalprice, 0.9)"), 4).alias("p90")))
query("agg_percentile_approx", "select o_orderstatus, true as close from orders group by all")(lambda s, d: load(s, d, "orders").groupBy("o_orderstatus").agg(F.expr("percentile(o_totalprice, 0.5)").alias("e"), F.percentile_approx("o_totalprice", 0.5, 1000).alias("a")).select("o_orderstatus", (F.abs(F.col("a") - F.col("e")) <= 20000).alias("close")))
query("agg_histogram_numeric")(lambda s, d: load(s, d, "orders").groupBy("o_orderstatus").agg(F.size(F.histogram_numeric("o_totalprice", F.lit(8))).alias("bins")))
query("agg_kll", "select o_orderstatus, true as close from orders group by all")(lambda s, d: load(s, d, "orders").groupBy("o_orderstatus").agg(F.expr("percentile(o_totalprice, 0.5)").alias("e"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(o_totalprice), 0.5d)").alias("a")).select("o_orderstatus", (F.abs(F.col("a") - F.col("e")) <= 25000).alias("close")))
query("agg_min_max_by", "select user_id, arg_min(event_id, value * 1000000 + event_id) as least, arg_max(event_id, value * 1000000 + event_id) as most from events group by all")(lambda s, d: load(s, d, "events").groupBy("user_id").agg(F.min_by("event_id", F.col("value") * 1000000 + F.col("event_id")).alias("least"), F.max_by("event_id", F.col("value") * 1000000 + F.col("event_id")).alias("most")))
query("agg_first_last_ordered", "select user_id, first(event_id order by ts, event_id) as f, last(event_id order by ts, event_id) as l from events group by all")(lambda s, d: load(s, d, "events").groupBy("user_id").agg(F.min(F.struct("ts", "event_id")).alias("a"), F.max(F.struct("ts", "event_id")).alias("b")).select("user_id", F.col("a.event_id").alias("f"), F.col("b.event_id").alias("l")))
query("agg_bool", "select user_id, bool_and(value > 1) as every_one, bool_or(value > 200) as some_one from events group by all")(lambda s, d: load(s, d, "events").groupBy("user_id").agg(F.bool_and(F.col("value") > 1).alias("every_one"), F.bool_or(F.col("value") > 200).alias("some_one")))
query("agg_mode", "select l_returnflag, min(q) as mode from (select l_returnflag, l_quantity as q, count(*) as n, max(count(*)) over (partition by l_returnflag) as m from lineitem group by 1, 2) where n = m group by 1")(lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(F.mode("l_quantity", True).alias("mode")))
query("agg_weekday_hour", "select isodow(ts) - 1 as wd, hour(ts) as hr, count(*) as n from events group by all")(lambda s, d: load(s, d, "events").groupBy(F.weekday("ts").cast("long").alias("wd"), F.hour("ts").cast("long").alias("hr")).agg(F.count("*").alias("n")))
query("agg_having", "select user_id, count(*) as n from events group by all having count(*) > 70")(lambda s, d: load(s, d, "events").groupBy("user_id").agg(F.count("*").alias("n")).where("n > 70"))

# ---- windows -----------------------------------------------------------------------------------------------------

query("win_prefix_1d", f"select t1, sum(value) over (order by t1)::bigint as upto from ({LINE.sql(PLANE.sql)})")(lambda s, d: indexed(s, d, "plane").chart(LINE).select("t1", F.sum("value").over(Window.orderBy("t1").rowsBetween(Window.unboundedPreceding, 0)).alias("upto")))
query("win_prefix_2d", f"select a.t1, a.t2, sum(b.value)::bigint as upto from ({HEAT.sql(PLANE.sql)}) a join ({HEAT.sql(PLANE.sql)}) b on b.t1 <= a.t1 and b.t2 <= a.t2 group by all")(lambda s, d: _prefix_of_chart(s, d))


def _prefix_of_chart(spark, sf_dir):
    table = prefix.sat(view(spark, sf_dir, "plane"), {"x": 7200, "y": 7200}, {"x": 8, "y": 8})
    return indexed(spark, sf_dir, "plane").chart(HEAT).join(table.withColumnsRenamed({"q_x": "t1", "q_y": "t2"}), ["t1", "t2"]).select("t1", "t2", "upto")


query("win_prefix_3d", f"with c as (select qty // 10 as a, disc // 4 as b, tax // 5 as c, count(*) as n from ({VIEWS['splom'].sql}) group by all) select x.a::bigint as a, x.b::bigint as b, x.c::bigint as c, (select sum(n) from c where c.a <= x.a and c.b <= x.b and c.c <= x.c)::bigint as upto from c x")(lambda s, d: _prefix3(s, d))


def _prefix3(spark, sf_dir):
    table = prefix.sat(view(spark, sf_dir, "splom"), {"qty": 10, "disc": 4, "tax": 5}, {"qty": 6, "disc": 3, "tax": 2})
    there = view(spark, sf_dir, "splom").select(*(F.floor(F.col(d) / w).cast("long").alias(f"q_{d}") for d, w in (("qty", 10), ("disc", 4), ("tax", 5)))).distinct()
    return table.join(there, ["q_qty", "q_disc", "q_tax"], "left_semi").select(F.col("q_qty").alias("a"), F.col("q_disc").alias("b"), F.col("q_tax").alias("c"), "upto")


query("win_difference_lag", f"select x // 7200 as t1, count(*) as value from ({PLANE.sql}) group by all")(lambda s, d: _lagged(s, d))


def _lagged(spark, sf_dir):
    table = prefix.sat(view(spark, sf_dir, "plane"), {"x": 7200}, {"x": 8})
    return table.select(F.col("q_x").alias("t1"), (F.col("upto") - F.lag("upto", 1, 0).over(Window.orderBy("q_x"))).alias("value")).where("value <> 0")


_USER = "(partition by user_id order by ts, event_id"
query("win_lead_next_value", f"select event_id, lead(round(value * 100)::bigint) over {_USER}) as nxt from events")(lambda s, d: load(s, d, "events").select("event_id", F.lead(F.round(F.col("value") * 100).cast("long")).over(_user()).alias("nxt")))


def _user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


query("win_row_number_topk", "select user_id, event_id from (select *, row_number() over (partition by user_id order by value desc, event_id) as r from events) where r <= 3")(lambda s, d: load(s, d, "events").withColumn("r", F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id"))).where("r <= 3").select("user_id", "event_id"))
query("win_rank_dense_ntile_percent_cume", "select o_orderkey, ntile(8) over w as bucket, rank() over w as r, dense_rank() over w as dr, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from orders window w as (partition by o_orderstatus order by o_totalprice, o_orderkey)")(lambda s, d: _ranks(s, d))


def _ranks(spark, sf_dir):
    w = Window.partitionBy("o_orderstatus").orderBy("o_totalprice", "o_orderkey")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.ntile(8).over(w).alias("bucket"), F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


query("win_rows_moving_avg", f"select event_id, round(avg(round(value * 100)::bigint) over {_USER} rows between 4 preceding and current row), 4) as avg5 from events")(lambda s, d: load(s, d, "events").select("event_id", F.round(F.avg(F.round(F.col("value") * 100).cast("long")).over(_user().rowsBetween(-4, 0)), 4).alias("avg5")))
query("win_range_interval", "select event_id, count(*) over (partition by user_id order by floor(epoch(ts))::bigint range between 604800 preceding and current row) as week from events")(lambda s, d: load(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-604800, 0)).alias("week")))
query("win_first_last_nth", f"select event_id, first_value(event_id) over w as f, last_value(event_id) over w as l, nth_value(event_id, 2) over w as n2 from events window w as {_USER} rows between unbounded preceding and unbounded following)")(lambda s, d: _firsts(s, d))


def _firsts(spark, sf_dir):
    w = _user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, sf_dir, "events").select("event_id", F.first("event_id").over(w).alias("f"), F.last("event_id").over(w).alias("l"), F.nth_value("event_id", 2).over(w).alias("n2"))


query("win_share_of_total", f"select t1, round(value::double / sum(value) over (), 6) as share from ({LINE.sql(PLANE.sql)})")(lambda s, d: indexed(s, d, "plane").chart(LINE).select("t1", F.round(F.col("value") / F.sum("value").over(Window.partitionBy(F.lit(0))), 6).alias("share")))

# ---- order, limit, sets ------------------------------------------------------------------------------------------

query("ord_global", "select o_orderkey, row_number() over (order by o_totalprice desc, o_orderkey) as place from orders qualify place <= 100")(lambda s, d: load(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100).select("o_orderkey", F.row_number().over(Window.orderBy(F.desc("o_totalprice"), "o_orderkey")).cast("long").alias("place")))
query("ord_within", "select o_custkey, count(*) as n from orders group by all")(lambda s, d: load(s, d, "orders").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderdate").groupBy("o_custkey").agg(F.count("*").alias("n")))
query("ord_topk_cells", f"select * from ({HEAT.sql(PLANE.sql)}) order by value desc, t1, t2 limit 5")(lambda s, d: indexed(s, d, "plane").chart(HEAT).orderBy(F.desc("value"), "t1", "t2").limit(5))
query("ord_limit_offset", "select o_orderkey from orders order by o_orderkey limit 50 offset 25")(lambda s, d: load(s, d, "orders").orderBy("o_orderkey").offset(25).limit(50).select("o_orderkey"))
query("ord_zorder", f"select count(*) as n, max(x)::bigint as mx from ({PLANE.sql})")(lambda s, d: view(s, d, "plane").withColumn("z", morton([F.col("x"), F.col("y")], 16)).repartitionByRange(8, "z").sortWithinPartitions("z").agg(F.count("*").alias("n"), F.max("x").alias("mx")))
_HI, _LO = "select user_id from events where value > 150", "select user_id from events where value < 5"


def _sides(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.where("value > 150").select("user_id"), e.where("value < 5").select("user_id")


for _key, _sql, _op in (
    ("set_union_all", f"{_HI} union all {_LO}", lambda a, b: a.union(b)),
    ("set_union_distinct", f"{_HI} union {_LO}", lambda a, b: a.union(b).distinct()),
    ("set_intersect", f"{_HI} intersect {_LO}", lambda a, b: a.intersect(b)),
    ("set_intersect_all", f"{_HI} intersect all {_LO}", lambda a, b: a.intersectAll(b)),
    ("set_except", f"{_HI} except {_LO}", lambda a, b: a.subtract(b)),
    ("set_except_all", f"{_HI} except all {_LO}", lambda a, b: a.exceptAll(b)),
):
    query(_key, _sql)(lambda s, d, op=_op: op(*_sides(s, d)))

# ---- functions ---------------------------------------------------------------------------------------------------

query("fn_math_scale", "select event_id, floor(value)::bigint as f, ceil(value)::bigint as c, floor(log10(value + 1) * 2)::bigint as l, (event_id * 7) % 5 as m from events")(lambda s, d: load(s, d, "events").select("event_id", F.floor("value").alias("f"), F.ceil("value").alias("c"), F.floor(F.log10(F.col("value") + 1) * 2).alias("l"), F.pmod(F.col("event_id") * 7, F.lit(5)).alias("m")))
_Z = " | ".join(f"(((x >> {b}) & 1)::bigint << {2 * b + 1}) | (((y >> {b}) & 1)::bigint << {2 * b})" for b in range(16))
query("fn_morton", f"select event_id, {_Z} as z from ({PLANE.sql})")(lambda s, d: view(s, d, "plane").select("event_id", morton([F.col("x"), F.col("y")], 16).alias("z")))
query("fn_width_bucket_closed", "select l_quantity as q, least(floor((l_quantity - 1) / 7) + 1, 7)::bigint as b from lineitem group by all")(lambda s, d: load(s, d, "lineitem").select(F.col("l_quantity").alias("q"), F.least(F.width_bucket("l_quantity", F.lit(1.0), F.lit(50.0), F.lit(7)), F.lit(7).cast("long")).alias("b")).distinct())
query("fn_date_parts", "select event_id, floor(epoch(ts))::bigint // 3600 as h, strftime(ts + interval 36 hour, '%Y-%m-%d') as later from events")(lambda s, d: load(s, d, "events").select("event_id", F.floor(F.unix_timestamp("ts") / 3600).alias("h"), F.date_format(F.col("ts") + F.expr("make_interval(0, 0, 0, 1, 12)"), "yyyy-MM-dd").alias("later")))
query("fn_string_url", "select page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, lower(substr(url, 1, 7)) as head, length(url)::int as n from pages")(lambda s, d: load(s, d, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.lower(F.substring("url", 1, 7)).alias("head"), F.length("url").alias("n")))
query("fn_array_prefix", f"select array_to_string(list(upto order by t1), ',') as sums from (select t1, sum(value) over (order by t1)::bigint as upto from ({LINE.sql(PLANE.sql)}))")(lambda s, d: _array_prefix(s, d))


def _array_prefix(spark, sf_dir):
    values = indexed(spark, sf_dir, "plane").chart(LINE).agg(F.array_sort(F.collect_list(F.struct("t1", "value"))).alias("a"))
    sums = F.transform("a", lambda x, i: F.aggregate(F.slice(F.col("a"), F.lit(1), i + 1), F.lit(0).cast("long"), lambda t, v: t + v["value"]))
    return values.select(F.array_join(F.transform(sums, lambda x: x.cast("string")), ",").alias("sums"))


query("fn_map_hist", "select user_id, event_type as k, count(*) as v from events group by all")(lambda s, d: _map_hist(s, d))


def _map_hist(spark, sf_dir):
    """Sparse histograms as maps, merged and laid out again."""
    e = load(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = e.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("h"))
    return maps.select("user_id", F.explode(F.transform_values("h", lambda k, v: v)).alias("k", "v"))


query("fn_json_props", "select json_extract_string(props, '$.k')::int as k, count(*) as n from events group by all")(lambda s, d: load(s, d, "events").select(F.from_json("props", "k int").alias("p")).groupBy("p.k").agg(F.count("*").alias("n")))
query("fn_variant", "select json_extract_string(props, '$.k')::int as k, count(*) as n from events group by all")(lambda s, d: load(s, d, "events").select(F.try_variant_get(F.parse_json("props"), "$.k", "int").alias("k")).groupBy("k").agg(F.count("*").alias("n")))

# ---- user-defined functions --------------------------------------------------------------------------------------

query("udf_assign_leaf", f"select b.id as leaf, count(*) as n from ({PLANE.sql}), {_values(BOXES, 'b')} where x between lo_x and hi_x and y between lo_y and hi_y group by all")(lambda s, d: _udf_assign(s, d))


def _udf_assign(spark, sf_dir):
    a = np.array(BOXES)

    @F.arrow_udf("int")
    def leaf(x: pa.Array, y: pa.Array) -> pa.Array:
        return pa.array(core.locate(np.stack([x.to_numpy(), y.to_numpy()], axis=1), a[:, 1:3], a[:, 3:5], np.array([57600.0, 57600.0])).astype(np.int32))

    return view(spark, sf_dir, "plane").select(leaf("x", "y").alias("leaf")).groupBy("leaf").agg(F.count("*").alias("n"))


@query("udf_hist_quantile", f"select x // 14400 as t1, true as ordered from ({PLANE.sql}) group by all")
def _(spark, sf_dir):
    """Quantiles of array histograms in a vectorised function."""
    @F.pandas_udf("double")
    def median(h: pd.Series) -> pd.Series:
        def one(v):
            total, run = sum(v), 0
            for i, n in enumerate(v):
                if n and run + n >= total / 2:
                    return i + (total / 2 - run) / n
                run += n
            return float("nan")

        return h.map(one).astype(float)

    b = view(spark, sf_dir, "plane").groupBy(F.floor(F.col("x") / 14400).cast("long").alias("t1")).pivot("hr", list(range(24))).count().fillna(0)
    return b.select("t1", median(F.array(*(F.col(str(i)) for i in range(24)))).between(0, 24).alias("ordered"))


@query("udaf_grouped_hist", f"select event_type, count(*) filter (x < 14400) as a, count(*) filter (x >= 14400) as b from ({PLANE.sql}) group by all")
def _(spark, sf_dir):
    """A grouped aggregate in pandas over cells, which are few, rather than over records."""
    cells = view(spark, sf_dir, "plane").groupBy("event_type", F.floor(F.col("x") / 14400).alias("q")).agg(F.count("*").alias("n"))

    @F.pandas_udf("array<bigint>")
    def halves(q: pd.Series, n: pd.Series) -> list:
        return [int(n[q == 0].sum()), int(n[q > 0].sum())]

    return cells.groupBy("event_type").agg(halves("q", "n").alias("h")).select("event_type", F.col("h")[0].alias("a"), F.col("h")[1].alias("b"))


@query("udtf_range_agg", f"select count(*) as value from ({PLANE.sql}) where x >= 0 and x < 14400 and y >= 0 and y < 7200")
def _(spark, sf_dir):
    """SELECT * FROM range_agg(TABLE(cells), ...): a table function over the index's cells."""
    store.register_functions(spark)
    indexed(spark, sf_dir, "plane").cells.select("q_x", "c_x", "q_y", "c_y", F.col("n").cast("long").alias("n")).createOrReplaceTempView("apcube_cells")
    return spark.sql("select cast(sum(value) as bigint) as value from range_agg(table(apcube_cells), 0, 14400, 0, 7200)")


@query("udtf_grid_cells", "select i as t1, i * 7200 as lo, i * 7200 + 7200 as hi from range(8) t(i)")
def _(spark, sf_dir):
    store.register_functions(spark)
    return spark.sql("select * from grid_cells(0, 57600, 7200)")


@query("map_in_arrow_assign", _IN_BOX.replace("as box", "as leaf"))
def _(spark, sf_dir):
    a = np.array(LEAF4)
    n = Nodes.of_boxes(a[:, 1:3], a[:, 3:5], np.zeros(16, int))
    got = core.assign(view(spark, sf_dir, "plane").select("x", "y"), XY, n, n.leaves, np.array([57600.0, 57600.0]))
    boxes = spark.createDataFrame(LEAF4, "leaf int, lo_x bigint, lo_y bigint, hi_x bigint, hi_y bigint")
    return got.join(F.broadcast(boxes), "leaf").where("x between lo_x and hi_x and y between lo_y and hi_y").groupBy("leaf").agg(F.count("*").alias("n"))


query("apply_in_arrow_prefix", LINE.sql(PLANE.sql))(lambda s, d: indexed(s, d, "plane", measure="x").chart_prefix(LINE))


@query("cogroup_arrow_merge", f"select x // 7200 as q, count(*) as n from ({PLANE.sql}) group by all")
def _(spark, sf_dir):
    """Old cells and a batch's cells merged group by group."""
    def cells(df: DataFrame) -> DataFrame:
        return df.groupBy(F.floor(F.col("x") / 7200).cast("long").alias("q")).agg(F.count("*").alias("n"))

    def merge(old: pa.Table, new: pa.Table) -> pa.Table:
        q = (old if old.num_rows else new).column("q")[0].as_py()
        return pa.table([[q], [sum(old.column("n").to_pylist()) + sum(new.column("n").to_pylist())]], ["q", "n"])

    p = view(spark, sf_dir, "plane")
    return cells(p.where("event_id % 3 <> 0")).groupBy("q").cogroup(cells(p.where("event_id % 3 = 0")).groupBy("q")).applyInArrow(merge, "q bigint, n bigint")
