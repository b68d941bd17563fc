"""The experiment workloads on the given tables.

Charts on aligned bins are compared with SQL row by row. Approximate arms return what SQL can state: the exact value and
whether bounds or error limits hold. Tables of times, sizes and errors have no SQL; ``bench.py`` and the README quote them.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from apcube.functions.scale import sampled
from apcube.operators import baselines as base, boxtree, histograms, index as core, lsh, measures
from apcube.operators.explore import explore
from apcube.plans.spec import Bins, Chart
from apcube.queries import methods as m
from apcube.queries.registry import INDEXED, boxes_of, indexed, kept, measured, query
from apcube.queries.surroundings import scratch
from apcube.sources.tables import VIEWS, load, view

PLANE, CHECKIN, SPLOM, DELAY, HAIL, DOCS = (VIEWS[v] for v in ("plane", "checkin", "splom", "delay", "hail", "docs"))
REGIONS = {"global": (0, 57600, 7200), "dense": (0, 3200, 800), "sparse": (12800, 25600, 3200)}


def union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def region_chart(name: str, agg: str = "count") -> Chart:
    lo, hi, w = REGIONS[name]
    return Chart([Bins.width("x", w, lo, hi), Bins.width("y", w, lo, hi)], agg=agg)


# ---- bins and dimensions of the scatterplot matrix ---------------------------------------------------------------

_SPLOM_HEAT = Chart([Bins.width("qty", 10, 0, 60), Bins.width("price", 10800, 0, 108000)])
for _b in (10, 20, 30, 40, 50):
    query(f"w01_splom_bins_{_b}", _SPLOM_HEAT.sql(SPLOM.sql))(lambda s, d, b=_b: indexed(s, d, "splom", bins=b, rate=0.1, leaves=32).chart(_SPLOM_HEAT))
for _k in range(1, 6):
    _dims = ("qty", "price", "disc", "tax", "day")[:_k]
    _chart = _SPLOM_HEAT if _k > 1 else Chart([Bins.width("qty", 10, 0, 60)])
    query(f"w02_splom_dims_{_k}", _chart.sql(SPLOM.sql))(lambda s, d, dims=_dims, c=_chart: indexed(s, d, "splom", dims=dims, bins=30, rate=0.1, leaves=32).chart(c))

SCATTER = "dimensions int, bins int, share double, records bigint, cells bigint, dense_entries bigint, bytes_on_disk bigint, build_seconds double, response_ms double"


def scatter_row(spark, sf_dir, dims: tuple[str, ...], bins: int, share: float, disk: bool = True) -> tuple:
    """Storage, construction time and response time of the scatterplot matrix's index over a share of the records."""
    df, w = view(spark, sf_dir, "splom"), SPLOM.widths
    part = df.where(sampled(F.col("l_orderkey"), share)) if share < 1 else df
    seconds, ix = measures.timed(lambda: core.build(part, dims, w, "l_orderkey", bins=bins, rate=0.1, leaves=32, grid_widths={d: INDEXED["splom"][2][d] for d in dims}))
    chart = _SPLOM_HEAT if len(dims) > 1 else Chart([Bins.width("qty", 10, 0, 60)])
    n, cells = (int(x or 0) for x in ix.cells.agg(F.sum("n"), F.count("*")).first())
    ms = min(measures.timed(lambda: ix.chart(chart).collect())[0] for _ in range(2)) * 1000
    row = (len(dims), bins, share, n, cells, ix.dense_entries(), m.stored_bytes(spark, ix) if disk else 0, round(seconds, 3), round(ms, 1))
    ix.cells.unpersist()
    return row


@query("w01_scatter_bins")
def _(spark, sf_dir):
    """Five dimensions, bins 10 to 50, against the number of records."""
    return spark.createDataFrame([scatter_row(spark, sf_dir, INDEXED["splom"][0], b, share) for b in (10, 20, 30, 40, 50) for share in (0.25, 1.0)], SCATTER)


@query("w02_scatter_dims")
def _(spark, sf_dir):
    """30 bins, one to five dimensions, against the number of records."""
    return spark.createDataFrame([scatter_row(spark, sf_dir, INDEXED["splom"][0][:k], 30, share) for k in range(1, 6) for share in (0.25, 1.0)], SCATTER)


@query("w01_scatter_trend", f"select 'bins' as parameter, count(*) as records, true as never_less, true as drives_storage from ({SPLOM.sql}) union all select 'dimensions', count(*), true, true from ({SPLOM.sql})")
def _(spark, sf_dir):
    """Cells never get fewer with bins or dimensions, and the last of a series has more than the first."""
    dims, out = INDEXED["splom"][0], []
    series = {"bins": [(dims, b) for b in (10, 30, 50)], "dimensions": [(dims[:k], 30) for k in (1, 3, 5)]}
    for name, runs in series.items():
        rows = [scatter_row(spark, sf_dir, d, b, 1.0, disk=False) for d, b in runs]
        cells = [r[4] for r in rows]
        out.append((name, rows[-1][3], cells == sorted(cells), cells[-1] > cells[0] or name == "bins" and cells[-1] == rows[-1][3]))
    return spark.createDataFrame(out, "parameter string, records bigint, never_less boolean, drives_storage boolean")


CARDS = {"splom_10": ("splom", 0.02, 10), "splom_50": ("splom", 0.02, 50), "checkin": ("checkin", 0.2, 60), "delay": ("delay", 0.05, 60), "plane": ("plane", 1.0, 60), "gps": ("gps", 0.01, 60), "gps_views": ("gps", 0.02, 60), "hail": ("hail", 0.01, 60), "vec": ("vec", 0.2, 60)}


def card_view(spark, sf_dir, name: str):
    df = view(spark, sf_dir, CARDS[name][0])
    return df.where("event_type = 'view'") if name == "gps_views" else df


@query("w03_index_card")
def _(spark, sf_dir):
    rows = []
    for name, (v, rate, bins) in CARDS.items():
        df = card_view(spark, sf_dir, name)
        n = df.count()
        seconds, ix = measures.timed(lambda: core.build(df, INDEXED[v][0], VIEWS[v].widths, INDEXED[v][1], bins=bins, rate=max(rate, min(1.0, 500 / max(n, 1))), leaves=64, grid_widths=INDEXED[v][2]))  # noqa: B023
        rows.append((*m.card(name, ix, seconds), n, m.stored_bytes(spark, ix)))
        ix.cells.unpersist()
    return spark.createDataFrame(rows, m.CARD + ", records bigint, bytes_on_disk bigint")


_CARD_SQL = {name: f"select * from ({VIEWS[v].sql})" + (" where event_type = 'view'" if name == "gps_views" else "") for name, (v, _, _) in CARDS.items()}


@query("w03_card_records", " union all ".join(f"select '{n}' as dataset, {len(INDEXED[CARDS[n][0]][0])} as dimensions, count(*) as records from ({q})" for n, q in _CARD_SQL.items()))
def _(spark, sf_dir):
    """What the nine builds hold: every record once."""
    out = []
    for name, (v, rate, bins) in CARDS.items():
        df = card_view(spark, sf_dir, name)
        ix = core.build(df, INDEXED[v][0], VIEWS[v].widths, INDEXED[v][1], bins=bins, rate=max(rate, 0.1), leaves=16, grid_widths=INDEXED[v][2])
        out.append(ix.cells.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("records")).select(F.lit(name).alias("dataset"), F.lit(len(ix.dims)).alias("dimensions"), "records"))
    return union(out)


def growth(spark, sf_dir, name: str) -> DataFrame:
    """Cells, dense entries and seconds after each tenth of the records; the tree is grown on the first share and then
    frozen, so later records only fill cells."""
    dims, key, grid = INDEXED[name]
    df = view(spark, sf_dir, name)
    rows, nodes = [], None
    for tenth in (1, 2, 4, 6, 8, 10):
        part = df.where(sampled(F.col(key), tenth / 10))
        seconds, ix = measures.timed(lambda: core.build(part, dims, VIEWS[name].widths, key, bins=16, rate=0.5 if nodes is None else 1.0, leaves=48, grid_widths=grid, nodes=nodes))  # noqa: B023
        nodes = nodes or ix.nodes
        rows.append((tenth / 10, int(ix.cells.agg(F.sum("n")).first()[0] or 0), ix.cells.count(), ix.dense_entries(), round(seconds, 3)))
        ix.cells.unpersist()
    return spark.createDataFrame(rows, "inserted double, records bigint, cells bigint, dense_entries bigint, seconds double")


for _v in ("plane", "checkin", "delay"):
    query(f"w04_growth_{_v}")(lambda s, d, v=_v: growth(s, d, v))


@query("w04_growth_trend", " union all ".join(f"select '{v}' as dataset, count(*) as records, true as cells_never_less, true as sublinear from ({VIEWS[v].sql})" for v in ("plane", "checkin", "delay")))
def _(spark, sf_dir):
    """Stored cells never get fewer as records come, and grow by no more than the records do."""
    rows = []
    for v in ("plane", "checkin", "delay"):
        g = growth(spark, sf_dir, v).orderBy("inserted").collect()
        cells, n = [r["cells"] for r in g], [r["records"] for r in g]
        rows.append((v, n[-1], cells == sorted(cells), all(b[0] - a[0] <= b[1] - a[1] for a, b in zip(zip(cells, n), zip(cells[1:], n[1:])))))
    return spark.createDataFrame(rows, "dataset string, records bigint, cells_never_less boolean, sublinear boolean")


#: Data sets with a category and a time of their own: both sides index the two dimensions, the category and the time.
CUBED = {"checkin": (("x", "y"), "event_type", "hr", 6), "gps": (("x", "y"), "event_type", "k", 10), "plane": (("x", "y"), "event_type", "wd", 1), "hail": (("price", "cust"), "o_orderstatus", "month", 1), "delay": (("price", "disc"), "o_orderpriority", "month", 1), "splom": (("qty", "price"), "l_returnflag", "day", 250)}


def cubes(spark, sf_dir, name: str):
    """(seconds, tree cube), (seconds, index) of one data set over the same dimensions, category and time."""
    dims, cat, time, step = CUBED[name]
    source = "checkin" if name == "plane" else name
    df, widths = view(spark, sf_dir, source), VIEWS[source].widths
    bits = max(widths[d] - 1 for d in dims).bit_length()
    t, cube = measures.timed(lambda: base.tree_cube(df, dims, bits, 8, cat, time, step).persist())
    t += measures.timed(cube.count)[0]
    s, ix = measures.timed(lambda: core.build(df, (*dims, time), widths, INDEXED[source][1], rate=0.2, leaves=32, grid_widths={**{d: INDEXED[source][2][d] for d in dims}, time: step}, axes=(cat,)))
    return (t, cube), (s, ix)


@query("w05_vs_tree_cube")
def _(spark, sf_dir):
    """Build seconds, stored rows, bytes on disk and response time of the index and of the exact tree cube."""
    rows = []
    for name in CUBED:
        (t, cube), (s, ix) = cubes(spark, sf_dir, name)
        path = scratch(spark, "cube")
        cube.write.parquet(path)
        ask = {"tree cube": lambda: base.tree_cube_counts(cube, 3, 2).collect(), "index": lambda: ix.chart(Chart([Bins.width(d, g, 0, -(-int(w) // g) * g) for d, w, g in zip(ix.dims[:2], ix.widths, ix.grids)])).collect()}  # noqa: B023
        ms = {k: min(measures.timed(f)[0] for _ in range(2)) * 1000 for k, f in ask.items()}
        rows.append((name, "tree cube", cube.count(), m.folder_bytes(spark, path), round(t, 3), round(ms["tree cube"], 1)))
        rows.append((name, "index", ix.cells.count(), m.stored_bytes(spark, ix), round(s, 3), round(ms["index"], 1)))
        cube.unpersist()
        ix.cells.unpersist()
    return spark.createDataFrame(rows, "dataset string, method string, stored_rows bigint, bytes_on_disk bigint, seconds double, response_ms double")


@query("w05_same_answers", " union all ".join(f"select '{n}' as dataset, {CUBED[n][1]}::varchar as cat, ({CUBED[n][2]} // {CUBED[n][3]})::bigint as bin, count(*) as by_tree, count(*) as by_index from ({VIEWS[n].sql}) group by all" for n in ("checkin", "hail", "delay")))
def _(spark, sf_dir):
    """Both sides give the exact counts by category and time."""
    out = []
    for name in ("checkin", "hail", "delay"):
        (_t, cube), (_s, ix) = cubes(spark, sf_dir, name)
        _dims, cat, time, step = CUBED[name]
        span = -(-int(ix.widths[2]) // step) * step
        cats = cube.where("cat is not null").select("cat").distinct().orderBy("cat").collect()  # a row a category
        counted = union([base.tree_cube_counts(cube, 0, 2, c["cat"]).withColumn("cat", F.lit(c["cat"])) for c in cats])
        by_index = ix.chart(Chart([Bins.width(time, step, 0, span)]), by=(cat,)).select(F.col(cat).alias("cat"), F.col("t1").alias("bin"), F.col("value").alias("by_index"))
        out.append(counted.select("cat", "bin", F.col("value").alias("by_tree")).join(by_index, ["cat", "bin"], "full_outer").select(F.lit(name).alias("dataset"), "cat", "bin", "by_tree", "by_index"))
    return union(out)


# ---- user sessions -----------------------------------------------------------------------------------------------

_STEPS = [(0, 57600, 7200), (0, 14400, 1800), (7200, 21600, 1800), (0, 7200, 900), (14400, 43200, 3600)]
_STEP_CHARTS = [Chart([Bins.width("x", w, lo, hi), Bins.width("y", w, lo, hi)]) for lo, hi, w in _STEPS]
query("w06_heatmap_session", " union all ".join(f"select {i} as step, * from ({c.sql(PLANE.sql)})" for i, c in enumerate(_STEP_CHARTS)))(lambda s, d: union([m.zoomed(s, d).chart(c).select(F.lit(i).alias("step"), "*") for i, c in enumerate(_STEP_CHARTS)]))
_BRUSHES = [{}, {"x": (0, 7200)}, {"x": (0, 7200), "wd": (0, 5)}, {"wd": (5, 7), "hr": (18, 24)}]
query("w07_linked_brush", " union all ".join(f"select {i} as step, * from ({m.linked_sql('checkin', m.LINKED, b)})" for i, b in enumerate(_BRUSHES)))(lambda s, d: _brushed(s, d))


def _brushed(spark, sf_dir):
    """All charts of all brushes in one pass over the cells."""
    ix = indexed(spark, sf_dir, "checkin")
    return ix.linked([((i, d), c) for i, b in enumerate(_BRUSHES) for d, c in m.linked_views(ix, m.LINKED, b)], "step, chart")


_BY_MONTH, _BY_YEAR = Chart([Bins.width("month", 1, 0, 12)], agg="mean"), Chart([Bins.width("year", 1, 0, 8)], {"disc": (2, 6)}, "sum")
query("w08_custom_charts", f"select 'mean_by_month' as chart, t1, value::double as value from ({_BY_MONTH.sql(measured('delay', 'qty'))}) union all select 'sum_by_year', t1, value::double from ({_BY_YEAR.sql(measured('delay', 'qty'))})")(lambda s, d: _custom(s, d))


def _custom(spark, sf_dir):
    ix = indexed(spark, sf_dir, "delay", dims=("price", "disc", "year", "month"), measure="qty", rate=0.05, leaves=32)
    return union([ix.chart(c).select(F.lit(n).alias("chart"), "t1", F.col("value").cast("double").alias("value")) for n, c in (("mean_by_month", _BY_MONTH), ("sum_by_year", _BY_YEAR))])


_LOG_PRICES = Chart([Bins.log("price", 4, 900, 108000)])


@query("w08_log_prices", _LOG_PRICES.sql(DELAY.sql))
def _(spark, sf_dir):
    """A chart on logarithmic bins from an adaptive index whose cells are one unit wide."""
    return indexed(spark, sf_dir, "delay", dims=("price",), grid={"price": 1}, leaves=32, budget=1 << 18).chart(_LOG_PRICES)


@query("w08_equal_counts", "select 6 as bins, true as balanced")
def _(spark, sf_dir):
    from apcube.operators.descriptors import depth_edges

    ix = indexed(spark, sf_dir, "delay", dims=("price",), grid={"price": 1}, leaves=32, budget=1 << 18)
    got = ix.chart(Chart([Bins("price", depth_edges(ix, "price", 6))]))
    return got.agg(F.count("*").cast("int").alias("bins"), (F.max("value") <= 1.25 * F.sum("value") / F.lit(6)).alias("balanced"))


query("w09_tree_cube_session", " union all ".join(f"select {lv} as level, * from ({base.tree_cube_sql(PLANE.sql, m.XY, 16, lv, 'hr', 6)})" for lv in (1, 3, 5)))(lambda s, d: _tree_session(s, d))


def _tree_session(spark, sf_dir):
    cube = base.tree_cube(view(spark, sf_dir, "checkin"), m.XY, 16, 8, "event_type", "hr", 6).persist()
    return union([base.tree_cube_counts(cube, lv, 2).select(F.lit(lv).alias("level"), "*") for lv in (1, 3, 5)])


def session_charts(spark, sf_dir) -> dict[str, list[tuple]]:
    """Per task of the user study its charts, as (answer, truth, keys, number of grids)."""
    plane, checkin, delay = (view(spark, sf_dir, v) for v in ("plane", "checkin", "delay"))
    heat, linked = m.zoomed(spark, sf_dir), indexed(spark, sf_dir, "checkin")
    months = indexed(spark, sf_dir, "delay", dims=("price", "disc", "year", "month"), measure="qty", rate=0.05, leaves=32)
    cube = base.tree_cube(checkin, m.XY, 16, 8, "event_type", "hr", 6).persist()
    size = lambda c: int(np.prod([len(b.edges) - 1 for b in c.bins]))
    tasks = {"heat_map": [(lambda c=c: heat.chart(c), lambda c=c: base.scan(plane, c), c.names, size(c)) for c in (*_STEP_CHARTS, Chart([Bins.width(d, 5000, 0, 55000) for d in m.XY]))]}
    brushes = [c for b in _BRUSHES for _, c in m.linked_views(linked, m.LINKED, b)]
    tasks["check_ins_index"] = [(lambda c=c: linked.chart(c), lambda c=c: base.scan(checkin, c), c.names, size(c)) for c in brushes]
    tasks["check_ins_tree_cube"] = [(lambda lv=lv: base.tree_cube_counts(cube, lv, 2), lambda lv=lv: base.tree_cube_counts(cube, lv, 2), ["prefix", "bin"], 4**lv * 4) for lv in (1, 2, 3, 4, 5)]
    custom = [_BY_MONTH, _BY_YEAR, Chart([Bins.width("price", 10800, 0, 108000)], {"month": (3, 9)}, "sum"), Chart([Bins.width("year", 1, 0, 8), Bins.width("month", 1, 0, 12)])]
    tasks["delays"] = [(lambda c=c: months.chart(c), lambda c=c: base.scan(delay, c, "qty"), c.names, size(c)) for c in custom]
    return tasks


@query("w_session_statistics")
def _(spark, sf_dir):
    """Per task of the user study: number of queries, median, mean, deviation, maximum and 90th percentile of the response in
    milliseconds (as Spark jobs), mean ARE and mean payload in bytes."""
    runs, errors = [], []
    for task, charts in session_charts(spark, sf_dir).items():
        for answer, truth, keys, grids in charts:
            for _ in range(3):
                seconds, rows = measures.timed(lambda: answer().collect())  # noqa: B023
                runs.append((task, round(seconds * 1000, 3)))
            errors.append((task, measures.are_of(rows, truth().collect(), keys, grids), measures.payload_of(rows)))
    times = measures.latency(spark.createDataFrame(runs, "task string, ms double"), by="task")
    means = spark.createDataFrame(errors, "task string, are double, bytes bigint").groupBy("task").agg(F.round(F.avg("are"), 6).alias("mean_are"), F.avg("bytes").alias("mean_payload"))
    return times.join(means, "task")


@query("w_session_errors", "select * from (values ('heat_map', 6, 5, true), ('check_ins_index', 16, 16, true), ('check_ins_tree_cube', 5, 5, true), ('delays', 4, 4, true)) as t(task, charts, exact, bounded)")
def _(spark, sf_dir):
    """How many charts of each task are exact: all but the one whose bins fit no cell."""
    rows = []
    for task, charts in session_charts(spark, sf_dir).items():
        ares = [measures.are_of(answer().collect(), truth().collect(), keys, grids) for answer, truth, keys, grids in charts]
        rows.append((task, len(ares), sum(a == 0 for a in ares), max(ares) <= 0.35))
    return spark.createDataFrame(rows, "task string, charts int, exact int, bounded boolean")


# ---- regions, heights, hashing, plain tables ---------------------------------------------------------------------

HEIGHTS = (2, 3, 4, 5)


def config_index(spark, sf_dir, config: str, grid: int | None = None) -> core.Index:
    """h2..h5: index of that height (unaligned, or cells that divide bins of ``grid``); lsh2..lsh5: the same, its leaves
    found by hashing; s1: very fine plain table; s2: plain table of the size of the unaligned h5."""
    if config == "s1":
        return m._flat(spark, sf_dir, 100)
    if config == "s2":
        ref = config_index(spark, sf_dir, f"h{HEIGHTS[-1]}")
        return m._flat(spark, sf_dir, -(-57600 // max(2, round(ref.dense_entries() ** 0.5))))
    return indexed(spark, sf_dir, "plane", aligned=grid is not None, grid=grid and {"x": grid, "y": grid}, bins=10, target_height=int(config[-1]))


def region_leaves(spark, ix: core.Index, region: str, config: str) -> list[int] | None:
    """Numbers of the leaves that the configuration reads: those that hashing finds, or None for all."""
    if not config.startswith("lsh"):
        return None
    lo, hi, _ = REGIONS[region]
    area = spark.createDataFrame([(0, lo, lo, hi - 1, hi - 1)], "id int, lo_x bigint, lo_y bigint, hi_x bigint, hi_y bigint")
    return m.hit_leaves(ix, m.search(boxes_of(spark, ix), area, m.XY, (57600, 57600), "probe"))


CONFIGS = (*(f"lsh{h}" for h in HEIGHTS), *(f"h{h}" for h in HEIGHTS), "s1", "s2")


def _region(region: str, config: str):
    def run(spark, sf_dir):
        """Exact grids, and whether the inner and outer cells of the leaves that the configuration reads enclose them: a
        search that misses a leaf with records can't."""
        chart, ix = region_chart(region), config_index(spark, sf_dir, config)
        exact = base.scan(view(spark, sf_dir, "plane"), chart)
        return m.in_bounds(exact, ix.with_error(chart, leaves=region_leaves(spark, ix, region, config)), chart.names)

    return run


def _aligned_region(region: str, config: str):
    """The chart on cells that divide its bins: exact."""
    width = REGIONS[region][2]

    def run(spark, sf_dir):
        ix = config_index(spark, sf_dir, config, width)
        return ix.chart(region_chart(region), leaves=region_leaves(spark, ix, region, config))

    return run


for _r in REGIONS:
    for _c in CONFIGS:
        query(f"w10_region_{_r}_{_c}", f"select *, true as in_bounds from ({region_chart(_r).sql(PLANE.sql)})")(_region(_r, _c))
    for _c in ("h2", "h5", "lsh5"):
        query(f"w10_aligned_{_r}_{_c}", region_chart(_r).sql(PLANE.sql))(_aligned_region(_r, _c))


def region_rows(spark, sf_dir, configs: tuple[str, ...] = CONFIGS) -> list[tuple]:
    """region, alignment, config, are, entries, ms."""
    rows = []
    for region, (_lo, _hi, width) in REGIONS.items():
        chart = region_chart(region)
        truth = base.scan(view(spark, sf_dir, "plane"), chart).collect()  # a row a bin
        n = (len(chart.bins[0].edges) - 1) ** 2
        for config in configs:
            for grid in (None, width) if config[0] in "hl" else (None,):
                ix = config_index(spark, sf_dir, config, grid)
                answer = lambda: ix.chart(chart, leaves=region_leaves(spark, ix, region, config))  # noqa: B023, E731
                seconds, got = measures.timed(lambda: answer().collect())  # noqa: B023
                rows.append((region, "off" if grid is None else "on", config, measures.are_of(got, truth, chart.names, n), ix.dense_entries(), round(seconds * 1000, 1)))
    return rows


REGION_ROWS = "region string, alignment string, config string, are double, entries bigint, ms double"


@query("w10_region_errors")
def _(spark, sf_dir):
    """ARE, stored entries and milliseconds of every configuration on every region, without and with scale alignment."""
    return spark.createDataFrame(region_rows(spark, sf_dir), REGION_ROWS)


@query("w10_region_trend", "select region, true as aligned_exact, true as fine_table_best, true as higher_is_better, true as hashing_loses_nothing from (values ('dense'), ('global'), ('sparse')) as t(region)")
def _(spark, sf_dir):
    """What the experiment shows, as statements: aligned charts have no error, the very fine plain table hardly any, height 5 less
    than height 2, and leaves found by probing are all that matter."""
    out, configs = [], ("h2", "h5", "lsh5", "s1")
    found = {(r, on, c): are for r, on, c, are, _, _ in region_rows(spark, sf_dir, configs)}
    for r in REGIONS:
        aligned = all(found[r, "on", c] == 0 for c in configs if c[0] in "hl")
        hashing = found[r, "off", "lsh5"] == found[r, "off", "h5"]
        out.append((r, aligned, found[r, "off", "s1"] < 0.001, found[r, "off", "h5"] < found[r, "off", "h2"], hashing))
    return spark.createDataFrame(out, "region string, aligned_exact boolean, fine_table_best boolean, higher_is_better boolean, hashing_loses_nothing boolean")


def align_row(spark, sf_dir, aligned: bool) -> list[tuple]:
    rows = []
    for region, (_lo, _hi, w) in REGIONS.items():
        chart = region_chart(region)
        ix = indexed(spark, sf_dir, "plane", aligned=aligned, grid={"x": w, "y": w} if aligned else None, bins=10, leaves=64)
        truth = base.scan(view(spark, sf_dir, "plane"), chart)
        are = measures.are(ix.chart(chart), truth, chart.names, (len(chart.bins[0].edges) - 1) ** 2).first()["are"]
        rows.append((region, float(are), round(ix.coincidence(chart), 4)))
    return rows


@query("w11_align_on", "select * from (values ('dense', 0.0::double, 1.0::double), ('global', 0.0::double, 1.0::double), ('sparse', 0.0::double, 1.0::double)) as t(region, are, coincidence)")
def _(spark, sf_dir):
    return spark.createDataFrame(align_row(spark, sf_dir, True), "region string, are double, coincidence double")


@query("w11_align_off", "select * from (values ('dense', true), ('global', true), ('sparse', true)) as t(region, worse_than_aligned)")
def _(spark, sf_dir):
    rows = [(r, a > 0.0 and c < 1.0) for r, a, c in align_row(spark, sf_dir, False)]
    return spark.createDataFrame(rows, "region string, worse_than_aligned boolean")


@query("w11_align_errors")
def _(spark, sf_dir):
    rows = [(r, "on" if on else "off", a, c) for on in (True, False) for r, a, c in align_row(spark, sf_dir, on)]
    return spark.createDataFrame(rows, "region string, alignment string, are double, coincidence double")


# ---- partitioners, categories, samplers --------------------------------------------------------------------------

@query("w12_partitioner_errors", "select * from (values ('area', true), ('density', true), ('kd', true), ('quad', true), ('str', true), ('uniform', true)) as t(partitioner, bounded)")
def _(spark, sf_dir):
    """The dense region on unaligned cells, where the partition matters: all bounds hold, and no partition's error is above that
    of the equal boxes by more than a tenth."""
    chart, rows = region_chart("dense"), {}
    df = view(spark, sf_dir, "plane")
    exact = base.scan(df, chart).persist()
    truth = exact.collect()  # a row a bin
    for kind in ("density", "area", "kd", "quad", "str", "uniform"):
        ix = core.build(df, m.XY, PLANE.widths, "event_id", bins=10, nodes=m.partition(spark, sf_dir, "plane", m.XY, kind))
        held = m.in_bounds(exact, ix.with_error(chart), chart.names).agg(F.bool_and("in_bounds")).first()[0]
        rows[kind] = (bool(held), measures.are_of(ix.chart(chart).collect(), truth, chart.names, 16))
        ix.cells.unpersist()
    return spark.createDataFrame([(k, held and are <= rows["uniform"][1] + 0.1) for k, (held, are) in rows.items()], "partitioner string, bounded boolean")


for _kind in ("density", "area", "kd", "quad", "str", "uniform"):
    query(f"w12_partitioner_{'rstar' if _kind == 'density' else _kind}", region_chart("dense").sql(PLANE.sql))(
        lambda s, d, k=_kind: core.build(view(s, d, "plane"), m.XY, PLANE.widths, "event_id", bins=32, grid_widths={"x": 800, "y": 800}, nodes=m.partition(s, d, "plane", m.XY, k)).chart(region_chart("dense"))
    )


@query("w12_partitioner_quality")
def _(spark, sf_dir):
    kinds = ("density", "area", "kd", "quad", "str", "uniform")
    out = []
    for name, dims in (("plane", m.XY), ("vec", ("e0", "e1"))):
        w = [float(VIEWS[name].widths[d]) for d in dims]
        pts = m.sample_points(spark, sf_dir, name, dims)
        out += [(name, k, *(round(v, 4) for v in boxtree.evenness(pts, m.partition(spark, sf_dir, name, dims, k), w).values())) for k in kinds]
    return spark.createDataFrame(out, "dataset string, partitioner string, leaves double, empty_share double, overlap_share double, count_variation double, inner_variation double")


query("w13_cat_axis", f"select event_type, x // 7200 as t1, count(*) as value from ({PLANE.sql}) group by all")(lambda s, d: _axis(s, d))


def _axis(spark, sf_dir):
    return m.rich(spark, sf_dir).chart_prefix(Chart([Bins.width("x", 7200, 0, 57600)]), by=("event_type",))


@query("w13_cat_brands", f"select p_brand, (price // 10800)::bigint as t1, count(*) as value from ({SPLOM.sql}) join part on l_partkey = p_partkey group by all")
def _(spark, sf_dir):
    """Brands as a category axis of the line items' index."""
    mark = (spark.sparkContext.applicationId, sf_dir, "brands")
    df = view(spark, sf_dir, "splom").join(load(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey")
    make = lambda: core.build(df, ("price", "qty"), SPLOM.widths, "l_orderkey", bins=16, rate=0.1, leaves=16, grid_widths={"price": 10800, "qty": 10}, axes=("p_brand",))
    return kept(m._FLATS, mark, make).chart(Chart([Bins.width("price", 10800, 0, 108000)]), by=("p_brand",)).select("p_brand", "t1", "value")


query("w13_cat_scale", f"select user_id // 25 as t1, count(*) as value from ({PLANE.sql}) group by all")(lambda s, d: _users(s, d))


def _users(spark, sf_dir):
    """Users as scales of a dimension: ranks are dense, so ranges of ranks are ranges of scales."""
    df = view(spark, sf_dir, "plane").select("user_id", "x")
    top = df.agg(F.max("user_id")).first()[0] or 0
    n = (top // 25 + 1) * 25
    ix = core.flat(df, ("user_id",), {"user_id": n}, {"user_id": 5})
    return ix.chart(Chart([Bins.width("user_id", 25, 0, n)]))


def _sampler(kind: str):
    def run(spark, sf_dir):
        from apcube.operators.descriptors import stratified

        dims = ("price", "disc", "year", "month")
        df = view(spark, sf_dir, "delay")
        key = F.col("l_orderkey") * 8 + F.col("l_linenumber")
        part = df.where(sampled(key, min(0.05, core.MOST_SAMPLE / max(df.count(), 1)))) if kind == "uniform" else stratified(df.withColumn("ym", F.col("year") * 12 + F.col("month")).withColumn("k", key), "ym", "k", 40)
        pts = part.select(*dims).toPandas().to_numpy()
        nodes = boxtree.build(pts, [float(DELAY.widths[d]) for d in dims], target_leaves=48)
        ix = core.build(df, dims, DELAY.widths, key, measure="qty", grid_widths={d: INDEXED["delay"][2][d] for d in dims}, nodes=nodes)
        return ix.chart(Chart([Bins.width("year", 1, 0, 8)], agg="sum"))

    return run


for _s in ("uniform", "stratified"):
    query(f"w14_sampler_{_s}", Chart([Bins.width("year", 1, 0, 8)], agg="sum").sql(measured("delay", "qty")))(_sampler(_s))


def lang_index(spark, sf_dir, kind: str, aligned: bool) -> core.Index:
    """Documents by length, on a tree grown on a uniform sample or on one stratified by language."""
    from apcube.operators.descriptors import stratified

    df = view(spark, sf_dir, "docs")
    part = df.where(sampled(F.col("doc_id"), min(0.2, core.MOST_SAMPLE / max(df.count(), 1)))) if kind == "uniform" else stratified(df, "lang", "doc_id", 50)
    nodes = boxtree.build(part.select("chars", "tokens").dropna().toPandas().to_numpy(np.int64), [float(DOCS.widths[d]) for d in ("chars", "tokens")], target_leaves=16)
    return core.build(df, ("chars", "tokens"), DOCS.widths, "doc_id", bins=16, grid_widths={"chars": 1000, "tokens": 100} if aligned else None, nodes=nodes, axes=("lang",))


_LANG = Chart([Bins.width("chars", 1000, 0, 144000)])
for _s in ("uniform", "stratified"):
    query(f"w14_sampler_docs_{_s}", f"select lang, (chars // 1000)::bigint as t1, count(*) as value from ({DOCS.sql}) where chars is not null and tokens is not null group by all")(lambda s, d, k=_s: lang_index(s, d, k, True).chart(_LANG, by=("lang",)).select("lang", "t1", "value"))


@query("w14_sampler_errors")
def _(spark, sf_dir):
    """Error of an unaligned chart per language under both samplers, and the documents of the language in the sample's tree."""
    out = []
    exact = view(spark, sf_dir, "docs").dropna(subset=["chars", "tokens"])
    for kind in ("uniform", "stratified"):
        got = lang_index(spark, sf_dir, kind, False).chart(_LANG, by=("lang",))
        truth = exact.groupBy("lang", F.floor(F.col("chars") / 1000).cast("long").alias("t1")).agg(F.count("*").alias("value"))
        both = truth.withColumnRenamed("value", "a").join(got.withColumnRenamed("value", "b"), ["lang", "t1"], "full_outer").fillna(0, ["a", "b"])
        out.append(both.groupBy("lang").agg(F.round(F.sum(F.abs(F.col("a") - F.col("b")) / F.greatest("a", "b")) / 144, 6).alias("are")).select(F.lit(kind).alias("sampler"), "lang", "are"))
    return union(out)


# ---- exploration, margins, filters, local bins, vectors, skew ----------------------------------------------------

for _h in (1, 2, 3):
    query(f"w15_explore_level_{_h}", m.HEAT.sql(PLANE.sql))(lambda s, d, h=_h: list(explore(indexed(s, d, "plane"), m.HEAT, h))[-1][1])


@query("w15_explore_narrowing", "select count(*) as levels, true as never_more from (values (1), (2), (3)) as t(x)")
def _(spark, sf_dir):
    """Three levels, each under the two densest grids of the one before; a narrowed view never shows more than the whole."""
    ix = indexed(spark, sf_dir, "plane")
    whole = ix.chart(m.HEAT).withColumnRenamed("value", "w")
    parts = [df.join(whole, m.HEAT.names, "left").select(F.lit(h).alias("h"), (F.col("value") <= F.col("w")).alias("ok")) for h, df in explore(ix, m.HEAT, 3, pick=2)]
    return union(parts).agg(F.countDistinct("h").alias("levels"), F.bool_and("ok").alias("never_more"))


def _margins(agg: str):
    def run(spark, sf_dir):
        ix = indexed(spark, sf_dir, "plane", measure="x", aligned=False)
        chart = m.on(region_chart("dense"), agg)
        return m.in_bounds(base.scan(view(spark, sf_dir, "plane"), chart, "x"), ix.with_error(chart), chart.names)

    return run


for _a in ("count", "sum"):
    query(f"w16_margin_{_a}", f"select *, true as in_bounds from ({m.on(region_chart('dense'), _a).sql(m.PLANE_X)})")(_margins(_a))


@query("w16_margin_mean", f"select t1, t2, true as in_bounds from ({region_chart('dense').sql(PLANE.sql)})")
def _(spark, sf_dir):
    ix, chart = indexed(spark, sf_dir, "plane", measure="x", aligned=False), region_chart("dense")
    n, s = ix.with_error(chart), ix.with_error(m.on(chart, "sum"))
    both = n.select(*chart.names, F.col("v_lo").alias("n_lo"), F.col("v_hi").alias("n_hi")).join(s.select(*chart.names, F.col("v_lo").alias("s_lo"), F.col("v_hi").alias("s_hi")), chart.names)
    exact = base.scan(view(spark, sf_dir, "plane"), m.on(chart, "mean"), "x").join(both, chart.names, "left")
    fine = (F.col("s_lo") / F.col("n_hi") <= F.col("value") + 1e-3) & F.coalesce(F.when(F.col("n_lo") > 0, F.col("s_hi") / F.col("n_lo")) >= F.col("value") - 1e-3, F.lit(True))
    return exact.select(*chart.names, F.coalesce(fine, F.lit(False)).alias("in_bounds"))


@query("w16_margin_median", f"select month::bigint as t1, true as in_bounds from ({HAIL.sql}) where price >= 50000 and price < 200000 group by all")
def _(spark, sf_dir):
    chart = Chart(m.MONTHS.bins, {"price": (50000, 200000)})
    found = histograms.quantile_bounds(m._hist_index(spark, sf_dir), chart, 32, 0.5)
    exact = view(spark, sf_dir, "hail").where("price >= 50000 and price < 200000").groupBy(F.col("month").alias("t1")).agg(F.expr("percentile_disc(0.5) within group (order by total)").alias("e"))
    return exact.join(found, "t1", "left").select("t1", F.coalesce((F.coalesce("z_lo", F.lit(0.0)) <= F.col("e") + 1) & (F.col("z_hi") >= F.col("e") - 1), F.lit(False)).alias("in_bounds"))


_MULTI = Chart([Bins.width("year", 1, 0, 8), Bins.width("wd", 1, 0, 7)], {"disc": (2, 6), "tax": (0, 4), "price": (10800, 75600)}, "sum")
query("w17_multi_filter", _MULTI.sql(measured("delay", "qty")))(lambda s, d: indexed(s, d, "delay", measure="qty", rate=0.05, leaves=32, budget=1 << 18).chart(_MULTI))

for _scope in ("local", "global"):
    query(f"w18_hist_{_scope}", f"select month::bigint as t1, count(*) as n, true as close from ({HAIL.sql}) group by all")(lambda s, d, sc=_scope: m._close(s, d, histograms.quantile(histograms.masses(m._hist_index(s, d, sc), m.MONTHS, 32), 0.5, "t1"), 0.5, 3_000_000))

@query("w18_local_against_global", f"select count(*) as n, true as local_no_worse from (select month from ({HAIL.sql}) group by month)")
def _(spark, sf_dir):
    """Mean error of the median by month: edges of each part's own range against edges of the whole range, at eight bins."""
    exact = view(spark, sf_dir, "hail").groupBy(F.col("month").alias("t1")).agg(F.expr("percentile(total, 0.5)").alias("e"), F.count("*").alias("rows"))
    for scope in ("local", "global"):
        found = histograms.quantile(histograms.masses(m._hist_index(spark, sf_dir, scope, 8), m.MONTHS, 8), 0.5, "t1").withColumnRenamed("value", scope)
        exact = exact.join(found, "t1", "left")
    off = lambda c: F.avg(F.abs(F.col(c) - F.col("e")))
    return exact.agg(F.count("*").alias("n"), F.coalesce(off("local") <= 1.1 * off("global") + 100_000, F.lit(False)).alias("local_no_worse"))


VEC_DIMS, VEC_DIMS_16 = (tuple(f"e{i}" for i in range(k)) for k in (5, 16))


def vec_boxes(spark, sf_dir, dims=VEC_DIMS):
    """Leaf boxes over the components, and query boxes around every vector whose id is divisible by 20."""
    ix = indexed(spark, sf_dir, "vec", leaves=32) if dims == VEC_DIMS else indexed(spark, sf_dir, "vec", dims=dims, aligned=False, bins=2, leaves=32)
    q = view(spark, sf_dir, "vec").where("vec_id % 20 = 0").select(F.col("vec_id").cast("int").alias("id"), *((F.col(d) - 40).alias(f"lo_{d}") for d in dims), *((F.col(d) + 40).alias(f"hi_{d}") for d in dims))
    return ix, boxes_of(spark, ix, True), q


def vec_quality(spark, sf_dir, schemes, dims=VEC_DIMS) -> DataFrame:
    """components, scheme and the quality of each search against exact tests of all pairs."""
    _, nodes, q = vec_boxes(spark, sf_dir, dims)
    truth = lsh.overlap_scan(nodes.where("is_leaf"), q, dims).persist()
    out = [measures.candidate_quality(m.search(nodes, q, dims, [2000] * len(dims), sc, 4), truth).select(F.lit(len(dims)).alias("components"), F.lit(sc).alias("scheme"), "*") for sc in schemes]
    return union(out)


SCHEMES = ("plain", "reversed", "probe", "edges", "combined")
for _s in SCHEMES:
    query(f"w19_lsh_{_s}", m.ENOUGH)(lambda s, d, sc=_s: m.found_enough(vec_quality(s, d, (sc,)), sc))
# the edges of a box of 16 components are 16 * 2 ** 15, too many to put points on
for _s in SCHEMES:
    if _s != "edges":
        query(f"w19_lsh_{_s}_16", m.ENOUGH)(lambda s, d, sc=_s: m.found_enough(vec_quality(s, d, (sc,), VEC_DIMS_16), sc))


@query("w19_lsh_recall")
def _(spark, sf_dir):
    return vec_quality(spark, sf_dir, SCHEMES).unionByName(vec_quality(spark, sf_dir, [x for x in SCHEMES if x != "edges"], VEC_DIMS_16))


_WIDTH, _LOG = Chart([Bins.width("chars", 1000, 0, 144000)]), Chart([Bins.log("chars", 2, 10, 144000)])
query("w20_docs_width", _WIDTH.sql(DOCS.sql))(lambda s, d: indexed(s, d, "docs").chart(_WIDTH))
query("w20_docs_log", _LOG.sql(DOCS.sql))(lambda s, d: m._docs_fine(s, d).chart(_LOG))


@query("w20_docs_depth", "select 10 as bins, true as balanced")
def _(spark, sf_dir):
    from apcube.operators.descriptors import depth_edges

    fine = m._docs_fine(spark, sf_dir)
    got = fine.chart(Chart([Bins("chars", depth_edges(fine, "chars", 10))]))
    return got.agg(F.count("*").cast("int").alias("bins"), (F.max("value") <= 1.3 * F.sum("value") / F.lit(10)).alias("balanced"))
