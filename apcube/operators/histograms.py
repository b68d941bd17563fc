"""Histograms of the aggregate dimension per part, with local or global edges; their merge; quantiles and bounds.

A part's histogram has B equal bins over its own range of the measure (local) or over that of all records (global); the
last bin is closed. Bins are a further axis of the cells, so a range query adds up bins like counts. Merging parts with
different edges spreads each bin evenly: the merged distribution function is piecewise linear.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from apcube.operators.index import Index, assign, to_cells
from apcube.plans.spec import Chart


def edges(points: DataFrame, part: str, m: str, scope: str = "local") -> DataFrame:
    """part, e_lo, e_hi: the range of the measure."""
    local = points.groupBy(part).agg(F.min(m).alias("e_lo"), F.max(m).alias("e_hi"))
    if scope == "local":
        return local
    whole = points.agg(F.min(m).alias("e_lo"), F.max(m).alias("e_hi"))
    return local.select(part).crossJoin(F.broadcast(whole))  # one row


def bin_of(m: str, bins: int) -> Column:
    """Bin number of a whole-number measure in [e_lo, e_hi]; a range of one value has one bin."""
    return F.when(F.col("e_hi") == F.col("e_lo"), F.lit(0)).otherwise(F.least(F.floor((F.col(m) - F.col("e_lo")) * bins / (F.col("e_hi") - F.col("e_lo"))), F.lit(bins - 1))).cast("int")


def binned(points: DataFrame, part: str, m: str, bins: int, scope: str = "local") -> DataFrame:
    """part, hb, n, e_lo, e_hi: counts per bin."""
    ranged = points.where(F.col(m).isNotNull()).join(edges(points, part, m, scope), part)
    return ranged.withColumn("hb", bin_of(m, bins)).groupBy(part, "e_lo", "e_hi", "hb").agg(F.count("*").alias("n"))


def binned_sql(source: str, part: str, m: str, bins: int, scope: str = "local") -> str:
    over = f"over (partition by {part})" if scope == "local" else "over ()"
    inner = f"select {part}, {m} as m, min({m}) {over} as e_lo, max({m}) {over} as e_hi from ({source}) where {m} is not null"
    return f"select {part}, e_lo, e_hi, case when e_lo = e_hi then 0 else least(floor((m - e_lo) * {bins} / (e_hi - e_lo)), {bins - 1}) end::int as hb, count(*) as n from ({inner}) group by all"


def cumulative(hist: DataFrame, part: str) -> DataFrame:
    """Adds ``upto``: the count of the bin and all below it."""
    return hist.withColumn("upto", F.sum("n").over(Window.partitionBy(part).orderBy("hb").rowsBetween(Window.unboundedPreceding, 0)))


def pieces(hist: DataFrame, bins: int, *keys: str) -> DataFrame:
    """keys.., a, b, n: bins as intervals of the measure (b = a for a degenerate one)."""
    width = (F.col("e_hi") - F.col("e_lo")) / F.lit(float(bins))
    return hist.select(*keys, (F.col("e_lo") + F.col("hb") * width).alias("a"), (F.col("e_lo") + (F.col("hb") + 1) * width).alias("b"), F.col("n").cast("double").alias("n"))


def cdf(mass: DataFrame, z: float, *keys: str) -> DataFrame:
    """keys.., below: mass at most z, bins spread evenly."""
    share = F.when(F.col("a") >= F.col("b"), (F.lit(z) >= F.col("a")).cast("double")).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), (F.lit(z) - F.col("a")) / (F.col("b") - F.col("a")))))
    agg = F.round(F.sum(F.col("n") * share), 4).alias("below")
    return mass.groupBy(*keys).agg(agg) if keys else mass.agg(agg)


def quantile(mass: DataFrame, q: float, *keys: str) -> DataFrame:
    """keys.., value: the smallest z whose merged distribution reaches q, by linear inversion on the union of all edges.

    A bin adds its density at its lower edge and takes it away at the upper one; running sums of density times distance
    give the mass at every edge. Degenerate bins are points of mass, set to a width of one scale."""
    b = F.when(F.col("b") > F.col("a"), F.col("b")).otherwise(F.col("a") + 1.0)
    d = F.col("n") / (b - F.col("a"))
    events = mass.select(*keys, F.explode(F.array(F.struct(F.col("a").alias("z"), d.alias("d")), F.struct(b.alias("z"), (-d).alias("d")))).alias("e")).select(*keys, "e.z", "e.d")
    events = events.groupBy(*keys, "z").agg(F.sum("d").alias("d"))
    w = Window.partitionBy(*keys).orderBy("z") if keys else Window.partitionBy(F.lit(0)).orderBy("z")
    run = events.withColumn("slope", F.sum("d").over(w)).withColumn("next", F.lead("z").over(w)).where("next is not null")
    run = run.withColumn("step", F.col("slope") * (F.col("next") - F.col("z")))
    run = run.withColumn("upto", F.sum("step").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    whole = Window.partitionBy(*keys) if keys else Window.partitionBy(F.lit(0))
    run = run.withColumn("want", F.max("upto").over(whole) * q).where("upto >= want - 1e-9 and upto - step <= want + 1e-9 and step > 1e-12")
    value = F.min(F.col("z") + (F.col("want") - (F.col("upto") - F.col("step"))) / F.col("slope")).alias("value")
    return run.groupBy(*keys).agg(value) if keys else run.agg(value)


def mode(mass: DataFrame, *keys: str) -> DataFrame:
    """keys.., value: the middle of the densest bin (ties: the lowest)."""
    b = F.when(F.col("b") > F.col("a"), F.col("b")).otherwise(F.col("a") + 1.0)
    best = F.max_by((F.col("a") + F.col("b")) / 2, F.struct(F.col("n") / (b - F.col("a")), -F.col("a"))).alias("value")
    return mass.groupBy(*keys).agg(best) if keys else mass.agg(best)


def of_index(df: DataFrame, index: Index, measure: str, bins: int, scope: str = "local") -> Index:
    """The index with a histogram bin of ``measure`` (the index's own measure) as a further axis: hb, e_lo, e_hi; its cells
    and prefix arrays are kept apart by it. The ranges of the parts come from the index's own cells, so that the records
    are read once; answers are masses (see ``masses``)."""
    local = index.cells.groupBy("leaf").agg(F.min("mn").alias("e_lo"), F.max("mx").alias("e_hi"))
    if scope == "global":
        local = local.select("leaf").crossJoin(F.broadcast(index.cells.agg(F.min("mn").alias("e_lo"), F.max("mx").alias("e_hi"))))  # one row
    points = df.select(*index.dims, F.col(measure).cast("bigint").alias("m")).dropna()
    placed = assign(points, index.dims, index.nodes, index.leaves, index.widths)
    ranged = placed.join(F.broadcast(local), "leaf").withColumn("hb", bin_of("m", bins))  # one row per leaf
    axes = (*index.axes, "hb", "e_lo", "e_hi")
    return replace(index, cells=to_cells(ranged, index.dims, index.cells_per, axes).persist(), axes=axes, extras=(), _prefix=None)


def masses(index: Index, chart: Chart, bins: int, snap: str = "nearest", prefix: bool = False) -> DataFrame:
    """t.., a, b, n: the bins of all cells that a chart's grids take, from cells or from prefix arrays."""
    by = ("hb", "e_lo", "e_hi")
    chart = Chart(chart.bins, chart.where)
    found = (index.chart_prefix if prefix else index.chart)(chart, snap, by=by).withColumnRenamed("value", "n")
    return pieces(found, bins, *chart.names)


def upto(index: Index, chart: Chart) -> DataFrame:
    """t.., hb, n, upto: the cumulative histogram of every grid, of parts that share their ranges (scope ``global``)."""
    found = index.chart_prefix(Chart(chart.bins, chart.where), by=("hb",)).withColumnRenamed("value", "n")
    w = Window.partitionBy(*chart.names).orderBy("hb").rowsBetween(Window.unboundedPreceding, 0)
    return found.withColumn("upto", F.sum("n").over(w))


def quantile_bounds(index: Index, chart: Chart, bins: int, q: float) -> DataFrame:
    """t.., z_lo, z_hi that enclose the exact quantile: mass of inner cells with bins wholly below z is certain, mass of
    outer cells with bins that begin below z is possible."""
    inner, outer = masses(index, chart, bins, "inner"), masses(index, chart, bins, "outer")
    keys = chart.names
    n_min, n_max = (m.groupBy(*keys).agg(F.sum("n").alias(name)) for m, name in ((inner, "n_min"), (outer, "n_max")))
    n = n_max.join(n_min, keys, "left").fillna(0.0, ["n_min"])
    w = Window.partitionBy(*keys).orderBy("z").rangeBetween(Window.unboundedPreceding, 0)
    most = outer.select(*keys, F.col("a").alias("z"), "n").withColumn("cum", F.sum("n").over(w))
    least = inner.select(*keys, F.col("b").alias("z"), "n").withColumn("cum", F.sum("n").over(w))
    lo = most.join(n, keys).where(F.col("cum") >= F.ceil(q * F.col("n_min"))).groupBy(*keys).agg(F.min("z").alias("z_lo"))
    hi = least.join(n, keys).where(F.col("cum") >= F.ceil(q * F.col("n_max"))).groupBy(*keys).agg(F.min("z").alias("z_hi"))
    top = outer.groupBy(*keys).agg(F.max("b").alias("top"))
    return top.join(lo, keys, "left").join(hi, keys, "left").select(*keys, "z_lo", F.coalesce("z_hi", "top").alias("z_hi"))
