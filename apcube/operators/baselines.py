"""The methods that the index is compared with, exact and approximate, each with the SQL of its answer where that differs
from the plain scan."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from apcube.functions.scale import morton, sampled, sampled_sql
from apcube.plans.spec import Bins, Chart


def bin_column(b: Bins):
    """The bin number of a raw coordinate, and the condition of being in a bin."""
    steps = {y - x for x, y in zip(b.edges, b.edges[1:])}
    inside = (F.col(b.dim) >= b.edges[0]) & (F.col(b.dim) < b.edges[-1])
    if len(steps) == 1:
        return F.floor((F.col(b.dim) - b.edges[0]) / steps.pop()).cast("long"), inside
    t = F.lit(0).cast("long")
    for e in b.edges[1:-1]:
        t = t + (F.col(b.dim) >= e).cast("long")
    return t, inside


def scan(df: DataFrame, chart: Chart, measure: str | None = None) -> DataFrame:
    """The exact answer from the records: predicates on raw columns, one partial and one final aggregate."""
    for d, (lo, hi) in chart.where.items():
        df = df.where((F.col(d) >= lo) & (F.col(d) < hi))
    for b, n in zip(chart.bins, chart.names):
        t, inside = bin_column(b)
        df = df.where(inside).withColumn(n, t)
    m = F.col(measure) if measure else F.lit(None).cast("long")
    value = {"count": F.count("*"), "sum": F.sum(m).cast("long"), "mean": F.round(F.sum(m).cast("double") / F.count("*"), 4), "var": F.round(F.var_pop(m), 2), "std": F.round(F.stddev_pop(m), 2), "min": F.min(m), "max": F.max(m)}[chart.agg].alias("value")
    return df.groupBy(*chart.names).agg(value) if chart.bins else df.agg(value)


# ---- exact tree cube ---------------------------------------------------------------------------------------------


def tree_cube(df: DataFrame, dims: Sequence[str], bits: int, depth: int, category: str, time: str, step: int) -> DataFrame:
    """level, prefix, category (null: all), bin, n: counts of quad-tree nodes by category and time bin. A node whose only
    child holds all its points shares the child's content: it is not stored."""
    k = len(dims)
    z = F.shiftright(morton([F.col(d) for d in dims], bits), (bits - depth) * k)
    leaf = df.select(z.alias("leaf"), F.col(category).alias("cat"), F.floor(F.col(time) / step).cast("long").alias("bin"))
    finest = leaf.groupBy("leaf", "cat", "bin").agg(F.count("*").alias("n"))
    every = finest.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(depth)))).withColumn("prefix", F.expr(f"shiftright(leaf, ({depth} - level) * {k})"))
    nodes = every.groupBy("level", "prefix", "bin", "cat").agg(F.sum("n").alias("n"), F.countDistinct(F.expr(f"case when level < {depth} then shiftright(leaf, ({depth} - level - 1) * {k}) end")).alias("kids"))
    # one more grouping for all categories; a chain of single children keeps its deepest node only
    whole = every.groupBy("level", "prefix", "bin").agg(F.sum("n").alias("n"), F.countDistinct(F.expr(f"case when level < {depth} then shiftright(leaf, ({depth} - level - 1) * {k}) end")).alias("kids")).withColumn("cat", F.lit(None).cast("string"))
    return nodes.unionByName(whole).where("kids <> 1").drop("kids")


def tree_cube_counts(cube: DataFrame, level: int, k: int, category: str | None = None) -> DataFrame:
    """prefix, bin, value at a level: the stored node, or the first stored one below it on its chain."""
    rows = cube.where(F.col("cat").isNull() if category is None else F.col("cat") == category).where(F.col("level") >= level)
    rows = rows.withColumn("top", F.expr(f"shiftright(prefix, (level - {level}) * {k})"))
    return rows.groupBy(F.col("top").alias("prefix"), "bin").agg(F.min_by("n", "level").alias("value"))


def tree_cube_sql(source: str, dims: Sequence[str], bits: int, level: int, time: str, step: int) -> str:
    k = len(dims)
    z = " | ".join(f"((({d} >> {bits - 1 - b}) & 1)::bigint << {(level - 1 - b) * k + (k - 1 - i)})" for b in range(level) for i, d in enumerate(dims))
    return f"select {z or '0'} as prefix, ({time} // {step})::bigint as bin, count(*) as value from ({source}) group by all"


# ---- sorted array with pivots ------------------------------------------------------------------------------------


def pivot_cube(df: DataFrame, dims: Sequence[str], bits: int, depth: int, key: Sequence[str]) -> DataFrame:
    """level, prefix, first, last: places of each node's records in the array sorted by Morton code. A baseline that sorts
    all records by design."""
    k = len(dims)
    z = morton([F.col(d) for d in dims], bits)
    placed = df.select(z.alias("z"), *key).withColumn("row", F.row_number().over(Window.orderBy("z", *key)))
    levels = placed.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(depth)))).withColumn("prefix", F.expr(f"shiftright(z, ({bits} - level) * {k})"))
    return levels.groupBy("level", "prefix").agg(F.min("row").alias("first"), F.max("row").alias("last"))


# ---- dense tiles, cross-filter, data cube ------------------------------------------------------------------------


def tiles(df: DataFrame, dims: Sequence[str], widths: dict[str, int], finest: int, levels: int) -> DataFrame:
    """level, i_<dim>, n: dense tiles of ``finest`` bins a side at level 0, halved in number at each further level; every
    level is rolled up from the one below."""
    cells = df.groupBy(*(F.floor(F.col(d) * finest / widths[d]).cast("long").alias(f"i_{d}") for d in dims)).agg(F.count("*").alias("n"))
    out = cells.select(F.lit(0).alias("level"), *cells.columns)
    for level in range(1, levels):
        cells = cells.groupBy(*(F.floor(F.col(f"i_{d}") / 2).cast("long").alias(f"i_{d}") for d in dims)).agg(F.sum("n").alias("n"))
        out = out.union(cells.select(F.lit(level), *cells.columns))
    return out


def tiles_sql(source: str, dims: Sequence[str], widths: dict[str, int], finest: int, levels: int) -> str:
    parts = []
    for level in range(levels):
        keys = ", ".join(f"({d} * {finest} // {widths[d]} // {2**level})::bigint as i_{d}" for d in dims)
        parts.append(f"select {level} as level, {keys}, count(*)::bigint as n from ({source}) group by all")
    return " union all ".join(parts)


def crossfilter(df: DataFrame, groups: dict[str, int], brushes: dict[str, tuple[int, int]]) -> DataFrame:
    """chart, t, value: one predefined 1-D chart per dimension (``groups``: bin width) under all brushes but its own; one
    scan for all charts."""
    charts = []
    for d, w in groups.items():
        others = [(o, r) for o, r in brushes.items() if o != d]
        ok = F.lit(True)
        for o, (lo, hi) in others:
            ok = ok & (F.col(o) >= lo) & (F.col(o) < hi)
        charts.append(F.when(ok, F.struct(F.lit(d).alias("chart"), F.floor(F.col(d) / w).cast("long").alias("t"))))
    rows = df.select(F.explode(F.array_compact(F.array(*charts))).alias("c"))
    return rows.groupBy("c.chart", "c.t").agg(F.count("*").alias("value"))


def crossfilter_sql(source: str, groups: dict[str, int], brushes: dict[str, tuple[int, int]]) -> str:
    parts = []
    for d, w in groups.items():
        cond = " and ".join(f"{o} >= {lo} and {o} < {hi}" for o, (lo, hi) in brushes.items() if o != d) or "true"
        parts.append(f"select '{d}' as chart, ({d} // {w})::bigint as t, count(*) as value from ({source}) where {cond} group by all")
    return " union all ".join(parts)


# ---- approximations ----------------------------------------------------------------------------------------------


def sample_chart(df: DataFrame, chart: Chart, key: str, rate: float) -> DataFrame:
    """Counts of a hashed sample, scaled up by the rate."""
    got = scan(df.where(sampled(F.col(key), rate)), chart)
    return got.withColumn("value", F.round(F.col("value") / rate, 2))


def sample_sql(source: str, chart: Chart, key: str, rate: float) -> str:
    return f"select * replace (round(value / {rate}, 2) as value) from ({chart.sql(f'select * from ({source}) where {sampled_sql(key, rate)}')})"


def bucket_spread(df: DataFrame, chart: Chart, cell: int) -> DataFrame:
    """Counts of plain square cells, spread evenly over each cell (no prefix sums)."""
    dims = [b.dim for b in chart.bins]
    cells = df.groupBy(*(F.floor(F.col(d) / cell).cast("long").alias(f"q_{d}") for d in dims)).agg(F.count("*").alias("n"))
    share = F.lit(1.0)
    for b, name in zip(chart.bins, chart.names):
        lit = F.array(*(F.struct(F.lit(i).cast("long").alias("t"), F.lit(lo).alias("lo"), F.lit(hi).alias("hi")) for i, (lo, hi) in enumerate(zip(b.edges, b.edges[1:]))))
        low, high = F.col(f"q_{b.dim}") * cell, F.col(f"q_{b.dim}") * cell + cell
        cells = cells.withColumn(f"g_{b.dim}", F.explode(F.filter(lit, lambda x: (x["lo"] < high) & (x["hi"] > low)))).withColumn(name, F.col(f"g_{b.dim}.t"))
        share = share * (F.least(high, F.col(f"g_{b.dim}.hi")) - F.greatest(low, F.col(f"g_{b.dim}.lo"))) / float(cell)
    return cells.groupBy(*chart.names).agg(F.round(F.sum(F.col("n") * share), 2).alias("value"))


def bucket_spread_sql(source: str, chart: Chart, cell: int) -> str:
    dims = [b.dim for b in chart.bins]
    q = f"select {', '.join(f'({d} // {cell})::bigint as q_{d}' for d in dims)}, count(*) as n from ({source}) group by all"
    tables = ", ".join(f"(values {', '.join(f'({i}, {lo}, {hi})' for i, (lo, hi) in enumerate(zip(b.edges, b.edges[1:])))}) as g{i}(t, lo, hi)" for i, b in enumerate(chart.bins))
    cond = " and ".join(f"g{i}.lo < q_{d} * {cell} + {cell} and g{i}.hi > q_{d} * {cell}" for i, d in enumerate(dims))
    share = " * ".join(f"(least(q_{d} * {cell} + {cell}, g{i}.hi) - greatest(q_{d} * {cell}, g{i}.lo)) / {float(cell)}::double" for i, d in enumerate(dims))
    return f"select {', '.join(f'g{i}.t::bigint as {n}' for i, n in enumerate(chart.names))}, round(sum(n * {share}), 2) as value from ({q}), {tables} where {cond} group by all"


def haar(df: DataFrame, dim: str, width: int, levels: int, keep: int) -> DataFrame:
    """t, value: counts of 2**levels equal bins rebuilt from the average and the ``keep`` largest normalised Haar
    coefficients (ties: coarser level, then lower place)."""
    n = 2**levels
    counts = df.groupBy(F.floor(F.col(dim) * n / width).cast("int").alias("t")).agg(F.count("*").alias("v"))
    level = F.explode(F.sequence(F.lit(1), F.lit(levels))).alias("level")
    signed = counts.select("t", "v", level).withColumn("k", F.expr("shiftright(t, level)")).withColumn("sign", F.expr("1 - 2 * (shiftright(t, level - 1) % 2)"))
    coefficients = signed.groupBy("level", "k").agg(F.sum(F.col("v") * F.col("sign")).alias("d")).where("d <> 0")
    order = Window.orderBy(F.desc(F.abs("d") / F.sqrt(F.pow(F.lit(2.0), "level"))), F.desc("level"), "k")
    kept = coefficients.withColumn("r", F.row_number().over(order)).where(F.col("r") <= keep).drop("r")  # at most 2**levels rows
    bins = df.sparkSession.range(n).select(F.col("id").cast("int").alias("t"))
    each = bins.select("t", level).withColumn("k", F.expr("shiftright(t, level)")).withColumn("sign", F.expr("1 - 2 * (shiftright(t, level - 1) % 2)"))
    rebuilt = each.join(kept, ["level", "k"]).groupBy("t").agg(F.sum(F.col("d") * F.col("sign") / F.pow(F.lit(2.0), "level")).alias("x"))
    total = counts.agg((F.sum("v") / float(n)).alias("avg"))
    return bins.join(rebuilt, "t", "left").crossJoin(F.broadcast(total)).select(F.col("t").cast("long").alias("t"), F.round(F.coalesce("x", F.lit(0.0)) + F.col("avg"), 4).alias("value"))


def haar_sql(source: str, dim: str, width: int, levels: int, keep: int) -> str:
    n = 2**levels
    return f"""with c as (select ({dim} * {n} // {width})::int as t, count(*) as v from ({source}) group by all),
l as (select unnest(range(1, {levels + 1}))::int as level), b as (select unnest(range({n}))::int as t),
k as (select level, t >> level as k, sum(v * (1 - 2 * ((t >> (level - 1)) % 2))) as d from c, l group by all having d <> 0),
p as (select * from k order by abs(d) / sqrt(pow(2.0::double, level)) desc, level desc, k limit {keep}),
x as (select b.t, sum(d * (1 - 2 * ((b.t >> (p.level - 1)) % 2)) / pow(2.0::double, p.level)) as x from b join p on (b.t >> p.level) = p.k group by all)
select b.t::bigint as t, round(coalesce(x, 0) + (select sum(v) / {float(n)}::double from c), 4) as value from b left join x using (t)"""


def compressed_prefix(df: DataFrame, dim: str, width: int, cells: int) -> DataFrame:
    """q, upto: a 1-D prefix table without the entries equal to the one before; an answer reads the last entry at or
    below its edge."""
    counts = df.groupBy(F.floor(F.col(dim) * cells / width).cast("long").alias("q")).agg(F.count("*").alias("n"))
    return counts.select("q", F.sum("n").over(Window.orderBy("q").rowsBetween(Window.unboundedPreceding, 0)).alias("upto"))  # at most ``cells`` rows


def compressed_answers(table: DataFrame, edges: Sequence[int]) -> DataFrame:
    """t, value: counts between consecutive edges (in cells) by as-of lookups of the compressed table."""
    e = table.sparkSession.createDataFrame([(i, x) for i, x in enumerate(edges)], "i int, e bigint")
    both = e.select(F.col("e").alias("at"), F.lit(1).alias("edge"), "i", F.lit(None).cast("long").alias("upto")).union(table.select((F.col("q") + 1).alias("at"), F.lit(0), F.lit(None).cast("int"), "upto"))
    w = Window.orderBy("at", "edge").rowsBetween(Window.unboundedPreceding, 0)
    read = both.withColumn("f", F.coalesce(F.last("upto", True).over(w), F.lit(0))).where("edge = 1")
    return read.select((F.col("i").cast("long") - 1).alias("t"), (F.col("f") - F.lag("f").over(Window.orderBy("i"))).alias("value")).where("t >= 0")
