"""Other partitioners: sort-tile packing, k-d cuts, page-wise k-d cuts, quad tree and a uniform grid.

Each is a function of a point DataFrame with a total order (``key`` columns), built from windows and grouped
aggregates, that returns boxes: part, n, lo_<dim>, hi_<dim>. The SQL of the same boxes stands beside it.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from apcube.functions.scale import morton
from apcube.operators.boxtree import Nodes


def boxes(df: DataFrame, dims: Sequence[str], part: str = "part") -> DataFrame:
    """The bounding box and number of points of every part."""
    return df.groupBy(part).agg(F.count("*").alias("n"), *(f(d).alias(f"{p}_{d}") for d in dims for f, p in ((F.min, "lo"), (F.max, "hi"))))


def boxes_sql(source: str, dims: Sequence[str]) -> str:
    return f"select part, count(*) as n, {', '.join(f'min({d}) as lo_{d}, max({d}) as hi_{d}' for d in dims)} from ({source}) group by part"


def to_nodes(found: DataFrame, dims: Sequence[str]) -> Nodes:
    """The boxes of a partition (as many as parts) on the driver."""
    rows = found.orderBy("part").collect()
    lo, hi = (np.array([[r[f"{p}_{d}"] for d in dims] for r in rows], np.int64).reshape(len(rows), len(dims)) for p in ("lo", "hi"))
    return Nodes.of_boxes(lo, hi, np.array([r["n"] for r in rows]))


def _tiles(df: DataFrame, value: str, key: Sequence[str], tiles: int) -> DataFrame:
    """``df`` with ``tile``: the number of the row's equal share of its ``part``, by (value, key); earlier tiles take the
    surplus. No task orders a whole part: a histogram of the values (as many rows as scales) gives the value at each cut, and
    only rows of those values are ordered by their keys, to find the key there. The cuts, tiles - 1 a part, go to the driver
    and come back as a table to look up, so the plan of many levels stays a chain."""
    spark, v = df.sparkSession, F.col(value).cast("long").alias("__v")
    over = Window.partitionBy("part").orderBy("__v")
    hist = df.groupBy("part", v).agg(F.count("*").alias("__n"))
    hist = hist.withColumn("__before", F.sum("__n").over(over.rowsBetween(Window.unboundedPreceding, 0)) - F.col("__n")).withColumn("__all", F.sum("__n").over(Window.partitionBy("part")))
    start = lambda t: F.expr(f"__all div {tiles}") * t + F.least(F.lit(t), F.col("__all") % tiles)
    cuts = hist.withColumn("__k", F.explode(F.array(*(start(t) - F.col("__before") for t in range(1, tiles))))).where("__k >= 0 and __k < __n")
    found = cuts.select("part", "__v", "__k").collect()  # tiles - 1 rows a part
    at = spark.createDataFrame([(r["part"], r["__v"], r["__k"]) for r in found], "__p long, __w long, __k long")
    met = df.select("part", v, *key).join(F.broadcast(at.select("__p", "__w").distinct()), (F.col("part") == F.col("__p")) & (F.col("__v") == F.col("__w")), "left_semi")
    ranked = met.withColumn("__r", F.row_number().over(Window.partitionBy("part", "__v").orderBy(*key)) - 1)
    keys = ranked.join(F.broadcast(at.distinct()), (F.col("part") == F.col("__p")) & (F.col("__v") == F.col("__w")) & (F.col("__r") == F.col("__k")))
    firsts = keys.select("part", F.struct("__v", *key).alias("c")).groupBy("part").agg(F.collect_list("c").alias("__cuts"))
    known = spark.createDataFrame(firsts.collect(), firsts.schema).withColumnRenamed("part", "__p")  # a row a part
    row = F.struct(v, *key)
    placed = df.join(F.broadcast(known), F.col("part") == F.col("__p"), "left").withColumn("__row", row)
    tile = F.coalesce(F.size(F.filter("__cuts", lambda c: c <= F.col("__row"))), F.lit(0))
    return placed.withColumn("tile", F.when(F.col("__cuts").isNull(), 0).otherwise(tile)).drop("__p", "__cuts", "__row")


def str_parts(df: DataFrame, dims: Sequence[str], key: Sequence[str], slabs: int) -> DataFrame:
    """Sort-tile packing: ``slabs`` equal slabs along the first dimension, each cut likewise along the next."""
    out = df.withColumn("part", F.lit(0))
    for d in dims:
        out = _tiles(out, d, key, slabs).withColumn("part", F.col("part") * slabs + F.col("tile")).drop("tile")
    return out


def str_sql(source: str, dims: Sequence[str], key: Sequence[str], slabs: int) -> str:
    q = f"select *, 0 as part from ({source})"
    for d in dims:
        q = f"select * exclude (part), part * {slabs} + ntile({slabs}) over (partition by part order by {', '.join([d, *key])}) - 1 as part from ({q})"
    return q


def _spread(dims: Sequence[str], widths: dict[str, int], quote: bool = False) -> list[str]:
    return [f"(max({d}) over p - min({d}) over p)::double / {widths[d]}" for d in dims]


def kd_parts(df: DataFrame, dims: Sequence[str], widths: dict[str, int], key: Sequence[str], depth: int, fanout: int = 2) -> DataFrame:
    """Cuts every part into ``fanout`` equal shares along its relatively widest dimension, ``depth`` times. A tie of
    widths goes to the first dimension; the earlier shares take the surplus points."""
    out = df.withColumn("part", F.lit(0))
    for _ in range(depth):
        spread = [(F.max(d) - F.min(d)) / F.lit(float(widths[d])) for d in dims]
        sides = out.groupBy("part").agg(*(x.alias(f"__w{i}") for i, x in enumerate(spread)))
        sides = df.sparkSession.createDataFrame(sides.collect(), sides.schema)  # a row a part
        top = F.greatest(*(f"__w{i}" for i in range(len(dims)))) if len(dims) > 1 else F.col("__w0")
        axis = F.lit(len(dims) - 1)
        for i in reversed(range(len(dims) - 1)):
            axis = F.when(F.col(f"__w{i}") == top, F.lit(i)).otherwise(axis)
        out = out.join(F.broadcast(sides.select("part", axis.alias("__axis"))), "part").withColumn("__value", F.element_at(F.array(*dims), F.col("__axis") + 1))
        out = _tiles(out, "__value", key, fanout).withColumn("part", F.col("part") * fanout + F.col("tile")).drop("tile", "__axis", "__value")
    return out


def kd_sql(source: str, dims: Sequence[str], widths: dict[str, int], key: Sequence[str], depth: int, fanout: int = 2) -> str:
    q = f"select *, 0 as part from ({source})"
    spread = _spread(dims, widths)
    for _ in range(depth):
        q = f"select *, {', '.join(f'{s} as w{i}' for i, s in enumerate(spread))} from ({q}) window p as (partition by part)"
        top = f"greatest({', '.join(f'w{i}' for i in range(len(dims)))})"
        value = "case " + " ".join(f"when w{i} = {top} then {d}" for i, d in enumerate(dims)) + " end"
        q = f"select * exclude (part, v, {', '.join(f'w{i}' for i in range(len(dims)))}), part * {fanout} + ntile({fanout}) over (partition by part order by v, {', '.join(key)}) - 1 as part from (select *, {value} as v from ({q}))"
    return q


def quad_parts(df: DataFrame, dims: Sequence[str], bits: int, cap: int, levels: int) -> DataFrame:
    """A quad tree over the domain [0, 2**bits) of every dimension: a cell is cut while it holds more than ``cap`` points,
    ``levels`` times at most. ``part`` is the Morton prefix with a leading one, so cells of all sizes have own numbers."""
    k = len(dims)
    z = F.shiftright(morton([F.col(d) for d in dims], bits), (bits - levels) * k)
    # counts of the finest cells, then of all cells above them; a cell is cut while it is too full, and so are those above it
    finest = df.groupBy(z.alias("__f")).agg(F.count("*").alias("__n"))
    each = finest.withColumn("__level", F.explode(F.sequence(F.lit(0), F.lit(levels - 1)))).withColumn("__cell", F.expr(f"shiftright(__f, ({levels} - __level) * {k})"))
    full = each.groupBy("__level", "__cell").agg(F.sum("__n").alias("__all")).where(F.col("__all") > cap)
    depth = each.join(full, ["__level", "__cell"], "left_semi").groupBy("__f").agg(F.count("*").cast("int").alias("__d"))
    out = df.withColumn("__f", z).join(depth, "__f", "left").withColumn("__d", F.coalesce("__d", F.lit(0)))
    return out.withColumn("part", F.expr(f"shiftleft(1L, __d * {k}) | shiftright(__f, ({levels} - __d) * {k})")).drop("__f", "__d")


def quad_sql(source: str, dims: Sequence[str], bits: int, cap: int, levels: int) -> str:
    k = len(dims)
    z = " | ".join(f"(((({d} >> {b}) & 1)::bigint) << {b * k + (k - 1 - i)})" for b in range(bits) for i, d in enumerate(dims))
    q = f"select *, {z} as z, 1::bigint as part, false as done from ({source})"
    for level in range(1, levels + 1):
        q = f"select * replace (done or count(*) over (partition by part) <= {cap} as done) from ({q})"
        q = f"select * replace (case when done then part else (1::bigint << {level * k}) | (z >> {(bits - level) * k}) end as part) from ({q})"
    return q


def uniform_parts(df: DataFrame, dims: Sequence[str], widths: dict[str, int], per_dim: int) -> DataFrame:
    """A grid of equal boxes whatever the data."""
    part = F.lit(0).cast("long")
    for d in dims:
        part = part * per_dim + F.least(F.floor(F.col(d) * per_dim / widths[d]), F.lit(per_dim - 1))
    return df.withColumn("part", part)


def uniform_sql(source: str, dims: Sequence[str], widths: dict[str, int], per_dim: int) -> str:
    part = "0"
    for d in dims:
        part = f"({part}) * {per_dim} + least({d} * {per_dim} // {widths[d]}, {per_dim - 1})"
    return f"select *, {part} as part from ({source})"
