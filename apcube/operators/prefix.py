"""Prefix tables and corner lookups as relations: chained windows, and joins of signed corners."""

from __future__ import annotations

from collections.abc import Sequence
from itertools import product

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def sat(df: DataFrame, width: dict[str, int], cells: dict[str, int]) -> DataFrame:
    """q_<dim>.., upto: the summed-area table of counts over a dense lattice of ``cells`` per dimension.

    One running sum per dimension, each over the rows of the one before; the lattice is small by the caller's choice and
    is laid out so that empty cells carry sums too."""
    dims = list(width)
    occupied = df.where(" and ".join(f"{d} >= 0 and {d} < {width[d] * cells[d]}" for d in dims)).groupBy(*(F.floor(F.col(d) / width[d]).cast("long").alias(f"q_{d}") for d in dims)).agg(F.count("*").alias("n"))
    lattice = df.sparkSession.range(1).select(F.lit(0).alias("z"))
    for d in dims:
        lattice = lattice.withColumn(f"q_{d}", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(cells[d] - 1).cast("long"))))
    out = lattice.drop("z").join(occupied, [f"q_{d}" for d in dims], "left").withColumn("upto", F.coalesce("n", F.lit(0)).cast("long")).drop("n")
    for d in dims:
        rest = [f"q_{o}" for o in dims if o != d]
        w = Window.partitionBy(*rest) if rest else Window.partitionBy(F.lit(0))
        out = out.withColumn("upto", F.sum("upto").over(w.orderBy(f"q_{d}").rowsBetween(Window.unboundedPreceding, 0)))
    return out


def corner_chart(table: DataFrame, dims: Sequence[str], per: int, bins: int) -> DataFrame:
    """t.., value: counts of equal bins of ``per`` cells from signed corners of the table; a corner counts positively when
    it takes an even number of low ends. Corners below the first cell are zero."""
    spark, k = table.sparkSession, len(dims)
    corners = [(*pick, 1 if sum(pick) % 2 == 0 else -1) for pick in product((0, 1), repeat=k)]
    signs = spark.createDataFrame(corners, ", ".join([*(f"low{i} int" for i in range(k)), "sign int"]))
    grids = spark.range(1).select(F.lit(0).alias("z"))
    for i in range(k):
        grids = grids.withColumn(f"t{i + 1}", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(bins - 1).cast("long"))))
    reads = grids.drop("z").crossJoin(F.broadcast(signs))  # 2**k rows
    for i, d in enumerate(dims):
        reads = reads.withColumn(f"q_{d}", (F.col(f"t{i + 1}") + 1 - F.col(f"low{i}")) * per - 1)
    names = [f"t{i + 1}" for i in range(k)]
    got = reads.join(table, [f"q_{d}" for d in dims]).groupBy(*names).agg(F.sum(F.col("upto") * F.col("sign")).alias("value"))
    return got.where("value <> 0")
