"""Connected components by alternating large-star and small-star steps, as DataFrame joins and aggregations.

Each step rewrites the edge list so that every node points at a smaller one; the minimum of a component ends as the
neighbour of all its members. No node's neighbours are gathered into one row: a step is a grouped minimum and a join,
so that a hub with very many neighbours is combined before the shuffle and its join side can be split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from apcube.llm.storage import drop, materialize


def _large_star(edges: DataFrame) -> DataFrame:
    """edges (u > v). Every larger neighbour of a node is tied to the least of the node's neighbours and itself."""
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    # neighbours larger than the node are exactly the edges read backwards
    up = edges.select(F.col("v").alias("u"), F.col("u").alias("w"))
    return up.join(least, "u").select(F.col("w").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    """Every smaller neighbour of a node, and the node, is tied to the least of them."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    down = edges.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return down.union(least.select("u", F.col("m").alias("v")))


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Rows (node, component) for the nodes that ``edges`` name: the least node of each component.

    Self-loops, repeated and reversed edges and nulls are harmless (a row with a null end links nothing). No edges give
    no rows. Every round is written to the shared folder; the rounds end when an edge list is a star forest, that is
    when a round changes nothing.
    """
    ends = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"), F.col(a).alias("x"), F.col(b).alias("y"))
    now = materialize(ends.where("x is not null and y is not null and u > v").select("u", "v").distinct(), "edges")
    mark = None
    while True:
        sums = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).first()
        if sums["n"] == 0 or (sums["n"], sums["s"]) == mark:
            break
        mark = (sums["n"], sums["s"])
        new = materialize(_small_star(_large_star(now).distinct()).distinct(), "edges")
        drop(now)
        now = new
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots)
