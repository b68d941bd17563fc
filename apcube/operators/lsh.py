"""Locality-sensitive hashing of boxes: p-stable directions, sampled projections, and overlap tests as equi-joins.

Boxes are DataFrames (id, lo_<dim>, hi_<dim>); coordinates are taken as shares of the domain. A projection of a box on a
direction is an interval; evenly spaced samples of it are hashed to buckets of width r. Two boxes are candidates when
every direction has a shared bucket; ``verify`` then tests the boxes themselves.

Schemes: ``plain`` keeps all samples of a direction in one table; ``reversed`` has one table per sample, stored samples
ascending and query samples descending; ``probe`` is reversed with both neighbouring buckets; ``edges`` hashes points on the
boxes' edges instead. What each finds depends on the bucket width r against the step between samples, which
``Family.fitted`` takes from the boxes' extents:

* plain, edges: with steps of at most r the samples of an interval hit every bucket that it meets, so overlapping boxes
  share one on every direction and none is missed.
* probe: where two boxes overlap, the difference of the ascending and the descending sample changes its sign between two
  tables, so in one it is at most half the sum of both steps; r of that size misses none.
* reversed: the tables around that place both miss where a bucket ends between the two samples, with a probability of
  about a quarter of (sum of both steps) / r a direction. r is 16 times that sum, so about 0.985 a direction are found.
* combined: inner nodes are hashed as well, and every hit one is descended by exact tests.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Family:
    """``a``: directions x dimensions, ``b``: offsets in [0, r). Coefficients are rounded so that they can be written out."""

    dims: tuple[str, ...]
    widths: tuple[int, ...]
    a: tuple[tuple[float, ...], ...]
    b: tuple[float, ...]
    r: float

    @classmethod
    def draw(cls, dims: Sequence[str], widths: Sequence[int], directions: int = 3, r: float = 0.1, seed: int = 4) -> Family:
        g = np.random.default_rng(seed)
        a = np.round(g.normal(size=(directions, len(dims))), 4)
        return cls(tuple(dims), tuple(int(w) for w in widths), tuple(map(tuple, a.tolist())), tuple(np.round(g.uniform(0, r, directions), 4).tolist()), r)

    @classmethod
    def fitted(cls, dims: Sequence[str], widths: Sequence[int], boxes: DataFrame, queries: DataFrame, directions: int = 3, samples: int = 6, scheme: str = "plain", seed: int = 4) -> Family:
        """A family whose r suits ``samples`` of the largest of these boxes under ``scheme``; one aggregate over each table."""
        family = cls.draw(dims, widths, directions, 1.0, seed)
        wide = []
        for df in (boxes, queries):
            spans = [b - a for a, b in (family.interval(i) for i in range(directions))] if scheme != "edges" else [F.abs((F.col(f"hi_{d}") - F.col(f"lo_{d}")) * (c / w)) for a in family.a for d, c, w in zip(dims, a, widths)]
            got = df.agg(*(F.max(x).alias(f"s{i}") for i, x in enumerate(spans))).first()
            wide.append(max((x for x in got if x is not None), default=0.0) / max(samples - 1, 1))
        r = {"plain": max(wide), "edges": max(wide), "probe": sum(wide) / 2, "reversed": 16 * sum(wide)}[scheme]
        r = max(round(1.001 * r + 5e-5, 4), 0.001)
        return cls.draw(dims, widths, directions, r, seed)

    def point(self, i: int) -> Column:
        """The bucket of a point on direction i."""
        terms = [F.col(d) * F.lit(c) / F.lit(float(w)) for d, c, w in zip(self.dims, self.a[i], self.widths)]
        return F.floor((sum(terms[1:], terms[0]) + F.lit(self.b[i])) / F.lit(self.r)).cast("long")

    def point_sql(self, i: int) -> str:
        terms = " + ".join(f"{d} * ({c}::double) / {float(w)}::double" for d, c, w in zip(self.dims, self.a[i], self.widths))
        return f"floor(({terms} + {self.b[i]}::double) / {self.r}::double)::bigint"

    def interval(self, i: int) -> tuple[Column, Column]:
        ends = []
        for first, second in (("lo", "hi"), ("hi", "lo")):
            terms = [F.col(f"{first if c >= 0 else second}_{d}") * F.lit(c) / F.lit(float(w)) for d, c, w in zip(self.dims, self.a[i], self.widths)]
            ends.append(sum(terms[1:], terms[0]))
        return ends[0], ends[1]

    @property
    def directions(self) -> int:
        return len(self.a)


def points_keys(points: DataFrame, family: Family, id_col: str) -> DataFrame:
    """id, dir, bucket of points."""
    return points.select(F.col(id_col).alias("id"), F.posexplode(F.array(*(family.point(i) for i in range(family.directions)))).alias("dir", "bucket"))


def box_keys(boxes: DataFrame, family: Family, samples: int, descending: bool = False, probe: int = 0) -> DataFrame:
    """id, dir, table, bucket: the samples of each box's projections."""
    spans = F.array(*(F.struct(lo.alias("lo"), hi.alias("hi"), F.lit(b).alias("b")) for (lo, hi), b in ((family.interval(i), family.b[i]) for i in range(family.directions))))
    df = boxes.select("id", F.posexplode(spans).alias("dir", "s")).withColumn("table", F.explode(F.sequence(F.lit(0), F.lit(samples - 1))))
    step = F.col("table") / F.lit(float(max(samples - 1, 1)))
    at = F.col("s.hi") - (F.col("s.hi") - F.col("s.lo")) * step if descending else F.col("s.lo") + (F.col("s.hi") - F.col("s.lo")) * step
    bucket = F.floor((at + F.col("s.b")) / F.lit(family.r)).cast("long")
    if probe:
        bucket = F.explode(F.array(*(bucket + k for k in range(-probe, probe + 1))))
    return df.select("id", "dir", "table", bucket.alias("bucket")).distinct()


def edge_keys(boxes: DataFrame, family: Family, samples: int) -> DataFrame:
    """id, dir, table (0), bucket of evenly spaced points on the edges of each box."""
    d = len(family.dims)
    places = []
    for axis in range(d):
        for corner in product((0.0, 1.0), repeat=d - 1):
            for j in range(samples):
                rest = list(corner)
                rest.insert(axis, j / max(samples - 1, 1))
                places.append(rest)
    df = boxes.withColumn("w", F.explode(F.array(*(F.array(*map(F.lit, p)) for p in places))))
    df = df.select("id", *((F.col(f"lo_{n}") + (F.col(f"hi_{n}") - F.col(f"lo_{n}")) * F.col("w")[i]).alias(n) for i, n in enumerate(family.dims)))
    return points_keys(df, family, "id").select("id", "dir", F.lit(0).alias("table"), "bucket").distinct()


def candidates(stored: DataFrame, asked: DataFrame, directions: int, by_table: bool) -> DataFrame:
    """(query, box) pairs that share a bucket on every direction."""
    keys = ["dir", "bucket", *(["table"] if by_table else [])]
    met = stored.withColumnRenamed("id", "box").join(asked.withColumnRenamed("id", "query"), keys)
    return met.groupBy("query", "box").agg(F.countDistinct("dir").alias("d")).where(F.col("d") == directions).select("query", "box")


def verify(pairs: DataFrame, boxes: DataFrame, queries: DataFrame, dims: Sequence[str]) -> DataFrame:
    """Pairs whose closed boxes meet on every dimension."""
    b = boxes.select(F.col("id").alias("box"), *(F.col(f"{p}_{d}").alias(f"b_{p}_{d}") for d in dims for p in ("lo", "hi")))
    q = queries.select(F.col("id").alias("query"), *(F.col(f"{p}_{d}").alias(f"q_{p}_{d}") for d in dims for p in ("lo", "hi")))
    joined = pairs.join(b, "box").join(q, "query")
    for d in dims:
        joined = joined.where((F.col(f"b_lo_{d}") <= F.col(f"q_hi_{d}")) & (F.col(f"b_hi_{d}") >= F.col(f"q_lo_{d}")))
    return joined.select("query", "box")


def overlap(boxes: DataFrame, queries: DataFrame, family: Family, samples: int = 4, scheme: str = "reversed") -> DataFrame:
    """Verified (query, box) pairs by one of the schemes."""
    if scheme == "edges":
        found = candidates(edge_keys(boxes, family, samples), edge_keys(queries, family, samples), family.directions, False)
    elif scheme == "plain":
        flat = lambda df: df.select("id", "dir", "bucket").distinct()
        found = candidates(flat(box_keys(boxes, family, samples)), flat(box_keys(queries, family, samples)), family.directions, False)
    elif scheme in ("reversed", "probe"):
        found = candidates(box_keys(boxes, family, samples), box_keys(queries, family, samples, True, int(scheme == "probe")), family.directions, True)
    else:
        raise ValueError(f"unknown scheme {scheme}")
    return verify(found, boxes, queries, family.dims)


def overlap_scan(boxes: DataFrame, queries: DataFrame, dims: Sequence[str]) -> DataFrame:
    """All (query, box) pairs that overlap, by testing every query with every box: the truth that searches are measured
    against. ``boxes`` is a list on the driver (leaves of an index), ``queries`` may be any table and isn't shuffled."""
    rows = boxes.select("id", *(f"{p}_{d}" for d in dims for p in ("lo", "hi"))).collect()  # as many as leaves
    known = boxes.sparkSession.sparkContext.broadcast(([r["id"] for r in rows], *(np.array([[r[f"{p}_{d}"] for d in dims] for r in rows], float).reshape(len(rows), len(dims)) for p in ("lo", "hi"))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, lo, hi = known.value
        for b in batches:
            if b.num_rows and len(ids):
                qlo, qhi = (np.stack([b.column(f"{p}_{d}").to_numpy(zero_copy_only=False) for d in dims], axis=1) for p in ("lo", "hi"))
                step = max(1, (1 << 22) // max(1, lo.size))
                for start in range(0, len(qlo), step):
                    part = slice(start, start + step)
                    i, j = np.nonzero(((lo[None] <= qhi[part, None]) & (hi[None] >= qlo[part, None])).all(axis=2))
                    yield pa.RecordBatch.from_arrays([b.column("id").take(pa.array(i + start)), pa.array(np.array(ids)[j], pa.int64())], ["query", "box"])

    return queries.mapInArrow(run, f"query {queries.schema['id'].dataType.simpleString()}, box bigint")


def overlap_combined(nodes: DataFrame, queries: DataFrame, family: Family, samples: int = 4, scheme: str = "plain") -> DataFrame:
    """nodes: id, parent, is_leaf, boxes. Inner nodes are hashed too; every hit inner node is descended by exact tests,
    level by level, to the leaves: as many joins as the tree has levels."""
    kinds = nodes.select(F.col("id").alias("box"), "is_leaf")
    hits = overlap(nodes, queries, family, samples, scheme).join(kinds, "box").persist()
    leaves, frontier = hits.where("is_leaf").select("query", "box"), hits.where("not is_leaf").select("query", "box")
    kids = nodes.select(F.col("id").alias("kid"), F.col("parent").alias("box"))
    held = [hits]
    while not frontier.isEmpty():
        below = frontier.join(kids, "box").select("query", F.col("kid").alias("box")).distinct()
        held.append(verify(below, nodes, queries, family.dims).join(kinds, "box").persist())
        leaves = leaves.union(held[-1].where("is_leaf").select("query", "box"))
        frontier = held[-1].where("not is_leaf").select("query", "box")
    out = leaves.distinct().persist()
    out.count()  # the levels are done with
    for df in held:
        df.unpersist()
    return out


def finder(dims: Sequence[str], widths: Sequence[int], directions: int = 2, samples: int = 8):
    """For ``index.build(find=...)``: leaves of points through buckets. Points meet the leaves whose sampled projections
    share a bucket with theirs on every direction; of those that hold the point the smallest (then the first) takes it,
    and points in no leaf go to the nearest as in ``assign``."""

    def find(points: DataFrame, nodes) -> DataFrame:
        from apcube.operators.index import assign

        at, spark = nodes.leaves, points.sparkSession
        area = ((nodes.hi[at] - nodes.lo[at] + 1) / np.array(widths, float)).prod(axis=1)
        rows = [(i, float(area[i]), *(int(x) for x in nodes.lo[n]), *(int(x) for x in nodes.hi[n])) for i, n in enumerate(at)]
        boxes = spark.createDataFrame(rows, ", ".join(["id int", "area double", *(f"lo_{d} bigint" for d in dims), *(f"hi_{d} bigint" for d in dims)])).persist()
        family = Family.fitted(dims, widths, boxes, boxes, directions, samples, "plain")
        keys = box_keys(boxes, family, samples).select("id", "dir", "bucket").distinct()
        held = points
        for i in range(directions):
            # per direction and bucket the list of leaves, as many rows as buckets; a point keeps the leaves in all lists
            lists = keys.where(F.col("dir") == i).groupBy("bucket").agg(F.collect_list(F.col("id")).alias(f"__l{i}")).withColumnRenamed("bucket", f"__b{i}")
            held = held.withColumn(f"__b{i}", family.point(i)).join(F.broadcast(lists), f"__b{i}", "left").drop(f"__b{i}")
        found = F.col("__l0")
        for i in range(1, directions):
            found = F.array_intersect(found, f"__l{i}")
        # leaves are told apart by their boxes' entries in one literal row per leaf number
        number = F.array(*(F.struct(F.lit(r[1]).alias("area"), F.lit(r[0]).alias("leaf"), *(F.lit(r[2 + k]).alias(f"lo_{d}") for k, d in enumerate(dims)), *(F.lit(r[2 + len(dims) + k]).alias(f"hi_{d}") for k, d in enumerate(dims))) for r in rows))
        inside = lambda x: F.forall(F.array(*(F.col(d).between(x[f"lo_{d}"], x[f"hi_{d}"]) for d in dims)), lambda ok: ok)
        best = F.array_min(F.transform(F.filter(F.transform(found, lambda i: F.get(number, i)), inside), lambda x: F.struct(x["area"].alias("area"), x["leaf"].alias("leaf"))))
        held = held.withColumn("__leaf", best["leaf"]).drop(*(f"__l{i}" for i in range(directions)))
        inner = held.where("__leaf is not null").withColumn("leaf", F.col("__leaf")).drop("__leaf")
        return inner.unionByName(assign(held.where("__leaf is null").drop("__leaf"), dims, nodes, at, np.array(widths, float)))

    return find


def point_in_range(points: DataFrame, boxes: DataFrame, family: Family, samples: int, id_col: str) -> DataFrame:
    """Verified (point, box): the point lies in the box and shares a bucket with a sample of it on every direction.

    ``samples`` so many that a step is at most r makes a point inside meet its box or a neighbouring bucket; both
    neighbours are probed."""
    keys = box_keys(boxes, family, samples, probe=1).select("id", "dir", "bucket").distinct()
    found = candidates(keys, points_keys(points, family, id_col), family.directions, False).withColumnRenamed("query", "point")
    b = boxes.withColumnRenamed("id", "box")
    joined = found.join(b, "box").join(points.withColumnRenamed(id_col, "point"), "point")
    for d in family.dims:
        joined = joined.where(F.col(d).between(F.col(f"lo_{d}"), F.col(f"hi_{d}")))
    return joined.select("point", "box")


def bucket_stats(keys: DataFrame, by: Sequence[str]) -> DataFrame:
    """Number of buckets, and mean, 90th percentile and largest number of boxes in one."""
    sizes = keys.groupBy(*by).agg(F.countDistinct("id").alias("n"))
    return sizes.agg(F.count("*").alias("buckets"), F.round(F.avg("n"), 4).alias("mean_size"), F.expr("percentile(n, 0.9)").alias("p90"), F.max("n").alias("largest"))
