"""Further descriptors and builds: cross sums, category cells, equal-count edges, outlier rows, other skeletons."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from apcube.functions.scale import morton
from apcube.operators import boxtree
from apcube.operators.baselines import scan
from apcube.operators.boxtree import Nodes
from apcube.operators.index import Extra, Index, assign
from apcube.plans.spec import Chart, Tiling


def cross(a: str, b: str) -> tuple[Extra, ...]:
    """Sums and cross sums of two dimensions, as further descriptors of an index's cells."""
    wide = lambda x: f"cast({x} as decimal(38,0))"
    sums = {"sx": a, "sy": b, "sxx": f"{wide(a)} * {a}", "syy": f"{wide(b)} * {b}", "sxy": f"{wide(a)} * {b}"}
    return tuple(Extra(name, f"sum({x})", "sum", (a, b)) for name, x in sums.items())


def covariance(index: Index, chart: Chart | Tiling) -> DataFrame:
    """t.., n, cov, corr, slope of the two dimensions of ``cross`` per grid, from the index's cells."""
    t = index.assigned(chart).groupBy(*chart.names).agg(*(F.sum(c).cast("double").alias(c) for c in ("n", "sx", "sy", "sxx", "syy", "sxy")))
    n, cov = F.col("n"), F.col("sxy") / F.col("n") - F.col("sx") * F.col("sy") / (F.col("n") * F.col("n"))
    vx, vy = (F.col(f"s{v}{v}") / n - (F.col(f"s{v}") / n) ** 2 for v in "xy")
    corr = F.when((n > 1) & (vx > 0) & (vy > 0), cov / F.sqrt(vx * vy)).otherwise(0.0)
    slope = F.when((n > 1) & (vx > 0), cov / vx).otherwise(0.0)
    return t.select(*chart.names, n.cast("long").alias("n"), F.round(cov, 0).alias("cov"), F.round(corr, 4).alias("corr"), F.round(slope, 4).alias("slope"))


def sketch(column: str) -> Extra:
    """A mergeable sketch of the distinct values of a column, as a further descriptor."""
    return Extra(f"hll_{column}", f"hll_sketch_agg({column})", "hll_union_agg", (column,))


def distinct(index: Index, chart: Chart | Tiling, column: str) -> DataFrame:
    """t.., value: about how many values of the column each grid has, from the sketches of its cells."""
    return index.assigned(chart).groupBy(*chart.names).agg(F.expr(f"hll_sketch_estimate(hll_union_agg(hll_{column}))").alias("value"))


def depth_edges(index: Index, dim: str, bins: int) -> tuple[int, ...]:
    """Edges of ``bins`` bins of about equal counts from the cells along one dimension; no record is read."""
    i = index.dims.index(dim)
    rows = index.cells.groupBy((F.col(f"q_{dim}") * F.col(f"c_{dim}")).alias("at")).agg(F.sum("n").alias("n")).orderBy("at").collect()  # at most one row a cell edge
    at, n = (np.array([r[k] for r in rows], np.int64) for k in ("at", "n"))
    upto = np.cumsum(n)
    inner = [int(at[min(np.searchsorted(upto, upto[-1] * k / bins) + 1, len(at) - 1)]) for k in range(1, bins)]
    return tuple(sorted({0, *inner, int(index.widths[i])}))


def stratified(df: DataFrame, stratum: str, key: str, quota: int) -> DataFrame:
    """``quota`` rows of every stratum, chosen by a hash of the key; rows beyond a hash bound that surely holds the quota
    never reach the window."""
    h = F.pmod(F.col(key) * F.lit(2654435761), F.lit(1 << 20))
    sizes = df.groupBy(stratum).agg(F.count("*").alias("__n"))
    bounded = df.join(sizes, stratum).where(h < F.greatest(F.lit(4096.0), F.lit(8.0 * quota * (1 << 20)) / F.col("__n")))
    w = Window.partitionBy(stratum).orderBy(h, key)
    return bounded.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= quota).drop("__r", "__n")


class OutlierStore:
    """An index whose thinnest ``share`` of leaves keep their records as rows, stored once, clustered by leaf, under ``path``;
    the other leaves keep cells alone. Charts add both; outliers are read exactly, whatever the bins."""

    def __init__(self, df: DataFrame, index: Index, share: float, path: str):
        n = index.nodes
        area = ((n.hi[index.leaves] - n.lo[index.leaves] + 1) / index.widths).prod(axis=1)
        density = n.count[index.leaves] / area
        self.thin = np.argsort(density, kind="stable")[: int(share * len(density))].tolist()
        placed = assign(df.select(*index.dims).dropna(), index.dims, n, index.leaves, index.widths).where(F.col("leaf").isin(self.thin))
        placed.repartition("leaf").sortWithinPartitions("leaf").write.parquet(path)
        self.index, self.rows = index, df.sparkSession.read.schema(placed.schema).parquet(path)
        self.dense = [i for i in range(len(index.leaves)) if i not in set(self.thin)]

    def chart(self, chart: Chart) -> DataFrame:
        met = set(self.index.candidates(chart).tolist())
        rows = scan(self.rows.where(F.col("leaf").isin([i for i in self.thin if i in met])), chart)
        cells = self.index.chart(chart, leaves=[i for i in self.dense if i in met])
        return rows.union(cells).groupBy(*chart.names).agg(F.sum("value").alias("value"))


def kmeans_nodes(df: DataFrame, dims: Sequence[str], widths: dict[str, int], k: int, seed: int = 6) -> Nodes:
    """The bounding boxes of k-means clusters (on shares of the domain) as a partition."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    scaled = df.select(*dims, *((F.col(d) / widths[d]).alias(f"s_{d}") for d in dims))
    points = VectorAssembler(inputCols=[f"s_{d}" for d in dims], outputCol="features").transform(scaled)
    model = KMeans(k=k, seed=seed, maxIter=10).fit(points)
    found = model.transform(points).groupBy(F.col("prediction").alias("part")).agg(F.count("*").alias("n"), *(f(d).alias(f"{p}_{d}") for d in dims for f, p in ((F.min, "lo"), (F.max, "hi")))).orderBy("part").collect()  # k rows
    lo, hi = (np.array([[r[f"{p}_{d}"] for d in dims] for r in found], np.int64) for p in ("lo", "hi"))
    return Nodes.of_boxes(lo, hi, np.array([r["n"] for r in found]))


def build_distributed(sample: DataFrame, dims: Sequence[str], widths: dict[str, int], trees: int, leaves: int) -> Nodes:
    """A skeleton from a sample too large for the driver: the sample is dealt by ranges of its Morton code, executors grow
    one tree each, and the trees hang under a common root. Only node boxes reach the driver."""
    bits = max(int(widths[d] - 1).bit_length() for d in dims)
    dealt = sample.select(*dims, morton([F.col(d) for d in dims], bits).alias("z"))
    cuts = dealt.approxQuantile("z", [i / trees for i in range(1, trees)], 0.001)
    part = F.lit(0)
    for c in cuts:
        part = part + (F.col("z") > c).cast("int")
    w = np.array([widths[d] for d in dims], float)
    per = max(1, leaves // trees)

    def grow(group: pa.Table) -> pa.Table:
        x = np.stack([group.column(d).to_numpy() for d in dims], axis=1)
        n = boxtree.build(x, w, target_leaves=per)
        return pa.table([np.full(len(n.lo), group.column("part")[0].as_py(), np.int32), np.arange(len(n.lo)), n.parent, n.depth, n.count, n.leaf, [*n.lo.tolist()], [*n.hi.tolist()]], ["part", "node", "parent", "depth", "n", "leaf", "lo", "hi"])

    rows = dealt.withColumn("part", part).groupBy("part").applyInArrow(grow, "part int, node bigint, parent bigint, depth bigint, n bigint, leaf boolean, lo array<bigint>, hi array<bigint>").orderBy("part", "node").collect()
    lo, hi, parent, depth, count, leaf, base, last = [], [], [], [], [], [], 1, None
    for r in rows:
        if r["part"] != last:
            base, last = 1 + len(lo), r["part"]
        lo.append(r["lo"])
        hi.append(r["hi"])
        parent.append(0 if r["parent"] < 0 else base + r["parent"])
        depth.append(r["depth"] + 1)
        count.append(r["n"])
        leaf.append(r["leaf"])
    a, b = np.array(lo, np.int64), np.array(hi, np.int64)
    return Nodes(np.vstack([a.min(axis=0), a]), np.vstack([b.max(axis=0), b]), np.array([-1, *parent]), np.array([1, *depth]), np.array([sum(c for c, p in zip(count, parent) if p == 0), *count]), np.array([False, *leaf]))
