"""Saving and loading an index, the index as a readable source, and table functions over its cells."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import udtf

from apcube.operators.boxtree import Nodes
from apcube.operators.index import Extra, Index


def save(index: Index, path: str) -> None:
    """Cells, nodes and metadata as Parquet under ``path``; cells are clustered by leaf so that a query opens few files."""
    index.cells.repartition("leaf").sortWithinPartitions("leaf").write.mode("overwrite").parquet(f"{path}/cells")
    n, spark = index.nodes, index.cells.sparkSession
    rows = [(i, int(n.parent[i]), int(n.depth[i]), int(n.count[i]), bool(n.leaf[i]), n.lo[i].tolist(), n.hi[i].tolist()) for i in range(len(n.lo))]
    spark.createDataFrame(rows, "node int, parent int, depth int, n bigint, leaf boolean, lo array<bigint>, hi array<bigint>").coalesce(1).write.mode("overwrite").parquet(f"{path}/nodes")
    meta = {"dims": index.dims, "widths": index.widths.tolist(), "leaves": index.leaves.tolist(), "cells_per": index.cells_per.tolist(), "budget": index.budget, "aligned": index.aligned, "height": index.height, "grids": [int(g) for g in index.grids], "axes": list(index.axes), "extras": [[x.name, x.collect, x.merge, list(x.columns)] for x in index.extras]}
    spark.createDataFrame([(json.dumps(meta),)], "meta string").coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")


def load(spark: SparkSession, path: str) -> Index:
    meta = json.loads(spark.read.parquet(f"{path}/meta").first()["meta"])
    rows = spark.read.parquet(f"{path}/nodes").orderBy("node").collect()  # as many as nodes
    col = lambda k, kind: np.array([r[k] for r in rows], kind)
    nodes = Nodes(col("lo", np.int64), col("hi", np.int64), col("parent", int), col("depth", int), col("n", int), col("leaf", bool))
    out = Index(meta["dims"], np.array(meta["widths"]), nodes, np.array(meta["leaves"]), np.array(meta["cells_per"], np.int64), spark.read.parquet(f"{path}/cells"), meta["budget"], meta["aligned"], meta["height"], axes=tuple(meta["axes"]), extras=tuple(Extra(a, b, c, tuple(d)) for a, b, c, d in meta["extras"]))
    out.grids = meta["grids"]
    return out


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _ChartReader(DataSourceReader):
    """One partition per cell file; partial counts per file, to be added by the caller."""

    def __init__(self, options: dict):
        self.path = options["path"]
        dim, width, lo, hi = options["bins"].split(":")
        self.bin = (dim, int(width), int(lo), int(hi))
        self.where = [(d, int(a), int(b)) for d, a, b in (x.split(":") for x in options.get("where", "").split(",") if x)]

    def _files(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path if ":" in self.path else f"file://{self.path}")

    def partitions(self):
        from pyarrow import fs

        files, root = self._files()
        return [_File(f.path) for f in files.get_file_info(fs.FileSelector(f"{root}/cells")) if f.path.endswith(".parquet")]

    def read(self, partition: _File) -> Iterator[tuple]:
        import pyarrow.parquet as pq

        files, _ = self._files()
        dims = [self.bin[0], *(d for d, _, _ in self.where)]
        t = pq.read_table(files.open_input_file(partition.path), columns=[*(f"{p}_{d}" for d in dict.fromkeys(dims) for p in ("q", "c")), "n"])
        col = lambda k: t.column(k).to_numpy()
        ok = np.ones(t.num_rows, bool)
        for d, lo, hi in self.where:
            q, c = col(f"q_{d}"), col(f"c_{d}")
            ok &= (q >= (2 * lo + c - 1) // (2 * c)) & (q < (2 * hi + c - 1) // (2 * c))
        d, w, lo, hi = self.bin
        edges = np.arange(lo, hi + 1, w)
        q, c = col(f"q_{d}")[ok], col(f"c_{d}")[ok]
        t1 = ((2 * edges[:, None] + c - 1) // (2 * c) <= q).sum(axis=0) - 1
        fine = (t1 >= 0) & (t1 < len(edges) - 1)
        if fine.any():
            keys, at = np.unique(t1[fine], return_inverse=True)
            for k, n in zip(keys, np.bincount(at, col("n")[ok][fine])):
                yield int(k), int(n)


class ChartSource(DataSource):
    """``spark.read.format("apcube_chart")`` with options path, bins ``dim:width:lo:hi`` and where ``dim:lo:hi,...``."""

    @classmethod
    def name(cls) -> str:
        return "apcube_chart"

    def schema(self) -> str:
        return "t1 bigint, value bigint"

    def reader(self, schema) -> DataSourceReader:
        return _ChartReader(self.options)


@udtf(returnType="value: bigint")
class RangeAgg:
    """The count of a box from cells (q_x, c_x, q_y, c_y, n), edges to the nearest cell edge; partial sums per partition."""

    def __init__(self):
        self.total = 0

    def eval(self, row, lo_x: int, hi_x: int, lo_y: int, hi_y: int):
        inside = True
        for q, c, lo, hi in ((row["q_x"], row["c_x"], lo_x, hi_x), (row["q_y"], row["c_y"], lo_y, hi_y)):
            inside &= (2 * lo + c - 1) // (2 * c) <= q < (2 * hi + c - 1) // (2 * c)
        if inside:
            self.total += row["n"]

    def terminate(self):
        yield (self.total,)


@udtf(returnType="t1: bigint, lo: bigint, hi: bigint")
class GridCells:
    """The bins of a width between two edges."""

    def eval(self, lo: int, hi: int, width: int):
        for i, a in enumerate(range(lo, hi, width)):
            yield i, a, a + width


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("range_agg", RangeAgg)
    spark.udtf.register("grid_cells", GridCells)
