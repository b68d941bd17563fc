"""The registry of queries, and indexes shared by the queries of a session."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from apcube.operators import index as core
from apcube.operators.boxtree import Nodes
from apcube.sources.tables import VIEWS, view

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
_BUILT: dict[tuple, core.Index] = {}
MOST_KEPT = 24

#: How each view is indexed: dimensions, the key that samples by, sampling rate and bin widths that cells divide.
INDEXED = {
    "plane": (("x", "y"), "event_id", {"x": 7200, "y": 7200}),
    "checkin": (("x", "y", "wd", "hr", "t"), "event_id", {"x": 7200, "y": 7200, "wd": 1, "hr": 1, "t": 86400}),
    "gps": (("x", "y", "t", "k", "dir"), "event_id", {"x": 7200, "y": 7200, "t": 86400, "k": 10, "dir": 30}),
    "splom": (("qty", "price", "disc", "tax", "day"), "l_orderkey", {"qty": 10, "price": 10800, "disc": 1, "tax": 1, "day": 250}),
    "delay": (("price", "disc", "tax", "year", "month", "wd"), "l_orderkey", {"price": 10800, "disc": 1, "tax": 1, "year": 1, "month": 1, "wd": 1}),
    "hail": (("price", "cust", "month", "dom", "day"), "o_orderkey", {"price": 50000, "cust": 1500, "month": 1, "dom": 1, "day": 90}),
    "vec": (tuple(f"e{i}" for i in range(5)), "vec_id", {f"e{i}": 100 for i in range(5)}),
    "docs": (("chars", "tokens"), "doc_id", {"chars": 1000, "tokens": 100}),
    "geo": (("price",), "o_orderkey", {"price": 50000}),
}


def query(name: str, sql: str | None = None):
    """Registers a function under ``name``; with the SQL of the same rows where there is one."""

    def put(f):
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return put


def kept(cache: dict, mark: tuple, make: Callable[[], core.Index]) -> core.Index:
    """The index under ``mark``, made where there is none; beyond MOST_KEPT the oldest is released (and would be computed
    anew by a query that still holds it)."""
    if mark not in cache:
        cache[mark] = make()
        if len(cache) > MOST_KEPT:
            old = cache.pop(next(iter(cache)))
            old.cells.unpersist()
            if old._prefix is not None:
                old._prefix.unpersist()
    return cache[mark]


def indexed(spark: SparkSession, sf_dir: str, name: str, dims: tuple[str, ...] | None = None, measure: str | None = None, aligned: bool = True, rate: float = 1.0, nodes: Nodes | None = None, tag: str = "", grid: dict[str, int] | None = None, **options) -> core.Index:
    """The index of a view, built once a session, table folder and set of options. ``grid``: bin widths that cells divide, in
    place of the view's own."""
    all_dims, key, widths = INDEXED[name]
    dims = dims or all_dims
    grid = {d: (grid or widths).get(d, widths.get(d)) for d in dims} if aligned else None
    mark = (spark.sparkContext.applicationId, sf_dir, name, dims, measure, tuple((grid or {}).items()), rate, tag, tuple(sorted(options.items(), key=lambda kv: kv[0])))
    return kept(_BUILT, mark, lambda: core.build(view(spark, sf_dir, name), dims, VIEWS[name].widths, key, measure, rate=rate, grid_widths=grid, nodes=nodes, **options))


def measured(name: str, m: str) -> str:
    """SQL of a view with its measure as m."""
    return f"select *, {m} as m from ({VIEWS[name].sql})"


def boxes_of(spark: SparkSession, index: core.Index, every: bool = False) -> DataFrame:
    """id, parent, is_leaf, lo_<dim>, hi_<dim> of the leaves (or of all nodes)."""
    at = np.arange(len(index.nodes.lo)) if every else index.leaves
    leaf = set(index.leaves.tolist())
    rows = [(int(n), int(index.nodes.parent[n]), int(n) in leaf, *(int(x) for x in index.nodes.lo[n]), *(int(x) for x in index.nodes.hi[n])) for n in at]
    return spark.createDataFrame(rows, ", ".join(["id int", "parent int", "is_leaf boolean", *(f"lo_{d} bigint" for d in index.dims), *(f"hi_{d} bigint" for d in index.dims)]))
