"""Progressive exploration: a coarse chart first, then finer levels under the parts that the user picks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame

from apcube.operators.index import Index
from apcube.plans.spec import Chart


def explore(index: Index, chart: Chart, levels: int, pick: int = 0) -> Iterator[tuple[int, DataFrame]]:
    """(depth, chart) from depth 1 to ``levels``. With ``pick`` > 0 only the densest ``pick`` grids of a level stay in view,
    and the next level reads only nodes that meet them."""
    seen: np.ndarray | None = None
    for depth in range(1, levels + 1):
        level = index.at_depth(min(depth, index.height)) if depth < index.height else index
        leaves = None if seen is None else [i for i, n in enumerate(level.leaves) if _meets(level, n, seen)]
        got = level.chart(chart, leaves=leaves)
        yield depth, got
        if pick:
            top = got.orderBy("value", *chart.names, ascending=[False, *([True] * len(chart.names))]).limit(pick).collect()
            edges = [b.array for b in chart.bins]
            seen = np.array([[(e[r[n]], e[r[n] + 1]) for e, n in zip(edges, chart.names)] for r in top])


def _meets(index: Index, node: int, grids: np.ndarray) -> bool:
    k = grids.shape[1]
    return bool(((grids[:, :, 0] <= index.nodes.hi[node, :k]) & (grids[:, :, 1] > index.nodes.lo[node, :k])).all(axis=1).any())
