"""An opened index on the driver: prefix arrays in memory, charts without a Spark job.

For indexes whose dense arrays are known to be small (the budget per leaf bounds them); larger ones answer as DataFrames.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import functions as F

from apcube.operators.index import Index, grids
from apcube.plans.spec import Chart

#: Bytes of arrays that ``LocalIndex`` takes to the driver at most.
MOST_BYTES = 1 << 30


class LocalIndex:
    def __init__(self, index: Index, most_bytes: int = MOST_BYTES):
        if index.axes:
            raise ValueError("an index with axes isn't opened on the driver")
        need = 8 * (index.prefix().agg(F.sum(F.size("sums").cast("long"))).first()[0] or 0)
        if need > most_bytes:
            raise MemoryError(f"the index needs {need} bytes on the driver; {most_bytes} are allowed")
        self.index, self.leaves = index, {}
        for r in index.prefix().collect():  # of checked size
            self.leaves.setdefault(r["leaf"], []).append((np.array(r["sums"], np.int64).reshape(4, *r["shape"]), r["origin"], r["width"]))

    def chart(self, chart: Chart, snap: str = "nearest", leaves: Sequence[int] | None = None) -> np.ndarray:
        """The values of all grids, empty ones 0 (NaN for a mean), as an array of the chart's shape."""
        edges, dims = chart.edges(), self.index.dims
        charted = [b.dim for b in chart.bins]
        order = [0, *(1 + dims.index(d) for d in charted), *(1 + i for i, d in enumerate(dims) if d not in charted)]
        total = np.zeros((4, *(len(b.edges) - 1 for b in chart.bins)), float if snap == "interp" else np.int64)
        for leaf in self.index.candidates(chart) if leaves is None else leaves:
            for sums, origin, width in self.leaves.get(leaf, ()):
                v = grids(sums, origin, width, [edges.get(d) for d in dims], snap)
                total += v.transpose(order).reshape(total.shape)
        n, s, s2 = total[0], total[1], total[2] * float(1 << 32) + total[3]
        with np.errstate(invalid="ignore", divide="ignore"):
            return {"count": n, "sum": s, "mean": s / n, "var": s2 / n - (s / n) ** 2, "std": np.sqrt(np.maximum(s2 / n - (s / n) ** 2, 0))}[chart.agg]
