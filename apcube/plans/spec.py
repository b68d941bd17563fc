"""What a user asks for: bins, ranges and charts, checked before any job runs."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np

from apcube.functions.scale import chain

AGGREGATES = ("count", "sum", "mean", "var", "std", "min", "max")


@dataclass(frozen=True)
class Bins:
    """Edges of a dimension on its scales; bin t is [edges[t], edges[t+1])."""

    dim: str
    edges: tuple[int, ...]

    def __post_init__(self):
        if len(self.edges) < 2 or any(b <= a for a, b in zip(self.edges, self.edges[1:])):
            raise ValueError(f"edges of {self.dim} must ascend and be at least two")

    @classmethod
    def width(cls, dim: str, width: int, lo: int, hi: int) -> Bins:
        """Equal widths from lo; the last bin ends at or after hi."""
        return cls(dim, tuple(range(lo, hi + width, width)) if (hi - lo) % width else tuple(range(lo, hi + 1, width)))

    @classmethod
    def log(cls, dim: str, per_decade: int, lo: int, hi: int) -> Bins:
        """Equal steps of the logarithm; whole-number edges, equal ones merged."""
        n = math.ceil(per_decade * math.log10(hi / lo))
        return cls(dim, tuple(sorted({max(1, round(lo * 10 ** (i / per_decade))) for i in range(n + 1)})))

    @property
    def array(self) -> np.ndarray:
        return np.array(self.edges, np.int64)


Range = dict[str, tuple[int, int]]


@dataclass(frozen=True)
class Tiling:
    """Bins of one width per dimension, counted from 0 over all records wherever they lie, where a Chart's bins have ends."""

    widths: dict[str, int]
    where: Range = field(default_factory=dict)
    agg: str = "count"

    @property
    def names(self) -> list[str]:
        return [f"t{i + 1}" for i in range(len(self.widths))]


@dataclass(frozen=True)
class Chart:
    """Bins per charted dimension, half-open filter ranges per dimension, and an aggregate."""

    bins: Sequence[Bins]
    where: Range = field(default_factory=dict)
    agg: str = "count"

    def __post_init__(self):
        if self.agg not in AGGREGATES:
            raise ValueError(f"unknown aggregate {self.agg}")
        for dim, (lo, hi) in self.where.items():
            if hi <= lo:
                raise ValueError(f"the range of {dim} is empty or inverted")
        if len({b.dim for b in self.bins}) != len(self.bins):
            raise ValueError("a dimension is charted twice")

    @property
    def names(self) -> list[str]:
        return [f"t{i + 1}" for i in range(len(self.bins))]

    @classmethod
    def viewport(cls, bounds: Range, pixels: int, grids: dict[str, int], agg: str = "count") -> Chart:
        """The chart of a viewport: per dimension at most ``pixels`` bins of one smooth width that divides, or is a multiple
        of, the dimension's grid, from the first bin that the bounds touch to the last."""
        bins = []
        for d, (lo, hi) in bounds.items():
            steps = [*chain(grids[d])[::-1], *(grids[d] * k for k in range(2, -(-(hi - lo) // grids[d]) + 2))]
            w = next((x for x in steps if -(-hi // x) - lo // x <= pixels), steps[-1])
            bins.append(Bins.width(d, w, lo // w * w, -(-hi // w) * w))
        return cls(bins, agg=agg)

    def edges(self) -> dict[str, np.ndarray]:
        """Per dimension that matters its edges; a charted and filtered dimension has its bins cut by the range."""
        out = {b.dim: b.array for b in self.bins}
        for dim, (lo, hi) in self.where.items():
            out[dim] = np.clip(out[dim], lo, hi) if dim in out else np.array([lo, hi], np.int64)
        return out

    def sql(self, source: str, value: str = "m") -> str:
        """The exact answer on raw rows, as SQL (``source``: a view's SQL with the measure as ``value``)."""
        cond = [f"{b.dim} >= {b.edges[0]} and {b.dim} < {b.edges[-1]}" for b in self.bins]
        cond += [f"{d} >= {lo} and {d} < {hi}" for d, (lo, hi) in self.where.items()]
        keys = [self._bin_sql(b) + f" as {n}" for b, n in zip(self.bins, self.names)]
        agg = {"count": "count(*)", "sum": f"sum({value})::bigint", "mean": f"round(sum({value})::double / count(*), 4)", "var": f"round(var_pop({value}), 2)", "std": f"round(stddev_pop({value}), 2)", "min": f"min({value})", "max": f"max({value})"}[self.agg]
        head = ", ".join([*keys, f"{agg} as value"])
        tail = f" group by {', '.join(str(i + 1) for i in range(len(keys)))}" if keys else ""
        return f"select {head} from ({source}) where {' and '.join(cond) or 'true'}{tail}"

    def _bin_sql(self, b: Bins) -> str:
        steps = {y - x for x, y in zip(b.edges, b.edges[1:])}
        if len(steps) == 1:
            return f"(({b.dim} - {b.edges[0]}) // {steps.pop()})::bigint"
        return "(" + " + ".join(f"({b.dim} >= {e})::bigint" for e in b.edges[1:-1]) + ")"
