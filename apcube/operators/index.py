"""The adaptive prefix-cube index: a partition of space, occupied cells per part, and prefix arrays per part.

Cells lie on an absolute lattice: a point's cell on dimension i of part l is floor(s_i / c_li). Boxes that grow never
move a cell, and a bin edge that is a multiple of c_li is a cell edge, so aligned charts are exact. One scan assigns
the records; what is shuffled is (part, cell) aggregates, never records.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from apcube.functions.scale import cell_width, chain, down, down_col, near, near_col, sampled, up, up_col
from apcube.operators import boxtree
from apcube.operators.boxtree import Nodes
from apcube.plans.spec import Bins, Chart, Tiling

#: Points that a driver grows a tree on, at most; a larger sample is thinned to this expectation (see ``whole_tree``, and
#: build_distributed, for trees over more).
MOST_SAMPLE = 200_000
DESCRIPTORS = {"n": "count", "s": "sum", "s2": "sum of squares", "mn": "least", "mx": "most"}


@dataclass(frozen=True)
class Extra:
    """A further descriptor of cells: an aggregate over records (SQL), and the aggregate that merges its values."""

    name: str
    collect: str
    merge: str
    columns: tuple[str, ...]


@dataclass
class Index:
    dims: list[str]
    widths: np.ndarray
    nodes: Nodes
    leaves: np.ndarray
    cells_per: np.ndarray
    """Cell width per leaf and dimension."""
    cells: DataFrame
    """leaf, q_<dim>, c_<dim>, n, s, s2, mn, mx"""
    budget: int
    aligned: bool
    height: int
    outside: int = 0
    axes: tuple[str, ...] = ()
    """Further keys of the cells that are never summed unless asked: categories, histogram bins."""
    extras: tuple[Extra, ...] = ()
    _prefix: DataFrame | None = field(default=None, repr=False)

    # ---- candidates ------------------------------------------------------------------------------------------

    def candidates(self, chart: Chart) -> np.ndarray:
        """Numbers of the leaves whose cells meet the chart's box: a vector test on the boxes."""
        ok = np.ones(len(self.leaves), bool)
        for d, e in chart.edges().items():
            i = self.dims.index(d)
            c = self.cells_per[:, i]
            ok &= (self.nodes.lo[self.leaves, i] // c * c < e[-1]) & ((self.nodes.hi[self.leaves, i] // c + 1) * c > e[0])
        return np.flatnonzero(ok)

    def descend(self, chart: Chart) -> tuple[np.ndarray, int]:
        """The same by descent from the root, level by level; also the number of boxes tested."""
        edges = {self.dims.index(d): (e[0], e[-1]) for d, e in chart.edges().items()}
        where = {n: i for i, n in enumerate(self.leaves)}
        frontier, found, tested = np.flatnonzero(self.nodes.parent < 0), [], 0
        while len(frontier):
            tested += len(frontier)
            ok = np.ones(len(frontier), bool)
            for i, (a, b) in edges.items():
                ok &= (self.nodes.lo[frontier, i] < b) & (self.nodes.hi[frontier, i] >= a)
            frontier = frontier[ok]
            found += [where[n] for n in frontier if n in where]
            frontier = np.flatnonzero(np.isin(self.nodes.parent, frontier[~np.isin(frontier, self.leaves)]))
        return np.array(sorted(found), int), tested

    def whole(self, dim: str, width: int) -> Bins:
        """Bins of ``width`` from 0 over the domain and all cells, also those of records beyond it."""
        i = self.dims.index(dim)
        c = self.cells_per[:, i]
        end = max(int(self.widths[i]), int(((self.nodes.hi[self.leaves, i] // c + 1) * c).max()))
        return Bins.width(dim, width, 0, -(-end // width) * width)

    # ---- answers from cells ----------------------------------------------------------------------------------

    @staticmethod
    def _values(agg: str) -> list[Column]:
        n, s, s2 = F.sum("n"), F.sum("s"), F.sum("s2")
        mean, var = s.cast("double") / n, s2.cast("double") / n - (s.cast("double") / n) ** 2
        value = {"count": n.cast("long"), "sum": s.cast("long"), "mean": F.round(mean, 4), "var": F.round(var, 2), "std": F.round(F.sqrt(F.greatest(var, F.lit(0.0))), 2), "min": F.min("mn"), "max": F.max("mx")}[agg]
        return [value.alias("value")]

    @staticmethod
    def _bin(d: str, e: np.ndarray, snap: str) -> tuple[Column, Column]:
        """The first and last bin of the edges ``e`` on dimension ``d`` that take a cell (outside [0, bins): none)."""
        q, c, lit = F.col(f"q_{d}"), F.col(f"c_{d}"), F.array(*(F.lit(int(x)) for x in e))
        low, high = F.slice(lit, 1, len(e) - 1), F.slice(lit, 2, len(e) - 1)
        count = lambda a, f: F.size(F.filter(a, lambda x: f(x, c) <= q)).cast("long")
        if snap == "outer":
            return count(high, up_col), count(low, down_col) - 1
        t = count(lit, near_col if snap == "nearest" else up_col) - 1
        if snap == "inner":
            t = F.when(t.between(0, len(e) - 2) & (down_col(F.get(lit, t.cast("int") + 1), c) > q), t).otherwise(-1)
        return t, t

    @staticmethod
    def _tile(d: str, w: int, snap: str) -> tuple[Column, Column]:
        """As ``_bin`` for bins [t * w, (t + 1) * w) without end."""
        q, c = F.col(f"q_{d}"), F.col(f"c_{d}")
        if snap == "nearest":
            t = down_col(q * c + F.expr(f"c_{d} div 2"), F.lit(w))
            return t, t
        first, last = down_col(q * c, F.lit(w)), down_col(q * c + c - 1, F.lit(w))
        return (first, last) if snap == "outer" else (F.when(first == last, first), F.when(first == last, first))

    def assigned(self, chart: Chart | Tiling, snap: str = "nearest", leaves: Sequence[int] | None = None) -> DataFrame:
        """Cells that fall into the chart's grids, with their t columns. ``snap``: each edge to the nearest cell edge, or
        ``inner``/``outer``: cells wholly inside a grid, or touching it (a cell may touch several)."""
        if isinstance(chart, Tiling):
            df = self.assigned(Chart([], chart.where), snap, leaves)
            for name, (d, w) in zip(chart.names, chart.widths.items()):
                first, last = self._tile(d, w, snap)
                df = df.withColumn(name, F.explode(F.sequence(first, last)) if snap == "outer" else first).where(F.col(name).isNotNull())
            return df
        df = self.cells if leaves is None else self.cells.where(F.col("leaf").isin([int(x) for x in leaves]))
        charted = {b.dim: n for b, n in zip(chart.bins, chart.names)}
        for d, e in chart.edges().items():
            name, (first, last) = charted.get(d, f"__{d}"), self._bin(d, e, snap)
            if snap == "outer":
                first, last = F.greatest(first, F.lit(0)), F.least(last, F.lit(len(e) - 2))
                df = df.where(first <= last).withColumn(name, F.explode(F.sequence(first, last)))
            else:
                df = df.withColumn(name, first).where(F.col(name).between(0, len(e) - 2))
        return df

    def chart(self, chart: Chart | Tiling, snap: str = "nearest", leaves: Sequence[int] | None = None, by: Sequence[str] = ()) -> DataFrame:
        """t1..tk (and the axes named in ``by``), value of the grids that hold something; without either one row."""
        found, keys = self.assigned(chart, snap, leaves), [*chart.names, *by]
        return found.groupBy(*keys).agg(*self._values(chart.agg)) if keys else found.agg(*self._values(chart.agg))

    def with_error(self, chart: Chart, leaves: Sequence[int] | None = None) -> DataFrame:
        """t.., value, v_lo, v_hi, margin of a count or a sum, in one pass over the cells.

        A cell inside a grid counts as it is. Of one that only touches it any part may lie inside: of a count from none to
        all, of a sum from all that is negative to all that is positive, which the cell's least and most measure bound."""
        if chart.agg not in ("count", "sum"):
            raise ValueError(f"no bounds for {chart.agg}")
        df, charted = self.cells if leaves is None else self.cells.where(F.col("leaf").isin([int(x) for x in leaves])), {b.dim: n for b, n in zip(chart.bins, chart.names)}
        near, inside = F.lit(True), F.lit(True)
        for d, e in chart.edges().items():
            name, (first, last) = charted.get(d, f"__{d}"), self._bin(d, e, "outer")
            first, last = F.greatest(first, F.lit(0)), F.least(last, F.lit(len(e) - 2))
            df = df.where(first <= last).withColumn(name, F.explode(F.sequence(first, last)))
            near, inside = near & (self._bin(d, e, "nearest")[0] == F.col(name)), inside & (self._bin(d, e, "inner")[0] == F.col(name))
        if chart.agg == "count":
            x, least, most = F.col("n"), F.lit(0), F.col("n")
        else:
            x, mn, mx = F.col("s"), F.coalesce("mn", F.lit(0)), F.coalesce("mx", F.lit(0))
            least = F.when(mn >= 0, 0).when(mx <= 0, x).otherwise(F.col("n") * mn)
            most = F.when(mn >= 0, x).when(mx <= 0, 0).otherwise(F.col("n") * mx)
        pick = lambda c, y, z: F.coalesce(F.sum(F.when(c, y).otherwise(z)), F.lit(0)).cast("long")
        found = df.groupBy(*chart.names).agg(pick(near, x, F.lit(0)).alias("value"), pick(inside, x, least).alias("v_lo"), pick(inside, x, most).alias("v_hi"))
        margin = F.when(F.col("value") != 0, F.round((F.col("v_hi") - F.col("v_lo")) / F.abs("value"), 6)).when(F.col("v_hi") == F.col("v_lo"), F.lit(0.0))
        return found.withColumn("margin", margin)

    def linked(self, views: Sequence[tuple[tuple, Chart]], keys: str) -> DataFrame:
        """Many one-dimensional charts (``views``: the values of the columns ``keys`` that name a view, and its chart) in
        one pass over the cells: keys.., t1, value (counts)."""
        parts = []
        for named, chart in views:
            t, ok = None, F.lit(True)
            for d, e in chart.edges().items():
                at = self._bin(d, e, "nearest")[0]
                ok = ok & at.between(0, len(e) - 2)
                t = at if d == chart.bins[0].dim else t
            parts.append(F.when(ok, F.struct(*(F.lit(v).alias(f"k{i}") for i, v in enumerate(named)), t.alias("t1"))))
        names = keys.split(", ")
        df = self.cells.select("n", F.explode(F.filter(F.array(*parts), lambda x: x.isNotNull())).alias("v"))
        return df.groupBy(*(F.col(f"v.k{i}").alias(k) for i, k in enumerate(names)), F.col("v.t1").alias("t1")).agg(F.sum("n").cast("long").alias("value"))

    # ---- answers from prefix arrays --------------------------------------------------------------------------

    def prefix(self) -> DataFrame:
        """Per leaf (and value of the axes): origin, shape, width of the cells and, as dense arrays of whole numbers, the
        prefix sums of n, s and the high and low 32 bits of s2. A leaf whose dense array would exceed the budget, since its
        box grew, has several arrays: its cells are halved along the longer side of their box until each part fits."""
        if self._prefix is None:
            dims, budget, axes = self.dims, self.budget, self.axes

            def tiles(q: np.ndarray, at: np.ndarray) -> Iterator[np.ndarray]:
                extent = q[at].max(axis=0) - q[at].min(axis=0) + 1
                if extent.astype(float).prod() <= max(budget, 1):
                    yield at
                    return
                axis = int(extent.argmax())
                values = np.unique(q[at, axis])
                low = q[at, axis] < values[len(values) // 2]
                yield from tiles(q, at[low])
                yield from tiles(q, at[~low])

            def dense(group: pa.Table) -> pa.Table:
                every = np.stack([group.column(f"q_{d}").to_numpy() for d in dims], axis=1)
                s2 = [int(x) for x in group.column("s2").to_pylist()]
                channels = [group.column("n").to_numpy(), group.column("s").to_numpy(), np.array([x >> 32 for x in s2]), np.array([x & 0xFFFFFFFF for x in s2])]
                out = []
                for at in tiles(every, np.arange(len(every))):
                    q = every[at]
                    lo, shape = q.min(axis=0), q.max(axis=0) - q.min(axis=0) + 1
                    sums = np.zeros((len(channels), *shape), np.int64)
                    for a, v in zip(sums, channels):
                        a[tuple((q - lo).T)] = v[at]
                        for axis in range(len(dims)):
                            np.cumsum(a, axis=axis, out=a)
                    out.append((lo.tolist(), shape.tolist(), sums.ravel()))
                same = lambda c: group.column(c).take(pa.array([0] * len(out)))
                c = [group.column(f"c_{d}")[0].as_py() for d in dims]
                lists = [pa.array(x, pa.list_(pa.int64())) for x in ([o[0] for o in out], [o[1] for o in out], [c] * len(out), [o[2] for o in out])]
                return pa.table([same("leaf"), *map(same, axes), *lists], ["leaf", *axes, "origin", "shape", "width", "sums"])

            kinds = [f"{f.name} {f.dataType.simpleString()}" for f in self.cells.schema if f.name in ("leaf", *axes)]
            head = ", ".join(sorted(kinds, key=lambda k: ["leaf", *axes].index(k.split()[0])))
            self._prefix = self.cells.groupBy("leaf", *axes).applyInArrow(dense, f"{head}, origin array<bigint>, shape array<bigint>, width array<bigint>, sums array<bigint>").persist()
        return self._prefix

    def chart_prefix(self, chart: Chart, snap: str = "nearest", leaves: Sequence[int] | None = None, by: Sequence[str] = ()) -> DataFrame:
        """As ``chart`` for count, sum and what follows from them, from the prefix arrays: every array is read once per
        vertex of the grids and differenced along each dimension in turn. ``snap`` may also be ``interp``: edges between
        cell edges read the multilinear interpolation."""
        edges, dims, names, by = chart.edges(), self.dims, chart.names, list(by)
        charted, exact = [b.dim for b in chart.bins], snap != "interp"
        value = ["n", "s", "s2h", "s2l"]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for row, (origin, shape, width) in enumerate(zip(*(b.column(c).to_pylist() for c in ("origin", "shape", "width")))):
                    sums = b.column("sums")[row].values.to_numpy()
                    values = grids(sums.reshape(len(value), *shape), origin, width, [edges.get(d) for d in dims], snap)
                    order = [0, *(1 + dims.index(d) for d in charted), *(1 + i for i, d in enumerate(dims) if d not in charted)]
                    values = values.transpose(order).reshape(len(value), *(values.shape[1 + dims.index(d)] for d in charted))
                    at = np.nonzero(np.abs(values).max(axis=0)) if charted else (np.zeros(1, int),)
                    picked = values[(slice(None), *at)] if charted else values.reshape(len(value), 1)
                    columns = [pa.array(x.astype(np.int64)) for x in at] if charted else []
                    columns += [b.column(c).take(pa.array([row] * picked.shape[1])) for c in by]
                    yield pa.RecordBatch.from_arrays([*columns, *(pa.array(x) for x in picked)], [*names, *by, *value])

        source = self.prefix() if leaves is None else self.prefix().where(F.col("leaf").isin([int(x) for x in leaves]))
        kind = "bigint" if exact else "double"
        found = source.mapInArrow(run, ", ".join([*(f"{n} bigint" for n in names), *(f"{c} {source.schema[c].dataType.simpleString()}" for c in by), *(f"{v} {kind}" for v in value)]))
        s2 = F.col("s2h").cast("decimal(38,0)" if exact else "double") * F.lit(1 << 32) + F.col("s2l")
        found = found.select(*names, *by, "n", "s", (s2.cast("decimal(38,0)") if exact else s2).alias("s2"))
        if exact:
            keys = [*names, *by]
            return found.where("n <> 0").groupBy(*keys).agg(*self._values(chart.agg)) if keys else found.where("n <> 0").agg(*self._values(chart.agg))
        total = found.groupBy(*names, *by).agg(*(F.sum(c).alias(c) for c in ("n", "s", "s2")))
        n, s, s2 = F.col("n"), F.col("s"), F.col("s2")
        answer = {"count": F.round(n, 4), "sum": F.round(s, 2), "mean": F.round(s / n, 4), "var": F.round(s2 / n - (s / n) ** 2, 2), "std": F.round(F.sqrt(F.greatest(s2 / n - (s / n) ** 2, F.lit(0.0))), 2)}[chart.agg]
        return total.where("n > 1e-9").select(*names, *by, answer.alias("value"))

    # ---- coarser levels --------------------------------------------------------------------------------------

    def at_depth(self, depth: int) -> Index:
        """The index of the tree's nodes at a depth (leaves above it stay): cells are merged, no record is read."""
        if not self.aligned:
            raise ValueError("cells of an unaligned index don't merge into coarser ones")
        keep = np.flatnonzero((self.nodes.depth == depth) | (self.nodes.leaf & (self.nodes.depth < depth)))
        up_to = {n: n for n in keep}

        def ancestor(n: int) -> int:
            while n not in up_to:
                n = self.nodes.parent[n]
            return up_to[n]

        of = [int(np.flatnonzero(keep == ancestor(n))[0]) for n in self.leaves]
        widths = np.array([[max(self.cells_per[[k for k, o in enumerate(of) if o == j], i].max(), 1) for i in range(len(self.dims))] for j in range(len(keep))])
        for j, n in enumerate(keep):
            extent = self.nodes.hi[n] - self.nodes.lo[n] + 1
            widths[j] = fit_budget(extent, widths[j], [list(reversed(chain(int(g)))) for g in self.grids], self.budget)
        table = self.cells.sparkSession.createDataFrame([(i, of[i], *(int(x) for x in widths[of[i]])) for i in range(len(of))], ", ".join(["leaf int", "part int", *(f"w_{d} bigint" for d in self.dims)]))
        joined = self.cells.join(F.broadcast(table), "leaf")  # one row per leaf
        keys = [F.floor(F.col(f"q_{d}") * F.col(f"c_{d}") / F.col(f"w_{d}")).cast("long").alias(f"q_{d}") for d in self.dims]
        kept = [*self.axes, "n", "s", "s2", "mn", "mx", *(x.name for x in self.extras)]
        cells = joined.select(F.col("part").alias("leaf"), *keys, *(F.col(f"w_{d}").alias(f"c_{d}") for d in self.dims), *kept)
        out = Index(self.dims, self.widths, self.nodes, keep, widths, merge_cells(cells, self.dims, self.axes, self.extras), self.budget, True, depth, axes=self.axes, extras=self.extras)
        out.grids = self.grids
        return out

    grids: Sequence[int] = ()

    # ---- numbers about the index -----------------------------------------------------------------------------

    def dense_entries(self) -> int:
        """Entries of all dense prefix arrays by the product law on the boxes."""
        c = self.cells_per
        lo, hi = self.nodes.lo[self.leaves] // c, self.nodes.hi[self.leaves] // c
        return int((hi - lo + 1).prod(axis=1).sum())

    def coincidence(self, chart: Chart) -> float:
        """Share of the chart's grids that are ``coincident``."""
        return float(self.coincident(chart).mean())

    def coincident(self, chart: Chart) -> np.ndarray:
        """Per grid whether all of its edges are cell edges in every leaf that it touches, or lie outside the leaf's cells."""
        edges = chart.edges()
        ok = np.ones([len(e) - 1 for e in edges.values()], bool)
        for leaf in self.candidates(chart):
            good, meets = [], []
            for d, e in edges.items():
                i = self.dims.index(d)
                c = self.cells_per[leaf, i]
                lo, hi = self.nodes.lo[self.leaves[leaf], i] // c * c, (self.nodes.hi[self.leaves[leaf], i] // c + 1) * c
                fine = (e % c == 0) | (e <= lo) | (e >= hi)
                good.append(fine[:-1] & fine[1:])
                meets.append((e[:-1] < hi) & (e[1:] > lo))
            ok &= reduce(np.logical_and.outer, good) | ~reduce(np.logical_and.outer, meets)
        return ok


def grids(sums: np.ndarray, origin: Sequence[int], width: Sequence[int], edges: Sequence[np.ndarray | None], snap: str) -> np.ndarray:
    """channels x cells prefix sums -> channels x grids. A dimension without edges is summed over.

    Along each dimension the low and high ends of all bins are read, then subtracted; a vertex shared by two bins
    (nearest, interp) is read once."""
    out = sums
    for i, e in enumerate(edges):
        axis = i + 1
        n = sums.shape[axis]
        padded = np.concatenate([np.zeros_like(out.take([0], axis)), out], axis)
        if e is None:
            out = padded.take([n], axis)
            continue
        c, o = int(width[i]), int(origin[i])
        if snap == "interp":
            x = np.clip(e / c - o, 0, n)
            k = np.minimum(x.astype(int), n - 1)
            w = (x - k).reshape([-1 if a == axis else 1 for a in range(out.ndim)])
            out = np.diff(padded.take(k, axis) * (1 - w) + padded.take(k + 1, axis) * w, axis=axis)
            continue
        if snap == "nearest":
            out = np.diff(padded.take(np.clip(near(e, c) - o, 0, n), axis), axis=axis)
            continue
        lo, hi = (up(e[:-1], c), down(e[1:], c)) if snap == "inner" else (down(e[:-1], c), up(e[1:], c))
        lo = np.clip(lo - o, 0, n)
        hi = np.maximum(np.clip(hi - o, 0, n), lo)
        out = padded.take(hi, axis) - padded.take(lo, axis)
    return out


def fit_budget(extent: np.ndarray, width: np.ndarray, ladders: Sequence[Sequence[int]] | None, budget: int) -> np.ndarray:
    """Widens the cells of the dimension with most cells to its next admissible width until all cells fit the budget."""
    width = width.astype(np.int64).copy()
    while True:
        n = -(-extent // width) + 1
        if n.astype(float).prod() <= budget or (n <= 2).all():
            return width
        for i in np.argsort(-n, kind="stable"):
            wider = [w for w in (ladders[i] if ladders else [2 * int(width[i])]) if w > width[i]]
            if wider and n[i] > 2:
                width[i] = wider[0]
                break
        else:
            return width


def choose_cells(nodes: Nodes, leaves: np.ndarray, bins: int, grid_widths: Sequence[int] | None, budget: int) -> np.ndarray:
    """Cell widths per leaf: its extent over ``bins``, on the ladder of divisors of the grid widths where aligned."""
    ladders = [list(reversed(chain(int(g)))) for g in grid_widths] if grid_widths is not None else None
    out = []
    for n in leaves:
        extent = nodes.hi[n] - nodes.lo[n] + 1
        w = np.array([cell_width(x / bins, None if grid_widths is None else int(grid_widths[i])) for i, x in enumerate(extent)])
        out.append(fit_budget(extent, w, ladders, budget))
    return np.array(out, np.int64).reshape(len(leaves), nodes.lo.shape[1])


class Locator:
    """Finds the leaf of points: of the boxes that contain a point the smallest (then the first); if none does, the nearest
    (squared distance in shares of the domain), then the smaller, then the first.

    Up to FEW boxes: per dimension the box edges cut the axis into intervals, each with a bit set of the boxes over it,
    smallest box first. A point's boxes are the bits common to its intervals. More boxes: a grid over the domain lists, cell
    by cell, the boxes that meet the cell, smallest first, and a point tests its cell's boxes until one holds it. The grid is
    as fine as MOST_LISTED entries a box allow, so memory is linear in the number of boxes."""

    #: Domains up to this width find their interval by a table of all scales.
    TABLE = 1 << 16
    FEW, MOST_LISTED = 1024, 16

    def __init__(self, lo: np.ndarray, hi: np.ndarray, widths: np.ndarray):
        area = ((hi - lo + 1) / widths).prod(axis=1)
        self.order = np.argsort(area, kind="stable")
        self.lo, self.hi, self.widths = lo[self.order], hi[self.order], np.asarray(widths, float)
        (self._bit_sets if len(lo) <= self.FEW else self._grid)()

    def _bit_sets(self) -> None:
        n, words = len(self.lo), -(-len(self.lo) // 64)
        self.cuts, self.bits, self.tables = [], [], []
        for i in range(self.lo.shape[1]):
            cuts = np.unique(np.concatenate([self.lo[:, i], self.hi[:, i] + 1]))
            start = np.concatenate([[cuts[0] - 1], cuts])
            over = (self.lo[:, i][None] <= start[:, None]) & (start[:, None] <= self.hi[:, i][None])
            flat = np.zeros((len(start), words * 64), bool)
            flat[:, :n] = over
            self.bits.append(np.packbits(flat, axis=1, bitorder="little").view("<u8"))
            self.cuts.append(cuts)
            w = int(self.widths[i])
            self.tables.append(np.searchsorted(cuts, np.arange(w), side="right").astype(np.int32) if w <= self.TABLE else None)

    def _spans(self, side: int) -> tuple[np.ndarray, np.ndarray]:
        return tuple(np.clip((x / self.widths * side).astype(np.int64), 0, side - 1) for x in (self.lo, self.hi))

    def _grid(self) -> None:
        n, d = self.lo.shape
        side = max(1, int((4 * n) ** (1 / d)))
        while side > 1:
            first, last = self._spans(side)
            if (last - first + 1).astype(float).prod(axis=1).sum() <= self.MOST_LISTED * n:
                break
            side = side * 3 // 4
        first, last = self._spans(side)
        many = (last - first + 1).prod(axis=1)
        box = np.repeat(np.arange(n), many)
        rest, cell = np.arange(len(box)) - np.repeat(np.cumsum(many) - many, many), np.zeros(len(box), np.int64)
        for i in range(d):
            extent = (last - first + 1)[box, i]
            cell = cell * side + first[box, i] + rest % extent
            rest //= extent
        by = np.argsort(cell, kind="stable")  # boxes of a cell stay in order of size
        self.side, self.listed, self.begin = side, box[by], np.searchsorted(cell[by], np.arange(side**d + 1))

    def find(self, columns: Sequence[np.ndarray]) -> np.ndarray:
        """``columns``: one array of coordinates per dimension."""
        got = self._by_bits(columns) if len(self.lo) <= self.FEW else self._by_grid(columns)
        miss = np.flatnonzero(got < 0)
        step = max(1, (1 << 22) // max(1, self.lo.size))
        for a in range(0, len(miss), step):
            at = miss[a : a + step]
            p = np.stack([x[at] for x in columns], axis=1)[:, None, :]
            gap = np.maximum(np.maximum(self.lo - p, p - self.hi), 0) / self.widths
            got[at] = (gap * gap).sum(axis=2).argmin(axis=1)
        return self.order[got]

    def _by_bits(self, columns: Sequence[np.ndarray]) -> np.ndarray:
        common = None
        for x, cuts, bits, table, w in zip(columns, self.cuts, self.bits, self.tables, self.widths):
            fast = table is not None and len(x) and x.min() >= 0 and x.max() < w
            mine = bits[table[x] if fast else np.searchsorted(cuts, x, side="right")]
            common = mine if common is None else common & mine
        got = np.full(len(common), -1, np.int64)
        for word in range(common.shape[1] - 1, -1, -1):
            some = np.flatnonzero(common[:, word])
            v = common[some, word]
            got[some] = 64 * word + np.frexp((v & (~v + np.uint64(1))).astype(np.float64))[1] - 1
        return got

    def _by_grid(self, columns: Sequence[np.ndarray]) -> np.ndarray:
        x = np.stack(columns, axis=1)
        cell = np.zeros(len(x), np.int64)
        for i, w in enumerate(self.widths):
            cell = cell * self.side + np.clip((x[:, i] / w * self.side).astype(np.int64), 0, self.side - 1)
        got, at, end = np.full(len(x), -1, np.int64), self.begin[cell], self.begin[cell + 1]
        left = np.flatnonzero(at < end)
        while len(left):
            box = self.listed[at[left]]
            held = ((x[left] >= self.lo[box]) & (x[left] <= self.hi[box])).all(axis=1)
            got[left[held]] = box[held]
            left = left[~held]
            at[left] += 1
            left = left[at[left] < end[left]]
        return got


def locate(points: np.ndarray, lo: np.ndarray, hi: np.ndarray, widths: np.ndarray) -> np.ndarray:
    """The leaf of each row of ``points`` (see Locator)."""
    return Locator(lo, hi, widths).find([np.ascontiguousarray(points[:, i]) for i in range(points.shape[1])])


def assign(df: DataFrame, dims: Sequence[str], nodes: Nodes, leaves: np.ndarray, widths: np.ndarray) -> DataFrame:
    """``df`` with ``leaf``: Arrow batches against the broadcast boxes (one row per leaf), no shuffle."""
    shared = df.sparkSession.sparkContext.broadcast((nodes.lo[leaves], nodes.hi[leaves], np.asarray(widths, float)))
    names = df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find = Locator(*shared.value).find
        for b in batches:
            if b.num_rows:
                leaf = find([b.column(d).to_numpy(zero_copy_only=False) for d in dims])
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(leaf.astype(np.int32))], [*names, "leaf"])

    return df.mapInArrow(run, ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in df.schema), "leaf int"]))


def merge_cells(cells: DataFrame, dims: Sequence[str], axes: Sequence[str] = (), extras: Sequence[Extra] = ()) -> DataFrame:
    keys = ["leaf", *(f"q_{d}" for d in dims), *(f"c_{d}" for d in dims), *axes]
    more = [F.expr(f"{x.merge}({x.name})").alias(x.name) for x in extras]
    return cells.groupBy(*keys).agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("s2").alias("s2"), F.min("mn").alias("mn"), F.max("mx").alias("mx"), *more)


def to_cells(points: DataFrame, dims: Sequence[str], cells_per: np.ndarray, axes: Sequence[str] = (), extras: Sequence[Extra] = ()) -> DataFrame:
    """points with leaf and m (measure, a whole number or null) -> cells. Without a measure column only counts are kept."""
    table = points.sparkSession.createDataFrame([(i, *(int(x) for x in row)) for i, row in enumerate(cells_per)], ", ".join(["leaf int", *(f"c_{d} bigint" for d in dims)]))
    df = points.join(F.broadcast(table), "leaf")  # one row per leaf
    # (s - pmod(s, c)) / c is the whole quotient of coordinates of either sign, without a detour over doubles
    keys = ["leaf", *(F.expr(f"({d} - pmod({d}, c_{d})) div c_{d}").alias(f"q_{d}") for d in dims), *(f"c_{d}" for d in dims), *axes]
    m, more = F.col("m"), [F.expr(x.collect).alias(x.name) for x in extras]
    if "m" not in points.columns:
        none = {"s": "0L", "s2": "cast(0 as decimal(38,0))", "mn": "cast(null as bigint)", "mx": "cast(null as bigint)"}
        counted = df.groupBy(*keys).agg(F.count("*").alias("n"), *more)
        return counted.select(*(c for c in counted.columns if c not in {x.name for x in extras}), *(F.expr(v).alias(k) for k, v in none.items()), *(x.name for x in extras))
    return df.groupBy(*keys).agg(F.count("*").alias("n"), F.coalesce(F.sum("m"), F.lit(0)).alias("s"), F.coalesce(F.sum(m.cast("decimal(20,0)") * m), F.lit(0)).cast("decimal(38,0)").alias("s2"), F.min("m").alias("mn"), F.max("m").alias("mx"), *more)


def whole_tree(points: DataFrame, dims: Sequence[str], widths: np.ndarray, **options) -> Nodes | None:
    """The tree of ``boxtree.build`` over all points, grown in one task; the driver gets its boxes alone. None without points."""
    dims = list(dims)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x = np.concatenate([np.empty((0, len(dims)), np.int64), *(np.stack([b.column(d).to_numpy() for d in dims], axis=1) for b in batches)])
        if len(x):
            n = boxtree.build(x, widths, **options)
            kinds = (pa.list_(pa.int64()), pa.list_(pa.int64()), pa.int64(), pa.int64(), pa.int64(), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(v.tolist(), k) for v, k in zip((n.lo, n.hi, n.parent, n.depth, n.count, n.leaf), kinds)], ["lo", "hi", "parent", "depth", "n", "leaf"])

    rows = points.select(*dims).repartition(1).mapInArrow(run, "lo array<bigint>, hi array<bigint>, parent bigint, depth bigint, n bigint, leaf boolean").collect()  # a row a node
    return Nodes(*(np.array([r[c] for r in rows], kind) for c, kind in zip(("lo", "hi", "parent", "depth", "n", "leaf"), (np.int64, np.int64, int, int, int, bool)))) if rows else None


def build(
    df: DataFrame,
    dims: Sequence[str],
    widths: dict[str, int],
    key: str | Column,
    measure: str | None = None,
    bins: int = 16,
    leaves: int = 64,
    rate: float = 1.0,
    grid_widths: dict[str, int] | None = None,
    budget: int = 65_536,
    criterion: str = "density",
    reinsert: float = 0.0,
    nodes: Nodes | None = None,
    target_height: int | None = None,
    axes: Sequence[str] = (),
    extras: Sequence[Extra] = (),
    find: Callable[[DataFrame, Nodes], DataFrame] | None = None,
    whole: bool = False,
) -> Index:
    """Builds an index over ``dims`` of ``df`` (whole numbers in [0, width)).

    ``rate``: share of rows, by a hash of ``key``, that the tree is grown on; the rest is only assigned to the frozen
    leaves; at most about MOST_SAMPLE rows. ``grid_widths``: bin widths that cells must divide (scale alignment); None switches
    alignment off. ``nodes``: a ready partition instead of the tree. Rows with a null dimension are in no range and are left
    out. ``axes``: columns of few values that cells are kept apart by. ``extras``: further descriptors. ``find``: finds the leaf
    (a number among the partition's leaves) of points in place of the vector test, given the points and the partition; see
    ``lsh.finder``. ``whole``: the tree is grown on every row, however many, see ``whole_tree``.
    """
    dims = list(dims)
    w = np.array([widths[d] for d in dims], float)
    further = list(dict.fromkeys(c for c in (*axes, *(c for x in extras for c in x.columns)) if c not in dims))
    points = df.select(*dims, *further, (F.col(measure) if measure else F.lit(None)).cast("bigint").alias("m"), (F.col(key) if isinstance(key, str) else key).alias("__key")).dropna(subset=dims)
    tree = {"target_leaves": leaves, "criterion": criterion, "reinsert": reinsert, "target_height": target_height}
    if nodes is None and whole:
        nodes = whole_tree(points, dims, w, **tree)
    elif nodes is None:
        rate = min(rate, MOST_SAMPLE / max(df.count(), 1))
        sample = points if rate >= 1 else points.where(sampled(F.col("__key"), rate))
        x = np.array([[*r] for r in sample.select(*dims).toPandas().itertuples(index=False)], np.int64).reshape(-1, len(dims))
        nodes = boxtree.build(x, w, **tree) if len(x) else None
    if nodes is None:
        nodes = Nodes.of_boxes(np.zeros((1, len(dims))), np.array([w - 1]), np.zeros(1, int))
    at = nodes.leaves
    grid = None if grid_widths is None else [grid_widths.get(d, int(widths[d])) for d in dims]
    per = choose_cells(nodes, at, bins, grid, budget)
    narrow = points.select(*dims, *further, *(["m"] if measure else []))
    cells = to_cells(find(narrow, nodes) if find else assign(narrow, dims, nodes, at, w), dims, per, axes, extras).persist()
    grown = cells.groupBy("leaf").agg(*(f(F.col(f"q_{d}") * F.col(f"c_{d}") + k).alias(f"{a}_{d}") for d in dims for f, a, k in ((F.min, "lo", 0), (F.max, "hi", F.col(f"c_{d}") - 1)))).collect()
    for r in grown:  # one row per leaf: boxes take in what the nearest rule gave them
        for i, d in enumerate(dims):
            c = per[r["leaf"], i]
            n = at[r["leaf"]]
            if nodes.lo[n, i] // c * c > r[f"lo_{d}"]:
                nodes.lo[n, i] = r[f"lo_{d}"]
            if (nodes.hi[n, i] // c + 1) * c - 1 < r[f"hi_{d}"]:
                nodes.hi[n, i] = r[f"hi_{d}"]
    for n in np.argsort(-nodes.depth):  # and their ancestors
        p = nodes.parent[n]
        if p >= 0:
            nodes.lo[p], nodes.hi[p] = np.minimum(nodes.lo[p], nodes.lo[n]), np.maximum(nodes.hi[p], nodes.hi[n])
    out = Index(dims, w, nodes, at, per, cells, budget, grid is not None, nodes.height, axes=tuple(axes), extras=tuple(extras))
    out.grids = grid or ()
    return out


def flat(df: DataFrame, dims: Sequence[str], widths: dict[str, int], cells: dict[str, int], measure: str | None = None, budget: int = 1 << 26) -> Index:
    """A plain prefix table: one part over the whole domain with the given cell widths."""
    dims = list(dims)
    w = np.array([widths[d] for d in dims], float)
    nodes = Nodes.of_boxes(np.zeros((1, len(dims))), np.array([w - 1]), np.zeros(1, int))
    per = np.array([[cells[d] for d in dims]], np.int64)
    points = df.select(*dims, (F.col(measure) if measure else F.lit(None)).cast("bigint").alias("m"), F.lit(0).alias("leaf")).dropna(subset=dims)
    out = Index(dims, w, nodes, nodes.leaves, per, to_cells(points, dims, per).persist(), budget, True, 1)
    out.grids = [cells[d] for d in dims]
    return out
