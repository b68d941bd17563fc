"""A box tree over points (all or a sample) whose leaves follow the density of the data.

Insertion goes to the child that costs least by a criterion; full nodes split by the R* rule (the axis of least margin,
the cut of least overlap, then of least area), optionally after re-inserting the farthest share once per level. Sides
are measured in shares of the domain plus one scale, so that points have an area and no axis outweighs others.

Points go in one after another, but those that grow no box and overflow no leaf are taken in batches: they cost the
smallest child that holds them nothing, whatever the criterion, so the tree is that of single insertions.
"""

from __future__ import annotations

from array import array
from dataclasses import dataclass

import numpy as np

CRITERIA = ("density", "density_n", "area")
#: Points that are tried at once.
LEAST_BATCH, MOST_BATCH = 16, 1 << 15


@dataclass
class Nodes:
    """A partition: boxes [lo, hi] (both ends are points), parents (-1 for the root), depth from the root (1), points
    held, and whether a node is a leaf. Leaves may lie at one depth only."""

    lo: np.ndarray
    hi: np.ndarray
    parent: np.ndarray
    depth: np.ndarray
    count: np.ndarray
    leaf: np.ndarray

    @property
    def leaves(self) -> np.ndarray:
        return np.flatnonzero(self.leaf)

    @property
    def height(self) -> int:
        return int(self.depth.max()) if len(self.depth) else 0

    @classmethod
    def of_boxes(cls, lo: np.ndarray, hi: np.ndarray, count: np.ndarray) -> Nodes:
        """A partition of one level."""
        n = len(lo)
        return cls(lo.astype(np.int64), hi.astype(np.int64), np.full(n, -1), np.ones(n, int), count, np.ones(n, bool))


class _Node:
    __slots__ = ("lo", "hi", "kids", "points", "up", "n", "sides")

    def __init__(self, lo, hi, leaf: bool):
        self.lo, self.hi, self.up, self.n = lo.copy(), hi.copy(), None, 0
        self.points = array("q") if leaf else None
        self.kids = None if leaf else []
        self.sides = None  # lo, hi and area of the children, while none of them changes

    def changed(self) -> None:
        if self.up is not None:
            self.up.sides = None


class BoxTree:
    def __init__(self, widths: np.ndarray, capacity: int, fanout: int = 12, criterion: str = "density", reinsert: float = 0.0):
        if criterion not in CRITERIA:
            raise ValueError(f"unknown criterion {criterion}")
        self.unit = 1.0 / np.asarray(widths, float)
        self.capacity, self.fanout, self.criterion, self.share = max(2, capacity), fanout, criterion, reinsert
        self.root: _Node | None = None
        self.data: np.ndarray | None = None
        self.again: set[int] = set()

    def area(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        return ((hi - lo + 1) * self.unit).prod(axis=-1)

    def sides(self, node: _Node) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if node.sides is None:
            lo, hi = np.array([k.lo for k in node.kids]), np.array([k.hi for k in node.kids])
            node.sides = lo, hi, self.area(lo, hi)
        return node.sides

    def cost(self, node: _Node, p: np.ndarray) -> tuple[int, np.ndarray]:
        """The child to take, and the costs of all."""
        lo, hi, old = self.sides(node)
        new = self.area(np.minimum(lo, p), np.maximum(hi, p))
        cost = new - old
        if self.criterion != "area":
            cost = new / old * cost
        if self.criterion == "density_n":
            n = np.array([k.n for k in node.kids], float)
            cost = cost * n / (n + 1)
        return int(np.lexsort((old, cost))[0]), cost

    def build(self, points: np.ndarray) -> BoxTree:
        self.data = np.asarray(points, np.int64)
        self.insert_all(np.arange(len(points)), True)
        return self

    def insert_all(self, order: np.ndarray, fresh: bool = False) -> None:
        """Points in their order. ``fresh``: each may re-insert at every level again."""
        at, step, alone = 0, LEAST_BATCH, 1
        while at < len(order):
            batch = order[at : at + step]
            done = self.settle(batch)
            at += done
            if done == len(batch):
                step = min(2 * step, MOST_BATCH)
                continue
            step, alone = min(max(2 * done, LEAST_BATCH), step), 1 if done >= LEAST_BATCH // 4 else min(2 * alone, LEAST_BATCH)
            for i in order[at : at + alone].tolist():
                if fresh:
                    self.again = set()
                self.insert(i)
            at += alone

    def settle(self, batch: np.ndarray) -> int:
        """Takes the first points of ``batch``, up to one that grows a box or overflows a leaf; their number."""
        if self.root is None:
            return 0
        x, stop, found = self.data[batch], len(batch), []
        held = ((x >= self.root.lo) & (x <= self.root.hi)).all(axis=1)
        stack = [(self.root, np.arange(stop))]
        if not held.all():
            stop = int(held.argmin())
            stack = [(self.root, np.arange(stop))]
        while stack:
            node, at = stack.pop()
            at = at[: np.searchsorted(at, stop)]
            if not len(at):
                continue
            if node.points is not None:
                room = self.capacity - len(node.points)
                if len(at) > room:
                    stop = int(at[room])
                found.append((node, at))
                continue
            lo, hi, area = self.sides(node)
            mine, small = x[at], np.argsort(area, kind="stable")
            held = np.ones((len(small), len(at)), bool)
            for d in range(x.shape[1]):
                c = mine[:, d]
                held &= (lo[small, d, None] <= c) & (c <= hi[small, d, None])
            first = held.argmax(axis=0)
            ok = held[first, np.arange(len(at))]
            if not ok.all():
                end = int(ok.argmin())
                stop, at, first = int(at[end]), at[:end], first[:end]
            stack += [(node.kids[small[j]], at[first == j]) for j in np.flatnonzero(np.bincount(first))]
        for node, at in found:
            at = at[: np.searchsorted(at, stop)]
            node.points.frombytes(batch[at].astype(np.int64).tobytes())
            while node is not None:
                node.n += len(at)
                node = node.up
        return stop

    def insert(self, i: int) -> None:
        p = self.data[i]
        if self.root is None:
            self.root = _Node(p, p, True)
        node, depth = self.root, 1
        while True:
            if (p < node.lo).any() or (p > node.hi).any():
                np.minimum(node.lo, p, out=node.lo)
                np.maximum(node.hi, p, out=node.hi)
                node.changed()
            node.n += 1
            if node.points is not None:
                break
            node, depth = node.kids[self.cost(node, p)[0]], depth + 1
        node.points.append(i)
        if len(node.points) > self.capacity:
            self.overflow(node, depth)

    def overflow(self, node: _Node, depth: int) -> None:
        if self.share and node.points is not None and node is not self.root and depth not in self.again:
            self.again.add(depth)
            held = np.array(node.points)
            far = np.argsort(-((((self.data[held] - (node.lo + node.hi) / 2) * self.unit) ** 2).sum(axis=1)), kind="stable")
            k = max(1, int(self.share * len(far)))
            node.points = array("q", held[np.sort(far[k:])].tobytes())
            self.shrink(node, k)
            self.insert_all(held[far[:k][::-1]])
            return
        items = np.array(node.points) if node.points is not None else node.kids
        lo = self.data[items] if node.points is not None else np.array([k.lo for k in items])
        hi = lo if node.points is not None else np.array([k.hi for k in items])
        left, right = (np.asarray(x) for x in split(lo, hi, self.unit, 0.5 if node.points is not None else 0.4))
        parts = []
        for at in (left, right):
            new = _Node(lo[at].min(axis=0), hi[at].max(axis=0), node.points is not None)
            if node.points is not None:
                new.points, new.n = array("q", items[at].tobytes()), len(at)
            else:
                new.kids = [items[j] for j in at]
                new.n = sum(k.n for k in new.kids)
                for k in new.kids:
                    k.up = new
            parts.append(new)
        up = node.up
        if up is None:
            self.root = _Node(np.minimum(parts[0].lo, parts[1].lo), np.maximum(parts[0].hi, parts[1].hi), False)
            self.root.n, self.root.kids = node.n, parts
            parts[0].up = parts[1].up = self.root
            return
        up.kids[up.kids.index(node)] = parts[0]
        up.kids.append(parts[1])
        up.sides = None
        parts[0].up = parts[1].up = up
        if len(up.kids) > self.fanout:
            self.overflow(up, depth - 1)

    def shrink(self, node: _Node, lost: int) -> None:
        while node is not None:
            node.n -= lost
            lo, hi = (self.data[np.array(node.points)],) * 2 if node.points is not None else self.sides(node)[:2]
            node.lo, node.hi = lo.min(axis=0).copy(), hi.max(axis=0).copy()
            node.changed()
            node = node.up

    def nodes(self) -> Nodes:
        rows, stack = [], [(self.root, -1, 1)] if self.root else []
        while stack:
            node, up, depth = stack.pop()
            me = len(rows)
            rows.append((node.lo, node.hi, up, depth, node.n, node.points is not None))
            stack += [(k, me, depth + 1) for k in reversed(node.kids or [])]
        lo, hi, up, depth, n, leaf = zip(*rows) if rows else ([], [], [], [], [], [])
        return Nodes(np.array(lo, np.int64), np.array(hi, np.int64), np.array(up, int), np.array(depth, int), np.array(n, int), np.array(leaf, bool))


def split(lo: np.ndarray, hi: np.ndarray, unit: np.ndarray, fill: float = 0.5) -> tuple[list[int], list[int]]:
    """R* split of boxes: row numbers of both sides, each at least the share ``fill`` of the entries. At one half, a node of
    capacity m that overflows leaves two of at least m/2."""
    n = len(lo)
    least = max(1, int(fill * n))
    best: tuple = ()
    for axis in range(lo.shape[1]):
        options = []
        for key in (lo, hi) if lo is not hi else (lo,):
            order = np.lexsort((hi[:, axis], key[:, axis]))
            a, b = lo[order], hi[order]
            l1, h1 = np.minimum.accumulate(a), np.maximum.accumulate(b)
            l2, h2 = np.minimum.accumulate(a[::-1])[::-1], np.maximum.accumulate(b[::-1])[::-1]
            k = np.arange(least, n - least + 1)
            s1, s2 = (h1[k - 1] - l1[k - 1] + 1) * unit, (h2[k] - l2[k] + 1) * unit
            both = np.minimum(h1[k - 1], h2[k]) - np.maximum(l1[k - 1], l2[k])
            overlap = np.where((both < 0).any(axis=1), 0.0, ((both + 1) * unit).prod(axis=1))
            options.append((s1.sum() + s2.sum(), overlap, s1.prod(axis=1) + s2.prod(axis=1), k, order))
        margin = sum(o[0] for o in options)
        if not best or margin < best[0]:
            best = (margin, options)
    pick = min(((o[1][j], o[2][j], i, j) for i, o in enumerate(best[1]) for j in range(len(o[3]))))
    chosen = best[1][pick[2]]
    cut = int(chosen[3][pick[3]])
    return chosen[4][:cut].tolist(), chosen[4][cut:].tolist()


def build(points: np.ndarray, widths: np.ndarray, target_leaves: int | None = None, capacity: int | None = None, target_height: int | None = None, fanout: int = 12, criterion: str = "density", reinsert: float = 0.0) -> Nodes:
    """A tree over ``points``, with a node capacity, or about a number of leaves, or the least number of leaves that gives
    a height. Points are taken in a fixed shuffled order, so the outcome depends on them alone."""
    points = np.asarray(points, np.int64)
    points = points[np.lexsort(points.T[::-1])] if len(points) else points
    points = points[np.random.default_rng(2).permutation(len(points))]
    if target_height is not None:
        target_leaves = max(1, int(0.6 * fanout) ** (target_height - 1))
    if capacity is None:
        capacity = max(2, round(len(points) * 1.5 / max(1, target_leaves or 64)))
    return BoxTree(widths, capacity, fanout, criterion, reinsert).build(points).nodes()


def evenness(points: np.ndarray, nodes: Nodes, widths: np.ndarray, cells: int = 4) -> dict[str, float]:
    """Quality of a partition over ``points``: share of leaf area without points in a raster, overlapping area of leaf
    pairs over all leaf area, variation of leaf counts, and mean variation of counts inside leaves."""
    lo, hi = nodes.lo[nodes.leaves], nodes.hi[nodes.leaves]
    side = (hi - lo + 1) / widths
    area = side.prod(axis=1)
    both = np.minimum(hi[:, None], hi[None]) - np.maximum(lo[:, None], lo[None])
    meet = np.where((both < 0).any(axis=2), 0, ((both + 1) / widths).prod(axis=2))
    overlap = (meet.sum() - np.trace(meet)) / 2
    counts, inner, empty = [], [], 0.0
    for a, b, size in zip(lo, hi, area):
        mine = points[((points >= a) & (points <= b)).all(axis=1)]
        counts.append(len(mine))
        cell = ((mine - a) * cells // (b - a + 1)).clip(0, cells - 1)
        n = np.bincount(cell @ cells ** np.arange(points.shape[1]), minlength=cells ** points.shape[1]) if len(mine) else np.zeros(1)
        empty += size * (n == 0).mean()
        if len(mine) > 1:
            inner.append(n.std() / n.mean())
    counts = np.array(counts, float)
    return {"leaves": float(len(lo)), "empty_share": float(empty / area.sum()), "overlap_share": float(overlap / area.sum()), "count_variation": float(counts.std() / max(counts.mean(), 1e-9)), "inner_variation": float(np.mean(inner)) if inner else 0.0}
