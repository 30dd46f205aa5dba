"""Trees over points in memory: kd-tree and packed R-tree, with one search for both.

A tree is a set of nodes with boxes.  Search keeps a priority queue of nodes by the distance of
their boxes and a bounded list of the best points; a branch whose box is farther than the worst
of them is never opened.  Ties in distance go to the smaller id, as in a sequential scan.
"""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass, field

import numpy as np

from metricblock.functions.edit_kernel import spread


@dataclass
class SearchStats:
    nodes_visited: int = 0
    distances: int = 0


@dataclass
class BoxTree:
    points: np.ndarray = field(repr=False)
    ids: np.ndarray = field(repr=False)
    low: np.ndarray = field(repr=False)
    high: np.ndarray = field(repr=False)
    children: list[list[int]] = field(repr=False)  # empty for leaves
    span: np.ndarray = field(repr=False)  # of a leaf's points

    def _far(self, nodes: list[int], q: np.ndarray) -> np.ndarray:
        gap = np.maximum(np.maximum(self.low[nodes] - q, q - self.high[nodes]), 0)
        return np.einsum("ij,ij->i", gap, gap)

    def knn(self, q: np.ndarray, k: int, without: int | None = None, stats: SearchStats | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Ids and distances of the ``k`` nearest points (all, if fewer), nearest first."""
        best_id, best = np.zeros(0, dtype=np.int64), np.zeros(0)
        if k < 1 or not len(self.ids):
            return best_id, best
        queue = [(float(self._far([0], q)[0]), 0)]
        while queue:
            far, node = heapq.heappop(queue)
            if len(best) == k and far > best[-1]:
                break
            if stats:
                stats.nodes_visited += 1
            if self.children[node]:
                kids = self.children[node]
                for d, kid in zip(self._far(kids, q).tolist(), kids, strict=True):
                    if len(best) < k or d <= best[-1]:
                        heapq.heappush(queue, (d, kid))
                continue
            a, b = self.span[node]
            gap = self.points[a:b] - q
            d, ids = np.einsum("ij,ij->i", gap, gap), self.ids[a:b]
            if stats:
                stats.distances += b - a
            if without is not None:
                d, ids = d[ids != without], ids[ids != without]
            if len(best) == k:
                near = d <= best[-1]
                d, ids = d[near], ids[near]
            if len(d):
                best_id, best = np.concatenate([best_id, ids]), np.concatenate([best, d])
                keep = np.lexsort((best_id, best))[:k]
                best_id, best = best_id[keep], best[keep]
        return best_id, np.sqrt(best)

    def leaves(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Boxes and spans of the leaves."""
        own = np.array([i for i, c in enumerate(self.children) if not c], dtype=np.int64)
        return self.low[own], self.high[own], self.span[own]

    def knn_many(self, qs: np.ndarray, k: int, without: np.ndarray | None = None, together: int = 32) -> list[tuple[np.ndarray, np.ndarray]]:
        """As ``knn`` for many queries: neighbours in space are answered together, as arrays.

        A group looks at leaves in the order of the distance between their box and its own, and
        ends where no box is nearer than the worst of the group's neighbours.  If all points are
        asked for, they are all measured and sorted.
        """
        n = len(self.ids)
        if k < 1 or not n:
            return [(np.zeros(0, dtype=np.int64), np.zeros(0)) for _ in qs]
        out: list = [None] * len(qs)
        low, high, span = self.leaves()
        for group in _groups(qs, together):
            q = qs[group]
            own = None if without is None else without[group]
            gap = np.maximum(np.maximum(low - q.max(axis=0), q.min(axis=0) - high), 0)
            far = np.einsum("ij,ij->i", gap, gap)
            order = np.argsort(far, kind="stable")
            sizes = np.cumsum((span[:, 1] - span[:, 0])[order])
            best = np.zeros((len(q), 0))
            best_id = np.zeros((len(q), 0), dtype=np.int64)
            a, want = 0, max(2 * k, 256)
            while a < len(order):
                b = a + 1 + int(np.searchsorted(sizes[a:] - (sizes[a - 1] if a else 0), want))
                if best.shape[1] == k:
                    b = min(b, a + int(np.searchsorted(far[order[a:]], best[:, -1].max() * (1 + 1e-12), side="right")))
                    if b == a:
                        break
                at = np.concatenate([np.arange(*span[j]) for j in order[a:b]])
                d = np.zeros((len(q), len(at)))
                for c in range(qs.shape[1]):  # in the order of the components
                    d += (q[:, c, None] - self.points[at, c][None, :]) ** 2
                ids = np.broadcast_to(self.ids[at], d.shape)
                if own is not None:
                    d[ids == own[:, None]] = np.inf
                best, best_id = _merged(best, best_id, d, ids, k)
                a, want = b, 2 * want
            for i, g in enumerate(group):
                real = best[i] < np.inf
                out[g] = (best_id[i][real], np.sqrt(best[i][real]))
        return out

    def within_many(self, qs: np.ndarray, radius: float, together: int = 32) -> list[tuple[np.ndarray, np.ndarray]]:
        """As ``within`` for many queries, nearest first."""
        out: list = [(np.zeros(0, dtype=np.int64), np.zeros(0))] * len(qs)
        if not len(self.ids):
            return out
        low, high, span = self.leaves()
        for group in _groups(qs, together):
            q = qs[group]
            gap = np.maximum(np.maximum(low - q.max(axis=0), q.min(axis=0) - high), 0)
            near = np.flatnonzero(np.einsum("ij,ij->i", gap, gap) <= radius * radius * (1 + 1e-12))
            parts = [np.arange(*span[j]) for j in near]
            at = np.concatenate([np.zeros(0, dtype=np.int64), *parts])
            for a in range(0, max(1, len(at)), 1 << 16):
                some = at[a : a + (1 << 16)]
                d = np.zeros((len(q), len(some)))
                for c in range(qs.shape[1]):
                    d += (q[:, c, None] - self.points[some, c][None, :]) ** 2
                d = np.sqrt(d)
                for i, g in enumerate(group):
                    hit = np.flatnonzero(d[i] <= radius)
                    out[g] = (np.concatenate([out[g][0], self.ids[some[hit]]]), np.concatenate([out[g][1], d[i][hit]]))
            for g in group:
                order = np.lexsort(out[g])
                out[g] = (out[g][0][order], out[g][1][order])
        return out

    def within(self, q: np.ndarray, radius: float) -> tuple[np.ndarray, np.ndarray]:
        """Ids and distances of all points at most ``radius`` away, nearest first."""
        found_id, found, stack = [np.zeros(0, dtype=np.int64)], [np.zeros(0)], [0] if len(self.ids) else []
        limit = radius * radius
        while stack:
            node = stack.pop()
            if self._far([node], q)[0] > limit * (1 + 1e-12):
                continue
            if self.children[node]:
                stack += self.children[node]
                continue
            a, b = self.span[node]
            gap = self.points[a:b] - q
            d = np.sqrt(np.einsum("ij,ij->i", gap, gap))
            found_id.append(self.ids[a:b][d <= radius])
            found.append(d[d <= radius])
        ids, d = np.concatenate(found_id), np.concatenate(found)
        order = np.lexsort((ids, d))
        return ids[order], d[order]


class Ranks:
    """Ranks of some points among all points of a tree, by distance from a query, ties to the smaller id.

    Leaves that are nearer than all of the points asked for are counted whole, farther ones aren't
    looked at; only points of those between are measured.
    """

    def __init__(self, tree: BoxTree):
        self.low, self.high, self.span = tree.leaves()
        self.ids, self.columns = tree.ids, np.ascontiguousarray(tree.points.T)
        self.place = np.argsort(tree.ids)

    def _far(self, q: np.ndarray, at: np.ndarray) -> np.ndarray:
        out = np.zeros(len(at))
        for x, c in zip(self.columns, q, strict=True):
            out += (x[at] - c) ** 2
        return out

    def of(self, q: np.ndarray, at: np.ndarray, without: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Ranks and distances of the points at places ``at``; the point with id ``without`` doesn't count."""
        far, ids = self._far(q, at), self.ids[at]
        order = np.lexsort((ids, far))
        mark, mark_ids = far[order], ids[order]
        near = (np.maximum(np.maximum(self.low - q, q - self.high), 0) ** 2).sum(axis=1)
        most = (np.maximum(np.abs(self.low - q), np.abs(self.high - q)) ** 2).sum(axis=1)
        inside = most * (1 + 1e-9) < mark[0]
        between = ~inside & (near <= mark[-1] * (1 + 1e-9))
        some = spread(*self.span[between].T)
        d = self._far(q, some)
        before = np.cumsum(np.bincount(np.searchsorted(mark, d, side="right"), minlength=len(mark) + 1))[:-1]  # strictly nearer ones
        before += int((self.span[inside, 1] - self.span[inside, 0]).sum())
        first = np.searchsorted(mark, mark)
        level = np.searchsorted(mark, d)
        tied = np.flatnonzero((level < len(mark)) & (mark[np.minimum(level, len(mark) - 1)] == d))
        tied = tied[np.lexsort((self.ids[some[tied]], level[tied]))]
        levels, tied_ids = level[tied], self.ids[some[tied]]
        for k in range(len(mark)):
            a, b = np.searchsorted(levels, [first[k], first[k] + 1])
            before[k] += np.searchsorted(tied_ids[a:b], mark_ids[k])
        if without is not None:
            own = self.place[min(np.searchsorted(self.ids, without, sorter=self.place), len(self.ids) - 1)]
            if self.ids[own] == without:
                mine = self._far(q, np.array([own]))[0]
                before -= (mine < mark) | ((mine == mark) & (without < mark_ids))
        rank = np.empty(len(at), dtype=np.int32)
        rank[order] = before + 1
        return rank, np.sqrt(far)


def _groups(qs: np.ndarray, together: int) -> list[np.ndarray]:
    """Queries split at medians of the widest side into groups of neighbours."""
    done, stack = [], [np.arange(len(qs))] if len(qs) else []
    while stack:
        own = stack.pop()
        if len(own) <= together:
            done.append(own)
            continue
        x = qs[own]
        dim = int(np.argmax(x.max(axis=0) - x.min(axis=0)))
        order = np.argpartition(x[:, dim], len(own) // 2)
        stack += [own[order[: len(own) // 2]], own[order[len(own) // 2 :]]]
    return done


def _merged(best: np.ndarray, best_id: np.ndarray, d: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The ``k`` best of each row of both, sorted; ties to the smaller id."""
    if best.shape[1] == k:
        some = (d <= best[:, -1:]).any(axis=0)  # columns that are of use to any row
        d, ids = d[:, some], ids[:, some]
    d, ids = np.concatenate([best, d], axis=1), np.concatenate([best_id, ids], axis=1)
    if d.shape[1] > 2 * k:  # all that aren't farther than the k-th, ties included
        kth = np.partition(d, k - 1, axis=1)[:, k - 1 : k]
        keep = d <= kth
        most = int(keep.sum(axis=1).max())
        at = np.argsort(~keep, axis=1, kind="stable")[:, :most]
        d, ids = np.where(np.take_along_axis(keep, at, axis=1), np.take_along_axis(d, at, axis=1), np.inf), np.take_along_axis(ids, at, axis=1)
    order = np.lexsort((ids, d), axis=1)[:, :k]
    return np.take_along_axis(d, order, axis=1), np.take_along_axis(ids, order, axis=1)


def _boxes(points: np.ndarray, leaves: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray]:
    low = np.array([points[a:b].min(axis=0) for a, b in leaves])
    high = np.array([points[a:b].max(axis=0) for a, b in leaves])
    return low, high


class KDTree(BoxTree):
    """Split at the median of one coordinate, in turn (``axis="cycle"``) or of the widest."""

    @classmethod
    def build(cls, points: np.ndarray, ids: np.ndarray, leaf_size: int = 32, axis: str = "cycle") -> KDTree:
        points, ids = np.asarray(points, dtype=float), np.asarray(ids, dtype=np.int64)
        order = np.lexsort((ids, *points.T)) if len(ids) else np.zeros(0, dtype=int)
        low, high, children, span = [], [], [], []

        def grow(a: int, b: int, depth: int) -> int:
            at = len(children)
            own = points[order[a:b]]
            low.append(own.min(axis=0))
            high.append(own.max(axis=0))
            children.append([])
            span.append((a, b))
            if b - a > leaf_size and (high[at] > low[at]).any():
                dim = depth % points.shape[1] if axis == "cycle" else int(np.argmax(high[at] - low[at]))
                mid = (b - a) // 2
                order[a:b] = order[a:b][np.argpartition(own[:, dim], mid)]
                children[at] = [grow(a, a + mid, depth + 1), grow(a + mid, b, depth + 1)]
            return at

        if len(ids):
            grow(0, len(ids), 0)
        shape = (0, points.shape[1] if points.ndim == 2 else 0)
        return cls(points[order], ids[order], np.array(low).reshape(-1, shape[1]), np.array(high).reshape(-1, shape[1]), children, np.array(span, dtype=np.int64).reshape(-1, 2))


class RTree(BoxTree):
    """Sort-tile packing: leaves of neighbours, then nodes of neighbouring leaves, up to one root."""

    @classmethod
    def pack(cls, points: np.ndarray, ids: np.ndarray, leaf_size: int = 32, fan: int = 8) -> RTree:
        points, ids = np.asarray(points, dtype=float), np.asarray(ids, dtype=np.int64)
        n, dims = points.shape if len(ids) else (0, 1)
        order = np.arange(n)
        groups = [order]
        for dim in range(dims):
            slabs = max(1, math.ceil((math.ceil(n / leaf_size)) ** (1 / dims)))
            groups = [part for g in groups for part in np.array_split(g[np.argsort(points[g, dim], kind="stable")], min(slabs, max(1, len(g) // leaf_size)))]
        leaves, at = [], 0
        for g in groups:
            for a in range(0, len(g), leaf_size):
                size = min(leaf_size, len(g) - a)
                leaves.append((at, at + size))
                at += size
        order = np.concatenate(groups) if n else order
        points, ids = points[order], ids[order]
        if not n:
            return cls(points.reshape(0, dims), ids, np.zeros((0, dims)), np.zeros((0, dims)), [], np.zeros((0, 2), dtype=np.int64))
        low, high = _boxes(points, leaves)
        level = [(low[i], high[i], None, leaves[i]) for i in range(len(leaves))]
        nodes = list(level)
        current = list(range(len(level)))
        while len(current) > 1:
            parents = []
            for a in range(0, len(current), fan):
                kids = current[a : a + fan]
                nodes.append((np.min([nodes[k][0] for k in kids], axis=0), np.max([nodes[k][1] for k in kids], axis=0), kids, (0, 0)))
                parents.append(len(nodes) - 1)
            current = parents
        last = len(nodes) - 1  # the root goes to the front
        back = {old: last - old for old in range(len(nodes))}
        turned = [nodes[last - i] for i in range(len(nodes))]
        return cls(points, ids, np.array([x[0] for x in turned]), np.array([x[1] for x in turned]), [[back[k] for k in x[2]] if x[2] else [] for x in turned], np.array([x[3] for x in turned], dtype=np.int64))


@dataclass(frozen=True)
class PartitionTree:
    """Cells of space by median splits of a sample; every point has exactly one cell."""

    dims: list[int]
    values: list[float]
    left: list[int]  # node, or -1 - cell
    right: list[int]

    @property
    def cells(self) -> int:
        return len(self.dims) + 1

    @classmethod
    def fit(cls, sample: np.ndarray, cells: int) -> PartitionTree:
        dims, values, left, right = [], [], [], []
        cell = iter(range(1 << 30))

        def grow(own: np.ndarray, want: int) -> int:
            if want <= 1 or len(own) < 2 or not (own.max(axis=0) > own.min(axis=0)).any():
                return -1 - next(cell)
            dim = int(np.argmax(own.max(axis=0) - own.min(axis=0)))
            value = float(np.median(own[:, dim]))
            if value == own[:, dim].max():
                value = float(own[own[:, dim] < value, dim].max())
            at = len(dims)
            for x, v in ((dims, dim), (values, value), (left, 0), (right, 0)):
                x.append(v)
            below = own[:, dim] <= value
            left[at], right[at] = grow(own[below], want // 2), grow(own[~below], want - want // 2)
            return at

        grow(np.asarray(sample, dtype=float), cells)
        return cls(dims, values, left, right)

    def assign(self, points: np.ndarray) -> np.ndarray:
        if not self.dims:
            return np.zeros(len(points), dtype=np.int32)
        at = np.zeros(len(points), dtype=np.int64)
        dims, values, left, right = (np.array(x) for x in (self.dims, self.values, self.left, self.right))
        while (inner := np.flatnonzero(at >= 0)).size:
            node = at[inner]
            below = points[inner, dims[node]] <= values[node]
            at[inner] = np.where(below, left[node], right[node])
        return (-1 - at).astype(np.int32)
