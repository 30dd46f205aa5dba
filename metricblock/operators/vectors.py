"""Distances of all pairs of vectors, by blocks: rows of pairs, sums over them, or the nearest of each."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.operators.pairwise import BLOCK, meet, packed, parallel, sliced

#: Rows of a block worked on at a time, so that their distances stay in cache.
ROWS = 64


def matrix(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray | None]:
    """Vectors as rows, and which components are there (nothing if all are); short and null ones are filled."""
    whole = column.combine_chunks()
    whole = whole.chunk(0) if isinstance(whole, pa.ChunkedArray) else whole
    sizes = whole.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    most = int(sizes.max()) if len(sizes) else 0
    flat = whole.flatten()
    if not flat.null_count and (sizes == most).all():
        return flat.to_numpy(zero_copy_only=False).astype(float).reshape(len(whole), most), None
    out, there = np.zeros((len(whole), most)), np.arange(most)[None, :] < sizes[:, None]
    valid = flat.is_valid().to_numpy(zero_copy_only=False)
    out[there] = np.where(valid, flat.fill_null(0).to_numpy(zero_copy_only=False).astype(float), 0)
    there[there] = valid
    return out, there


def distances(x: np.ndarray, y: np.ndarray, p: float = 2, xt: np.ndarray | None = None, yt: np.ndarray | None = None) -> np.ndarray:
    """L^p distances, rows of x by rows of y, summed in the order of the components.

    Components that either side lacks don't count; where none is left the distance is nan.
    """
    out = np.zeros((len(x), len(y)))
    gap = np.empty_like(out)
    common = min(x.shape[1], y.shape[1])
    count = np.zeros(out.shape, dtype=np.int32) if xt is not None or yt is not None else None
    for k in range(common):
        np.subtract(x[:, k, None], y[None, :, k], out=gap)
        if count is not None:
            both = (True if xt is None else xt[:, k, None]) & (True if yt is None else yt[None, :, k])
            gap[~np.broadcast_to(both, gap.shape)] = 0
            count += both
        if p == 2:
            np.multiply(gap, gap, out=gap)
        else:
            np.abs(gap, out=gap)
            if p not in (1, float("inf")):
                np.power(gap, p, out=gap) if p != 3 else np.multiply(gap, gap * gap, out=gap)
        np.maximum(out, gap, out=out) if p == float("inf") else np.add(out, gap, out=out)
    if p == 2:
        np.sqrt(out, out=out)
    elif p not in (1, float("inf")):
        np.power(out, 1.0 / p, out=out)
    if count is not None:
        out[count == 0] = np.nan
    elif not common:
        out[:] = np.nan
    return out


class Side:
    """A block as arrays: ids, vectors, and maybe coordinates and labels."""

    def __init__(self, some: pa.Table):
        self.ids = some["id"].to_numpy()
        self.v, self.there = matrix(some["v"])
        self.columns = np.asfortranarray(self.v)
        self.some = some
        if "coords" in some.column_names:
            self.coords, self.known = matrix(some["coords"])
        if "label" in some.column_names:
            self.labels = some["label"].to_numpy(zero_copy_only=False)

    def part(self, rows: slice) -> np.ndarray | None:
        return None if self.there is None else self.there[rows]


def rounded(d: np.ndarray, digits: int) -> np.ndarray:
    """Distances to so many digits, halves up, as DuckDB's ``round`` does it; where that overflows they stay."""
    scale = 10.0**digits
    scaled = d * scale
    whole = np.floor(scaled)
    with np.errstate(invalid="ignore"):  # infinite less infinite
        whole += scaled - whole >= 0.5
    whole /= scale
    return whole if np.isfinite(whole.max(initial=0)) else np.where(np.isfinite(whole), whole, d)


def pair_rows(points: DataFrame, p: float, digits: int | None = None) -> DataFrame:
    """``(a, b, d)``, a < b, of all pairs of ``points(id long, v array<double>)``: the L^p distance, null where no component is common.

    Distances are rounded to ``digits`` if given, in the task that has them as arrays.
    """
    blocks = packed(points.select(F.col("id").cast("long").alias("id"), F.col("v").cast("array<double>").alias("v")), min(BLOCK, max(128, -(-points.count() // parallel(points)))))

    def work(x: Side, y: Side, same: bool) -> Iterator[pa.RecordBatch]:
        again = not same and bool(np.isin(x.ids, y.ids).any())
        for r in range(0, len(x.ids), ROWS):
            rows = slice(r, r + ROWS)
            d = distances(x.v[rows], y.columns, p, x.part(rows), y.there)
            d = d if digits is None else rounded(d, digits)
            a, b = np.broadcast_arrays(x.ids[rows, None], y.ids[None, :])
            a, b, d, unknown = a.ravel(), b.ravel(), d.ravel(), None
            if same or again:
                keep = a < b if same else a != b
                a, b, d = a[keep], b[keep], d[keep]
            if x.there is not None or y.there is not None:
                unknown = np.isnan(d)
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(d, mask=unknown)], ["a", "b", "d"])

    return meet(blocks, blocks, Side, work, "a long, b long, d double", triangle=True)


def _both(x: Side, y: Side, same: bool) -> Iterator[tuple[slice, np.ndarray, np.ndarray, np.ndarray]]:
    """Slices of x's rows with their distances to y in full dimension (``delta``) and by coordinates (``d``), and which pairs count."""
    for r in range(0, len(x.ids), ROWS):
        rows = slice(r, r + ROWS)
        delta = distances(x.v[rows], y.columns, 2, x.part(rows), y.there)
        d = distances(x.coords[rows], y.coords, 2, None if x.known is None else x.known[rows], y.known)
        seen = x.ids[rows, None] < y.ids[None, :] if same else np.ones(d.shape, dtype=bool)
        if not (x.there is y.there is None and x.known is y.known is None):
            seen &= ~(np.isnan(delta) | np.isnan(d))
        yield rows, delta, d, seen


def stress_parts(points: DataFrame, by: bool = False) -> DataFrame:
    """Sums over all pairs of ``points(id, v, coords[, label])``: ``(miss, size, expansion, contraction[, label])``, a row for two blocks.

    ``miss`` is the sum of squared differences of both distances, ``size`` that of squared distances of ``v``; the
    other two are the largest ratios where both distances are over zero.  With ``by`` there is a row
    for each label of a pair's vector of smaller id.
    """
    blocks = packed(points)
    kind = dict(points.dtypes).get("label", "long")

    def work(x: Side, y: Side, same: bool) -> Iterator[pa.RecordBatch]:
        out: dict = {}
        for rows, delta, d, seen in _both(x, y, same):
            if not seen.any():
                continue
            miss, size = np.where(seen, (d - delta) ** 2, 0), np.where(seen, delta * delta, 0)
            if not by:
                ok = seen & (d > 0) & (delta > 0)
                ratio = d[ok] / delta[ok]
                old = out.get(0, (0.0, 0.0, None, None))
                most = [(np.max(z) if len(z) else None) for z in (ratio, delta[ok] / d[ok])]
                out[0] = (old[0] + float(miss.sum()), old[1] + float(size.sum()), *[max((v for v in (a, b) if v is not None), default=None) for a, b in zip(old[2:], most, strict=True)])
                continue
            first = x.ids[rows, None] < y.ids[None, :]
            for labels, axis, own in ((x.labels[rows], 1, first), (y.labels, 0, ~first)):
                sums = [np.where(own, z, 0).sum(axis=axis) for z in (miss, size, seen)]
                for label, m, s, n in zip(labels.tolist(), *sums, strict=True):
                    if n:
                        old = out.get(label, (0.0, 0.0, None, None))
                        out[label] = (old[0] + float(m), old[1] + float(s), None, None)
        columns = list(zip(*((*v, k if by and k == k else None) for k, v in out.items()), strict=True)) or [()] * 5
        yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.float64()) for c in columns[:4]), pa.array([None if c is None else int(c) for c in columns[4]], pa.int64())], ["miss", "size", "expansion", "contraction", "label"])

    found = meet(blocks, blocks, Side, work, "miss double, size double, expansion double, contraction double, label long", triangle=True)
    return found.withColumn("label", F.col("label").cast(kind)) if by else found.drop("label")


def majorize_all(points: DataFrame) -> DataFrame:
    """One majorization step over all pairs of ``points(id, v, coords)``, unit weights: ``(id, coords)`` of the vectors that have a pair with d over zero."""
    blocks = packed(points)

    def work(x: Side, y: Side, same: bool) -> Iterator[pa.RecordBatch]:
        pull, touched = np.zeros_like(y.coords), np.zeros(len(y.ids), dtype=bool)
        ids, moves = [], []
        for rows, delta, d, seen in _both(x, y, same):
            ok = seen & (d > 0)
            r = np.divide(delta, d, out=np.zeros_like(d), where=ok)
            mine = x.coords[rows]
            some = ok.any(axis=1)
            ids.append(x.ids[rows][some])
            moves.append((r.sum(axis=1)[:, None] * mine - r @ y.coords)[some])
            pull += r.sum(axis=0)[:, None] * y.coords - r.T @ mine
            touched |= ok.any(axis=0)
        ids.append(y.ids[touched])
        moves.append(pull[touched])
        at = np.concatenate(moves)
        if len(at):
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(ids)), pa.ListArray.from_arrays(np.arange(0, at.size + 1, at.shape[1], dtype=np.int32), at.ravel())], ["id", "move"])

    n = F.lit(points.count())
    moved = meet(blocks, blocks, Side, work, "id long, move array<double>", triangle=True).select("id", F.posexplode("move").alias("dim", "m"))
    summed = moved.groupBy("id", "dim").agg((F.sum("m") / n).alias("at"))
    return summed.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "at"))), lambda s: s["at"]).alias("coords"))


def nearest(queries: DataFrame, points: DataFrame, k: int, include_self: bool = True) -> DataFrame:
    """``(q_id, n_id, dist)``: for each query its ``k`` nearest of a part of the points, by looking at all of them; the caller ranks the parts.

    An inner product bounds each distance; those that may be among the nearest are measured themselves.
    """
    names = [F.col("id").cast("long").alias("id"), F.col("coords").cast("array<double>").alias("v")]
    left, right = packed(queries.select(*names)), packed(points.select(*names), 4096)

    class Asked(Side):
        def __init__(self, some: pa.Table):
            super().__init__(some)
            self.square = np.einsum("ij,ij->i", self.v, self.v)
            self.row, self.near, self.dist = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0)
            self.limit = np.full(len(self.ids), np.inf)

    def work(x: Asked, y: Asked, same: bool) -> Iterator[pa.RecordBatch]:
        if not len(y.ids) or k < 1:
            return
        for r in range(0, len(x.ids), 4 * ROWS):
            rows = slice(r, r + 4 * ROWS)
            plain = x.there is None and y.there is None and x.v.shape[1] == y.v.shape[1]
            if plain:
                about = (x.square[rows, None] + y.square[None, :]) - 2 * (x.v[rows] @ y.v.T)
                slack = 1e-9 * (x.square[rows, None] + y.square.max()) + 1e-300
                limit = x.limit[rows]
                if not np.isfinite(limit).all() and about.shape[1] > k + 1:
                    kth = np.partition(about, k, axis=1)[:, k]  # one more than k, since the query itself may be among them
                    limit = np.minimum(limit, np.sqrt(np.maximum(kth + 2 * slack[:, 0], 0)))
                q, n = np.nonzero(~(about > limit[:, None] ** 2 + slack))
                gap = np.zeros(len(q))
                for c in range(x.v.shape[1]):
                    gap += (x.v[r + q, c] - y.columns[n, c]) ** 2
                d = np.sqrt(gap)
            else:
                d = distances(x.v[rows], y.columns, 2, x.part(rows), y.there)
                q, n = np.nonzero(~np.isnan(d))
                d = d[q, n]
            q = q + r
            if not include_self:
                other = y.ids[n] != x.ids[q]
                q, n, d = q[other], n[other], d[other]
            row, near, dist = np.concatenate([x.row, q]), np.concatenate([x.near, y.ids[n]]), np.concatenate([x.dist, d])
            order = np.lexsort((near, dist, row))
            row, near, dist = row[order], near[order], dist[order]
            starts = np.searchsorted(row, np.arange(len(x.ids) + 1))
            keep = np.arange(len(row)) - starts[row] < k
            full = starts[1:] - starts[:-1] >= k
            x.limit[full] = dist[starts[:-1][full] + k - 1]
            x.row, x.near, x.dist = row[keep], near[keep], dist[keep]
        yield from ()

    def end(x: Asked) -> Iterator[pa.RecordBatch]:
        yield from sliced([x.ids[x.row], x.near, x.dist], ["q_id", "n_id", "dist"])

    return meet(left, right, Asked, work, "q_id long, n_id long, dist double", end=end)
