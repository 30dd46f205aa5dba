"""Multidimensional scaling: least squares by majorization or gradient, and classical scaling.

Dense matrices of landmarks live on the driver; the whole collection is scaled by
``lsmds_distributed``, whose dissimilarities are stored by groups of keys.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from metricblock.functions.edit_kernel import key_matrix
from metricblock.operators.clusters import drop, stored

DRIVER_ROWS, DISTRIBUTED_ROWS = 5_000, 50_000
#: Keys in a group of the complete embedding, and rows that are measured against a group at a time.
GROUP, MEASURED = 8192, 256
#: Rows and columns that a step works on at a time, so that their distances stay in cache.
ROWS_AT_ONCE, COLUMNS_AT_ONCE = 32, 1024


def distances(x: np.ndarray) -> np.ndarray:
    gap = x[:, None, :] - x[None, :, :]
    return np.sqrt(np.einsum("ijk,ijk->ij", gap, gap))


def aligned(x: np.ndarray) -> np.ndarray:
    """Centred, turned to principal axes, each axis pointing to its largest entry: one of all equal solutions."""
    x = x - x.mean(axis=0)
    _, _, axes = np.linalg.svd(x, full_matrices=False)
    x = x @ axes.T
    return x * np.where(x[np.abs(x).argmax(axis=0), np.arange(x.shape[1])] < 0, -1, 1)


def stress_of(delta: np.ndarray, x: np.ndarray, weights: np.ndarray | None = None, normalized: bool = True) -> float:
    w = np.ones_like(delta) if weights is None else weights
    known = np.nan_to_num(delta)
    raw = float((w * (distances(x) - known) ** 2).sum())
    return float(np.sqrt(raw / max((w * known**2).sum(), 1e-300))) if normalized else raw


def classical_mds(delta: np.ndarray, k: int) -> np.ndarray:
    """Coordinates from the leading eigenvectors of the double-centred squares."""
    n = len(delta)
    centre = np.eye(n) - 1 / n
    values, vectors = np.linalg.eigh(-0.5 * centre @ delta**2 @ centre)
    top = np.argsort(-values)[:k]
    out = vectors[:, top] * np.sqrt(np.maximum(values[top], 0))
    return np.pad(out, ((0, 0), (0, k - out.shape[1])))


def lsmds(delta: np.ndarray, k: int, solver: str = "majorize", weights: np.ndarray | None = None, init: str | np.ndarray = "classical", max_iter: int = 300, tol: float = 1e-6, seed: int = 42) -> tuple[np.ndarray, list[float]]:
    """Coordinates of least raw stress found, and the stress after each step (never rising).

    Missing dissimilarities (nan) get weight zero.  Restart from ``init="random"`` with other
    seeds to escape a poor optimum.
    """
    delta = np.asarray(delta, dtype=float)
    n = len(delta)
    if np.isnan(delta).any():
        weights = np.where(np.isnan(delta), 0.0, 1.0 if weights is None else weights)
    known = np.nan_to_num(delta)
    if n < 2:
        return np.zeros((n, k)), [0.0]
    if isinstance(init, np.ndarray):
        x = init.astype(float)
    elif init == "classical":
        x = classical_mds(known, k)
        if not distances(x).any():
            x = np.random.default_rng(seed).standard_normal((n, k))
    else:
        x = np.random.default_rng(seed).standard_normal((n, k)) * known.mean()
    pinv = None
    if weights is not None:
        v = -weights * (1 - np.eye(n))
        pinv = np.linalg.pinv(v - np.diag(v.sum(axis=1)))
    trace, step = [stress_of(known, x, weights, normalized=False)], 1.0
    for _ in range(max_iter):
        d = distances(x)
        ratio = np.divide(known, d, out=np.zeros_like(d), where=d > 0)
        if weights is not None:
            ratio *= weights
        if solver == "majorize":
            b = -ratio
            np.fill_diagonal(b, 0)
            np.fill_diagonal(b, -b.sum(axis=1))
            new = b @ x / n if pinv is None else pinv @ b @ x
        elif solver == "gradient":
            w = np.ones((n, n)) if weights is None else weights
            pull = w - ratio
            np.fill_diagonal(pull, 0)
            slope = 2 * (pull.sum(axis=1)[:, None] * x - pull @ x)
            new = x - step * slope / n
            while stress_of(known, new, weights, normalized=False) > trace[-1] and step > 1e-9:
                step /= 2
                new = x - step * slope / n
            step *= 1.5
        else:
            raise ValueError(solver)
        now = stress_of(known, new, weights, normalized=False)
        if now > trace[-1]:
            break
        x = new
        trace.append(now)
        if trace[-2] - now <= tol * max(trace[-2], 1e-300):
            break
    return aligned(x), trace


def landmark_delta(landmarks: list[list[str]], combine: str = "sum", weights: tuple[float, ...] | None = None) -> np.ndarray:
    """The dissimilarities of the landmarks among each other."""
    return key_matrix(landmarks, landmarks, combine, weights)


def lsmds_distributed(keys: DataFrame, k: int, max_iter: int = 30, tol: float = 1e-4, seed: int = 42, combine: str = "sum", force: bool = False) -> tuple[DataFrame, list[float]]:
    """The complete embedding of ``keys(key_id, key)``: ``(key_id, key, coords)`` and the stress trace.

    Every step costs all pairs, as the method does: a baseline, refused above ``DISTRIBUTED_ROWS``
    unless forced.  Keys are dealt into groups; the dissimilarities of two groups are computed once
    and stored.  Each step is one narrow pass over them with all coordinates at hand: a pair
    moves both its points, and a task gives the moves of its groups, so nothing is shuffled.
    """
    spark = keys.sparkSession
    rows = keys.select("key_id", "key").orderBy("key", "key_id").collect() if force or keys.count() <= DISTRIBUTED_ROWS else None
    if rows is None:
        raise ValueError(f"over {DISTRIBUTED_ROWS} keys: use landmarks")
    n = len(rows)
    every = spark.sparkContext.broadcast([r["key"] for r in rows])
    tasks = 4 * spark.sparkContext.defaultParallelism
    groups = max(1, min(n, max(math.isqrt(2 * tasks), -(-n // GROUP))))
    edge = [n * g // groups for g in range(groups + 1)]
    # which rows are measured against which group; a group meets itself and those after it
    pieces = [(g, h, a, min(a + MEASURED, edge[h + 1])) for g in range(groups) for h in range(g, groups) for a in range(edge[h], edge[h + 1], MEASURED)]
    tasks = max(1, min(len(pieces), max(tasks, groups * (groups + 1) // 2)))

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in batch.column(0).to_pylist():
                for g, h, a, b in pieces[len(pieces) * t // tasks : len(pieces) * (t + 1) // tasks]:
                    found = key_matrix(every.value[edge[g] : edge[g + 1]], every.value[a:b], combine).T
                    kind = next((x for x in (np.uint8, np.uint16) if found.max() <= np.iinfo(x).max), np.int32)
                    yield pa.RecordBatch.from_arrays([*(pa.array([v]) for v in (g, h, a, b)), pa.array([found.astype(kind).tobytes()], pa.binary())], ["g", "h", "a", "b", "data"])

    delta = stored(spark.range(0, tasks, 1, tasks).mapInArrow(measured, "g long, h long, a long, b long, data binary"), compression="zstd")
    reader = spark.newSession()  # with settings of its own: as many parts as were written, not few large ones
    reader.conf.set("spark.sql.files.minPartitionNum", tasks)
    reader.conf.set("spark.sql.files.openCostInBytes", 1 << 16)
    parts = reader.read.schema(delta.schema).parquet(delta.stored_at)
    x = np.random.default_rng(seed).standard_normal((n, k)) * 4
    trace: list[float] = []
    for _ in range(max_iter):
        shipped = spark.sparkContext.broadcast(x)

        def step(batches: Iterator[pa.RecordBatch], shipped=shipped) -> Iterator[pa.RecordBatch]:
            base = shipped.value
            moves: dict[int, np.ndarray] = {}
            miss = 0.0
            for batch in batches:
                for g, h, a, b, data in zip(*(batch.column(c).to_pylist() for c in range(4)), batch.column(4), strict=True):
                    data, own = data.as_buffer(), base[edge[g] : edge[g + 1]]
                    want = np.frombuffer(data, dtype={1: np.uint8, 2: np.uint16, 4: np.int32}[len(data) // ((b - a) * len(own))]).reshape(b - a, len(own))
                    for at in (g, h):
                        moves.setdefault(at, np.zeros((edge[at + 1] - edge[at], k)))
                    mine, theirs, missed = _pulled(base[a:b], own, want)
                    moves[h][a - edge[h] : b - edge[h]] += mine
                    if g != h:
                        moves[g] += theirs
                    miss += missed * (1 if g == h else 2)
            yield pa.RecordBatch.from_arrays([pa.array([*moves, None], pa.int64()), pa.array([*(m.tobytes() for m in moves.values()), None], pa.binary()), pa.array([*(0.0 for _ in moves), miss])], ["g", "moves", "miss"])

        x, missed = np.zeros((n, k)), 0.0
        for r in parts.mapInArrow(step, "g long, moves binary, miss double").collect():
            missed += r["miss"]
            if r["g"] is not None:
                x[edge[r["g"]] : edge[r["g"] + 1]] += np.frombuffer(r["moves"]).reshape(-1, k)
        x /= max(n, 1)
        shipped.destroy()
        trace.append(missed)
        if len(trace) > 1 and trace[-2] - trace[-1] <= tol * trace[-2]:
            break
    drop(delta)
    x = aligned(x)
    return spark.createDataFrame([(r["key_id"], r["key"], c) for r, c in zip(rows, x.tolist(), strict=True)], "key_id long, key array<string>, coords array<double>"), trace


def _pulled(x: np.ndarray, y: np.ndarray, want: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Where pairs of x and y, which should be ``want`` apart, pull both sides, and the sum of squared misses."""
    sx, sy = np.einsum("ij,ij->i", x, x), np.einsum("ij,ij->i", y, y)
    one_x, one_y = np.ones((len(x), 1)), np.ones((len(y), 1))
    left, right = np.hstack([-2 * x, sx[:, None], one_x]), np.hstack([y, one_y, sy[:, None]]).T
    x_one, y_one = np.hstack([x, one_x]), np.hstack([y, one_y])
    near = 1e-9 * (sx.max() + sy.max())  # here the product is too coarse
    by_x, by_y, miss = np.zeros_like(x_one), np.zeros_like(y_one), 0.0
    room, other = np.empty(ROWS_AT_ONCE * COLUMNS_AT_ONCE), np.empty(ROWS_AT_ONCE * COLUMNS_AT_ONCE)
    for a in range(0, len(x), ROWS_AT_ONCE):
        for b in range(0, len(y), COLUMNS_AT_ONCE):
            rows, columns = slice(a, a + ROWS_AT_ONCE), slice(b, b + COLUMNS_AT_ONCE)
            aim = want[rows, columns].astype(float)
            d, gap = (z[: aim.size].reshape(aim.shape) for z in (room, other))
            np.matmul(left[rows], right[:, columns], out=d)
            if d.min() <= near:
                i, j = np.nonzero(d <= near)
                d[i, j] = ((x[a + i] - y[b + j]) ** 2).sum(axis=1)
            np.sqrt(d, out=d)
            np.subtract(d, aim, out=gap)
            miss += float(np.vdot(gap, gap))
            if not d.min() > 0:
                d[d == 0] = np.inf  # points at one place don't pull
            np.divide(aim, d, out=d)
            by_x[rows] += d @ y_one[columns]
            by_y[columns] += d.T @ x_one[rows]
    return by_x[:, -1:] * x - by_x[:, :-1], by_y[:, -1:] * y - by_y[:, :-1], miss
