"""Placing a new value by its dissimilarities to anchors alone.

``place_batch`` minimises the sum over anchors of (distance - dissimilarity) squared for many
values at once.  Results depend on the value and the anchors only, never on batch or partition.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from metricblock.functions.edit_kernel import key_matrix

SOLVERS = ("sgd", "gd", "majorize", "gauss_newton")
#: Anchors of the un-scaled form, which measures every value against all embedded ones.
ALL_ANCHORS = 5_000
#: A point this near to an anchor has no direction from it.
TINY = 1e-7


@dataclass(frozen=True)
class PlacementOptions:
    solver: str = "gauss_newton"
    start: str = "linear"
    max_iter: int = 60
    tol: float = 1e-5
    rate: float = 1.0
    batch: int = 32
    epochs: int = 12
    seed: int = 42


def _distances(y: np.ndarray, anchors: np.ndarray) -> np.ndarray:
    """Values x anchors, by one matrix product instead of an array of all gaps."""
    squares = (y**2).sum(axis=1)[:, None] + (anchors**2).sum(axis=1) - 2 * (y @ anchors.T)
    return np.sqrt(np.maximum(squares, 0))


def losses(y: np.ndarray, anchors: np.ndarray, delta: np.ndarray) -> np.ndarray:
    return ((_distances(y, anchors) - delta) ** 2).sum(axis=1)


def starts(anchors: np.ndarray, delta: np.ndarray, how: str, seeds: np.ndarray) -> np.ndarray:
    centre = anchors.mean(axis=0)
    if how == "centroid":
        return np.tile(centre, (len(delta), 1))
    if how == "nearest_landmark":
        jitter = np.stack([np.random.default_rng(abs(int(s))).standard_normal(anchors.shape[1]) for s in seeds]) if len(seeds) else np.zeros((0, anchors.shape[1]))
        return anchors[delta.argmin(axis=1)] + 1e-3 * jitter
    if how == "linear":  # triangulation: exact if the dissimilarities are Euclidean
        x = anchors - centre
        inner = ((x**2).sum(axis=1) - delta**2) / 2
        inner -= inner.mean(axis=1, keepdims=True)
        return centre + inner @ np.linalg.pinv(x).T
    raise ValueError(how)


def place_batch(anchors: np.ndarray, delta: np.ndarray, seeds: np.ndarray, options: PlacementOptions) -> tuple[np.ndarray, np.ndarray]:
    """Coordinates and loss for each row of ``delta`` (values x anchors); the best point met is kept."""
    delta = delta.astype(float)
    y = starts(anchors, delta, options.start, seeds)
    best, loss = y.copy(), losses(y, anchors, delta)

    def keep(y: np.ndarray, at: np.ndarray) -> np.ndarray:
        now = losses(y, anchors, delta[at])
        better = now < loss[at]
        best[at[better]], gain = y[better], loss[at] - now
        loss[at] = np.minimum(loss[at], now)
        return gain

    if options.solver == "sgd":
        n = len(anchors)
        order = np.stack([np.random.default_rng(abs(int(s))).permutation(n) for s in seeds]) if len(seeds) else np.zeros((0, n), dtype=int)
        every = np.arange(len(y))
        for epoch in range(options.epochs):
            rate = options.rate / (1 + 0.1 * epoch)
            for a in range(0, n, options.batch):
                some = order[:, a : a + options.batch]
                gap = y[:, None, :] - anchors[some]
                d = np.sqrt(np.einsum("ijk,ijk->ij", gap, gap))
                pull = 1 - np.divide(np.take_along_axis(delta, some, 1), d, out=np.ones_like(d), where=d > 0)
                y = y - rate * np.einsum("ij,ijk->ik", pull, gap) / some.shape[1]
            keep(y, every)
        return best, loss
    if options.solver not in SOLVERS:
        raise ValueError(options.solver)
    k = anchors.shape[1]
    outer = (anchors[:, :, None] * anchors[:, None, :]).reshape(len(anchors), k * k)
    active = np.arange(len(y))
    step = np.full(len(y), 1.0)
    for _ in range(options.max_iter):
        if not len(active):
            break
        at, want = y[active], delta[active]
        d = _distances(at, anchors)
        pull = 1 - np.divide(want, d, out=np.ones_like(d), where=d > TINY)
        slope = (pull.sum(axis=1)[:, None] * at - pull @ anchors) / len(anchors)
        if options.solver == "majorize":
            new = at - slope
        elif options.solver == "gd":
            new = at - step[active][:, None] * slope
        else:
            near = np.divide(1.0, d**2, out=np.zeros_like(d), where=d > TINY)  # sum of outer products of unit gaps
            pulled = near @ anchors
            cross = at[:, :, None] * pulled[:, None, :]
            normal = near.sum(axis=1)[:, None, None] * (at[:, :, None] * at[:, None, :]) - cross - cross.transpose(0, 2, 1) + (near @ outer).reshape(-1, k, k)
            normal += (1e-3 * len(anchors)) * np.eye(k)
            new = at - np.linalg.solve(normal, slope[..., None] * len(anchors))[..., 0]
        gain = keep(new, active)
        y[active] = np.where((gain > 0)[:, None], new, best[active])
        step[active] = np.where(gain > 0, step[active] * 1.1, step[active] / 2)
        stay = gain > options.tol * np.maximum(loss[active], 1e-12)
        if options.solver == "gd":
            stay |= (gain <= 0) & (step[active] > 1e-4)
        active = active[stay]
    return best, loss


def place(keys: DataFrame, landmarks: list[list[str]], anchors: np.ndarray, options: PlacementOptions, id_col: str = "key_id", combine: str = "sum", weights: tuple[float, ...] | None = None, more: tuple[str, ...] = ()) -> DataFrame:
    """``(id, *more, coords, loss)`` of ``keys(id, key)``: measured against the landmarks and placed in one narrow pass.

    The dissimilarities exist for one slice of rows at a time and are never a column.
    """
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in keys.select(id_col, *more).schema)
    rows = max(256, min(4096, (1 << 21) // max(1, len(landmarks))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, whole.num_rows, rows):
                b = whole.slice(a, rows)
                delta = key_matrix(b.column("key").to_pylist(), landmarks, combine, weights)
                y, loss = place_batch(anchors, delta, b.column("_seed").to_numpy(), options)
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in (id_col, *more)), pa.array(y.tolist(), pa.list_(pa.float64())), pa.array(loss)], [id_col, *more, "coords", "loss"])

    seeded = keys.select(id_col, *dict.fromkeys([*more, "key"]), F.xxhash64("key", F.lit(options.seed)).alias("_seed"))
    return seeded.mapInArrow(run, f"{fields}, coords array<double>, loss double")


# The objective and single steps as column expressions; ``anchors`` is a column array<array<double>>.


def placement_loss(y: Column, anchors: Column, delta: Column) -> Column:
    from metricblock.functions.distance import minkowski

    return F.aggregate(F.zip_with(anchors, delta, lambda x, w: F.pow(minkowski(x, y, 2) - w, F.lit(2.0))), F.lit(0.0), lambda s, v: s + v)


def placement_step(y: Column, anchors: Column, delta: Column, kind: str = "majorize", rate: float = 1.0) -> Column:
    """The point after one step: "majorize" moves to the mean of where the anchors want it; "gradient" along the slope of the loss; "sgd" along the mean slope of the batch of anchors given."""
    from metricblock.functions.distance import minkowski

    n = F.size(anchors).cast("double")

    def pull(x: Column, w: Column) -> Column:
        d = minkowski(x, y, 2)
        return F.when(d > 0, 1 - w / d).otherwise(0.0)

    zero = F.transform(y, lambda _: F.lit(0.0))
    pulls = F.zip_with(anchors, delta, lambda x, w: F.zip_with(y, x, lambda a, b: (a - b) * pull(x, w)))
    total = F.aggregate(pulls, zero, lambda s, v: F.zip_with(s, v, lambda a, b: a + b))
    scale = {"majorize": 1 / n, "sgd": F.lit(rate) / n, "gradient": F.lit(2.0 * rate)}[kind]
    return F.zip_with(y, total, lambda a, b: a - b * scale)
