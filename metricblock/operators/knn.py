"""k-nearest-neighbour joins.

``points`` and ``queries`` have ``id`` and ``coords``.  Results are ``(q_id, n_id, rank, dist)``,
ranks from 1, ties to the smaller id; with fewer than k points all are returned.

Strategies: "scan" compares all pairs (the baseline); "broadcast" and "rtree" ship one tree, if
it is small enough; "partitioned" splits space into cells: a query searches its home cell, which
bounds the radius, and then only cells whose box meets that ball, so the result is exact;
``probes`` limits those cells for a faster, approximate answer.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from metricblock.functions.edit_kernel import EditTargets
from metricblock.operators.clusters import stored
from metricblock.operators.trees import KDTree, PartitionTree, Ranks, RTree
from metricblock.operators.vectors import nearest

#: A tree over this many bytes isn't sent to executors.
BROADCAST_BYTES = 256 << 20
CELL_POINTS = 200_000
SAMPLE, SAMPLE_A_CELL = 20_000, 32
RESULT = "q_id long, n_id long, rank int, dist double"


def tree_bytes(points: int, dimension: int) -> int:
    return points * (8 * dimension + 16)


def _matrix(column: pa.Array | pa.ChunkedArray, rows: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(rows, -1)


def collected(points: DataFrame, limit_bytes: int = BROADCAST_BYTES) -> tuple[np.ndarray, np.ndarray]:
    """All points on the driver; refused where they are over the limit."""
    dimension = points.select(F.max(F.size("coords"))).first()[0] or 1
    most = limit_bytes // tree_bytes(1, dimension)
    got = points.select(F.col("id").cast("long").alias("id"), "coords").limit(most + 1).toArrow()
    if got.num_rows > most:
        raise ValueError(f"more than {most} points: use the partitioned strategy")
    return _matrix(got["coords"], got.num_rows) if got.num_rows else np.zeros((0, dimension)), got["id"].to_numpy()


def _rows(found: list[tuple[int, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    sizes = [len(ids) for _, ids, _ in found]
    q = np.repeat(np.array([q for q, _, _ in found], dtype=np.int64), sizes)
    rank = np.concatenate([np.arange(1, n + 1) for n in sizes]) if sizes else np.zeros(0)
    ids = np.concatenate([i for _, i, _ in found]) if sizes else np.zeros(0)
    dist = np.concatenate([d for _, _, d in found]) if sizes else np.zeros(0)
    return pa.RecordBatch.from_arrays([pa.array(q), pa.array(ids.astype(np.int64)), pa.array(rank.astype(np.int32)), pa.array(dist.astype(float))], ["q_id", "n_id", "rank", "dist"])


def shared(df: DataFrame, tree):
    """The tree as a broadcast: an executor fetches it once, whatever its number of tasks."""
    return df.sparkSession.sparkContext.broadcast(tree)


def tree_search(queries: DataFrame, tree, k: int, include_self: bool = True) -> DataFrame:
    """Queries against one shipped tree: a narrow pass, no exchange."""

    shipped = shared(queries, tree)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = shipped.value
        most = max(1, min(4096, (1 << 20) // max(1, min(k, len(tree.ids)))))  # rows out at once
        for whole in batches:
            for a in range(0, whole.num_rows, most):
                b = whole.slice(a, most)
                ids = b.column(0).to_numpy()
                found = tree.knn_many(_matrix(b.column(1), b.num_rows), k, None if include_self else ids)
                yield _rows([(i, *f) for i, f in zip(ids.tolist(), found, strict=True)])

    return queries.select(F.col("id").cast("long"), "coords").mapInArrow(run, RESULT)


def knn_scan(queries: DataFrame, points: DataFrame, k: int, include_self: bool = True) -> DataFrame:
    """Every query with every point, by blocks: the sequential scan, kept as the baseline.  Only each block's best leave a task."""
    near = nearest(queries, points, k, include_self)
    rank = F.row_number().over(Window.partitionBy("q_id").orderBy("dist", "n_id"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k).select("q_id", "n_id", "rank", "dist")


def search_full(queries: DataFrame, points: DataFrame, theta: float, include_self: bool = True, limit_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """``(q_id, n_id, rank, dist, delta)``: of blocks as large as the database, the neighbours whose keys are at most ``theta`` apart.

    Both sides have ``id, coords, key``.  A block is every point there is, so the threshold is
    applied where the block is searched: rows that fail it never leave the task.  Ranks and
    distances are those of the whole block.
    """
    at, ids = collected(points, limit_bytes)
    keyed = points.select(F.col("id").cast("long").alias("id"), "key").toArrow()
    order, by_id = np.argsort(ids), np.argsort(keyed["id"].to_numpy())
    if not np.array_equal(keyed["id"].to_numpy()[by_id], ids[order]):
        raise RuntimeError("points changed between two reads")
    tree = KDTree.build(at, ids)
    where = by_id[np.searchsorted(ids[order], tree.ids)]  # keys in the order of the tree's points
    shipped = shared(queries, (tree, EditTargets(keyed["key"].take(pa.array(where)).to_pylist())))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree, targets = shipped.value
        ranks = Ranks(tree)
        for whole in batches:
            for a in range(0, whole.num_rows, 1024):
                b = whole.slice(a, 1024)
                asked, place = b.column(0).to_numpy(), _matrix(b.column(1), b.num_rows)
                i, j, delta = targets.close(b.column(2).to_pylist(), theta)
                if not include_self:
                    other = tree.ids[j] != asked[i]
                    i, j, delta = i[other], j[other], delta[other]
                order = np.argsort(i, kind="stable")
                i, j, delta = i[order], j[order], delta[order]
                rank, dist = np.zeros(len(i), dtype=np.int32), np.zeros(len(i))
                for q, first in zip(*np.unique(i, return_index=True), strict=True):
                    mine = slice(first, first + int(np.searchsorted(i[first:], q, side="right")))
                    rank[mine], dist[mine] = ranks.of(place[q], j[mine], None if include_self else int(asked[q]))
                yield pa.RecordBatch.from_arrays([pa.array(asked[i]), pa.array(tree.ids[j]), pa.array(rank), pa.array(dist), pa.array(delta.astype(np.int32))], ["q_id", "n_id", "rank", "dist", "delta"])

    return queries.select(F.col("id").cast("long"), F.col("coords").cast("array<double>"), "key").mapInArrow(run, f"{RESULT}, delta int")


def _with_cells(df: DataFrame, tree: PartitionTree, more: str = "") -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.append_column("cell", pa.array(tree.assign(_matrix(b.column("coords"), b.num_rows))))

    return df.select(F.col("id").cast("long").alias("id"), F.col("coords").cast("array<double>").alias("coords")).mapInArrow(run, "id long, coords array<double>, cell int")


def knn_partitioned(queries: DataFrame, points: DataFrame, k: int, include_self: bool = True, cells: int | None = None, probes: int | None = None) -> DataFrame:
    """Two rounds over cells.  Only boxes (one row a cell) reach the driver."""
    spark = points.sparkSession
    n = points.count()
    cells = cells or max(1, -(-n // CELL_POINTS))
    wanted = max(SAMPLE, SAMPLE_A_CELL * cells)  # a cell's split needs rows of its own
    share = min(1.0, 1.2 * wanted / max(n, 1))
    sample = points.select("coords").sample(share, seed=7).limit(wanted).toArrow() if share < 1 else points.select("coords").toArrow()
    tree = PartitionTree.fit(_matrix(sample["coords"], sample.num_rows) if sample.num_rows else np.zeros((0, 1)), cells)
    placed = stored(_with_cells(points, tree))
    corner = placed.select("cell", F.posexplode("coords").alias("dim", "v")).groupBy("cell", "dim").agg(F.min("v").alias("low"), F.max("v").alias("high"), F.count("*").alias("n"))
    boxes = sorted(corner.collect(), key=lambda r: (r["cell"], r["dim"]))
    names = sorted({r["cell"] for r in boxes})
    low, high, count = (np.array([r[c] for r in boxes], dtype=float).reshape(len(names), -1) for c in ("low", "high", "n"))
    count = count[:, 0] if names else count
    if not names:
        return spark.createDataFrame([], RESULT)

    def searched(own: pa.Table, asked: pa.Table) -> list[tuple[int, np.ndarray, np.ndarray]]:
        ids, at = asked["id"].to_pylist(), _matrix(asked["coords"], asked.num_rows)
        kd = KDTree.build(_matrix(own["coords"], own.num_rows), own["id"].to_numpy()) if own.num_rows else None
        return [(i, *(kd.knn(q, k, None if include_self else i) if kd else (np.zeros(0, dtype=np.int64), np.zeros(0)))) for i, q in zip(ids, at, strict=True)]

    first_schema = pa.schema([("q_id", pa.int64()), ("n_id", pa.int64()), ("dist", pa.float64()), ("visit", pa.int32()), ("coords", pa.list_(pa.float64()))])

    def home(own: pa.Table, asked: pa.Table) -> pa.Table:
        """Neighbours in the home cell (``visit`` null), and the other cells to visit (``n_id`` null)."""
        rows: list[tuple] = []
        if asked.num_rows:
            here = asked["cell"][0].as_py()
            at = _matrix(asked["coords"], asked.num_rows)
            for (i, ids, dist), q in zip(searched(own, asked), at, strict=True):
                rows += [(i, n, d, None, None) for n, d in zip(ids.tolist(), dist.tolist(), strict=True)]
                gap = np.maximum(np.maximum(low - q, q - high), 0)
                near = np.sqrt((gap**2).sum(axis=1))
                reach = dist[-1] if len(dist) == k else np.inf
                if not np.isfinite(reach):  # the k-th nearest is no farther than the far corners of enough cells
                    far = np.sqrt((np.maximum(np.abs(low - q), np.abs(high - q)) ** 2).sum(axis=1))
                    order = np.argsort(far)
                    enough = np.flatnonzero(np.cumsum(count[order]) >= k + (not include_self))
                    reach = far[order[enough[0]]] if len(enough) else np.inf
                visit = [j for j in np.argsort(near, kind="stable") if near[j] <= reach * (1 + 1e-12) and names[j] != here]
                rows += [(i, None, None, names[j], q.tolist()) for j in (visit if probes is None else visit[: max(0, probes - 1)])]
        columns = zip(*rows, strict=True) if rows else [()] * 5
        return pa.table([pa.array(v, t) for v, t in zip(columns, first_schema.types, strict=True)], schema=first_schema)

    second_schema = pa.schema([("q_id", pa.int64()), ("n_id", pa.int64()), ("dist", pa.float64())])

    def visited(own: pa.Table, asked: pa.Table) -> pa.Table:
        rows = _rows(searched(own, asked)) if asked.num_rows else _rows([])
        return pa.table([rows.column("q_id"), rows.column("n_id"), rows.column("dist")], schema=second_schema)

    asked = _with_cells(queries, tree)
    first = stored(placed.groupBy("cell").cogroup(asked.groupBy("cell")).applyInArrow(home, "q_id long, n_id long, dist double, visit int, coords array<double>"))
    go = first.where("visit is not null").select(F.col("q_id").alias("id"), "coords", F.col("visit").alias("cell"))
    second = placed.groupBy("cell").cogroup(go.groupBy("cell")).applyInArrow(visited, "q_id long, n_id long, dist double")
    both = first.where("visit is null").select("q_id", "n_id", "dist").unionByName(second)
    rank = F.row_number().over(Window.partitionBy("q_id").orderBy("dist", "n_id"))
    return both.withColumn("rank", rank).where(F.col("rank") <= k).select("q_id", "n_id", F.col("rank").cast("int").alias("rank"), "dist")


def knn_join(queries: DataFrame, points: DataFrame, k: int, strategy: str = "auto", include_self: bool = True, probes: int | None = None, cells: int | None = None) -> DataFrame:
    if strategy == "auto":
        dimension = points.select(F.max(F.size("coords"))).first()[0] or 1
        strategy = "broadcast" if tree_bytes(points.count(), dimension) <= BROADCAST_BYTES else "partitioned"
    if strategy == "scan":
        return knn_scan(queries, points, k, include_self)
    if strategy == "partitioned":
        return knn_partitioned(queries, points, k, include_self, cells, probes)
    at, ids = collected(points)
    return tree_search(queries, KDTree.build(at, ids) if strategy == "broadcast" else RTree.pack(at, ids), k, include_self)


def self_knn(points: DataFrame, k: int, include_self: bool = False, strategy: str = "auto", **how) -> DataFrame:
    """Every point asks for its own block."""
    return knn_join(points, points, k, strategy, include_self, **how)


def within_join(queries: DataFrame, points: DataFrame, radius: float) -> DataFrame:
    """``(q_id, n_id, dist)`` of all points at most ``radius`` away, by one shipped tree."""
    shipped = shared(queries, KDTree.build(*collected(points)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = shipped.value
        for whole in batches:
            for a in range(0, whole.num_rows, 256):
                b = whole.slice(a, 256)
                found = tree.within_many(_matrix(b.column(1), b.num_rows), radius)
                rows = _rows([(i, *f) for i, f in zip(b.column(0).to_pylist(), found, strict=True)])
                yield pa.RecordBatch.from_arrays([rows.column("q_id"), rows.column("n_id"), rows.column("dist")], ["q_id", "n_id", "dist"])

    return queries.select(F.col("id").cast("long"), "coords").mapInArrow(run, "q_id long, n_id long, dist double")
