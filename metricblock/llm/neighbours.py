"""Nearest neighbours by low-dimensional stable projections in kd-trees.

A vector's projections on a few Gaussian directions keep distances in this sense: the squared
projected distance over the squared true one follows a chi-square law with as many degrees of
freedom as directions.  So the candidates are met in the order of projected distance, out of a
kd-tree over the projections, and verified on the original vectors, until the next projected
distance is so large that a closer vector would have come before it with probability
``SURE``.  Then each of the true neighbours is missing with probability at most 1 - ``SURE``.

Cells are the upper levels of one kd-tree over all projections; its splits come from a bounded
sample, its boxes and sizes from all rows.  A query searches its own cell first.  What it finds
there bounds the distance of its neighbours, and by the same test the projected distance: it
goes on to the cells alone whose boxes lie within that.  Large cells are dealt in parts, and
queries in blocks, so no task grows with the table.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from metricblock.llm.common import stored, table
from metricblock.llm.vectors import matrix, usable

DIRECTIONS = 16
SURE = 0.99
LEAF = 48
#: Rows of a part of a cell at most (about), rows for which a cell of its own is worth while, and queries of a block.
CELL_ROWS, LEAST_ROWS, QUERY_ROWS = 250_000, 2_048, 20_000
#: Cells at most, and rows of the sample that each is split by.
CELLS, SAMPLE = 4_096, 64


def chi_square_point(sure: float, freedom: int) -> float:
    """Where the chi-square law of an even number of degrees of freedom reaches ``sure``."""
    if freedom % 2:
        raise ValueError("an even number of directions is needed")

    def beyond(x: float) -> float:
        return math.exp(-x / 2) * sum((x / 2) ** i / math.factorial(i) for i in range(freedom // 2))

    low, high = 0.0, 1.0
    while beyond(high) > 1 - sure:
        high *= 2
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (mid, high) if beyond(mid) > 1 - sure else (low, mid)
    return high


class ProjectionTree:
    """A kd-tree whose leaves are runs of a permutation, each with its bounding box."""

    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        self.order = np.arange(len(points))
        self.starts: list[int] = []
        stack, ends = [(0, len(points))], []
        while stack:
            a, b = stack.pop()
            if b - a <= leaf:
                self.starts.append(a)
                ends.append(b)
                continue
            own = self.order[a:b]
            at = points[own]
            axis = int(np.argmax(at.max(axis=0) - at.min(axis=0)))
            mid = (b - a) // 2
            self.order[a:b] = own[np.argpartition(at[:, axis], mid)]
            stack += [(a, a + mid), (a + mid, b)]
        place = np.argsort(self.starts, kind="stable")
        self.starts, self.ends = np.array(self.starts)[place], np.array(ends)[place]
        ordered = points[self.order]
        self.low = np.minimum.reduceat(ordered, self.starts)
        self.high = np.maximum.reduceat(ordered, self.starts)

    def leaves_by_distance(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Leaves in order of their boxes' squared distance from ``q``, and those distances."""
        gap = np.maximum(np.maximum(self.low - q, q - self.high), 0)
        far = np.einsum("ij,ij->i", gap, gap)
        order = np.argsort(far, kind="stable")
        return order, far[order]


def nearest(x: np.ndarray, ids: np.ndarray, queries: np.ndarray, query_ids: np.ndarray, k: int, base: np.ndarray, sure: float = SURE, within: np.ndarray | None = None, at_once: int = 32) -> Iterator[tuple[int, np.ndarray, np.ndarray, int]]:
    """For each query: its id, ids and squared distances of its ``k`` nearest rows of ``x`` found, and how many were verified.

    ``base`` has the directions as columns.  ``within``: squared distances beyond which a query wants nothing.
    """
    tree = ProjectionTree(x @ base)
    x, ids = x[tree.order], ids[tree.order]
    points = x @ base
    enough = chi_square_point(sure, base.shape[1])
    for n, (q, own) in enumerate(zip(queries, query_ids, strict=True)):
        at_q = q @ base
        leaves, far = tree.leaves_by_distance(at_q)
        best_id, best, verified = np.zeros(0, dtype=ids.dtype), np.zeros(0), 0
        least = math.inf if within is None else float(within[n])
        pool, near, at, done = np.zeros(0, dtype=np.int64), np.zeros(0), 0, False
        while not done:
            reach = far[at] if at < len(far) else math.inf  # all that lies nearer than this is in the pool
            ready = int(np.searchsorted(near, reach, side="left")) if reach < math.inf else len(near)
            for a in range(0, ready, at_once):  # in order of projected distance, the test before each few
                limit = enough * min(least, best[-1] if len(best) == k else math.inf)
                if near[a] > limit:
                    done = True
                    break
                rows = pool[a : min(ready, a + at_once, int(np.searchsorted(near, limit, side="right")))]
                gap = x[rows] - q
                verified += len(rows)
                best_id, best = np.concatenate([best_id, ids[rows]]), np.concatenate([best, np.einsum("ij,ij->i", gap, gap)])
                keep = np.lexsort((best_id, best))[:k]
                best_id, best = best_id[keep], best[keep]
            pool, near = pool[ready:], near[ready:]
            if done or at >= len(far) or far[at] > enough * min(least, best[-1] if len(best) == k else math.inf):
                break
            opened = leaves[at : at + 8]
            at += 8
            rows = np.concatenate([np.arange(tree.starts[i], tree.ends[i]) for i in opened])
            rows = rows[ids[rows] != own]
            gap = points[rows] - at_q
            pool, near = np.concatenate([pool, rows]), np.concatenate([near, np.einsum("ij,ij->i", gap, gap)])
            order = np.argsort(near, kind="stable")
            pool, near = pool[order], near[order]
        yield int(own), best_id, best, verified


class Cells:
    """The upper levels of a kd-tree: ``depth`` splits from the root to every cell."""

    def __init__(self, sample: np.ndarray, depth: int):
        self.depth = depth
        self.axis, self.value = np.zeros(max(1, 2**depth - 1), dtype=np.int64), np.zeros(max(1, 2**depth - 1))
        own = [sample]
        for node in range(2**depth - 1):
            part = own[node]
            if len(part):
                self.axis[node] = np.argmax(part.max(axis=0) - part.min(axis=0))
                self.value[node] = np.median(part[:, self.axis[node]])
            left = part[:, self.axis[node]] <= self.value[node]
            own += [part[left], part[~left]]

    def of(self, points: np.ndarray) -> np.ndarray:
        node = np.zeros(len(points), dtype=np.int64)
        for _ in range(self.depth):
            node = 2 * node + 1 + (points[np.arange(len(points)), self.axis[node]] > self.value[node])
        return node - (2**self.depth - 1)


def directions(width: int, seed: int, number: int) -> np.ndarray:
    return np.random.default_rng([seed, width]).standard_normal((width, number))


def _by_width(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.RecordBatch, np.ndarray]]:
    for b in batches:
        widths = b.column("width").to_numpy()
        for width in np.unique(widths).tolist():
            part = b.filter(pa.array(widths == width))
            yield width, part, matrix(part.column("vector"), width)


def _projected(seed: int, number: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for width, part, x in _by_width(batches):
            yield pa.RecordBatch.from_arrays([part.column("width"), pa.array((x @ directions(width, seed, number)).tolist(), pa.list_(pa.float64()))], ["width", "point"])

    return run


def _celled(cells: dict[int, Cells], seed: int, number: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for width, part, x in _by_width(batches):
            points = x @ directions(width, seed, number)
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array(cells[width].of(points) if width in cells else np.zeros(len(x), dtype=np.int64)), pa.array(points.tolist(), pa.list_(pa.float64()))], [*part.schema.names, "cell", "point"])

    return run


def _visits(boxes: dict[int, tuple], enough: float):
    """For each query and the distance it knows already, the parts of cells (but the one searched) that its ball meets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for width, part, x in _by_width(batches):
            if width not in boxes:
                continue
            cell, piece, low, high = boxes[width]
            points = matrix(part.column("point"), low.shape[1])
            reach = part.column("within").to_numpy(zero_copy_only=False) * enough
            home, own = part.column("cell").to_numpy(), part.column("part").to_numpy()
            for i in range(len(points)):
                gap = np.maximum(np.maximum(low - points[i], points[i] - high), 0)
                go = np.flatnonzero((np.einsum("ij,ij->i", gap, gap) <= reach[i]) & ((cell != home[i]) | (piece != own[i])))
                at = pa.array(np.full(len(go), i))
                yield pa.RecordBatch.from_arrays([*(part.column(c).take(at) for c in ("vec_id", "vector", "width", "within")), pa.array(cell[go]), pa.array(piece[go])], ["vec_id", "vector", "width", "within", "cell", "part"])

    return run


def _search(k: int, seed: int, number: int, sure: float):
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("square", pa.float64()), ("verified", pa.int64())])

    def run(rows: pa.Table, queries: pa.Table) -> pa.Table:
        if not rows.num_rows or not queries.num_rows:
            return schema.empty_table()
        width = rows["width"][0].as_py()
        found = list(nearest(matrix(rows["vector"], width), rows["vec_id"].to_numpy(), matrix(queries["vector"], width), queries["vec_id"].to_numpy(), k, directions(width, seed, number), sure, queries["within"].to_numpy()))
        n = [len(i) for _, i, _, _ in found]
        return pa.table([pa.array(np.repeat([f[0] for f in found], n), pa.int64()), pa.array(np.concatenate([f[1] for f in found])), pa.array(np.concatenate([f[2] for f in found])), pa.array(np.repeat([f[3] for f in found], n), pa.int64())], schema=schema)

    return run


def search(vectors: DataFrame, queries: DataFrame, k: int = 10, seed: int = 2, sure: float = SURE, number: int = DIRECTIONS) -> DataFrame:
    """``(query_id, rank, vec_id, score)``: the ``k`` nearest rows found for each query.

    Both tables have ``vec_id`` and ``embedding``; a row is no candidate for the query of its
    own id.  Ties go to the smaller vec_id; with fewer candidates all are returned.  Vectors
    that are null, zero or hold null or non-finite components, and rows without an id, take no
    part; vectors of another width are no candidates.  A query id that is repeated is searched
    once.  Other columns are ignored; empty tables give no rows.
    """
    best = found_by_cells(vectors, queries, k, seed, sure, number)
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("square", "vec_id"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", F.sqrt("square").alias("score"))


def found_by_cells(vectors: DataFrame, queries: DataFrame, k: int = 10, seed: int = 2, sure: float = SURE, number: int = DIRECTIONS) -> DataFrame:
    """``(query_id, vec_id, square, verified)``: what each part of a cell found for a query, and how many rows it verified for that."""

    def sound(t: DataFrame) -> DataFrame:
        t = t.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("vector"))
        return t.where(F.col("vec_id").isNotNull() & usable(F.col("vector"))).withColumn("width", F.size("vector"))

    rows, asked = sound(vectors), sound(queries).dropDuplicates(["vec_id"])
    spark = vectors.sparkSession
    cells: dict[int, Cells] = {}
    for r in rows.groupBy("width").count().collect():
        wanted = max(math.ceil(r["count"] / CELL_ROWS), min(math.ceil(r["count"] / LEAST_ROWS), 2 * spark.sparkContext.defaultParallelism))
        depth = min(CELLS, wanted).bit_length() - 1
        some = rows.where((F.col("width") == r["width"]) & (F.pmod(F.xxhash64(F.lit(seed), "vec_id"), F.lit(max(1, r["count"] // (SAMPLE * 2**depth)))) == 0))
        sample = some.mapInArrow(_projected(seed, number), "width int, point array<double>").select("point").limit(4 * SAMPLE * 2**depth).toArrow() if depth else None
        cells[r["width"]] = Cells(matrix(sample["point"], number) if depth else np.zeros((0, number)), depth)
    kind = dict(rows.dtypes)["vector"]
    schema = f"vec_id long, vector {kind}, width int, cell long, point array<double>"
    placed = stored(rows.mapInArrow(_celled(cells, seed, number), schema))
    edges = [f(F.col("point")[i]).alias(f"{n}{i}") for i in range(number) for n, f in (("low", F.min), ("high", F.max))]
    report = placed.groupBy("width", "cell").agg(F.count("*").alias("n"), *edges).collect()
    parts = {(r["width"], r["cell"]): math.ceil(r["n"] / CELL_ROWS) for r in report}
    boxes = {}
    for width in cells:
        own = [r for r in report if r["width"] == width]
        times = [parts[width, r["cell"]] for r in own]
        at = lambda name: np.repeat(np.array([[r[f"{name}{i}"] for i in range(number)] for r in own]), times, axis=0)  # noqa: B023, E731
        boxes[width] = (np.repeat([r["cell"] for r in own], times), np.concatenate([np.arange(t) for t in times]), at("low"), at("high"))
    many = spark.createDataFrame([(w, c, n) for (w, c), n in parts.items()], "width int, cell long, parts long")
    part = F.pmod(F.xxhash64("vec_id"), F.coalesce("parts", F.lit(1)))
    dealt = placed.join(F.broadcast(many), ["width", "cell"]).select("vec_id", "vector", "width", "cell", part.alias("part"))

    def searched(visits: DataFrame) -> DataFrame:
        group = ["width", "cell", "part"]
        asks = visits.groupBy(*group).agg(F.ceil(F.count("*") / QUERY_ROWS).alias("blocks"))
        inside = dealt.join(asks, group).withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
        again = asks.select(*[F.col(c).alias(f"of_{c}") for c in group], F.col("blocks").alias("of"))
        same = [F.col(c) == F.col(f"of_{c}") for c in group]
        outside = visits.join(again, same).select(*visits.columns, F.pmod(F.xxhash64("vec_id"), F.col("of")).alias("block"))
        return inside.groupBy(*group, "block").cogroup(outside.groupBy(*group, "block")).applyInArrow(_search(k, seed, number, sure), "query_id long, vec_id long, square double, verified long")

    asked = asked.mapInArrow(_celled(cells, seed, number), schema).join(F.broadcast(many), ["width", "cell"], "left")
    asked = stored(asked.select("vec_id", "vector", "width", "cell", "point", part.alias("part"), F.lit(float("inf")).alias("within")))
    home = stored(searched(asked.drop("point")))
    known = home.groupBy("query_id").agg(F.count("*").alias("found"), F.max("square").alias("square")).where(F.col("found") >= k)
    bounded = asked.drop("within").join(known.select(F.col("query_id").alias("vec_id"), "square"), "vec_id", "left").withColumn("within", F.coalesce("square", F.lit(float("inf"))))
    visits = stored(bounded.mapInArrow(_visits(boxes, chi_square_point(sure, number)), f"vec_id long, vector {kind}, width int, within double, cell long, part long"))
    return home.unionByName(searched(visits))


def op2_projection_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return search(vectors, vectors.where("vec_id % 100 = 0"))
