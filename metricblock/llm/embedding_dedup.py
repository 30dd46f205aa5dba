"""Near-duplicate vectors by sorted projection passes.

Each pass hashes every vector to the signs of random projections, put together to one number,
and sorts the vectors of a label by it, so that the order is lexicographic in the hashes.
Vectors at a small angle agree in a long prefix with some probability, and then lie close in
the order.  Each is compared with the next ``WINDOW`` ones.  Projections are of the vectors less
their label's mean, so a direction that all of a label share tells nothing and costs nothing.

What a pass adds is which vectors are connected: of the links in its windows a task gives a
spanning forest, so large groups of near copies cost a row a vector.  Passes go on in rounds
until a round connects nothing new.  Links lie inside components alone, so they are counted
there at the end, all of them, by products of blocks of vectors; no pair leaves a task.

Vectors travel through the passes in one byte a component, with a bound on what that changes;
a cosine that the bound leaves open is settled on the vectors themselves.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from metricblock.llm.common import drop, stored, table
from metricblock.llm.vectors import matrix, usable
from metricblock.operators.clusters import components

THRESHOLD = 0.93
WINDOW = 64
BITS = 48
ROWS_A_TASK = 40_000
#: Passes of a round, and vectors of a block in which links are counted.
ROUND, BLOCK = 6, 2_048
#: Rounds go on until one connects less than this share of the components that have been connected.
SETTLED = 1e-3


def _sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums of unit vectors by label and width, a row each."""
    for b in batches:
        if not b.num_rows:
            continue
        group = np.stack([b.column("label").to_numpy(), b.column("width").to_numpy()], axis=1)
        found, of = np.unique(group, axis=0, return_inverse=True)
        for g, (label, width) in enumerate(found.tolist()):
            own = np.flatnonzero(of.ravel() == g)
            x = matrix(b.column("vector").take(pa.array(own)), width)
            total = (x / np.linalg.norm(x, axis=1, keepdims=True)).sum(axis=0)
            yield pa.RecordBatch.from_arrays([pa.array([label] * width), pa.array([width] * width, pa.int32()), pa.array(range(width), pa.int32()), pa.array(total), pa.array([len(own)] * width)], ["label", "width", "axis", "total", "n"])


def label_means(unique: DataFrame) -> DataFrame:
    """``(label, width, mean)`` of the unit vectors; as many rows as labels."""
    parts = unique.select("label", "width", "vector").mapInArrow(_sums, "label long, width int, axis int, total double, n long")
    axes = parts.groupBy("label", "width", "axis").agg((F.sum("total") / F.sum("n")).alias("mean"))
    ordered = F.array_sort(F.collect_list(F.struct("axis", F.round("mean", 9).alias("mean"))))
    return axes.groupBy("label", "width").agg(F.transform(ordered, lambda x: x["mean"]).alias("mean"))


def small_vectors(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Unit vectors in one byte a component: the bytes, their scales, and the lengths of what is lost."""
    scale = np.maximum(np.abs(x).max(axis=1), 1e-30) / 127
    small = np.rint(x / scale[:, None]).astype(np.int8)
    return small, scale, np.linalg.norm(x - small * scale[:, None], axis=1)


def _hashed(first: int, passes: int, seed: int, bits: int):
    names = ["pass", "label", "width", "code", "id", "small", "scale", "lost"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = (1 << np.arange(bits - 1, -1, -1, dtype=np.int64)).astype(np.int64)
        planes: dict[tuple[int, int], np.ndarray] = {}
        for b in batches:
            widths = b.column("width").to_numpy()
            for width in np.unique(widths).tolist():
                part = b.filter(pa.array(widths == width))
                x = matrix(part.column("vector"), width)
                x /= np.linalg.norm(x, axis=1, keepdims=True)
                small, scale, lost = small_vectors(x)
                rows = pa.array([r.tobytes() for r in small], pa.binary())
                apart = x - matrix(part.column("mean"), width)
                for k in range(first, first + passes):
                    if (k, width) not in planes:
                        planes[k, width] = np.random.default_rng([seed, k, width]).standard_normal((width, bits))
                    code = ((apart @ planes[k, width]) > 0) @ weights
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), k, np.int32)), part.column("label"), part.column("width"), pa.array(code), part.column("id"), rows, pa.array(scale), pa.array(lost)], names)

    return run


def window_links(x: np.ndarray, lost: np.ndarray, threshold: float, window: int, block: int = 256) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions (i < j) at most ``window`` apart whose cosine may reach the threshold, and whether it surely does."""
    left, right, sure = [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=bool)]
    n = len(x)
    for a in range(0, n, block):
        rows, last = np.arange(a, min(n, a + block)), min(n, a + block + window)
        cosine = x[rows] @ x[a:last].T
        off = np.arange(a, last)[None, :] - rows[:, None]
        slack = (lost[rows][:, None] + lost[a:last][None, :]) * 1.01 + 1e-9  # small vectors are hardly longer than 1
        i, j = np.nonzero((cosine >= threshold - slack) & (off > 0) & (off <= window))
        left.append(a + i)
        right.append(a + j)
        sure.append(cosine[i, j] >= threshold + slack[i, j])
    return np.concatenate(left), np.concatenate(right), np.concatenate(sure)


def forest(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Which of the pairs join two trees, one after the other."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = x = parent.setdefault(up, up)
        return x

    keep = np.zeros(len(a), dtype=bool)
    for at, (u, v) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
        u, v = root(u), root(v)
        if u != v:
            parent[max(u, v)] = min(u, v)
            keep[at] = True
    return keep


def _linked(threshold: float, window: int):
    """Rows come in order; groups are held as they end, so a task needs no more memory than one batch and a window."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tail: list[pa.RecordBatch] = []
        for b in batches:
            held = pa.Table.from_batches([*tail, b]).combine_chunks()
            fresh = held.num_rows - b.num_rows
            group = np.stack([held[c].to_numpy().astype(np.int64) for c in ("pass", "label", "width")], axis=1)
            ids = held["id"].to_numpy()
            borders = np.flatnonzero(np.any(group[1:] != group[:-1], axis=1)) + 1
            for s, e in zip([0, *borders], [*borders, len(ids)], strict=True):
                if e <= max(s, fresh):
                    continue
                part = held.slice(s, e - s).combine_chunks()
                small = np.frombuffer(b"".join(part["small"].to_pylist()), dtype=np.int8).reshape(e - s, -1)
                x = small * part["scale"].to_numpy()[:, None]
                i, j, sure = window_links(x, part["lost"].to_numpy(), threshold, window)
                new = s + j >= fresh
                i, j, sure = ids[s + i[new]], ids[s + j[new]], sure[new]
                keep = np.ones(len(i), dtype=bool)
                keep[sure] = forest(i[sure], j[sure])
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(i, j)[keep]), pa.array(np.maximum(i, j)[keep]), pa.array(sure[keep])], ["a", "b", "sure"])
            tail = held.slice(max(0, held.num_rows - window)).combine_chunks().to_batches()

    return run


def _cosines(threshold: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            widths = b.column("width").to_numpy()
            for width in np.unique(widths).tolist():
                part = b.filter(pa.array(widths == width))
                x, y = matrix(part.column("x"), width), matrix(part.column("y"), width)
                cosine = (x * y).sum(axis=1) / np.sqrt((x * x).sum(axis=1) * (y * y).sum(axis=1))
                yield part.select(["a", "b"]).filter(pa.array(cosine >= threshold))

    return run


def _counts(threshold: float):
    """Rows (key, side, id, copies, width, vector) come sorted by key and side: links of a block with itself, or of one with another."""

    def block(rows: pa.Table) -> pa.RecordBatch:
        width = rows["width"][0].as_py()
        x = matrix(rows["vector"], width)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        side, copies, ids = rows["side"].to_numpy(), rows["copies"].to_numpy(), rows["id"].to_numpy()
        n = np.zeros(len(ids), dtype=np.int64)
        if side[0] == 2:  # one block alone
            hit = x @ x.T >= threshold
            np.fill_diagonal(hit, False)
            n = hit @ copies
        else:
            one, two = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
            hit = x[one] @ x[two].T >= threshold
            n[one], n[two] = hit @ copies[two], copies[one] @ hit
        return pa.RecordBatch.from_arrays([pa.array(ids), pa.array(n.astype(np.int64))], ["id", "others"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for b in batches:
            held = pa.Table.from_batches([b]) if held is None else pa.concat_tables([held, pa.Table.from_batches([b])])
            key = held["key"].to_numpy()
            borders = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1).tolist()]
            for s, e in zip(borders[:-1], borders[1:], strict=True):
                yield block(held.slice(s, e - s))
            held = held.slice(borders[-1])
        if held is not None and held.num_rows:
            yield block(held)

    return run


def _links(members: DataFrame, threshold: float) -> DataFrame:
    """``(id, others)``: for each of ``members(component, id, copies, width, vector)`` how many rows of others link with it.

    A component is cut into blocks of about ``BLOCK`` vectors; each pair of blocks is one product.
    """
    sizes = stored(members.groupBy("component").agg(F.ceil(F.count("*") / BLOCK).alias("blocks")))
    of = members.join(sizes, "component").withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")))
    each = of.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    key = F.struct("component", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"))
    side = F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1)
    rows = each.select(F.xxhash64(key).alias("key"), side.cast("int").alias("side"), "id", "copies", "width", "vector")
    return rows.repartition("key").sortWithinPartitions("key", "side", "id").mapInArrow(_counts(threshold), "id long, others long").groupBy("id").agg(F.sum("others").alias("others"))


def link_vectors(vectors: DataFrame, threshold: float = THRESHOLD, window: int = WINDOW, bits: int = BITS, seed: int = 5) -> DataFrame:
    """``(vec_id, n_links, component_id, kept)`` for each row of ``vectors(vec_id, embedding, label)``.

    Links join different rows of equal label (not null) at a cosine of at least ``threshold``.
    Vectors that are null, zero or hold null or non-finite components link with nothing, nor do
    vectors of different widths.  Equal vectors count as one in the passes and are counted by
    number afterwards; the smallest vec_id stands for them.  Rows whose vec_id is null form no
    links.  Other columns are ignored; an empty table gives no rows.
    """
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.col("embedding").alias("vector"))
    fit = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & usable(F.col("vector"))
    good = rows.where(fit)
    unique = stored(good.groupBy("label", "vector").agg(F.min("vec_id").alias("id"), F.count("*").alias("copies")).withColumn("width", F.size("vector")))
    centred = unique.select("id", "label", "width", "vector").join(stored(label_means(unique)), ["label", "width"])
    n = unique.count()
    tasks = max(1, math.ceil(n * ROUND / ROWS_A_TASK), vectors.sparkSession.sparkContext.defaultParallelism)
    order = ["pass", "label", "width", "code", "id"]
    joined, connected, done = None, 0, 0
    while n:
        hashed = centred.mapInArrow(_hashed(done, ROUND, seed, bits), "pass int, label long, width int, code long, id long, small binary, scale double, lost double")
        met = stored(hashed.repartitionByRange(tasks, *order).sortWithinPartitions(*order).mapInArrow(_linked(threshold, window), "a long, b long, sure boolean").distinct())
        ends = [unique.select(F.col("id").alias(i), F.col("vector").alias(v)) for i, v in (("a", "x"), ("b", "y"))]
        unsure = met.where("not sure").join(ends[0], "a").join(ends[1], "b").withColumn("width", F.size("x")).mapInArrow(_cosines(threshold), "a long, b long")
        links = met.where("sure").select("a", "b").unionByName(unsure)
        if joined is not None:
            links = links.unionByName(joined.select(F.col("id").alias("a"), F.col("component").alias("b")))
        joined = stored(components(links))
        drop(met)
        before, connected, done = connected, joined.where("id <> component").count(), done + ROUND
        if connected - before <= SETTLED * connected:
            break

    named = unique if joined is None else unique.join(joined, "id", "left")
    named = named.withColumn("component", F.lit(None).cast("long")) if joined is None else named
    members = named.where("component is not null").select("component", "id", "copies", "width", "vector")
    found = (
        named.join(_links(members, threshold), "id", "left")
        .select("label", "vector", F.coalesce("component", "id").alias("component_id"), (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    )
    found = good.join(found, ["label", "vector"]).select("vec_id", "n_links", "component_id")
    alone = rows.where(~fit).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return found.unionByName(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op5_sorted_passes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_vectors(table(spark, sf_dir, "embeddings"))
