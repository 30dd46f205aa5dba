"""Connected components of a graph given as pairs, for graphs that no machine can hold."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.sources.scratch import drop, stored


def _spanning_forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The pairs of one batch that join two trees: what is left of a partition never has a cycle."""
    for b in batches:
        parent: dict[int, int] = {}

        def root(x: int, parent: dict[int, int] = parent) -> int:
            while (up := parent.setdefault(x, x)) != x:
                parent[x] = x = parent.setdefault(up, up)
            return x

        for u, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            u, v = root(u), root(v)
            parent[max(u, v)] = min(u, v)
        found = [(x, r) for x in parent if (r := root(x)) != x]
        yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in found], pa.int64()), pa.array([r for _, r in found], pa.int64())], ["u", "v"])


def components(pairs: DataFrame, max_rounds: int = 64) -> DataFrame:
    """``(id, component)`` for every id in ``pairs(a long, b long)``; the component is its smallest id.

    Large-star and small-star steps in turn hook every id to smaller ones until all trees are
    stars.  A hub's neighbours never meet in one task: only minima are grouped, and they come
    back to the pairs by a join that may be split.  Each round is a table in the shared folder.
    Pairs with a null and of an id with itself add nothing.
    """
    edges = pairs.where("a is not null and b is not null and a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    edges = stored(edges.mapInArrow(_spanning_forest, "u long, v long").distinct())
    mark = _mark(edges)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        new = stored(small.unionByName(least.select("u", F.col("m").alias("v"))).distinct())
        drop(edges)
        edges, before, mark = new, mark, _mark(new)
        if mark == before:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = edges.select(F.col("v").alias("id")).distinct()
    return edges.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(roots.withColumn("component", F.col("id")))


def _mark(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
    return row[0], row[1]


def clusters(pairs: DataFrame, ids: DataFrame) -> DataFrame:
    """``(rec_id, cluster_id)`` for all of ``ids(rec_id)``: linked records share their smallest id, others are alone."""
    found = components(pairs.select(F.col("a").cast("long"), F.col("b").cast("long")))
    return ids.select("rec_id").join(found.withColumnRenamed("id", "rec_id"), "rec_id", "left").select("rec_id", F.coalesce("component", "rec_id").alias("cluster_id"))


def representatives(clustered: DataFrame) -> DataFrame:
    """One record of each cluster, the one that names it."""
    return clustered.where("rec_id = cluster_id").select("rec_id")
