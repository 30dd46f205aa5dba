"""Query matching: a reference, embedded and indexed once, answers queries by their landmark distances."""

from __future__ import annotations

import json
import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from metricblock.functions.edit_kernel import key_matrix
from metricblock.operators import knn
from metricblock.operators.clusters import stored
from metricblock.operators.model import EmbeddingModel
from metricblock.operators.pairwise import parallel
from metricblock.operators.placement import place_batch
from metricblock.operators.records import BlockingSpec, blocking_keys, check_schema, key_dictionary
from metricblock.operators.trees import KDTree, RTree


@dataclass
class ReferenceIndex:
    """``points``: (key_id, key, coords) of the distinct reference values; ``records``: (rec_id, key_id).

    A small index also holds its tree, which is shipped to the tasks; a large one is searched
    by cells (``strategy`` "partitioned").
    """

    model: EmbeddingModel
    points: DataFrame
    records: DataFrame
    id_col: str
    strategy: str = "broadcast"
    version: int = 1
    _tree: object = None
    _size: int | None = None

    @property
    def size(self) -> int:
        """Number of distinct reference values, counted once."""
        if self._size is None:
            self._size = self.points.count()
        return self._size

    @property
    def spec(self) -> BlockingSpec:
        return self.model.spec

    @classmethod
    def fit(cls, reference: DataFrame, id_col: str, spec: BlockingSpec, strategy: str = "auto", **embedding) -> ReferenceIndex:
        keys = stored(blocking_keys(reference, id_col, spec))
        dictionary = stored(key_dictionary(keys))
        model = EmbeddingModel.fit(dictionary, spec, **embedding)
        return cls.of(model, keys, dictionary, id_col, strategy)

    @classmethod
    def of(cls, model: EmbeddingModel, keys: DataFrame, dictionary: DataFrame, id_col: str, strategy: str = "auto") -> ReferenceIndex:
        points = stored(model.transform(dictionary).select("key_id", "key", "coords"))
        records = stored(keys.select("rec_id", F.xxhash64("key").alias("key_id")))
        if strategy == "auto":
            strategy = "broadcast" if knn.tree_bytes(points.count(), model.dimension) <= knn.BROADCAST_BYTES else "partitioned"
        return cls(model, points, records, id_col, strategy)

    def tree(self):
        if self._tree is None:
            at, ids = knn.collected(self.points.select(F.col("key_id").alias("id"), "coords"))
            self._tree = RTree.pack(at, ids) if self.strategy == "rtree" else KDTree.build(at, ids)
        return self._tree

    def query_keys(self, queries: DataFrame, id_col: str = "q_id") -> DataFrame:
        return blocking_keys(queries, id_col, self.spec, out="q_id")

    def block(self, queries: DataFrame, k: int, id_col: str = "q_id", probes: int | None = None) -> DataFrame:
        """``(q_id, key, n_id, rank, dist)``: each query's block of reference values."""
        keys = self.query_keys(queries, id_col)
        if self.strategy != "partitioned" and len(self.model.spaces) == 1:
            return self._fused(keys, k)
        placed = self.model.transform(keys, "q_id")
        if self.strategy != "partitioned":
            near = knn.tree_search(placed.select(F.col("q_id").alias("id"), "coords"), self.tree(), k)
        else:
            placed = stored(placed)
            near = knn.knn_partitioned(placed.select(F.col("q_id").alias("id"), "coords"), self.points.select(F.col("key_id").alias("id"), "coords"), k, probes=probes)
        return near.join(keys.select("q_id", "key"), "q_id")

    def _fused(self, keys: DataFrame, k: int) -> DataFrame:
        """Landmark distances, placement and search in one narrow pass; stateless, so it also runs on streams."""
        space, options = self.model.spaces[0], self.model.placement
        shipped = knn.shared(self.points, self.tree())
        combine = "sum" if space.spec.combine == "split_space" else space.spec.combine
        seeded = keys.select("q_id", "key", F.xxhash64("key", F.lit(options.seed)).alias("_seed"))
        fixed = {tuple(key): c for key, c in zip(space.keys, space.coords, strict=True)} if self.model.index_coords == "mds" else {}

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            tree = shipped.value
            for whole in batches:
                for a in range(0, whole.num_rows, 1024):
                    b = whole.slice(a, 1024)
                    keys = b.column("key").to_pylist()
                    delta = key_matrix(keys, space.keys, combine, space.spec.weights)
                    y, _ = place_batch(space.coords, delta, b.column("_seed").to_numpy(), options)
                    for i, key in enumerate(keys):
                        if tuple(key) in fixed:
                            y[i] = fixed[tuple(key)]
                    found = [tree.knn(q, k) for q in y]
                    size = [len(ids) for ids, _ in found]
                    of = np.repeat(np.arange(len(keys)), size)
                    columns = [
                        b.column("q_id").take(pa.array(of)),
                        b.column("key").take(pa.array(of)),
                        pa.array(np.concatenate([np.zeros(0, dtype=np.int64), *(ids for ids, _ in found)])),
                        pa.array(np.concatenate([np.zeros(0, dtype=np.int32), *(np.arange(1, n + 1, dtype=np.int32) for n in size)])),
                        pa.array(np.concatenate([np.zeros(0), *(d for _, d in found)])),
                    ]
                    yield pa.RecordBatch.from_arrays(columns, ["q_id", "key", "n_id", "rank", "dist"])

        return seeded.mapInArrow(run, "q_id long, key array<string>, n_id long, rank int, dist double")

    def match(self, queries: DataFrame, k: int = 150, theta: float = 2, id_col: str = "q_id", emit: str = "matches", probes: int | None = None) -> DataFrame:
        """``(q_id, rec_id, delta, rank, dist)``: reference records in the query's block at most ``theta`` away.

        ``emit="block"`` keeps the whole block.  A query without a match gives no rows.
        """
        if emit == "matches" and self.strategy == "broadcast" and self.spec.combine in ("sum", "split_space") and not queries.isStreaming and k >= self.size:
            keys = self.query_keys(queries, id_col)
            placed = self.model.transform(keys.repartition(parallel(keys)), "q_id").select(F.col("q_id").alias("id"), "coords", "key")
            found = knn.search_full(placed, self.points.select(F.col("key_id").alias("id"), "coords", "key"), theta)
            return found.join(self.records.withColumnRenamed("key_id", "n_id"), "n_id").select("q_id", "rec_id", "delta", "rank", "dist")
        near = self.block(queries, k, id_col, probes)
        values = self.points.select(F.col("key_id").alias("n_id"), F.col("key").alias("n_key"))
        measured = near.join(values, "n_id").withColumn("delta", self.spec.delta("key", "n_key"))
        if emit == "matches":
            measured = measured.where(F.col("delta") <= F.lit(theta))
        return measured.join(self.records.withColumnRenamed("key_id", "n_id"), "n_id").select("q_id", "rec_id", "delta", "rank", "dist")

    def match_distinct(self, queries: DataFrame, k: int = 150, theta: float = 2, id_col: str = "q_id") -> DataFrame:
        """As ``match``, with every distinct value searched once, however often it is asked."""
        keys = self.query_keys(queries, id_col).withColumn("v_id", F.xxhash64("key"))
        once = keys.dropDuplicates(["v_id"]).select(F.col("v_id").alias("q_id"), *[F.get("key", F.lit(i)).alias(c) for i, c in enumerate(self.spec.cols)])
        found = self.match(once, k, theta)
        return keys.select("q_id", "v_id").join(found.withColumnRenamed("q_id", "v_id"), "v_id").drop("v_id")

    def match_within(self, queries: DataFrame, k: int, theta: float, seconds: float, order: str = "q_id", batch: int = 100) -> tuple[DataFrame, int]:
        """Matches of as many queries, in order, as are done in ``seconds``; and how many those are.

        A batch counts only if it was finished in time.
        """
        ranked = stored(running_sum(queries, F.lit(1), (order,), "_nth").withColumn("_nth", F.col("_nth") - 1))
        total, done, parts, began = ranked.count(), 0, [], time.monotonic()
        while done < total:
            some = stored(self.match(ranked.where((F.col("_nth") >= done) & (F.col("_nth") < done + batch)).drop("_nth"), k, theta))
            if time.monotonic() - began > seconds:
                break
            parts.append(some)
            done = min(total, done + batch)
        out = parts[0] if parts else ranked.sparkSession.createDataFrame([], "q_id long, rec_id long, delta int, rank int, dist double")
        for p in parts[1:]:
            out = out.unionByName(p)
        return out, done

    def query_ops(self, k: int, iterations: int = 20) -> float:
        """Cost of one query in operations: landmark distances, placement, search."""
        n = max(2, self.points.count())
        return self.model.landmarks * (1 + iterations * self.model.dimension) + k * float(np.log2(n))

    def absorb(self, unmatched: DataFrame, id_col: str = "rec_id") -> ReferenceIndex:
        """A new version of the index with more records; values it already knows cost nothing, and records it knows stay once.

        Trees and cells are built over all points of a version, so they are balanced again; an
        index that has grown too large to be shipped is searched by cells from then on.
        """
        keys = stored(blocking_keys(unmatched, id_col, self.spec))
        fresh = key_dictionary(keys).join(self.points.select("key_id"), "key_id", "left_anti")
        points = stored(self.points.unionByName(self.model.transform(fresh).select("key_id", "key", "coords")))
        records = stored(self.records.unionByName(keys.select("rec_id", F.xxhash64("key").alias("key_id"))).distinct())
        fits = knn.tree_bytes(points.count(), self.model.dimension) <= knn.BROADCAST_BYTES
        return ReferenceIndex(self.model, points, records, self.id_col, self.strategy if fits else "partitioned", self.version + 1)

    def save(self, path: str) -> None:
        spark = self.points.sparkSession
        self.model.save(spark, f"{path}/model")
        self.points.write.mode("overwrite").parquet(f"{path}/points")
        self.records.write.mode("overwrite").parquet(f"{path}/records")
        about = json.dumps({"id_col": self.id_col, "strategy": self.strategy, "version": self.version, "model_id": self.model.model_id})
        spark.createDataFrame([(about,)], "manifest string").coalesce(1).write.mode("overwrite").parquet(f"{path}/index")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> ReferenceIndex:
        about = json.loads(spark.read.parquet(f"{path}/index").first()[0])
        model = EmbeddingModel.load(spark, f"{path}/model")
        if model.model_id != about["model_id"]:
            raise ValueError("the index was built with another model")
        return cls(model, spark.read.parquet(f"{path}/points"), spark.read.parquet(f"{path}/records"), about["id_col"], about["strategy"], about["version"])


def exact_prefilter(queries: DataFrame, reference: DataFrame, cols: tuple[str, ...], q_id: str = "q_id", rec_id: str = "rec_id") -> tuple[DataFrame, DataFrame]:
    """Exact hits ``(q_id, rec_id)`` by an equi-join, and the queries left over."""
    check_schema(reference, queries, cols)
    hits = queries.join(reference, list(cols)).select(q_id, rec_id)
    return hits, queries.join(reference, list(cols), "left_anti")


def running_sum(rows: DataFrame, cost, order: tuple[str, ...], name: str) -> DataFrame:
    """``rows`` with the running sum of ``cost`` in ``order``, summed by ranges: no task holds all rows.

    The driver gets one sum from each range.
    """
    dealt = stored(rows.withColumn(name, cost).repartitionByRange(*order).withColumn("_range", F.spark_partition_id()))
    sums = dict(dealt.groupBy("_range").agg(F.sum(name)).collect())
    before, offsets = 0, []
    for r in sorted(sums):
        offsets.append((r, before))
        before += sums[r]
    kind = dict(dealt.groupBy().agg(F.sum(name).alias("s")).dtypes)["s"]
    starts = dealt.sparkSession.createDataFrame([(r, float(b) if kind == "double" else b) for r, b in offsets], f"_range int, _before {kind}")
    inside = F.sum(name).over(Window.partitionBy("_range").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return dealt.withColumn(name, inside).join(F.broadcast(starts), "_range").withColumn(name, F.col(name) + F.col("_before")).drop("_range", "_before")


def budgeted(queries: DataFrame, cost, budget: float, order: tuple[str, ...]) -> DataFrame:
    """Queries, in order, whose running cost stays within the budget: the deterministic form of a time limit."""
    return running_sum(queries, cost, order, "running_cost").where(F.col("running_cost") <= F.lit(budget))


def link(left: DataFrame, right: DataFrame, left_id: str, right_id: str, spec: BlockingSpec, k: int = 150, theta: float = 2, **fit) -> DataFrame:
    """Two duplicate-free collections: ``(a, b, delta)`` with a from the left and b from the right."""
    check_schema(left, right, spec.cols)
    index = ReferenceIndex.fit(right, right_id, spec, **fit)
    return index.match(left, k, theta, id_col=left_id).select(F.col("q_id").alias("a"), F.col("rec_id").alias("b"), "delta")
