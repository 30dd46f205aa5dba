"""The published experiments on the workloads of this repository, one function per figure.

Each returns a table shaped like the figure's axes, so that trends can be compared.  Sizes
default to the published ones; wall-clock columns are of this machine, counts are not.
"""

from __future__ import annotations

import time
from collections.abc import Sequence
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from metricblock import workloads as W
from metricblock.functions.edit_kernel import key_matrix
from metricblock.operators import landmarks as lm
from metricblock.operators import measures, mds
from metricblock.operators.blocks import block_pairs, filter_pairs
from metricblock.operators.clusters import stored
from metricblock.operators.dedup import embed
from metricblock.operators.knn import self_knn
from metricblock.operators.model import EmbeddingModel, sweep_dimension
from metricblock.operators.placement import PlacementOptions, place_batch
from metricblock.operators.querymatch import ReferenceIndex
from metricblock.operators.records import BlockingSpec, blocking_keys, key_dictionary
from metricblock.operators.trees import KDTree

NAMES = BlockingSpec(("given", "surname"))
BLOCK_SIZES = (20, 30, 40, 50, 60, 70, 80, 90, 100)
#: Controlled stand-ins of the two datasets: typo profile, threshold, share of duplicates, queries.
DATASETS = {"first": ("typos2", 2, 0.10, 500), "second": ("typos3", 3, 0.075, 375)}


def stress_by_dimension(spark: SparkSession, sf_dir: str, n: int = 2_000, Ks: Sequence[int] = tuple(range(1, 21)), L: int = 500) -> DataFrame:
    """Stress falls with the dimension and flattens; the time to embed grows with it."""
    keys = key_dictionary(blocking_keys(W.names_ref(spark, sf_dir, n), "rec_id", NAMES))
    return sweep_dimension(keys, Ks, L)


def _candidates(blocks: DataFrame, gold: DataFrame, keys: DataFrame, sizes: Sequence[int], mode: str, theta: float) -> DataFrame:
    """``(B, n_b, found, n_theta, found_theta)``: pairs of values in blocks of the B nearest and true ones among them, before and after ``theta``."""
    of = keys.select("rec_id", F.xxhash64("key").alias("key_id"))
    true = gold.join(of.withColumnRenamed("rec_id", "a").withColumnRenamed("key_id", "x"), "a").join(of.withColumnRenamed("rec_id", "b").withColumnRenamed("key_id", "y"), "b").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), F.lit(1).alias("gold"))
    values = keys.select(F.xxhash64("key").alias("key_id"), "key").dropDuplicates(["key_id"])
    if mode == "star":
        pairs = blocks.where("q_id <> n_id").groupBy(F.least("q_id", "n_id").alias("a"), F.greatest("q_id", "n_id").alias("b")).agg(F.min("rank").alias("rank"))
    else:
        each = [block_pairs(blocks.where(F.col("rank") <= b), "clique").withColumn("rank", F.lit(b)) for b in sizes]
        pairs = reduce(DataFrame.unionByName, each).groupBy("a", "b").agg(F.min("rank").alias("rank"))
    measured = filter_pairs(pairs, values, NAMES, float("inf")).join(pairs, ["a", "b"]).join(true, ["a", "b"], "left")
    by_size = measured.withColumn("B", F.explode(F.lit(list(sizes)))).where("rank <= B")
    near = F.col("delta") <= theta
    return by_size.groupBy("B").agg(F.count("*").alias("n_b"), F.count("gold").alias("found"), F.count_if(near).alias("n_theta"), F.count_if(near & F.col("gold").isNotNull()).alias("found_theta"))


def blocking_curve(spark: SparkSession, sf_dir: str, dataset: str = "first", n: int = W.DEDUP, Ks: Sequence[int] = (3, 7, 10), Ls: Sequence[int] = (300,), embeddings: Sequence[str] = ("landmark",), sizes: Sequence[int] = BLOCK_SIZES, mode: str = "star") -> DataFrame:
    """Reduction ratio and pair completeness by block size, dimension, landmarks and kind of embedding.

    ``rr`` and ``pc`` are of the blocks' pairs, ``rr_theta`` and ``pc_theta`` of those at most theta apart.
    """
    profile, theta, share, _ = DATASETS[dataset]
    records = stored(W.names_dedup(spark, sf_dir, n, share, profile))
    gold = stored(W.gold_pairs(records))
    total = gold.count()
    keys = stored(blocking_keys(records, "rec_id", NAMES))
    dictionary = stored(key_dictionary(keys))
    parts = []
    for kind in embeddings:
        for K in Ks:
            for L in Ls if kind == "landmark" else (n,):
                fit = {"L": L, "landmarks": "farthest_first" if L <= lm.EXACT_LANDMARKS else "coreset"} if kind == "landmark" else {}
                points = embed(dictionary, NAMES, K, kind, **fit)
                blocks = stored(self_knn(points.select("id", "coords"), max(sizes), strategy="broadcast"))
                counts = _candidates(blocks, gold, keys, sizes, mode, theta)
                labels = [F.lit(v).alias(c) for c, v in (("dataset", dataset), ("embedding", kind), ("K", K), ("L", L), ("mode", mode), ("theta", theta))]
                parts.append(counts.select(*labels, "B", "n_b", measures.reduction_ratio(F.col("n_b"), n).alias("rr"), (F.col("found") / F.lit(total)).alias("pc"), "n_theta", measures.reduction_ratio(F.col("n_theta"), n).alias("rr_theta"), (F.col("found_theta") / F.lit(total)).alias("pc_theta")))
    return reduce(DataFrame.unionByName, parts)


def time_by_landmarks(spark: SparkSession, sf_dir: str, n: int = W.REFERENCE, q: int = W.QUERIES, Ls: Sequence[int] = (100, 300, 700, 1500), K: int = 7, solver: str = "sgd") -> DataFrame:
    """Mean seconds of a query's landmark distances and of its placement, one query at a time; nothing but the kernels is timed."""
    keys = stored(key_dictionary(blocking_keys(W.names_ref(spark, sf_dir, n), "rec_id", NAMES)))
    asked = blocking_keys(W.names_query(spark, sf_dir, n, q), "q_id", NAMES, out="q_id")
    got = asked.select("q_id", "key", F.xxhash64("key").alias("s")).orderBy("q_id").collect()
    rows = []
    for L in Ls:
        chosen = lm.choose(keys, L, "coreset")
        x, _ = mds.lsmds(mds.landmark_delta(chosen), K)
        options, distance, placement = PlacementOptions(solver=solver), 0.0, 0.0
        key_matrix([got[0]["key"]], chosen)
        for r in got:
            began = time.perf_counter()
            delta = key_matrix([r["key"]], chosen)
            between = time.perf_counter()
            place_batch(x, delta, np.array([r["s"]]), options)
            distance += between - began
            placement += time.perf_counter() - between
        rows.append((L, distance / len(got), placement / len(got)))
    return spark.createDataFrame(rows, "L int, distance_s double, placement_s double")


def matching_curve(spark: SparkSession, sf_dir: str, datasets: Sequence[str] = ("first", "second"), n: int = W.REFERENCE, Ls: Sequence[int] = (100, 300, 700), ks: Sequence[int] = (50, 100, 150), K: int = 7, budget_s: float = 60.0, placement: PlacementOptions = PlacementOptions()) -> DataFrame:
    """True and false positives by landmarks and block size, of the queries answered within ``budget_s`` seconds of real time."""
    parts = []
    for dataset in datasets:
        profile, theta, _, q = DATASETS[dataset]
        reference, asked = stored(W.names_ref(spark, sf_dir, n)), stored(W.names_query(spark, sf_dir, n, q, profile))
        total = asked.count()  # fewer than q where there are fewer names
        for L in Ls:
            index = ReferenceIndex.fit(reference, "rec_id", NAMES, K=K, L=L, landmarks="farthest_first" if L <= lm.EXACT_LANDMARKS else "coreset", placement=placement)
            for k in ks:
                began = time.perf_counter()
                found, done = index.match_within(asked, k, theta, budget_s, batch=q)
                if not done:
                    found, done = index.match_within(asked, k, theta, budget_s, batch=max(1, q // 10))
                seconds = time.perf_counter() - began
                answered = asked.where(F.col("q_id") <= done)
                report = measures.matching_report(found, answered, reference)
                labels = [F.lit(v).alias(c) for c, v in (("dataset", dataset), ("theta", theta), ("L", L), ("k", k))]
                parts.append(report.select(*labels, "processed", "tp", "fp", "precision", "recall", F.lit(done / total if total else 1.0).alias("share_in_budget"), F.lit(seconds).alias("seconds")))
    return reduce(DataFrame.unionByName, parts)


def search_time(spark: SparkSession, sf_dir: str, n: int = W.REFERENCE, ks: Sequence[int] = (10, 50, 150), K: int = 7, L: int = 100) -> DataFrame:
    """Mean milliseconds of a tree search: little effect of k, below the placement by far."""
    keys = key_dictionary(blocking_keys(W.names_ref(spark, sf_dir, n), "rec_id", NAMES))
    model = EmbeddingModel.fit(keys, NAMES, K=K, L=L, landmarks="random")
    points = model.transform(keys).select("key_id", "coords").collect()
    asked = model.transform(blocking_keys(W.names_query(spark, sf_dir, n), "q_id", NAMES, out="q_id"), "q_id").orderBy("q_id").collect()
    x, ids = np.array([r["coords"] for r in points]), np.array([r["key_id"] for r in points])
    tree, rows = KDTree.build(x, ids), []
    for k in ks:
        began = time.perf_counter()
        for r in asked:
            tree.knn(np.array(r["coords"]), k)
        rows.append((k, len(x), (time.perf_counter() - began) / len(asked) * 1000))
    return spark.createDataFrame(rows, "k int, n int, mean_ms double")
