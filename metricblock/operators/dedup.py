"""Self-blocking: candidates within one collection, from complete or landmark embedding."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.functions.distance import levenshtein, record_score
from metricblock.operators.blocks import block_pairs, expand_links, expand_pairs, filter_pairs
from metricblock.operators.clusters import clusters, representatives, stored
from metricblock.operators.knn import BROADCAST_BYTES, search_full, self_knn, tree_bytes
from metricblock.operators.model import EmbeddingModel, complete_embedding
from metricblock.operators.records import BlockingSpec, blocking_keys, key_dictionary


def embed(dictionary: DataFrame, spec: BlockingSpec, K: int = 7, embedding: str = "landmark", **fit) -> DataFrame:
    """``(id, coords, key)`` of the distinct keys, stored."""
    if embedding == "complete":
        placed, _ = complete_embedding(dictionary, K, combine="sum" if spec.combine == "split_space" else spec.combine, force=True)
    else:
        placed = EmbeddingModel.fit(dictionary, spec, K=K, **fit).transform(dictionary)
    return stored(placed.select(F.col("key_id").alias("id"), "coords", "key"))


def dedup_blocks(records: DataFrame, id_col: str, spec: BlockingSpec, B: int = 50, K: int = 7, embedding: str = "landmark", strategy: str = "auto", **fit) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Blocks over distinct values, the record keys and the dictionary: every value asks for its ``B`` nearest."""
    points, keys, dictionary = embedded_keys(records, id_col, spec, K, embedding, **fit)
    return self_knn(points.select("id", "coords"), B, strategy=strategy), keys, dictionary


def embedded_keys(records: DataFrame, id_col: str, spec: BlockingSpec, K: int = 7, embedding: str = "landmark", **fit) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The embedded distinct values, the record keys and the dictionary."""
    keys = stored(blocking_keys(records, id_col, spec))
    dictionary = stored(key_dictionary(keys))
    return embed(dictionary, spec, K, embedding, **fit), keys, dictionary


def dedup(records: DataFrame, id_col: str, spec: BlockingSpec, theta: float = 2, B: int = 50, K: int = 7, pairs: str = "star", embedding: str = "landmark", expand: str = "pairs", strategy: str = "auto", **how) -> DataFrame:
    """Candidate record pairs ``(a, b, delta)``: in one block, and at most ``theta`` apart in original values.

    ``expand="links"`` gives as many as the components need: a frequent value costs a row a record, not a row a pair.
    A block that holds all values isn't written out: the threshold is applied where it is searched.
    """
    points, keys, dictionary = embedded_keys(records, id_col, spec, K, embedding, **how)
    n = points.count()
    if B >= n - 1 and strategy == "auto" and spec.combine in ("sum", "split_space") and tree_bytes(n, K * len(spec.parts())) <= BROADCAST_BYTES:
        found = search_full(points, points, theta, include_self=False)
        close = found.where("q_id < n_id").select(F.col("q_id").alias("a"), F.col("n_id").alias("b"), "delta")
    else:
        close = filter_pairs(block_pairs(self_knn(points.select("id", "coords"), B, strategy=strategy), pairs), dictionary, spec, theta)
    return (expand_links if expand == "links" else expand_pairs)(close, keys, dictionary)


def detailed_compare(candidates: DataFrame, records: DataFrame, id_col: str, attrs: Sequence[str], theta: float) -> DataFrame:
    """Candidates with the summed distance of the other attributes, and whether they match."""
    cols = [F.col(c).cast("string") for c in attrs]
    x = records.select(F.col(id_col).alias("a"), *[c.alias(f"x{i}") for i, c in enumerate(cols)])
    y = records.select(F.col(id_col).alias("b"), *[c.alias(f"y{i}") for i, c in enumerate(cols)])
    parts = [F.coalesce(levenshtein(f"x{i}", f"y{i}"), F.lit(0)) for i in range(len(cols))]
    scored = candidates.join(x, "a").join(y, "b").withColumn("score", record_score(parts))
    return scored.select(*candidates.columns, "score", (F.col("score") <= F.lit(theta)).alias("is_match"))


def iterative_er(records: DataFrame, id_col: str, spec: BlockingSpec, theta: float = 2, rounds: int = 5, **how) -> DataFrame:
    """Merge clusters to their representatives and block again until nothing merges: ``(rec_id, cluster_id)``."""
    found = stored(records.select(F.col(id_col).alias("rec_id"), F.col(id_col).alias("cluster_id")))
    current = records
    for _ in range(rounds):
        linked = stored(dedup(current, id_col, spec, theta, expand="links", **how))
        if linked.isEmpty():
            break
        step = clusters(linked, current.select(F.col(id_col).alias("rec_id"))).select(F.col("rec_id").alias("cluster_id"), F.col("cluster_id").alias("root"))
        found = stored(found.join(step, "cluster_id").select("rec_id", F.col("root").alias("cluster_id")))
        kept = representatives(step.select(F.col("cluster_id").alias("rec_id"), F.col("root").alias("cluster_id")))
        current = records.join(kept.withColumnRenamed("rec_id", id_col), id_col, "left_semi")
    return found
