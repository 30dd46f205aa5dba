"""What the index is compared with: all pairs, scans, disjoint keys, exact lookup; and an exact pruned join."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from metricblock.functions.distance import METRIC, delta_to_landmarks, key_delta
from metricblock.functions.edit_kernel import EditTargets
from metricblock.operators.blocks import expand_pairs
from metricblock.operators.pairwise import meet, packed
from metricblock.operators.records import key_dictionary
from metricblock.sources.scratch import stored


def all_pairs(keys: DataFrame, theta: float | None = None, combine: str = "sum", id_col: str = "rec_id") -> DataFrame:
    """``(a, b, delta)`` of every pair of one collection.  Quadratic by definition: the baseline."""
    if theta is not None and combine in ("sum", "split_space"):
        return close_pairs(keys.select(F.col(id_col).alias("rec_id"), "key"), theta)
    x = keys.select(F.col(id_col).alias("a"), F.col("key").alias("x"))
    y = keys.select(F.col(id_col).alias("b"), F.col("key").alias("y"))
    pairs = x.join(y, F.col("a") < F.col("b")).select("a", "b", key_delta("x", "y", combine).cast("long").alias("delta"))
    return pairs if theta is None else pairs.where(F.col("delta") <= F.lit(theta))


def close_pairs(keys: DataFrame, theta: float) -> DataFrame:
    """``(a, b, delta)``, a < b, of all records whose keys are at most ``theta`` apart; every two distinct keys are looked at, by blocks."""
    keys = stored(keys)
    dictionary = stored(key_dictionary(keys))

    class Side:
        def __init__(self, some: pa.Table):
            self.ids, self.keys, self.targets = some["key_id"].to_numpy(), some["key"].to_pylist(), None

    def work(x: Side, y: Side, same: bool) -> Iterator[pa.RecordBatch]:
        x.targets = x.targets or EditTargets(x.keys)
        i, j, delta = x.targets.close(y.keys, theta)
        a, b = y.ids[i], x.ids[j]
        keep = a < b if same else a != b
        yield pa.RecordBatch.from_arrays([pa.array(a[keep]), pa.array(b[keep]), pa.array(delta[keep].astype(np.int64))], ["a", "b", "delta"])

    blocks = packed(dictionary.select("key_id", "key"), 4096)
    return expand_pairs(meet(blocks, blocks, Side, work, "a long, b long, delta long", triangle=True), keys, dictionary)


def cross_pairs(left: DataFrame, right: DataFrame, theta: float | None = None, combine: str = "sum") -> DataFrame:
    """``(a, b, delta)`` of every pair across two collections."""
    x = left.select(F.col("rec_id").alias("a"), F.col("key").alias("x"))
    y = right.select(F.col("rec_id").alias("b"), F.col("key").alias("y"))
    pairs = x.join(y, F.lit(True)).select("a", "b", key_delta("x", "y", combine).cast("long").alias("delta"))
    return pairs if theta is None else pairs.where(F.col("delta") <= F.lit(theta))


def scan_match(queries: DataFrame, reference: DataFrame, theta: float, combine: str = "sum") -> DataFrame:
    """``(q_id, rec_id, delta)``: each query measured against the whole reference."""
    q = queries.select("q_id", F.col("key").alias("x"))
    r = reference.select("rec_id", F.col("key").alias("y"))
    return q.join(r, F.lit(True)).select("q_id", "rec_id", key_delta("x", "y", combine).cast("long").alias("delta")).where(F.col("delta") <= F.lit(theta))


def key_blocking(records: DataFrame, id_col: str, key: Callable[[], Column] | Column) -> DataFrame:
    """Distinct ``(a, b)`` of records that share a key: disjoint blocks, an equi-join."""
    key = key() if callable(key) else key
    own = records.select(F.col(id_col).alias("a"), key.alias("k")).where("k is not null")
    return own.join(own.withColumnRenamed("a", "b"), "k").where("a < b").select("a", "b")


def exact_lookup(queries: DataFrame, reference: DataFrame) -> DataFrame:
    """``(q_id, rec_id)`` of equal keys."""
    return queries.select("q_id", "key").join(reference.select("rec_id", "key"), "key").select("q_id", "rec_id")


def pivot_join(queries: DataFrame, reference: DataFrame, theta: int, pivots: list[list[str]], dissimilarity: str = "levenshtein") -> DataFrame:
    """``(q_id, rec_id, delta)``, exactly those within ``theta``, most pairs never measured.

    By the triangle inequality two keys within theta differ by at most theta in their distances to
    any pivot.  The first pivot's distance is the join's band; the others are checked before the
    edit distance is.  Only for metrics.
    """
    if not METRIC[dissimilarity]:
        raise ValueError(f"{dissimilarity} breaks the triangle inequality")
    q = delta_to_landmarks(queries.select("q_id", F.col("key")), pivots, name="pq").select("q_id", F.col("key").alias("x"), "pq")
    r = delta_to_landmarks(reference.select("rec_id", F.col("key")), pivots, name="pr").select("rec_id", F.col("key").alias("y"), "pr")
    width = theta + 1  # bands of this width: partners are in the same or a neighbouring band
    q = q.withColumn("band", F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda s: s + F.floor(F.get("pq", F.lit(0)) / width).cast("int"))))
    r = r.withColumn("band", F.floor(F.get("pr", F.lit(0)) / width).cast("int"))
    near = F.forall(F.zip_with("pq", "pr", lambda a, b: F.abs(a - b) <= theta), lambda ok: ok)
    return q.join(r, "band").where(near).select("q_id", "rec_id", key_delta("x", "y").cast("long").alias("delta")).where(F.col("delta") <= theta)
