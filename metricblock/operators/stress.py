"""How well coordinates keep dissimilarities: stress and distortion.

``pairs`` has ``i, j, delta`` and maybe ``w``; ``coords`` has ``id, coords``.  A missing delta
weighs nothing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.functions.distance import minkowski


def pair_distances(pairs: DataFrame, coords: DataFrame) -> DataFrame:
    """``pairs`` with ``d`` (Euclidean) and ``w`` (0 where delta is null): two equi-joins."""
    a = coords.select(F.col("id").alias("i"), F.col("coords").alias("x"))
    b = coords.select(F.col("id").alias("j"), F.col("coords").alias("y"))
    w = F.col("w") if "w" in pairs.columns else F.lit(1.0)
    joined = pairs.join(a, "i").join(b, "j").withColumn("d", minkowski("x", "y", 2)).drop("x", "y")
    return joined.withColumn("w", F.when(F.col("delta").isNull(), 0.0).otherwise(w.cast("double")))


def raw_stress(pairs: DataFrame, coords: DataFrame, ordered_pairs: bool = True) -> DataFrame:
    """The weighted sum of squared misses.  Pairs given once count twice with ``ordered_pairs``."""
    miss = F.col("w") * F.pow(F.col("d") - F.coalesce("delta", F.lit(0)), 2)
    return pair_distances(pairs, coords).agg((F.sum(miss) * (2 if ordered_pairs else 1)).alias("stress"))


def normalized_stress(pairs: DataFrame, coords: DataFrame) -> DataFrame:
    """Root of the squared misses over the squared dissimilarities; 0 is perfect."""
    delta = F.coalesce(F.col("delta").cast("double"), F.lit(0.0))
    seen = pair_distances(pairs, coords).agg(F.sum(F.col("w") * F.pow(F.col("d") - delta, 2)).alias("miss"), F.sum(F.col("w") * delta * delta).alias("size"))
    return seen.select(F.when(F.col("size") > 0, F.sqrt(F.col("miss") / F.col("size"))).alias("stress"))


def distortion(pairs: DataFrame, coords: DataFrame) -> DataFrame:
    """Largest expansion times largest contraction over pairs with both distances over zero."""
    both = pair_distances(pairs, coords).where("delta > 0 and d > 0 and w > 0")
    return both.agg((F.max(F.col("d") / F.col("delta")) * F.max(F.col("delta") / F.col("d"))).alias("distortion"))


def majorize_step(pairs: DataFrame, coords: DataFrame) -> DataFrame:
    """One majorization step of unit weights, distributed: ``(id, coords)`` after it.

    Needs each unordered pair once.  A point moves to the mean of where its pairs want it.
    """
    d = pair_distances(pairs, coords).where("d > 0").withColumn("r", F.col("delta") / F.col("d"))
    both = d.select(F.col("i").alias("id"), F.col("j").alias("other"), "r").unionByName(d.select(F.col("j").alias("id"), F.col("i").alias("other"), "r"))
    own = coords.select("id", F.col("coords").alias("x"))
    other = coords.select(F.col("id").alias("other"), F.col("coords").alias("y"))
    moves = both.join(own, "id").join(other, "other").select("id", F.posexplode(F.zip_with("x", "y", lambda a, b: a - b)).alias("dim", "gap"), "r")
    n = F.lit(coords.count())
    summed = moves.groupBy("id", "dim").agg((F.sum(F.col("r") * F.col("gap")) / n).alias("at"))
    return summed.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "at"))), lambda s: s["at"]).alias("coords"))
