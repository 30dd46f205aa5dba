"""Dissimilarities between strings, vectors and records, as column expressions.

Those that Spark's functions can express run in the JVM; Jaro and the transposition-aware
edit distance are Arrow-batched functions.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from metricblock.functions.text import _col

METRIC = {"levenshtein": True, "qgram_set": True, "jaro": False, "jaro_winkler": False, "osa": False}


def levenshtein(a: Column | str, b: Column | str, cap: int | None = None) -> Column:
    """Edit distance in code points.  With ``cap`` a distance over it is -1, at less work."""
    a, b = _col(a), _col(b)
    return (F.levenshtein(a, b) if cap is None else F.levenshtein(a, b, cap)).cast("int")


def _jaro(a: str, b: str) -> float:
    if a == b:
        return 1.0
    reach = max(0, max(len(a), len(b)) // 2 - 1)
    used = [False] * len(b)
    ours = []
    for i, x in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not used[j] and b[j] == x:
                used[j] = True
                ours.append(x)
                break
    m = len(ours)
    if not m:
        return 0.0
    theirs = [y for y, u in zip(b, used, strict=True) if u]
    swaps = sum(x != y for x, y in zip(ours, theirs, strict=True)) // 2
    return (m / len(a) + m / len(b) + (m - swaps) / m) / 3


def _osa(a: str, b: str) -> int:
    before, last = [], list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row = [i]
        for j, y in enumerate(b, 1):
            best = min(last[j] + 1, row[j - 1] + 1, last[j - 1] + (x != y))
            if i > 1 and j > 1 and x == b[j - 2] and a[i - 2] == y:
                best = min(best, before[j - 2] + 1)
            row.append(best)
        before, last = last, row
    return last[-1]


def _winkler(a: str, b: str) -> float:
    s = _jaro(a, b)
    same = next((i for i, (p, q) in enumerate(zip(a, b, strict=False)) if p != q), min(len(a), len(b)))
    return s + min(same, 4) * 0.1 * (1 - s) if s > 0.7 else s


def _batched(f, kind: str, dtype: str):
    """``f(a, b)`` over Arrow batches; null if either side is.  Made on use, since it needs a session."""

    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else f(x, y) for x, y in zip(a, b, strict=True)], dtype=dtype)

    return F.pandas_udf(run, kind)


def jaro(a: Column | str, b: Column | str) -> Column:
    """Jaro similarity."""
    return _batched(_jaro, "double", "float64")(a, b)


def jaro_winkler(a: Column | str, b: Column | str) -> Column:
    """Jaro similarity raised for a common prefix of up to four letters, if over 0.7."""
    return _batched(_winkler, "double", "float64")(a, b)


def osa(a: Column | str, b: Column | str) -> Column:
    """Edit distance in which swapping two neighbours costs one (no stretch is edited twice)."""
    return _batched(_osa, "int", "Int32")(a, b)


def qgrams(a: Column | str, q: int = 2) -> Column:
    """All substrings of length ``q``, in order."""
    a = _col(a)
    last = F.length(a) - q + 1
    return F.when(last >= 1, F.transform(F.sequence(F.lit(1), last), lambda i: F.substring(a, i, F.lit(q)))).when(a.isNotNull(), F.array().cast("array<string>"))


def qgram(a: Column | str, b: Column | str, q: int = 2, kind: str = "bag") -> Column:
    """q-gram distance: of bags, the sum of count differences; of sets, the size of what isn't common."""
    x, y = qgrams(a, q), qgrams(b, q)
    if kind == "set":
        return (F.size(F.array_except(x, y)) + F.size(F.array_except(y, x))).cast("int")

    def times(grams: Column, g: Column) -> Column:
        return F.size(F.filter(grams, lambda z: z == g))

    return F.aggregate(F.array_union(x, y), F.lit(0), lambda s, g: s + F.abs(times(x, g) - times(y, g))).cast("int")


def minkowski(x: Column | str, y: Column | str, p: float = 2) -> Column:
    """L^p distance of two arrays, p >= 1; ``float("inf")`` is the largest difference."""
    gaps = F.zip_with(_col(x), _col(y), lambda a, b: F.abs(a.cast("double") - b.cast("double")))
    if p == float("inf"):
        return F.array_max(gaps)
    if p < 1:
        raise ValueError("p has to be at least 1")
    if p == 1:
        return F.aggregate(gaps, F.lit(0.0), lambda s, g: s + g)
    if p == 2:
        return F.sqrt(F.aggregate(gaps, F.lit(0.0), lambda s, g: s + g * g))
    return F.pow(F.aggregate(gaps, F.lit(0.0), lambda s, g: s + F.pow(g, F.lit(float(p)))), F.lit(1.0 / p))


def record_score(parts: Sequence[Column], weights: Sequence[float] | None = None) -> Column:
    """The sum of per-attribute scores, weighted if ``weights`` are given."""
    weighted = [p if w is None else p * F.lit(float(w)) for p, w in zip(parts, weights or [None] * len(parts), strict=True)]
    return reduce(lambda a, b: a + b, weighted)


def classify(score: Column, theta: float, similarity: bool = False) -> Column:
    """Match or not: at most ``theta`` for dissimilarities, at least ``theta`` for similarities."""
    return score >= F.lit(theta) if similarity else score <= F.lit(theta)


def to_dissimilarity(s: Column, kind: str = "complement", most: float = 1.0) -> Column:
    """``most - s``, or the negative logarithm of ``s`` for kind "log"."""
    return -F.log(s) if kind == "log" else F.lit(most) - s


def attribute_delta(a: Column, b: Column, on_missing: str = "weight0") -> tuple[Column, Column]:
    """Edit distance of one attribute and its weight; a missing side weighs nothing, or costs the other's length."""
    missing = a.isNull() | b.isNull()
    if on_missing == "weight0":
        return F.coalesce(levenshtein(a, b), F.lit(0)), F.when(missing, 0).otherwise(1)
    if on_missing == "max":
        return F.coalesce(levenshtein(a, b), F.length(a), F.length(b), F.lit(0)), F.lit(1)
    if on_missing == "error":
        return F.when(missing, F.raise_error(F.lit("missing attribute value")).cast("int")).otherwise(levenshtein(a, b)), F.lit(1)
    raise ValueError(on_missing)


def key_delta(a: Column | str, b: Column | str, combine: str = "sum", weights: Sequence[float] | None = None) -> Column:
    """Edit distance of two keys (arrays of strings): summed over attributes, of the joined values, or weighted."""
    a, b = _col(a), _col(b)
    if combine == "concat":
        return levenshtein(F.array_join(a, " "), F.array_join(b, " "))
    each = F.zip_with(a, b, lambda x, y: F.coalesce(F.levenshtein(x, y), F.lit(0)))
    if combine == "sum":
        return F.aggregate(each, F.lit(0), lambda s, d: s + d)
    if combine == "weighted":
        scaled = F.zip_with(each, F.lit([float(w) for w in weights or ()]), lambda d, w: d * w)
        return F.aggregate(scaled, F.lit(0.0), lambda s, d: s + d)
    raise ValueError(combine)


def delta_to_landmarks(keys: DataFrame, landmarks: Sequence[Sequence[str]], combine: str = "sum", name: str = "delta") -> DataFrame:
    """``keys`` with the distances of ``key`` to all landmarks, in order, as one array: no join, no extra rows.

    The landmarks are part of the plan; their number is a parameter of the method, not of the data.
    """
    fixed = F.lit([list(x) for x in landmarks]) if landmarks else F.array().cast("array<array<string>>")
    return keys.withColumn(name, F.transform(fixed, lambda x: key_delta(F.col("key"), x, combine)))


def metric_violations(sample: DataFrame, delta) -> DataFrame:
    """How often ``delta(a, b)`` breaks identity, symmetry and the triangle inequality on ``sample(id, value)``.

    Three values at a time: for small samples.
    """
    x, y, z = (sample.select(F.col("id").alias(f"{n}_id"), F.col("value").alias(f"{n}")) for n in "xyz")
    two = x.crossJoin(y).withColumns({"xy": delta(F.col("x"), F.col("y")), "yx": delta(F.col("y"), F.col("x"))})
    pairs = two.agg(
        F.count_if((F.col("x") == F.col("y")) != (F.col("xy") == 0)).cast("long").alias("identity"),
        F.count_if(F.col("xy") != F.col("yx")).cast("long").alias("symmetry"),
    )
    yz = two.select(F.col("x_id").alias("y_id"), F.col("y_id").alias("z_id"), F.col("xy").alias("yz"))
    xz = two.select("x_id", F.col("y_id").alias("z_id"), F.col("xy").alias("xz"))
    three = two.select("x_id", "y_id", "xy").join(yz, "y_id").join(xz, ["x_id", "z_id"])
    return pairs.crossJoin(three.agg(F.count_if(F.col("xz") > F.col("xy") + F.col("yz")).cast("long").alias("triangle")))
