"""The methods as SQL functions: ``register(spark, index)`` makes them callable from any query.

lb_jaro(a, b), lb_jaro_winkler(a, b), lb_osa(a, b), lb_qgram(a, b): values of two strings.
lb_stress(d, delta): normalized stress of a group's distances.
lb_place(key): coordinates of a blocking value (an array of strings) in the index's space.
lb_knn(coords, k): a table function, rows (n_id, rank, dist) of the index's nearest values.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from metricblock.functions.distance import _batched, _jaro, _osa, _winkler
from metricblock.functions.edit_kernel import key_matrix
from metricblock.operators.placement import place_batch
from metricblock.operators.querymatch import ReferenceIndex


def _bag(a: str, b: str, q: int = 2) -> int:
    x, y = (Counter(s[i : i + q] for i in range(len(s) - q + 1)) for s in (a, b))
    return sum(((x - y) + (y - x)).values())


def stress_of_group():
    """Normalized stress as an aggregate of two columns."""

    def run(d: pd.Series, delta: pd.Series) -> float:
        return float(np.sqrt(((d - delta) ** 2).sum() / (delta**2).sum()))

    run.__annotations__ = {"d": pd.Series, "delta": pd.Series, "return": float}
    return F.pandas_udf(run, "double")


def register(spark: SparkSession, index: ReferenceIndex | None = None) -> list[str]:
    """Register the functions with the session; those of the space need a shipped index of one space.  Returns their names."""
    spark.udf.register("lb_jaro", _batched(_jaro, "double", "float64"))
    spark.udf.register("lb_jaro_winkler", _batched(_winkler, "double", "float64"))
    spark.udf.register("lb_osa", _batched(_osa, "int", "Int32"))
    spark.udf.register("lb_qgram", _batched(_bag, "int", "Int32"))
    spark.udf.register("lb_stress", stress_of_group())
    names = ["lb_jaro", "lb_jaro_winkler", "lb_osa", "lb_qgram", "lb_stress"]
    if index is None:
        return names
    space, options, tree = index.model.spaces[0], index.model.placement, index.tree()

    def place(keys: pd.Series) -> pd.Series:
        delta = key_matrix([list(k) for k in keys], space.keys)
        y, _ = place_batch(space.coords, delta, np.zeros(len(keys), dtype=np.int64), options)
        return pd.Series(list(y))

    place.__annotations__ = {"keys": pd.Series, "return": pd.Series}

    class Nearest:
        def eval(self, coords, k: int):
            ids, dist = tree.knn(np.array(coords, dtype=float), k)
            for rank, (i, d) in enumerate(zip(ids.tolist(), dist.tolist(), strict=True), 1):
                yield i, rank, d

    spark.udf.register("lb_place", F.pandas_udf(place, "array<double>"))
    spark.udtf.register("lb_knn", F.udtf(Nearest, returnType="n_id long, rank int, dist double"))
    return [*names, "lb_place", "lb_knn"]
