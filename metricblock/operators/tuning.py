"""Choice of dimension, landmarks and block size by true matches at a cost."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from metricblock.operators import measures
from metricblock.operators.clusters import stored
from metricblock.operators.querymatch import ReferenceIndex
from metricblock.operators.records import BlockingSpec


def tune(reference: DataFrame, queries: DataFrame, spec: BlockingSpec, Ks: Sequence[int] = (7,), Ls: Sequence[int] = (100, 300), ks: Sequence[int] = (50, 150), theta: float = 2, most_ops: float | None = None, **fit) -> DataFrame:
    """``(place, K, L, B, tp, fp, precision, ops)``, B the block size, of every setting, the best first.

    ``queries`` are a labelled sample with ``entity_id``.  Settings whose cost per query is over
    ``most_ops`` come last; of the others those with more true positives first, then the cheaper.
    """
    spark, rows = reference.sparkSession, []
    for K in Ks:
        for L in Ls:
            index = ReferenceIndex.fit(reference, "rec_id", spec, K=K, L=L, **fit)
            # the largest block holds the smaller ones
            found = stored(index.match(queries, max(ks), theta))
            for k in ks:
                r = measures.matching_report(found.where(F.col("rank") <= k), queries, reference).first()
                rows.append((K, L, k, r["tp"], r["fp"], r["precision"], index.query_ops(k)))
    table = spark.createDataFrame(rows, "K int, L int, B int, tp long, fp long, precision double, ops double")
    over = F.col("ops") > F.lit(most_ops) if most_ops is not None else F.lit(False)
    return table.withColumn("place", F.row_number().over(Window.orderBy(over, F.desc("tp"), "ops"))).select("place", *table.columns)
