"""The SQL functions of the library, called from SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from metricblock import workloads as W
from metricblock.functions import sql
from metricblock.operators import vectors
from metricblock.operators.querymatch import ReferenceIndex
from metricblock.queries.distances import QUERY_PAIRS, query_pairs, r6
from metricblock.queries.methods import NAMES, SPACE, space_points
from metricblock.queries.registry import query


@query(QUERY_PAIRS + " SELECT q_id, round(jaro_similarity(a, b), 6) AS s, round(jaro_winkler_similarity(c, d), 6) AS w FROM pairs")
def rel_udf_jaro(spark, sf):
    sql.register(spark)
    query_pairs(spark, sf).createOrReplaceTempView("mb_pairs")
    return spark.sql("SELECT q_id, round(lb_jaro(a, b), 6) AS s, round(lb_jaro_winkler(c, d), 6) AS w FROM mb_pairs")


@query(SPACE + " SELECT a.label, round(sqrt(sum((d - delta) * (d - delta)) / sum(delta * delta)), 6) AS stress FROM d JOIN full_ a ON a.id = i GROUP BY a.label")
def rel_udaf_stress(spark, sf):
    """Stress by the label of a pair's first vector.

    Two blocks give one row a label, with the squared miss and size of all their pairs: of such
    rows the aggregate is that of the pairs.
    """
    parts = vectors.stress_parts(space_points(spark, sf, "label"), by=True)
    one = parts.select("label", (F.sqrt("size") + F.sqrt("miss")).alias("d"), F.sqrt("size").alias("delta"))
    return one.groupBy("label").agg(sql.stress_of_group()("d", "delta").alias("stress")).withColumn("stress", r6("stress"))


@query()
def rel_udtf_knn(spark, sf):
    """Placement and search from SQL, by a lateral table function."""
    index = ReferenceIndex.fit(W.names_ref(spark, sf), "rec_id", NAMES, K=5, L=40, landmarks="random")
    sql.register(spark, index)
    index.query_keys(W.names_query(spark, sf)).createOrReplaceTempView("mb_queries")
    return spark.sql("SELECT q.q_id, t.n_id, t.rank, t.dist FROM (SELECT q_id, lb_place(key) AS coords FROM mb_queries) q, LATERAL lb_knn(q.coords, 5) t")
