"""Measures of blocking and matching, each a one-row DataFrame or a column."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def reduction_ratio(pairs: int | Column, n: int | Column, convention: str = "paper") -> Column:
    """Share of comparisons avoided.  "paper" divides by n (n - 1), "unordered" by half of that."""
    n = n if isinstance(n, Column) else F.lit(n)
    pairs = pairs if isinstance(pairs, Column) else F.lit(pairs)
    n = n.cast("double")  # the product of two whole numbers may be too large for one
    all_ = n * (n - 1) / (1.0 if convention == "paper" else 2.0)
    return F.when(all_ > 0, 1 - pairs / all_)


def blocking_report(pairs: DataFrame, gold: DataFrame, n: int) -> DataFrame:
    """``n_b, found, gold, rr, rr_unordered, pc, pq, f1`` of distinct candidate pairs (a, b), a < b."""
    detected = pairs.join(gold.select("a", "b"), ["a", "b"], "left_semi").agg(F.count("*").alias("found"))
    counts = pairs.agg(F.count("*").alias("n_b")).crossJoin(detected).crossJoin(gold.agg(F.count("*").alias("gold")))
    pc = F.when(F.col("gold") > 0, F.col("found") / F.col("gold"))
    pq = F.when(F.col("n_b") > 0, F.col("found") / F.col("n_b"))
    rows = counts.withColumns({"rr": reduction_ratio(F.col("n_b"), n), "rr_unordered": reduction_ratio(F.col("n_b"), n, "unordered"), "pc": pc, "pq": pq})
    return rows.withColumn("f1", F.when(F.col("pc") + F.col("pq") > 0, 2 * F.col("pc") * F.col("pq") / (F.col("pc") + F.col("pq"))))


def duplicate_rate(records: DataFrame, entity: str = "entity_id", rec: str = "rec_id") -> DataFrame:
    """Duplicates (records beyond the first of their entity) over all records."""
    return records.agg((F.lit(1.0) - F.count_distinct(entity) / F.count(rec)).alias("dmr"))


def query_match_rates(queries: DataFrame, reference: DataFrame) -> DataFrame:
    """Queries' matched entities over the reference's size, and queries with a match over all queries."""
    known = reference.select("entity_id").distinct().withColumn("known", F.lit(1))
    seen = queries.join(known, "entity_id", "left").agg(F.count_distinct(F.when(F.col("known") == 1, F.col("entity_id"))).alias("entities"), F.count("known").alias("with_match"), F.count("*").alias("queries"))
    both = seen.crossJoin(reference.agg(F.count("*").alias("n")))
    return both.select((F.col("entities") / F.col("n")).alias("qmr_reference"), (F.col("with_match") / F.col("queries")).alias("qmr_query"))


def matching_report(matches: DataFrame, queries: DataFrame, reference: DataFrame) -> DataFrame:
    """``processed, tp, fp, precision, recall`` over the processed ``queries(q_id, entity_id)``."""
    found = matches.join(queries.select("q_id", "entity_id"), "q_id").join(reference.select("rec_id", F.col("entity_id").alias("rec_entity")), "rec_id")
    right = F.coalesce(F.col("entity_id") == F.col("rec_entity"), F.lit(False))
    hits = found.agg(F.count_if(right).alias("tp"), F.count_if(~right).alias("fp"))
    asked = queries.agg(F.count("*").alias("processed"), F.count("entity_id").alias("answerable"))
    return asked.crossJoin(hits).select("processed", "tp", "fp", F.when(F.col("tp") + F.col("fp") > 0, F.col("tp") / (F.col("tp") + F.col("fp"))).alias("precision"), F.when(F.col("answerable") > 0, F.col("tp") / F.col("answerable")).alias("recall"))


def knn_recall(found: DataFrame, true: DataFrame) -> DataFrame:
    """Share of the true (q_id, n_id) that were found."""
    hit = true.join(found.select("q_id", "n_id").withColumn("hit", F.lit(1)), ["q_id", "n_id"], "left")
    return hit.agg((F.count("hit") / F.count("*")).alias("recall"))


def operation_counts(n: int, l: int, q: int, k: int) -> dict[str, float]:
    """Machine-independent costs: distances of either embedding, of the scan and of matching."""
    import math

    return {
        "complete_deltas": n * (n - 1) / 2,
        "landmark_deltas": l * (l - 1) / 2 + l * (n - l),
        "scan_deltas_per_query": float(n),
        "match_deltas_per_query": float(l),
        "search_steps_per_query": k * math.log2(max(n, 2)),
        "query_deltas": float(q * l),
    }
