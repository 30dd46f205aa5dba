"""Headline queries at one scale: ``python bench.py`` prints one JSON line.

``BENCH_SF_DIR`` names the tables, ``BENCH_CPUS`` the cores.  Each query is timed once after one
small warm-up of the session; ``checks`` holds the quality that goes with a time.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession


def session() -> SparkSession:
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = session()
    from metricblock import workloads as W
    from metricblock.experiments import NAMES
    from metricblock.operators import baselines, dedup, knn, measures
    from metricblock.operators.clusters import stored
    from metricblock.operators.model import EmbeddingModel
    from metricblock.operators.querymatch import ReferenceIndex
    from metricblock.operators.records import blocking_keys, key_dictionary
    from metricblock.queries.all import QUERIES

    QUERIES["rel_scan_parquet"](spark, sf).collect()
    times: dict[str, float] = {}
    checks: dict[str, float] = {}

    def timed(name, run):
        began = time.perf_counter()
        out = run()
        times[name] = round(time.perf_counter() - began, 3)
        return out

    reference = timed("names_reference_5000", lambda: stored(W.names_ref(spark, sf)))
    asked = stored(W.names_query(spark, sf))
    index = timed("fit_index_5000_L100_K7", lambda: ReferenceIndex.fit(reference, "rec_id", NAMES, K=7, L=100, landmarks="farthest_first"))
    index.tree()
    found = timed("match_500_k150_L100", lambda: stored(index.match(asked, 150, 2)))
    report = measures.matching_report(found, asked, reference).first()
    checks |= {"true_positives_of_500": report["tp"], "precision": round(report["precision"], 4), "queries_a_second": round(500 / times["match_500_k150_L100"], 1)}
    q, r = blocking_keys(asked, "q_id", NAMES, out="q_id"), blocking_keys(reference, "rec_id", NAMES)
    timed("scan_500_x_5000", lambda: baselines.scan_match(q, r, 2).count())
    timed("pivot_join_500_x_5000", lambda: baselines.pivot_join(q, r, 2, [["arbitrary", "stone"], ["thousand", "other"], ["tion", "ingredient"], ["eastern", "hand"]]).count())

    records = stored(W.names_dedup(spark, sf))
    pairs = timed("dedup_5000_B50_L300", lambda: stored(dedup.dedup(records, "rec_id", NAMES, 2, 50, 7, L=300, landmarks="coreset")))
    gold = W.gold_pairs(records)
    checks["dedup_pairs_found"] = pairs.join(gold, ["a", "b"], "left_semi").count()
    checks["dedup_pairs_gold"] = gold.count()

    everyone = timed("dictionary_all_names", lambda: stored(key_dictionary(blocking_keys(W.names_all(spark, sf).selectExpr("xxhash64(given, surname) as id", "given", "surname"), "id", NAMES))))
    checks["all_names"] = everyone.count()
    model = timed("train_all_names_L100", lambda: EmbeddingModel.fit(everyone, NAMES, K=7, L=100, landmarks="coreset"))
    points = timed("place_all_names_L100", lambda: stored(model.transform(everyone).selectExpr("key_id as id", "coords")))
    checks["placed_a_second"] = round(checks["all_names"] / times["place_all_names_L100"])
    space = points.select("id", "coords")
    few = stored(space.where("pmod(id, 100) = 0"))
    timed("knn_tree_all_names_k50", lambda: knn.knn_join(few, space, 50, "broadcast").count())
    timed("knn_cells_all_names_k50", lambda: knn.knn_join(few, space, 50, "partitioned", cells=16).count())
    for name in ("stress_normalized", "landmarks_farthest_first", "base_key_multi", "rel_join_sort_merge", "rel_agg_cube", "rel_win_row_number", "stream_tumbling"):
        timed(name, lambda name=name: QUERIES[name](spark, sf).write.format("noop").mode("overwrite").save())

    print(json.dumps({"metric": "seconds for the headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "checks": checks, "sf": sf}))


if __name__ == "__main__":
    main()
