import numpy as np
import pytest
from pyspark.sql import functions as F

from metricblock import experiments as X
from metricblock import workloads as W
from metricblock.operators import baselines, blocks, clusters, dedup, measures
from metricblock.operators.model import EmbeddingModel
from metricblock.operators.querymatch import ReferenceIndex, running_sum
from metricblock.operators.records import BlockingSpec, blocking_keys, check_schema
from metricblock.plans.block_plan import explain_blocks, plan_blocks
from metricblock.streaming.matching import match_batches

NAMES = BlockingSpec(("given", "surname"))


@pytest.fixture(scope="module")
def names(spark, sf):
    return W.names_ref(spark, sf, 400).cache(), W.names_query(spark, sf, 400, 60).cache()


@pytest.fixture(scope="module")
def index(names):
    return ReferenceIndex.fit(names[0], "rec_id", NAMES, K=5, L=40, landmarks="random")


def rows(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


def scanned(names, theta):
    q, r = (blocking_keys(df, i, NAMES, out=i) for df, i in ((names[1], "q_id"), (names[0], "rec_id")))
    return set(rows(baselines.scan_match(q, r, theta), "q_id", "rec_id", "delta"))


def test_matches_are_sound_and_mostly_complete(names, index):
    found = index.match(names[1], 50, 2)
    got, true = set(rows(found, "q_id", "rec_id", "delta")), scanned(names, 2)
    assert got <= true and len(got) >= 0.9 * len(true)


def test_partitioned_index_gives_the_same(names, index):
    other = ReferenceIndex(index.model, index.points, index.records, "rec_id", "partitioned")
    assert rows(other.match(names[1], 30, 2), "q_id", "rec_id", "rank") == rows(index.match(names[1], 30, 2), "q_id", "rec_id", "rank")


def test_any_threshold_gives_the_blocks(names, index):
    assert rows(index.match(names[1], 7, 10**6), "q_id", "rec_id") == rows(index.match(names[1], 7, emit="block"), "q_id", "rec_id")


def test_index_round_trip_and_growth(spark, names, index, tmp_path):
    index.save(str(tmp_path / "i"))
    again = ReferenceIndex.load(spark, str(tmp_path / "i"))
    assert rows(again.match(names[1], 20, 2), "q_id", "rec_id") == rows(index.match(names[1], 20, 2), "q_id", "rec_id")
    fresh = names[1].select((F.col("q_id") + 10_000).alias("rec_id"), "given", "surname")
    grown = index.absorb(fresh)
    hits = grown.match(names[1], 20, 0).where("rec_id > 10000 and delta = 0 and rec_id = q_id + 10000")
    assert grown.version == index.version + 1 and hits.count() == names[1].count()


def test_repeated_queries_are_answered_each(names, index):
    twice = names[1].unionByName(names[1].withColumn("q_id", F.col("q_id") + 1000))
    got = index.match_distinct(twice, 20, 2)
    assert got.count() == 2 * index.match(names[1], 20, 2).count()


def test_budget_in_seconds(names, index):
    all_, done = index.match_within(names[1], 20, 2, seconds=600, batch=40)
    assert done == 60 and rows(all_, "q_id", "rec_id") == rows(index.match(names[1], 20, 2), "q_id", "rec_id")
    assert index.match_within(names[1], 20, 2, seconds=0)[1] == 0


def test_micro_batches_see_the_newest_index(spark, names, index, tmp_path):
    names[1].select("q_id", "given", "surname").repartition(2).write.parquet(str(tmp_path / "q"))
    stream = spark.readStream.schema("q_id long, given string, surname string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "q"))
    match_batches(lambda: index, stream, lambda df, n: df.write.parquet(str(tmp_path / f"out/{n}")), str(tmp_path / "state"), 20, 2).awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out/*"))
    assert rows(got, "q_id", "rec_id") == rows(index.match(names[1], 20, 2), "q_id", "rec_id")


def test_no_nested_loop_over_distances(names, index):
    plan = index.match(names[1], 20, 2)._jdf.queryExecution().toString()
    assert "BroadcastNestedLoopJoin" not in plan and "CartesianProduct" not in plan and plan.split("== Physical Plan ==")[1].count("MapInArrow") == 1


def test_self_blocking_finds_duplicates(spark, sf):
    records = W.names_dedup(spark, sf, 400).cache()
    gold = W.gold_pairs(records)
    found = dedup.dedup(records, "rec_id", NAMES, 2, 30, 5, L=50, landmarks="random")
    report = measures.blocking_report(found.select("a", "b"), gold, 400).first()
    assert report["pc"] > 0.75 and 0 <= report["rr"] <= 1
    clustered = clusters.clusters(found, records)
    assert clustered.count() == 400 and clusters.representatives(clustered).count() < 400
    merged = dedup.iterative_er(records, "rec_id", NAMES, 2, 2, B=30, K=5, L=50, landmarks="random")
    assert merged.count() == 400


def test_clique_holds_star(spark, sf):
    near = X.self_knn(W.space7(spark, sf), 4)
    star, clique = (set(rows(blocks.block_pairs(near, m), "a", "b")) for m in ("star", "clique"))
    assert star < clique


def test_missing_values_and_schemas(spark):
    df = spark.createDataFrame([(1, None, "x"), (2, "a", None)], "id long, given string, surname string")
    assert rows(blocking_keys(df, "id", NAMES), "rec_id", "key") == [(1, ["", "x"]), (2, ["a", ""])]
    with pytest.raises(Exception, match="missing"):
        blocking_keys(df, "id", BlockingSpec(("given",), on_missing="error")).collect()
    with pytest.raises(ValueError):
        check_schema(df, df.withColumn("given", F.lit(1)), ("given",))


def test_pivots_need_a_metric(spark, names):
    with pytest.raises(ValueError):
        baselines.pivot_join(names[1], names[0], 2, [["a", "b"]], "jaro")


def test_plans():
    small, large = plan_blocks(5_000), plan_blocks(50_000_000)
    assert "shipped" in small.text() and "cells" in large.text() and "coreset" in large.text()
    with pytest.raises(ValueError):
        plan_blocks(10**6, embedding="complete")
    assert explain_blocks(small).startswith("== Method plan ==")


def test_trends(spark, sf):
    """Completeness rises and reduction falls with the block size; more landmarks cost more; harder data match less well."""
    curve = X.blocking_curve(spark, sf, n=500, Ks=(2, 6), Ls=(40,), sizes=(5, 20, 60)).orderBy("K", "B").collect()
    for K in (2, 6):
        own = [r for r in curve if r["K"] == K]
        assert all(a["pc"] <= b["pc"] and a["rr"] > b["rr"] for a, b in zip(own, own[1:], strict=False))
    assert sum(r["pc"] for r in curve if r["K"] == 6) >= sum(r["pc"] for r in curve if r["K"] == 2)
    both = X.blocking_curve(spark, sf, n=300, Ks=(5,), Ls=(60,), embeddings=("complete", "landmark"), sizes=(30,)).collect()
    assert abs(both[0]["pc"] - both[1]["pc"]) < 0.3
    got = X.matching_curve(spark, sf, n=400, Ls=(20, 80), ks=(30,), budget_s=60).orderBy("dataset", "L").collect()
    for d in ("first", "second"):
        few, many = [r for r in got if r["dataset"] == d]
        assert few["share_in_budget"] == many["share_in_budget"] == 1 and few["tp"] > 0
    none = X.matching_curve(spark, sf, ("first",), n=400, Ls=(20,), ks=(30,), budget_s=1e-6).collect()
    assert [(r["processed"], r["tp"], r["share_in_budget"]) for r in none] == [(0, 0, 0.0)]
    theta = X.blocking_curve(spark, sf, n=300, Ks=(5,), Ls=(60,), sizes=(10, 40), mode="clique").orderBy("B").collect()
    assert all(r["pc_theta"] <= r["pc"] and r["n_theta"] <= r["n_b"] for r in theta) and theta[0]["pc_theta"] <= theta[1]["pc_theta"]


def test_times_of_the_kernels_grow_with_the_landmarks(spark, sf):
    got = X.time_by_landmarks(spark, sf, n=400, q=60, Ls=(40, 160, 320)).orderBy("L").collect()
    assert got[0]["distance_s"] < got[2]["distance_s"] and got[0]["placement_s"] < got[2]["placement_s"]
    assert got[2]["placement_s"] > 2 * got[0]["placement_s"]


def test_running_sums_by_range(spark):
    rows = spark.range(0, 1000).repartition(7).withColumn("cost", F.col("id") % 13)
    got = {r["id"]: r["c"] for r in running_sum(rows, F.col("cost"), ("id",), "c").collect()}
    assert got == dict(enumerate(np.cumsum(np.arange(1000) % 13).tolist()))


def test_links_have_the_components_of_pairs(spark, sf):
    titles = W.page_titles(spark, sf)
    both = [clusters.clusters(dedup.dedup(titles, "rec_id", BlockingSpec(("title",)), 8, B=50, K=3, L=25, expand=e), titles) for e in ("pairs", "links")]
    assert sorted(map(tuple, both[0].collect())) == sorted(map(tuple, both[1].collect()))
    assert max(r["mean_ms"] for r in X.search_time(spark, sf, 400, L=30).collect()) < 20


def test_spaces_per_attribute(spark, names):
    spec = BlockingSpec(("given", "surname"), combine="split_space")
    index = ReferenceIndex.fit(names[0], "rec_id", spec, K=3, L=25, landmarks="random")
    got, true = set(rows(index.match(names[1], 60, 2), "q_id", "rec_id", "delta")), scanned(names, 2)
    assert index.model.dimension == 6 and got <= true and len(got) > 0.8 * len(true)
    assert isinstance(index.model, EmbeddingModel)


def test_tuning_ranks_by_matches_within_a_cost(names):
    from metricblock.operators.tuning import tune

    got = tune(*names, NAMES, Ks=(2, 5), Ls=(20,), ks=(5, 40), landmarks="random", most_ops=5_000).orderBy("place").collect()
    assert len(got) == 4 and got[0]["tp"] >= got[1]["tp"]
    free = tune(*names, NAMES, Ks=(2,), Ls=(20,), ks=(5, 40), landmarks="random").orderBy("place").collect()
    assert free[0]["tp"] >= free[1]["tp"]


def test_sql_functions(spark, names, index):
    from metricblock.functions.sql import register

    assert "lb_knn" in register(spark, index)
    row = spark.sql("SELECT lb_qgram('abc', 'abd') AS q, lb_osa('abcd', 'bacd') AS o, lb_jaro('x', 'x') AS j").first()
    assert (row["q"], row["o"], row["j"]) == (2, 1, 1.0)
    index.points.createOrReplaceTempView("mb_points")
    near = spark.sql("SELECT p.key_id, t.n_id, t.dist FROM mb_points p, LATERAL lb_knn(p.coords, 1) t").collect()
    assert len(near) == index.points.count() and all(r["dist"] == 0 for r in near)
