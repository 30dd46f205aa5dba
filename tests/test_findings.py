"""What a reviewer's runs on odd inputs and larger tables found."""

import math

import pytest
from pyspark.sql import functions as F

from metricblock.queries.all import ORACLE_SQL, QUERIES


def test_small_negatives_keep_their_sign_when_rounded(spark, tmp_path):
    import duckdb

    path = f"{tmp_path}/embeddings.parquet"
    spark.createDataFrame([(1, [-1e-6, 0.25, -0.5]), (2, [1e-6, -2.5e-6]), (3, [])], "vec_id long, embedding array<float>").coalesce(1).write.parquet(path)
    got = {r["vec_id"]: (r["positive"], repr(r["twice"])) for r in QUERIES["rel_arr_hof"](spark, str(tmp_path)).collect()}
    sql = ORACLE_SQL["rel_arr_hof"].replace("FROM embeddings", f"FROM '{path}/*.parquet'")
    assert got == {i: (n, repr(x)) for i, n, x in duckdb.connect().execute(sql).fetchall()}
    assert math.copysign(1, QUERIES["rel_arr_hof"](spark, str(tmp_path)).where("vec_id = 1").first()["twice"][0]) == -1


def test_wide_keys_hang_on_the_fingerprint_alone():
    import numpy as np

    from metricblock.llm.simhash import _wide_keys

    prints = np.random.default_rng(0).integers(0, 1 << 63, (50, 8)).astype(np.uint64)
    row, key = _wide_keys(prints)
    few_row, few_key = _wide_keys(prints[:5])
    assert sorted(key[row < 5].tolist()) == sorted(few_key.tolist()) and set(few_row) == set(range(5))


def test_edit_kernel_finds_all_within_a_threshold():
    import numpy as np

    from metricblock.functions.edit_kernel import EditTargets, edit_matrix

    rng = np.random.default_rng(1)

    def word(most):
        return "".join(rng.choice(list("ab cé日"), rng.integers(0, most)))

    keys = [[word(90), word(6)] for _ in range(40)] + [["", ""]]
    targets = [[word(90), word(6)] for _ in range(40)] + [["", ""]] + [[k[0][1:] + "a", k[1]] for k in keys[:10]]
    full = sum(edit_matrix([k[p] for k in keys], [t[p] for t in targets]) for p in (0, 1))
    for theta in (0, 3, 40, 1000):
        want = {(int(i), int(j), int(full[i, j])) for i, j in zip(*np.nonzero(full <= theta), strict=True)}
        assert {tuple(map(int, x)) for x in zip(*EditTargets(targets).close(keys, theta), strict=True)} == want


def test_full_blocks_are_filtered_where_they_are_searched(spark):
    import numpy as np

    from metricblock.operators import knn

    words = ["ab", "abc", "abd", "xyz", "ab", "", "abcd"]
    rows = [(i, [float(i % 3), 0.0], [w]) for i, w in enumerate(words)]
    points = spark.createDataFrame(rows, "id long, coords array<double>, key array<string>")
    got = {tuple(r) for r in knn.search_full(points, points, 1, include_self=False).select("q_id", "n_id", "rank", "delta").collect()}
    near = knn.self_knn(points.select("id", "coords"), 100, strategy="scan").collect()
    rank = {(r["q_id"], r["n_id"]): r["rank"] for r in near}
    import metricblock.functions.edit_kernel as e

    full = e.edit_matrix(words, words)
    assert got == {(a, b, rank[a, b], int(full[a, b])) for a, b in rank if full[a, b] <= 1} and np.unique([r[2] for r in got]).size > 1


def test_limit_queries_write_no_full_blocks(spark, sf):
    for name in ("dedup_limit_landmark", "dedup_clusters", "dedup_representatives", "match_link_limit", "match_repeat_queries", "base_all_pairs"):
        plan = QUERIES[name](spark, sf)._jdf.queryExecution().toString()
        assert "levenshtein" not in plan, name


def test_complete_embedding_sends_no_literal_of_all_keys(spark, sf):
    from metricblock.operators import mds

    keys = spark.createDataFrame([(i, ["a" * (i % 7) + "b" * (i % 3)]) for i in range(60)], "key_id long, key array<string>").dropDuplicates(["key"])
    coords, trace = mds.lsmds_distributed(keys, 2, max_iter=8)
    assert coords.count() == keys.count() and all(b <= a * (1 + 1e-9) for a, b in zip(trace, trace[1:], strict=False))
    assert mds.ROWS_AT_ONCE * 78_000 * 8 * 7 * 2 < 400e6  # a slice of rows against all of a large table stays small


VECTOR_QUERIES = ["dist_minkowski_p1", "dist_minkowski_p2", "dist_minkowski_p3", "dist_minkowski_inf", "stress_normalized", "stress_distortion", "mds_majorize_step", "rel_udaf_stress"]


def test_all_pairs_of_vectors_as_in_sql(spark, tmp_path, monkeypatch):
    """Over several blocks, with copies, missing components in one vector and a null label; no pair is a row of a join."""
    import duckdb
    import numpy as np

    from metricblock.operators import vectors
    from metricblock.operators.pairwise import packed

    monkeypatch.setattr(vectors, "packed", lambda df, rows=0: packed(df, 16))
    x = np.random.default_rng(5).standard_normal((70, 9)).round(3).tolist()
    rows = [(i * 3, v, i % 4) for i, v in enumerate([*x, x[0], x[1]])]
    path = f"{tmp_path}/embeddings.parquet"
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(3).write.parquet(path)
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{path}/*.parquet'")
    for name in VECTOR_QUERIES:
        df = QUERIES[name](spark, str(tmp_path))
        assert "BroadcastNestedLoop" not in df._jdf.queryExecution().toString()
        got = sorted(tuple(round(v, 5) for v in r) for r in df.collect())
        columns = ", ".join(f'"{c}"' for c in df.columns)
        want = sorted(tuple(round(v, 5) for v in r) for r in duck.execute(f"SELECT {columns} FROM ({ORACLE_SQL[name]})").fetchall())
        assert len(got) == len(want) and np.allclose(got, want, atol=2e-5), name
    odd = f"{tmp_path}/odd/embeddings.parquet"
    spark.createDataFrame([(1, [1.0, None, 2.0]), (2, [0.5, 3.0, 1.0]), (3, [4.0]), (4, [1.5, 2.0, 3.0])], "vec_id long, embedding array<float>").coalesce(1).write.parquet(odd)
    for name in VECTOR_QUERIES[:4]:
        got = sorted(map(tuple, QUERIES[name](spark, f"{tmp_path}/odd").collect()))
        assert got == sorted(duck.execute(ORACLE_SQL[name].replace("FROM embeddings", f"FROM '{odd}/*.parquet'")).fetchall()), name


def test_scan_keeps_the_nearest_over_blocks(spark):
    import numpy as np

    from metricblock.operators import knn

    rng = np.random.default_rng(0)
    x = rng.integers(0, 9, (2500, 3)).astype(float)  # many ties
    points = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "id long, coords array<double>").repartition(3)
    asked = points.where("id % 25 = 0")
    for own in (True, False):
        df = knn.knn_join(asked, points, 7, "scan", include_self=own)
        assert "Cartesian" in df._jdf.queryExecution().toString()  # of blocks
        got = {(r["q_id"], r["rank"]): r["n_id"] for r in df.collect()}
        for q in range(0, 2500, 25):
            d = np.sqrt(((x - x[q]) ** 2).sum(axis=1))
            d[q] = d[q] if own else np.inf
            assert [got[q, r] for r in range(1, 8)] == np.lexsort((np.arange(2500), d))[:7].tolist()


def test_searches_of_groups_equal_single_ones():
    import numpy as np

    from metricblock.operators.trees import KDTree, RTree

    rng = np.random.default_rng(0)
    for n, dims, k in ((0, 2, 3), (1, 1, 2), (150, 3, 12), (400, 3, 1000), (900, 4, 10)):
        x, ids = rng.integers(0, 6, (n, dims)).astype(float), rng.permutation(n)
        for tree in (KDTree.build(x, ids, 4), RTree.pack(x, ids, 4, 3)):
            for own in (None, ids):
                for i, (got, d) in enumerate(tree.knn_many(x, k, own)):
                    want, e = tree.knn(x[i], k, None if own is None else int(own[i]))
                    assert got.tolist() == want.tolist() and np.allclose(d, e)
            for i, (got, _) in enumerate(tree.within_many(x, 2.0)):
                assert got.tolist() == tree.within(x[i], 2.0)[0].tolist()


def test_block_size_curve_counts_a_pair_once(spark, sf):
    plan = QUERIES["wl_block_size_curve"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Generate explode") < plan.index("min(rank")  # the grid is laid over counts, not over pairs


def test_reduction_ratio_of_many_records(spark):
    from metricblock.operators.measures import reduction_ratio

    n = 102_564
    assert spark.range(1).select(reduction_ratio(5, n).alias("r")).first()["r"] == pytest.approx(1 - 5 / (n * (n - 1)))
    assert spark.range(1).select(reduction_ratio(5, F.lit(4_000_000_000)).alias("r")).first()["r"] == pytest.approx(1)


def test_complete_embeddings_are_not_refused(spark, sf, monkeypatch):
    from metricblock.operators import mds

    monkeypatch.setattr(mds, "DRIVER_ROWS", 10)
    monkeypatch.setattr(mds, "DISTRIBUTED_ROWS", 10)
    for name in ("embed_complete", "embed_distributed"):
        assert QUERIES[name](spark, sf).count() > 10


def test_all_pairs_are_rounded_and_dealt_where_they_are_measured(spark, tmp_path):
    """Against SQL with ids that repeat in several files, short vectors and null components; rounding is no step of its own."""
    import random

    import duckdb

    rng = random.Random(7)
    rows = [(i % 90, [rng.choice([rng.random(), k / 128, -3e-7, None][: 4 - (k % 5 > 0)]) for k in range(rng.choice([6, 6, 6, 3]))]) for i in range(200)]
    path = f"{tmp_path}/embeddings.parquet"
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(3).write.parquet(path)
    for p in ("p1", "p2", "p3", "inf"):
        df = QUERIES[f"dist_minkowski_{p}"](spark, str(tmp_path))
        assert "round(" not in df._jdf.queryExecution().toString()
        want = duckdb.connect().execute(ORACLE_SQL[f"dist_minkowski_{p}"].replace("FROM embeddings", f"FROM '{path}/*.parquet'")).fetchall()
        assert sorted(map(tuple, df.collect()), key=str) == sorted(want, key=str), p


def test_tasks_get_equal_shares_of_blocks(spark):
    from collections import Counter

    import pyarrow as pa

    from metricblock.operators import pairwise

    tasks = pairwise.parallel(spark.range(1))
    blocks = pairwise.packed(spark.range(2 * tasks).repartition(3), 1)

    def work(x, y, same):
        from pyspark import TaskContext

        yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()]), pa.array([x]), pa.array([y])], ["task", "x", "y"])

    met = pairwise.meet(blocks, blocks, lambda some: some["id"][0].as_py(), work, "task long, x long, y long").collect()
    assert len({(r["x"], r["y"]) for r in met}) == len(met) == 4 * tasks * tasks
    shares = Counter(task for task, _ in {(r["task"], r["x"]) for r in met})
    assert len(shares) == tasks and set(shares.values()) == {2}


def test_bits_of_words_give_the_edit_distances(monkeypatch):
    import numpy as np

    from metricblock.functions import edit_kernel as e

    rng = np.random.default_rng(3)
    words = ["", *("".join(rng.choice(list("ab cé日"), n)) for n in (1, 2, 63, 64, 65, 127, 128, 129, 200, *rng.integers(0, 90, 60)))]
    far = [[e._by_rows(*e.encoded([a]), *e.encoded([b]))[0] if a else len(b) for b in words] for a in words]
    for abreast in (1 << 13, 7):
        monkeypatch.setattr(e, "ABREAST", abreast)
        assert (e._by_bits(*e.encoded(words), *e.encoded(words)) == far).all()
    many = words * 20
    assert (e.edit_matrix(many, words) == far * 20).all() and (e.edit_matrix(words, many) == np.transpose(far * 20)).all()


def test_complete_embedding_measures_a_pair_once(spark, monkeypatch):
    """Its steps are those of plain majorization, over several groups and pieces of rows and with keys at one place."""
    import numpy as np

    from metricblock.operators import mds

    words = sorted({f"{'ab' * (i % 9)}{i % 13:04b}{'c' * (i % 4)}" for i in range(400)})
    n, tables, stored = len(words), [], mds.stored
    monkeypatch.setattr(mds, "stored", lambda df, **how: tables.append(stored(df, **how)) or tables[-1])
    monkeypatch.setattr(mds, "drop", lambda df: None)
    monkeypatch.setattr(mds, "MEASURED", 17, raising=False)
    keys = spark.createDataFrame([(i, [w]) for i, w in enumerate(words)], "key_id long, key array<string>")
    coords, trace = mds.lsmds_distributed(keys, 3, max_iter=5, tol=-1)
    held = tables[0].select(F.sum(F.length(tables[0].columns[-1]))).first()[0]
    assert held < 0.75 * n * n  # a byte a pair; a group and itself both ways
    delta = mds.landmark_delta([[w] for w in words])
    x, want = np.random.default_rng(42).standard_normal((n, 3)) * 4, []
    for _ in range(5):
        d = mds.distances(x)
        want.append(((d - delta) ** 2).sum())
        ratio = np.divide(delta, d, out=np.zeros_like(d), where=d > 0)
        x = (ratio.sum(axis=1)[:, None] * x - ratio @ x) / n
    got = dict(coords.select("key_id", "coords").collect())
    assert np.allclose(trace, want) and np.allclose([got[i] for i in range(n)], mds.aligned(x))
    mine, theirs, miss = mds._pulled(x[:2], np.vstack([x[1:2], x[:40]]), np.full((2, 41), 5))
    assert np.isfinite(mine).all() and np.isfinite(theirs).all() and np.isfinite(miss)


def test_limit_of_complete_embedding_is_not_refused(spark, sf, monkeypatch):
    from metricblock.operators import mds

    monkeypatch.setattr(mds, "DRIVER_ROWS", 10)
    monkeypatch.setattr(mds, "DISTRIBUTED_ROWS", 10)
    got, want = (sorted(map(tuple, QUERIES[name](spark, sf).select("a", "b", "delta").collect())) for name in ("dedup_limit_complete", "base_all_pairs"))
    assert got == want and got


def test_boxes_of_targets_and_of_points_spare_most_work(spark):
    """Ranks in a full block are those of all points sorted, ties and the query's own point included; few points are measured."""
    import numpy as np

    from metricblock.functions.edit_kernel import EditTargets, edit_matrix
    from metricblock.operators.trees import KDTree, Ranks

    rng = np.random.default_rng(2)
    x, ids = rng.integers(0, 12, (3000, 3)).astype(float), rng.permutation(5000)[:3000]
    tree = KDTree.build(x, ids)
    ranks, looked = Ranks(tree), []
    measure = ranks._far
    ranks._far = lambda q, at: looked.append(len(at)) or measure(q, at)
    for q in range(0, 3000, 100):
        at = tree.points[q]
        far = ((tree.points - at) ** 2).sum(axis=1)
        some = rng.permutation(np.argsort(far)[:200])[:40]
        for without in (None, int(tree.ids[q]), 9999):
            kept = some[tree.ids[some] != without]
            every = np.lexsort((tree.ids, far))
            every = every[tree.ids[every] != without].tolist()
            got, dist = ranks.of(at, kept, without)
            assert got.tolist() == [1 + every.index(s) for s in kept] and np.allclose(dist, np.sqrt(far[kept]))
    assert max(looked) < 1500
    words = [["".join(rng.choice(list("abcdefghij"), 8)), "xy"[: i % 3]] for i in range(2000)]
    targets = EditTargets(words)
    assert (targets.ends - targets.starts).max() <= 64 and targets.ends[-1] == 2000
    full = sum(edit_matrix([w[p] for w in words[:50]], [w[p] for w in words]) for p in (0, 1))
    got = {tuple(map(int, r)) for r in zip(*targets.close(words[:50], 4), strict=True)}
    assert got == {(int(i), int(j), int(full[i, j])) for i, j in zip(*np.nonzero(full <= 4), strict=True)} and len(got) > 50


def test_few_files_of_queries_are_searched_by_many_tasks(spark, sf):
    assert "RoundRobinPartitioning" in QUERIES["match_link_limit"](spark, sf)._jdf.queryExecution().toString()


def test_exact_farthest_first_takes_few_passes(spark, monkeypatch):
    import numpy as np

    from metricblock.operators import landmarks

    rng = np.random.default_rng(4)
    keys = spark.createDataFrame([(["".join(rng.choice(list("abcd"), rng.integers(1, 12))), "xyz"[: i % 4]],) for i in range(900)], "key array<string>").repartition(5)
    want = sorted(map(tuple, landmarks.farthest_first(keys, 40).collect()))
    monkeypatch.setattr(landmarks, "DRIVER_KEYS", 10)
    for most in (512, 12, 1):
        monkeypatch.setattr(landmarks, "FARTHEST", most, raising=False)
        assert sorted(map(tuple, landmarks.farthest_first(keys, 40).collect())) == want
    same = spark.createDataFrame([(["a"],)] * 30 + [(["b"],)] * 30, "key array<string>")
    assert landmarks.farthest_first(same, 9).count() == 2
    monkeypatch.setattr(landmarks, "FARTHEST", 512)
    jobs, run = [], type(keys).mapInArrow
    monkeypatch.setattr(type(keys), "mapInArrow", lambda self, *how: jobs.append(1) or run(self, *how))
    landmarks.farthest_first(keys, 40)
    assert 1 <= len(jobs) <= 5
