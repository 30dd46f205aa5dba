import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from metricblock.operators import knn
from metricblock.operators.trees import KDTree, PartitionTree, RTree, SearchStats


def brute(x, ids, q, k):
    d = np.sqrt(((x - q) ** 2).sum(axis=1))
    order = np.lexsort((ids, d))[:k]
    return ids[order].tolist(), d[order]


@given(st.integers(0, 150), st.integers(1, 4), st.integers(1, 12), st.integers(0, 10_000))
@settings(max_examples=120, deadline=None)
def test_trees_equal_the_scan(n, dims, k, seed):
    rng = np.random.default_rng(seed)
    x = rng.integers(0, 6, (n, dims)).astype(float)  # many ties
    ids = rng.permutation(n)
    for tree in (KDTree.build(x, ids, leaf_size=4), KDTree.build(x, ids, 4, "widest"), RTree.pack(x, ids, 4, 3)):
        q = rng.integers(0, 6, dims).astype(float)
        got, d = tree.knn(q, k)
        want, e = brute(x, ids, q, k) if n else ([], np.zeros(0))
        assert got.tolist() == want and np.allclose(d, e)
        inside, _ = tree.within(q, 2.0)
        assert sorted(inside.tolist()) == sorted(ids[np.sqrt(((x - q) ** 2).sum(axis=1)) <= 2.0].tolist() if n else [])


def test_branches_are_pruned():
    x = np.random.default_rng(0).random((20_000, 3))
    stats = SearchStats()
    KDTree.build(x, np.arange(20_000)).knn(x[5], 10, stats=stats)
    assert stats.distances < 2_000


@given(st.integers(1, 200), st.integers(1, 9), st.integers(0, 1000))
@settings(max_examples=60, deadline=None)
def test_cells_part_the_space(n, cells, seed):
    x = np.random.default_rng(seed).integers(0, 5, (n, 2)).astype(float)
    tree = PartitionTree.fit(x, cells)
    cell = tree.assign(x)
    assert cell.min() >= 0 and cell.max() < tree.cells <= max(1, cells)
    assert (cell == tree.assign(x[::-1])[::-1]).all()


@pytest.mark.parametrize("k", [1, 7, 300])
def test_partitioned_join_is_exact(spark, k):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((250, 3)) * [1, 5, 1]
    points = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, coords array<double>")
    queries = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.standard_normal((40, 3)) * 8)], "id long, coords array<double>")
    want = {(r["q_id"], r["rank"]): r["n_id"] for r in knn.knn_join(queries, points, k, "scan").collect()}
    for strategy, how in (("partitioned", {"cells": 9}), ("broadcast", {}), ("rtree", {})):
        assert {(r["q_id"], r["rank"]): r["n_id"] for r in knn.knn_join(queries, points, k, strategy, **how).collect()} == want


def test_probes_trade_recall(spark):
    x = np.random.default_rng(3).standard_normal((400, 4))
    points = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, coords array<double>")
    true = {(r["q_id"], r["n_id"]) for r in knn.self_knn(points, 5, strategy="scan").collect()}
    found = [len(true & {(r["q_id"], r["n_id"]) for r in knn.self_knn(points, 5, strategy="partitioned", cells=8, probes=p).collect()}) for p in (1, 3, 8)]
    assert found[0] <= found[1] <= found[2] == len(true)


def test_large_trees_are_not_shipped(spark):
    points = spark.range(1000).selectExpr("id", "array(cast(id as double)) as coords")
    with pytest.raises(ValueError):
        knn.collected(points, limit_bytes=1000)
    assert knn.knn_join(points.limit(0), points, 3, "partitioned").count() == 0
