import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from metricblock import workloads as W
from metricblock.functions.distance import _osa
from metricblock.functions.edit_kernel import edit_matrix, key_matrix
from metricblock.operators import landmarks, mds
from metricblock.operators.model import EmbeddingModel, place_against_all, sweep_dimension
from metricblock.operators.placement import SOLVERS, PlacementOptions, losses, place_batch
from metricblock.operators.records import BlockingSpec, blocking_keys, key_dictionary

NAMES = BlockingSpec(("given", "surname"))


@pytest.fixture(scope="module")
def keys(spark, sf):
    return key_dictionary(blocking_keys(W.names_ref(spark, sf, 150), "rec_id", NAMES)).cache()


def points(n=40, k=3, seed=0):
    return np.random.default_rng(seed).standard_normal((n, k)) * 5


@pytest.mark.parametrize("solver", ["majorize", "gradient"])
@pytest.mark.parametrize("init", ["random", "classical"])
def test_stress_never_rises(solver, init):
    delta = np.round(mds.distances(points(k=6)))
    x, trace = mds.lsmds(delta, 3, solver, init=init)
    assert all(b <= a + 1e-9 for a, b in zip(trace, trace[1:], strict=False))
    assert mds.stress_of(delta, x, normalized=False) == pytest.approx(trace[-1], rel=1e-6)


def test_euclidean_dissimilarities_are_kept():
    delta = mds.distances(points())
    assert mds.stress_of(delta, mds.classical_mds(delta, 3)) < 1e-9
    assert mds.stress_of(delta, mds.lsmds(delta, 3)[0]) < 1e-6


def test_least_squares_beats_classical():
    delta = np.round(mds.distances(points(k=8)))
    assert mds.stress_of(delta, mds.lsmds(delta, 2)[0]) < mds.stress_of(delta, mds.classical_mds(delta, 2))


def test_missing_dissimilarities_weigh_nothing():
    delta = mds.distances(points(30))
    holes = delta.copy()
    holes[0, 5] = holes[5, 0] = holes[3, 7] = holes[7, 3] = np.nan
    x, trace = mds.lsmds(holes, 3, max_iter=500, tol=1e-9)
    assert trace[-1] <= trace[0] and mds.stress_of(delta, x) < 0.05


@given(st.floats(0, 6.28), st.floats(-9, 9))
@settings(max_examples=25, deadline=None)
def test_stress_is_blind_to_motions(angle, shift):
    x = points(12, 2)
    delta = np.ceil(mds.distances(points(12, 4, 1)))
    turn = np.array([[np.cos(angle), -np.sin(angle)], [np.sin(angle), np.cos(angle)]])
    assert mds.stress_of(delta, x @ turn + shift) == pytest.approx(mds.stress_of(delta, x))


@pytest.mark.parametrize("solver", SOLVERS)
@pytest.mark.parametrize("start", ["centroid", "nearest_landmark", "linear"])
def test_placement_finds_euclidean_points(solver, start):
    anchors, true = points(25), points(8, seed=4)
    delta = np.sqrt(((true[:, None] - anchors[None]) ** 2).sum(-1))
    options = PlacementOptions(solver, start, max_iter=400, tol=1e-9, epochs=60)
    y, loss = place_batch(anchors, delta, np.arange(8), options)
    assert np.allclose(loss, losses(y, anchors, delta))
    first = place_batch(anchors, delta, np.arange(8), PlacementOptions(solver, start, max_iter=0, epochs=0))[1]
    assert (loss <= first + 1e-9).all() and np.median(np.abs(y - true)) < 0.2


def test_placement_depends_on_the_value_only(keys):
    for solver in ("sgd", "majorize"):
        model = EmbeddingModel.fit(keys, NAMES, K=3, L=20, landmarks="random", placement=PlacementOptions(solver, "nearest_landmark"))
        one = {r["key_id"]: r["coords"] for r in model.transform(keys.repartition(1)).collect()}
        many = {r["key_id"]: r["coords"] for r in model.transform(keys.repartition(7)).collect()}
        assert all(np.allclose(one[k], many[k]) for k in one)


def test_all_landmarks_equal_all_anchors(keys):
    model = EmbeddingModel.fit(keys, NAMES, K=3, L=1000, landmarks="random", index_coords="mds")
    embedded = model.transform(keys).select("key", "coords")
    anchored = {r["key_id"]: r["loss"] for r in place_against_all(keys, embedded, model.placement).collect()}
    placed = {r["key_id"]: r["loss"] for r in EmbeddingModel(model.spec, model.spaces, model.placement, "x").transform(keys).collect()}
    assert np.allclose([placed[k] for k in anchored], list(anchored.values()), rtol=1e-6)


def test_distributed_steps_lower_the_stress(keys):
    coords, trace = mds.lsmds_distributed(keys, 4, max_iter=12)
    assert all(b <= a * (1 + 1e-9) for a, b in zip(trace, trace[1:], strict=False)) and coords.count() == keys.count()
    with pytest.raises(ValueError):
        mds.DISTRIBUTED_ROWS, keep = 10, mds.DISTRIBUTED_ROWS
        try:
            mds.lsmds_distributed(keys, 4)
        finally:
            mds.DISTRIBUTED_ROWS = keep


def test_coreset_covers_nearly_as_well(spark, keys):
    exact = landmarks.cover_radius(keys, landmarks.choose(keys, 12, "farthest_first")).first()[0]
    core = landmarks.cover_radius(keys, landmarks.choose(keys, 12, "coreset")).first()[0]
    rand = landmarks.cover_radius(keys, landmarks.choose(keys, 12, "random")).first()[0]
    assert exact <= core <= 3 * exact and exact <= rand


def plain_edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, last = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
    return row[-1]


@given(st.lists(st.text("abcé東", max_size=7), max_size=8), st.lists(st.text("abcé東", max_size=7), max_size=5))
@settings(max_examples=150, deadline=None)
def test_edit_matrix(values, targets):
    got = edit_matrix(values, targets)
    assert got.tolist() == [[plain_edits(a, b) for b in targets] for a in values]


def test_long_strings_and_combinations():
    assert edit_matrix(["a" * 300, ""], ["a" * 299 + "b", "x" * 400]).tolist() == [[1, 400], [300, 400]]
    keys, marks = [["ab", "c"], ["", "cd"]], [["abc", "d"]]
    assert key_matrix(keys, marks).tolist() == [[2], [4]]
    assert key_matrix(keys, marks, "weighted", (2.0, 0.5)).tolist() == [[2.5], [6.5]]
    assert key_matrix(keys, marks, "concat").tolist() == [[2], [3]]


def test_farthest_first_in_passes_equals_the_driver(keys, monkeypatch):
    small = landmarks.farthest_first(keys, 6).orderBy("lm_ord").collect()
    monkeypatch.setattr(landmarks, "DRIVER_KEYS", 10)
    assert landmarks.farthest_first(keys, 6).orderBy("lm_ord").collect() == small


def test_model_round_trip(spark, keys, tmp_path):
    model = EmbeddingModel.fit(keys, BlockingSpec(("given", "surname"), combine="split_space"), K=2, L=10, landmarks="random")
    model.save(spark, str(tmp_path / "m"))
    again = EmbeddingModel.load(spark, str(tmp_path / "m"))
    assert again.model_id == model.model_id and again.dimension == 4
    a, b = ({r["key_id"]: r["coords"] for r in m.transform(keys).collect()} for m in (model, again))
    assert a == b


def test_stress_falls_with_the_dimension(keys):
    rows = [r["stress"] for r in sweep_dimension(keys, (1, 2, 4, 8), L=80, init="classical").orderBy("k").collect()]
    assert all(b < a for a, b in zip(rows, rows[1:], strict=False)) and rows[2] - rows[3] < rows[0] - rows[1]


@given(st.text("abc", max_size=6), st.text("abc", max_size=6))
def test_swaps_cost_one(a, b):
    assert _osa(a, b) == _osa(b, a) and (_osa(a, b) == 0) == (a == b)
    if len(a) > 1 and a[0] != a[1]:
        assert _osa(a, a[1] + a[0] + a[2:]) == 1
