"""The published experiments as queries; no SQL form.  Trends are tested, not values."""

from __future__ import annotations

from metricblock import experiments as X
from metricblock.operators.placement import PlacementOptions
from metricblock.queries.registry import query


@query()
def exp_stress_by_dimension(spark, sf):
    return X.stress_by_dimension(spark, sf, Ks=(1, 2, 3, 5, 7, 10, 14, 20), L=300)


@query()
def exp_block_size_by_dimension(spark, sf):
    return X.blocking_curve(spark, sf, Ks=(3, 7, 10), Ls=(100,))


@query()
def exp_block_size_by_dataset(spark, sf):
    first = X.blocking_curve(spark, sf, "first", Ks=(7,), Ls=(100,))
    return first.unionByName(X.blocking_curve(spark, sf, "second", Ks=(7,), Ls=(100,)))


@query()
def exp_complete_or_landmarks(spark, sf):
    return X.blocking_curve(spark, sf, n=2_000, Ks=(7,), Ls=(100, 300, 700), embeddings=("complete", "landmark"), sizes=(30, 50, 70, 100))


@query()
def exp_clique_pairs(spark, sf):
    return X.blocking_curve(spark, sf, n=1_000, Ks=(7,), Ls=(100,), sizes=(20, 50), mode="clique")


@query()
def exp_time_by_landmarks(spark, sf):
    return X.time_by_landmarks(spark, sf, Ls=(100, 300, 700, 1500))


@query()
def exp_matches_by_landmarks(spark, sf):
    return X.matching_curve(spark, sf, Ls=(100, 300, 700), ks=(50, 100, 150))


@query()
def exp_matches_by_sgd(spark, sf):
    """The published setting with stochastic gradient descent as the placement."""
    return X.matching_curve(spark, sf, Ls=(100, 300), ks=(150,), placement=PlacementOptions(solver="sgd"))


@query()
def exp_search_time(spark, sf):
    return X.search_time(spark, sf)
