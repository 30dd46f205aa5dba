"""Suffix order, common prefixes and neighbours in it, for whole arrays at once."""

from __future__ import annotations

import numpy as np


def dense(keys: np.ndarray) -> np.ndarray:
    """Ranks from 1; equal keys have equal ranks, and 0 is left for what lies beyond the end."""
    return np.unique(keys, return_inverse=True)[1].astype(np.int64) + 1


def beyond(ranks: np.ndarray, by: int) -> np.ndarray:
    out = np.zeros_like(ranks)
    if by < len(ranks):
        out[:-by or None] = ranks[by:]
    return out


def ladder(first: np.ndarray, step: int, depth: int) -> list[tuple[int, np.ndarray]]:
    """(length, rank of every suffix by so many units), lengths doubling from ``step`` and ending with ``depth``.

    ``first`` are the ranks by ``step`` units.  The last rung joins two overlapping stretches.
    """
    rungs = [(step, first)]
    while rungs[-1][0] < depth:
        length, rank = rungs[-1]
        shift = min(length, depth - length)
        rungs.append((length + shift, dense(rank * (len(rank) + 1) + beyond(rank, shift))))
    return rungs


def common_prefix(rungs: list[tuple[int, np.ndarray]], a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Length of the common prefix of suffixes ``a`` and ``b``, up to the ladder's depth; needs rungs from 1."""
    depth = rungs[-1][0]
    far = np.where(rungs[-1][1][a] == rungs[-1][1][b], depth, 0)
    open_ = far == 0
    n = len(rungs[0][1])
    for length, rank in reversed([r for r in rungs if r[0] & (r[0] - 1) == 0]):
        rank = np.append(rank, 0)
        x, y = np.minimum(a + far, n), np.minimum(b + far, n)
        same = open_ & (rank[x] == rank[y]) & (rank[x] > 0) & (np.maximum(a, b) + far + length <= n)
        far = np.where(same, far + length, far)
    return np.minimum(far, depth)


def previous_smaller(values: np.ndarray) -> np.ndarray:
    """For each place the last place before it that holds a smaller value, or -1; pointers double."""
    at = np.arange(len(values)) - 1
    while True:
        wrong = np.flatnonzero((at >= 0) & (values[at] > values))
        if not len(wrong):
            return at
        at[wrong] = at[at[wrong]]


def next_smaller(values: np.ndarray) -> np.ndarray:
    """For each place the first place after it that holds a smaller value, or the length."""
    return len(values) - 1 - previous_smaller(values[::-1])[::-1]
