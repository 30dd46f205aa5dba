"""Rolling hashes over whole buffers, by prefix sums in arithmetic modulo 2**64."""

from __future__ import annotations

import numpy as np

BASE = 0x9E3779B97F4A7C15 | 5  # odd, so that it has an inverse
INVERSE = pow(BASE, -1, 1 << 64)
LENGTH = np.uint64(0xD6E8FEB86659FD93)
_powers: dict[int, np.ndarray] = {}
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True


def powers(base: int, n: int) -> np.ndarray:
    """``base`` to the powers 0 to n - 1; kept for the process, so buffers should be of bounded size."""
    if len(_powers.get(base, ())) < n:
        x = np.full(max(n, 1 << 16), base, dtype=np.uint64)
        x[0] = 1
        _powers[base] = np.multiply.accumulate(x)
    return _powers[base][:n]


def mixed(x: np.ndarray) -> np.ndarray:
    """Every bit of the result depends on all bits (the public splitmix64 finaliser)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def prefixes(units: np.ndarray) -> np.ndarray:
    """Of n units the n + 1 sums from which ``spans`` hashes any stretch."""
    out = np.zeros(len(units) + 1, dtype=np.uint64)
    np.cumsum(units.astype(np.uint64) * powers(BASE, len(units)), out=out[1:])
    return out


def spans(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of the stretches; equal stretches have equal hashes wherever they are."""
    back = powers(INVERSE, len(sums))
    return mixed((sums[ends] - sums[starts]) * back[starts] + (ends - starts).astype(np.uint64) * LENGTH)


def word_spans(data: np.ndarray, between: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of what ``between`` (ASCII white space) leaves of a byte buffer."""
    inside = np.zeros(len(data) + 2, dtype=np.int8)
    inside[1:-1] = ~between[data]
    turn = np.diff(inside)
    return np.flatnonzero(turn == 1), np.flatnonzero(turn == -1)


def word_hashes(data: np.ndarray, between: np.ndarray = SPACE, at_once: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Starts and hashes of the words of a byte buffer, in slices cut between words."""
    starts, hashes, a = [], [], 0
    while a < len(data):
        b = min(len(data), a + at_once)
        while b < len(data) and not between[data[b]]:
            gap = np.flatnonzero(between[data[b : b + at_once]])
            b += int(gap[0]) if len(gap) else min(at_once, len(data) - b)
        s, e = word_spans(data[a:b], between)
        starts.append(s + a)
        hashes.append(spans(prefixes(data[a:b].astype(np.uint64) + np.uint64(1)), s, e))
        a = b
    if not starts:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.uint64)
    return np.concatenate(starts), np.concatenate(hashes)
