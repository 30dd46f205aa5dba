"""Edit distances of many strings to many others at once, as one dynamic program over arrays.

For numbers of calls at which the row-wise function of the JVM takes the most time: placing all
values of a table measures each against every landmark.  Code points are compared, as there.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

#: Pairs worked on at once: their rows of the program stay in cache.
AT_ONCE = 1 << 18
#: Values worked on at once as words of bits, and bytes of their letters' masks.
ABREAST, MASK_BYTES = 8192, 32 << 20


def encoded(values: Sequence[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points (position x value, zero beyond the end) and lengths."""
    lengths = np.array([len(v) for v in values], dtype=np.int64)
    most = int(lengths.max()) if len(lengths) else 0
    if not most:
        return np.zeros((0, len(values)), dtype=np.uint32), lengths
    codes = np.array([v.replace("\0", "�") for v in values], dtype=f"<U{most}").view(np.uint32).reshape(len(values), most)
    return np.ascontiguousarray(codes.T.astype(np.uint8) if codes.max() < 256 else codes.T), lengths


def edit_matrix(values: Sequence[str], targets: Sequence[str]) -> np.ndarray:
    """Edit distances, values x targets."""
    out = np.zeros((len(values), len(targets)), dtype=np.int32)
    if not len(values) or not len(targets):
        return out
    codes, lengths = encoded(values)
    aims, aim_lengths = encoded(targets)
    # nanoseconds a pair, as measured: by cells of the program, or by letters and words of bits with a share of the calls
    cells, letters = 0.8 * len(codes) * len(aims), 16 * (0.45 + 800 / min(ABREAST, max(len(values), len(targets))))
    if len(values) >= len(targets) and letters * aim_lengths.mean() * (1 + len(codes) // 64) < cells:
        return _by_bits(codes, lengths, aims, aim_lengths)
    if len(values) < len(targets) and letters * lengths.mean() * (1 + len(aims) // 64) < cells:
        return _by_bits(aims, aim_lengths, codes, lengths).T
    kind = np.uint8 if max(len(codes), len(aims)) < 255 else np.int32
    step = max(1, AT_ONCE // len(values))
    every = np.arange(len(values))
    for a in range(0, len(targets), step):
        aim, size = aims[:, a : a + step], aim_lengths[a : a + step]
        rows = np.empty((len(codes) + 1, aim.shape[1], len(values)), dtype=kind)
        rows[:] = np.arange(len(codes) + 1, dtype=kind)[:, None, None]
        for j in range(int(size.max()) + 1):
            if j:
                diagonal = rows[0].copy()
                rows[0] = j
                letter = aim[j - 1][:, None]
                for k in range(1, len(codes) + 1):
                    change = diagonal + (codes[k - 1] != letter)
                    diagonal = rows[k].copy()
                    np.minimum(rows[k], rows[k - 1], out=rows[k])
                    rows[k] += 1
                    np.minimum(rows[k], change, out=rows[k])
            done = np.flatnonzero(size == j)
            if len(done):
                out[:, a + done] = rows[lengths[:, None], done[None, :], every[:, None]]
    return out


def _by_bits(codes: np.ndarray, lengths: np.ndarray, aims: np.ndarray, aim_lengths: np.ndarray) -> np.ndarray:
    """The same with a column of the program as bits of words, for many values at once; a target's letters come one after the other.

    A bit says whether the distance rises (``up``) or falls (``down``) from a row to the next; the last column's bits sum up to the distance.
    """
    out = np.zeros((len(lengths), len(aim_lengths)), dtype=np.int32)
    one, last, full = np.uint64(1), np.uint64(63), ~np.uint64(0)
    width = max(1, min(ABREAST, MASK_BYTES // (8 * (len(np.unique(codes)) + 1) * (1 + len(codes) // 64))))
    for a in range(0, len(lengths), width):
        size = lengths[a : a + width]
        own, m = codes[: max(1, int(size.max())), a : a + width], len(size)
        words = max(1, -(-len(own) // 64))
        alphabet = np.unique(own)
        masks = np.zeros((len(alphabet) + 1, words, m), dtype=np.uint64)  # the last row is for letters that no value has
        for k in range(len(own)):
            real = np.flatnonzero(k < size)
            masks[np.searchsorted(alphabet, own[k, real]), k // 64, real] |= one << np.uint64(k % 64)
        used = np.clip(size[None, :] - 64 * np.arange(words)[:, None], 0, 64)
        valid = np.where(used == 64, full, (one << (used % 64).astype(np.uint64)) - one)
        up, down = np.empty((words, m), dtype=np.uint64), np.empty((words, m), dtype=np.uint64)
        along, fall, rise = (np.empty(m, dtype=np.uint64) for _ in range(3))
        for j, n in enumerate(aim_lengths.tolist()):
            up[:], down[:] = full, 0
            place = np.searchsorted(alphabet, aims[:n, j])
            known = place < len(alphabet)
            known[known] = alphabet[place[known]] == aims[:n, j][known]
            for at in np.where(known, place, len(alphabet)).tolist():
                carried = None  # what rises and falls from the word before
                for w in range(words):
                    same, u, d = masks[at, w], up[w], down[w]
                    np.bitwise_or(same, d, out=along)
                    if carried:
                        same = same | carried[1]
                    np.bitwise_and(same, u, out=fall)
                    np.add(fall, u, out=fall)
                    np.bitwise_xor(fall, u, out=fall)
                    np.bitwise_or(fall, same, out=fall)
                    np.bitwise_or(fall, u, out=rise)
                    np.invert(rise, out=rise)
                    np.bitwise_or(rise, d, out=rise)
                    np.bitwise_and(fall, u, out=fall)
                    before, carried = carried, (rise >> last, fall >> last) if w + 1 < words else None
                    np.add(rise, rise, out=rise)
                    np.bitwise_or(rise, before[0] if before else one, out=rise)
                    np.add(fall, fall, out=fall)
                    if before:
                        np.bitwise_or(fall, before[1], out=fall)
                    np.bitwise_or(along, rise, out=u)
                    np.invert(u, out=u)
                    np.bitwise_or(u, fall, out=u)
                    np.bitwise_and(along, rise, out=d)
            out[a : a + m, j] = n + (np.bitwise_count(up & valid).astype(np.int32) - np.bitwise_count(down & valid)).sum(axis=0)
    return out


def key_matrix(keys: Sequence[Sequence[str]], landmarks: Sequence[Sequence[str]], combine: str = "sum", weights: Sequence[float] | None = None) -> np.ndarray:
    """Dissimilarities of keys (several attributes each) to landmarks; repeated attribute values are measured once."""
    if combine == "concat":
        return _once([" ".join(k) for k in keys], [" ".join(x) for x in landmarks])
    parts = len(landmarks[0]) if landmarks else 0
    total = np.zeros((len(keys), len(landmarks)))
    for i in range(parts):
        each = _once([k[i] or "" for k in keys], [x[i] or "" for x in landmarks])
        total += each * (weights[i] if combine == "weighted" and weights else 1.0)
    return total


def _once(values: list[str], targets: list[str]) -> np.ndarray:
    different: dict[str, int] = {}
    at = np.array([different.setdefault(v, len(different)) for v in values], dtype=np.int64)
    aims: dict[str, int] = {}
    to = np.array([aims.setdefault(t, len(aims)) for t in targets], dtype=np.int64)
    found = edit_matrix(list(different), list(aims))
    return found[at][:, to].astype(float) if len(values) and len(targets) else np.zeros((len(values), len(targets)))


#: Letters are counted in this many classes: merged classes make the bound looser, never wrong.
CLASSES = 32
WORD = 64
#: Targets whose counts share a box.
LEAF = 64


def _bags(codes: np.ndarray, lengths: np.ndarray, kind: type) -> np.ndarray:
    """How many letters of each class, classes x values."""
    n = len(lengths)
    real = np.arange(len(codes))[:, None] < lengths[None, :]
    at = (codes.astype(np.int64) % CLASSES * n + np.arange(n)[None, :])[real]
    return np.bincount(at, minlength=CLASSES * n).reshape(CLASSES, n).astype(kind)


def _boxed(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order of rows in which those of like counts follow one another, and where boxes of them start: split at medians of the widest column."""
    done, stack = [], [np.arange(len(counts))] if len(counts) else []
    while stack:
        own = stack.pop()
        x = counts[own]
        spread = x.max(axis=0) - x.min(axis=0)
        if len(own) <= LEAF or not spread.any():
            done.append(own)
            continue
        x = x[:, int(np.argmax(spread))]
        middle = np.partition(x, len(x) // 2)[len(x) // 2]
        below = x < middle if (x < middle).any() else x <= middle
        stack += [own[below], own[~below]]
    return np.concatenate([np.zeros(0, dtype=np.int64), *done]), np.cumsum([0, *(len(x) for x in done[:-1])]) if done else np.zeros(0, dtype=np.int64)


def spread(starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The numbers of all ranges, one after the other."""
    sizes = ends - starts
    return np.arange(sizes.sum()) + np.repeat(starts - np.cumsum(sizes) + sizes, sizes)


def _by_rows(a: np.ndarray, m: np.ndarray, b: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Edit distances of pairs of any length, one row of the program after the other: letters (position x pair) and lengths."""
    rows = np.repeat(np.arange(len(a) + 1, dtype=np.int32)[:, None], len(m), axis=1)
    every = np.arange(len(m))
    out = m.astype(np.int32).copy()
    for j in range(1, int(n.max()) + 1 if len(n) else 0):
        diagonal = rows[0].copy()
        rows[0] = j
        for k in range(1, len(a) + 1):
            change = diagonal + (a[k - 1] != b[j - 1])
            diagonal = rows[k].copy()
            rows[k] = np.minimum(np.minimum(rows[k], rows[k - 1]) + 1, change)
        done = n == j
        out[done] = rows[m, every][done]
    return out


class EditTargets:
    """Keys (lists of strings) that many others are compared with, exactly and within a threshold.

    The distance is the sum over attributes.  A pair is measured only if lengths and counted
    letters allow the threshold, first those of boxes of targets; then the program's columns are worked on as bits of one word,
    for all pairs at once.  Longer values go row by row.
    """

    def __init__(self, keys: Sequence[Sequence[str]]):
        self.parts = len(keys[0]) if len(keys) else 0
        every = [encoded([k[p] or "" for k in keys]) for p in range(self.parts)]
        self.total = sum((n for _, n in every), np.zeros(len(keys), dtype=np.int64))
        self.kind = np.int8 if not len(keys) or self.total.max() < 127 else np.int32
        counts = np.concatenate([np.zeros((0, len(keys)), dtype=self.kind), *(_bags(c, n, self.kind) for c, n in every)]).T.copy()
        self.order, self.starts = _boxed(counts)
        self.counts, self.ends = counts[self.order], np.append(self.starts[1:], len(keys))
        self.low, self.high = (f.reduceat(self.counts, self.starts, axis=0) if len(keys) else self.counts for f in (np.minimum, np.maximum))
        self.lengths = [n[self.order] for _, n in every]
        self.alphabets = [np.unique(c) for c, _ in every]
        self.codes = [c[:, self.order] for c, _ in every]
        self.places = [np.searchsorted(a, c).astype(np.int32) for a, c in zip(self.alphabets, self.codes, strict=True)]

    def close(self, keys: Sequence[Sequence[str]], theta: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Which key, which target, and their distance, of all pairs at most ``theta`` apart."""
        none = np.zeros(0, dtype=np.int64)
        if not len(keys) or not len(self.total) or theta < 0:
            return none, none, none
        found = []
        step = max(1, min(256, (1 << 22) // (max(len(a) for a in self.alphabets) + 1)))
        for a in range(0, len(keys), step):
            i, j, delta = self._some(keys[a : a + step], theta)
            found.append((i + a, self.order[j], delta))
        return tuple(np.concatenate(x) for x in zip(*found, strict=True))

    def _some(self, keys: Sequence[Sequence[str]], theta: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        every = [encoded([k[p] or "" for k in keys]) for p in range(self.parts)]
        total = sum((n for _, n in every), np.zeros(len(keys), dtype=np.int64))
        kind = self.kind if total.max() < 127 else np.int32
        mine = np.concatenate([_bags(c, n, kind) for c, n in every]).T
        low, high = (x.astype(kind, copy=False) for x in (self.low, self.high))

        def excess(x: np.ndarray, y: np.ndarray) -> np.ndarray:
            """How many letters x has over y, by attributes."""
            return np.maximum(x - y, kind(0)).reshape(-1, self.parts, CLASSES).sum(axis=2, dtype=kind)

        rows, at = [], []
        for i in range(len(keys)):
            q = mine[i]
            boxes = np.flatnonzero(np.maximum(excess(low, q), excess(q, high)).sum(axis=1, dtype=np.int64) <= theta)
            near = spread(self.starts[boxes], self.ends[boxes])
            more = excess(self.counts[near].astype(kind, copy=False), q)
            shift = np.stack([every[p][1][i] - self.lengths[p][near] for p in range(self.parts)], axis=1)
            near = near[np.maximum(more, more + shift).sum(axis=1, dtype=np.int64) <= theta]
            rows.append(np.full(len(near), i))
            at.append(near)
        i, j = np.concatenate(rows), np.concatenate(at)
        delta = np.zeros(len(i), dtype=np.int64)
        for a in range(0, len(i), AT_ONCE):
            for p in range(self.parts):
                delta[a : a + AT_ONCE] += self._edits(p, *every[p], i[a : a + AT_ONCE], j[a : a + AT_ONCE])
        ok = delta <= theta
        return i[ok], j[ok], delta[ok]

    def _edits(self, p: int, codes: np.ndarray, lengths: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        out = np.where(lengths[i] == 0, self.lengths[p][j], lengths[i])
        long = lengths[i] > WORD
        if long.any():
            x, y = i[long], j[long]
            out[long] = _by_rows(codes[: lengths[x].max(), x], lengths[x], self.codes[p][: max(1, self.lengths[p][y].max()), y], self.lengths[p][y])
        words = np.flatnonzero((lengths[i] > 0) & ~long)
        if not len(words):
            return out
        alphabet, most = self.alphabets[p], min(WORD, len(codes))
        of = np.arange(len(lengths))
        masks = np.zeros((len(lengths), len(alphabet) + 1), dtype=np.uint64)
        for k in range(most):
            place = np.searchsorted(alphabet, codes[k])
            known = (k < lengths) & (place < len(alphabet))
            known[known] = alphabet[place[known]] == codes[k][known]
            masks[of[known], place[known]] |= np.uint64(1 << k)
        words = words[np.argsort(-self.lengths[p][j[words]], kind="stable")]
        x, y = i[words], j[words]
        size = self.lengths[p][y]
        top = np.uint64(1) << (lengths[x] - 1).astype(np.uint64)
        score = lengths[x].copy()
        up, down = np.full(len(x), ~np.uint64(0)), np.zeros(len(x), dtype=np.uint64)
        one = np.uint64(1)
        for t in range(int(size[0])):
            n = int(np.searchsorted(-size, -t))  # pairs whose target has a letter here come first
            same = masks[x[:n], self.places[p][t, y[:n]]]
            u, d = up[:n], down[:n]
            across = (((same & u) + u) ^ u) | same
            rise, fall = d | ~(across | u), u & across
            score[:n] += (rise & top[:n]) != 0
            score[:n] -= (fall & top[:n]) != 0
            rise, fall = (rise << one) | one, fall << one
            along = same | d
            up[:n], down[:n] = fall | ~(along | rise), rise & along
        out[words] = score
        return out
