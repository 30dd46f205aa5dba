"""Choice of landmarks among distinct keys."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.functions.distance import key_delta
from metricblock.functions.edit_kernel import key_matrix
from metricblock.functions.text import hash8
from metricblock.operators.clusters import drop, stored

#: Rows that exact farthest-first may pass over; each landmark costs one pass.  Up to
#: ``DRIVER_KEYS`` distinct keys the passes run on the driver.
EXACT_ROWS, EXACT_LANDMARKS, DRIVER_KEYS = 1_000_000, 500, 50_000
#: Keys that a task sends in a pass of exact farthest-first.
FARTHEST = 512
#: Tasks whose picks are merged in one.
MERGE = 32


def _place(seed: int):
    return hash8(f"lm{seed}", F.array_join("key", "|"))


def random_landmarks(keys: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """``(lm_ord, key)``: the ``n`` keys first in a hashed order; the exact number, and the same each time."""
    top = keys.select("key", _place(seed).alias("at")).orderBy("at", "key").limit(n)
    ranked = top.agg(F.array_sort(F.collect_list(F.struct("at", "key"))).alias("all")).select(F.posexplode("all").alias("lm_ord", "x"))
    return ranked.select((F.col("lm_ord") + 1).cast("int").alias("lm_ord"), F.col("x.key").alias("key"))


def farthest_first(keys: DataFrame, n: int, seed: int = 42, combine: str = "sum") -> DataFrame:
    """``(lm_ord, key, radius)``: each next landmark is the key farthest from those before.

    Starts from the first key in hashed order; ties go to the smallest such place.  ``radius`` is
    the distance at which the landmark was chosen (null for the first).  A narrow pass gives the
    farthest keys of each task; distances only fall, so the driver goes on among those until one
    that stayed in a task may be farther, then there is another pass.
    """
    spark = keys.sparkSession
    few = keys.select("key", _place(seed).alias("at")).limit(DRIVER_KEYS + 1).collect()
    if len(few) <= DRIVER_KEYS:
        few = sorted({(r["at"], tuple(r["key"])) for r in few})
        picked = _greedy([k for _, k in few], n, combine)
        return spark.createDataFrame([(i, list(k), None if far is None else int(far)) for i, (k, far) in enumerate(picked, 1)], "lm_ord int, key array<string>, radius int")
    state = stored(keys.select("key", _place(seed).cast("long").alias("at")))
    first = state.agg(F.min_by("key", F.struct("at", "key"))).first()[0]
    chosen: list[tuple] = [(1, first, None)] if first is not None else []

    def farthest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The task's ``FARTHEST`` keys, and whether it has more."""
        best: list[tuple] = []
        cut = False
        for whole in batches:
            for a in range(0, whole.num_rows, 8192):
                b = whole.slice(a, 8192)
                own, at = b.column(0).to_pylist(), b.column(1).to_pylist()
                far = key_matrix(own, [k for _, k, _ in chosen], combine).min(axis=1).astype(np.int64)
                best += [(-far[i], at[i], own[i]) for i in np.flatnonzero(far > 0)]
                best.sort(key=lambda x: x[:2])
                cut |= len(best) > FARTHEST
                best = best[:FARTHEST]
        columns = zip(*best, strict=True) if best else ((), (), ())
        kinds = (pa.int64(), pa.int64(), pa.list_(pa.string()))
        yield pa.RecordBatch.from_arrays([*(pa.array(list(c), k) for c, k in zip(columns, kinds, strict=True)), pa.array([cut and i + 1 == len(best) for i in range(len(best))], pa.bool_())], ["near", "at", "key", "cut"])

    while chosen and len(chosen) < n:
        found = state.mapInArrow(farthest, "near long, at long, key array<string>, cut boolean").collect()
        bound = min(((r["near"], r["at"]) for r in found if r["cut"]), default=None)  # keys that were left in the tasks come after this
        far, place, some = -np.array([r["near"] for r in found], dtype=np.int64), np.array([r["at"] for r in found], dtype=np.int64), [r["key"] for r in found]
        started = len(chosen)
        while len(chosen) < n and len(far) and far.max() > 0:
            i = max(np.flatnonzero(far == far.max()).tolist(), key=lambda i: (-place[i], some[i]))
            if len(chosen) > started and bound and (-far[i], place[i]) >= bound:
                break
            chosen.append((len(chosen) + 1, some[i], int(far[i])))
            far = np.minimum(far, key_matrix(some, [some[i]], combine)[:, 0].astype(np.int64))
        if len(chosen) == started or (bound is None and (not len(far) or far.max() <= 0)):
            break
    drop(state)
    return spark.createDataFrame(chosen, "lm_ord int, key array<string>, radius int")


def _greedy(keys: list[tuple], n: int, combine: str = "sum") -> list[tuple]:
    """Farthest-first over keys in memory: (key, distance at which it was chosen); ties go to the first."""
    far, at, out = np.full(len(keys), np.inf), 0, []
    while keys and len(out) < n:
        out.append((keys[at], None if not out else far[at]))
        far = np.minimum(far, key_matrix(keys, [keys[at]], combine)[:, 0])
        at = int(np.argmax(far))
        if not far[at] > 0:
            break
    return out


def farthest_first_coreset(keys: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """Farthest-first in one pass: each task picks ``n`` of its own keys; picks are merged, and the driver picks ``n`` of the last.

    The cover radius is within a constant factor of the exact one at each merge.  ``MERGE`` tasks'
    picks go to one task, until so few tasks are left; the driver gets ``n`` keys from each of those.
    """

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: list[tuple] = []
        for b in batches:
            best = [k for k, _ in _greedy(best + [tuple(k) for k in b.column(0).to_pylist()], n)]
        yield pa.RecordBatch.from_arrays([pa.array([list(k) for k in best], pa.list_(pa.string()))], ["key"])

    picked = stored(keys.select("key").mapInArrow(pick, "key array<string>"))
    while (tasks := -(-picked.count() // max(1, n))) > MERGE:
        picked = stored(picked.repartition(-(-tasks // MERGE), F.xxhash64("key")).mapInArrow(pick, "key array<string>"))
    picks = sorted({tuple(r["key"]) for r in picked.collect()})
    chosen = _greedy(picks, n)
    return keys.sparkSession.createDataFrame([(i, list(k)) for i, (k, _) in enumerate(chosen, 1)], "lm_ord int, key array<string>")


def cover_radius(keys: DataFrame, landmarks: list[list[str]], combine: str = "sum") -> DataFrame:
    """The largest distance of any key to its nearest landmark."""
    each = F.transform(F.lit(landmarks), lambda x: key_delta(F.col("key"), x, combine))
    return keys.agg(F.max(F.array_min(each)).cast("long").alias("radius"))


def choose(keys: DataFrame, n: int, how: str, seed: int = 42, combine: str = "sum") -> list[list[str]]:
    """Landmark keys in order.  "auto" is exact farthest-first where its passes are affordable, else the coreset."""
    if how == "auto":
        how = "farthest_first" if n <= EXACT_LANDMARKS and keys.count() <= EXACT_ROWS else "coreset"
    found = {"random": lambda: random_landmarks(keys, n, seed), "farthest_first": lambda: farthest_first(keys, n, seed, combine), "coreset": lambda: farthest_first_coreset(keys, n, seed)}[how]()
    return [r["key"] for r in found.orderBy("lm_ord").select("key").collect()]
