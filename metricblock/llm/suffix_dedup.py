"""Removal of long byte strings that occur more than once, by longest previous factors.

In suffix order, the longest earlier match of a suffix is with the previous or the next suffix
that starts further left in the text; those two come from one pass over the suffix array.  So
the array of longest previous factors says at once which stretches repeat something earlier.
The same array of the text's mirror order (neighbours that start further right) says what
repeats something later, which the query's contract counts as well.

A corpus is reduced to the stretches that may matter by ``repeats``; suffix arrays are built
over those, block by block.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from metricblock.llm import suffixes
from metricblock.llm.common import table
from metricblock.llm.repeats import NO_ID, Kind, cut_stretches, repeated_stretches, unions

WIDTH = 400
GRAM = 128


def longest_factors(units: np.ndarray, depth: int, later: bool = False) -> np.ndarray:
    """For each position the length, up to ``depth``, of the longest string from there that also starts earlier (or ``later``).

    In suffix order the longest match with an earlier start is with one of two neighbours: the
    last suffix before it, or the first after it, that starts further left.
    """
    if not len(units):
        return np.zeros(0, dtype=np.int64)
    rungs = suffixes.ladder(suffixes.dense(units), 1, max(2, depth))
    order = np.argsort(rungs[-1][1], kind="stable")
    starts = -order if later else order
    best = np.zeros(len(units), dtype=np.int64)
    for at in (suffixes.previous_smaller(starts), suffixes.next_smaller(starts)):
        has = (at >= 0) & (at < len(order))
        best[order[has]] = np.maximum(best[order[has]], suffixes.common_prefix(rungs, order[has], order[at[has]]))
    return np.minimum(best, depth)


def longest_previous_factors(data: bytes) -> np.ndarray:
    """For each position the length of the longest string from there that also starts earlier."""
    return longest_factors(np.frombuffer(data, dtype=np.uint8).astype(np.int64), 1 << max(1, len(data) - 1).bit_length())


def repeated_windows(pieces: list[bytes], kind: Kind) -> np.ndarray:
    """For each window of the pieces: is its longest previous factor (or, unless ``later``, next factor) as long as it?

    Ranks at the depth of a window say whether a common prefix is that long, so the suffixes are
    ordered to that depth only and the neighbours that start further left (right) are compared
    by rank; whole lengths, as ``longest_factors`` gives them, take five times as long.
    """
    data = np.frombuffer(b"".join(pieces) + bytes(8), dtype=np.uint8).astype(np.uint64)
    word = np.zeros(len(data) - 8, dtype=np.uint64)
    step = min(8, 1 << (kind.width.bit_length() - 1))
    for i in range(step):
        word = word << np.uint64(8) | data[i : i + len(word)]
    rank = suffixes.ladder(suffixes.dense(word), step, kind.width)[-1][1]
    lengths = np.array([len(p) for p in pieces])
    starts = np.cumsum(lengths) - lengths
    n = lengths - kind.width + 1
    windows = np.repeat(starts - (np.cumsum(n) - n), n) + np.arange(n.sum())
    order = windows[np.argsort(rank[windows], kind="stable")]
    depth = rank[order]
    found = np.zeros(len(rank), dtype=bool)
    for values in (order,) if kind.later else (order, -order):
        for at in (suffixes.previous_smaller(values), suffixes.next_smaller(values)):
            has = np.flatnonzero((at >= 0) & (at < len(order)))
            found[order[has[depth[at[has]] == depth[has]]]] = True
    return found[windows]


def _kept(digest_only: bool):
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256" if digest_only else "kept"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for doc, text, (starts, stops) in zip(b.column("doc").to_pylist(), b.column("text"), unions(b.column("cuts")), strict=True):
                data = text.as_py()
                rest, at = [], 0
                for start, stop in zip(starts.tolist(), stops.tolist(), strict=True):
                    rest.append(data[at:start])
                    at = stop
                kept = b"".join([*rest, data[at:]])
                rows.append((None if doc == NO_ID else doc, len(data), len(data) - len(kept), len(starts), hashlib.sha256(kept).hexdigest() if digest_only else kept))
            types = (pa.int64(),) * 4 + (pa.string() if digest_only else pa.binary(),)
            columns = zip(*rows, strict=True) if rows else [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(columns, types, strict=True)], names)

    return run


def remove_repeated_bytes(docs: DataFrame, width: int = WIDTH, keep_first: bool = True, digest_only: bool = False) -> DataFrame:
    """``(doc_id, n_bytes, n_removed, n_spans, kept)`` for each row of ``docs(doc_id, text)``.

    Texts are UTF-8 bytes, null is empty, matches never cross documents.  A byte goes if a
    string of ``width`` bytes over it also starts earlier (in a smaller doc_id, or further left
    in the same document); with ``keep_first=False`` also if it starts later.  What repeats is
    judged on the input, and the rest is put together.  ``kept`` is binary, since a cut may fall
    inside a character; with ``digest_only`` its SHA-256 is given instead.  Rows that share id
    and text are cut alike; rows that share only the id are ordered by a checksum; null ids come
    first.  Texts shorter than ``width`` stay whole.  An empty table gives no rows.
    """
    kind = Kind("byte", width, max(1, min(GRAM, width // 3)), later=keep_first)
    cuts = repeated_stretches(docs, kind, repeated_windows)
    texts = docs.select("doc_id", "text")
    return cut_stretches(texts, cuts, _kept(digest_only), f"doc_id long, n_bytes long, n_removed long, n_spans long, {'kept_sha256 string' if digest_only else 'kept binary'}")


def op4_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeated_bytes(table(spark, sf_dir, "documents"), keep_first=False, digest_only=True)
