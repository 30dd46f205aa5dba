"""Removal of repeated passages of words, by prefix-partitioned suffix trees.

Suffixes are split by prefixes of variable length, each as long as it takes for its group to
fit: over the corpus by ``repeats`` (the gram at a window's anchor, a longer one where that is
too frequent), and inside a block by one, two, four ... words, small groups sharing a bin.
Each bin gives one subtree.  A subtree's internal nodes at the depth of a window or deeper are
the repeats, and their earliest leaf is the place that stays.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from metricblock.llm import suffixes
from metricblock.llm.common import released, table
from metricblock.llm.hashing import word_spans
from metricblock.llm.repeats import KEY, NO_ID, Kind, cut_stretches, keyed, repeated_stretches, unions

WIDTH = 20
GRAM = 7


def prefix_bins(rungs: list[tuple[int, np.ndarray]], starts: np.ndarray, most: int) -> Iterator[np.ndarray]:
    """``starts`` split by prefixes, small groups put together to bins of about ``most``.

    A group of more than ``most`` is split by a prefix twice as long, up to the depth.
    """
    waiting = [(0, starts)]
    while waiting:
        rung, group = waiting.pop()
        rank = rungs[rung][1][group]
        order = np.argsort(rank, kind="stable")
        group, rank = group[order], rank[order]
        borders = np.concatenate([[0], np.flatnonzero(np.diff(rank)) + 1, [len(group)]])
        sizes = np.diff(borders)
        small = sizes <= most if rung + 1 < len(rungs) else sizes > 0
        waiting += [(rung + 1, group[borders[i] : borders[i + 1]]) for i in np.flatnonzero(~small)]
        bin_of = np.repeat((np.cumsum(sizes[small]) - 1) // most, sizes[small])
        if len(bin_of):
            yield from np.split(group[np.repeat(small, sizes)], np.flatnonzero(np.diff(bin_of)) + 1)


def deep_nodes(rungs: list[tuple[int, np.ndarray]], leaves: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The leaves in suffix order, and for each internal node at full depth its first leaf and the leaf after its last.

    Neighbours in suffix order whose common prefix reaches the depth are under one node.
    """
    rank = rungs[-1][1][leaves]
    order = np.argsort(rank, kind="stable")
    deep = np.zeros(len(order) + 1, dtype=np.int8)
    deep[1:-1] = rank[order][1:] == rank[order][:-1]
    turn = np.diff(deep)
    return leaves[order], np.flatnonzero(turn == 1), np.flatnonzero(turn == -1) + 1


def later_windows(pieces: list[bytes], kind: Kind, most: int = 1 << 15) -> np.ndarray:
    """For each window of the pieces (in corpus order): is it below a deep node, and not its earliest leaf?"""
    number: dict[bytes, int] = {}
    words = [p.split(b" ") for p in pieces]
    lengths = np.array([len(w) for w in words])
    flat = np.array([number.setdefault(w, len(number)) for ws in words for w in ws], dtype=np.int64)
    rungs = suffixes.ladder(flat + 1, 1, kind.width)
    starts = np.cumsum(lengths) - lengths
    n = lengths - kind.width + 1
    windows = np.repeat(starts - (np.cumsum(n) - n), n) + np.arange(n.sum())
    found = np.zeros(len(flat), dtype=bool)
    for bin_ in prefix_bins(rungs, windows, most):
        leaves, first, end = deep_nodes(rungs, bin_)
        if not len(first):
            continue
        size = end - first
        under = np.repeat(first - (np.cumsum(size) - size), size) + np.arange(size.sum())
        earliest = np.minimum.reduceat(leaves[under], np.cumsum(size) - size)
        found[leaves[under]] = leaves[under] > np.repeat(earliest, size)
    return found[windows]


def _words_kept(digest_only: bool):
    names = ["doc_id", "n_words", "n_removed", "kept_sha256" if digest_only else "kept"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for doc, text, (firsts, lasts) in zip(b.column("doc").to_pylist(), b.column("text"), unions(b.column("cuts")), strict=True):
                data, spans = text.as_py(), list(zip(firsts.tolist(), lasts.tolist(), strict=True))
                doc = None if doc == NO_ID else doc
                if digest_only:
                    words, rest, at = data.split(), [], 0
                    for start, stop in spans:
                        rest += words[at:start]
                        at = stop
                    rest += words[at:]
                    rows.append((doc, len(words), len(words) - len(rest), hashlib.sha256(b" ".join(rest)).hexdigest()))
                else:
                    starts, ends = word_spans(np.frombuffer(data, dtype=np.uint8))
                    rest, at = [], 0
                    for start, stop in spans:  # white space before a removed stretch stays
                        rest.append(data[at : starts[start]])
                        at = int(starts[stop]) if stop < len(starts) else int(ends[-1])
                    kept = b"".join([*rest, data[at:]]) if spans else data
                    rows.append((doc, len(starts), sum(b - a for a, b in spans), kept.decode()))
            types = (pa.int64(), pa.int64(), pa.int64(), pa.string())
            columns = zip(*rows, strict=True) if rows else [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(columns, types, strict=True)], names)

    return run


def passage_kind(width: int = WIDTH) -> Kind:
    return Kind("word", width, max(1, min(GRAM, width // 3)), later=True)


def remove_repeated_passages(docs: DataFrame, width: int = WIDTH, digest_only: bool = False) -> DataFrame:
    """``(doc_id, n_words, n_removed, kept)`` for each row of ``docs(doc_id, text)``.

    Words are what ASCII white space leaves, unchanged; a null text has none.  A word goes if a
    window of ``width`` words over it also starts earlier: in a smaller doc_id, or further left
    in the same document.  ``kept`` is the text without the removed words and the white space
    after them; with ``digest_only`` the SHA-256 of the kept words joined by one space is given
    instead.  Rows that share id and text are one document and cut alike; rows that share only
    the id are ordered by a checksum; null ids come first.  An empty table gives no rows.
    """
    cuts = repeated_stretches(docs, passage_kind(width), later_windows)
    texts = docs.select("doc_id", "text")
    return cut_stretches(texts, cuts, _words_kept(digest_only), f"doc_id long, n_words long, n_removed long, {'kept_sha256' if digest_only else 'kept'} string")


def cut_texts(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """``docs`` with all its columns, ``text`` without repeated passages, and ``_n_removed`` words.

    Texts without repeats, null ones included, stay as they are.
    """
    cuts = repeated_stretches(docs, passage_kind(width), later_windows)
    key = keyed(docs, *[F.col(f"`{c}`").alias(f"_own_{c}") for c in docs.columns]).drop("text")
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = _words_kept(False)
        for b in batches:
            text = pa.array([(x.as_py() or "").encode() for x in b.column("_own_text")], pa.binary())
            out = next(kept(iter([pa.RecordBatch.from_arrays([b.column("doc"), text, b.column("cuts")], ["doc", "text", "cuts"])])))
            changed = pa.array([new if n else old.as_py() for old, new, n in zip(b.column("_own_text"), out.column("kept").to_pylist(), out.column("n_removed").to_pylist(), strict=True)], pa.string())
            yield pa.RecordBatch.from_arrays([*(changed if c == "text" else b.column(f"_own_{c}") for c in names), out.column("n_removed")], [*names, "_n_removed"])

    schema = T.StructType([*docs.schema.fields, T.StructField("_n_removed", T.LongType())])
    return key.join(cuts, KEY, "left").select("doc", "cuts", *[f"`_own_{c}`" for c in names]).mapInArrow(released(run), schema)


def op7_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeated_passages(table(spark, sf_dir, "documents"), digest_only=True)
