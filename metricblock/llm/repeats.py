"""Stretches that occur more than once in a corpus, exactly, without sorting every suffix.

A window is ``width`` consecutive units (bytes or words) of one document.  Among the shorter
grams inside a window, the one of least hash is its anchor.  The anchor depends on the window's
content alone, so equal windows have equal anchors, at equal places.  Neighbouring windows
mostly share their anchor; together they are a run.  Only runs travel:

1. each task hashes the runs of its documents (gram ``a``, whole stretch ``u``), and settles
   runs whose stretch it has seen before;
2. runs whose gram is nowhere else are dropped; those whose whole stretch is elsewhere are
   settled; no task ever holds all runs of a gram here, counts come by partial sums;
3. grams around which different stretches occur are left: there one copy of each different
   stretch is fetched, and a solver (suffix array or suffix tree) compares their windows;
4. where a gram has more different stretches than a task should hold, the stretches go through
   the same steps with longer grams, and so on; the last are as long as the window, and leave
   nothing to compare.

Nothing is sampled or capped, and the rows at every step grow with the repeated text only.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.llm.common import drop, released, stored, text_of
from metricblock.llm.hashing import INVERSE, mixed, powers, prefixes, word_hashes

PLACE_BITS = 26
CHUNK = 1 << 18
FLUSH = 1 << 19
NO_ID = -(1 << 63)
KEY = ["doc", "tag"]
KEYED = b"repeated stretches"


@dataclass(frozen=True)
class Kind:
    """``unit``: "byte" or "word".  ``later``: only what starts earlier counts, so first places stay."""

    unit: str
    width: int
    gram: int
    later: bool
    group_up_to: int = 256

    def longer(self) -> Kind | None:
        """The same with longer grams: a quarter of the places for an anchor in a window."""
        places = self.width - self.gram + 1
        return replace(self, gram=self.width - max(1, places // 4) + 1) if places > 1 else None


def least_places(grams: np.ndarray, span: int) -> np.ndarray:
    """For each start the place of the least of ``span`` grams from there; ties go to the first."""
    n = len(grams)
    place = np.uint64((1 << PLACE_BITS) - 1)
    v = (grams & ~place) | np.arange(n, dtype=np.uint64)
    if span == 1:
        return np.arange(n)
    full = -(-n // span) * span
    padded = np.full(full, np.iinfo(np.uint64).max, dtype=np.uint64)
    padded[:n] = v
    blocks = padded.reshape(-1, span)
    ahead = np.minimum.accumulate(blocks, axis=1).reshape(-1)
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    out = np.minimum(behind[: n - span + 1], ahead[span - 1 : n])
    return (out & place).astype(np.int64)


def runs(units: np.ndarray, lengths: np.ndarray, kind: Kind) -> tuple[np.ndarray, ...]:
    """Runs in documents laid end to end: gram, stretch, document's position, start, stop (in the document)."""
    w, k = kind.width, kind.gram
    none = np.zeros(0, dtype=np.int64)
    if len(units) < w:
        return none.astype(np.uint64), none.astype(np.uint64), none, none, none
    sums = prefixes(units)
    grams = mixed((sums[k:] - sums[:-k]) * powers(INVERSE, len(sums) - k))
    place = least_places(grams, w - k + 1)
    doc = np.repeat(np.arange(len(lengths)), lengths)
    starts = np.flatnonzero(doc[: len(place)] == doc[w - 1 :])
    if not len(starts):
        return none.astype(np.uint64), none.astype(np.uint64), none, none, none
    at = place[starts]
    new = np.flatnonzero((at[1:] != at[:-1]) | (starts[1:] != starts[:-1] + 1)) + 1
    first = starts[np.concatenate([[0], new])]
    stop = starts[np.concatenate([new - 1, [len(starts) - 1]])] + w
    own = doc[first]
    base = (np.cumsum(lengths) - lengths)[own]
    return grams[place[first]], digests(units, first, stop), own, first - base, stop - base


def digests(units: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """BLAKE2b of whole stretches, 64 bits: no two different ones can be made to agree.

    Two stretches count as equal only if their anchors' hashes agree as well.
    """
    if units.max() <= 256:
        units = (units - np.uint64(1)).astype(np.uint8)
    data, size, digest = memoryview(units.tobytes()), units.itemsize, hashlib.blake2b
    found = b"".join([digest(data[a:b], digest_size=8, key=KEYED).digest() for a, b in zip((starts * size).tolist(), (stops * size).tolist(), strict=True)])
    return np.frombuffer(found, dtype=np.uint64)


def _chunks(batches: Iterator[pa.RecordBatch], kind: Kind) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Units of several texts end to end, and for each of them: key, checksum, offset, copies, length."""
    held: list[tuple[int, int, int, int, bytes]] = []
    size = 0
    for b in batches:
        for doc, tag, base, m, text in zip(*(c.to_pylist() for c in b.columns[:4]), b.column(4), strict=True):
            data = text.as_py()
            held.append((doc, tag, base, m, data))
            size += len(data)
            if size >= CHUNK:
                yield from _laid(held, kind)
                held, size = [], 0
    if held:
        yield from _laid(held, kind)


def _laid(held: list[tuple[int, int, int, int, bytes]], kind: Kind) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """A text longer than a chunk comes in parts that overlap by a window less one unit."""
    if kind.unit == "byte":
        parts = [np.frombuffer(h[4], dtype=np.uint8) for h in held]
    else:
        flat = np.frombuffer(b" ".join(h[4] for h in held), dtype=np.uint8)
        starts, hashes = word_hashes(flat)
        ends = np.cumsum([len(h[4]) + 1 for h in held])
        parts = np.split(hashes, np.searchsorted(starts, ends[:-1]))
    units, about, total = [], [], 0

    def flush() -> tuple[np.ndarray, np.ndarray]:
        x = np.concatenate(units).astype(np.uint64)
        out = (x + np.uint64(1) if kind.unit == "byte" else x), np.array(about, dtype=np.int64)
        units.clear()
        about.clear()
        return out

    for (doc, tag, base, m, _), part in zip(held, parts, strict=True):
        for at in range(0, max(1, len(part) - kind.width + 1), CHUNK):
            piece = part[at : at + CHUNK + kind.width - 1]
            if len(piece) < kind.width:
                continue
            units.append(piece)
            about.append((doc, tag, base + at, m, len(piece)))
            total += len(piece)
            if total >= 2 * CHUNK:
                yield flush()
                total = 0
    if units:
        yield flush()


def _settled_here(a, u, doc, tag, base, start, stop, copies, later: bool) -> Iterator[pa.RecordBatch]:
    """One row for each stretch seen; its other places are settled now (``a`` is null there)."""
    order = np.lexsort((start, tag, doc, u))
    a, u, doc, tag, base, start, stop, copies = (x[order] for x in (a, u, doc, tag, base, start, stop, copies))
    if later:  # rows that share id and text are one document
        fresh = np.ones(len(u), dtype=bool)
        fresh[1:] = (u[1:] != u[:-1]) | (doc[1:] != doc[:-1]) | (tag[1:] != tag[:-1]) | (start[1:] != start[:-1])
        a, u, doc, tag, base, start, stop, copies = (x[fresh] for x in (a, u, doc, tag, base, start, stop, copies))
    lead = np.ones(len(u), dtype=bool)
    lead[1:] = u[1:] != u[:-1]
    at = np.flatnonzero(lead)
    n = np.minimum(np.add.reduceat(copies, at), 2)
    yield _rows(a[at].view(np.int64), u[at].view(np.int64), doc[at], tag[at], base[at], start[at], stop[at], n)
    if len(at) < len(u):
        doc, tag, start, stop = merged(*(x[~lead] for x in (doc, tag, start, stop)))
        none = np.zeros(len(doc), dtype=np.int64)
        yield _rows(None, None, doc, tag, none, start, stop, none)


def _rows(a, u, doc, tag, base, start, stop, n) -> pa.RecordBatch:
    empty = pa.nulls(len(doc), pa.int64())
    columns = [empty if a is None else pa.array(a), empty if u is None else pa.array(u), pa.array(doc), pa.array(tag), *(pa.array(x.astype(np.int32)) for x in (base, start, stop, n))]
    return pa.RecordBatch.from_arrays(columns, ["a", "u", "doc", "tag", "base", "start", "stop", "n"])


def merged(doc, tag, start, stop) -> tuple[np.ndarray, ...]:
    """Stretches of documents, those that touch put together."""
    order = np.lexsort((stop, start, tag, doc))
    doc, tag, start, stop = (x[order] for x in (doc, tag, start, stop))
    new_doc = np.ones(len(doc), dtype=bool)
    new_doc[1:] = (doc[1:] != doc[:-1]) | (tag[1:] != tag[:-1])
    # the furthest stop so far in the document: shift documents apart so that one running maximum serves all
    group = np.cumsum(new_doc) - 1
    apart = np.int64(stop.max() + 1) if len(stop) else np.int64(1)
    reach = np.maximum.accumulate(stop + group * apart) - group * apart
    new = new_doc.copy()
    new[1:] |= start[1:] > reach[:-1]
    at = np.flatnonzero(new)
    last = np.append(at[1:], len(doc)) - 1
    return doc[at], tag[at], start[at], reach[last] if len(at) else stop[:0]


RUNS = "a long, u long, doc long, tag int, base int, start int, stop int, n int"


def _run_rows(kind: Kind):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0
        for units, about in _chunks(batches, kind):
            a, u, own, start, stop = runs(units, about[:, 4], kind)
            doc, tag, base, copies, _ = about[own].T
            held.append((a, u, doc, tag.astype(np.int32), base, start + base, stop + base, copies))
            size += len(a)
            if size >= FLUSH:
                yield from _settled_here(*map(np.concatenate, zip(*held, strict=True)), kind.later)
                held, size = [], 0
        if size:
            yield from _settled_here(*map(np.concatenate, zip(*held, strict=True)), kind.later)

    return run


def _pieces(kind: Kind):
    """Fetched stretches, as bytes (words joined by one space)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[list] = [[] for _ in range(7)]
            for doc, tag, base, text, wanted in zip(*(b.column(c).to_pylist() for c in ("doc", "tag", "base")), b.column("text"), b.column("wanted"), strict=True):
                data = text.as_py()
                units = data if kind.unit == "byte" else data.split()
                for x in wanted.as_py():
                    piece = units[x["start"] - base : x["stop"] - base]
                    row = (x["a"], doc, tag, x["start"], x["m"], x["hot"], piece if kind.unit == "byte" else b" ".join(piece))
                    for column, value in zip(out, row, strict=True):
                        column.append(value)
            types = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.bool_(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out, types, strict=True)], ["a", "doc", "tag", "start", "m", "hot", "piece"])

    return run


PIECES = "a long, doc long, tag int, start int, m long, hot boolean, piece binary"
STRETCHES = "doc long, tag int, start int, stop int"
#: Of every window of the pieces in turn (pieces in corpus order): is it a repeat?
Solver = Callable[[list[bytes], "Kind"], np.ndarray]


def _solved(kind: Kind, solver: Solver, block_bytes: int = 1 << 18):
    """Stretches of the pieces' windows that count as repeats; all pieces of a gram are in one block."""

    def solve(rows: list[tuple]) -> pa.RecordBatch:
        rows.sort(key=lambda r: r[1:4])
        repeated = solver([r[5] for r in rows], kind)  # of each window in turn: does it count?
        counts = np.array([(len(r[5]) if kind.unit == "byte" else r[5].count(b" ") + 1) - kind.width + 1 for r in rows])
        own = np.repeat(np.arange(len(rows)), counts)
        nth = np.arange(len(own)) - np.repeat(np.cumsum(counts) - counts, counts)
        if not kind.later:  # stretches with copies are settled already
            repeated = repeated & (np.array([r[4] for r in rows]) == 1)[own]
        own, nth = own[repeated], nth[repeated]
        start = np.array([r[3] for r in rows], dtype=np.int64)[own] + nth
        found = merged(np.array([r[1] for r in rows], dtype=np.int64)[own], np.array([r[2] for r in rows], dtype=np.int32)[own], start, start + kind.width)
        return pa.RecordBatch.from_arrays([pa.array(found[0]), pa.array(found[1]), pa.array(found[2].astype(np.int32)), pa.array(found[3].astype(np.int32))], ["doc", "tag", "start", "stop"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        size = 0
        for b in batches:
            for row in zip(*(b.column(c).to_pylist() for c in ("a", "doc", "tag", "start", "m", "piece")), strict=True):
                if size >= block_bytes and row[0] != rows[-1][0]:
                    yield solve(rows)
                    rows, size = [], 0
                rows.append(row)
                size += len(row[5])
        if rows:
            yield solve(rows)

    return run


def keyed(docs: DataFrame, *more: str) -> DataFrame:
    """Whole texts as UTF-8 with the key of a document: its id, and a checksum in case ids repeat."""
    data = text_of().cast("binary")
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc"), F.crc32(data).bitwiseAND(0x7FFFFFFF).cast("int").alias("tag"), data.alias("text"), *more)


def repeated_stretches(docs: DataFrame, kind: Kind, solver: Solver) -> DataFrame:
    """``(doc, tag, cuts)``: for each document with repeats its stretches (start, stop) to remove, in units."""
    texts = keyed(docs).select(*KEY, F.lit(0).alias("base"), F.lit(1).cast("long").alias("m"), "text")
    found: list[DataFrame] = []
    level: Kind | None = kind
    while level:
        settled, firsts = _settled(texts, level)
        found.append(settled)
        wanted = firsts.groupBy(*KEY, "base").agg(F.collect_list(F.struct("a", "start", "stop", "m", "hot")).alias("wanted"))
        pieces = stored(texts.join(wanted, [*KEY, "base"]).dropDuplicates([*KEY, "base"]).mapInArrow(released(_pieces(level)), PIECES))
        cool = pieces.where("not hot").select("a", *KEY, "start", "m", "piece")
        found.append(cool.repartition("a").sortWithinPartitions("a").mapInArrow(released(_solved(level, solver)), STRETCHES))
        hot = pieces.where("hot").select(*KEY, F.col("start").alias("base"), "m", F.col("piece").alias("text"))
        texts, level = hot, level.longer() if not hot.isEmpty() else None
    cuts = found[0]
    for more in found[1:]:
        cuts = cuts.unionByName(more)
    return stored(cuts.groupBy(*KEY).agg(F.collect_list(F.struct("start", "stop")).alias("cuts")))


def _settled(texts: DataFrame, kind: Kind) -> tuple[DataFrame, DataFrame]:
    """Stretches that whole runs settle, and one copy of each stretch whose gram has several.

    ``texts`` are documents, or stretches of them from ``base`` on, with their number ``m`` of copies.
    """
    seen = stored(texts.mapInArrow(released(_run_rows(kind)), RUNS))
    whole = seen.where("a is not null")
    grams = whole.groupBy("a").agg(F.sum("n").alias("all"), F.min("u").alias("least"), F.max("u").alias("most")).where(F.col("all") > 1)
    grams = stored(grams.select("a", (F.col("least") != F.col("most")).alias("mixed")))  # a table, so that a hot gram's rows may be split in the join
    shared = stored(whole.join(grams, "a"))
    here = stored(seen.where("a is null").select(*KEY, "start", "stop"))
    drop(seen)

    place = F.struct(*KEY, "start")
    stretches = shared.groupBy("a", "u").agg(F.sum("n").alias("m"), F.min(place).alias("first"))
    known = stored(shared.join(stretches, ["a", "u"]).withColumn("is_first", place == F.col("first")).drop("first", "n"))
    drop(shared)
    full = known.where(~F.col("is_first") if kind.later else F.col("m") > 1).select(*KEY, "start", "stop")
    firsts = known.where("mixed and is_first").dropDuplicates(["a", "u"])
    hot = stored(firsts.groupBy("a").count().where(F.col("count") > kind.group_up_to).select("a", F.lit(True).alias("hot")))
    return full.unionByName(here), firsts.join(hot, "a", "left").withColumn("hot", F.coalesce("hot", F.lit(False)))


def cut_stretches(docs: DataFrame, cuts: DataFrame, apply, schema: str, *columns: str) -> DataFrame:
    """``docs`` through ``apply(batches)``, which finds ``text`` as bytes and ``cuts`` (null if none) there."""
    texts = keyed(docs, *columns)
    return texts.join(cuts, KEY, "left").select("doc", "text", "cuts", *columns).mapInArrow(released(apply), schema)


def unions(cuts: pa.ListArray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each row the starts and stops of its maximal stretches, in order; none for null.

    Rows can hold a great many stretches, so they never become Python objects.
    """
    flat = cuts.flatten()
    starts, stops = (flat.field(c).to_numpy(zero_copy_only=False) for c in ("start", "stop"))
    ends = np.cumsum(pc.fill_null(pc.list_value_length(cuts), 0).to_numpy(zero_copy_only=False))
    for a, b in zip([0, *ends[:-1]], ends, strict=True):
        order = np.argsort(starts[a:b], kind="stable")
        start, reach = starts[a:b][order], np.maximum.accumulate(stops[a:b][order]) if b > a else stops[a:b]
        new = np.flatnonzero(start[1:] > reach[:-1]) + 1
        yield start[np.concatenate([[0], new])] if b > a else start, reach[np.concatenate([new - 1, [b - a - 1]])] if b > a else reach
