"""SimHash near-duplicates, found by Golay-code fuzzy hashing.

A fingerprint of 64 bits is seen as three segments.  If two fingerprints differ in at most two
bits, one segment is equal in both, and any other differs in at most two bits.  The second
kind of segment becomes a few indices of the perfect binary Golay code: every word of 23 bits
lies within three bits of exactly one codeword.  A word within two bits of its codeword has
that one index; a word at three bits also has the indices of the five codewords four bits away.
Then any two words that differ in at most two bits have an index in common (the test of this
module goes through all cases).  Equal segment plus shared index is the join key; candidates
are verified on all 64 bits.

Equal fingerprints are merged before anything is joined.  A key that more than ``PAIR_UP_TO``
different fingerprints share isn't joined in pairs: there, fingerprints meet at the values one
bit away from each of them.  Two that meet differ in at most two bits, and all that do so
meet, so this is exact, and its cost is in proportion to the number of fingerprints.

Texts of a given similarity, not of a given distance, need wider fingerprints: at a Jaccard
similarity of 0.8 about 15 of 100 bits differ.  ``similar_pairs`` takes several words of 64
bits; a key is the Golay index of a segment of 23 bits and some bits of another place that have
to be equal, and candidates are verified on all bits.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StructField, StructType

from metricblock.llm.common import drop, released, stored, table, text_of, unused
from metricblock.llm.hashing import LENGTH, mixed
from metricblock.operators.clusters import components

#: Fixed value: the generator polynomial of the cyclic Golay code of length 23.
GOLAY_POLYNOMIAL = 0b110001110101
#: First bit and width of the segments.
SEGMENTS = ((0, 23), (23, 23), (46, 18))
#: Which segment has to be equal, and which one gives the indices.
PLANS = ((0, 1), (1, 2), (2, 0))
PAIR_UP_TO = 64
#: Bits of a wide key that have to be equal: one number for tables of any size, so that what is found doesn't hang on it.
EQUAL_BITS = 9
SEED = 42


def shingle_hashes(text: bytes, shingle: int) -> np.ndarray:
    """XXH64 of each run of ``shingle`` words, A-Z lowered, repeats included; fewer words: of all; none: empty."""
    flat = b" ".join(text.lower().split())
    if not flat:
        return np.zeros(0, dtype="<u8")
    gaps = np.flatnonzero(np.frombuffer(flat, dtype=np.uint8) == 32)
    n = len(gaps) + 1
    if n <= shingle:
        return np.array([xxhash.xxh64_intdigest(flat, SEED)], dtype="<u8")
    starts = [0, *(gaps[: n - shingle] + 1).tolist()]
    ends = [*gaps[shingle - 1 :].tolist(), len(flat)]
    hashed = xxhash.xxh64_intdigest
    return np.array([hashed(flat[a:b], SEED) for a, b in zip(starts, ends, strict=True)], dtype="<u8")


def majority(hashes: np.ndarray) -> int:
    """A bit is 1 if set in over half of the hashes; of none: zero."""
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 8192):
        ones += np.unpackbits(hashes[at : at + 8192].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")[0])


def fingerprint(text: bytes, shingle: int = 3) -> int:
    """A bit is 1 if set in over half of the shingles' hashes.  No word: zero."""
    return majority(shingle_hashes(text, shingle))


def wide_fingerprint(text: bytes, shingle: int = 5, words: int = 8) -> list[int]:
    """``words`` fingerprints of 64 bits from different hashes of the same different shingles."""
    hashes = np.unique(shingle_hashes(text, shingle))
    return [majority(mixed(hashes + np.uint64(i * int(LENGTH) % (1 << 64)))) for i in range(1, words + 1)]


def jaccard(a: bytes, b: bytes, shingle: int = 5) -> float:
    """Share of the different shingles of two texts that both have; two texts without words are equal."""
    x, y = np.unique(shingle_hashes(a, shingle)), np.unique(shingle_hashes(b, shingle))
    both = len(np.intersect1d(x, y, assume_unique=True))
    return both / (len(x) + len(y) - both) if len(x) + len(y) else 1.0


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        found = np.fromiter((fingerprint(x.as_py()) for x in b.column(1)), dtype=np.uint64, count=b.num_rows)
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found.view(np.int64))], ["doc_id", "fingerprint"])


def simhash(docs: DataFrame) -> DataFrame:
    """``(doc_id, fingerprint long)``; a null text counts as empty."""
    return docs.select(F.col("doc_id").cast("long"), text_of().cast("binary").alias("text")).mapInArrow(released(_fingerprints), "doc_id long, fingerprint long")


def fingerprinted(docs: DataFrame, name: str = "fingerprint", shingle: int = 5, words: int = 8) -> DataFrame:
    """``docs`` with one more column, ``name array<long>``: the words of the wide fingerprint."""
    (data,) = unused(docs, "text_bytes")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = np.array([wide_fingerprint(x.as_py(), shingle, words) for x in b.column(b.num_columns - 1)], dtype=np.uint64).reshape(b.num_rows, words)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(found.view(np.int64).tolist(), pa.list_(pa.int64()))], [*b.schema.names[:-1], name])

    schema = StructType([*docs.schema.fields, StructField(name, ArrayType(LongType()))])
    return docs.select("*", text_of().cast("binary").alias(data)).mapInArrow(released(run), schema)


def bits_at(similarity: float, bits: int, deviations: float = 0.0) -> int:
    """How many of ``bits`` fingerprint bits differ at a Jaccard similarity of two sets of equal size: the mean, and so many standard deviations more."""
    share = math.acos(2 * similarity / (1 + similarity)) / math.pi
    return math.floor(bits * share + deviations * math.sqrt(bits * share * (1 - share)))


def _wide_keys(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which row, and a key: the Golay index of a segment of a word, with other bits that have to be equal."""
    rows, keys = [], []
    width = prints.shape[1]
    for w in range(width):
        for near in (0, 23):
            of, index = golay_indices((prints[:, w] >> np.uint64(near) & np.uint64((1 << 23) - 1)).astype(np.int64))
            for other in {w, (w + 1) % width}:
                same = (prints[:, other] >> np.uint64(64 - EQUAL_BITS)).astype(np.int64)
                rows.append(of)
                keys.append((same[of] << 32) | (index << 16) | (w * 2 + (near > 0)) * 2 + (other != w))
    return np.concatenate(rows), np.concatenate(keys)


def _peeled(key: np.ndarray, words: np.ndarray, most: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Rows come sorted by key.  In turn: heads, and rows close to a head with that head.

    The first row of each key is its head; rows that aren't close to it have a head among
    themselves in the next turn, till none is left.
    """
    rest = np.arange(len(key))
    while len(rest):
        lead = np.ones(len(rest), dtype=bool)
        lead[1:] = key[rest[1:]] != key[rest[:-1]]
        head = rest[np.maximum.accumulate(np.where(lead, np.arange(len(rest)), 0))]
        close = (np.bitwise_count(words[rest] ^ words[head]).sum(axis=1) <= most) & ~lead
        yield rest[lead], rest[close], head[close]
        rest = rest[~close & ~lead]


def _local_heads(most: int, at_once: int = 1024):
    """Keys of a task's prints, each with one word to compare; what is close to a head here is linked to it at once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(ids: np.ndarray, prints: np.ndarray) -> Iterator[pa.RecordBatch]:
            row, key = _wide_keys(prints)
            order = np.lexsort((ids[row], key))
            row, key = row[order], key[order]
            for heads, close, head in _peeled(key, prints[row], most):
                pairs = np.unique(np.stack([row[close], row[head]], axis=1), axis=0)
                none = pa.nulls(len(pairs), pa.int64())
                yield pa.RecordBatch.from_arrays([none, pa.array(ids[pairs[:, 0]]), pa.array(ids[pairs[:, 1]])], ["key", "id", "more"])
                check = prints[row[heads], ((key[heads] & 0xFFFF) // 4 + 2) % prints.shape[1]].view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(key[heads]), pa.array(ids[row[heads]]), pa.array(check)], ["key", "id", "more"])

        held: list[pa.RecordBatch] = []
        for b in batches:
            held += [b] if b.num_rows else []
            if sum(x.num_rows for x in held) >= at_once:
                yield from out(*_columns(held))
                held = []
        if held:
            yield from out(*_columns(held))

    return run


def _columns(held: list[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray]:
    ids = np.concatenate([b.column(0).to_numpy() for b in held])
    return ids, np.concatenate([b.column(1).flatten().to_numpy() for b in held]).view(np.uint64).reshape(len(ids), -1)


def _meetings(most: int):
    """Rows (key, id, check) come sorted by key: each is paired with a head of its key whose check word is close."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros((0, 3), dtype=np.int64)

        def out(x: np.ndarray) -> Iterator[pa.RecordBatch]:
            for _, close, head in _peeled(x[:, 0], x[:, 2:].view(np.uint64), most):
                pairs = np.unique(np.stack([x[close, 1], x[head, 1]], axis=1), axis=0)
                pairs = pairs[pairs[:, 0] != pairs[:, 1]]
                yield pa.RecordBatch.from_arrays([pa.array(pairs.min(axis=1)), pa.array(pairs.max(axis=1))], ["a", "b"])

        for b in batches:
            held = np.concatenate([held, np.stack([c.to_numpy() for c in b.columns], axis=1)])
            last = int(np.searchsorted(held[:, 0], held[-1, 0])) if len(held) else 0
            if last >= 1 << 16:  # the last key may go on in the next batch
                yield from out(held[:last])
                held = held[last:]
        if len(held):
            yield from out(np.ascontiguousarray(held))

    return run


def similar_pairs(prints: DataFrame, similarity: float = 0.8) -> DataFrame:
    """Candidates ``(a, b, bits)`` among ``prints(id long, words array<long>)``: fingerprints that share a key
    and differ in no more ``bits`` than texts of that similarity do, three standard deviations allowed.

    Rows of a key are compared with its head, the first of them; those that aren't close have a
    head of their own, and so on.  Each task does so with its own rows first, so a key of many
    copies sends one row from each task, and its copies cost a link each, not one a pair.
    """
    width = prints.select(F.max(F.size("words"))).first()[0] or 1
    most, check = bits_at(similarity, 64 * width, 3), bits_at(similarity, 64, 3)
    local = stored(prints.select("id", "words").mapInArrow(released(_local_heads(most)), "key long, id long, more long"))
    met = local.where("key is not null").repartition("key").sortWithinPartitions("key", "id").mapInArrow(released(_meetings(check)), "a long, b long")
    linked = local.where("key is null").select(F.least("id", "more").alias("a"), F.greatest("id", "more").alias("b"))
    side = prints.select(F.col("id"), "words")
    pairs = met.unionByName(linked).distinct().join(side.select(F.col("id").alias("a"), F.col("words").alias("x")), "a").join(side.select(F.col("id").alias("b"), F.col("words").alias("y")), "b")
    apart = F.aggregate(F.zip_with("x", "y", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
    found = stored(pairs.select("a", "b", apart.alias("bits")).where(F.col("bits") <= most))
    drop(local)
    return found


def verified(pairs: DataFrame, texts: Callable[[DataFrame], DataFrame], bits: int, similarity: float = 0.8, shingle: int = 5, sure: float = 0.9) -> DataFrame:
    """Of the candidates ``(a, b, bits)`` those whose texts have that similarity.

    As few differing bits as at a similarity of ``sure`` are enough; other pairs are compared by
    their shingles: ``texts`` gives ``(id, text binary)``, one row an id, for a table of ids.
    """
    pairs = stored(pairs)
    clear = F.col("bits") <= bits_at(sure, bits)
    close = pairs.where(~clear)
    asked = close.select(F.col("a").alias("id")).union(close.select("b")).distinct()
    fetched = stored(texts(stored(asked)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yes = [jaccard(x.as_py(), y.as_py(), shingle) >= similarity for x, y in zip(b.column(2), b.column(3), strict=True)]
            yield b.select(["a", "b"]).filter(pa.array(yes, pa.bool_()))

    both = close.join(fetched.select(F.col("id").alias("a"), F.col("text").alias("x")), "a").join(fetched.select(F.col("id").alias("b"), F.col("text").alias("y")), "b")
    return both.select("a", "b", "x", "y").mapInArrow(released(run), "a long, b long").unionByName(pairs.where(clear).select("a", "b"))


@cache
def golay_tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Remainders of the bytes at their three places; changes of the index, by remainder; their number."""

    def remainder(word: int) -> int:
        for bit in range(22, 10, -1):
            if word >> bit & 1:
                word ^= GOLAY_POLYNOMIAL << (bit - 11)
        return word

    by_byte = np.array([[remainder((b << 8 * place) & 0x7FFFFF) for b in range(256)] for place in range(3)], dtype=np.int64)
    light = [message << 11 ^ remainder(message << 11) for message in range(4096)]
    light = [word for word in light if word.bit_count() == 7]
    changes = np.zeros((2048, 6), dtype=np.int64)
    number = np.ones(2048, dtype=np.int64)
    bits = [1 << i for i in range(23)]
    errors = [0, *bits, *(a | b for a in bits for b in bits if a < b), *(a | b | c for a in bits for b in bits if a < b for c in bits if b < c)]
    for error in errors:  # each remainder has exactly one error of at most three bits
        others = [word for word in light if word & error == error] if error.bit_count() == 3 else []
        at = remainder(error)
        changes[at, : 1 + len(others)] = [(error ^ other) >> 11 for other in (0, *others)]
        number[at] = 1 + len(others)
    return by_byte, changes, number


def golay_indices(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For words of 23 bits: which word (by position), and one of its indices of 12 bits."""
    by_byte, changes, number = golay_tables()
    words = words.astype(np.int64)
    rest = by_byte[0][words & 255] ^ by_byte[1][words >> 8 & 255] ^ by_byte[2][words >> 16 & 255]
    n = number[rest]
    of = np.repeat(np.arange(len(words)), n)
    nth = np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)
    return of, (words[of] >> 11) ^ changes[rest[of], nth]


def _keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        prints = b.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
        parts = [(prints.view(np.uint64) >> np.uint64(first) & np.uint64((1 << width) - 1)).astype(np.int64) for first, width in SEGMENTS]
        for plan, (same, near) in enumerate(PLANS):
            of, index = golay_indices(parts[near])
            key = (parts[same][of] << 14) | (index << 2) | plan
            yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(prints[of])], ["key", "fingerprint"])


def _flipped(plan: int) -> list[int]:
    """Zero, and each bit outside the segment that is equal under ``plan``, as signed values."""
    first, width = SEGMENTS[PLANS[plan][0]]
    return [0] + [b - (1 << 64) if b >> 63 else b for b in (1 << i for i in range(64) if not first <= i < first + width)]


def near_pairs(prints: DataFrame) -> DataFrame:
    """Pairs ``(a, b)`` of different fingerprints whose components are those of all links.

    ``prints`` has one column, ``fingerprint long``, without repeats.  Every pair given differs
    in one or two bits; pairs that share no small key are linked through the ones between.
    """
    keys = prints.mapInArrow(released(_keys), "key long, fingerprint long")
    groups = keys.groupBy("key").agg(F.count("*").alias("n"), F.min("fingerprint").alias("a"), F.max("fingerprint").alias("b")).where("n > 1")
    groups = stored(groups)
    close = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= 2
    twos = groups.where("n = 2").where(close).select("a", "b")

    shared = stored(keys.join(groups.where("n > 2").select("key", "n"), "key"))
    few = shared.where(F.col("n") <= PAIR_UP_TO).select("key", F.col("fingerprint").alias("a"))
    threes = few.join(few.withColumnRenamed("a", "b"), "key").where("a < b").where(close).select("a", "b")

    many = shared.where(F.col("n") > PAIR_UP_TO).select(F.col("key").bitwiseAND(3).alias("plan"), "fingerprint").distinct()
    flips = F.array(*[F.lit(_flipped(i)) for i in range(len(PLANS))])
    met = many.select("fingerprint", F.explode(F.transform(F.get(flips, F.col("plan").cast("int")), lambda m: m.bitwiseXOR(F.col("fingerprint")))).alias("at"))
    meetings = met.distinct().groupBy("at").agg(F.collect_set("fingerprint").alias("all")).where(F.size("all") > 1)  # 64 at most
    stars = meetings.select(F.array_min("all").alias("a"), F.explode("all").alias("b")).where("a <> b")
    return twos.unionByName(threes).unionByName(stars)


def rooted(prints: DataFrame) -> DataFrame:
    """``prints``, whose ``fingerprint`` has no repeats, with the fingerprint that stands for each one's component in ``root``."""
    joined = components(near_pairs(prints.select("fingerprint")))
    return prints.join(joined.withColumnRenamed("id", "fingerprint"), "fingerprint", "left").withColumn("root", F.coalesce("component", "fingerprint"))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """``(doc_id, fingerprint long, component_id)`` for each row of ``docs``.

    Fingerprints link at two or fewer differing bits; the component is the smallest doc_id
    reachable.  Null and empty texts have fingerprint zero and link like any other.  Repeated
    rows give a row each.  Rows without a doc_id take the smallest one of their component, or
    null if it has none.  Other columns are ignored.  An empty table gives no rows.
    """
    marked = stored(simhash(docs))
    prints = stored(marked.groupBy("fingerprint").agg(F.min("doc_id").alias("first")))
    roots = rooted(prints)
    least = roots.groupBy("root").agg(F.min("first").alias("component_id"))
    named = roots.join(least, "root").select(F.col("fingerprint").alias("print"), "component_id")
    return marked.join(named, F.col("fingerprint") == F.col("print")).select("doc_id", "fingerprint", "component_id")


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fingerprint"), 16, "0")).alias("fingerprint"), "component_id")
