"""Document quality from a linear-chain conditional random field over lines.

Every line is good or bad.  What a line looks like, and what its neighbours look like, speaks
for either; neighbouring lines tend to be of one kind.  Only documents are labelled, so in
training every line has its document's label.  Forward and backward passes give each line's
probability to be good, and their mean, weighted by the lines' lengths, is the score.

The model is fitted on the driver to a bounded number of labelled documents: ``SAMPLE`` of
them, the first in a seeded order.  Features come from whole texts, by array operations over
all bytes of a batch.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from metricblock.llm.common import released, table, text_of
from metricblock.llm.hashing import word_hashes

SAMPLE = 4_000
#: Longer texts (in bytes) are no examples; they are scored like any other.
LONGEST_EXAMPLE = 1 << 18
BUCKETS = 10
FEATURES = ("length", "words", "upper", "digits", "symbols", "points", "bars", "shouts", "high", "again", "variety", "word_length", "copies", "ends")


def _bytes_in(letters: bytes) -> np.ndarray:
    out = np.zeros(256, dtype=bool)
    out[list(letters)] = True
    return out


UPPER = _bytes_in(bytes(range(65, 91)))
CLASSES = {
    "digits": _bytes_in(b"0123456789"),
    "symbols": _bytes_in(b"#$%&*@^~<>=_+{}[]\\/"),
    "points": _bytes_in(b".,;:'\"?()-"),
    "bars": _bytes_in(b"|"),
    "shouts": _bytes_in(b"!"),
    "high": _bytes_in(bytes(range(128, 256))),
}
LETTERS = UPPER | _bytes_in(bytes(range(97, 123)))
ENDINGS = _bytes_in(b".!?\"")


def line_features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features of all lines (rows), lines of each text, and the lines' lengths in bytes.

    An empty text has one empty line.
    """
    data = np.frombuffer(b"\n".join(texts), dtype=np.uint8)
    breaks = np.flatnonzero(data == 10)
    starts, ends = np.concatenate([[0], breaks + 1]), np.concatenate([breaks, [len(data)]])
    sizes = np.array([len(t) for t in texts])
    doc_starts = np.concatenate([[0], np.cumsum(sizes + 1)[:-1]])
    first = np.searchsorted(starts, doc_starts)
    per_doc = np.diff(np.append(first, len(starts)))
    length = (ends - starts).astype(np.float64)

    def count(letters: np.ndarray) -> np.ndarray:
        upto = np.zeros(len(data) + 1, dtype=np.int64)
        np.cumsum(letters[data], out=upto[1:])
        return (upto[ends] - upto[starts]).astype(np.float64)

    out = np.zeros((len(starts), len(FEATURES)), dtype=np.float32)
    at = {name: i for i, name in enumerate(FEATURES)}
    some = np.maximum(length, 1)
    for name, letters in CLASSES.items():
        out[:, at[name]] = count(letters) / some
    out[:, at["upper"]] = count(UPPER) / np.maximum(count(LETTERS), 1)
    out[:, at["length"]] = np.log2(length + 1)

    word_at, hashes = word_hashes(data)
    line = np.searchsorted(starts, word_at, side="right") - 1
    words = np.bincount(line, minlength=len(starts)).astype(np.float64)
    out[:, at["words"]] = np.log2(words + 1)
    again = (hashes[1:] == hashes[:-1]) & (line[1:] == line[:-1])
    out[:, at["again"]] = np.bincount(line[1:][again], minlength=len(starts)) / np.maximum(words, 1)
    order = np.lexsort((hashes, line))
    fresh = np.ones(len(order), dtype=bool)
    fresh[1:] = (hashes[order][1:] != hashes[order][:-1]) | (line[order][1:] != line[order][:-1])
    different = np.bincount(line[order][fresh], minlength=len(starts))
    # of few words all may well differ: the square root of the number makes lines of any length comparable
    out[:, at["variety"]] = np.where(words > 0, different / np.maximum(words, 1) * np.sqrt(np.minimum(words, 64)), 0)
    out[:, at["word_length"]] = length / np.maximum(words, 1)
    out[:, at["ends"]] = np.where(length > 0, ENDINGS[data[np.maximum(ends - 1, 0)]] if len(data) else False, False)

    total = np.zeros(len(hashes) + 1, dtype=np.uint64)
    np.cumsum(hashes, out=total[1:])
    upto = np.concatenate([[0], np.cumsum(words).astype(np.int64)])
    content = total[upto[1:]] - total[upto[:-1]]
    doc = np.repeat(np.arange(len(texts)), per_doc)
    order = np.lexsort((content, doc))
    same = np.zeros(len(order), dtype=bool)
    same[1:] = (content[order][1:] == content[order][:-1]) & (doc[order][1:] == doc[order][:-1])
    copies = np.zeros(len(order), dtype=bool)
    copies[order] = same
    out[:, at["copies"]] = copies & (words > 0)
    return out, per_doc, length


@dataclass
class LineChain:
    """``edges``: bucket borders of each feature.  ``weights``: (before, own, after) x feature x bucket, for good.

    A missing neighbour has a bucket of its own.  ``stay``: how lines of either kind like to
    have a successor of the same kind.
    """

    edges: np.ndarray
    weights: np.ndarray
    bias: float
    stay: np.ndarray

    @classmethod
    def blank(cls, features: np.ndarray) -> LineChain:
        edges = np.quantile(features, np.linspace(0, 1, BUCKETS + 1)[1:-1], axis=0).T if len(features) else np.zeros((len(FEATURES), BUCKETS - 1))
        return cls(edges, np.zeros((3, len(FEATURES), BUCKETS + 1)), 0.0, np.zeros(2))

    def buckets(self, features: np.ndarray, per_doc: np.ndarray) -> np.ndarray:
        """Indices into the flattened weights for each line: 3 x features of them."""
        own = np.stack([np.searchsorted(e, features[:, i], side="left") for i, e in enumerate(self.edges)], axis=1)
        first = np.cumsum(per_doc) - per_doc
        before, after = np.roll(own, 1, axis=0), np.roll(own, -1, axis=0)
        before[first], after[first + per_doc - 1] = BUCKETS, BUCKETS
        k = len(FEATURES)
        base = np.arange(k) * (BUCKETS + 1)
        return np.concatenate([x + base + i * k * (BUCKETS + 1) for i, x in enumerate((before, own, after))], axis=1)

    def emissions(self, buckets: np.ndarray) -> np.ndarray:
        flat = self.weights.ravel()
        out = np.full(len(buckets), self.bias)
        for column in buckets.T:
            out += flat[column]
        return out

    def passes(self, emission: np.ndarray, per_doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Log odds of good after the forward and the backward pass: with a line's own emission, and without it."""
        order = np.argsort(-per_doc, kind="stable")
        first = (np.cumsum(per_doc) - per_doc)[order]
        lengths = per_doc[order]
        bad, good = self.stay
        ahead, back = np.empty(len(emission)), np.empty(len(emission))
        most = int(lengths[0]) if len(lengths) else 0
        active = np.searchsorted(-lengths, -np.arange(1, most + 1), side="right")  # documents with more than t lines
        for t in range(most):
            at = first[: active[t]] + t
            if t:
                m = ahead[at - 1]
                ahead[at] = emission[at] + np.logaddexp(0, m + good) - np.logaddexp(bad, m)
            else:
                ahead[at] = emission[at]
        for t in range(most - 1, -1, -1):
            at = first[: active[t]] + t
            back[at] = 0.0
            if t + 1 < most:
                at = at[: active[t + 1]]
                m = back[at + 1] + emission[at + 1]
                back[at] = np.logaddexp(0, m + good) - np.logaddexp(bad, m)
        return ahead, back

    def marginals(self, emission: np.ndarray, per_doc: np.ndarray) -> np.ndarray:
        ahead, back = self.passes(emission, per_doc)
        return 1 / (1 + np.exp(-np.clip(ahead + back, -500, 500)))

    def scores(self, texts: list[bytes]) -> np.ndarray:
        features, per_doc, length = line_features(texts)
        good = self.marginals(self.emissions(self.buckets(features, per_doc)), per_doc)
        first = np.cumsum(per_doc) - per_doc
        weight = length + 1
        return np.add.reduceat(good * weight, first) / np.add.reduceat(weight, first)

    def fit(self, features: np.ndarray, per_doc: np.ndarray, label: np.ndarray, rounds: int = 160, rate: float = 0.05, keep: float = 2e-3) -> LineChain:
        """Adam on the conditional likelihood; documents weigh the same, whatever their length."""
        if not len(per_doc):
            return self
        buckets = self.buckets(features, per_doc)
        want = np.repeat(label, per_doc).astype(np.float64)
        share = np.repeat(1 / per_doc, per_doc) / len(per_doc)
        inner = np.ones(len(want), dtype=bool)
        inner[np.cumsum(per_doc) - 1] = False
        left = np.flatnonzero(inner)
        n = self.weights.size
        theta, one, two = np.zeros(n + 3), np.zeros(n + 3), np.zeros(n + 3)
        for step in range(1, rounds + 1):
            self.weights, self.bias, self.stay = theta[:n].reshape(self.weights.shape), theta[n], theta[n + 1 :]
            emission = self.emissions(buckets)
            ahead, back = self.passes(emission, per_doc)
            miss = (want - 1 / (1 + np.exp(-np.clip(ahead + back, -500, 500)))) * share
            slope = np.zeros(n + 3)
            for column in buckets.T:
                slope[:n] += np.bincount(column, weights=miss, minlength=n)
            slope[n] = miss.sum()
            after = emission[left + 1] + back[left + 1]
            both = np.stack([np.full(len(left), self.stay[0]), ahead[left], after, ahead[left] + after + self.stay[1]])
            both = np.exp(both - both.max(axis=0))
            both /= both.sum(axis=0)
            slope[n + 1] = ((1 - want[left] - both[0]) * share[left]).sum()
            slope[n + 2] = ((want[left] - both[3]) * share[left]).sum()
            slope[:n] -= keep * theta[:n] / 10
            slope[n + 1 :] -= keep * theta[n + 1 :]
            one = 0.9 * one + 0.1 * slope
            two = 0.999 * two + 0.001 * slope**2
            theta = theta + rate * (one / (1 - 0.9**step)) / (np.sqrt(two / (1 - 0.999**step)) + 1e-9)
        self.weights, self.bias, self.stay = theta[:n].reshape(self.weights.shape), float(theta[n]), theta[n + 1 :]
        return self


def _sample_features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = []
        for doc, text, label in zip(b.column(0).to_pylist(), b.column(1), b.column(2).to_pylist(), strict=True):
            features, _, _ = line_features([text.as_py()])
            rows.append((doc, label, features.tobytes()))
        columns = zip(*rows, strict=True) if rows else [()] * 3
        yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(columns, (pa.int64(), pa.int32(), pa.binary()), strict=True)], ["doc_id", "label", "features"])


def labelled_sample(docs: DataFrame, labels: DataFrame, column: str, most: int, modulus: int, left_out: int, seed: int = 9, longest: int = LONGEST_EXAMPLE) -> DataFrame:
    """At most ``most`` labelled ids, the first in a seeded order, whose crc32 modulo ``modulus`` isn't ``left_out``.

    Texts of more than ``longest`` bytes aren't given, so what the driver gets has a bound.
    """
    held = F.crc32(F.col("doc_id").cast("string")) % modulus
    ids = labels.where(F.col("doc_id").isNotNull() & F.col(column).isin(0, 1) & (held != left_out)).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(column).cast("int").alias("label"))
    ids = ids.orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(most)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().cast("binary").alias("text")).where(F.octet_length("text") <= longest).join(F.broadcast(ids), "doc_id").select("doc_id", "text", "label")


def train(docs: DataFrame, labels: DataFrame, modulus: int = 3, left_out: int = 1, sample: int = SAMPLE) -> LineChain:
    """The model for ``labels.quality``, from at most ``sample`` labelled documents."""
    rows = labelled_sample(docs, labels, "quality", sample, modulus, left_out).mapInArrow(released(_sample_features), "doc_id long, label int, features binary").collect()
    rows.sort(key=lambda r: (r["doc_id"], r["features"]))
    each = [np.frombuffer(r["features"], dtype=np.float32).reshape(-1, len(FEATURES)) for r in rows]
    features = np.concatenate(each) if each else np.zeros((0, len(FEATURES)), dtype=np.float32)
    return LineChain.blank(features).fit(features, np.array([len(e) for e in each], dtype=np.int64), np.array([r["label"] for r in rows]))


def _scored(model: LineChain, at_once: int = 1 << 20):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            scores, held, size = [np.zeros(0)], [], 0
            for text in b.column(1):
                held.append(text.as_py())
                size += len(held[-1])
                if size >= at_once:
                    scores.append(model.scores(held))
                    held, size = [], 0
            if held:
                scores.append(model.scores(held))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.concatenate(scores))], ["doc_id", "score"])

    return run


def score_quality(docs: DataFrame, model: LineChain) -> DataFrame:
    """``(doc_id, score)`` for each row; null texts count as empty, and an empty text as one empty line.

    A model that was fitted to nothing scores every document 0.5.  Repeated rows get a row
    each; other columns are ignored; an empty table gives no rows.
    """
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().cast("binary").alias("text")).mapInArrow(released(_scored(model)), "doc_id long, score double")


def with_scores(docs: DataFrame, model: LineChain, name: str = "_score") -> DataFrame:
    """``docs`` with all its columns and the score in one more, ``name``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for scored, b in _beside(_scored(model), batches):
            yield b.append_column(name, scored.column(1))

    schema = T.StructType([*docs.schema.fields, T.StructField(name, T.DoubleType())])
    return docs.mapInArrow(released(run), schema)


def _beside(score, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, pa.RecordBatch]]:
    for b in batches:
        text = pa.array([(x.as_py() or "").encode() for x in b.column("text")], pa.binary())
        yield next(score(iter([pa.RecordBatch.from_arrays([pa.nulls(len(text), pa.int64()), text], ["doc_id", "text"])]))), b


def op9_line_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    held_out = F.crc32(F.col("doc_id").cast("string")) % 3 == 1
    return score_quality(docs, model).select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
