"""Toxicity by nearest labelled examples, over a block-max inverted index.

Texts and examples are TF-IDF vectors over all their terms; none is left out.  The nearest
examples by cosine are found exactly: postings lie in blocks of examples, each term knows its
largest weight in each block that has it, so a block's best possible cosine is known before it
is opened, and blocks that cannot reach the neighbours found so far stay closed.  The neighbours
vote with their similarity; a logistic curve makes the vote a probability.  The neighbours are
the evidence.

A few insults in a long text weigh little among its rare words, so by plain TF-IDF the nearest
examples of half of the toxic texts are clean.  Therefore each term also has a gain, from
``FLOOR`` to 1, by the chi-square of its presence and the label.  One half of the examples gives
the gains; the votes among the neighbours of the other half fit the curve.

Document frequencies of the examples' terms come from all documents.  Terms that no example has
change a text's length alone: neither the order of its neighbours nor their votes, which are in
proportion to the nearest.  Only the evidence shows whole cosines; their document frequencies
are counted and joined by term there.

Examples are a bounded number of labelled documents: ``SAMPLE``, the first in a seeded order.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from metricblock.llm.common import released, stored, table, text_of
from metricblock.llm.hashing import mixed, word_hashes
from metricblock.llm.line_crf import labelled_sample

SAMPLE = 4_000
#: Longer texts (in bytes) are no examples; they are scored like any other.
LONGEST_EXAMPLE = 1 << 18
NEIGHBOURS = 25
BLOCK = 64
#: Terms of the index that are kept as a dense panel.
PANEL = 512
PRIOR = 0.1
#: The least gain of a term, and the chi-square at which the gain is a half.
FLOOR, HALF = 0.1, 50.0
#: Squared lengths are summed in whole steps of this size, so that the order of rows changes nothing.
STEP = 2.0**-32

LOWERED = np.arange(256, dtype=np.uint8)
LOWERED[65:91] += 32
BETWEEN = np.ones(256, dtype=bool)
BETWEEN[[*range(48, 58), *range(97, 123), *range(128, 256)]] = False


def terms_of(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Text number and hash of every term (letters, digits, bytes over 127; A-Z lowered), in order."""
    data = LOWERED[np.frombuffer(b"\n".join(texts), dtype=np.uint8)]
    starts, hashes = word_hashes(data, BETWEEN)
    ends = np.cumsum([len(t) + 1 for t in texts])
    return np.searchsorted(ends, starts, side="right"), hashes


def counted(doc: np.ndarray, term: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Different (text, term) pairs in order, and how often each occurs; ``term`` is under ``width``."""
    pairs, n = np.unique(doc.astype(np.int64) * width + term, return_counts=True)
    return pairs // width, pairs % width, n


def known(hashes: np.ndarray, vocabulary: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which hashes are in the sorted vocabulary, and their places there."""
    if not len(vocabulary):
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    place = np.minimum(np.searchsorted(vocabulary, hashes), len(vocabulary) - 1)
    hit = np.flatnonzero(vocabulary[place] == hashes)
    return hit, place[hit]


def stretches(starts: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Positions of stretches of ``n`` each from ``starts`` on, one after the other."""
    reach = np.cumsum(n)
    return np.arange(reach[-1] if len(reach) else 0) + np.repeat(starts - reach + n, n)


@dataclass
class BlockMaxIndex:
    """Postings by term and block.  ``find`` gives the exact best examples by inner product.

    The most frequent terms are a dense panel instead: a text's part of the product with them is
    exact for every example at once, and its maximum in a block is part of that block's bound.
    """

    width: int
    examples: int
    row: np.ndarray = field(repr=False)  # of a term in the panel, or -1
    panel: np.ndarray = field(repr=False)
    cells: np.ndarray = field(repr=False)  # of a term, into the blocks that have it
    block: np.ndarray = field(repr=False)  # of a cell
    largest: np.ndarray = field(repr=False)  # of a cell
    pointers: np.ndarray = field(repr=False)  # of a cell, into the postings
    where: np.ndarray = field(repr=False)  # example of a posting
    weight: np.ndarray = field(repr=False)

    @classmethod
    def build(cls, example: np.ndarray, term: np.ndarray, weight: np.ndarray, examples: int, width: int, panel: int = PANEL) -> BlockMaxIndex:
        often = np.bincount(term, minlength=width)
        common = np.argsort(-often, kind="stable")[:panel]
        common = common[often[common] > 1]
        row = np.full(width, -1, dtype=np.int32)
        row[common] = np.arange(len(common))
        dense = np.zeros((len(common), examples))
        inside = row[term] >= 0
        dense[row[term[inside]], example[inside]] = weight[inside]
        example, term, weight = example[~inside], term[~inside], weight[~inside]
        blocks = max(1, -(-examples // BLOCK))
        cell = term.astype(np.int64) * blocks + example // BLOCK
        order = np.lexsort((example, cell))
        example, weight = example[order].astype(np.int32), weight[order]
        found, first = np.unique(cell[order], return_index=True)
        largest = np.maximum.reduceat(weight, first) if len(first) else np.zeros(0)
        return cls(width, examples, row, dense, np.searchsorted(found, np.arange(width + 1) * blocks), (found % blocks).astype(np.int32), largest, np.append(first, len(weight)), example, weight)

    def common_part(self, doc: np.ndarray, terms: np.ndarray, weights: np.ndarray, docs: int) -> np.ndarray:
        """For each text (row) and example the inner product over the panel's terms."""
        row = self.row[terms]
        inside = row >= 0
        asked = np.zeros((docs, len(self.panel)))
        asked[doc[inside], row[inside]] = weights[inside]
        return asked @ self.panel

    def find(self, terms: np.ndarray, weights: np.ndarray, k: int, without: int = -1, common: np.ndarray | None = None, at_once: int = 8) -> tuple[np.ndarray, np.ndarray]:
        """Examples and cosines, best first, ties to the first example; only those with a term in common."""
        if common is None:
            common = self.common_part(np.zeros(len(terms), dtype=np.int64), terms, weights, 1)[0]
        if not self.examples:
            return np.zeros(0, dtype=np.int64), np.zeros(0)
        rare = self.row[terms] < 0
        terms, weights = terms[rare], weights[rare]
        n = self.cells[terms + 1] - self.cells[terms]
        cells, weights = stretches(self.cells[terms], n), np.repeat(weights, n)
        blocks = max(1, -(-self.examples // BLOCK))
        block = self.block[cells]
        bound = np.maximum.reduceat(common, np.arange(0, self.examples, BLOCK)) + np.bincount(block, weights=self.largest[cells] * weights, minlength=blocks)
        order = np.argsort(-bound, kind="stable")
        rank = np.empty(blocks, dtype=np.int64)
        rank[order] = np.arange(blocks)
        by_rank = np.argsort(rank[block], kind="stable")
        cells, weights = cells[by_rank], weights[by_rank]
        ends = np.cumsum(np.bincount(block, minlength=blocks)[order])
        best, near = np.zeros(0, dtype=np.int64), np.zeros(0)
        at = 0
        while at < blocks:
            if bound[order[at]] <= 0 or len(near) == k and bound[order[at]] < near[-1] * (1 - 1e-9):
                break
            opened = slice(ends[at - 1] if at else 0, ends[min(blocks, at + at_once) - 1])
            members = (order[at : at + at_once, None] * BLOCK + np.arange(BLOCK)).ravel()
            members = members[members < self.examples]
            at, at_once = at + at_once, at_once * 2
            start = self.pointers[cells[opened]]
            n = self.pointers[cells[opened] + 1] - start
            at_posting = stretches(start, n)
            score = common[members] + np.bincount(self.where[at_posting], weights=self.weight[at_posting] * np.repeat(weights[opened], n), minlength=self.examples)[members]
            found = score > (max(0.0, near[-1] * (1 - 1e-9)) if len(near) == k else 0)
            found &= members != without
            best, near = np.concatenate([best, members[found]]), np.concatenate([near, score[found]])
            top = np.lexsort((best, -np.round(near, 11)))[:k]
            best, near = best[top], near[top]
        return best, near


@dataclass
class ToxicityModel:
    vocabulary: np.ndarray = field(repr=False)
    rarity: np.ndarray = field(repr=False)  # inverse document frequency times gain
    gain: np.ndarray = field(repr=False)
    index: BlockMaxIndex = field(repr=False)
    ids: np.ndarray = field(repr=False)
    toxic: np.ndarray = field(repr=False)
    base: float = 0.0
    curve: tuple[float, float] = (1.0, 0.0)

    def vectors(self, doc: np.ndarray, term: np.ndarray, n: np.ndarray, docs: int) -> tuple[np.ndarray, np.ndarray]:
        """Weights of the (text, term) pairs, of unit length by text, and where each text's pairs begin."""
        weight = (1 + np.log(n)) * self.rarity[term]
        length = np.sqrt(np.bincount(doc, weights=weight**2, minlength=docs))
        return weight / np.where(length > 0, length, 1)[doc], np.searchsorted(doc, np.arange(docs + 1))

    def vote(self, example: np.ndarray, near: np.ndarray) -> float:
        """Squared cosines in proportion to the nearest one's, so a text's length plays no part."""
        w = (near / near[0]) ** 2 if len(near) else near
        return float((w @ self.toxic[example] + PRIOR * self.base) / (w.sum() + PRIOR))

    def probability(self, vote: np.ndarray) -> np.ndarray:
        vote = np.clip(vote, 1e-6, 1 - 1e-6)
        slope, shift = self.curve
        return np.round(1 / (1 + np.exp(-np.clip(slope * np.log(vote / (1 - vote)) + shift, -30, 30))), 9)

    def search(self, texts: list[bytes], k: int = NEIGHBOURS, others: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray, float, np.ndarray, np.ndarray]]:
        """For each text its nearest examples, their cosines times the text's length, what the known terms give of
        that length, squared, and the hashes and counts of the terms that no example has (none if not asked for)."""
        doc, hashes = terms_of(texts)
        terms, term = np.unique(hashes, return_inverse=True)
        doc, term, n = counted(doc, term, max(1, len(terms)))
        hit, found = known(terms, self.vocabulary)
        place = np.full(len(terms), -1, dtype=np.int64)
        place[hit] = found
        place = place[term]
        mine = place >= 0
        weight = np.zeros(len(doc))
        weight[mine] = (1 + np.log(n[mine])) * self.rarity[place[mine]]
        common = self.index.common_part(doc[mine], place[mine], weight[mine], len(texts))
        begins = np.searchsorted(doc, np.arange(len(texts) + 1))
        none = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
        for i, (a, b) in enumerate(zip(begins[:-1], begins[1:], strict=True)):
            here = np.flatnonzero(mine[a:b]) + a
            example, near = self.index.find(place[here], weight[here], k, common=common[i])
            rest = np.flatnonzero(~mine[a:b]) + a
            yield example, near, float(weight[here] @ weight[here]), *((terms[term[rest]], n[rest]) if others else none)


def gains(doc: np.ndarray, term: np.ndarray, width: int, label: np.ndarray, docs: np.ndarray) -> np.ndarray:
    """How much each term counts, from ``FLOOR`` to 1: it grows with the chi-square of its presence and the label.

    Only the examples that ``docs`` marks are looked at; a text has each of its terms once.
    """
    inside = docs[doc]
    a = np.bincount(term[inside], weights=label[doc[inside]], minlength=width)
    b = np.bincount(term[inside], minlength=width) - a
    yes, no = float(label[docs].sum()), float((1 - label[docs]).sum())
    below = (a + b) * (yes + no - a - b) * yes * no
    chi = (yes + no) * (a * (no - b) - b * (yes - a)) ** 2 / np.where(below > 0, below, 1)
    return np.maximum(FLOOR, chi / (chi + HALF))


def _sample_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = []
        for doc, text, label in zip(b.column(0).to_pylist(), b.column(1), b.column(2).to_pylist(), strict=True):
            terms, n = np.unique(terms_of([text.as_py()])[1], return_counts=True)
            rows.append((doc, label, terms.tobytes(), n.astype(np.int32).tobytes()))
        columns = zip(*rows, strict=True) if rows else [()] * 4
        types = (pa.int64(), pa.int32(), pa.binary(), pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(columns, types, strict=True)], ["doc_id", "label", "terms", "counts"])


def _frequencies(vocabulary: np.ndarray, at_once: int = 1 << 20):
    """In how many texts of a task each term is; place -1 counts the texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(vocabulary), dtype=np.int64)
        texts, held, size = 0, [], 0

        def add():
            doc, hashes = terms_of(held)
            hit, place = known(hashes, vocabulary)
            total[:] += np.bincount(counted(doc[hit], place, len(vocabulary))[1], minlength=len(vocabulary))

        for b in batches:
            texts += b.num_rows
            for text in b.column(0):
                held.append(text.as_py())
                size += len(held[-1])
                if size >= at_once:
                    add()
                    held, size = [], 0
        if held:
            add()
        place = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(place, -1)), pa.array(np.append(total[place], texts))], ["place", "n"])

    return run


def train(docs: DataFrame, labels: DataFrame, modulus: int = 5, left_out: int = 0, sample: int = SAMPLE, k: int = NEIGHBOURS) -> ToxicityModel:
    """The model for ``labels.toxic``: at most ``sample`` examples; term frequencies from all of ``docs``."""
    rows = labelled_sample(docs, labels, "toxic", sample, modulus, left_out, seed=3, longest=LONGEST_EXAMPLE).mapInArrow(released(_sample_terms), "doc_id long, label int, terms binary, counts binary").collect()
    rows.sort(key=lambda r: (r["label"], r["doc_id"], r["terms"]))
    label = np.array([r["label"] for r in rows], dtype=float)
    terms = [np.frombuffer(r["terms"], dtype=np.uint64) for r in rows]
    doc = np.repeat(np.arange(len(rows)), [len(t) for t in terms])
    flat = np.concatenate([np.zeros(0, dtype=np.uint64), *terms])
    vocabulary = np.unique(flat)

    frequency, texts = np.zeros(len(vocabulary)), 0
    for r in docs.select(text_of().cast("binary").alias("text")).mapInArrow(released(_frequencies(vocabulary)), "place long, n long").groupBy("place").agg(F.sum("n").alias("n")).collect() if len(vocabulary) else ():
        if r["place"] < 0:
            texts = r["n"]
        else:
            frequency[r["place"]] = r["n"]
    rarity = np.log((texts + 1) / (frequency + 1)) + 1e-3

    base = float(label.mean()) if len(label) else 0.0
    ids = np.array([r["doc_id"] for r in rows], dtype=np.int64)
    hit, place = known(flat, vocabulary)
    fold = mixed(ids.astype(np.uint64)) >> np.uint64(63) == 0  # one half chooses the gains, the other fits the curve
    gain = gains(doc[hit], place, len(vocabulary), label, fold) if len(vocabulary) else np.zeros(0)
    model = ToxicityModel(vocabulary, rarity * gain, gain, None, ids, label, base)
    n = np.concatenate([np.zeros(0, dtype=np.int32), *(np.frombuffer(r["counts"], dtype=np.int32) for r in rows)])
    order = np.lexsort((place, doc[hit]))
    doc, term, n = doc[hit][order], place[order], n[hit][order]
    weight, begins = model.vectors(doc, term, n, len(rows))
    place = similar_together(doc, term, weight, label, max(1, len(vocabulary)))
    order = np.argsort(place)
    model.ids, model.toxic = ids[order], label[order]
    model.index = BlockMaxIndex.build(place[doc], term, weight, len(rows), max(1, len(vocabulary)))
    fit = np.flatnonzero(~fold)
    votes = np.array([model.vote(*model.index.find(term[begins[i] : begins[i + 1]], weight[begins[i] : begins[i + 1]], k, without=int(place[i]))) for i in fit])
    model.curve = _curve(votes, label[fit])
    return model


def similar_together(doc: np.ndarray, term: np.ndarray, weight: np.ndarray, label: np.ndarray, width: int, most: int = 256) -> np.ndarray:
    """Places of the examples, by label and by angle on the second and third singular vector of the commonest terms.

    Any order gives the same neighbours; this one gives blocks of similar examples, whose bounds are tight.
    """
    panel = BlockMaxIndex.build(doc, term, weight, len(label), width, most).panel
    if min(panel.shape) < 3:
        return np.arange(len(label))
    _, _, axes = np.linalg.svd(panel, full_matrices=False)
    place = np.empty(len(label), dtype=np.int64)
    place[np.lexsort((np.arctan2(axes[2], axes[1]), label))] = np.arange(len(label))
    return place


def _curve(votes: np.ndarray, label: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """Slope and shift of a logistic curve over the log odds of the votes, by Newton steps with a weak prior."""
    if not len(label) or label.min() == label.max():
        return 1.0, 0.0
    x = np.clip(votes, 1e-6, 1 - 1e-6)
    x = np.stack([np.log(x / (1 - x)), np.ones(len(x))])
    theta, prior = np.array([1.0, 0.0]), np.array([1.0, 0.0])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(theta @ x, -30, 30)))
        slope = x @ (label - p) - 0.1 * (theta - prior)
        theta = theta + np.linalg.solve((x * np.maximum(p * (1 - p), 1e-9)) @ x.T + 0.1 * np.eye(2), slope).clip(-2, 2)
    return max(float(theta[0]), 1e-3), float(theta[1])


def _groups(texts: Iterator[bytes], bytes_at_once: int = 1 << 20, texts_at_once: int = 256) -> Iterator[list[bytes]]:
    held, size = [], 0
    for text in texts:
        held.append(text)
        size += len(text)
        if size >= bytes_at_once or len(held) >= texts_at_once:
            yield held
            held, size = [], 0
    if held:
        yield held


def _scores(model: ToxicityModel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            votes = [model.vote(found[0], found[1]) for texts in _groups(x.as_py() for x in b.column(1)) for found in model.search(texts, others=False)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.probability(np.array(votes, dtype=float)))], ["doc_id", "score"])

    return run


def _searched(model: ToxicityModel):
    types = (pa.list_(pa.int32()), pa.list_(pa.float64()), pa.float64(), pa.list_(pa.struct([("term", pa.int64()), ("n", pa.int32())])))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for texts in _groups(x.as_py() for x in b.column(1)):
                for example, near, known_part, terms, n in model.search(texts):
                    others = zip(terms.view(np.int64).tolist(), n.tolist(), strict=True) if len(example) else ()
                    rows.append((example.tolist(), near.tolist(), known_part, [{"term": t, "n": c} for t, c in others]))
            columns = zip(*rows, strict=True) if rows else [()] * 4
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, t) for c, t in zip(columns, types, strict=True))], ["doc_id", "examples", "near", "known", "others"])

    return run


def _explained(model: ToxicityModel):
    """Scores and evidence of the rows of ``_searched``, whose length is whole now."""
    shape = pa.list_(pa.struct([("doc_id", pa.int64()), ("cosine", pa.float64()), ("toxic", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            votes, why = np.zeros(b.num_rows), []
            length = np.sqrt(b.column("square").to_numpy(zero_copy_only=False))
            for i, (example, near) in enumerate(zip(b.column("examples").to_pylist(), b.column("near").to_pylist(), strict=True)):
                example, near = np.array(example, dtype=np.int64), np.array(near)
                votes[i] = model.vote(example, near)
                why.append([{"doc_id": d, "cosine": c, "toxic": t} for d, c, t in zip(model.ids[example].tolist(), (near / (length[i] or 1)).tolist(), model.toxic[example].astype(int).tolist(), strict=True)])
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(model.probability(votes)), pa.array(why, shape)], ["doc_id", "score", "evidence"])

    return run


def score_toxicity(docs: DataFrame, model: ToxicityModel, evidence: bool = True) -> DataFrame:
    """``(doc_id, score, evidence)`` for each row; ``evidence`` lists the nearest examples with cosine and label.

    Without ``evidence`` one pass over the texts is enough: neighbours and votes don't depend on
    a text's length.  With it, terms that no example has are weighted by their frequency in
    ``docs``, which takes a join by term.  Null texts count as empty; a text without a term of
    any example has no neighbours and gets the score of that case.  Repeated rows get a row
    each; other columns are ignored; an empty table gives no rows, and a model without examples
    scores by its prior alone.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().cast("binary").alias("text"))
    if not evidence:
        return texts.mapInArrow(released(_scores(model)), "doc_id long, score double")
    found = texts.mapInArrow(released(_searched(model)), "doc_id long, examples array<int>, near array<double>, known double, others array<struct<term: long, n: int>>")
    found = stored(found.withColumn("row", F.monotonically_increasing_id()))
    total = found.count()
    words = found.select("row", F.inline("others"))
    often = words.groupBy("term").agg(F.count("*").alias("docs")).where("docs > 1")
    rarity = (F.log((total + 1) / (F.coalesce("docs", F.lit(1)) + 1)) + 1e-3) * FLOOR
    square = F.pow((1 + F.log("n")) * rarity, 2)
    rest = words.join(often, "term", "left").groupBy("row").agg((F.sum(F.round(square / STEP).cast("long")) * STEP).alias("rest"))
    whole = found.drop("others").join(rest, "row", "left").select("doc_id", "examples", "near", (F.col("known") + F.coalesce("rest", F.lit(0.0))).alias("square"))
    slim = ToxicityModel(np.zeros(0), np.zeros(0), np.zeros(0), None, model.ids, model.toxic, model.base, model.curve)
    return whole.mapInArrow(released(_explained(slim)), "doc_id long, score double, evidence array<struct<doc_id: long, cosine: double, toxic: int>>")


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    held_out = F.crc32(F.col("doc_id").cast("string")) % 5 == 0
    return score_toxicity(docs, model, evidence=False).select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
