import itertools
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from metricblock.llm import line_crf, toxicity
from metricblock.llm.line_crf import LineChain, line_features


@pytest.fixture(scope="module")
def tables(spark):
    d = "/root/testdata/sf0.01"
    return spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet"), d


def test_marginals_against_all_labellings():
    rng = np.random.default_rng(0)
    chain = LineChain(np.zeros((14, 9)), np.zeros((3, 14, 11)), 0.0, np.array([0.7, 1.3]))
    per_doc = np.array([1, 4, 2])
    emission = rng.standard_normal(7)
    got = chain.marginals(emission, per_doc)
    for first, n in zip((0, 1, 5), per_doc, strict=True):
        e = emission[first : first + n]
        weight = {y: np.exp(sum(e[i] for i in range(n) if y[i]) + sum((0.7, 1.3)[y[i]] for i in range(n - 1) if y[i] == y[i + 1])) for y in itertools.product((0, 1), repeat=int(n))}
        for i in range(n):
            assert abs(got[first + i] - sum(w for y, w in weight.items() if y[i]) / sum(weight.values())) < 1e-9


def test_fit_raises_the_likelihood():
    texts = [b"good line of text.\nanother good line here.", b"BAD!! BAD!! BAD!!\nBAD!! WORSE!!"] * 20
    features, per_doc, _ = line_features(texts)
    model = LineChain.blank(features).fit(features, per_doc, np.array([1, 0] * 20))
    scores = model.scores(texts)
    assert scores[0] > 0.9 and scores[1] < 0.1


def test_lines():
    features, per_doc, length = line_features([b"", b"a a b\n\na a b", b"X!"])
    assert per_doc.tolist() == [1, 3, 1] and length.tolist() == [0, 5, 0, 5, 2]
    copies = features[:, line_crf.FEATURES.index("copies")]
    assert copies.tolist() == [0, 0, 0, 1, 0]
    again = features[:, line_crf.FEATURES.index("again")]
    assert again[1] == pytest.approx(1 / 3)


def held(rows, modulus, left):
    return all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % modulus == left) and 0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in rows)


def test_quality_on_held_out_documents(spark, tables):
    docs, labels, d = tables
    rows = line_crf.op9_line_crf(spark, d).join(labels, "doc_id").collect()
    assert held(rows, 3, 1)
    out = [r for r in rows if r["held_out"]]
    assert np.mean([r["predicted"] == r["quality"] for r in out]) > 0.97
    assert line_crf.op9_line_crf(spark, d).count() == docs.count()


def test_toxicity_on_held_out_documents(spark, tables):
    docs, labels, d = tables
    rows = toxicity.op3_toxicity(spark, d).join(labels, "doc_id").collect()
    assert held(rows, 5, 0)
    out = [r for r in rows if r["held_out"]]
    assert np.mean([r["predicted"] == r["toxic"] for r in out]) > 0.9
    assert toxicity.op3_toxicity(spark, d).count() == docs.count()


def test_block_max_search_is_exact():
    rng = np.random.default_rng(0)
    dense = rng.random((500, 40)) * (rng.random((500, 40)) < 0.2)
    dense[100:110] = dense[7]
    example, term = np.nonzero(dense)
    for q, panel in itertools.product(dense[::25], (0, 8, 40)):
        index = toxicity.BlockMaxIndex.build(example, term, dense[example, term], 500, 40, panel)
        terms = np.flatnonzero(q)
        score = dense @ q
        order = [i for i in np.lexsort((np.arange(500), -np.round(score, 9))) if score[i] > 0][:15]
        found, near = index.find(terms, q[terms], 15)
        assert np.allclose(near, score[found]) and np.allclose(near, score[order])


def test_toxicity_is_the_cosine_over_all_terms(spark):
    rows = [(i, f"common word number{i} only{i} only{i} here", i % 2) for i in range(40)]
    rows += [(40, "common strange stranger strange", None), (41, "strange word", None), (42, rows[7][1], None), (43, "nothing shared", None)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    model = toxicity.train(docs, spark.createDataFrame([(r[0], r[2]) for r in rows if r[2] is not None], "doc_id long, toxic int"))
    gain_of = dict(zip(model.vocabulary.tolist(), model.gain.tolist(), strict=True))
    gain = lambda w: gain_of.get(int(toxicity.terms_of([w.encode()])[1][0]), toxicity.FLOOR)
    vectors, texts = {}, {r[0]: r[1].split() for r in rows}
    for i, t in texts.items():
        v = {w: gain(w) * (1 + np.log(t.count(w))) * (np.log(45 / (1 + sum(w in o for o in texts.values()))) + 1e-3) for w in t}
        vectors[i] = {w: x / np.sqrt(sum(y * y for y in v.values())) for w, x in v.items()}
    found = {r["doc_id"]: r["evidence"] for r in toxicity.score_toxicity(docs, model).collect()}
    examples = [r[0] for r in rows if r[2] is not None and zlib.crc32(str(r[0]).encode()) % 5 != 0]
    for i in texts:
        exact = sorted((sum(x * vectors[e].get(w, 0) for w, x in vectors[i].items()) for e in examples), reverse=True)
        exact = [c for c in exact if c > 0][: toxicity.NEIGHBOURS]
        assert np.allclose([e["cosine"] for e in found[i]], exact)
        assert all(np.isclose(e["cosine"], sum(x * vectors[e["doc_id"]].get(w, 0) for w, x in vectors[i].items())) for e in found[i])
    assert len(found[40]) == toxicity.NEIGHBOURS and not found[43]
    assert (found[42][0]["doc_id"] == 7) == (7 in examples)


def test_labels_are_read_from_the_given_rows_only(spark, tables):
    docs, labels, _ = tables
    kept = labels.where(F.crc32(F.col("doc_id").cast("string")) % 5 != 0)
    rows = line_crf.labelled_sample(docs, labels, "toxic", 10_000, 5, 0).select("doc_id").collect()
    assert {r[0] for r in rows} <= {r["doc_id"] for r in kept.collect()}
    assert line_crf.labelled_sample(docs, labels, "toxic", 7, 5, 0).count() == 7


def test_odd_rows(spark, odd, none, tables):
    docs, labels, _ = tables
    no_labels = labels.limit(0)
    for model in (line_crf.train(docs, labels), line_crf.train(none, no_labels)):
        assert line_crf.score_quality(odd, model).count() == 10 and line_crf.score_quality(none, model).count() == 0
        scored = line_crf.with_scores(odd, model, "line_score")
        assert scored.columns == [*odd.columns, "line_score"] and scored.count() == 10
    assert all(r["score"] == 0.5 for r in line_crf.score_quality(odd, line_crf.train(none, no_labels)).collect())
    for model in (toxicity.train(docs, labels), toxicity.train(none, no_labels)):
        rows = toxicity.score_toxicity(odd, model).collect()
        assert len(rows) == 10 and all(0 <= r["score"] <= 1 for r in rows)
        assert toxicity.score_toxicity(none, model).count() == 0
