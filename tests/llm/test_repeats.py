import hashlib
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from metricblock.llm import passage_dedup, repeats, suffix_dedup, suffixes
from metricblock.llm.repeats import Kind, keyed, repeated_stretches


@given(st.binary(max_size=60).map(lambda b: bytes(97 + x % 3 for x in b)))
@settings(max_examples=200, deadline=None)
def test_longest_previous_factors(data):
    n = len(data)
    expected = [max([0] + [next((k for k in range(n - i, 0, -1) if data[j : j + k] == data[i : i + k]), 0) for j in range(i)]) for i in range(n)]
    assert suffix_dedup.longest_previous_factors(data).tolist() == expected


@given(st.permutations(range(20)))
def test_neighbours_with_smaller_values(values):
    v = np.array(values)
    assert suffixes.previous_smaller(v).tolist() == [max([j for j in range(i) if v[j] < v[i]], default=-1) for i in range(20)]
    assert suffixes.next_smaller(v).tolist() == [min([j for j in range(i + 1, 20) if v[j] < v[i]], default=20) for i in range(20)]


@given(st.lists(st.text("ab", min_size=4, max_size=12), min_size=1, max_size=8), st.booleans())
@settings(max_examples=200, deadline=None)
def test_solvers_agree_with_counting(texts, later):
    pieces = [t.encode() for t in texts]
    windows = [p[i : i + 4] for p in pieces for i in range(len(p) - 3)]
    count, seen, expected = Counter(windows), set(), []
    for w in windows:
        expected.append(w in seen if later else count[w] > 1)
        seen.add(w)
    assert suffix_dedup.repeated_windows(pieces, Kind("byte", 4, 2, later)).tolist() == expected


@given(st.lists(st.lists(st.sampled_from("abc"), min_size=3, max_size=9), min_size=1, max_size=8), st.integers(1, 5))
@settings(max_examples=200, deadline=None)
def test_subtrees_agree_with_counting(texts, most):
    pieces = [" ".join(t).encode() for t in texts]
    seen, expected = set(), []
    for t in texts:
        for i in range(len(t) - 2):
            expected.append(tuple(t[i : i + 3]) in seen)
            seen.add(tuple(t[i : i + 3]))
    assert passage_dedup.later_windows(pieces, Kind("word", 3, 1, True), most).tolist() == expected


def brute(texts, width, later, words):
    """{doc: covered flags}, documents in order of their ids."""
    units = {i: t.encode().split() if words else t.encode() for i, t in sorted(texts.items())}
    windows = Counter(tuple(u[k : k + width]) for u in units.values() for k in range(len(u) - width + 1))
    seen, out = set(), {}
    for i, u in units.items():
        flags = np.zeros(len(u), dtype=bool)
        for k in range(len(u) - width + 1):
            w = tuple(u[k : k + width])
            if w in seen if later else windows[w] > 1:
                flags[k : k + width] = True
            seen.add(w)
        out[i] = flags
    return out


def corpus(seed=0, n=60, words=True):
    """Texts that share passages, near copies, a very frequent one, and texts that repeat themselves."""
    rng = np.random.default_rng(seed)
    word = lambda: "w%d" % rng.integers(0, 400)
    shared = [" ".join(word() for _ in range(rng.integers(4, 40))) for _ in range(6)]
    texts = {}
    for i in range(n):
        parts = [" ".join(word() for _ in range(rng.integers(0, 30)))]
        for _ in range(rng.integers(0, 4)):
            parts += [shared[int(rng.integers(0, 6))], " ".join(word() for _ in range(rng.integers(0, 12)))]
        parts.append(shared[0])
        texts[i] = " ".join(parts)
    texts[n] = "ab " * 200
    texts[n + 1] = texts[3]
    texts[n + 2] = texts[3][: len(texts[3]) // 2]
    return texts


@pytest.mark.parametrize("unit,width,gram,later", [("word", 6, 2, True), ("word", 6, 2, False), ("byte", 40, 12, True), ("byte", 40, 12, False)])
@pytest.mark.parametrize("group_up_to", [2, 256])
def test_stretches_against_brute_force(spark, monkeypatch, unit, width, gram, later, group_up_to):
    """With groups of two at most every level of longer grams is gone through; with small flushes and chunks, documents are cut."""
    monkeypatch.setattr(repeats, "FLUSH", 64)
    texts = corpus()
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3)
    solver = passage_dedup.later_windows if unit == "word" and later else suffix_dedup.repeated_windows
    if unit == "word" and not later:
        pytest.skip("no solver for words counts later places")
    cuts = {r["doc"]: r["cuts"] for r in repeated_stretches(docs, Kind(unit, width, gram, later, group_up_to), solver).collect()}
    for i, flags in brute(texts, width, later, unit == "word").items():
        got = np.zeros(len(flags), dtype=bool)
        for c in cuts.get(i, []):
            got[c["start"] : c["stop"]] = True
        assert (got == flags).all(), i


def test_queries_against_brute_force(spark, sf):
    texts = {r["doc_id"]: r["text"] or "" for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    bytes_ = {r["doc_id"]: r for r in suffix_dedup.op4_suffix_array(spark, sf).collect()}
    for i, flags in brute(texts, 400, False, False).items():
        kept = bytes(np.frombuffer(texts[i].encode(), dtype=np.uint8)[~flags])
        runs = int((np.diff(np.concatenate([[0], flags.astype(int)])) == 1).sum())
        assert (bytes_[i]["n_bytes"], bytes_[i]["n_removed"], bytes_[i]["n_spans"], bytes_[i]["kept_sha256"]) == (len(flags), flags.sum(), runs, hashlib.sha256(kept).hexdigest())
    words = {r["doc_id"]: r for r in passage_dedup.op7_passages(spark, sf).collect()}
    for i, flags in brute(texts, 20, True, True).items():
        kept = b" ".join(w for w, gone in zip(texts[i].encode().split(), flags, strict=True) if not gone)
        assert (words[i]["n_words"], words[i]["n_removed"], words[i]["kept_sha256"]) == (len(flags), flags.sum(), hashlib.sha256(kept).hexdigest())


def test_odd_rows(odd, none):
    rows = suffix_dedup.remove_repeated_bytes(odd, width=10, keep_first=False).collect()
    by = {r["doc_id"]: r for r in rows}
    assert len(rows) == 10 and by[1]["n_bytes"] == by[2]["n_bytes"] == 0 and by[1]["kept"] == b""
    assert by[4]["n_removed"] == by[5]["n_removed"] == 23 and by[8]["n_removed"] == 50_000 and by[None]["n_removed"] == 0
    rows = passage_dedup.remove_repeated_passages(odd, width=3).collect()
    by = {r["doc_id"]: r for r in rows}
    assert len(rows) == 10 and by[1]["n_words"] == 0 and by[3]["kept"] == " \t\n"
    assert by[4]["n_removed"] == 0 and by[5]["n_removed"] == 5 and by[7]["n_removed"] == 29_999 and by[6]["kept"] == "Größe 東京 naïve"
    assert suffix_dedup.remove_repeated_bytes(none).count() == passage_dedup.remove_repeated_passages(none).count() == 0
    assert keyed(none).count() == 0


def test_cut_texts_keep_columns_and_white_space(spark):
    docs = spark.createDataFrame([(1, "a b c\nd e", "x"), (2, "z  a b c\nq", "y"), (3, None, "w")], "doc_id long, text string, cuts string")
    rows = {r["doc_id"]: r for r in passage_dedup.cut_texts(docs, 3).collect()}
    assert (rows[1]["text"], rows[2]["text"], rows[3]["text"]) == ("a b c\nd e", "z  q", None)
    assert [rows[i]["cuts"] for i in (1, 2, 3)] == ["x", "y", "w"] and rows[2]["_n_removed"] == 3


def test_windows_are_those_of_long_factors():
    rng = np.random.default_rng(2)
    for later in (True, False):
        pieces = [bytes(rng.integers(97, 99, n).astype(np.uint8)) for n in (60, 30, 44, 30)] + [b"ab" * 20]
        units = np.concatenate([np.append(np.frombuffer(p, dtype=np.uint8).astype(np.int64), 256 + i) for i, p in enumerate(pieces)])
        inside = np.concatenate([np.arange(len(p) + 1) <= len(p) - 9 for p in pieces])
        long = suffix_dedup.longest_factors(units, 9) >= 9
        if not later:
            long |= suffix_dedup.longest_factors(units, 9, later=True) >= 9
        found = suffix_dedup.repeated_windows(pieces, Kind("byte", 9, 3, later=later))
        assert found.tolist() == long[inside].tolist()
