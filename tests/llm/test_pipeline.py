import random
from collections import defaultdict

import corpus_pipeline
from metricblock.llm.common import stored


def test_stages(spark):
    """Each stage by a plain check of what it has to keep and to drop, on its own input."""
    d = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    quality, near, passages, mixing, packing = (f for _, f in corpus_pipeline.STAGES)
    columns = docs.columns

    one = stored(quality(spark, docs, d))
    kept = {r["doc_id"] for r in one.select("doc_id").collect()}
    assert one.columns == columns and sum((i in kept) == bool(q) for i, q in labels.items()) > 0.97 * len(labels)

    two = stored(near(spark, one, d))
    exact = defaultdict(list)
    for r in one.collect():
        exact[r["text"]].append(r["doc_id"])
    ids = {r["doc_id"] for r in two.select("doc_id").collect()}
    assert two.columns == columns and ids < kept and all(not set(g[1:]) & ids for g in map(sorted, exact.values()))

    three = stored(passages(spark, two, d))
    seen, again = set(), 0
    for r in sorted(three.collect(), key=lambda r: r["doc_id"]):
        w = r["text"].split()
        assert r["n_chars"] == len(r["text"])
        for i in range(len(w) - 19):
            again += tuple(w[i : i + 20]) in seen
            seen.add(tuple(w[i : i + 20]))
    assert three.columns == columns and again == 0

    four = stored(mixing(spark, three, d))
    times = defaultdict(int)
    for r in four.select("doc_id").collect():
        times[r[0]] += 1
    assert four.columns == columns and max(times.values()) <= 2 and set(times) <= ids
    words = lambda df: sum(len(r["text"].split()) for r in df.select("text").collect())
    assert abs(words(four) / words(three) - 1.5) < 0.05

    last = packing(spark, four, d)
    length = defaultdict(int)
    for r in last.collect():
        length[r["sequence_id"]] += r["length"]
    assert sum(n != 1024 for n in length.values()) <= 10 * four.rdd.getNumPartitions()


def test_near_dedup_keeps_different_texts_of_null_or_shared_ids(spark, sf):
    text = lambda tag: " ".join(f"{tag}{i}" for i in range(60))
    rows = [(None, text("a")), (None, text("b")), (None, text("b")), (5, text("c")), (5, text("d")), (5, text("d")), (7, text("d")), (3, text("e")), (5, text("e")), (None, text("c"))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = corpus_pipeline.one_of_each_group(spark, docs.repartition(4), sf)
    got = sorted(((r["doc_id"], r["text"]) for r in kept.collect()), key=str)
    assert kept.columns == docs.columns
    assert got == sorted([(None, text("a")), (None, text("b")), (5, text("c")), (5, text("d")), (3, text("e"))], key=str)


def test_stages_with_clashing_names(spark, odd, sf):
    docs = odd
    for _, stage in corpus_pipeline.STAGES[1:4]:
        docs = stored(stage(spark, docs, sf))
        assert docs.columns == odd.columns and docs.count() > 0


def test_near_dedup_finds_edited_copies(spark, sf):
    rng = random.Random(4)
    word = lambda: "".join(rng.choices("abcdefghij", k=6))
    rows, gone = [], set()
    for base in range(60):
        text = [word() for _ in range(rng.choice([60, 200, 800]))]
        rows.append((base * 10, " ".join(text)))
        for copy in range(1, 4):
            edited = list(text)
            for _ in range(max(1, len(text) // 80)):
                edited[rng.randrange(len(text))] = word()
            shingles = [{tuple(t[i : i + 5]) for i in range(len(t) - 4)} for t in (text, edited)]
            if len(shingles[0] & shingles[1]) / len(shingles[0] | shingles[1]) >= 0.85:
                gone.add(base * 10 + copy)
                rows.append((base * 10 + copy, " ".join(edited)))
        half = text[: len(text) // 2] + [word() for _ in range(len(text) // 2)]
        rows.append((base * 10 + 9, " ".join(half)))
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r["doc_id"] for r in corpus_pipeline.one_of_each_group(spark, docs.repartition(4), sf).select("doc_id").collect()}
    assert len(gone) > 100 and len(gone & kept) <= 0.05 * len(gone)
    assert {i for i, _ in rows} - gone <= kept


def test_run(spark, sf):
    assert corpus_pipeline.run(spark, sf).count() > 0


def test_empty(spark, sf, none):
    docs = none
    for _, stage in corpus_pipeline.STAGES:
        docs = stored(stage(spark, docs, sf))
    assert docs.count() == 0


def test_near_dedup_leaves_no_copy_of_the_texts(spark):
    """What the stage leaves in the shared folder is less than its texts: the next stage's tables come beside it."""
    from pathlib import Path

    from metricblock.llm.common import scratch_root

    d = "/root/testdata/sf0.01"
    size = lambda path: sum(f.stat().st_size for f in Path(path.removeprefix("file:")).rglob("*.parquet"))
    docs = spark.read.parquet(f"{d}/documents.parquet")
    before = size(scratch_root(spark))
    kept = corpus_pipeline.one_of_each_group(spark, docs, d)
    assert 0 < size(scratch_root(spark)) - before < 0.5 * Path(f"{d}/documents.parquet").stat().st_size
    assert kept.count() > 0
