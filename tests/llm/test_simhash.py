import re

import numpy as np
import xxhash

from metricblock.llm.simhash import PAIR_UP_TO, fingerprint, golay_indices, near_duplicates, near_pairs, op6_simhash
from metricblock.operators.clusters import components


def plain_fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or ([" ".join(words)] if words else [])
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h)) if h else 0


def brute(prints):
    """id -> smallest id reachable, of (id, fingerprint) pairs."""
    ids, f = np.array([i for i, _ in prints]), np.array([x for _, x in prints], dtype=np.uint64)
    near = np.bitwise_count(f[:, None] ^ f[None, :]) <= 2
    comp = ids.copy()
    while True:
        new = np.array([comp[near[i]].min() for i in range(len(ids))])
        if (new == comp).all():
            return dict(zip(ids.tolist(), comp.tolist(), strict=True))
        comp = new


def test_golay_indices_meet_within_two_bits():
    flips = [0] + [1 << i for i in range(23)] + [1 << i | 1 << j for i in range(23) for j in range(i)]
    # one word of each distance from its codeword stands for all: the code is linear and the flips are exhaustive
    rng = np.random.default_rng(0)
    for v in rng.integers(0, 1 << 23, 40):
        near = v ^ np.array(flips)
        of, index = golay_indices(near)
        own = set(index[of == 0].tolist())
        assert all(own & set(index[of == i].tolist()) for i in range(len(flips)))


def test_fingerprints(spark, odd):
    for t in ("", " ", "One", "a B", "a b c", "a b c d a b c d", "Ä b\x0bc\td  e f g", "x y z " * 5000):
        assert fingerprint(t.encode()) == plain_fingerprint(t)


def test_query_against_brute_force(spark, sf):
    rows = op6_simhash(spark, sf).collect()
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    assert {r["doc_id"]: r["fingerprint"] for r in rows} == {k: f"{plain_fingerprint(t):016x}" for k, t in texts.items()}
    assert {r["doc_id"]: r["component_id"] for r in rows} == brute([(r["doc_id"], int(r["fingerprint"], 16)) for r in rows])


def test_large_groups_of_near_copies_keep_their_links(spark):
    rng = np.random.default_rng(1)
    base = int(rng.integers(0, 1 << 62))
    prints = {base}
    while len(prints) < 6 * PAIR_UP_TO:  # a chain of copies, each one or two bits from an earlier one
        x = int(rng.choice(np.array(sorted(prints), dtype=np.uint64)))
        for b in rng.integers(0, 64, int(rng.integers(1, 3))):
            x ^= 1 << int(b)
        prints.add(x)
    prints |= {int(x) for x in rng.integers(0, 1 << 63, 300)}
    signed = sorted(x - (1 << 64) if x >> 63 else x for x in prints)
    df = spark.createDataFrame([(x,) for x in signed], "fingerprint long")
    got = {r["id"]: r["component"] for r in components(near_pairs(df)).collect()}
    expected = brute([(x, x & (1 << 64) - 1) for x in signed])
    assert {x: got.get(x, x) for x in signed} == expected


def test_odd_rows(odd, none):
    rows = near_duplicates(odd).collect()
    by = {r["doc_id"]: r for r in rows}
    assert len(rows) == 10 and by[1]["fingerprint"] == by[2]["fingerprint"] == by[3]["fingerprint"] == 0
    assert [by[i]["component_id"] for i in (1, 2, 3, 4, 5)] == [1, 1, 1, 4, 4]
    assert near_duplicates(none).count() == 0
