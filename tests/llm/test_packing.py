import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from metricblock.llm.packing import Packer, encoder, op1_packing, pack_documents

PATH = public_tokenizers.path("byte_bpe_50k.json")


@given(st.text(max_size=300))
@settings(max_examples=300, deadline=None)
def test_ids_are_those_of_the_tokenizers_library(text):
    reference = Tokenizer.from_file(PATH)
    reference.encode_special_tokens = True
    assert encoder(PATH)(text) == reference.encode(text, add_special_tokens=False).ids


def packed(sizes, window=16):
    p = Packer(window)
    rows = [r for i, n in enumerate(sizes) for r in p.add(i, np.arange(n, dtype="<u4"))]
    return rows + list(p.close())


@given(st.lists(st.integers(0, 50), max_size=60))
@settings(max_examples=300, deadline=None)
def test_every_id_lies_in_one_piece_and_nothing_needs_padding(sizes):
    rows = packed(sizes)
    ids, length = defaultdict(list), defaultdict(int)
    for doc, start, piece, total, sequence, offset in sorted(rows, key=lambda r: (r[4], r[5])):
        assert offset == length[sequence] and total == sizes[doc] and list(piece) == list(range(start, start + len(piece)))
        length[sequence] += len(piece)
        ids[doc] += list(piece)
    assert all(sorted(ids[i]) == list(range(n)) for i, n in enumerate(sizes))
    assert all(n == 16 or n & (n - 1) == 0 for n in length.values())
    assert sum(n != 16 for n in length.values()) <= 4


def test_level_minimises_the_sum_of_squares():
    rng = np.random.default_rng(0)
    for _ in range(300):
        p = Packer(12)
        p.counts[1:12] = rng.integers(0, 4, 11)
        size = int(rng.integers(1, 12))

        def after(level):
            c = p.counts.copy()
            c[level] -= level > 0
            c[level + size] += level + size < 12
            return (c[1:12] ** 2).sum()

        options = [0] + [h for h in range(1, 13 - size) if p.counts[h]]
        assert after(p.level_for(size)) == min(map(after, options))


def test_query_over_the_table(spark, sf):
    rows = op1_packing(spark, sf).collect()
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    encode = encoder(PATH)
    ids = {k: np.array(encode(t or "") + [0], dtype="<u4") for k, t in texts.items()}
    assert sum(r["length"] for r in rows) == sum(map(len, ids.values()))
    assert all(r["ids_crc32"] == zlib.crc32(ids[r["doc_id"]][r["start"] : r["start"] + r["length"]].tobytes()) for r in rows)


def test_odd_rows(odd, none):
    rows = pack_documents(odd, PATH).collect()
    for doc in (1, 2):
        assert [r["ids"] for r in rows if r["doc_id"] == doc] == [[0]]
    assert sum(r["length"] for r in rows if r["doc_id"] == 4) == 2 * len(encoder(PATH)("one two three four five") + [0])
    assert pack_documents(none, PATH).count() == 0
