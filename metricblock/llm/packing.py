"""Sum-of-squares online packing of token sequences into fixed windows.

Every document's ids are cut at the window size; whole windows are done at once.  The rest of
a document goes where it keeps the open windows most evenly spread over the fill levels: a
level array counts the windows of each level, and of all levels that leave room (and of a
fresh window) the one is taken after which the sum of squared counts is smallest.

Each task packs its own input split, so nothing is shuffled, and a task that is run again
gives the same rows.  What a task leaves open at its end is closed by cutting: the emptiest
windows fill up the fullest, and the last rest becomes sequences whose lengths are powers of
two.  So no sequence needs padding, and a task adds at most ten short sequences.
"""

from __future__ import annotations

import json
import zlib
from collections import defaultdict
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from metricblock.llm.common import released, table, text_of

WINDOW = 1024
_encoders: dict[str, Callable[[str], list[int]]] = {}


def _byte_letters() -> dict[str, int]:
    """The letters by which a byte-level vocabulary file writes the 256 bytes."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    other = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(other)}


def encoder(path: str) -> Callable[[str], list[int]]:
    """text -> ids of the byte-level vocabulary in ``path``, a ``tokenizers`` file.

    The ids are those of that library.  They are made by ``tiktoken`` from the vocabulary of
    the same file, at about five times the speed; on first use in a process both encode some
    texts, and a difference is an error.
    """
    if path not in _encoders:
        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        reference = Tokenizer.from_file(path)
        reference.encode_special_tokens = True
        with open(path, encoding="utf-8") as f:
            parsed = json.load(f)
        special = {t["content"] for t in parsed["added_tokens"]}
        letters = _byte_letters()
        ranks = {bytes(letters[c] for c in token): i for token, i in parsed["model"]["vocab"].items() if token not in special}
        fast = tiktoken.Encoding("from-file", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        for probe in ("", "It's  a\ttest,\n\n 12 or 1234!? ", "Éte naïve 東京 ​😀 <|endoftext|>", "a" * 300):
            if fast.encode_ordinary(probe) != reference.encode(probe, add_special_tokens=False).ids:
                raise ValueError(f"{path}: the two tokenizers differ on {probe!r}")
        _encoders[path] = fast.encode_ordinary
    return _encoders[path]


class Packer:
    """Packs pieces one by one.  ``add`` and ``close`` yield finished rows.

    A row is (document, start, ids, ids of the whole document, sequence, offset).
    Open windows hold their pieces, since closing may cut them; their number stays small, as
    the rule keeps every level's count low.
    """

    def __init__(self, window: int = WINDOW, first_sequence: int = 0):
        self.window, self.sequence = window, first_sequence
        self.counts = np.zeros(window + 1, dtype=np.int64)
        self.open: dict[int, list[list]] = defaultdict(list)  # level -> windows, each a list of pieces

    def level_for(self, size: int) -> int:
        """The level whose window takes ``size`` more ids; 0 is a fresh window."""
        counts, room = self.counts, self.window - size
        change = 2 * (counts[size : self.window + 1] - counts[: room + 1]) + 2
        change[0] = 2 * counts[size] + 1
        change[room] -= 2 * counts[self.window] + 1  # a full window is no longer counted
        usable = counts[: room + 1] > 0
        usable[0] = True
        change[~usable] = np.iinfo(np.int64).max
        return room - int(np.argmin(change[::-1]))  # ties go to the fullest

    def add(self, doc, ids: np.ndarray) -> Iterator[tuple]:
        total = len(ids)
        whole = total - total % self.window
        for start in range(0, whole, self.window):
            yield from self._seal([(doc, start, ids[start : start + self.window], total)])
        if whole == total:
            return
        piece = (doc, whole, ids[whole:], total)
        size = total - whole
        level = self.level_for(size)
        pieces = []
        if level:
            pieces = self.open[level].pop()
            self.counts[level] -= 1
        pieces.append(piece)
        level += size
        if level == self.window:
            yield from self._seal(pieces)
        else:
            self.open[level].append(pieces)
            self.counts[level] += 1

    def close(self) -> Iterator[tuple]:
        rest = [p for level in sorted(self.open, reverse=True) for p in self.open[level]]
        self.open.clear()
        self.counts[:] = 0
        first, last = 0, len(rest) - 1
        while first < last:
            need = self.window - sum(len(p[2]) for p in rest[first])
            while need and first < last:
                taken, rest[last] = _cut(rest[last], need)
                rest[first] += taken
                need -= sum(len(p[2]) for p in taken)
                if not rest[last]:
                    last -= 1
            if not need:
                yield from self._seal(rest[first])
                first += 1
        if first == last:
            pieces = rest[first]
            while pieces:
                left = sum(len(p[2]) for p in pieces)
                part, pieces = _cut(pieces, 1 << (left.bit_length() - 1))
                yield from self._seal(part)

    def _seal(self, pieces: list) -> Iterator[tuple]:
        offset = 0
        for doc, start, ids, total in pieces:
            yield doc, start, ids, total, self.sequence, offset
            offset += len(ids)
        self.sequence += 1


def _cut(pieces: list, size: int) -> tuple[list, list]:
    """The first ``size`` ids of ``pieces``, or all if they are fewer, and the rest."""
    head, at = [], 0
    while at < len(pieces) and size:
        doc, start, ids, total = pieces[at]
        if len(ids) > size:
            head.append((doc, start, ids[:size], total))
            return head, [(doc, start + size, ids[size:], total), *pieces[at + 1 :]]
        head.append(pieces[at])
        size -= len(ids)
        at += 1
    return head, pieces[at:]


def _batches(rows: Iterable[tuple], doc_type: pa.DataType, with_ids: bool, rows_at_once: int = 16384, ids_at_once: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    held: list[tuple] = []
    size = 0

    def batch() -> pa.RecordBatch:
        docs, starts, ids, totals, sequences, offsets = zip(*held, strict=True)
        columns = {
            "doc_id": pa.array(docs, doc_type),
            "start": pa.array(starts, pa.int64()),
            "length": pa.array(list(map(len, ids)), pa.int64()),
            "ids_crc32": pa.array([zlib.crc32(x.tobytes()) for x in ids], pa.int64()),
            "doc_tokens": pa.array(totals, pa.int64()),
            "sequence_id": pa.array(sequences, pa.int64()),
            "offset": pa.array(offsets, pa.int64()),
        }
        if with_ids:
            ends = np.cumsum([0, *map(len, ids)], dtype=np.int32)
            columns["ids"] = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(ids).astype(np.int32)))
        held.clear()
        return pa.RecordBatch.from_pydict(columns)

    for row in rows:
        held.append(row)
        size += len(row[2])
        if len(held) >= rows_at_once or size >= ids_at_once:
            yield batch()
            size = 0
    if held:
        yield batch()


def pack_documents(docs: DataFrame, tokenizer: str, window: int = WINDOW, end_id: int = 0, with_ids: bool = True) -> DataFrame:
    """One row for each piece of each document; with ``with_ids`` the ids themselves as well.

    Reads ``doc_id`` (long; null stays null) and ``text`` alone, whatever other columns there
    are.  A null or empty text is the end id alone.  Repeated rows are packed each.  A document
    longer than the window spans several sequences.  An empty table gives no rows.
    """

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        packer = Packer(window, TaskContext.get().partitionId() << 40)
        end = [end_id]

        def rows():
            for b in batches:
                for doc, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                    yield from packer.add(doc, np.array(encode(text.as_py()) + end, dtype="<u4"))
            yield from packer.close()

        yield from _batches(rows(), pa.int64(), with_ids)

    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    return docs.select(docs["doc_id"].cast("long"), text_of().alias("text")).mapInArrow(released(pack), schema + ", ids array<int>" * with_ids)


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), with_ids=False)
