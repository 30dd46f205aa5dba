"""What the operators of this package share: tables, words, texts."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from metricblock.sources.scratch import drop, scratch_root, stored

__all__ = ["WORD", "drop", "released", "scratch_root", "stored", "table", "text_of", "unused"]

#: Rows of an Arrow batch: whole texts travel in them, on both sides and in both directions at once.
BATCH_ROWS = 1_000
GIVE_BACK_BYTES = 8 << 20
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"

#: A word, in Java's, Python's and DuckDB's syntax: what ASCII white space leaves.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_of(column: str = "text") -> F.Column:
    """The whole text; null counts as empty."""
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def unused(df: DataFrame, *names: str) -> list[str]:
    """``names``, each with underscores put before it until no column of ``df`` has that name."""
    taken, found = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        found.append(name)
    return found


def _give_back() -> None:
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def released(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run`` for mapInArrow, that gives freed memory back to the system after every few batches: workers live on, and so would what they held.

    The session's batches are kept to ``BATCH_ROWS`` rows; a smaller setting of the user's stays.
    """
    conf = SparkSession.builder.getOrCreate().conf
    if not 0 < int(conf.get(_BATCH)) <= BATCH_ROWS:
        conf.set(_BATCH, str(BATCH_ROWS))

    def fed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        passed = 0
        for b in batches:
            passed += b.nbytes
            yield b
            del b
            if passed >= GIVE_BACK_BYTES:
                _give_back()
                passed = 0

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(fed(batches))
        _give_back()

    return wrapped
