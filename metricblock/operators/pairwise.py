"""All pairs of a table's rows, by blocks: what is made of two blocks leaves the task, the pairs stay inside.

Rows are packed into blocks of a fixed number.  Two lists of blocks meet without a shuffle; a
task gets two blocks at a time and works on them as arrays.  Work is quadratic, memory is not.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.sources.scratch import stored

BLOCK = 1024
#: Blocks in a part of the right side, which a task goes through for each block of the left one.
RIGHT = 512


def packed(df: DataFrame, rows: int = BLOCK) -> DataFrame:
    """``(block long, data binary)``: the rows of ``df``, so many in a block, as Arrow streams; stored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        number = TaskContext.get().partitionId() << 33
        held: list[pa.RecordBatch] = []

        def out(some: pa.Table) -> pa.RecordBatch:
            nonlocal number
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, some.schema) as writer:
                writer.write_table(some.combine_chunks())
            number += 1
            return pa.RecordBatch.from_arrays([pa.array([number - 1]), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["block", "data"])

        for b in batches:
            held += [b] if b.num_rows else []
            while sum(x.num_rows for x in held) >= rows:
                whole = pa.Table.from_batches(held)
                yield out(whole.slice(0, rows))
                held = whole.slice(rows).to_batches()
        if held:
            yield out(pa.Table.from_batches(held))

    return stored(df.mapInArrow(run, "block long, data binary"))


def unpacked(data: bytes) -> pa.Table:
    return pa.ipc.open_stream(data).read_all()


def parallel(df: DataFrame) -> int:
    """Tasks for quadratic work."""
    return max(1, 4 * df.sparkSession.sparkContext.defaultParallelism)


def meet(left: DataFrame, right: DataFrame, make: Callable, work: Callable, schema: str, triangle: bool = False, end: Callable | None = None) -> DataFrame:
    """``work(x, y, same)`` of every block of ``left`` with every one of ``right``, both ``packed``; ``make`` turns a block's table into x or y.

    With ``triangle``, for one table with itself, two blocks meet once; ``same`` tells a block that meets itself.
    ``work`` gives record batches.  The blocks of the right side follow one another for each left
    block; ``end(x)`` is asked for batches when the left block changes.
    """
    tasks, n = parallel(left), left.count()
    # dealt in turn from few lists, since keys by hash would leave some tasks empty and others with several blocks
    x = left.coalesce(max(1, -(-n // RIGHT))).select(F.col("block").alias("bx"), F.col("data").alias("x")).repartition(max(1, min(tasks, n)))
    y = right.select(F.col("block").alias("by"), F.col("data").alias("y")).coalesce(max(1, -(-right.count() // RIGHT)))
    # a block meets the half of the blocks that its number's parity says, so that tasks have equal shares
    odd = F.pmod(F.xxhash64(F.least("bx", "by"), F.greatest("bx", "by")), F.lit(2)) == 1
    once = (F.col("bx") == F.col("by")) | (odd & (F.col("bx") < F.col("by"))) | (~odd & (F.col("bx") > F.col("by")))
    both = x.hint("shuffle_replicate_nl").join(y, once if triangle else F.lit(True))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, mine = None, None
        for b in batches:
            bx, by = b.column(0).to_pylist(), b.column(2).to_pylist()
            for r in range(b.num_rows):
                if bx[r] != last:
                    if end and mine is not None:
                        yield from end(mine)
                    last, mine = bx[r], make(unpacked(b.column(1)[r].as_buffer()))
                yield from work(mine, make(unpacked(b.column(3)[r].as_buffer())), bx[r] == by[r])
        if end and mine is not None:
            yield from end(mine)

    return both.select("bx", "x", "by", "y").mapInArrow(run, schema)


def sliced(arrays: list[np.ndarray], names: list[str], rows: int = 1 << 16) -> Iterator[pa.RecordBatch]:
    for a in range(0, len(arrays[0]), rows):
        yield pa.RecordBatch.from_arrays([pa.array(x[a : a + rows]) for x in arrays], names)
