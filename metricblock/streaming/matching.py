"""Query matching on streams.

Distances, placement and search of a shipped index are stateless, so a stream of queries runs
through the same plan as a batch, in append mode, and gives the same rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from metricblock.operators.querymatch import ReferenceIndex


def match_stream(index: ReferenceIndex, queries: DataFrame, k: int = 150, theta: float = 2, id_col: str = "q_id") -> DataFrame:
    """A stream of ``(q_id, rec_id, delta, rank, dist)``; the index has to be of the shipped kind."""
    if index.strategy == "partitioned":
        raise ValueError("an index in cells is searched per micro-batch: use match_batches")
    return index.match(queries, k, theta, id_col)


def match_batches(newest: Callable[[], ReferenceIndex], queries: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str, k: int = 150, theta: float = 2) -> StreamingQuery:
    """Match every micro-batch against the newest version of the index; a batch sees one version."""

    def one(batch: DataFrame, number: int) -> None:
        index = newest()
        sink(index.match(batch, k, theta).withColumn("version", F.lit(index.version)), number)

    return queries.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def once_each(queries: DataFrame, time_col: str, key_cols: list[str], delay: str = "10 minutes") -> DataFrame:
    """Repeated queries within the watermark are answered once."""
    return queries.withWatermark(time_col, delay).dropDuplicatesWithinWatermark(key_cols)


def first_unmatched(unmatched: DataFrame, key: str = "key") -> DataFrame:
    """Of a stream of unmatched queries each key once, however often it comes: what ``absorb`` should add.

    Keeps one flag per key as state.
    """

    def step(key: tuple, rows: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        first = next(rows)
        for _ in rows:
            pass
        if not state.exists:
            state.update((True,))
            yield first.head(1)

    schema = unmatched.schema
    return unmatched.groupBy(key).applyInPandasWithState(step, schema, "seen boolean", "append", "NoTimeout")


def absorbed(index: ReferenceIndex, queries: DataFrame, checkpoint: str, k: int = 150, theta: float = 2, id_col: str = "q_id") -> ReferenceIndex:
    """The index after a stream of queries: those of a micro-batch that match nothing become records of the next version."""
    versions = [index]

    def one(batch: DataFrame, number: int) -> None:
        now = versions[-1]
        hit = now.match(batch, k, theta, id_col).select(F.col("q_id").alias(id_col)).distinct()
        versions.append(now.absorb(batch.join(hit, id_col, "left_anti"), id_col))

    queries.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return versions[-1]


def drained(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there now into Parquet, and read the result."""
    writer = stream.writeStream.outputMode(mode).format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state")
    query = writer.trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{path}/out")
