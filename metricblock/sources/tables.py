"""Readers and writers with explicit schemas, over the shared folder."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession

from metricblock.sources.scratch import scratch_path

FORMATS = ("parquet", "orc", "json", "csv", "text")


def read(spark: SparkSession, path: str, schema, fmt: str = "parquet", **options) -> DataFrame:
    """A table of a known schema: nothing is inferred from the data."""
    if fmt not in FORMATS:
        raise ValueError(fmt)
    return spark.read.format(fmt).options(**options).schema(schema).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: Sequence[str] = (), mode: str = "errorifexists", **options) -> None:
    df.write.format(fmt).options(**options).mode(mode).partitionBy(*partition_by).save(path)


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """``df`` through a file format and back."""
    path = scratch_path(df.sparkSession, fmt)
    options = {"header": "true", "escape": '"'} if fmt == "csv" else {}
    write(df, path, fmt, **options)
    return read(df.sparkSession, path, df.schema, fmt, **options)


def partitioned(df: DataFrame, by: Sequence[str]) -> DataFrame:
    """``df`` by directories of ``by``, which later filters prune."""
    path = scratch_path(df.sparkSession, "partitioned")
    write(df.repartition(*by), path, partition_by=by)
    return read(df.sparkSession, path, df.schema)


def bucketed(df: DataFrame, name: str, buckets: int, by: Sequence[str]) -> DataFrame:
    """``df`` as a table bucketed and sorted by its join key, so that later joins need no exchange."""
    df.write.bucketBy(buckets, *by).sortBy(*by).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)
