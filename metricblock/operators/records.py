"""Records, blocking values and the dictionary of distinct values."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.functions.distance import key_delta
from metricblock.functions.text import ascii_fold


@dataclass(frozen=True)
class BlockingSpec:
    """Which attributes make the blocking value, and how their dissimilarities combine.

    ``combine``: "sum" over attributes, "concat" of the values, "weighted", or "split_space"
    (each attribute gets a space of its own).  ``on_missing``: a missing value counts as empty
    text ("max": it differs by the other's whole length) or stops the run ("error").
    """

    cols: tuple[str, ...]
    normalizer: str = "ascii_fold"
    combine: str = "sum"
    weights: tuple[float, ...] | None = None
    on_missing: str = "max"

    def delta(self, a, b):
        return key_delta(a, b, "sum" if self.combine == "split_space" else self.combine, self.weights)

    def parts(self) -> list[BlockingSpec]:
        return [BlockingSpec((c,), self.normalizer, "sum", None, self.on_missing) for c in self.cols] if self.combine == "split_space" else [self]


def check_schema(reference: DataFrame, queries: DataFrame, cols: tuple[str, ...]) -> None:
    """Queries have to share the reference's types in the blocking columns."""
    ours, theirs = dict(reference.dtypes), dict(queries.dtypes)
    wrong = [c for c in cols if ours.get(c) is None or ours.get(c) != theirs.get(c)]
    if wrong:
        raise ValueError(f"columns {wrong} differ: {[(ours.get(c), theirs.get(c)) for c in wrong]}")


def blocking_keys(records: DataFrame, id_col: str, spec: BlockingSpec, out: str = "rec_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """``(rec_id, key array<string>)``, normalized; rows stay where they are."""

    def value(c: str):
        col = F.col(c).cast("string")
        col = ascii_fold(col) if spec.normalizer == "ascii_fold" else col
        gone = F.raise_error(F.lit(f"{c} is missing")) if spec.on_missing == "error" else F.lit("")
        return F.coalesce(col, gone.cast("string"))

    return records.select(F.col(id_col).cast("long").alias(out), F.array(*map(value, spec.cols)).alias("key"), *keep)


def key_dictionary(keys: DataFrame) -> DataFrame:
    """``(key_id, key, freq)`` of the distinct keys.  The id is a hash, so no global numbering is needed."""
    return keys.groupBy("key").agg(F.count("*").alias("freq")).select(F.xxhash64("key").alias("key_id"), "key", "freq")
