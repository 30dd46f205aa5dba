"""Blocks of nearest neighbours, and the candidate pairs they stand for.

A block is ``(q_id, n_id, rank, dist)``: a centre and its neighbours.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from metricblock.operators.records import BlockingSpec


def block_pairs(blocks: DataFrame, mode: str = "star") -> DataFrame:
    """Distinct ``(a, b)``, a < b.  "star": centre and member; "clique": all pairs inside a block.

    A block has a fixed number of members, so a clique costs a fixed number of pairs a block.
    """
    star = blocks.where("q_id <> n_id").select(F.least("q_id", "n_id").alias("a"), F.greatest("q_id", "n_id").alias("b"))
    if mode == "star":
        return star.distinct()
    if mode != "clique":
        raise ValueError(mode)
    members = blocks.groupBy("q_id").agg(F.array_sort(F.array_union(F.collect_list("n_id"), F.array(F.first("q_id")))).alias("m"))
    inner = F.flatten(F.transform("m", lambda x, i: F.transform(F.slice("m", i + 2, F.size("m")), lambda y: F.struct(x.alias("a"), y.alias("b")))))
    return members.select(F.explode(inner).alias("p")).select("p.a", "p.b").distinct()


def filter_pairs(pairs: DataFrame, keys: DataFrame, spec: BlockingSpec, theta: float, id_col: str = "key_id") -> DataFrame:
    """``(a, b, delta)`` of pairs whose original values differ by at most ``theta``."""
    x = keys.select(F.col(id_col).alias("a"), F.col("key").alias("x"))
    y = keys.select(F.col(id_col).alias("b"), F.col("key").alias("y"))
    measured = pairs.join(x, "a").join(y, "b").select("a", "b", spec.delta("x", "y").alias("delta"))
    return measured.where(F.col("delta") <= F.lit(theta))


def expand_pairs(value_pairs: DataFrame, keys: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Pairs of values to pairs of records, with those of equal values (delta 0) added.

    Records of a value pair all match each other, so the rows are the answer itself.
    """
    of = keys.join(dictionary.select("key_id", "key"), "key").select("rec_id", "key_id")
    left, right = of.select(F.col("rec_id").alias("r"), F.col("key_id").alias("a")), of.select(F.col("rec_id").alias("s"), F.col("key_id").alias("b"))
    across = value_pairs.join(left, "a").join(right, "b").select(F.least("r", "s").alias("a"), F.greatest("r", "s").alias("b"), "delta")
    same = of.select(F.col("rec_id").alias("a"), "key_id").join(of.select(F.col("rec_id").alias("b"), "key_id"), "key_id").where("a < b").select("a", "b", F.lit(0).cast(dict(value_pairs.dtypes)["delta"]).alias("delta"))
    return across.unionByName(same)


def expand_links(value_pairs: DataFrame, keys: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Links ``(a, b, delta)`` with the components of ``expand_pairs``, a row a record and a row a value pair.

    The smallest record of a value stands for it; the others are linked to that one.
    """
    kind = dict(value_pairs.dtypes)["delta"]
    of = keys.join(dictionary.select("key_id", "key"), "key").select("rec_id", "key_id")
    heads = of.groupBy("key_id").agg(F.min("rec_id").alias("head"))
    same = of.join(heads, "key_id").where("rec_id <> head").select(F.col("head").alias("a"), F.col("rec_id").alias("b"), F.lit(0).cast(kind).alias("delta"))
    x, y = heads.select(F.col("key_id").alias("a"), F.col("head").alias("x")), heads.select(F.col("key_id").alias("b"), F.col("head").alias("y"))
    return value_pairs.join(x, "a").join(y, "b").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "delta").unionByName(same)


def block_sizes(blocks: DataFrame) -> DataFrame:
    """How many members blocks have: one row of count, least, most and mean."""
    per = blocks.groupBy("q_id").agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("blocks"), F.min("n").alias("least"), F.max("n").alias("most"), F.avg("n").alias("mean"))
