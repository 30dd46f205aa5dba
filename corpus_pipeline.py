"""A corpus from raw documents to packed token sequences, in five stages.

Each stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame, which is written and read
again as the next one's ``docs``.  All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from metricblock.llm import line_crf, mixing, packing, passage_dedup, simhash
from metricblock.llm.common import drop, stored, table, text_of, unused
from metricblock.operators.clusters import components


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line model rates good (score of at least 0.5)."""
    model = line_crf.train(docs, table(spark, sf_dir, "labels"))
    (score,) = unused(docs, "line_score")
    return line_crf.with_scores(docs, model, score).where(F.col(score) >= 0.5).select(*docs.columns)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates the document with the smallest id, null last, then by text.

    Texts whose sets of five-word shingles have a Jaccard similarity of 0.8 or more are near-
    duplicates; candidates come from SimHash fingerprints of 512 bits and Golay keys.  Rows are
    told apart by id and whole text: different texts stay, whatever their ids.
    """
    text, again, id_ = unused(docs, "text_hash", "second_hash", "id_long")
    named = docs.withColumns({text: F.xxhash64(text_of()), again: F.xxhash64(F.lit(1), text_of()), id_: F.col("doc_id").cast("long")})
    plain = named.select(F.col(id_).alias("doc_id"), F.col(text).alias("hash"), F.col(again).alias("hash_2"), text_of().alias("text"))
    # texts stay in ``docs``: a copy of them here would lie beside the next stage's tables
    marked = stored(simhash.fingerprinted(plain, "words").select("doc_id", "hash", "hash_2", "words", F.xxhash64("words").alias("print")))
    who = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "print", "hash", "hash_2")
    prints = stored(marked.groupBy(F.col("print").alias("id")).agg(F.min("words").alias("words"), F.min(who).alias("head")))
    drop(marked)

    h_id, h_text, h_again, h_print = unused(docs, "head_id", "head_hash", "head_second_hash", "head_print")

    def of_heads(heads: DataFrame, how: str) -> DataFrame:
        heads = heads.select("head.*").select(F.col("doc_id").alias(h_id), F.col("hash").alias(h_text), F.col("hash_2").alias(h_again), F.col("print").alias(h_print))
        return named.join(heads, F.col(id_).eqNullSafe(F.col(h_id)) & (F.col(text) == F.col(h_text)) & (F.col(again) == F.col(h_again)), how)

    def heads_texts(ids: DataFrame) -> DataFrame:
        found = of_heads(prints.join(ids, "id", "left_semi"), "inner")
        return found.select(F.col(h_print).alias("id"), text_of().cast("binary").alias("text")).dropDuplicates(["id"])

    links = simhash.verified(simhash.similar_pairs(prints), heads_texts, 512)
    rooted = prints.join(components(links), "id", "left")
    kept = of_heads(rooted.groupBy(F.coalesce("component", "id")).agg(F.min("head").alias("head")), "left_semi")
    row = F.min(F.struct(*[F.col(f"`{c}`") for c in docs.columns])).alias("row")
    return kept.groupBy(id_, text, again).agg(row).select("row.*")


def passages_once(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages that occur earlier; documents of which nothing is left go."""
    cut = passage_dedup.cut_texts(docs).where(~((F.col("_n_removed") > 0) & (F.length(F.trim("text")) == 0)))
    return cut.withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def target_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it: not at all, once or twice."""
    mixed, _ = mixing.mix_documents(docs, boundary="whole")
    times = F.when(F.col("_size") > 0, F.col("_taken") / F.col("_size")).otherwise(F.lit(0)).cast("int")
    return mixed.withColumn("_nth", F.explode(F.array_repeat(F.lit(0), times))).select(*docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences of at most 1024 ids, with their ids."""
    import public_tokenizers

    return packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("quality classifier", good_quality),
    ("SimHash near-dedup", one_of_each_group),
    ("substring dedup", passages_once),
    ("mixing sources to target weights", target_mix),
    ("packing", packed),
]

#: Training, hashing and tokenizing have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
