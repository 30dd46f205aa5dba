"""Fixtures, dissimilarities and record comparison, over whole tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from metricblock import workloads as W
from metricblock.functions import distance as D
from metricblock.functions.text import ascii_fold
from metricblock.operators import records as R
from metricblock.operators import vectors
from metricblock.queries.registry import query

PART = R.BlockingSpec(("p_name", "p_brand", "p_type"), normalizer="none")


def r6(c) -> F.Column:
    """Six digits; adding zero turns a negative zero to a plain one."""
    return F.round(c, 6) + F.lit(0.0)


@query("WITH" + W.NAMES_SQL + " SELECT given, surname FROM names_all")
def fx_names_all(spark, sf):
    return W.names_all(spark, sf)


@query("WITH" + W.names_ref_sql() + " SELECT rec_id, rec_id AS entity_id, given, surname FROM names_ref")
def fx_names_ref(spark, sf):
    return W.names_ref(spark, sf)


for profile in W.PROFILES:

    @query("WITH" + W.names_query_sql(profile=profile) + " SELECT q_id, entity_id, given, surname FROM names_query", f"fx_names_query_{profile}")
    def fx_names_query(spark, sf, profile=profile):
        return W.names_query(spark, sf, profile=profile).drop("n_typos")


@query("WITH" + W.names_dedup_sql() + " SELECT * FROM names_dedup")
def fx_names_dedup(spark, sf):
    return W.names_dedup(spark, sf)


@query("WITH" + W.names_dedup_sql() + W.GOLD_SQL + " SELECT a, b FROM gold")
def fx_gold_pairs(spark, sf):
    return W.gold_pairs(W.names_dedup(spark, sf))


@query("WITH" + W.TITLES_SQL + " SELECT rec_id, title FROM page_titles")
def fx_page_titles(spark, sf):
    return W.page_titles(spark, sf)


@query("SELECT p_name, p_brand, p_type, CAST(count(*) AS BIGINT) AS freq FROM part GROUP BY ALL")
def fx_key_dictionary(spark, sf):
    d = R.key_dictionary(R.blocking_keys(W.table(spark, sf, "part"), "p_partkey", PART))
    return d.select(*[F.get("key", F.lit(i)).alias(c) for i, c in enumerate(PART.cols)], "freq")


@query("SELECT c_custkey, c_name, n_name, c_mktsegment FROM customer JOIN nation ON c_nationkey = n_nationkey")
def fx_customer_profile(spark, sf):
    """Records as name-value maps, and back."""
    c = W.table(spark, sf, "customer").join(W.table(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    names = ("c_name", "n_name", "c_mktsegment")
    profile = c.select("c_custkey", F.create_map(*[x for n in names for x in (F.lit(n), F.col(n))]).alias("attrs"))
    return profile.select("c_custkey", *[F.element_at("attrs", n).alias(n) for n in names])


PARTS = "SELECT p_partkey, p_name AS a, p_type AS b FROM part"


def part_pairs(spark, sf):
    return W.table(spark, sf, "part").select("p_partkey", F.col("p_name").alias("a"), F.col("p_type").alias("b"))


@query(f"SELECT p_partkey, CAST(levenshtein(a, b) AS BIGINT) AS d FROM ({PARTS})")
def dist_levenshtein(spark, sf):
    return part_pairs(spark, sf).select("p_partkey", D.levenshtein("a", "b").cast("long").alias("d"))


@query(f"SELECT p_partkey, CAST(CASE WHEN levenshtein(a, b) <= 15 THEN levenshtein(a, b) ELSE -1 END AS BIGINT) AS d FROM ({PARTS})")
def dist_levenshtein_capped(spark, sf):
    return part_pairs(spark, sf).select("p_partkey", D.levenshtein("a", "b", 15).cast("long").alias("d"))


QUERY_PAIRS = "WITH" + W.names_query_sql(profile="typos3") + ", pairs AS (SELECT q_id, q.given AS a, r.given AS b, q.surname AS c, r.surname AS d FROM names_query q JOIN names_ref r ON r.rec_id = q.entity_id)"


def query_pairs(spark, sf):
    r = W.names_ref(spark, sf).select("entity_id", F.col("given").alias("b"), F.col("surname").alias("d"))
    return W.names_query(spark, sf, profile="typos3").select("q_id", "entity_id", F.col("given").alias("a"), F.col("surname").alias("c")).join(r, "entity_id")


@query(QUERY_PAIRS + " SELECT q_id, round(jaro_similarity(a, b), 6) AS s FROM pairs")
def dist_jaro(spark, sf):
    return query_pairs(spark, sf).select("q_id", r6(D.jaro("a", "b")).alias("s"))


@query(QUERY_PAIRS + " SELECT q_id, round(jaro_winkler_similarity(a, b), 6) AS s FROM pairs")
def dist_jaro_winkler(spark, sf):
    return query_pairs(spark, sf).select("q_id", r6(D.jaro_winkler("a", "b")).alias("s"))


GRAMS = """, g AS (SELECT q_id, list_transform(range(1, length(a)), lambda i: substr(a, i, 2)) AS x, list_transform(range(1, length(b)), lambda i: substr(b, i, 2)) AS y FROM pairs)"""


@query(QUERY_PAIRS + GRAMS + ", u AS (SELECT q_id, x, y, unnest(list_distinct(list_concat(x, y))) AS t FROM g) SELECT q_id, CAST(sum(abs(len(list_filter(x, lambda z: z = t)) - len(list_filter(y, lambda z: z = t)))) AS BIGINT) AS d FROM u GROUP BY q_id")
def dist_qgram_bag(spark, sf):
    return query_pairs(spark, sf).select("q_id", D.qgram("a", "b").cast("long").alias("d"))


@query(QUERY_PAIRS + GRAMS + " SELECT q_id, CAST(len(list_distinct(list_concat(x, y))) - len(list_intersect(list_distinct(x), list_distinct(y))) AS BIGINT) AS d FROM g")
def dist_qgram_set(spark, sf):
    return query_pairs(spark, sf).select("q_id", D.qgram("a", "b", kind="set").cast("long").alias("d"))


@query("WITH" + W.names_query_sql(profile="typos2") + ", pairs AS (SELECT q_id, n_typos, q.given AS a, r.given AS b FROM names_query q JOIN names_ref r ON r.rec_id = q.entity_id) SELECT q_id, CAST(damerau_levenshtein(a, b) AS BIGINT) AS d FROM pairs WHERE n_typos = 1")
def dist_osa_single_edit(spark, sf):
    """With one typo the restricted and the unrestricted form agree."""
    r = W.names_ref(spark, sf).select("entity_id", F.col("given").alias("b"))
    one = W.names_query(spark, sf).where("n_typos = 1").select("q_id", "entity_id", F.col("given").alias("a")).join(r, "entity_id")
    return one.select("q_id", D.osa("a", "b").cast("long").alias("d"))


VECTOR_PAIRS = "WITH e AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings), p AS (SELECT x.vec_id AS a, y.vec_id AS b, list_transform(list_zip(x.v, y.v), lambda z: abs(z[1] - z[2])) AS g FROM e x JOIN e y ON x.vec_id < y.vec_id)"


def vectors_of(spark, sf):
    return W.table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))


for label, p, sql in (("p1", 1, "list_sum(g)"), ("p2", 2, "sqrt(list_sum(list_transform(g, lambda z: z * z)))"), ("p3", 3, "pow(list_sum(list_transform(g, lambda z: pow(z, 3))), 1.0 / 3)"), ("inf", float("inf"), "list_max(g)")):

    @query(VECTOR_PAIRS + f" SELECT a, b, round({sql}, 6) AS d FROM p", f"dist_minkowski_{label}")
    def dist_minkowski(spark, sf, p=p):
        return vectors.pair_rows(vectors_of(spark, sf), p, digits=6)


@query(QUERY_PAIRS + " SELECT q_id, CAST(levenshtein(a, b) + levenshtein(c, d) AS BIGINT) AS score, levenshtein(a, b) + levenshtein(c, d) <= 2 AS is_match FROM pairs")
def dist_record_score_sum(spark, sf):
    score = D.record_score([D.levenshtein("a", "b"), D.levenshtein("c", "d")]).cast("long")
    return query_pairs(spark, sf).select("q_id", score.alias("score"), D.classify(score, 2).alias("is_match"))


@query(QUERY_PAIRS + " SELECT q_id, CAST(levenshtein(a || ' ' || c, b || ' ' || d) AS BIGINT) AS score, 2.0::DOUBLE * levenshtein(a, b) + 0.5::DOUBLE * levenshtein(c, d) AS weighted FROM pairs")
def dist_record_concat(spark, sf):
    x, y = F.array("a", "c"), F.array("b", "d")
    return query_pairs(spark, sf).select("q_id", D.key_delta(x, y, "concat").cast("long").alias("score"), D.key_delta(x, y, "weighted", (2.0, 0.5)).alias("weighted"))


@query("SELECT doc_id, CAST(coalesce(levenshtein(a, b), 0) AS BIGINT) AS delta, CAST(CASE WHEN a IS NULL OR b IS NULL THEN 0 ELSE 1 END AS BIGINT) AS w FROM (SELECT d.doc_id, source AS a, CASE WHEN toxic = 1 THEN lang END AS b FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id)")
def dist_missing_weight(spark, sf):
    d = W.table(spark, sf, "documents").join(W.table(spark, sf, "labels"), "doc_id", "left").select("doc_id", F.col("source").alias("a"), F.when(F.col("toxic") == 1, F.col("lang")).alias("b"))
    delta, w = D.attribute_delta(F.col("a"), F.col("b"))
    return d.select("doc_id", delta.cast("long").alias("delta"), w.cast("long").alias("w"))


LANDMARKS = [["almond antique", "Brand#13", "PROMO"], ["steel", "Brand#55", "STANDARD TIN"], ["", "", ""]]


@query("SELECT p_partkey, [" + ", ".join(f"CAST(levenshtein(p_name, '{a}') + levenshtein(p_brand, '{b}') + levenshtein(p_type, '{c}') AS BIGINT)" for a, b, c in LANDMARKS) + "] AS delta FROM part")
def dist_landmark_vector(spark, sf):
    keys = R.blocking_keys(W.table(spark, sf, "part"), "p_partkey", PART)
    return D.delta_to_landmarks(keys, LANDMARKS).select(F.col("rec_id").alias("p_partkey"), F.transform("delta", lambda x: x.cast("long")).alias("delta"))


@query("WITH v AS (SELECT n_nationkey AS id, n_name AS v FROM nation), t AS (SELECT x.id AS i, y.id AS j, z.id AS k, levenshtein(x.v, y.v) AS xy, levenshtein(y.v, x.v) AS yx, levenshtein(y.v, z.v) AS yz, levenshtein(x.v, z.v) AS xz, x.v = y.v AS same FROM v x, v y, v z) SELECT CAST(count(DISTINCT CASE WHEN same <> (xy = 0) THEN (i, j) END) AS BIGINT) AS identity, CAST(count(DISTINCT CASE WHEN xy <> yx THEN (i, j) END) AS BIGINT) AS symmetry, CAST(count(*) FILTER (xz > xy + yz) AS BIGINT) AS triangle FROM t")
def dist_metric_violations(spark, sf):
    nations = W.table(spark, sf, "nation").select(F.col("n_nationkey").alias("id"), F.col("n_name").alias("value"))
    return D.metric_violations(nations, D.levenshtein)


@query("SELECT doc_id, trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g')) AS folded FROM documents WHERE lang = 'en'")
def dist_ascii_fold(spark, sf):
    return W.table(spark, sf, "documents").where("lang = 'en'").select("doc_id", ascii_fold("text").alias("folded"))


@query(QUERY_PAIRS + " SELECT q_id, round(1 - jaro_similarity(a, b), 6) AS d, round(-ln(0.5 + jaro_similarity(a, b) / 2), 6) AS lg FROM pairs")
def dist_to_dissimilarity(spark, sf):
    s = D.jaro("a", "b")
    return query_pairs(spark, sf).withColumn("s", s).select("q_id", r6(D.to_dissimilarity(F.col("s"))).alias("d"), r6(D.to_dissimilarity(0.5 + F.col("s") / 2, "log")).alias("lg"))
