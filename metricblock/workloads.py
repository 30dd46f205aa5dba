"""Deterministic workloads on the given tables, each as a DataFrame and as SQL.

Person-like names come from neighbouring words of English documents; a corruptor makes erroneous
copies with a known number of typos.  All choices hang on md5, so both engines agree.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from metricblock.functions.text import ascii_fold, hash8
from metricblock.sources.scratch import stored

#: Sizes of the published experiments.
REFERENCE, QUERIES, DEDUP = 5_000, 500, 5_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


# --- names ------------------------------------------------------------------------------------

NAMES_SQL = """
folded AS (SELECT string_split(trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g')), ' ') AS w FROM documents WHERE lang = 'en'),
word_pairs AS (SELECT w[2 * i + 1] AS given, w[2 * i + 2] AS surname FROM folded, unnest(range(0, len(w) // 2)) AS t(i)),
names_all AS (SELECT DISTINCT given, surname FROM word_pairs WHERE length(given) BETWEEN 5 AND 12 AND length(surname) BETWEEN 5 AND 12)"""


def names_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct ``(given, surname)``: words 1 and 2, 3 and 4, ... of English documents, 5 to 12 letters each."""
    w = F.split(ascii_fold("text"), " ")
    halves = table(spark, sf_dir, "documents").where("lang = 'en'").select(w.alias("w")).where("size(w) >= 2")
    at = F.sequence(F.lit(0), F.floor(F.size("w") / 2).cast("int") - 1)
    pairs = halves.select(F.explode(F.transform(at, lambda i: F.struct(F.get("w", i * 2).alias("given"), F.get("w", i * 2 + 1).alias("surname")))).alias("p")).select("p.*")
    return pairs.where("length(given) between 5 and 12 and length(surname) between 5 and 12").distinct()


def names_ref_sql(n: int = REFERENCE) -> str:
    return NAMES_SQL + f""",
names_ref AS (SELECT CAST(row_number() OVER (ORDER BY md5(given || '|' || surname)) AS BIGINT) AS rec_id, given, surname
  FROM (SELECT * FROM names_all ORDER BY md5(given || '|' || surname) LIMIT {n}))"""


def names_ref(spark: SparkSession, sf_dir: str, n: int = REFERENCE) -> DataFrame:
    """The reference of the experiments: ``(rec_id, entity_id, given, surname)``, the first n names by md5."""
    order = F.md5(F.concat_ws("|", "given", "surname"))
    top = names_all(spark, sf_dir).orderBy(order).limit(n)
    return top.select(F.row_number().over(Window.orderBy(order)).cast("long").alias("rec_id"), "given", "surname").select("rec_id", F.col("rec_id").alias("entity_id"), "given", "surname")


# --- corruptor --------------------------------------------------------------------------------

Hash = Callable[[str], str]
SPARK_HASH: Hash = lambda s: f"CAST(conv(substr(md5({s}), 1, 8), 16, 10) AS BIGINT)"
DUCK_HASH: Hash = lambda s: f"CAST(('0x' || substr(md5({s}), 1, 8)) AS BIGINT)"


def _typo(word: str, seed: str, h: Hash) -> str:
    """SQL for ``word`` with one typo: substitute, delete, insert or transpose."""
    at = f"CAST(1 + {h(seed + " || '|at'")} % length({word}) AS INT)"
    letter = h(seed + " || '|letter'")
    kind = f"{h(seed + " || '|kind'")} % 4"
    head, one, rest = f"substr({word}, 1, {at} - 1)", f"substr({word}, {at}, 1)", f"substr({word}, {at} + 1)"
    two = f"substr({word}, {at} + 1, 1)"
    other = f"{head} || chr(CAST(97 + (ascii({one}) - 97 + 1 + {letter} % 25) % 26 AS INT)) || {rest}"
    return (
        f"CASE WHEN {kind} = 1 AND length({word}) > 2 THEN {head} || {rest} "
        f"WHEN {kind} = 2 THEN {head} || chr(CAST(97 + {letter} % 26 AS INT)) || {one} || {rest} "
        f"WHEN {kind} = 3 AND {at} < length({word}) AND {one} <> {two} THEN {head} || {two} || {one} || substr({word}, {at} + 2) "
        f"ELSE {other} END"
    )


def _corrupt_steps(typos: tuple[int, int], h: Hash, tag: str) -> list[list[str]]:
    """Select lists, one per step, over columns ``given, surname, seed`` and any carried along by ``*``."""
    low, high = typos
    count = h(f"'{tag}|t|' || seed")
    steps = [[f"{low} + {count} % {high - low + 1} AS n_typos"]]
    for i in range(1, high + 1):
        seed = f"('{tag}|{i}|' || seed)"
        side = h(seed + " || '|side'")
        steps.append(
            [
                f"CASE WHEN {i} <= n_typos AND {side} % 2 = 0 THEN {_typo('given', seed, h)} ELSE given END AS given",
                f"CASE WHEN {i} <= n_typos AND {side} % 2 = 1 THEN {_typo('surname', seed, h)} ELSE surname END AS surname",
            ]
        )
    return steps


def corrupted(df: DataFrame, typos: tuple[int, int], tag: str) -> DataFrame:
    """``df`` with typos in ``given`` and ``surname``; the number is in ``n_typos``."""
    out = df.withColumn("seed", F.concat_ws("|", "given", "surname"))
    first, *others = _corrupt_steps(typos, SPARK_HASH, tag)
    out = out.selectExpr("*", *first)
    for i, step in enumerate(others):
        if i and i % 2 == 0:  # steps that are merged into one expression grow beyond what can be compiled
            out = stored(out)
        keep = [c for c in out.columns if c not in ("given", "surname")]
        out = out.selectExpr(*keep, *step)
    return stored(out.drop("seed"))


def corrupted_sql(source: str, keep: list[str], typos: tuple[int, int], tag: str, name: str) -> str:
    """CTEs that end with ``name`` = ``source`` corrupted."""
    kept = ", ".join(keep)
    first, *others = _corrupt_steps(typos, DUCK_HASH, tag)
    out = f"\n{name}_0 AS (SELECT *, {first[0]} FROM (SELECT {kept}, given, surname, given || '|' || surname AS seed FROM {source}) AS s)"
    for i, step in enumerate(others, 1):
        out += f",\n{name}_{i} AS (SELECT {kept}, seed, n_typos, {', '.join(step)} FROM {name}_{i - 1})"
    return out + f",\n{name} AS (SELECT {kept}, n_typos, given, surname FROM {name}_{len(others)})"


PROFILES = {"typos2": (1, 2), "typos3": (1, 3), "heavy": (4, 6), "exact": (0, 0)}


def names_query(spark: SparkSession, sf_dir: str, n: int = REFERENCE, q: int = QUERIES, profile: str = "typos2") -> DataFrame:
    """``(q_id, entity_id, n_typos, given, surname)``: q corrupted copies of reference records."""
    order = [hash8("q", F.col("given"), F.col("surname")), F.col("rec_id")]
    top = names_ref(spark, sf_dir, n).orderBy(*order).limit(q)
    asked = top.select(F.row_number().over(Window.orderBy(*order)).cast("long").alias("q_id"), "entity_id", "given", "surname")
    return corrupted(asked, PROFILES[profile], profile)


def names_query_sql(n: int = REFERENCE, q: int = QUERIES, profile: str = "typos2") -> str:
    order = f"{DUCK_HASH("'q|' || given || '|' || surname")}, rec_id"
    return (
        names_ref_sql(n)
        + f""",
asked AS (SELECT CAST(row_number() OVER (ORDER BY {order}) AS BIGINT) AS q_id, rec_id AS entity_id, given, surname
  FROM (SELECT * FROM names_ref ORDER BY {order} LIMIT {q})),"""
        + corrupted_sql("asked", ["q_id", "entity_id"], PROFILES[profile], profile, "names_query")
    )


def names_dedup(spark: SparkSession, sf_dir: str, n: int = DEDUP, share: float = 0.10, profile: str = "typos2") -> DataFrame:
    """``(rec_id, entity_id, given, surname)`` in which ``share`` of the n records are corrupted copies of others."""
    copies = round(n * share)
    base = names_ref(spark, sf_dir, n - copies)
    order = [hash8("d", F.col("given"), F.col("surname")), F.col("rec_id")]
    picked = base.orderBy(*order).limit(copies)
    renumbered = picked.select((F.row_number().over(Window.orderBy(*order)) + n).cast("long").alias("rec_id"), "entity_id", "given", "surname")
    return base.unionByName(corrupted(renumbered, PROFILES[profile], "d" + profile).select("rec_id", "entity_id", "given", "surname"))


def names_dedup_sql(n: int = DEDUP, share: float = 0.10, profile: str = "typos2") -> str:
    copies = round(n * share)
    order = f"{DUCK_HASH("'d|' || given || '|' || surname")}, rec_id"
    return (
        names_ref_sql(n - copies)
        + f""",
picked AS (SELECT CAST(row_number() OVER (ORDER BY {order}) + {n} AS BIGINT) AS rec_id, rec_id AS entity_id, given, surname
  FROM (SELECT * FROM names_ref ORDER BY {order} LIMIT {copies})),"""
        + corrupted_sql("picked", ["rec_id", "entity_id"], PROFILES[profile], "d" + profile, "copied")
        + """,
names_dedup AS (SELECT rec_id, rec_id AS entity_id, given, surname FROM names_ref UNION ALL SELECT rec_id, entity_id, given, surname FROM copied)"""
    )


GOLD_SQL = """,
gold AS (SELECT a.rec_id AS a, b.rec_id AS b FROM names_dedup a JOIN names_dedup b ON a.entity_id = b.entity_id AND a.rec_id < b.rec_id)"""


def gold_pairs(records: DataFrame) -> DataFrame:
    """``(a, b)``, a < b, of records of one entity."""
    one = records.select("entity_id", F.col("rec_id").alias("a"))
    return one.join(one.withColumnRenamed("a", "b"), "entity_id").where("a < b").select("a", "b")


# --- other tables as blocking values ----------------------------------------------------------

TITLES_SQL = """
page_titles AS (SELECT page_id AS rec_id, trim(regexp_replace(lower(regexp_extract(html, '<title>([^<]*)</title>', 1)), '[^a-z]+', ' ', 'g')) AS title FROM pages)"""


def page_titles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(rec_id, title)`` of all pages, folded."""
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("rec_id"), ascii_fold(F.regexp_extract("html", "<title>([^<]*)</title>", 1)).alias("title"))


def space7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(id, coords)``: the first seven coordinates of every vector, a given space of the usual dimension."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.slice("embedding", 1, 7).cast("array<double>").alias("coords"))


SPACE7_SQL = """
space7 AS (SELECT vec_id AS id, CAST(embedding[1:7] AS DOUBLE[]) AS coords FROM embeddings)"""


# --- natural near-copies and further tables ----------------------------------------------------

DOC_KEYS_SQL = """
doc_keys AS (SELECT rec_id, opening FROM (SELECT doc_id AS rec_id, trim(substr(trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g')), 1, 64)) AS opening FROM documents WHERE lang = 'en') WHERE length(opening) > 0)"""


def doc_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(rec_id, opening)``: the first 64 folded letters of English documents, whose copies differ as they happen to."""
    docs = table(spark, sf_dir, "documents").where("lang = 'en'")
    return docs.select(F.col("doc_id").alias("rec_id"), F.trim(F.substring(ascii_fold("text"), 1, 64)).alias("opening")).where("length(opening) > 0")
