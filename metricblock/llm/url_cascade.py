"""URL rules held in Bloom filter cascades.

A list of keys becomes a chain of Bloom filters.  The first holds the keys; the second holds
those keys of the corpus that the first accepts wrongly; the third holds the listed keys that
the second accepts, and so on until a level accepts nothing wrongly.  Over the keys the chain
was built for, which are all keys any url of the corpus can ask for, membership is exact, and
asking takes a few bit tests in the scan: no join and no exchange.

A key is a host suffix followed by a path prefix.  Everything runs in Spark's own functions.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from metricblock.llm.common import unused

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: A filter travels inside the plan, so its size has a limit: 2**23 bits, one megabyte.
MAX_BITS = 1 << 23


@dataclass(frozen=True)
class Bloom:
    """Words of 64 bits; ``probes`` hashes, seeded by the level so that levels fail apart."""

    level: int
    probes: int
    words: tuple[int, ...] = field(repr=False)

    def accepts(self, key: Column) -> Column:
        words = F.lit(list(self.words))
        hit = F.lit(True)
        for at in bit_positions(key, self.level, self.probes, len(self.words) * 64):
            word = F.get(words, F.shiftright(at, 6).cast("int"))
            hit = hit & (_bit(word, at) == 1)
        return hit


def _bit(word: Column, at: Column) -> Column:
    # the shift is a column, which only the SQL form of the function takes
    return F.call_function("shiftrightunsigned", word, at.bitwiseAND(F.lit(63)).cast("int")).bitwiseAND(F.lit(1))


def bit_positions(key: Column, level: int, probes: int, bits: int) -> list[Column]:
    return [F.xxhash64(key, F.lit(level), F.lit(i)).bitwiseAND(F.lit(bits - 1)) for i in range(probes)]


def shape_of(n: int, rate: float) -> tuple[int, int]:
    """Bits (a power of two) and probes of a filter for ``n`` keys that errs at ``rate``."""
    need = max(64.0, -max(n, 1) * math.log(rate) / math.log(2) ** 2)
    bits = 1 << math.ceil(math.log2(need))
    if bits > MAX_BITS:
        raise ValueError(f"a filter of {bits} bits for {n} keys is over the limit of {MAX_BITS}")
    return bits, max(1, min(8, round(bits / max(n, 1) * math.log(2))))


def fill(keys: DataFrame, level: int, n: int, rate: float) -> Bloom:
    """A filter of column ``key``.  Bits are joined per word before they move; only words reach the driver."""
    bits, probes = shape_of(n, rate)
    at = keys.select(F.explode(F.array(*bit_positions(F.col("key"), level, probes, bits))).alias("at"))
    one = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("at").bitwiseAND(F.lit(63)).cast("int"))
    words = [0] * (bits // 64)
    for row in at.groupBy(F.shiftright("at", 6).alias("word")).agg(F.bit_or(one).alias("bits")).collect():
        words[row["word"]] = row["bits"]
    return Bloom(level, probes, tuple(words))


@dataclass(frozen=True)
class Cascade:
    levels: tuple[Bloom, ...]

    def holds(self, key: Column) -> Column:
        """Is ``key`` listed?  Exact for every key of the universe the chain was built over."""
        found = F.lit(len(self.levels) % 2 == 1)
        for level in reversed(self.levels):
            found = F.when(level.accepts(key), found).otherwise(F.lit(level.level % 2 == 0))
        return found


def build_cascade(universe: DataFrame, listed: Sequence[str], max_levels: int = 24) -> Cascade:
    """A cascade for ``listed``, exact over the column ``key`` of ``universe`` and over the list.

    The universe may repeat keys.  Each even level reads it once; the list is a parameter of
    bounded size.  An empty list gives a cascade without levels, which holds nothing.
    """
    listed = sorted(set(listed))
    if not listed:
        return Cascade(())
    spark = universe.sparkSession
    ours = spark.range(1).select(F.explode(F.lit(listed)).alias("key"))
    others = universe.where(F.col("key").isNotNull() & ~F.col("key").isin(listed))
    n_others = others.agg(F.approx_count_distinct("key")).first()[0]
    levels: list[Bloom] = []
    passed, n = (ours, others), len(listed)
    while n and len(levels) < max_levels:
        level = len(levels) + 1
        holds, against = passed if level % 2 else passed[::-1]
        rate = min(0.5, max(2.0**-16, len(listed) / max(n_others, 1))) if level == 1 else 0.5
        filt = fill(holds, level, n, rate)
        levels.append(filt)
        against = against.where(filt.accepts(F.col("key")))
        passed = (holds, against) if level % 2 else (against, holds)
        n = against.agg(F.approx_count_distinct("key")).first()[0]
    if n:
        raise RuntimeError(f"{n} keys are still unsettled after {max_levels} levels")
    return Cascade(tuple(levels))


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lowered) and path; both empty for null and for urls without ``://``."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), UPPER, LOWER)
    return host, F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def keys_of(host: Column, path: Column, path_lengths: Sequence[int]) -> Column:
    """All keys that could fit, longest first: host suffixes at label borders by path prefixes."""
    labels = F.split(host, r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    prefixes = F.filter(
        F.array(*[F.when(F.length(path) >= n, F.substring(path, 1, n)) for n in sorted(set(path_lengths))]),
        lambda p: p.isNotNull(),
    )
    keys = F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.concat(s, p))))
    return F.reverse(F.array_sort(F.transform(keys, lambda k: F.struct(F.length(k).alias("n"), k.alias("key")))))


def judge_urls(urls: DataFrame, block: Sequence[tuple[str, str]], allow: Sequence[tuple[str, str]], url: str = "url", default: str = "allow") -> DataFrame:
    """``urls`` with ``host``, ``path``, ``rule`` and ``verdict``; columns of these names are replaced.

    A rule (host, path) fits its host and all subdomains where the url's path starts with the
    rule's; the longest rule wins.  Where none fits, the cascades hold no key of the url, and
    the verdict is ``default``: what is not listed is allowed.  Null and broken urls have empty
    host and path.  Repeated rows are judged each; an empty table gives an empty result.
    """
    if overlap := {h + p for h, p in block} & {h + p for h, p in allow}:
        raise ValueError(f"both blocked and allowed: {sorted(overlap)}")
    lengths = [len(p) for _, p in [*block, *allow]]
    host, path = url_parts(F.col(url))
    parts = urls.withColumns({"host": host, "path": path})
    if not lengths:
        return parts.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default)})
    universe = parts.select(F.explode(F.transform(keys_of(F.col("host"), F.col("path"), lengths), lambda x: x["key"])).alias("key"))
    blocked, allowed = (build_cascade(universe, [h + p for h, p in rules]) for rules in (block, allow))
    judged = F.filter(
        F.transform(
            keys_of(F.col("host"), F.col("path"), lengths),
            lambda x: F.struct(x["key"].alias("key"), F.when(blocked.holds(x["key"]), "block").when(allowed.holds(x["key"]), "allow").alias("verdict")),
        ),
        lambda x: x["verdict"].isNotNull(),
    )
    (name,) = unused(parts, "judged")
    best = F.get(F.col(name), F.lit(0))
    return parts.withColumn(name, judged).withColumns({"rule": best["key"], "verdict": F.coalesce(best["verdict"], F.lit(default))}).drop(name)


BLOCK = (("net", "/"), ("example.com", "/de/"))
ALLOW = (("example.net", "/en/"), ("org", "/fr/"))


def op8_url_cascade(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge_urls(pages, BLOCK, ALLOW).select("page_id", "host", "path", "rule", "verdict")


OP8_SQL = r"""
WITH parts AS (
  SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path
  FROM (SELECT page_id, CASE WHEN position('://' IN url) > 0 THEN substr(url, position('://' IN url) + 3) ELSE '' END AS rest FROM pages)),
rules(h, p, verdict) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
fits AS (
  SELECT page_id, h || p AS rule, verdict, row_number() OVER (PARTITION BY page_id ORDER BY length(h || p) DESC) AS k
  FROM parts JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p))
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict
FROM parts LEFT JOIN (SELECT * FROM fits WHERE k = 1) USING (page_id)
"""
