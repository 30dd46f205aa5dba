"""Operators around the methods: sources, joins, aggregates, windows, sets and functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from metricblock import workloads as W
from metricblock.operators import records
from metricblock.queries.registry import query
from metricblock.sources import tables
from metricblock.workloads import table

# --- sources ----------------------------------------------------------------------------------


@query("SELECT p_brand, CAST(count(*) AS BIGINT) AS n FROM part WHERE p_size > 25 GROUP BY p_brand")
def rel_scan_parquet(spark, sf):
    """Filter and two columns reach the scan."""
    return table(spark, sf, "part").where("p_size > 25").groupBy("p_brand").agg(F.count("*").alias("n"))


@query("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def rel_scan_csv(spark, sf):
    return tables.round_trip(table(spark, sf, "nation"), "csv")


@query("SELECT event_id, user_id, event_type, props FROM events")
def rel_scan_json(spark, sf):
    return tables.round_trip(table(spark, sf, "events").select("event_id", "user_id", "event_type", "props"), "json")


@query("SELECT c_custkey, c_name, c_nationkey, c_mktsegment FROM customer")
def rel_scan_orc(spark, sf):
    return tables.round_trip(table(spark, sf, "customer").select("c_custkey", "c_name", "c_nationkey", "c_mktsegment"), "orc")


@query("SELECT item_id || ' ' || regexp_replace(text, '[\\n\\r]', ' ', 'g') AS value FROM benchmark")
def rel_scan_text(spark, sf):
    lines = table(spark, sf, "benchmark").select(F.concat_ws(" ", F.col("item_id").cast("string"), F.regexp_replace("text", "[\\n\\r]", " ")).alias("value"))
    return tables.round_trip(lines, "text")


@query("SELECT p_brand, p_partkey, p_name FROM part WHERE p_brand IN ('Brand#11', 'Brand#12')")
def rel_sink_partitioned(spark, sf):
    """Written by directory, read back with directories pruned."""
    out = tables.partitioned(table(spark, sf, "part").select("p_brand", "p_partkey", "p_name"), ["p_brand"])
    return out.where(F.col("p_brand").isin("Brand#11", "Brand#12")).select("p_brand", "p_partkey", "p_name")


@query("SELECT 'c' || substr(c_name, 2) AS name, c_nationkey AS nation FROM customer UNION ALL SELECT s_name, s_nationkey FROM supplier")
def rel_schema_check(spark, sf):
    c = table(spark, sf, "customer").select(F.concat(F.lit("c"), F.substring("c_name", 2, 100)).alias("name"), F.col("c_nationkey").alias("nation"))
    s = table(spark, sf, "supplier").select(F.col("s_name").alias("name"), F.col("s_nationkey").alias("nation"))
    records.check_schema(c, s, ("name", "nation"))
    return c.unionByName(s)


# --- projection and filters -------------------------------------------------------------------


@query("SELECT doc_id, upper(substr(source, 1, 3)) || '-' || lang AS key, length(text) AS n FROM documents")
def rel_project_key(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.concat(F.upper(F.substring("source", 1, 3)), F.lit("-"), "lang").alias("key"), F.length("text").cast("long").alias("n"))


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_discount >= 0.05 AND (l_quantity < 10 OR l_returnflag = 'R') AND NOT l_linestatus = 'F'")
def rel_filter_compound(spark, sf):
    return table(spark, sf, "lineitem").where((F.col("l_discount") >= 0.05) & ((F.col("l_quantity") < 10) | (F.col("l_returnflag") == "R")) & ~(F.col("l_linestatus") == "F")).select("l_orderkey", "l_linenumber")


@query("SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 15 AND p_brand IN ('Brand#11', 'Brand#23')")
def rel_filter_in_between(spark, sf):
    return table(spark, sf, "part").where(F.col("p_size").between(5, 15) & F.col("p_brand").isin("Brand#11", "Brand#23")).select("p_partkey")


@query("SELECT page_id FROM pages WHERE url LIKE '%example.org%'")
def rel_filter_like(spark, sf):
    return table(spark, sf, "pages").where(F.col("url").like("%example.org%")).select("page_id")


@query("SELECT page_id FROM pages WHERE regexp_matches(url, '/[0-9]+[.]html$')")
def rel_filter_rlike(spark, sf):
    return table(spark, sf, "pages").where(F.col("url").rlike("/[0-9]+[.]html$")).select("page_id")


@query("SELECT doc_id, CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 5000 THEN 'middle' ELSE 'long' END AS size FROM documents")
def rel_case_match(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.when(F.col("n_chars") < 500, "short").when(F.col("n_chars") < 5000, "middle").otherwise("long").alias("size"))


@query("SELECT d.doc_id, coalesce(l.toxic, -1) AS toxic, l.quality IS NULL AS missing FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def rel_null_weights(spark, sf):
    return table(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id", "left").select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("toxic"), F.col("quality").isNull().alias("missing"))


# --- joins ------------------------------------------------------------------------------------


@query("SELECT n_name, count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def rel_join_hash_broadcast(spark, sf):
    """25 nations by definition: the fixed side is shipped."""
    j = table(spark, sf, "customer").join(F.broadcast(table(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query("SELECT o_orderkey, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def rel_join_sort_merge(spark, sf):
    j = table(spark, sf, "orders").hint("merge").join(table(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderkey").agg(F.count("*").alias("lines"))


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def rel_join_shuffle_hash(spark, sf):
    j = table(spark, sf, "orders").join(table(spark, sf, "customer").hint("shuffle_hash"), F.col("c_custkey") == F.col("o_custkey"))
    return j.groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("SELECT s_suppkey, n_nationkey FROM supplier JOIN nation ON levenshtein(s_name, n_name) <= 15")
def rel_join_theta_distance(spark, sf):
    return table(spark, sf, "supplier").join(F.broadcast(table(spark, sf, "nation")), F.levenshtein("s_name", "n_name") <= 15).select("s_suppkey", "n_nationkey")


@query("WITH" + W.names_query_sql() + " SELECT q_id, rec_id FROM names_query q JOIN names_ref r ON abs(length(q.given) - length(r.given)) <= 1 AND q.surname = r.surname AND levenshtein(q.given, r.given) <= 1")
def rel_join_length_band(spark, sf):
    q = W.names_query(spark, sf).select("q_id", F.col("given").alias("g"), "surname")
    r = W.names_ref(spark, sf).select("rec_id", "given", "surname")
    return q.join(r, "surname").where((F.abs(F.length("g") - F.length("given")) <= 1) & (F.levenshtein("g", "given") <= 1)).select("q_id", "rec_id")


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
def rel_join_semi_gold(spark, sf):
    return table(spark, sf, "documents").join(table(spark, sf, "labels").where("toxic = 1"), "doc_id", "left_semi").select("doc_id")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def rel_join_anti_unmatched(spark, sf):
    return table(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id", "left_anti").select("doc_id")


@query("SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def rel_join_left_outer(spark, sf):
    return table(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id", "left").select("doc_id", "quality")


@query("SELECT coalesce(c.k, s.k) AS k, c.n AS customers, s.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) s ON c.k = s.k")
def rel_join_full_outer(spark, sf):
    c = table(spark, sf, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    return c.join(table(spark, sf, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers")), "k", "full")


VERSIONS = "versions AS (SELECT CAST(row_number() OVER (ORDER BY d) AS BIGINT) AS version, d AS valid_from FROM (SELECT DISTINCT date_trunc('day', ts) AS d FROM events))"


@query(f"WITH {VERSIONS} SELECT e.event_id, v.version FROM events e ASOF JOIN versions v ON e.ts >= v.valid_from")
def rel_join_asof_version(spark, sf):
    """Each event with the latest version at its time: one sweep over both, ordered, within their days' partition."""
    e = table(spark, sf, "events")
    days = e.select(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("valid_from")).distinct()
    v = days.withColumn("version", F.row_number().over(Window.orderBy("valid_from")).cast("long"))
    both = e.select("ts", "event_id", F.lit(None).cast("long").alias("version")).unionByName(v.select(F.col("valid_from").alias("ts"), F.lit(None).cast("long").alias("event_id"), "version"))
    day = F.date_trunc("day", "ts")
    w = Window.partitionBy(day).orderBy("ts", F.col("version").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("version", F.last("version", ignorenulls=True).over(w)).where("event_id is not null").select("event_id", "version")


@query("SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_type = y.event_type AND x.event_id <> y.event_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 1 HOUR")
def rel_join_interval(spark, sf):
    e = table(spark, sf, "events").select("user_id", "event_type", "event_id", "ts")
    later = e.select("user_id", "event_type", F.col("event_id").alias("b"), F.col("ts").alias("t"))
    inside = (F.col("t") > F.col("ts")) & (F.col("t") <= F.col("ts") + F.expr("interval 1 hour"))
    return e.join(later, ["user_id", "event_type"]).where(inside & (F.col("event_id") != F.col("b"))).select(F.col("event_id").alias("a"), "b")


@query("SELECT n_nationkey, c.c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3) c")
def rel_join_lateral_topk(spark, sf):
    n, c = table(spark, sf, "nation"), table(spark, sf, "customer")
    best = c.where(F.col("c_nationkey") == F.col("n_nationkey").outer()).orderBy(F.desc("c_acctbal"), "c_custkey").limit(3)
    return n.lateralJoin(best).select("n_nationkey", "c_custkey")


# --- aggregates -------------------------------------------------------------------------------


@query("SELECT substr(p_name, 1, 3) AS k, count(*) AS n, min(p_size) AS least, max(p_size) AS most, round(avg(p_size), 6) AS mean FROM part GROUP BY 1")
def rel_agg_block_sizes(spark, sf):
    return table(spark, sf, "part").groupBy(F.substring("p_name", 1, 3).alias("k")).agg(F.count("*").alias("n"), F.min("p_size").alias("least"), F.max("p_size").alias("most"), F.round(F.avg("p_size"), 6).alias("mean"))


@query("SELECT source, count(DISTINCT lang) AS langs, count(DISTINCT n_chars) AS sizes FROM documents GROUP BY source")
def rel_agg_distinct(spark, sf):
    return table(spark, sf, "documents").groupBy("source").agg(F.count_distinct("lang").alias("langs"), F.count_distinct("n_chars").alias("sizes"))


@query("SELECT lang, count(*) FILTER (n_chars > 2000) AS n_long, count(*) AS n FROM documents GROUP BY lang")
def rel_agg_conditional(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.count_if(F.col("n_chars") > 2000).alias("n_long"), F.count("*").alias("n"))


@query("SELECT lang, quantile_cont(n_chars, 0.25) AS q1, quantile_cont(n_chars, 0.5) AS q2, quantile_cont(n_chars, 0.9) AS q9 FROM documents GROUP BY lang")
def rel_agg_percentiles(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(*[F.percentile("n_chars", F.lit(p)).alias(n) for p, n in ((0.25, "q1"), (0.5, "q2"), (0.9, "q9"))])


@query()
def rel_agg_approx_distinct(spark, sf):
    return table(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.approx_count_distinct("l_orderkey", 0.01).alias("orders"))


@query()
def rel_agg_kll(spark, sf):
    s = table(spark, sf, "lineitem").agg(F.expr("kll_sketch_agg_double(cast(l_extendedprice as double))").alias("s"))
    return s.selectExpr("kll_sketch_get_quantile_double(s, 0.5D) as median")


@query("SELECT p_brand, list(p_partkey ORDER BY p_partkey) AS members FROM part GROUP BY p_brand")
def rel_agg_collect_block(spark, sf):
    return table(spark, sf, "part").groupBy("p_brand").agg(F.array_sort(F.collect_list("p_partkey")).alias("members"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def rel_agg_rollup(spark, sf):
    return table(spark, sf, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) AS BIGINT) AS g, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def rel_agg_cube(spark, sf):
    return table(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping("l_returnflag").cast("long").alias("g"), F.count("*").alias("n"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())")
def rel_agg_grouping_sets(spark, sf):
    return table(spark, sf, "documents").groupingSets([["lang", "source"], ["lang"], []], "lang", "source").agg(F.count("*").alias("n"))


@query("SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en FROM documents GROUP BY source")
def rel_pivot_curve(spark, sf):
    return table(spark, sf, "documents").groupBy("source").pivot("lang", ["de", "en"]).count().select("source", F.coalesce("de", F.lit(0)).alias("de"), F.coalesce("en", F.lit(0)).alias("en"))


# --- windows, order, sets ---------------------------------------------------------------------


@query("SELECT p_partkey, row_number() OVER w AS rn FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey)")
def rel_win_row_number(spark, sf):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(spark, sf, "part").select("p_partkey", F.row_number().over(w).cast("long").alias("rn"))


@query("SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS dr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def rel_win_rank_dense(spark, sf):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return table(spark, sf, "part").select("p_partkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"))


@query("SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_partkey) AS q FROM part")
def rel_win_ntile(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_partkey")).cast("long").alias("q"))


@query("SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def rel_win_lag_lead(spark, sf):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return table(spark, sf, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"))


@query("SELECT conv_id, turn, CAST(sum(length(text)) OVER (PARTITION BY conv_id ORDER BY turn) AS BIGINT) AS used FROM conversations")
def rel_win_running_budget(spark, sf):
    w = Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, sf, "conversations").select("conv_id", "turn", F.sum(F.length("text")).over(w).alias("used"))


@query("SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM events")
def rel_win_range_frame(spark, sf):
    e = table(spark, sf, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("event_type").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("n"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def rel_topk_global(spark, sf):
    return table(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@query("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def rel_topk_per_group(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, sf, "orders").withColumn("k", F.row_number().over(w)).where("k <= 2").select("o_custkey", "o_orderkey")


@query("SELECT page_id, CAST(row_number() OVER (ORDER BY lower(url), page_id) AS BIGINT) AS place FROM pages")
def rel_sort_multi(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.row_number().over(Window.orderBy(F.lower("url"), "page_id")).cast("long").alias("place"))


@query("SELECT p_partkey FROM part ORDER BY p_name, p_partkey LIMIT 30 OFFSET 10")
def rel_limit_offset(spark, sf):
    return table(spark, sf, "part").orderBy("p_name", "p_partkey").offset(10).limit(30).select("p_partkey")


def _two_sets(spark, sf):
    p = table(spark, sf, "part")
    return p.where("p_size < 20").select("p_brand", "p_type"), p.where("p_size > 15").select("p_brand", "p_type")


A, B = "(SELECT p_brand, p_type FROM part WHERE p_size < 20)", "(SELECT p_brand, p_type FROM part WHERE p_size > 15)"
for _name, _sql, _op in (("union", "UNION", lambda x, y: x.union(y).distinct()), ("intersect", "INTERSECT", lambda x, y: x.intersect(y)), ("except", "EXCEPT", lambda x, y: x.subtract(y)), ("union_all", "UNION ALL", lambda x, y: x.unionByName(y)), ("intersect_all", "INTERSECT ALL", lambda x, y: x.intersectAll(y)), ("except_all", "EXCEPT ALL", lambda x, y: x.exceptAll(y))):

    @query(f"{A} {_sql} {B}", f"rel_set_{_name}")
    def rel_set(spark, sf, op=_op):
        return op(*_two_sets(spark, sf))


# --- functions --------------------------------------------------------------------------------


@query("SELECT doc_id, trim(lower(source)) AS s, translate(lang, 'aeiou', '12345') AS t, reverse(source) AS r, md5(text) AS h FROM documents")
def rel_str_normalize(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.trim(F.lower("source")).alias("s"), F.translate("lang", "aeiou", "12345").alias("t"), F.reverse("source").alias("r"), F.md5("text").alias("h"))


@query("SELECT p_partkey, list_transform(range(1, length(p_name) - 1), lambda i: substr(p_name, i, 3)) AS grams FROM part")
def rel_str_ngrams(spark, sf):
    from metricblock.functions.distance import qgrams

    return table(spark, sf, "part").select("p_partkey", qgrams("p_name", 3).alias("grams"))


@query("SELECT p_partkey, string_split(p_type, ' ') AS words, CAST(len(string_split(p_type, ' ')) AS BIGINT) AS n FROM part")
def rel_str_split(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.split("p_type", " ").alias("words"), F.size(F.split("p_type", " ")).cast("long").alias("n"))


@query(f"SELECT p_partkey, {W.DUCK_HASH('p_name')} AS h FROM part")
def rel_str_hash(spark, sf):
    return table(spark, sf, "part").selectExpr("p_partkey", f"{W.SPARK_HASH('p_name')} as h")


@query()
def rel_str_soundex(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.soundex("p_name").alias("code"))


@query("SELECT o_orderkey, date_trunc('month', o_orderdate) AS month FROM orders")
def rel_date_trunc(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month"))


@query("SELECT l_orderkey, l_linenumber, CAST(date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS BIGINT) AS days FROM lineitem JOIN orders ON o_orderkey = l_orderkey")
def rel_date_diff(spark, sf):
    j = table(spark, sf, "lineitem").join(table(spark, sf, "orders"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.select("l_orderkey", "l_linenumber", F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date")).cast("long").alias("days"))


@query("SELECT c_custkey, count(DISTINCT year(o_orderdate)) AS years, count(*) AS orders FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def rel_date_parts(spark, sf):
    """Several entries of one entity over the years."""
    j = table(spark, sf, "customer").join(table(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"))
    return j.groupBy("c_custkey").agg(F.count_distinct(F.year("o_orderdate")).alias("years"), F.count("*").alias("orders"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(v, lambda x: x * x))), 5) AS l2, round(list_sum(list_transform(v, lambda x: abs(x))), 5) AS l1 FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)")
def rel_math_norms(spark, sf):
    v = F.col("embedding").cast("array<double>")
    return table(spark, sf, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x)), 5).alias("l2"), F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + F.abs(x)), 5).alias("l1"))


@query("SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive, list_transform(embedding[1:3], lambda x: round(CAST(x AS DOUBLE) * 2, 5)) AS twice FROM embeddings")
def rel_arr_hof(spark, sf):
    """Rounded as in SQL: the sign stays, also of what rounds to zero."""

    def rounded(x):
        return F.signum(x) * (F.round(F.abs(x) * 100_000, 0) / 100_000)

    return table(spark, sf, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.transform(F.slice("embedding", 1, 3), lambda x: rounded(x.cast("double") * 2)).alias("twice"))


@query("SELECT vec_id, CAST(i AS BIGINT) AS i, round(CAST(embedding[i + 1] AS DOUBLE), 6) AS x FROM embeddings, unnest(range(0, 7)) AS t(i)")
def rel_arr_slice_explode(spark, sf):
    return table(spark, sf, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 7)).alias("i", "x")).select("vec_id", F.col("i").cast("long").alias("i"), F.round(F.col("x").cast("double"), 6).alias("x"))


@query("SELECT vec_id, list_min(embedding) AS low, list_max(embedding) AS high FROM embeddings")
def rel_arr_minmax(spark, sf):
    return table(spark, sf, "embeddings").select("vec_id", F.array_min("embedding").alias("low"), F.array_max("embedding").alias("high"))


@query("SELECT p_partkey, p_brand AS brand, CAST(2 AS BIGINT) AS n FROM part")
def rel_map_profile(spark, sf):
    m = F.create_map(F.lit("name"), "p_name", F.lit("brand"), "p_brand")
    return table(spark, sf, "part").select("p_partkey", F.element_at(m, "brand").alias("brand"), F.size(F.map_keys(m)).cast("long").alias("n"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def rel_json_props(spark, sf):
    parsed = F.from_json("props", T.StructType([T.StructField("k", T.LongType())]))
    return table(spark, sf, "events").select("event_id", parsed["k"].alias("k"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def rel_json_variant(spark, sf):
    return table(spark, sf, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(15, 2))) AS DOUBLE) AS total FROM lineitem GROUP BY l_returnflag")
def rel_decimal_sums(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(15,2)")).cast("double").alias("total"))


@query("SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part)")
def rel_subquery_scalar(spark, sf):
    mean = table(spark, sf, "part").agg(F.avg("p_retailprice"))
    return table(spark, sf, "part").where(F.col("p_retailprice") > mean.scalar()).select("p_partkey")


@query("SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 100000)")
def rel_subquery_exists(spark, sf):
    c, o = table(spark, sf, "customer"), table(spark, sf, "orders")
    return c.where(o.where((F.col("o_custkey") == F.col("c_custkey").outer()) & (F.col("o_totalprice") > 100000)).exists()).select("c_custkey")


@query("WITH RECURSIVE chain(n_nationkey, step) AS (SELECT n_nationkey, 0 FROM nation UNION ALL SELECT (n_nationkey * 2 + 1) % 25, step + 1 FROM chain WHERE step < 3) SELECT n_nationkey, CAST(step AS BIGINT) AS step, count(*) AS n FROM chain GROUP BY ALL")
def rel_cte_recursive_chain(spark, sf):
    table(spark, sf, "nation").createOrReplaceTempView("mb_nation")
    return spark.sql("WITH RECURSIVE chain(k, step) AS (SELECT CAST(n_nationkey AS INT), 0 FROM mb_nation UNION ALL SELECT CAST((k * 2 + 1) % 25 AS INT), step + 1 FROM chain WHERE step < 3) SELECT k AS n_nationkey, CAST(step AS BIGINT) AS step, count(*) AS n FROM chain GROUP BY k, step").withColumn("n_nationkey", F.col("n_nationkey").cast("int"))
