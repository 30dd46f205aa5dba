"""Streams, run over all there is (``availableNow``) and compared with batch SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from metricblock import workloads as W
from metricblock.operators.querymatch import ReferenceIndex
from metricblock.queries.methods import LIMIT, NAMES, SCAN, TITLES
from metricblock.queries.registry import query
from metricblock.queries.relational import VERSIONS
from metricblock.sources.scratch import scratch_path
from metricblock.streaming.matching import absorbed, drained, first_unmatched, match_stream, once_each
from metricblock.workloads import table


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as a stream in order of time, in files; ``ts`` with a zone, as watermarks need."""
    path = scratch_path(spark, "events")
    table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")).repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(path)
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 2).parquet(path)


def batch_stream(df: DataFrame, files: int = 3) -> DataFrame:
    path = scratch_path(df.sparkSession, "stream")
    df.repartition(files).write.parquet(path)
    return df.sparkSession.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def run(stream: DataFrame, mode: str = "append") -> DataFrame:
    return drained(stream, scratch_path(stream.sparkSession, "drained"), mode)


def complete(stream: DataFrame) -> DataFrame:
    """Aggregates in complete mode: the last micro-batch's result, kept in the shared folder."""
    spark, path = stream.sparkSession, scratch_path(stream.sparkSession, "complete")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        batch.sparkSession.createDataFrame([(number,)], "n long").coalesce(1).write.mode("overwrite").parquet(f"{path}/last")

    stream.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    last = spark.read.parquet(f"{path}/last").first()[0]
    return spark.read.schema(stream.schema).parquet(f"{path}/{last}")


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, sf):
    e = event_stream(spark, sf).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return complete(e).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) - to_hours(CAST(k AS BIGINT)) AS start, count(*) AS n FROM events, unnest(range(0, 2)) AS t(k) GROUP BY ALL")
def stream_sliding(spark, sf):
    e = event_stream(spark, sf).groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count("*").alias("n"))
    return complete(e).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts > lag(ts) OVER w + INTERVAL 1 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def stream_session(spark, sf):
    e = event_stream(spark, sf).groupBy("user_id", F.session_window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return complete(e).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf):
    """Repeated (user, type) within a watermark longer than the data: each once."""
    e = event_stream(spark, sf).select("ts", "user_id", "event_type")
    return run(once_each(e, "ts", ["user_id", "event_type"], "10000 days")).select("user_id", "event_type")


@query("SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf):
    return run(event_stream(spark, sf).join(table(spark, sf, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"))


@query("SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_type < y.event_type AND y.ts BETWEEN x.ts AND x.ts + INTERVAL 1 HOUR")
def stream_interval_join(spark, sf):
    e = event_stream(spark, sf)
    x = e.select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("event_type").alias("t"), F.col("ts").alias("at")).withWatermark("at", "1000 days")
    y = event_stream(spark, sf).select(F.col("event_id").alias("b"), "user_id", "event_type", "ts").withWatermark("ts", "1000 days")
    on = (F.col("u") == F.col("user_id")) & (F.col("t") < F.col("event_type")) & (F.col("ts") >= F.col("at")) & (F.col("ts") <= F.col("at") + F.expr("interval 1 hour"))
    return run(x.join(y, on).select("a", "b"))


@query("WITH e AS (SELECT *, date_trunc('millisecond', (SELECT max(ts) FROM events WHERE event_id % 4 = 1)) - INTERVAL 2 DAYS AS mark FROM events) SELECT count(*) AS n, count(DISTINCT user_id) AS users, (SELECT count(*) FROM events) - count(*) AS late FROM e WHERE event_id % 2 = 1 OR ts > mark")
def stream_watermark_late(spark, sf):
    """Odd events come first and move the watermark on; of the even ones those older than it are late and not counted.

    A batch's rows are late against the watermark of the batch before, so the odd ones come in two.
    """
    path = scratch_path(spark, "late")
    events = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    for some in ("event_id % 4 = 1", "event_id % 4 = 3", "event_id % 2 = 0"):
        events.where(some).coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    kept = run(stream.withWatermark("ts", "2 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))
    return kept.agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users")).withColumn("late", F.lit(events.count()) - F.col("n"))


@query(SCAN + " SELECT q_id, rec_id, delta FROM found WHERE delta <= 2")
def stream_match_limit(spark, sf):
    """The stream of queries through the whole method, in the limit, equals the scan."""
    index = ReferenceIndex.fit(W.names_ref(spark, sf), "rec_id", NAMES, K=4, L=30, landmarks="random", strategy="broadcast")
    asked = batch_stream(W.names_query(spark, sf).select("q_id", "given", "surname"))
    return run(match_stream(index, asked, LIMIT, 2).select("q_id", "rec_id", F.col("delta").cast("long").alias("delta")))


@query(f"WITH {W.TITLES_SQL} SELECT DISTINCT title AS key FROM page_titles")
def stream_absorb_index(spark, sf):
    """An index of half of the titles meets the others as a stream and takes in what it doesn't know: it ends with every title once."""
    titles = W.page_titles(spark, sf)
    index = ReferenceIndex.fit(titles.where("rec_id % 2 = 0"), "rec_id", TITLES, K=3, L=25, strategy="broadcast")
    asked = batch_stream(titles.where("rec_id % 2 = 1").withColumnRenamed("rec_id", "q_id"))
    grown = absorbed(index, asked, scratch_path(spark, "absorb"), LIMIT, 0)
    return grown.points.select(F.get("key", F.lit(0)).alias("key"))


@query("SELECT DISTINCT source AS key FROM documents")
def stream_state_absorb(spark, sf):
    """Of a stream of keys each is passed on once: state that grows with distinct keys only."""
    keys = batch_stream(table(spark, sf, "documents").select(F.col("source").alias("key")))
    return run(first_unmatched(keys)).select("key")


@query(f"WITH {VERSIONS} SELECT e.event_id, v.version FROM events e ASOF JOIN versions v ON e.ts >= v.valid_from")
def stream_asof_reference(spark, sf):
    """Each streamed event with the reference version of its time; versions begin with a day, which makes the join an equality."""
    days = table(spark, sf, "events").select(F.date_trunc("day", "ts").alias("day")).distinct()
    versions = days.withColumn("version", F.row_number().over(Window.orderBy("day")).cast("long"))
    asked = event_stream(spark, sf).withColumn("day", F.date_trunc("day", "ts"))
    return run(asked.join(versions, "day").select("event_id", "version"))


@query("SELECT user_id, arg_max(event_type, ts) AS last_type FROM events GROUP BY user_id")
def stream_latest(spark, sf):
    e = event_stream(spark, sf).groupBy("user_id").agg(F.max_by("event_type", "ts").alias("last_type"))
    return complete(e)


@query("SELECT event_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS nth FROM events")
def stream_batch_rank(spark, sf):
    """Arrival numbers per user over what a stream delivered."""
    got = run(event_stream(spark, sf).select("event_id", "user_id", "ts"))
    return got.select("event_id", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")).cast("long").alias("nth"))
