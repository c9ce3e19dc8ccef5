"""Queries: streams that end, each equal to its batch result."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import config
from ..operators import dedup
from ..registry import query
from ..streaming import intake


@query("SELECT time_bucket(INTERVAL 1 DAY, ts)::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def q_stream_tumbling(spark, d):
    out = intake.run_available(intake.tumbling(intake.read(spark, d, "events"), "1 day"), "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("SELECT doc_id, lang FROM documents WHERE n_chars > 200")
def q_stream_documents(spark, d):
    """Stateless filter on a document stream."""
    return intake.run_available(intake.read(spark, d, "documents").filter("n_chars > 200").select("doc_id", "lang"))


@query("SELECT DISTINCT user_id, event_type FROM events")
def q_stream_dedup(spark, d):
    e = intake.read(spark, d, "events").select("user_id", "event_type", F.col("ts").cast("timestamp").alias("ts")).withWatermark("ts", "40 days")
    return intake.run_available(e.dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"))


@query("SELECT time_bucket(INTERVAL 12 HOUR, ts - INTERVAL 12 HOUR * k)::TIMESTAMP AS start, event_type, count(*) AS n FROM events, range(0, 2) r(k) GROUP BY ALL")
def q_stream_sliding(spark, d):
    """Windows of a day every twelve hours."""
    out = intake.run_available(intake.tumbling(intake.read(spark, d, "events"), "1 day", slide="12 hours"), "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("""WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w >= INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
n AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM o) SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n FROM n GROUP BY user_id, s""")
def q_stream_sessions(spark, d):
    """Session windows per user."""
    out = intake.run_available(intake.sessions(intake.read(spark, d, "events"), "6 hours"), "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("SELECT lang, count(*) AS docs, count(*) FILTER (n_chars > 100) AS long_enough, count(*) FILTER (n_chars > 100 AND text LIKE '%.%') AS ended FROM documents GROUP BY lang")
def q_stream_attrition(spark, d):
    """Running counts of documents that pass each rule."""
    rules = {"long_enough": F.col("n_chars") > 100, "ended": F.col("text").contains(".")}
    return intake.run_available(intake.running_attrition(intake.read(spark, d, "documents"), rules), "complete")


@query()
def q_stream_near(spark, d):
    """Documents that share a bucket with an earlier one, from a state table of buckets (tested against the batch)."""
    docs = intake.read(spark, d, "documents").select("doc_id", "lang", "text")
    bands = dedup.signatures(docs, config.DEDUP_NGRAM, *dedup.bands_at_recall()).select("doc_id", F.posexplode("bands").alias("band", "h"))
    return intake.near_copies_available(bands).select("doc_id", "first").distinct()
