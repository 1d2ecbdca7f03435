"""Streaming queries, drained over the events table; results are those of the final state."""

from __future__ import annotations

from pyspark.sql import functions as F

from semcat.queries.registry import query
from semcat.streaming import stream


def _events(spark, sf):
    return stream.source(spark, f"{sf}/events.parquet")


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') AS window_start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling_counts(spark, sf):
    return stream.drain(stream.tumbling(_events(spark, sf)))


@query("SELECT strftime(d, '%Y-%m-%d %H:%M') AS window_start, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY 1")
def stream_sliding_counts(spark, sf):
    return stream.drain(stream.sliding(_events(spark, sf)))


@query("WITH g AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k")
def stream_session_counts(spark, sf):
    return stream.drain(stream.sessions(_events(spark, sf)))


@query("SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedupe_ids(spark, sf):
    e = _events(spark, sf)
    return stream.drain(stream.deduplicated(e.unionByName(_events(spark, sf))).select("event_id"), "append").agg(F.count("*").alias("n"))


_CUT = "date_trunc('day', (SELECT max(ts) FROM events)) - INTERVAL 5 DAY"


@query(f"SELECT count(*) FILTER (WHERE ts >= {_CUT} AND date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY) AS n_closed, count(*) FILTER (WHERE ts < {_CUT}) AS n_late FROM events")
def stream_late_rows(spark, sf):
    """The last five days arrive first and everything older after them: counts by day close with the watermark of one day, and what
    comes later than that is left out."""
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    cut = e.agg(F.date_trunc("day", F.max("ts")).alias("d")).select((F.col("d") - F.expr("INTERVAL 5 DAYS")).alias("cut"))
    both = e.crossJoin(cut)  # one row
    new, old = both.where("ts >= cut").drop("cut"), both.where("ts < cut").drop("cut")
    # a batch drops what is later than the watermark of the batch before the last, so two batches of new rows come first
    day = stream.replayed(spark, [new.where("event_id % 2 = 0"), new.where("event_id % 2 = 1"), old]).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    closed = stream.drain(day.select("n"), "append").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_closed"))
    return closed.crossJoin(old.agg(F.count("*").alias("n_late")))  # one row each


@query("SELECT DISTINCT event_type FROM events WHERE event_type <> (SELECT min(event_type) FROM events)")
def stream_new_category_alert(spark, sf):
    known = spark.read.parquet(f"{sf}/events.parquet").agg(F.min("event_type").alias("event_type"))
    return stream.drain(stream.new_categories(_events(spark, sf), known).select("event_type"), "append").distinct()


@query("SELECT 1 AS batch, count(*) FILTER (WHERE event_id % 2 = 0) AS n_rows, true AS passed FROM events UNION ALL SELECT 2, count(*) FILTER (WHERE event_id % 2 = 1), true FROM events UNION ALL SELECT 3, count(*) FILTER (WHERE event_id % 2 = 0), count(*) FILTER (WHERE event_id % 2 = 0) = 0 FROM events")
def stream_claim_recheck(spark, sf):
    """The uniqueness claim is proved again with each batch, over all batches so far: the first batch comes once more at the end."""
    e = spark.read.parquet(f"{sf}/events.parquet")
    even, odd = e.where("event_id % 2 = 0"), e.where("event_id % 2 = 1")
    got = stream.recheck_key(stream.replayed(spark, [even, odd, even]), ["event_id"])
    return spark.createDataFrame([(i + 1, *r) for i, r in enumerate(got)], "batch int, n_rows long, passed boolean")
