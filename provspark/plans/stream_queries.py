"""Streaming queries; each equals its batch form."""

from __future__ import annotations

from pyspark.sql import functions as F

from provspark.functions.keys import join_key
from provspark.operators.lineage import hex_key
from provspark.plans.registry import query, with_items
from provspark.sources import carriers as C
from provspark.streaming import flows as S


def events(spark, sf):
    return C.table(spark, sf, "events")


@query("stream_tumbling", "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf):
    return S.windowed(events(spark, sf), F.window("ts", "6 hours"))


@query("stream_sliding", "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 6 HOUR AS start, event_type, count(*) AS n FROM events CROSS JOIN (VALUES (0), (1)) AS t(k) GROUP BY 1, 2")
def stream_sliding(spark, sf):
    return S.windowed(events(spark, sf), F.window("ts", "12 hours", "6 hours"))


@query("stream_session", "SELECT min(ts) AS start, event_type, count(*) AS n FROM (SELECT *, sum(g) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY event_type ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS g FROM events)) GROUP BY event_type, s")
def stream_session(spark, sf):
    """Sessions close when the watermark passes them; a last far row closes those still open."""
    e = events(spark, sf).select("event_id", "ts", "user_id", "event_type", "value")
    end = e.agg(F.max("ts").alias("m")).select(F.lit(-1).cast("bigint").alias("event_id"), (F.col("m") + F.expr("INTERVAL 30 DAYS")).alias("ts"), F.lit(0).cast("bigint").alias("user_id"), F.lit("end").alias("event_type"), F.lit(0.0).alias("value"))
    closed = S.drain(S.events_stream(e.unionByName(end)).groupBy(F.session_window("ts", "30 minutes").alias("w"), "event_type").agg(F.count("*").alias("n")))
    return closed.filter("event_type <> 'end'").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf):
    return S.deduplicated(events(spark, sf))


@query("stream_late")
def stream_late(spark, sf):
    return S.late_rows(events(spark, sf), 1)


@query("stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON c_custkey = user_id")
def stream_static_join(spark, sf):
    c = C.table(spark, sf, "customer").select(F.col("c_custkey").alias("user_id"), "c_name")
    return S.with_static(events(spark, sf), c, "user_id").select("event_id", "c_name")


@query("stream_stream_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.event_type = 'purchase' AND b.event_type = 'click' AND a.user_id = b.user_id AND a.ts >= b.ts AND a.ts <= b.ts + INTERVAL 600 MINUTE")
def stream_stream_join(spark, sf):
    return S.stream_stream(events(spark, sf), 600)


@query("stream_first_seen", "SELECT event_type || props AS key, min(event_id) AS first_id FROM events GROUP BY 1")
def stream_first_seen(spark, sf):
    return S.first_seen(events(spark, sf))


@query("stream_index_merge", with_items("SELECT key, dataset_id, n AS n_items, seq FROM ks"))
def stream_index_merge(spark, sf):
    """The index after micro-batches, one of them delivered twice."""
    return S.index_upkeep(C.document_items(spark, sf), replay=1).select(hex_key().alias("key"), "dataset_id", "n_items", "seq")


@query("stream_modes", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_modes(spark, sf):
    """Complete mode: the last batch holds the whole result."""
    out = S.drain(S.events_stream(events(spark, sf)).groupBy("event_type").agg(F.count("*").alias("n")), "complete")
    return out.join(out.agg(F.max("batch").alias("batch")), "batch").select("event_type", "n")


@query("stream_leak_alert", "SELECT CAST(doc_id AS VARCHAR) AS item_id, item_id AS bench_item FROM documents d JOIN benchmark b ON regexp_replace(lower(d.text), '[^a-z0-9]+', '', 'g') = regexp_replace(lower(b.text), '[^a-z0-9]+', '', 'g') OR contains(d.text, b.text)")
def stream_leak_alert(spark, sf):
    b = C.table(spark, sf, "benchmark").select(F.col("item_id").alias("bench_item"), F.col("text").alias("t"))
    keys = b.withColumn("key", join_key(F.col("t"), "letters"))
    keys = F.broadcast(keys) if b.count() <= 200_000 else keys
    items = C.document_items(spark, sf).select("item_id", "seq", "prompt")

    def match(s):
        # Equal letters without the passage itself, and all that hold it: no pair is in both.
        same = s.withColumn("key", join_key(F.col("prompt"), "letters")).join(keys, "key").filter(~F.col("prompt").contains(F.col("t")))
        return same.select("item_id", "bench_item").unionByName(S.contained(s, b))

    return S.leak_alerts(items, match)


@query("sink_stream", "SELECT count(*) AS n FROM events")
def sink_stream(spark, sf):
    return S.drain(S.events_stream(events(spark, sf))).agg(F.count("*").alias("n"))
