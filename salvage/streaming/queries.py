"""Streams drained to tables, each checked against the batch form."""

from __future__ import annotations

from pyspark.sql import functions as F

from salvage.registry import query, read
from salvage.streaming import streams


def _stamp(c: str):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


@query("stream_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf):
    counted = streams.events_stream(spark, sf).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return streams.drain_complete(counted, "tumbling").select(_stamp("window.start").alias("start"), "event_type", "n")


@query("stream_sliding", "SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 3 HOUR, ts), time_bucket(INTERVAL 3 HOUR, ts) - INTERVAL 3 HOUR]) AS s FROM events) GROUP BY 1")
def stream_sliding(spark, sf):
    counted = streams.events_stream(spark, sf).withWatermark("ts", "1 hour").groupBy(F.window("ts", "6 hours", "3 hours")).agg(F.count("*").alias("n"))
    return streams.drain_complete(counted, "sliding").select(_stamp("window.start").alias("start"), "n")


@query("stream_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k")
def stream_session(spark, sf):
    counted = streams.events_stream(spark, sf).withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", "12 hours").alias("w")).agg(F.count("*").alias("n"))
    return streams.drain_complete(counted, "session").select("user_id", _stamp("w.start").alias("start"), "n")


@query("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_dedup(spark, sf):
    """Every event is sent twice; one of each goes through."""
    stream = streams.events_stream(spark, sf)
    twice = stream.select("event_id", "event_type", "ts", F.explode(F.array(F.lit(0), F.lit(1))).alias("copy"))
    once = twice.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type")
    return streams.drain_append(once, "dedup").groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(spark, sf):
    static = read(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    joined = streams.events_stream(spark, sf).join(static, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")
    return streams.drain_append(joined, "static").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("stream_stream_join", "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts BETWEEN v.ts AND v.ts + INTERVAL 1 HOUR")
def stream_stream_join(spark, sf):
    views = streams.events_stream(spark, sf).where("event_type = 'view'").withWatermark("ts", "2 hours").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u"), F.col("ts").alias("vt"))
    buys = streams.events_stream(spark, sf).where("event_type = 'purchase'").withWatermark("ts", "2 hours").select(F.col("event_id").alias("purchase_id"), "user_id", "ts")
    met = views.join(buys, (F.col("u") == F.col("user_id")) & (F.col("ts") >= F.col("vt")) & (F.col("ts") <= F.col("vt") + F.expr("interval 1 hour")))
    return streams.drain_append(met.select("view_id", "purchase_id"), "pairs")


@query("stream_late", "SELECT count(*) AS n FROM events")
def stream_late(spark, sf):
    """Rows that arrive more than an hour behind the latest time of earlier batches go to a table of their own; none is
    lost. The feed is replayed in the order of users, so that later files hold old times."""
    feed = streams.replayed(spark, read(spark, sf, "events"), 3, "user_id")
    seen: list = [None]

    def split(batch, number):
        bound = seen[0]
        late = F.lit(False) if bound is None else F.col("ts") < F.lit(bound) - F.expr("interval 1 hour")
        newest = batch.agg(F.max("ts")).first()[0]
        seen[0] = max(x for x in (bound, newest) if x is not None) if newest or bound else None
        return {"late": batch.where(late), "on_time": batch.where(~late)}

    out = streams.drain_batches(feed, "late", split)
    return spark.read.parquet(f"{out}/late").select("event_id").union(spark.read.parquet(f"{out}/on_time").select("event_id")).agg(F.count("*").alias("n"))


@query("stream_stateful", "SELECT previous, event_type, count(*) AS n FROM (SELECT lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS previous, event_type FROM events) WHERE previous IS NOT NULL GROUP BY 1, 2")
def stream_stateful(spark, sf):
    feed = streams.replayed(spark, read(spark, sf, "events").select("event_id", "user_id", "event_type", "ts"), 3)
    pairs = streams.stateful(feed, "user_id", streams.PairCounts(), "user_id bigint, previous string, event_type string")
    return streams.drain_append(pairs, "state").where("previous is not null").groupBy("previous", "event_type").agg(F.count("*").alias("n"))


@query("stream_online_assign")
def stream_online_assign(spark, sf):
    """Vectors arrive in the order of their ids; each label has its own leaders."""
    feed = streams.replayed(spark, read(spark, sf, "embeddings").select("vec_id", "embedding", "label"), 2, "vec_id")
    return streams.drain_append(streams.stateful(feed, "label", streams.Leaders(), "label int, vec_id bigint, leader bigint"), "leaders")
