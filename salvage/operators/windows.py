"""Window functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from salvage.registry import query, read


@query("win_rank", "SELECT doc_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM documents WINDOW w AS (PARTITION BY lang, source ORDER BY n_chars DESC, doc_id), v AS (PARTITION BY lang, source ORDER BY n_chars DESC)")
def win_rank(spark, sf):
    w = Window.partitionBy("lang", "source").orderBy(F.desc("n_chars"))
    return read(spark, sf, "documents").select("doc_id", F.row_number().over(w.orderBy(F.desc("n_chars"), "doc_id")).cast("bigint").alias("rn"), F.rank().over(w).cast("bigint").alias("rk"), F.dense_rank().over(w).cast("bigint").alias("dr"))


@query("win_ntile", "SELECT doc_id, ntile(6) OVER (PARTITION BY source ORDER BY n_chars, doc_id) - 1 AS bin FROM documents")
def win_ntile(spark, sf):
    return read(spark, sf, "documents").select("doc_id", (F.ntile(6).over(Window.partitionBy("source").orderBy("n_chars", "doc_id")) - 1).cast("bigint").alias("bin"))


@query("win_dist", "SELECT doc_id, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM documents WINDOW w AS (PARTITION BY lang, source ORDER BY n_chars)")
def win_dist(spark, sf):
    w = Window.partitionBy("lang", "source").orderBy("n_chars")
    return read(spark, sf, "documents").select("doc_id", F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("win_laglead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_laglead(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read(spark, sf, "events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"))


@query("win_running", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n FROM events")
def win_running(spark, sf):
    return read(spark, sf, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)).alias("n"))


@query("win_rows", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3 FROM events")
def win_rows(spark, sf):
    return read(spark, sf, "events").select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)), 6).alias("mean3"))


@query("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS day_count FROM events")
def win_range(spark, sf):
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    return read(spark, sf, "events").withColumn("us", micros).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)).alias("day_count"))


@query("topk_group", "SELECT source, doc_id FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
def topk_group(spark, sf):
    ranked = read(spark, sf, "documents").select("source", "doc_id", F.row_number().over(Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")).alias("r"))
    return ranked.where("r <= 3").select("source", "doc_id")  # the limit moves below the exchange
