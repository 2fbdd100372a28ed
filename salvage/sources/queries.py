"""Round trips through the sources and sinks."""

from __future__ import annotations

from pyspark.sql import functions as F

from salvage.functions.scratch import scratch
from salvage.plans.samples import samples_from_conversations
from salvage.registry import query, read
from salvage.sources.chat import MESSAGES, ChatSource, to_chat


@query("scan_jsonl_roundtrip", "SELECT role, count(*) AS n, sum(length(text)) AS chars FROM conversations GROUP BY 1")
def scan_jsonl_roundtrip(spark, sf):
    path = scratch(spark, "jsonl")
    read(spark, sf, "conversations").write.json(path)
    back = spark.read.schema("conv_id bigint, turn bigint, role string, text string").json(path)
    return back.groupBy("role").agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("chars"))


@query("scan_csv_roundtrip", "SELECT quality, toxic, count(*) AS n FROM labels GROUP BY 1, 2")
def scan_csv_roundtrip(spark, sf):
    path = scratch(spark, "csv")
    read(spark, sf, "labels").write.csv(path, header=True)
    return spark.read.schema("doc_id bigint, quality int, toxic int").csv(path, header=True).groupBy("quality", "toxic").agg(F.count("*").alias("n"))


@query("scan_orc_roundtrip", "SELECT event_type, count(*) AS n, round(sum(value::DECIMAL(18,6))::DOUBLE, 4) AS total FROM events GROUP BY 1")
def scan_orc_roundtrip(spark, sf):
    path = scratch(spark, "orc")
    read(spark, sf, "events").select("event_type", "value").write.orc(path)
    return spark.read.orc(path).groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum(F.col("value").cast("decimal(18,6)")).cast("double"), 4).alias("total"))


@query("sink_partitioned", "SELECT lang, count(*) AS n, max(n_chars) AS longest FROM documents WHERE lang <> 'fr' OR n_chars < 1000 GROUP BY 1")
def sink_partitioned(spark, sf):
    """A table by language, one of whose partitions is then replaced."""
    path = scratch(spark, "by-lang")
    docs = read(spark, sf, "documents").select("doc_id", "lang", "n_chars")
    docs.repartition("lang").write.partitionBy("lang").parquet(path)
    docs.where("lang = 'fr' and n_chars < 1000").write.option("partitionOverwriteMode", "dynamic").mode("overwrite").partitionBy("lang").parquet(path)
    return spark.read.parquet(path).groupBy("lang").agg(F.count("*").alias("n"), F.max("n_chars").alias("longest"))


_CHAT = "SELECT n, count(*) AS records FROM (SELECT 2 + (max(CASE WHEN role = 'system' THEN 1 ELSE 0 END) OVER (PARTITION BY conv_id ORDER BY turn ROWS UNBOUNDED PRECEDING)) AS n, role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS nr FROM conversations) WHERE role = 'user' AND nr = 'assistant' GROUP BY 1"


@query("sink_chat_jsonl", _CHAT)
def sink_chat_jsonl(spark, sf):
    path = scratch(spark, "chat")
    to_chat(samples_from_conversations(read(spark, sf, "conversations"))).write.text(path)
    back = spark.read.text(path).select(F.from_json("value", f"struct<messages:{MESSAGES}>").alias("r"))
    return back.groupBy(F.size("r.messages").alias("n")).agg(F.count("*").alias("records"))


@query("source_chat", _CHAT)
def source_chat(spark, sf):
    """The same through the Python data source."""
    spark.dataSource.register(ChatSource)
    path = scratch(spark, "chat")
    to_chat(samples_from_conversations(read(spark, sf, "conversations"))).write.text(path)
    return spark.read.format("salvage_chat").load(path).groupBy(F.size("messages").alias("n")).agg(F.count("*").alias("records"))
