"""Scalar, array, map, JSON, date and maths expressions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from salvage.registry import query, read


@query("scan_pruned", "SELECT doc_id, n_chars FROM documents WHERE lang = 'en' AND n_chars BETWEEN 100 AND 2000")
def scan_pruned(spark, sf):
    return read(spark, sf, "documents").where("lang = 'en' and n_chars between 100 and 2000").select("doc_id", "n_chars")


@query("project_nested", "SELECT conv_id, count(*) AS turns, list(role ORDER BY turn)[1] AS first_role, sum(length(text)) AS chars FROM conversations GROUP BY 1")
def project_nested(spark, sf):
    nested = read(spark, sf, "conversations").groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", F.length("text").alias("n")))).alias("turns"))
    return nested.select("conv_id", F.size("turns").cast("bigint").alias("turns"), F.col("turns")[0]["role"].alias("first_role"), F.aggregate("turns.n", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("chars"))


@query("case_bucket", "SELECT CASE WHEN n_chars < 100 THEN 0 WHEN n_chars < 500 THEN 1 WHEN n_chars < 1000 THEN 2 WHEN n_chars < 2000 THEN 3 WHEN n_chars < 5000 THEN 4 ELSE 5 END AS bin, count(*) AS n FROM documents GROUP BY 1")
def case_bucket(spark, sf):
    n = F.col("n_chars")
    bucket = F.when(n < 100, 0).when(n < 500, 1).when(n < 1000, 2).when(n < 2000, 3).when(n < 5000, 4).otherwise(5)
    return read(spark, sf, "documents").groupBy(bucket.alias("bin")).agg(F.count("*").alias("n"))


@query("str_clean", r"SELECT doc_id, md5(trim(regexp_replace(regexp_replace(lower(text), '(###|\*\*\*|%%%|&&&|\$\$\$|!!)', '', 'g'), '[ \t\n\r]+', ' ', 'g'))) AS h FROM documents")
def str_clean(spark, sf):
    clean = F.trim(F.regexp_replace(F.regexp_replace(F.lower("text"), r"(###|\*\*\*|%%%|&&&|\$\$\$|!!)", ""), r"[ \t\n\r]+", " "))
    return read(spark, sf, "documents").select("doc_id", F.md5(clean).alias("h"))


@query("str_ngrams", "WITH w AS (SELECT item_id, unnest(words) AS word, generate_subscripts(words, 1) AS i FROM (SELECT item_id, string_split(lower(text), ' ') AS words FROM benchmark)), g AS (SELECT word || ' ' || lead(word) OVER p || ' ' || lead(word, 2) OVER p AS gram FROM w WINDOW p AS (PARTITION BY item_id ORDER BY i)) SELECT gram, count(*) AS n FROM g WHERE gram IS NOT NULL GROUP BY 1 ORDER BY n DESC, gram LIMIT 50")
def str_ngrams(spark, sf):
    words = read(spark, sf, "benchmark").select(F.split(F.lower("text"), " ").alias("w")).where("size(w) >= 3")
    shifted = F.arrays_zip(*(F.slice("w", i, F.size("w") - 2).alias(f"w{i}") for i in (1, 2, 3)))
    grams = words.select(F.explode(F.transform(shifted, lambda z: F.concat_ws(" ", z["w1"], z["w2"], z["w3"]))).alias("gram"))
    return grams.groupBy("gram").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "gram").limit(50)


@query("str_distance", "SELECT a.item_id, levenshtein(regexp_replace(a.text, '[^ -~]', '', 'g'), regexp_replace(b.text, '[^ -~]', '', 'g'))::INT AS d FROM benchmark a JOIN benchmark b ON b.item_id = a.item_id + 1")
def str_distance(spark, sf):
    items = read(spark, sf, "benchmark").select("item_id", F.regexp_replace("text", "[^ -~]", "").alias("t"))
    return items.alias("a").join(items.alias("b"), F.col("b.item_id") == F.col("a.item_id") + 1).select("a.item_id", F.levenshtein("a.t", "b.t").alias("d"))


@query("str_hash", "SELECT substr(md5(doc_id::VARCHAR), 1, 1) AS bucket, count(*) AS n FROM documents GROUP BY 1")
def str_hash(spark, sf):
    return read(spark, sf, "documents").groupBy(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 1).alias("bucket")).agg(F.count("*").alias("n"))


@query("str_template", "SELECT item_id, md5('Keep: ' || item_id || '. Text: ' || text) AS h, length('Keep: ' || item_id || '. Text: ' || text) AS n FROM benchmark")
def str_template(spark, sf):
    prompt = F.format_string("Keep: %d. Text: %s", "item_id", "text")
    return read(spark, sf, "benchmark").select("item_id", F.md5(prompt).alias("h"), F.length(prompt).cast("bigint").alias("n"))


@query("date_parts", "SELECT year(o_orderdate) AS y, quarter(o_orderdate) AS q, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY 1, 2, 3")
def date_parts(spark, sf):
    d = F.col("o_orderdate")
    return read(spark, sf, "orders").groupBy(*(f(d).cast("bigint").alias(a) for f, a in ((F.year, "y"), (F.quarter, "q"), (F.month, "m")))).agg(F.count("*").alias("n"))


@query("date_diff", "SELECT date_diff('day', o_orderdate::DATE, l_shipdate::DATE) AS lag_days, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def date_diff(spark, sf):
    joined = read(spark, sf, "lineitem").select("l_orderkey", "l_shipdate").join(read(spark, sf, "orders").select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy(F.datediff("l_shipdate", "o_orderdate").cast("bigint").alias("lag_days")).agg(F.count("*").alias("n"))


@query("date_trunc", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS hour, count(*) AS n FROM events GROUP BY 1")
def date_trunc(spark, sf):
    return read(spark, sf, "events").groupBy(F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH:mm").alias("hour")).agg(F.count("*").alias("n"))


@query("math_softmax", "WITH c AS (SELECT event_type, count(*) AS n FROM events GROUP BY 1), e AS (SELECT event_type, exp(ln(n) - ln((SELECT max(n) FROM c))) AS x FROM c) SELECT event_type, round(x / sum(x) OVER (), 6) AS p FROM e")
def math_softmax(spark, sf):
    counts = read(spark, sf, "events").groupBy("event_type").agg(F.log(F.count("*").cast("double")).alias("z"))
    whole = Window.partitionBy()  # one row an event type
    return counts.withColumn("x", F.exp(F.col("z") - F.max("z").over(whole))).select("event_type", F.round(F.col("x") / F.sum("x").over(whole), 6).alias("p"))


@query("math_entropy", "WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2), t AS (SELECT user_id, n / sum(n) OVER (PARTITION BY user_id) AS p FROM c) SELECT user_id, round(-sum(p * ln(p)), 6) AS entropy FROM t GROUP BY 1")
def math_entropy(spark, sf):
    c = read(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    p = c.withColumn("p", F.col("n") / F.sum("n").over(Window.partitionBy("user_id")))
    return p.groupBy("user_id").agg(F.round(-F.sum(F.col("p") * F.log("p")), 6).alias("entropy"))


@query("math_zscore", "SELECT doc_id, round((n_chars - m) / s, 6) AS z FROM documents JOIN (SELECT lang, avg(n_chars) AS m, stddev_samp(n_chars) AS s FROM documents GROUP BY 1) USING (lang)")
def math_zscore(spark, sf):
    docs = read(spark, sf, "documents").select("doc_id", "lang", "n_chars")
    stats = docs.groupBy("lang").agg(F.avg("n_chars").alias("m"), F.stddev_samp("n_chars").alias("s"))
    return docs.join(stats, "lang").select("doc_id", F.round((F.col("n_chars") - F.col("m")) / F.col("s"), 6).alias("z"))


@query("math_decimal", "SELECT l_returnflag, round(sum(l_extendedprice::DECIMAL(18,2) * (1 - l_discount::DECIMAL(18,2)))::DOUBLE, 2) AS revenue FROM lineitem GROUP BY 1")
def math_decimal(spark, sf):
    amount = F.col("l_extendedprice").cast("decimal(18,2)") * (1 - F.col("l_discount").cast("decimal(18,2)"))
    return read(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(F.sum(amount).cast("double"), 2).alias("revenue"))


@query("arr_hof", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * 2)), 5) AS total, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def arr_hof(spark, sf):
    e = F.col("embedding").cast("array<double>")
    return read(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate(F.transform(e, lambda x: x * 2), F.lit(0.0), lambda a, x: a + x), 5).alias("total"), F.size(F.filter(e, lambda x: x > 0)).cast("bigint").alias("positive"))


@query("arr_setops", "SELECT a.item_id, len(list_intersect(a.w, b.w)) AS both_, len(list_distinct(list_concat(a.w, b.w))) AS any_ FROM (SELECT item_id, list_distinct(string_split(lower(text), ' ')) AS w FROM benchmark) a JOIN (SELECT item_id, list_distinct(string_split(lower(text), ' ')) AS w FROM benchmark) b ON b.item_id = a.item_id + 1")
def arr_setops(spark, sf):
    items = read(spark, sf, "benchmark").select("item_id", F.array_distinct(F.split(F.lower("text"), " ")).alias("w"))
    pairs = items.alias("a").join(items.alias("b"), F.col("b.item_id") == F.col("a.item_id") + 1)
    return pairs.select("a.item_id", F.size(F.array_intersect("a.w", "b.w")).cast("bigint").alias("both_"), F.size(F.array_union("a.w", "b.w")).cast("bigint").alias("any_"))


@query("arr_explode", "SELECT i, round(avg(x), 6) AS mean FROM (SELECT unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings) GROUP BY 1")
def arr_explode(spark, sf):
    parts = read(spark, sf, "embeddings").select(F.posexplode("embedding").alias("i", "x"))
    return parts.groupBy(F.col("i").cast("bigint").alias("i")).agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean"))


@query("map_ops", "SELECT item_id, count(*) AS frequent FROM (SELECT item_id, w, count(*) AS c FROM (SELECT item_id, unnest(string_split(lower(text), ' ')) AS w FROM benchmark) GROUP BY 1, 2 HAVING c > 1) GROUP BY 1")
def map_ops(spark, sf):
    words = F.split(F.lower("text"), " ")
    counts = F.map_from_entries(F.transform(F.array_distinct(words), lambda w: F.struct(w, F.size(F.filter(words, lambda x: x == w)))))
    frequent = F.map_filter(counts, lambda k, v: v > 1)
    return read(spark, sf, "benchmark").select("item_id", F.size(F.map_keys(frequent)).cast("bigint").alias("frequent")).where("frequent > 0")


@query("json_props", "SELECT event_type, sum(json_extract_string(props, '$.k')::BIGINT) AS k FROM events GROUP BY 1")
def json_props(spark, sf):
    return read(spark, sf, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("bigint")).alias("k"))


@query("json_variant", "SELECT event_type, max(json_extract_string(props, '$.k')::BIGINT) AS k FROM events GROUP BY 1")
def json_variant(spark, sf):
    return read(spark, sf, "events").groupBy("event_type").agg(F.max(F.variant_get(F.parse_json("props"), "$.k", "bigint")).alias("k"))


@query("json_loss_roundtrip", "SELECT item_id, len(string_split(text, ' ')) AS n_keep, 0::BIGINT AS broken FROM benchmark")
def json_loss_roundtrip(spark, sf):
    kind = "keep array<string>, drop array<string>, missing array<string>, score int"
    loss = F.struct(F.split("text", " ").alias("keep"), F.array().cast("array<string>").alias("drop"), F.array(F.lit("a")).alias("missing"), F.lit(1).alias("score"))
    back = read(spark, sf, "benchmark").select("item_id", loss.alias("loss")).withColumn("again", F.from_json(F.to_json("loss"), kind))
    return back.select("item_id", F.size("again.keep").cast("bigint").alias("n_keep"), (F.col("again.keep") != F.col("loss.keep")).cast("bigint").alias("broken"))
