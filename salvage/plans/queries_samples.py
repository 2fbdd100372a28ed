"""Queries over sample assembly, encoding, purge rules and duplicates."""

from __future__ import annotations

from pyspark.sql import functions as F

from salvage.functions import vectors
from salvage.functions.keys import order_key_sql
from salvage.functions.materialize import spread
from salvage.plans.fixtures import TEXT_SQL, text_vectors
from salvage.plans import samples
from salvage.registry import query, read

_CONV = "conv AS (SELECT conv_id * 1048576 + turn AS sample_id, text AS instruction, system AS input, next_text AS response FROM (SELECT conv_id, turn, role, text, lead(role) OVER w AS next_role, lead(text) OVER w AS next_text, last_value(CASE WHEN role = 'system' THEN text END IGNORE NULLS) OVER (PARTITION BY conv_id ORDER BY turn ROWS UNBOUNDED PRECEDING) AS system FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND next_role = 'assistant')"
_DOC = r"docs_ AS (SELECT doc_id AS sample_id, 'documents-' || (('0x' || substr(md5(source), 1, 4))::INT % 5) AS component, regexp_extract(text, '(?s)^([^.!?]*[.!?])\s+(.+)$', 1) AS instruction, regexp_extract(text, '(?s)^([^.!?]*[.!?])\s+(.+)$', 2) AS response FROM documents WHERE regexp_extract(text, '(?s)^([^.!?]*[.!?])\s+(.+)$', 2) <> '')"
_PAGE = r"pages_ AS (SELECT * FROM (SELECT page_id AS sample_id, regexp_extract(html, '(?s)<title>(.*?)</title>', 1) AS instruction, trim(regexp_replace(regexp_replace(regexp_extract(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<script[^>]*>.*?</script>', ' ', 'g'), '(?s)<style[^>]*>.*?</style>', ' ', 'g'), '(?s)<nav[^>]*>.*?</nav>', ' ', 'g'), '(?s)<!--.*?-->', ' ', 'g'), '(?s)<article>(.*)</article>', 1), '<[^>]*>', ' ', 'g'), '[ \t\n\r]+', ' ', 'g')) AS response FROM pages) WHERE instruction <> '' AND response <> '')"
_POOL = f"WITH {_CONV}, {_DOC}, {_PAGE}, pool AS (SELECT sample_id, 'conversations' AS component FROM conv UNION ALL SELECT sample_id, component FROM docs_ UNION ALL SELECT sample_id, 'pages' FROM pages_) "


def _all(spark, sf):
    return samples.pool(samples.samples_from_conversations(read(spark, sf, "conversations")), samples.samples_from_documents(read(spark, sf, "documents")), samples.samples_from_pages(read(spark, sf, "pages")))


@query("samples_conv", f"WITH {_CONV} SELECT sample_id, md5(instruction) AS i, md5(input) AS s, md5(response) AS r FROM conv")
def samples_conv(spark, sf):
    return samples.samples_from_conversations(read(spark, sf, "conversations")).select("sample_id", F.md5("instruction").alias("i"), F.md5("input").alias("s"), F.md5("response").alias("r"))


@query("samples_doc", f"WITH {_DOC} SELECT sample_id, component, md5(instruction) AS i, md5(response) AS r FROM docs_")
def samples_doc(spark, sf):
    return samples.samples_from_documents(read(spark, sf, "documents")).select("sample_id", "component", F.md5("instruction").alias("i"), F.md5("response").alias("r"))


@query("samples_page", f"WITH {_PAGE} SELECT sample_id, md5(instruction) AS i, md5(response) AS r FROM pages_")
def samples_page(spark, sf):
    return samples.samples_from_pages(read(spark, sf, "pages")).select("sample_id", F.md5("instruction").alias("i"), F.md5("response").alias("r"))


@query("pool_stats", _POOL + "SELECT component, count(*) AS n, round(count(*) / (SELECT count(*) FROM pool), 6) AS share FROM pool GROUP BY ROLLUP (component)")
def pool_stats(spark, sf):
    counted = _all(spark, sf).groupBy("component").agg(F.count("*").alias("c"))
    total = counted.agg(F.sum("c").alias("t"))
    return counted.rollup("component").agg(F.sum("c").alias("n")).crossJoin(total).select("component", "n", F.round(F.col("n") / F.col("t"), 6).alias("share"))


@query("pool_quota", _POOL + f"SELECT component, sample_id FROM (SELECT *, row_number() OVER (PARTITION BY component ORDER BY {order_key_sql('sample_id')}, sample_id) AS r FROM pool) WHERE r <= 50")
def pool_quota(spark, sf):
    return samples.take_quota(_all(spark, sf).select("sample_id", "component"), 50).select("component", "sample_id")


@query("encode_sql", "WITH w AS (SELECT doc_id AS item_id, unnest(regexp_extract_all(lower(text), '[a-zà-ÿ]+')) AS t FROM documents), c AS (SELECT item_id, t, count(*) AS tf FROM w GROUP BY 1, 2), b AS (SELECT item_id, ('0x' || substr(md5(t), 1, 2))::INT AS dim, sum(CASE WHEN ('0x' || substr(md5(t), 3, 1))::INT < 8 THEN 1 ELSE -1 END * (1 + ln(tf))) AS x FROM c GROUP BY 1, 2) SELECT item_id, dim, round(x / sqrt(sum(x * x) OVER (PARTITION BY item_id)), 6) AS x FROM b")
def encode_sql(spark, sf):
    """The word encoder in plain SQL functions: hash buckets and signs from md5."""
    from pyspark.sql import Window

    tf = samples.terms(read(spark, sf, "documents"), "doc_id", "text").groupBy("id", "term").agg(F.count("*").alias("tf"))
    h = F.md5("term")
    dim, sign = F.conv(F.substring(h, 1, 2), 16, 10).cast("int"), F.when(F.conv(F.substring(h, 3, 1), 16, 10).cast("int") < 8, 1).otherwise(-1)
    b = tf.groupBy(F.col("id").alias("item_id"), dim.alias("dim")).agg(F.sum(sign * (1 + F.log("tf"))).alias("x"))
    size = F.sqrt(F.sum(F.col("x") * F.col("x")).over(Window.partitionBy("item_id")))  # 0 if the words cancel out: no number, as in SQL
    return b.select("item_id", "dim", F.round(F.when(size == 0, F.lit(float("nan"))).otherwise(F.col("x") / size), 6).alias("x"))


_CHECKSUM = "round(list_sum(list_transform(v, lambda x, i: x * i)), 4)"


@query("encode_char3", f"WITH {TEXT_SQL} SELECT id AS sample_id, len(v) AS dim, round(sqrt(list_sum(list_transform(v, lambda x: x * x))), 5) AS length, {_CHECKSUM} AS weighted FROM tv")
def encode_char3(spark, sf):
    """The character encoder: length of each vector and a sum of its components by place."""
    vecs = text_vectors(spark, sf)
    weighted = F.aggregate(F.transform("vec", lambda x, i: x.cast("double") * (i + 1)), F.lit(0.0), lambda t, x: t + x)
    return vecs.select("sample_id", F.size("vec").cast("bigint").alias("dim"), F.round(vectors.norm(F.col("vec")), 5).alias("length"), F.round(weighted, 4).alias("weighted"))


for _kind in ("word1", "word2"):

    def _encode(spark, sf, kind=_kind):
        vecs = text_vectors(spark, sf, kind)
        return vecs.select("sample_id", F.size("vec").alias("dim"), F.round(vectors.norm(F.col("vec")), 5).alias("length"))

    query(f"encode_{_kind}")(_encode)

_PAIR = "FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"


@query("vec_cosine", f"SELECT a.vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS sim {_PAIR}")
def vec_cosine(spark, sf):
    e = read(spark, sf, "embeddings").select("vec_id", "embedding")
    return e.alias("a").join(e.alias("b"), F.col("b.vec_id") == F.col("a.vec_id") + 1).select("a.vec_id", F.round(vectors.cosine(F.col("a.embedding"), F.col("b.embedding")), 6).alias("sim"))


@query("vec_euclid", f"SELECT a.vec_id, round(list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS dist {_PAIR}")
def vec_euclid(spark, sf):
    e = read(spark, sf, "embeddings").select("vec_id", "embedding")
    return e.alias("a").join(e.alias("b"), F.col("b.vec_id") == F.col("a.vec_id") + 1).select("a.vec_id", F.round(vectors.euclid(F.col("a.embedding"), F.col("b.embedding")), 6).alias("dist"))


@query("vec_mean", "SELECT i, round(avg(x), 6) AS m FROM (SELECT unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings) GROUP BY 1")
def vec_mean(spark, sf):
    one = vectors.mean_vectors(read(spark, sf, "embeddings").withColumn("g", F.lit(1)), ["g"], "embedding")
    return one.select(F.posexplode("mean").alias("i", "m")).select(F.col("i").cast("bigint").alias("i"), F.round("m", 6).alias("m"))


_SHARES = {"symbol_share": r"[#*%&$!|]", "upper_share": r"[A-Z]", "digit_share": r"[0-9]"}


_RUN = "[^A-Za-zÀ-ÿ0-9 \\n]+"


@query("noise_profile", "WITH p AS (SELECT doc_id, lang, n_chars, " + ", ".join(f"round(len(regexp_extract_all(text, '{p}')) / greatest(length(text), 1), 6) AS {n}" for n, p in _SHARES.items()) + f", round(length(regexp_replace(text, '[ \\n]+', '', 'g')) / greatest(len(regexp_extract_all(text, '[^ \\n]+')), 1), 6) AS word_length, round(len(list_distinct(regexp_extract_all(lower(text), '[^ \\n]+'))) / greatest(len(regexp_extract_all(text, '[^ \\n]+')), 1), 6) AS distinct_share, round(1 - len(list_distinct(string_split(text, chr(10)))) / len(string_split(text, chr(10))), 6) AS repeated_lines, coalesce(list_max(list_transform(regexp_extract_all(text, '{_RUN}'), lambda r: length(r))), 0) AS longest_run FROM documents) SELECT doc_id, " + ", ".join(_SHARES) + ", word_length, distinct_share, repeated_lines, longest_run, round((n_chars - avg(n_chars) OVER (PARTITION BY lang)) / nullif(stddev_samp(n_chars) OVER (PARTITION BY lang), 0), 6) AS length_z FROM p")
def noise_profile(spark, sf):
    """Statistical signs of noise for each text; the length is set against the language's mean, a null language being one."""
    docs = read(spark, sf, "documents").select("doc_id", "lang", "n_chars", "text")
    words = F.greatest(F.regexp_count("text", F.lit(r"[^ \n]+")), F.lit(1))
    stats = docs.groupBy(F.col("lang").alias("l")).agg(F.avg("n_chars").alias("m"), F.stddev_samp("n_chars").alias("s"))
    lines = F.split("text", "\n")
    runs = F.transform(F.regexp_extract_all("text", F.lit(_RUN), F.lit(0)), lambda r: F.length(r))
    signs = spread(docs).select(
        "doc_id", "lang", "n_chars", *(F.round(F.regexp_count("text", F.lit(p)) / F.greatest(F.length("text"), F.lit(1)), 6).alias(n) for n, p in _SHARES.items()),
        F.round(F.length(F.regexp_replace("text", r"[ \n]+", "")) / words, 6).alias("word_length"), F.round(F.size(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"[^ \n]+"), 0))) / words, 6).alias("distinct_share"),
        F.round(1 - F.size(F.array_distinct(lines)) / F.size(lines), 6).alias("repeated_lines"), F.coalesce(F.array_max(runs), F.lit(0)).cast("bigint").alias("longest_run"),
    )
    z = F.round((F.col("n_chars") - F.col("m")) / F.nullif(F.col("s"), F.lit(0.0)), 6)
    return signs.join(stats, F.col("lang").eqNullSafe(F.col("l")), "left").select("doc_id", *_SHARES, "word_length", "distinct_share", "repeated_lines", "longest_run", z.alias("length_z"))


def purged_sql(text: str = "text") -> str:
    for _, pattern, repl, _ in samples.PURGE_RULES:
        text = f"regexp_replace({text}, '{pattern}', '{repl}', 'g')"
    return f"trim(regexp_replace({text}, '[ ]+', ' ', 'g'))"


@query("purge_text", f"SELECT doc_id, md5({purged_sql()}) AS h FROM documents")
def purge_text(spark, sf):
    return samples.purge(spread(read(spark, sf, "documents").select("doc_id", "text"))).select("doc_id", F.md5("text").alias("h"))


def _purge_counts_sql() -> str:
    text, parts = "text", []
    for name, pattern, repl, _ in samples.PURGE_RULES:
        parts.append(f"SELECT '{name}' AS rule, sum(len(regexp_extract_all({text}, '{pattern}')))::BIGINT AS hits FROM documents")
        text = f"regexp_replace({text}, '{pattern}', '{repl}', 'g')"
    return " UNION ALL ".join(parts)


@query("purge_counts", _purge_counts_sql())
def purge_counts(spark, sf):
    names = [name for name, *_ in samples.PURGE_RULES]
    purged = samples.purge(spread(read(spark, sf, "documents").select("doc_id", "text")))
    total = purged.agg(*(F.sum(F.element_at("removed", F.lit(n))).alias(n) for n in names))  # one row; a filter on the map would be pushed through every rule
    return total.select(F.explode(F.array(*(F.struct(F.lit(n).alias("rule"), F.col(n).alias("hits")) for n in names))).alias("x")).select("x.rule", "x.hits")


_BOILER = "lines AS (SELECT DISTINCT md5(text) AS h, unnest(string_split(text, chr(10))) AS line FROM documents), boiler AS (SELECT line, count(*) AS n_texts FROM lines WHERE line <> '' GROUP BY line HAVING count(*) >= 5)"


@query("purge_boilerplate", f"WITH {_BOILER} SELECT md5(line) AS line, n_texts FROM boiler")
def purge_boilerplate(spark, sf):
    return samples.boilerplate(read(spark, sf, "documents")).select(F.md5("line").alias("line"), "n_texts")


@query("purge_lines", f"WITH {_BOILER}, l AS (SELECT doc_id, unnest(ls) AS line, generate_subscripts(ls, 1) AS i FROM (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents)), k AS (SELECT *, line = '' OR (line NOT IN (SELECT line FROM boiler) AND i = min(i) OVER (PARTITION BY doc_id, line)) AS kept FROM l) SELECT doc_id AS id, md5(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE kept), '')) AS h, count(*) FILTER (WHERE NOT kept) AS n_removed FROM k GROUP BY 1")
def purge_lines(spark, sf):
    """Texts without the lines that many texts share and without lines that repeat."""
    return samples.purge_lines(read(spark, sf, "documents")).select("id", F.md5("text").alias("h"), F.col("n_removed").cast("bigint").alias("n_removed"))


@query("key_terms", "WITH t AS (SELECT doc_id AS id, unnest(regexp_extract_all(lower(text), '[a-zà-ÿ]+')) AS term FROM documents), tf AS (SELECT id, term, count(*) AS tf FROM t GROUP BY 1, 2), d AS (SELECT term, count(*) AS df FROM tf GROUP BY 1), s AS (SELECT id, term, round(tf * ln((SELECT count(*) FROM documents) / df), 6) AS score FROM tf JOIN d USING (term)) SELECT id, term, score, place FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY score DESC, term) AS place FROM s) WHERE place <= 10")
def key_terms(spark, sf):
    return samples.key_terms(read(spark, sf, "documents")).withColumn("place", F.col("place").cast("bigint"))


_CUES = {"numbers": r"[0-9]+", "dates": r"[0-9]{4}-[0-9]{2}-[0-9]{2}", "lists": r"\n[-*] ", "questions": r"\?", "code": r"[(){};=]"}


@query("pattern_hits", "SELECT doc_id, " + ", ".join(f"len(regexp_extract_all(text, '{p}')) AS {n}" for n, p in _CUES.items()) + " FROM documents")
def pattern_hits(spark, sf):
    return read(spark, sf, "documents").select("doc_id", *(F.regexp_count("text", F.lit(p)).cast("bigint").alias(n) for n, p in _CUES.items()))


@query("dedup_exact", "SELECT min(doc_id) AS class_id, count(*) AS n FROM documents GROUP BY md5(text)")
def dedup_exact(spark, sf):
    return samples.dedup_exact(read(spark, sf, "documents"))


def _grams_sql(name: str, table: str, key: str, n: int) -> str:
    """Distinct word n-grams of each text."""
    gram = " || ' ' || ".join(["w"] + [f"lead(w, {i}) OVER o" for i in range(1, n)])
    words = f"SELECT {key} AS id, list_filter(regexp_split_to_array(lower(text), '[ \\t\\n\\r]+'), lambda x: x <> '') AS ws FROM {table}"
    return f"{name} AS (SELECT DISTINCT id, g FROM (SELECT id, {gram} AS g FROM (SELECT id, unnest(ws) AS w, generate_subscripts(ws, 1) AS i FROM ({words})) WINDOW o AS (PARTITION BY id ORDER BY i)) WHERE g IS NOT NULL)"


_SETS = _grams_sql("g", "documents", "doc_id", 5) + ", sets AS (SELECT id, md5(string_agg(g, '|' ORDER BY g)) AS h, count(*) AS n FROM g GROUP BY 1), classes AS (SELECT h, min(id) AS class_id, any_value(n) AS n FROM sets GROUP BY 1)"


@query("dedup_near", f"WITH {_SETS}, own AS (SELECT class_id, n, g FROM classes JOIN g ON g.id = class_id), met AS (SELECT x.class_id AS a, y.class_id AS b, any_value(x.n) AS na, any_value(y.n) AS nb, count(*) AS i FROM own x JOIN own y ON x.g = y.g AND x.class_id < y.class_id GROUP BY 1, 2) SELECT a, b, round(i / (na + nb - i), 6) AS jaccard FROM met WHERE i / (na + nb - i) >= 0.8")
def dedup_near(spark, sf):
    return samples.dedup_near(read(spark, sf, "documents"))[1]


@query("dedup_near_classes", f"WITH {_SETS} SELECT id, class_id FROM sets JOIN classes USING (h)")
def dedup_near_classes(spark, sf):
    return samples.dedup_near(read(spark, sf, "documents"))[0]


@query("decontaminate", f"WITH {_grams_sql('b', 'benchmark', 'item_id', 8)}, {_grams_sql('d', 'documents', 'doc_id', 8)} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT d.id FROM d WHERE g IN (SELECT g FROM b))")
def decontaminate(spark, sf):
    return samples.decontaminate(read(spark, sf, "documents"), read(spark, sf, "benchmark")).select("doc_id")
