"""Aggregations, sketches, set operators, sorting and sampling."""

from __future__ import annotations

from pyspark.sql import functions as F

from salvage.functions.keys import order_key, order_key_sql, uniform, uniform_sql
from salvage.registry import query, read


def _money(c: str):
    return F.sum(F.col(c).cast("decimal(18,2)")).cast("double")


@query("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity::DECIMAL(18,2))::DOUBLE, 2) AS quantity, round(avg(l_discount), 6) AS discount, max(l_extendedprice) AS top, min(l_tax) AS tax FROM lineitem GROUP BY 1, 2")
def agg_basic(spark, sf):
    return read(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(_money("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"), F.max("l_extendedprice").alias("top"), F.min("l_tax").alias("tax"))


@query("agg_filter", "SELECT user_id, count(*) AS n, count(*) FILTER (WHERE event_type = 'error') AS errors FROM events GROUP BY 1")
def agg_filter(spark, sf):
    return read(spark, sf, "events").groupBy("user_id").agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "error").alias("errors"))


@query("agg_distinct", "SELECT strftime(ts, '%Y-%m-%d') AS day, count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS types FROM events GROUP BY 1")
def agg_distinct(spark, sf):
    return read(spark, sf, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.countDistinct("user_id").alias("users"), F.countDistinct("event_type").alias("types"))


@query("agg_percentile", "SELECT lang, round(quantile_cont(n_chars, 0.25), 6) AS q25, round(quantile_cont(n_chars, 0.5), 6) AS q50, round(quantile_cont(n_chars, 0.75), 6) AS q75 FROM documents GROUP BY 1")
def agg_percentile(spark, sf):
    return read(spark, sf, "documents").groupBy("lang").agg(*(F.round(F.percentile("n_chars", p), 6).alias(f"q{round(100 * p)}") for p in (0.25, 0.5, 0.75)))


@query("agg_maxby", "SELECT source, arg_max(doc_id, (n_chars, -doc_id)) AS doc_id, max(n_chars) AS n_chars FROM documents GROUP BY 1")
def agg_maxby(spark, sf):
    return read(spark, sf, "documents").groupBy("source").agg(F.max_by("doc_id", F.struct("n_chars", -F.col("doc_id"))).alias("doc_id"), F.max("n_chars").alias("n_chars"))


@query("agg_listagg", "SELECT user_id, string_agg(event_type, ',' ORDER BY event_type) AS types FROM (SELECT DISTINCT user_id, event_type FROM events) GROUP BY 1")
def agg_listagg(spark, sf):
    return read(spark, sf, "events").groupBy("user_id").agg(F.array_join(F.sort_array(F.collect_set("event_type")), ",").alias("types"))


def _rated(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "lang").join(read(spark, sf, "labels"), "doc_id")


@query("agg_cube", "SELECT lang, quality, grouping_id(lang, quality)::BIGINT AS level, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY CUBE (lang, quality)")
def agg_cube(spark, sf):
    return _rated(spark, sf).cube("lang", "quality").agg(F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("n"))


@query("agg_rollup", "SELECT r_name, n_name, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(spark, sf):
    return read(spark, sf, "nation").join(F.broadcast(read(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("agg_gsets", "SELECT lang, quality, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY GROUPING SETS ((lang), (quality), ())")
def agg_gsets(spark, sf):
    return _rated(spark, sf).groupingSets([["lang"], ["quality"], []], "lang", "quality").agg(F.count("*").alias("n"))


_TYPES = ["click", "error", "purchase", "signup", "view"]


@query("agg_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS \"{t}\"" for t in _TYPES) + " FROM events GROUP BY 1")
def agg_pivot(spark, sf):
    return read(spark, sf, "events").groupBy("user_id").pivot("event_type", _TYPES).count().fillna(0, _TYPES)


@query("agg_unpivot", "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def agg_unpivot(spark, sf):
    return agg_pivot(spark, sf).unpivot("user_id", _TYPES, "event_type", "n").where("n > 0")


@query("agg_sketch_hll")
def agg_sketch_hll(spark, sf):
    per_day = read(spark, sf, "events").groupBy(F.to_date("ts").alias("day")).agg(F.hll_sketch_agg("user_id", 12).alias("s"))
    exact = read(spark, sf, "events").agg(F.countDistinct("user_id").alias("exact"))
    return per_day.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("estimate")).crossJoin(exact)


@query("agg_sketch_theta")
def agg_sketch_theta(spark, sf):
    events = read(spark, sf, "events")
    return events.groupBy("event_type").agg(F.expr("theta_sketch_estimate(theta_sketch_agg(user_id))").alias("estimate"), F.countDistinct("user_id").alias("exact"))


@query("agg_sketch_kll")
def agg_sketch_kll(spark, sf):
    return read(spark, sf, "events").agg(F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5D)").alias("estimate"), F.percentile("value", 0.5).alias("exact"))


@query("agg_sketch_cms")
def agg_sketch_cms(spark, sf):
    return read(spark, sf, "events").groupBy("event_type").agg(F.length(F.count_min_sketch("user_id", F.lit(0.01), F.lit(0.99), F.lit(42))).alias("sketch_bytes"), F.count("*").alias("n"))


@query("agg_sketch_topk")
def agg_sketch_topk(spark, sf):
    return read(spark, sf, "events").agg(F.expr("approx_top_k(event_type, 3)").alias("top")).select(F.inline("top"))


_PICKS = f"""WITH longest AS (SELECT doc_id, lang, source FROM documents ORDER BY n_chars DESC, doc_id LIMIT 200),
good AS (SELECT doc_id, lang, source FROM documents JOIN labels USING (doc_id) WHERE quality = 1),
drawn AS (SELECT doc_id, lang, source FROM documents ORDER BY {order_key_sql('doc_id')}, doc_id LIMIT 200) """


def _picks(spark, sf):
    docs = read(spark, sf, "documents").select("doc_id", "lang", "source", "n_chars")
    keep = ["doc_id", "lang", "source"]
    longest = docs.orderBy(F.desc("n_chars"), "doc_id").limit(200).select(*keep)
    good = docs.join(read(spark, sf, "labels").where("quality = 1"), "doc_id").select(*keep)
    drawn = docs.orderBy(order_key("doc_id"), "doc_id").limit(200).select(*keep)
    return longest, good, drawn


@query("set_union", _PICKS + "SELECT doc_id FROM longest UNION SELECT doc_id FROM good")
def set_union(spark, sf):
    longest, good, _ = _picks(spark, sf)
    return longest.select("doc_id").union(good.select("doc_id")).distinct()


@query("set_intersect", _PICKS + "SELECT doc_id FROM longest INTERSECT SELECT doc_id FROM good")
def set_intersect(spark, sf):
    longest, good, _ = _picks(spark, sf)
    return longest.select("doc_id").intersect(good.select("doc_id"))


@query("set_intersect_all", _PICKS + "SELECT lang, source FROM longest INTERSECT ALL SELECT lang, source FROM drawn")
def set_intersect_all(spark, sf):
    longest, _, drawn = _picks(spark, sf)
    return longest.select("lang", "source").intersectAll(drawn.select("lang", "source"))


@query("set_except", _PICKS + "SELECT doc_id FROM longest EXCEPT SELECT doc_id FROM good")
def set_except(spark, sf):
    longest, good, _ = _picks(spark, sf)
    return longest.select("doc_id").subtract(good.select("doc_id"))


@query("set_except_all", _PICKS + "SELECT lang, source FROM longest EXCEPT ALL SELECT lang, source FROM drawn")
def set_except_all(spark, sf):
    longest, _, drawn = _picks(spark, sf)
    return longest.select("lang", "source").exceptAll(drawn.select("lang", "source"))


@query("topk_global", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 100")
def topk_global(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(100)


@query("sort_multi", "SELECT doc_id, row_number() OVER (ORDER BY lang, quality DESC NULLS LAST, n_chars DESC, doc_id) AS place FROM (SELECT d.doc_id, lang, quality, n_chars FROM documents d LEFT JOIN labels l USING (doc_id)) ORDER BY place LIMIT 300")
def sort_multi(spark, sf):
    joined = read(spark, sf, "documents").select("doc_id", "lang", "n_chars").join(read(spark, sf, "labels"), "doc_id", "left")
    first = joined.orderBy("lang", F.desc_nulls_last("quality"), F.desc("n_chars"), "doc_id").limit(300)
    from pyspark.sql import Window

    return first.select("doc_id", F.row_number().over(Window.orderBy("lang", F.desc_nulls_last("quality"), F.desc("n_chars"), "doc_id")).cast("bigint").alias("place"))  # 300 rows


@query("limit_offset", "SELECT doc_id FROM documents ORDER BY n_chars DESC, doc_id LIMIT 50 OFFSET 50")
def limit_offset(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").offset(50).limit(50).select("doc_id")


@query("sample_hash", f"SELECT doc_id FROM documents WHERE {uniform_sql('doc_id')} < 0.2")
def sample_hash(spark, sf):
    return read(spark, sf, "documents").select("doc_id").where(uniform("doc_id") < 0.2)


@query("sample_bernoulli")
def sample_bernoulli(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "lang").sample(0.2, seed=42)


@query("sample_stratified")
def sample_stratified(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "lang").sampleBy("lang", {"en": 0.1, "fr": 0.3, "de": 0.3, "es": 0.5}, seed=42)
