"""Joins and filters: broadcast, hash, merge, theta, range, as-of, interval, semi, anti, outer, cross, lateral, salted."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.registry import query, read


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str, name: str) -> DataFrame:
    """``left`` with the value of the latest right row of its key at or before its time; one exchange, no pairs."""
    marked = left.withColumns({"_v": F.lit(None).cast(right.schema[value].dataType), "_side": F.lit(1)}).unionByName(right.select(key, time, F.col(value).alias("_v"), F.lit(0).alias("_side")), allowMissingColumns=True)
    latest = F.last("_v", ignorenulls=True).over(Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0))
    return marked.withColumn(name, latest).where("_side = 1").drop("_v", "_side")


def range_join(points: DataFrame, value: str, bands: DataFrame, low: str, high: str, width: int) -> DataFrame:
    """Rows of ``points`` with the bands [low, high) that hold their value, by an equi-join on buckets of ``width``."""
    cells = bands.withColumn("_cell", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width))))
    return points.withColumn("_cell", F.floor(F.col(value) / width)).join(cells, "_cell").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_cell")


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int, spread: Column) -> DataFrame:
    """An equi-join whose hot keys of ``big`` are spread over ``salts`` copies of the rows of ``small``."""
    many = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return big.withColumn("_salt", F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int")).join(many, [key, "_salt"]).drop("_salt")


@query("filter_basic", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity::DECIMAL(18,2))::DOUBLE, 2) AS quantity FROM lineitem WHERE l_quantity < 24 AND l_discount BETWEEN 0.05 AND 0.07 AND l_shipdate >= TIMESTAMP '1994-01-01' AND l_returnflag IN ('A', 'N') GROUP BY 1")
def filter_basic(spark, sf):
    rows = read(spark, sf, "lineitem").where((F.col("l_quantity") < 24) & F.col("l_discount").between(0.05, 0.07) & (F.col("l_shipdate") >= F.expr("timestamp_ntz'1994-01-01'")) & F.col("l_returnflag").isin("A", "N"))
    return rows.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_quantity").cast("decimal(18,2)")).cast("double"), 2).alias("quantity"))


@query("filter_null_safe", "SELECT lang, count(*) AS unrated FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.quality IS NOT DISTINCT FROM NULL GROUP BY 1")
def filter_null_safe(spark, sf):
    joined = read(spark, sf, "documents").select("doc_id", "lang").join(read(spark, sf, "labels").select("doc_id", "quality"), "doc_id", "left")
    return joined.where(F.col("quality").eqNullSafe(F.lit(None))).groupBy("lang").agg(F.count("*").alias("unrated"))


@query("join_broadcast", "SELECT r_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def join_broadcast(spark, sf):
    place = F.broadcast(read(spark, sf, "nation").join(F.broadcast(read(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name"))  # 25 rows
    customers = read(spark, sf, "customer").select("c_custkey", "c_nationkey").join(place, F.col("c_nationkey") == F.col("n_nationkey"))
    return read(spark, sf, "orders").select("o_custkey").join(customers, F.col("o_custkey") == F.col("c_custkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("join_shuffle_hash", "SELECT o_orderstatus, count(*) AS n, round(sum(l_extendedprice::DECIMAL(18,2))::DOUBLE, 2) AS revenue FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_shuffle_hash(spark, sf):
    joined = read(spark, sf, "lineitem").join(read(spark, sf, "orders").hint("shuffle_hash"), F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double"), 2).alias("revenue"))


@query("join_sort_merge", "SELECT quality, count(*) AS n, round(avg(n_chars), 6) AS mean_chars FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def join_sort_merge(spark, sf):
    joined = read(spark, sf, "documents").select("doc_id", "n_chars").join(read(spark, sf, "labels").hint("merge"), "doc_id")
    return joined.groupBy("quality").agg(F.count("*").alias("n"), F.round(F.avg("n_chars"), 6).alias("mean_chars"))


@query("join_theta", "SELECT a.item_id AS a, b.item_id AS b FROM benchmark a JOIN benchmark b ON a.item_id < b.item_id AND abs(length(a.text) - length(b.text)) <= 10")
def join_theta(spark, sf):
    items = read(spark, sf, "benchmark").select("item_id", F.length("text").alias("n"))
    band = items.withColumn("cell", F.explode(F.array(*(F.floor(F.col("n") / 11) + d for d in (-1, 0, 1)))))  # lengths at most 10 apart are in neighbouring cells
    left = items.withColumn("cell", F.floor(F.col("n") / 11))
    return left.alias("x").join(band.alias("y"), "cell").where("x.item_id < y.item_id and abs(x.n - y.n) <= 10").select(F.col("x.item_id").alias("a"), F.col("y.item_id").alias("b"))


@query("join_range", "SELECT b.low, count(d.doc_id) AS n FROM range(0, 10) t(i), LATERAL (SELECT i * i * 200 AS low, (i + 1) * (i + 1) * 200 AS high) b JOIN documents d ON d.n_chars >= b.low AND d.n_chars < b.high GROUP BY 1")
def join_range(spark, sf):
    bands = spark.range(10).select((F.col("id") * F.col("id") * 200).alias("low"), ((F.col("id") + 1) * (F.col("id") + 1) * 200).alias("high"))
    return range_join(read(spark, sf, "documents").select("doc_id", "n_chars"), "n_chars", F.broadcast(bands), "low", "high", 1000).groupBy("low").agg(F.count("*").alias("n"))


@query("join_asof", "SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY 1, 2) v ON p.user_id = v.user_id AND p.ts >= v.ts")
def join_asof(spark, sf):
    events = read(spark, sf, "events")
    views = events.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("view"))
    return as_of(events.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), views, "user_id", "ts", "view", "view_id").select("event_id", "view_id")


@query("join_interval", "SELECT e.event_id, count(*) AS clicks FROM events e JOIN events c ON e.user_id = c.user_id AND c.event_type = 'click' AND c.ts BETWEEN e.ts - INTERVAL 6 HOUR AND e.ts WHERE e.event_type = 'error' GROUP BY 1")
def join_interval(spark, sf):
    events = read(spark, sf, "events").select("event_id", "user_id", "ts", "event_type")
    hours = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / (6 * 3600 * 10**6))
    errors = events.where("event_type = 'error'").withColumn("cell", F.explode(F.array(hours, hours - 1)))
    clicks = events.where("event_type = 'click'").select("user_id", F.col("ts").alias("click_ts"), hours.alias("cell"))
    near = errors.join(clicks, ["user_id", "cell"]).where("click_ts <= ts and click_ts >= ts - interval 6 hours")
    return near.groupBy("event_id").agg(F.count("*").alias("clicks"))


@query("join_semi", "SELECT lang, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) GROUP BY 1")
def join_semi(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "lang").join(read(spark, sf, "labels"), "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("n"))


@query("join_anti", "SELECT lang, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY 1")
def join_anti(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "lang").join(read(spark, sf, "labels"), "doc_id", "left_anti").groupBy("lang").agg(F.count("*").alias("n"))


@query("join_left", "SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left(spark, sf):
    counted = read(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"))  # before the join
    return read(spark, sf, "customer").join(counted, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n_orders"))


@query("join_full", "WITH a AS (SELECT doc_id FROM documents ORDER BY n_chars DESC, doc_id LIMIT 100), b AS (SELECT doc_id FROM labels WHERE quality = 1) SELECT a.doc_id AS long_id, b.doc_id AS good_id FROM a FULL JOIN b ON a.doc_id = b.doc_id")
def join_full(spark, sf):
    long = read(spark, sf, "documents").orderBy(F.desc("n_chars"), "doc_id").limit(100).select(F.col("doc_id").alias("long_id"))
    return long.join(read(spark, sf, "labels").where("quality = 1").select(F.col("doc_id").alias("good_id")), F.col("long_id") == F.col("good_id"), "full")


@query("join_cross", "SELECT g.lang, g.quality, count(d.doc_id) AS n FROM (SELECT lang, quality FROM (VALUES ('en'), ('fr'), ('de'), ('es')) a(lang), (VALUES (0), (1)) b(quality)) g LEFT JOIN (SELECT doc_id, lang, quality FROM documents JOIN labels USING (doc_id)) d ON g.lang = d.lang AND g.quality = d.quality GROUP BY 1, 2")
def join_cross(spark, sf):
    grid = spark.createDataFrame([(x,) for x in ("en", "fr", "de", "es")], "lang string").crossJoin(spark.createDataFrame([(0,), (1,)], "quality int"))  # eight rows
    rated = read(spark, sf, "documents").select("doc_id", "lang").join(read(spark, sf, "labels"), "doc_id").groupBy("lang", "quality").agg(F.count("*").alias("c"))
    return grid.join(rated, ["lang", "quality"], "left").select("lang", "quality", F.coalesce("c", F.lit(0)).alias("n"))


@query("join_lateral", "SELECT s_suppkey, l_orderkey, l_linenumber FROM (SELECT l_suppkey AS s_suppkey, l_orderkey, l_linenumber, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) AS r FROM lineitem JOIN supplier ON s_suppkey = l_suppkey) WHERE r <= 2")
def join_lateral(spark, sf):
    from pyspark.sql import Window

    lines = read(spark, sf, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", "l_extendedprice")
    nth = F.row_number().over(Window.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber"))  # Spark keeps two a partition before the exchange
    two = lines.withColumn("nth", nth).where("nth <= 2")
    return read(spark, sf, "supplier").join(two, F.col("s_suppkey") == F.col("l_suppkey")).select("s_suppkey", "l_orderkey", "l_linenumber")


@query("join_salted", "SELECT event_type, count(*) AS n, sum(total) AS weight FROM events JOIN (SELECT user_id, count(*) AS total FROM events GROUP BY 1) USING (user_id) GROUP BY 1")
def join_salted(spark, sf):
    events = read(spark, sf, "events").select("event_id", "user_id", "event_type")
    totals = events.groupBy("user_id").agg(F.count("*").alias("total"))
    return salted_join(events, totals, "user_id", 8, F.col("event_id")).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("total").alias("weight"))


@query("sub_scalar", "SELECT doc_id FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents e WHERE e.lang = d.lang)")
def sub_scalar(spark, sf):
    read(spark, sf, "documents").select("doc_id", "lang", "n_chars").createOrReplaceTempView("salvage_docs")
    return spark.sql("select doc_id from salvage_docs d where n_chars > (select avg(n_chars) from salvage_docs e where e.lang = d.lang)")


@query("sub_exists", "SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.quality = 1)")
def sub_exists(spark, sf):
    read(spark, sf, "documents").select("doc_id").createOrReplaceTempView("salvage_docs")
    read(spark, sf, "labels").createOrReplaceTempView("salvage_labels")
    return spark.sql("select doc_id from salvage_docs d where exists (select 1 from salvage_labels l where l.doc_id = d.doc_id and l.quality = 1)")


@query("sub_in", "SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT c_nationkey FROM customer GROUP BY 1 ORDER BY count(*) DESC, c_nationkey LIMIT 3)")
def sub_in(spark, sf):
    customers = read(spark, sf, "customer").select("c_custkey", "c_nationkey")
    top = customers.groupBy("c_nationkey").count().orderBy(F.desc("count"), "c_nationkey").limit(3).select("c_nationkey")
    return customers.join(top, "c_nationkey", "left_semi").select("c_custkey")


_MERGES = "SELECT s_suppkey AS child, cast(floor(s_suppkey / 4) AS BIGINT) AS parent FROM {supplier} WHERE s_suppkey > 0"
_LINEAGE = "WITH RECURSIVE merges(child, parent) AS ({merges}), up(node, leaf, depth) AS (SELECT parent, child, 1 FROM merges WHERE NOT EXISTS (SELECT 1 FROM merges below WHERE below.parent = merges.child) UNION ALL SELECT m.parent, u.leaf, u.depth + 1 FROM up u JOIN merges m ON m.child = u.node) SELECT leaf, node AS root, cast(depth AS INT) AS depth FROM up WHERE node = 0"


@query("cte_recursive_lineage", _LINEAGE.format(merges=_MERGES.format(supplier="supplier")))
def cte_recursive_lineage(spark, sf):
    """Suppliers as merges of up to four, the key of a merge being a quarter of theirs: the way of each leaf to the root."""
    read(spark, sf, "supplier").select("s_suppkey").createOrReplaceTempView("salvage_suppliers")
    return spark.sql(_LINEAGE.format(merges=_MERGES.format(supplier="salvage_suppliers")))
