"""Star-schema reports."""

from __future__ import annotations

from pyspark.sql import functions as F

from salvage.registry import query, read


def _revenue():
    return F.round(F.sum(F.col("l_extendedprice").cast("decimal(18,2)") * (1 - F.col("l_discount").cast("decimal(18,2)"))).cast("double"), 2).alias("revenue")


_SQL_REVENUE = "round(sum(l_extendedprice::DECIMAL(18,2) * (1 - l_discount::DECIMAL(18,2)))::DOUBLE, 2) AS revenue"


@query("rel_pricing_summary", f"SELECT l_returnflag, l_linestatus, count(*) AS n, {_SQL_REVENUE} FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2")
def rel_pricing_summary(spark, sf):
    return read(spark, sf, "lineitem").where("l_shipdate <= timestamp_ntz'1998-09-02'").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), _revenue())


@query("rel_top_orders", f"SELECT o_orderkey, {_SQL_REVENUE} FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey WHERE c_mktsegment = 'BUILDING' GROUP BY 1 ORDER BY revenue DESC, o_orderkey LIMIT 10")
def rel_top_orders(spark, sf):
    buyers = read(spark, sf, "customer").where("c_mktsegment = 'BUILDING'").select("c_custkey")
    orders = read(spark, sf, "orders").select("o_orderkey", "o_custkey").join(buyers, F.col("o_custkey") == F.col("c_custkey"), "left_semi")
    return read(spark, sf, "lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderkey").agg(_revenue()).orderBy(F.desc("revenue"), "o_orderkey").limit(10)


@query("rel_region_revenue", f"SELECT r_name, n_name, {_SQL_REVENUE} FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def rel_region_revenue(spark, sf):
    places = read(spark, sf, "nation").join(F.broadcast(read(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    suppliers = read(spark, sf, "supplier").select("s_suppkey", "s_nationkey").join(F.broadcast(places), F.col("s_nationkey") == F.col("n_nationkey"))
    return read(spark, sf, "lineitem").join(suppliers, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("r_name", "n_name").agg(_revenue())


@query("rel_priority", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45) GROUP BY 1")
def rel_priority(spark, sf):
    large = read(spark, sf, "lineitem").where("l_quantity > 45").select("l_orderkey")
    return read(spark, sf, "orders").join(large, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("rel_discount_revenue", f"SELECT {_SQL_REVENUE}, count(*) AS n FROM lineitem WHERE l_discount BETWEEN 0.05 AND 0.07 AND l_quantity < 24")
def rel_discount_revenue(spark, sf):
    return read(spark, sf, "lineitem").where("l_discount between 0.05 and 0.07 and l_quantity < 24").agg(_revenue(), F.count("*").alias("n"))
