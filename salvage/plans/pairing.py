"""Which two rows are merged: inside clusters until one is left, and across clusters."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from salvage.functions.keys import order_key
from salvage.functions.materialize import checkpoint
from salvage.plans import neighbors


def global_position(df: DataFrame, *order) -> DataFrame:
    """``df`` with ``pos``, the row's place from 0 in one order: a range exchange, counts of the partitions, offsets."""
    placed = checkpoint(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()))
    part = F.shiftright("_at", 33)
    starts, total = [], 0
    for p, n in sorted((r["p"], r["count"]) for r in placed.groupBy(part.alias("p")).count().collect()):  # one row a partition
        starts.append((p, total))
        total += n
    offsets = F.broadcast(df.sparkSession.createDataFrame(starts, "_p long, _start long"))
    return placed.withColumn("_p", part).join(offsets, "_p").withColumn("pos", F.col("_start") + F.col("_at").bitwiseAND((1 << 33) - 1)).drop("_p", "_start", "_at")


def intra_plan(reps: DataFrame, mode: str = "tree") -> DataFrame:
    """(cluster_id, round, left, right): the merges of each cluster's m representatives, m - 1 in all.

    Items are positions in seed order; a merge of round r is named by its left item. A tree pairs neighbours each round
    and takes about log m rounds; a fold merges the running result with the next and takes m - 1.
    """
    sizes = reps.groupBy("cluster_id").agg(F.count("*").alias("m"))
    if mode == "fold":
        steps = sizes.where("m > 1").withColumn("round", F.explode(F.sequence(F.lit(1), (F.col("m") - 1).cast("int"))))
        return steps.select("cluster_id", "round", F.lit(0).alias("left"), F.col("round").alias("right"))
    rounds = sizes.where("m > 1").withColumn("round", F.explode(F.sequence(F.lit(1), F.ceil(F.log2("m")).cast("int"))))
    step = F.expr("cast(shiftleft(1, round) as int)")
    lefts = rounds.withColumn("left", F.explode(F.sequence(F.lit(0), (F.col("m") - 1).cast("int"), step)))
    right = F.col("left") + F.expr("cast(shiftleft(1, round - 1) as int)")
    return lefts.withColumn("right", right).where("right < m").select("cluster_id", "round", "left", "right")


def inter_pairs(reps: DataFrame, pairing: str = "ring", seed: int = 42, vectors: DataFrame | None = None) -> DataFrame:
    """(a, b, cluster_a, cluster_b): two rows of different clusters.

    ``ring`` goes through the clusters in turn and pairs places 2i and 2i + 1; ``random`` does so in md5 order. A pair
    inside one cluster is rejected. ``nearest_other`` and ``farthest_other`` take for each row the best or worst row of
    another cluster by the cosine of ``vectors`` (sample_id, cluster_id, vec): each block hands on one row a row.
    """
    rows = reps.select("sample_id", "cluster_id").withColumn("ord", order_key("sample_id", seed))
    if pairing in ("ring", "random"):
        inside = F.row_number().over(Window.partitionBy("cluster_id").orderBy("ord", "sample_id")) if pairing == "ring" else F.lit(0)
        placed = global_position(rows.withColumn("inside", inside), F.col("inside"), F.col("ord"), F.col("sample_id"))
        sides = placed.withColumn("pair", F.expr("pos div 2")).groupBy("pair").agg(F.min(F.struct("pos", "sample_id", "cluster_id")).alias("x"), F.max(F.struct("pos", "sample_id", "cluster_id")).alias("y"))
        found = sides.select(F.col("x.sample_id").alias("a"), F.col("y.sample_id").alias("b"), F.col("x.cluster_id").alias("cluster_a"), F.col("y.cluster_id").alias("cluster_b"))
    else:
        cluster = lambda i, c: rows.select(F.col("sample_id").alias(i), F.col("cluster_id").alias(c))
        near = neighbors.best_in_blocks(vectors, vectors, 1, apart="cluster_id", farthest=pairing == "farthest_other")
        found = near.select(F.col("sample_id").alias("a"), F.col("nn_id").alias("b")).join(cluster("a", "cluster_a"), "a").join(cluster("b", "cluster_b"), "b").select("a", "b", "cluster_a", "cluster_b")
    return found.where("cluster_a <> cluster_b")


def blend(high: DataFrame, synthetic: DataFrame) -> DataFrame:
    """High-rated rows and merged rows in one table, with their origin."""
    return high.withColumn("origin", F.lit("high")).unionByName(synthetic.withColumn("origin", F.lit("synthetic")), allowMissingColumns=True)
