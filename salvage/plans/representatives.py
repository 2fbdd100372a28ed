"""Choosing relevant but diverse representatives of each sub-cluster."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from salvage.functions.materialize import checkpoint
from salvage.functions.vectors import cosine, mean_vectors

CELL = ["cluster_id", "sub_id"]


def relevance(cells: DataFrame, vectors: DataFrame) -> DataFrame:
    """(cluster_id, sub_id, sample_id, vec, relevance): the cosine of each row to the mean of its cell."""
    joined = cells.select(*CELL, "sample_id").join(vectors.select("sample_id", "vec"), "sample_id")
    return joined.join(mean_vectors(joined, CELL), CELL).withColumn("relevance", F.round(cosine(F.col("vec"), F.col("mean")), 9)).drop("mean")


def first(rel: DataFrame) -> DataFrame:
    """The row of each cell that is closest to its mean; ties to the smallest id."""
    return rel.groupBy(*CELL).agg(F.max_by(F.struct("sample_id", "vec", "relevance"), F.struct("relevance", -F.col("sample_id"))).alias("r")).select(*CELL, "r.*")


def scores(rel: DataFrame, alpha: float = 0.2) -> DataFrame:
    """Rows other than the first with redundancy (cosine to the first) and mmr = alpha relevance - (1 - alpha) redundancy."""
    if not 0 <= alpha <= 1:
        raise ValueError("alpha must be in [0, 1]")
    chosen = first(rel).select(*CELL, F.col("sample_id").alias("first_id"), F.col("vec").alias("first_vec"))
    rest = rel.join(chosen, CELL).where("sample_id <> first_id").withColumn("redundancy", F.round(cosine(F.col("vec"), F.col("first_vec")), 9))
    return rest.select(*CELL, "sample_id", "relevance", "redundancy", F.round(alpha * F.col("relevance") - (1 - alpha) * F.col("redundancy"), 6).alias("mmr"))


def second(scored: DataFrame) -> DataFrame:
    return scored.groupBy(*CELL).agg(F.max_by(F.struct("sample_id", "relevance", "redundancy", "mmr"), F.struct("mmr", -F.col("sample_id"))).alias("r")).select(*CELL, "r.*")


def greedy(rel: DataFrame, alpha: float = 0.2, n_rep: int = 3) -> DataFrame:
    """(cluster_id, sub_id, sample_id, rep_rank): n_rep rows a cell, each the best against all chosen before it."""

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([("sample_id", "ascending")])
        x = np.asarray(rows.column("vec").combine_chunks().flatten(), float).reshape(rows.num_rows, -1)
        size = np.linalg.norm(x, axis=1, keepdims=True)
        x = np.divide(x, size, out=np.zeros_like(x), where=size > 0)
        r = rows.column("relevance").to_numpy()
        picked = [int(r.argmax())]
        worst = x @ x[picked[0]]
        while len(picked) < min(n_rep, len(x)):
            m = np.round(alpha * r - (1 - alpha) * worst, 9)
            m[picked] = -np.inf
            picked.append(int(m.argmax()))
            worst = np.maximum(worst, x @ x[picked[-1]])
        at = pa.array(picked)
        return pa.table({c: rows.column(c).take(at) for c in (*CELL, "sample_id")} | {"rep_rank": pa.array(range(len(picked)), pa.int32())})

    return rel.select(*CELL, "sample_id", "vec", "relevance").groupBy(*CELL).applyInArrow(run, "cluster_id bigint, sub_id int, sample_id bigint, rep_rank int")


def choose(cells: DataFrame, vectors: DataFrame, alpha: float = 0.2, small: int = 3, eligibility: str = "per_subcluster") -> DataFrame:
    """(cluster_id, sub_id, sample_id, rep_rank, relevance, redundancy, mmr): all rows of a cell below ``small`` rows,
    two of any other. With ``strict_two`` the two-row rule wants two or more large cells in the cluster; else a cluster
    passes all rows of its small cells and two of its large one, which comes to the same rows, marked by ``rule``."""
    sizes = cells.groupBy(*CELL).agg(F.count("*").alias("size"))
    rel = checkpoint(relevance(cells, vectors).join(sizes, CELL))  # read for the first rows, the scores and the small cells
    few = rel.where(F.col("size") < small)
    many = rel.where(F.col("size") >= small).drop("size")
    null = F.lit(None).cast("double")
    kept = few.select(*CELL, "sample_id", F.lit(0).alias("rep_rank"), "relevance", null.alias("redundancy"), null.alias("mmr"), F.lit("all").alias("rule"))
    one = first(many).select(*CELL, "sample_id", F.lit(0).alias("rep_rank"), "relevance", null.alias("redundancy"), null.alias("mmr"), F.lit("two").alias("rule"))
    two = second(scores(many, alpha)).select(*CELL, "sample_id", F.lit(1).alias("rep_rank"), "relevance", "redundancy", "mmr", F.lit("two").alias("rule"))
    out = kept.union(one).union(two)
    if eligibility == "strict_two":
        large = sizes.where(F.col("size") >= small).groupBy("cluster_id").agg(F.count("*").alias("n_large"))
        out = out.join(large, "cluster_id", "left").withColumn("rule", F.when((F.col("rule") == "two") & (F.col("n_large") < 2), "two_of_single").otherwise(F.col("rule"))).drop("n_large")
    return out


def coverage(reps: DataFrame, pairs: DataFrame, rows: DataFrame) -> DataFrame:
    """Rows, and the share that is a representative or similar to one; ``pairs`` is (a, b, sim)."""
    both = pairs.select("a", "b").union(pairs.select("b", "a"))
    near = both.join(reps.select(F.col("sample_id").alias("b")).distinct(), "b", "left_semi").select(F.col("a").alias("sample_id"))
    covered = near.union(reps.select("sample_id")).distinct()
    hit = rows.select("sample_id").join(covered, "sample_id", "left_semi").agg(F.count("*").alias("covered"))
    return hit.crossJoin(rows.agg(F.count("*").alias("n"))).select("n", "covered", F.round(F.col("covered") / F.col("n"), 6).alias("share"))
