"""Correcting noisy ratings with the agreement of neighbours.

Ratings of a row and of its two nearest neighbours, which are taken to share one true class, are counted (orders 1, 2
and 3). The counts determine the transition matrix T (true to observed) and the class prior p; Bayes' rule then corrects
each row, and a threshold parts the rows into tiers. The counts have at most K^3 rows whatever the input's size.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.functions.keys import uniform


def matrix_literal(m: np.ndarray) -> Column:
    """A small matrix as a constant of the plan."""
    return F.array(*(F.array(*(F.lit(float(x)) for x in row)) for row in np.asarray(m, float)))


def planted_matrix(k: int = 6, diagonal: float = 0.75) -> np.ndarray:
    """A test matrix: most mass on the diagonal, the rest falling off with the distance of the classes."""
    away = np.abs(np.arange(k)[:, None] - np.arange(k)[None, :])
    off = np.where(away > 0, 0.5 ** away, 0.0)
    out = np.round((1 - diagonal) * off / off.sum(1, keepdims=True), 6)
    return out + np.diag(np.round(1 - out.sum(1), 6))


def simulate_rating(df: DataFrame, t: np.ndarray, id_col: str = "sample_id", truth_col: str = "y", seed: int = 42) -> DataFrame:
    """``df`` with raw_score: the true class pushed through a row of T by a draw from the id."""
    cumulative = np.cumsum(np.asarray(t, float), 1)
    cumulative[:, -1] = 2.0  # rounding never leaves the last class out
    row = F.element_at(matrix_literal(cumulative), F.col(truth_col) + 1)
    u = uniform(id_col, seed)
    return df.withColumn("raw_score", F.size(F.filter(row, lambda c: c <= u)).cast("int"))


def rater_agreement(df: DataFrame, a: str, b: str) -> DataFrame:
    """Rows, share of equal ratings, mean absolute gap and Cohen's kappa of two raters."""
    both = df.where(F.col(a).isNotNull() & F.col(b).isNotNull())
    cells = both.groupBy(a, b).agg(F.count("*").alias("n"))
    rows, cols = cells.groupBy(a).agg(F.sum("n").alias("na")), cells.groupBy(b).agg(F.sum("n").alias("nb"))
    chance = rows.join(cols, F.col(a) == F.col(b)).agg(F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0)).alias("pe"))
    total = cells.agg(F.sum("n").alias("n"), F.sum(F.when(F.col(a) == F.col(b), F.col("n")).otherwise(0)).alias("eq"), F.sum(F.abs(F.col(a) - F.col(b)) * F.col("n")).alias("gap"))
    joined = total.crossJoin(chance)  # one row each
    po, pe = F.col("eq") / F.col("n"), F.col("pe") / (F.col("n") * F.col("n"))
    return joined.select("n", F.round(po, 6).alias("equal_share"), F.round(F.col("gap") / F.col("n"), 6).alias("mean_gap"), F.round(F.when(pe == 1, 1.0).otherwise((po - pe) / (1 - pe)), 6).alias("kappa"))


def neighbour_scores(neighbours: DataFrame, scores: DataFrame, score_col: str = "raw_score") -> DataFrame:
    """(sample_id, y1, y2, y3): a row's own rating and those of its first and second neighbour."""
    two = neighbours.where("nn_rank <= 2").join(scores.select(F.col("sample_id").alias("nn_id"), F.col(score_col).alias("s")), "nn_id")
    wide = two.groupBy("sample_id").agg(F.max(F.when(F.col("nn_rank") == 1, F.col("s"))).alias("y2"), F.max(F.when(F.col("nn_rank") == 2, F.col("s"))).alias("y3"))
    return scores.select("sample_id", F.col(score_col).alias("y1")).join(wide, "sample_id").where("y1 is not null and y2 is not null and y3 is not null")


def consensus(triples: DataFrame, k: int, order: int) -> DataFrame:
    """Counts and probabilities of rating tuples of the given order, on the dense grid of all tuples."""
    names = [f"y{i + 1}" for i in range(order)]
    grid = triples.sparkSession.range(k**order)
    for i, name in enumerate(names):
        grid = grid.withColumn(name, F.expr(f"cast((id div {k ** (order - 1 - i)}) % {k} as int)"))
    counted = triples.groupBy(*(F.col(n).cast("int").alias(n) for n in names)).agg(F.count("*").alias("n"))
    total = counted.agg(F.sum("n").alias("total"))
    filled = grid.drop("id").join(F.broadcast(counted), names, "left").crossJoin(F.broadcast(total))
    return filled.select(*names, F.coalesce("n", F.lit(0)).cast("bigint").alias("n"), F.coalesce(F.round(F.coalesce("n", F.lit(0)) / F.col("total"), 9), F.lit(0.0)).alias("prob"))


def shift(t: DataFrame, g: int, k: int) -> DataFrame:
    """Columns of T moved left by g, cyclically; T is (i, j, prob)."""
    return t.select("i", F.pmod(F.col("j") - g, F.lit(k)).cast("int").alias("j"), "prob")


def forward(t: DataFrame, p: DataFrame, order: int = 3) -> DataFrame:
    """Probabilities of rating tuples (y1, .. of the given order) that T (i, j, prob) and p (i, prior) predict."""
    one = lambda n: t.select("i", F.col("j").alias(f"y{n}"), F.col("prob").alias(f"t{n}"))
    joined, product = p, F.col("prior")
    for n in range(1, order + 1):
        joined, product = joined.join(one(n), "i"), product * F.col(f"t{n}")
    return joined.groupBy(*(f"y{n}" for n in range(1, order + 1))).agg(F.round(F.sum(product), 9).alias("prob"))


def consensus_vectors(t: DataFrame, p: DataFrame, k: int, order: int = 3) -> DataFrame:
    """The same by cyclic shifts: for each (z, g), shifts of the second and third rating, the probabilities by the first
    rating ``y``. Order 2 has z only, order 1 neither. A shifted matrix holds at (i, y) what T holds at y + shift."""
    joined, product = p.join(t.select("i", F.col("j").alias("y"), F.col("prob").alias("t1")), "i"), F.col("prior") * F.col("t1")
    for n, name in list(enumerate(("z", "g")[: order - 1], 2)):
        moved = None
        for by in range(k):
            part = shift(t, by, k).select("i", F.col("j").alias("y"), F.lit(by).alias(name), F.col("prob").alias(f"t{n}"))
            moved = part if moved is None else moved.union(part)
        joined, product = joined.join(moved, ["i", "y"]), product * F.col(f"t{n}")
    return joined.groupBy(*("z", "g")[: order - 1], "y").agg(F.round(F.sum(product), 9).alias("prob"))


class Estimate:
    """T, p, the residual sum of squares, the steps taken and warnings."""

    def __init__(self, t: np.ndarray, p: np.ndarray, residual: float, steps: int, n: float):
        self.t, self.p, self.residual, self.steps = t, p, residual, steps
        self.warnings = []
        if n and residual > 10 / n:
            self.warnings.append("the residual is larger than sampling explains")
        if (t.argmax(1) != np.arange(len(t))).any():
            self.warnings.append("a class is not its row's maximum; classes may be permuted")


def residual_and_gradient(a: np.ndarray, b: np.ndarray, q3: np.ndarray, orders: int = 3) -> tuple[float, np.ndarray, np.ndarray]:
    """Sum of squared gaps of orders 1 to ``orders`` between q3's marginals and the forward model, with its gradient for
    the logits. Counted tensors are not symmetric, so a gap acts on each of its axes."""
    t = np.exp(a - a.max(1, keepdims=True))
    t /= t.sum(1, keepdims=True)
    p = np.exp(b - b.max())
    p /= p.sum()
    q2, q1 = q3.sum(2), q3.sum((1, 2))
    g1 = p @ t - q1
    g2 = np.einsum("i,ij,ik->jk", p, t, t) - q2
    loss = (g1**2).sum() + (g2**2).sum()
    dp = 2 * t @ g1 + 2 * np.einsum("jk,ij,ik->i", g2, t, t)
    dt = 2 * p[:, None] * g1[None, :] + 2 * p[:, None] * (t @ (g2 + g2.T))
    if orders == 3:
        g3 = np.einsum("i,ij,ik,il->jkl", p, t, t, t, optimize=True) - q3
        loss += (g3**2).sum()
        dp += 2 * np.einsum("jkl,ij,ik,il->i", g3, t, t, t, optimize=True)
        each = g3 + g3.transpose(1, 0, 2) + g3.transpose(2, 0, 1)
        dt += 2 * p[:, None] * np.einsum("jkl,ik,il->ij", (each + each.transpose(0, 2, 1)) / 2, t, t, optimize=True)
    return float(loss), t * (dt - (dt * t).sum(1, keepdims=True)), p * (dp - dp @ p)


def solve(counts: np.ndarray, orders: int = 3, steps: int = 4000, rate: float = 0.05, symmetric: bool = False) -> Estimate:
    """T and p that explain the counted triples best, by Adam on logits from a diagonal start."""
    total = counts.sum()
    q3 = counts / max(total, 1)
    if symmetric:
        q3 = sum(q3.transpose(x) for x in ((0, 1, 2), (0, 2, 1), (1, 0, 2), (1, 2, 0), (2, 0, 1), (2, 1, 0))) / 6
    k = len(q3)
    a, b = 2.5 * np.eye(k), np.log(np.maximum(q3.sum((1, 2)), 1e-6))
    moment = [[np.zeros_like(a), np.zeros_like(b)] for _ in range(2)]
    last, done = np.inf, steps
    for step in range(1, steps + 1):
        loss, *grads = residual_and_gradient(a, b, q3, orders)
        for i, (x, g) in enumerate(zip((a, b), grads, strict=True)):
            moment[0][i] = 0.9 * moment[0][i] + 0.1 * g
            moment[1][i] = 0.999 * moment[1][i] + 0.001 * g * g
            x -= rate * moment[0][i] / (1 - 0.9**step) / (np.sqrt(moment[1][i] / (1 - 0.999**step)) + 1e-12)
        if abs(last - loss) < 1e-12:
            done = step
            break
        last = loss
    t = np.exp(a - a.max(1, keepdims=True))
    p = np.exp(b - b.max())
    return Estimate(t / t.sum(1, keepdims=True), p / p.sum(), loss, done, float(total))


def solve_likelihood(counts: np.ndarray, steps: int = 50, diagonal: float = 0.7) -> Estimate:
    """T and p that make the counted triples most likely, by expectation and maximisation from a diagonal start.

    The same model as ``solve``, of which it weighs the gaps by what sampling allows them; rare classes, whose gaps are
    small beside those of the common ones, are found better by it.
    """
    k, total = len(counts), max(counts.sum(), 1)
    t = np.full((k, k), (1 - diagonal) / (k - 1))
    np.fill_diagonal(t, diagonal)
    p = counts.sum((1, 2)) / total
    for _ in range(steps):
        w = np.einsum("i,ia,ib,ic->iabc", p, t, t, t)
        w = counts * w / np.maximum(w.sum(0), 1e-300)
        n = w.sum((1, 2, 3))
        p = n / max(n.sum(), 1e-300)
        t = (w.sum((2, 3)) + w.sum((1, 3)) + w.sum((1, 2))) / (3 * np.maximum(n, 1e-300))[:, None]
    gap = np.einsum("i,ia,ib,ic->abc", p, t, t, t) - counts / total
    return Estimate(t, p, float((gap**2).sum()), steps, float(total))


def count_tensor(triples: DataFrame, k: int) -> np.ndarray:
    """The K^3 counts on the driver; their number does not depend on the rows."""
    counts = np.zeros((k, k, k))
    for r in triples.groupBy("y1", "y2", "y3").count().collect():
        counts[r["y1"], r["y2"], r["y3"]] = r["count"]
    return counts


def estimate_transition(triples: DataFrame, k: int, method: str = "squares", **options) -> Estimate:
    """T and p from rating triples, by least squares on the consensus vectors or by their likelihood."""
    return (solve if method == "squares" else solve_likelihood)(count_tensor(triples, k), **options)


def estimate_by_group(triples: DataFrame, group: str, k: int, **options) -> DataFrame:
    """(group, i, j, prob, prior): one estimate a group, from the group's counts only."""
    counted = triples.groupBy(group, "y1", "y2", "y3").count()
    kind = triples.schema[group].dataType.simpleString()

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        counts = np.zeros((k, k, k))
        counts[rows["y1"], rows["y2"], rows["y3"]] = rows["count"]
        found = solve(counts, **options)
        i, j = np.divmod(np.arange(k * k), k)
        return pd.DataFrame({group: rows[group].iloc[0], "i": i.astype("int32"), "j": j.astype("int32"), "prob": found.t.ravel(), "prior": found.p[i]})

    return counted.groupBy(group).applyInPandas(run, f"`{group}` {kind}, i int, j int, prob double, prior double")


def transition_by_counting(df: DataFrame, k: int, truth_col: str = "y", score_col: str = "raw_score") -> DataFrame:
    """(i, j, n, prob): the row-normalised confusion of true and observed classes, on the dense grid."""
    grid = df.sparkSession.range(k * k).select(F.expr(f"cast(id div {k} as int)").alias("i"), F.expr(f"cast(id % {k} as int)").alias("j"))
    counted = df.groupBy(F.col(truth_col).cast("int").alias("i"), F.col(score_col).cast("int").alias("j")).agg(F.count("*").alias("n"))
    rows = counted.groupBy("i").agg(F.sum("n").alias("total"))
    return grid.join(F.broadcast(counted), ["i", "j"], "left").join(F.broadcast(rows), "i", "left").select("i", "j", F.coalesce("n", F.lit(0)).cast("bigint").alias("n"), F.coalesce(F.round(F.coalesce("n", F.lit(0)) / F.col("total"), 9), F.lit(0.0)).alias("prob"))


def transition_error(t: DataFrame, p: DataFrame) -> DataFrame:
    """How far T is from the identity: the prior-weighted error rate, the worst row's, and the Frobenius distance."""
    wrong = 1 - F.col("prob")
    rows = t.where("i = j").join(p, "i").agg(F.round(F.sum(F.col("prior") * wrong), 9).alias("error_rate"), F.round(F.max(wrong), 9).alias("worst_row"))
    away = F.col("prob") - F.when(F.col("i") == F.col("j"), 1.0).otherwise(0.0)
    return rows.crossJoin(t.agg(F.round(F.sqrt(F.sum(away * away)), 9).alias("frobenius")))


def correct(df: DataFrame, t: np.ndarray, p: np.ndarray, evidence: str = "neighbours", cols: tuple[str, ...] = ("y1", "y2", "y3")) -> DataFrame:
    """``df`` with posterior and corrected: the class with the largest posterior given the own rating, or also the two
    neighbours'. Ties go to the own rating, then to the lower class. A null rating of the row gives nulls; a null
    neighbour is no evidence. T and p are constants of the plan, so there is no exchange."""
    k, table = len(p), matrix_literal(np.asarray(t).T)  # by observed class
    used = cols[:1] if evidence == "own" else cols
    weight = F.array(*(F.lit(float(x)) for x in p))
    for c in used:
        likelihood = F.element_at(table, F.col(c) + 1)
        weight = F.when(F.col(c).isNull(), weight).otherwise(F.zip_with(weight, likelihood, lambda x, y: x * y))
    total = F.aggregate(weight, F.lit(0.0), lambda s, x: s + x)
    out = df.withColumn("posterior", F.when(F.col(cols[0]).isNotNull(), F.transform(weight, lambda x: F.round(x / total, 9))))
    top = F.array_max("posterior")
    first = F.array_position("posterior", top).cast("int") - 1
    own = F.when(F.element_at("posterior", F.col(cols[0]) + 1) == top, F.col(cols[0]).cast("int"))
    assert k == len(t)
    return out.withColumn("corrected", F.when(F.col(cols[0]).isNotNull(), F.coalesce(own, first)))


def suspects(df: DataFrame, threshold: float = 0.5, raw: str = "y1") -> DataFrame:
    """Rows whose rating was changed or is not probable enough."""
    return df.where((F.col("corrected") != F.col(raw)) | (F.element_at("posterior", F.col(raw) + 1) < threshold))


def partition_by_score(df: DataFrame, score_col: str = "corrected", low_max: int = 2) -> DataFrame:
    """``df`` with tier: low up to ``low_max``, high above, unassigned without a score. No row is dropped."""
    score = F.col(score_col)
    return df.withColumn("tier", F.when(score.isNull(), "unassigned").when(score <= low_max, "low").otherwise("high"))


def correction_gain(df: DataFrame, by: str | None = None, raw: str = "y1", truth: str = "y") -> DataFrame:
    """Rows, accuracy before and after, and the share of changed ratings; with ``by``, a row a group and a total."""
    aggs = [F.count("*").alias("n"), *(F.round(F.avg(x.cast("int")), 6).alias(name) for x, name in ((F.col(raw) == F.col(truth), "raw_accuracy"), (F.col("corrected") == F.col(truth), "corrected_accuracy"), (F.col("corrected") != F.col(raw), "changed")))]
    return df.agg(*aggs) if by is None else df.rollup(by).agg(*aggs)
