"""Measures over results and corpora."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.functions.vectors import sum_vectors, unit
from salvage.plans.samples import TERM, terms


def normal(text: Column) -> Column:
    """Lower case, punctuation to blanks, single blanks; articles stay, as texts come in several languages."""
    return F.trim(F.regexp_replace(F.regexp_replace(F.lower(text), r"[^a-zà-ÿ0-9]+", " "), " +", " "))


def exact_match(df: DataFrame, pred: str, gold: str) -> DataFrame:
    return df.agg(F.count("*").alias("n"), F.round(100 * F.avg((normal(F.col(pred)) == normal(F.col(gold))).cast("int")), 6).alias("em"))


def token_f1(pred: Column, gold: Column) -> Column:
    """Token F1 as an expression: the multiset overlap of two word lists."""
    p, g = (F.filter(F.split(normal(c), " "), lambda x: x != "") for c in (pred, gold))
    times = lambda words, w: F.size(F.filter(words, lambda x: x == w))
    common = F.aggregate(F.array_distinct(p), F.lit(0), lambda s, w: s + F.least(times(p, w), times(g, w)))
    return F.when((F.size(p) == 0) & (F.size(g) == 0), 1.0).when((F.size(p) == 0) | (F.size(g) == 0), 0.0).otherwise(2 * common / (F.size(p) + F.size(g)))


def mean_score(results: DataFrame) -> DataFrame:
    """(model, method, mean): the unweighted mean over tasks, half up to one decimal."""
    return results.groupBy("model", "method").agg(F.round(F.sum(F.col("score").cast("decimal(10,2)")) / F.count("*"), 1).cast("double").alias("mean"))


def delta(results: DataFrame, base: str = "low") -> DataFrame:
    """Each score less the base method's score on the same task."""
    own = results.where(F.col("method") == base).select("model", "task", F.col("score").alias("b"))
    return results.join(F.broadcast(own), ["model", "task"]).select("model", "method", "task", F.round(F.col("score") - F.col("b"), 1).alias("delta"))


def rank_rows(means: DataFrame) -> DataFrame:
    """Place of each method by its mean, and whether it is best or second."""
    place = F.dense_rank().over(Window.partitionBy("model").orderBy(F.desc("mean")))
    return means.withColumn("place", place.cast("bigint")).withColumn("mark", F.when(F.col("place") == 1, "best").when(F.col("place") == 2, "second"))


#: Rows of a comparison that are no selectors.
CONTROLS = ("none", "low", "high", "full", "merged")


def spread(means: DataFrame, base: str = "low") -> DataFrame:
    """Least and greatest mean of the selectors, their mean, and their distances to the base."""
    low = means.where(F.col("method") == base).select("model", F.col("mean").alias("base"))
    own = means.where(~F.col("method").isin(*CONTROLS)).groupBy("model").agg(F.min("mean").alias("least"), F.max("mean").alias("most"), F.round(F.avg("mean"), 3).alias("centre"))
    return own.join(low, "model").select("model", "least", "most", "centre", "base", F.round(F.col("most") - F.col("base"), 1).alias("above"), F.round(F.col("base") - F.col("least"), 1).alias("below"))


def scaling(scores: DataFrame) -> DataFrame:
    """Slope of the mean score over the logarithm of the size, and the number of steps that do not fall; ``scores`` is
    (model, share, mean)."""
    step = F.col("mean") - F.lag("mean").over(Window.partitionBy("model").orderBy("share"))
    return scores.withColumn("d", step).groupBy("model").agg(F.round(F.regr_slope("mean", F.log("share")), 6).alias("slope"), F.count_if(F.col("d") >= 0).alias("rising"))


def distinct_ngrams(df: DataFrame, id_col: str, text_col: str, n: int = 2) -> DataFrame:
    """Different word n-grams, all of them, and their ratio."""
    words = df.select(F.regexp_extract_all(F.lower(text_col), F.lit(TERM), 0).alias("w"))
    grams = words.where(F.size("w") >= n).select(F.explode(F.transform(F.arrays_zip(*(F.slice("w", i, F.size("w") - (n - 1)).alias(f"w{i}") for i in range(1, n + 1))), lambda z: F.concat_ws(" ", *(z[f"w{i}"] for i in range(1, n + 1))))).alias("g"))
    counts = grams.groupBy("g").agg(F.count("*").alias("c"))
    return counts.agg(F.count("*").alias("different"), F.sum("c").alias("total"), F.round(F.count("*") / F.sum("c"), 6).alias("ratio"))


def mean_pair_cosine(vectors: DataFrame) -> DataFrame:
    """The mean cosine of all pairs of different rows, from the sum of the unit vectors alone."""
    total = sum_vectors(vectors.select(F.lit(1).alias("g"), unit(F.col("vec")).alias("u")), ["g"], "u")
    full = vectors.select(F.count_if(F.exists("vec", lambda x: x != 0)).alias("full"))  # zero vectors have no cosine with themselves
    square = F.aggregate("sums", F.lit(0.0), lambda s, x: s + x * x)
    return total.crossJoin(full).select("n", F.round((square - F.col("full")) / (F.col("n") * (F.col("n") - 1)), 6).alias("mean_cosine"))  # one row each


def diversity(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Types, tokens, their ratio, and the entropy of the word distribution."""
    counts = terms(df, id_col, text_col).groupBy("term").agg(F.count("*").alias("c"))
    total = counts.agg(F.sum("c").alias("n"))
    return counts.crossJoin(F.broadcast(total)).agg(F.count("*").alias("types"), F.max("n").alias("tokens"), F.round(F.count("*") / F.max("n"), 6).alias("ratio"), F.round(-F.sum(F.col("c") / F.col("n") * F.log(F.col("c") / F.col("n"))), 6).alias("entropy"))
