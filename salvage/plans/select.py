"""Ways of choosing rows: each gives (sample_id, score, rank) of at most n rows of a set."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.functions.keys import order_key, uniform
from salvage.functions.materialize import checkpoint
from salvage.plans import clusters, neighbors
from salvage.plans.pairing import global_position

#: Budget as a share of the set when no count is given.
SHARE = 0.443
#: How many times the least number of turns are asked of every target at once.
AHEAD = 8


def take(df: DataFrame, score: Column, n: int, seed: int = 42, descending: bool = True, first: Column | None = None) -> DataFrame:
    """The n best rows by score, ties in md5 order; rows without a score come last, and ``first`` (ascending) goes before
    the score. A range exchange puts ids and scores in order; n may be any size, and n rows come if there are as many."""
    scored = df.select("sample_id", score.cast("double").alias("score"), (F.lit(0) if first is None else first).alias("_f"))
    key = F.col("score").desc_nulls_last() if descending else F.col("score").asc_nulls_last()
    placed = global_position(scored.withColumn("_o", order_key("sample_id", seed)), F.col("_f"), key, F.col("_o"), F.col("sample_id"))
    return placed.where(F.col("pos") < n).select("sample_id", F.round("score", 6).alias("score"), (F.col("pos") + 1).alias("rank"))


def by_length(df: DataFrame, n: int, unit: str = "chars") -> DataFrame:
    return take(df, F.length("text") if unit == "chars" else F.regexp_count("text", F.lit(r"[^ \n\t]+")), n)


def distances(vectors: DataFrame, i: int = 10) -> DataFrame:
    """(sample_id, d): each row's mean distance to its i nearest neighbours."""
    return neighbors.knn(vectors, i, "euclid").groupBy("sample_id").agg(F.round(-F.avg("sim"), 5).alias("d"))


def by_knn(vectors: DataFrame, n: int, i: int = 10, far: DataFrame | None = None) -> DataFrame:
    """Rows far from their i nearest neighbours first; a row without neighbours comes last. ``far``: their distances, if
    they are known."""
    far = distances(vectors, i) if far is None else far
    return take(vectors.select("sample_id").join(far, "sample_id", "left"), F.col("d"), n)


def by_perplexity(scored: DataFrame, n: int, end: str = "low") -> DataFrame:
    """``scored`` is (sample_id, ppl); ``middle`` takes the rows closest to the median."""
    if end == "middle":
        mid = scored.agg(F.percentile("ppl", 0.5).alias("m"))
        scored = scored.crossJoin(F.broadcast(mid)).withColumn("ppl", F.abs(F.col("ppl") - F.col("m")))
    return take(scored, F.round("ppl", 6), n, descending=end == "high")


def at_random(df: DataFrame, n: int, seed: int = 42) -> DataFrame:
    return take(df, uniform("sample_id", seed), n, descending=False)


def top_rated(df: DataFrame, n: int, rating: str = "raw_score") -> DataFrame:
    """Highest ratings; md5 order within the rating at the cut."""
    return take(df, F.col(rating), n)


def by_difficulty(scored: DataFrame, n: int) -> DataFrame:
    """Largest ratio below 1. Where these are fewer than n, the rows at 1 and above follow, the least first, then rows
    without a ratio (no response)."""
    above = F.coalesce((F.col("difficulty") >= 1).cast("int"), F.lit(2))
    return take(scored, F.when(F.col("difficulty") < 1, F.col("difficulty")).otherwise(-F.col("difficulty")), n, first=above)


def score_diverse(df: DataFrame, pairs: DataFrame, score: Column, n: int) -> DataFrame:
    """In order of score, rows that are not similar to one accepted before, by the rounds of one-hop clusters; where these
    are fewer than n, the other rows follow in order of score. ``pairs`` is (a, b, sim)."""
    scored = df.withColumn("_score", score.cast("double"))
    hop = clusters.one_hop(scored, pairs, order=-F.col("_score")).select("sample_id", (~F.col("is_centroid")).cast("int").alias("_like"))
    return take(scored.join(hop, "sample_id"), F.col("_score"), n, first=F.col("_like"))


def score_diverse_of(df: DataFrame, vectors: DataFrame, score: Column, n: int, min_sim: float = 0.9, first_rows: int = clusters.FIRST_ROWS) -> DataFrame:
    """``score_diverse`` from the vectors (sample_id, vec) of ``df``, by prefixes of the order: later rows are compared
    with the accepted ones alone, so the pairs of all rows are never listed. A zero vector is similar to none."""
    scored = df.withColumn("_score", score.cast("double"))
    known = checkpoint(vectors.select("sample_id", "vec").join(scored.select("sample_id", (-F.col("_score")).alias("_o")), "sample_id"))
    real = F.exists("vec", lambda x: x != 0)
    hop = clusters.one_hop_of_copies(known.where(real), min_sim, "exact", first_rows, order="_o")
    like = hop.select("sample_id", (~F.col("is_centroid")).cast("int").alias("_like")).union(known.where(~real).select("sample_id", F.lit(0)))
    return take(scored.join(like, "sample_id"), F.col("_score"), n, first=F.col("_like"))


def by_target(vectors: DataFrame, targets: DataFrame, n: int) -> DataFrame:
    """Rows most similar to the targets (target_id, tvec), in turn: every target's first, then every second, and so on.

    Targets go to blocks of rows, and each block hands on as many rows a target as the turns need: about n over the number
    of targets times AHEAD, as targets share rows, four times as many whenever the turns gave fewer than n different rows.
    """
    rows = checkpoint(vectors.select("sample_id", "vec"))
    asked = checkpoint(targets.select((-1 - F.col("target_id")).alias("sample_id"), F.col("tvec").alias("vec")))
    whole, count = rows.count(), asked.count()
    turns = max(1, min(whole, AHEAD * -(-n // max(count, 1))))
    while True:
        near = checkpoint(neighbors.best_in_blocks(asked, rows, turns))
        seat = F.struct(F.col("nn_rank").alias("turn"), (-F.col("sample_id")).alias("t"))
        first = near.groupBy("nn_id").agg(F.min(seat).alias("m"), F.max("sim").alias("s"))
        placed = global_position(first, F.col("m"), F.col("nn_id"))
        if turns >= whole or placed.where(F.col("pos") == n - 1).count():
            break
        turns = min(whole, 4 * turns)
    # A row's best score is over all targets that may reach it in later turns too, so it is worked out for chosen rows.
    chosen = checkpoint(placed.where(F.col("pos") < n).select(F.col("nn_id").alias("sample_id"), (F.col("pos") + 1).alias("rank")))
    best = neighbors.best_in_blocks(rows.join(chosen.select("sample_id"), "sample_id", "left_semi"), asked, 1)
    return chosen.join(best.select("sample_id", "sim"), "sample_id").select("sample_id", F.round("sim", 6).alias("score"), "rank")


def corrected_rare(df: DataFrame, n: int) -> DataFrame:
    """Corrected rating first, distance to the neighbours second; ``df`` is (sample_id, corrected, d)."""
    return take(df, F.col("corrected") * 1000 + F.col("d"), n)


def by_rules(df: DataFrame, n: int, least: int = 100, most: int = 20_000, max_symbols: float = 0.05) -> DataFrame:
    """Thresholds on length and noise; what passes, longest first, then the rest in the same order."""
    symbols = F.regexp_count("text", F.lit(r"[#*%&$!|]")) / F.greatest(F.length("text"), F.lit(1))
    fails = ~(F.length("text").between(least, most) & (symbols <= max_symbols))
    return take(df, F.length("text"), n, first=F.coalesce(fails, F.lit(True)).cast("int"))


def overlap(selections: DataFrame) -> DataFrame:
    """Common rows and Jaccard of each two methods; ``selections`` is (method, sample_id)."""
    sizes = selections.groupBy("method").agg(F.count("*").alias("n"))
    x, y = selections.alias("x"), selections.alias("y")
    both = x.join(y, (F.col("x.sample_id") == F.col("y.sample_id")) & (F.col("x.method") < F.col("y.method"))).groupBy(F.col("x.method").alias("a"), F.col("y.method").alias("b")).agg(F.count("*").alias("common"))
    na, nb = sizes.select(F.col("method").alias("a"), F.col("n").alias("na")), sizes.select(F.col("method").alias("b"), F.col("n").alias("nb"))
    return na.crossJoin(nb).where("a < b").join(both, ["a", "b"], "left").select("a", "b", F.coalesce("common", F.lit(0)).alias("common"), F.round(F.coalesce("common", F.lit(0)) / (F.col("na") + F.col("nb") - F.coalesce("common", F.lit(0))), 6).alias("jaccard"))


#: Every way of choosing by one name; ``select`` takes what each needs as keywords.
METHODS = {
    "length": by_length, "knn": by_knn, "perplexity": by_perplexity, "random": at_random, "top_rated": top_rated, "difficulty": by_difficulty,
    "score_diverse": score_diverse, "target_sim": by_target, "corrected_rare": corrected_rare, "rules": by_rules,
}


def select(df: DataFrame, method: str, n: int, **options) -> DataFrame:
    """(sample_id, score, rank) of n rows by the named method; ``options`` are those of its function."""
    if method not in METHODS:
        raise ValueError(f"{method} is none of {', '.join(METHODS)}")
    return METHODS[method](df, n=n, **options)
