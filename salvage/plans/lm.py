"""Language models by counting: interpolated bigrams, and difficulty as a ratio of perplexities."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.functions.materialize import checkpoint, spread
from salvage.plans.pairing import global_position
from salvage.plans.samples import TERM

START = "<s>"


def bigrams(df: DataFrame, id_col: str, text: Column) -> DataFrame:
    """(id, v, w): each word with the word before it, a start mark before the first."""
    words = spread(df.select(F.col(id_col).alias("id"), text.alias("t"))).select("id", F.regexp_extract_all(F.lower("t"), F.lit(TERM), 0).alias("ws")).where("size(ws) > 0")
    pairs = F.arrays_zip(F.concat(F.array(F.lit(START)), F.slice("ws", 1, F.size("ws") - 1)).alias("v"), F.col("ws").alias("w"))
    return words.select("id", F.explode(pairs).alias("p")).select("id", F.col("p.v").alias("v"), F.col("p.w").alias("w"))


def words(df: DataFrame, text: Column) -> DataFrame:
    """(w, cw, cv, first): how often each word occurs, is followed by another, and begins a text."""
    found = spread(df.select(text.alias("t"))).select(F.regexp_extract_all(F.lower("t"), F.lit(TERM), 0).alias("ws"))
    each = found.select(F.size("ws").alias("n"), F.posexplode("ws").alias("at", "w"))
    last, first = (F.col("at") == F.col("n") - 1).cast("int"), (F.col("at") == 0).cast("int")
    return each.groupBy("w").agg(F.count("*").alias("cw"), (F.count("*") - F.sum(last)).alias("cv"), F.sum(first).alias("first"))


class Counts:
    """Bigram and word counts of a corpus, as tables; only three totals are scalars. With ``words`` of the same texts the
    word counts do not wait for those of the pairs."""

    def __init__(self, grams: DataFrame, words: DataFrame | None = None):
        self.grams = grams
        self.pair = grams.groupBy("v", "w").agg(F.count("*").alias("cvw"))
        if words is None:
            self.left = self.pair.groupBy("v").agg(F.sum("cvw").alias("cv"))
            self.word = self.pair.groupBy("w").agg(F.sum("cvw").alias("cw"))
        else:
            known = checkpoint(words)
            begin = known.agg(F.lit(START).alias("v"), F.sum("first").alias("cv"))
            self.left = known.where("cv > 0").select(F.col("w").alias("v"), "cv").union(begin)
            self.word = known.select("w", "cw")
        self.total = self.word.agg(F.sum("cw").alias("n"), F.count("*").alias("types"))

    def perplexity(self, some: DataFrame | None = None) -> DataFrame:
        """(id, ppl) of the counted rows themselves, or of ``some`` of them, whose words and pairs alone move then, once all
        are counted. A pair's probability is worked out once a pair, so the words are moved once, to their pairs, and then
        as sums by row."""
        low = 0.25 * F.col("cw") / F.greatest(F.col("n"), F.lit(1)) + 0.05 / F.col("types")
        pair = self.pair if some is None else self.pair.join(some.select("v", "w").distinct().hint("shuffle_hash"), ["v", "w"], "left_semi")
        known = pair.join(self.left, "v").join(self.word, "w").crossJoin(F.broadcast(self.total))  # one row
        scored = known.select("v", "w", F.log(low + 0.70 * (F.col("cvw") / F.col("cv"))).alias("log"))
        return (self.grams if some is None else some).join(scored, ["v", "w"]).groupBy("id").agg(F.exp(-F.sum("log") / F.count("*")).alias("ppl"))

    def probability(self, grams: DataFrame, order: int = 2, leave_out: bool = False) -> DataFrame:
        """``grams`` counted by row, with p = .70 c(v,w)/c(v) + .25 c(w)/N + .05/V, or the last two terms only, scaled.

        With ``leave_out`` the grams are part of the counted corpus, and a row's own counts are taken out of all of them.
        """
        own = grams.groupBy("id", "v", "w").agg(F.count("*").alias("k"))
        out = lambda part: part if leave_out else F.lit(0)
        by_word = own.groupBy("id", "w").agg(F.sum("k").alias("kw"))
        by_row = own.groupBy("id").agg(F.sum("k").alias("kn"))
        joined = own.join(by_word, ["id", "w"]).join(by_row, "id").join(self.word, "w").crossJoin(F.broadcast(self.total))  # one row
        low = 0.25 * (F.col("cw") - out(F.col("kw"))) / F.greatest(F.col("n") - out(F.col("kn")), F.lit(1)) + 0.05 / F.col("types")
        if order == 1:
            return joined.select("id", "v", "w", "k", (low / 0.30).alias("p"))
        by_left = own.groupBy("id", "v").agg(F.sum("k").alias("kv"))
        full = joined.join(by_left, ["id", "v"]).join(self.pair, ["v", "w"], "left").join(self.left, "v", "left")
        left = F.col("cv") - out(F.col("kv"))
        high = F.when(left > 0, (F.col("cvw") - out(F.col("k"))) / left).otherwise(0.0)
        return full.select("id", "v", "w", "k", (low + 0.70 * F.coalesce(high, F.lit(0.0))).alias("p"))


def perplexity(scored: DataFrame) -> DataFrame:
    """(id, ppl): exp of the negative mean log-probability of a row's words."""
    return scored.groupBy("id").agg(F.exp(-F.sum(F.col("k") * F.log("p")) / F.sum("k")).alias("ppl"))


#: Words that the model's own probability counts for beside the words of an instruction.
PRIOR_WORDS = 200


def difficulty(samples: DataFrame, order: int = 2) -> DataFrame:
    """(id, difficulty): perplexity of the response given the instruction over that of the response alone.

    The conditional model has the instruction's words as a cache: (c(w in instruction) + m p) / (length + m), with m =
    PRIOR_WORDS. The counts are of all other responses, never of the scored one. Order 1 is the small model.
    """
    response = bigrams(samples, "sample_id", F.col("response"))
    plain = Counts(response).probability(response, order, leave_out=True)
    cache = bigrams(samples, "sample_id", F.col("instruction")).groupBy("id", "w").agg(F.count("*").alias("ci"))
    size = cache.groupBy("id").agg(F.sum("ci").alias("li"))
    both = plain.join(cache, ["id", "w"], "left").join(size, "id", "left")
    given = (F.coalesce("ci", F.lit(0)) + PRIOR_WORDS * F.col("p")) / (F.coalesce("li", F.lit(0)) + PRIOR_WORDS)
    log = lambda x: F.sum(F.col("k") * F.log(x)) / F.sum("k")
    return both.groupBy("id").agg(F.round(F.exp(log("p") - log(given)), 6).alias("difficulty"))


def rank_correlation(a: DataFrame, b: DataFrame, key: str, x: str, y: str) -> DataFrame:
    """Spearman's correlation of two scores, mean ranks for ties; ranks come from global positions, not one partition."""
    joined = a.join(b, key).select(F.col(x).alias("x"), F.col(y).alias("y"))

    def mean_rank(c: str) -> DataFrame:
        placed = global_position(joined.select(c), F.col(c))
        return placed.groupBy(c).agg(F.avg(F.col("pos") + 1).alias(f"r{c}"))

    ranked = joined.join(mean_rank("x"), "x").join(mean_rank("y"), "y")
    return ranked.agg(F.count("*").alias("n"), F.round(F.corr("rx", "ry"), 6).alias("rho"))
