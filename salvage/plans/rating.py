"""Raters: a rubric of three dimensions from corpus statistics, and a text model that is asked for the same."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.functions.keys import let
from salvage.functions.materialize import spread
from salvage.plans.fuse.backends import TextModel, ask
from salvage.plans.fuse.rules import is_junk
from salvage.plans.samples import TERM, terms

#: Marks of noise, and those that are stuck to words.
MARKS, SUFFIXES = r"(###|\*\*\*|%%%|&&&|\$\$\$|!!| \| )", r"(###|\*\*\*|%%%|&&&|\$\$\$)"
#: Marks a word from which a text is noisy, share of distinct words below which it is poor, and numbers of distinct words
#: below which a text is poor, from which a clean one is full, and from which it is rich.
NOISY, POOR, FEW, FULL, RICH = 0.02, 0.35, 20, 30, 800


def _clamp(x: Column) -> Column:
    return F.least(F.lit(5), F.greatest(F.lit(0), x)).cast("int")


def grade(text: Column) -> Column:
    """The overall rating of a text, 0 to 5: noise stuck to words, other noise, poor wording, and three grades of clean
    texts by their number of distinct words. A text's words are looked for once."""
    words = F.greatest(F.regexp_count(text, F.lit(r"[^ \n\t\r]+")), F.lit(1))
    noisy = is_junk(text) & (F.regexp_count(text, F.lit(MARKS)) > NOISY * words)
    stuck = F.regexp_count(text, F.lit(SUFFIXES)) > NOISY * words

    def clean(f: Column) -> Column:
        types, n = f["types"], f["n"]
        return F.when((types < FEW) | (types < POOR * n), 2).when(types < FULL, 3).when(types < RICH, 4).otherwise(5)

    found = F.regexp_extract_all(F.lower(text), F.lit(TERM), F.lit(0))
    counted = let(found, lambda w: F.struct(F.size(F.array_distinct(w)).alias("types"), F.size(w).alias("n")))
    return F.when(noisy, F.when(stuck, 0).otherwise(1)).otherwise(let(counted, clean))


def grade_sql(text: str = "text") -> str:
    words = f"greatest(len(regexp_extract_all({text}, '[^ \\n\\t\\r]+')), 1)"
    found = f"regexp_extract_all(lower({text}), '{TERM}')"
    marks = lambda p: f"len(regexp_extract_all({text}, '{p}')) > {NOISY}::DOUBLE * {words}"
    types = f"len(list_distinct({found}))"
    return f"(CASE WHEN {marks(MARKS)} THEN CASE WHEN {marks(SUFFIXES)} THEN 0 ELSE 1 END WHEN {types} < {FEW} OR {types} < {POOR}::DOUBLE * len({found}) THEN 2 WHEN {types} < {FULL} THEN 3 WHEN {types} < {RICH} THEN 4 ELSE 5 END)"


def rubric(docs: DataFrame) -> DataFrame:
    """(doc_id, rarity, complexity, informativeness, raw_score), each 0 to 5.

    Rarity is the mean idf of the words, complexity the share of distinct words, informativeness the number of distinct
    words less the noise marks; the overall rating is ``grade``. A text without words rates 2 at most.
    """
    docs = spread(docs.select("doc_id", "text"))
    tf = terms(docs, "doc_id", "text").groupBy("id", "term").agg(F.count("*").alias("tf"))
    df = tf.groupBy("term").agg(F.count("*").alias("df"))
    n = docs.agg(F.count("*").alias("n"))
    idf = F.sum(F.col("tf") * F.log(F.col("n") / F.col("df"))) / F.sum("tf")
    facts = tf.join(df, "term").crossJoin(F.broadcast(n)).groupBy("id").agg(idf.alias("idf"), (F.count("*") / F.sum("tf")).alias("variety"), F.count("*").alias("uniq"))
    noise = docs.select("doc_id", F.regexp_count("text", F.lit(r"[#*%&$!|]")).alias("noise"), grade(F.col("text")).alias("raw_score"))
    x = noise.join(facts, F.col("doc_id") == F.col("id"), "left").fillna(0, ["noise", "idf", "variety", "uniq"])
    net = F.col("uniq") - F.col("noise")
    informative = F.when(net < 10, 0).when(net < 50, 1).when(net < 100, 2).when(net < 200, 3).when(net < 400, 4).otherwise(5)
    return x.select("doc_id", _clamp(F.floor("idf")).alias("rarity"), _clamp(F.floor(F.col("variety") * 6)).alias("complexity"), informative.alias("informativeness"), "raw_score")


RATING = "rarity int, complexity int, informativeness int, overall int"


def rate(docs: DataFrame, model: TextModel, cache: str, options: dict[str, str] | None = None) -> DataFrame:
    """(doc_id, rarity, complexity, informativeness, raw_score) as a text model rates them, in JSON.

    A reply that is missing, is no JSON object or names an overall rating beyond 0 to 5 gives a null raw_score: such a
    row is unassigned later, never dropped. ``cache`` is the folder of the calls made so far.
    """
    asked = docs.select("doc_id", F.concat(F.lit("Rate the text from 0 to 5 for rarity, complexity, informativeness and overall; answer as JSON.\n"), "text").alias("prompt"))
    said = ask(asked, model, "rate", cache, options or {"temperature": "0.2"})
    parsed = said.withColumn("r", F.from_json("reply", RATING))
    return parsed.select("doc_id", "r.rarity", "r.complexity", "r.informativeness", F.when(F.col("r.overall").between(0, 5), F.col("r.overall")).alias("raw_score"))
