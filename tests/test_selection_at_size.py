"""Selectors that move only what they choose from."""

import numpy as np
from pyspark.sql import functions as F

from salvage.plans import lm, neighbors, select
from test_clusters import frame


def test_diverse_rows_need_no_list_of_pairs(spark):
    rng = np.random.default_rng(11)
    base = rng.standard_normal((30, 8))
    v = frame(spark, np.vstack([base, base + 0.05 * rng.standard_normal((30, 8)), np.repeat(base[:3], 5, 0), np.zeros((3, 8))])).select("sample_id", "vec")
    rows = v.select("sample_id", F.pmod(F.xxhash64("sample_id"), F.lit(7)).alias("s"))
    strip = lambda df: sorted((r["sample_id"], r["score"], r["rank"]) for r in df.collect())
    want = strip(select.score_diverse(rows, neighbors.sim_pairs(v, 0.9), F.col("s"), 50))
    assert strip(select.score_diverse_of(rows, v, F.col("s"), 50, first_rows=9)) == want


def test_perplexity_of_some_rows_counts_all(spark):
    docs = spark.createDataFrame([(1, "a b a b c"), (2, "b c d"), (3, ""), (4, "a c")], "id long, t string")
    grams = lm.bigrams(docs, "id", F.col("t"))
    whole = {r["id"]: round(r["ppl"], 9) for r in lm.Counts(grams).perplexity().collect()}
    some = lm.bigrams(docs.where("id in (1, 3)"), "id", F.col("t"))
    assert {r["id"]: round(r["ppl"], 9) for r in lm.Counts(grams).perplexity(some).collect()} == {1: whole[1]}
