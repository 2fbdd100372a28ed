import pytest
from pyspark.sql import functions as F

from salvage.plans import lm


def test_perplexity_of_the_counted_rows(spark):
    """The same numbers as from each row's own counts, and no exchange of the words by row and word."""
    texts = ["the cat sat on the mat", "the the the", "a dog", "dog a dog a dog", "", "rare"]
    df = spark.createDataFrame(list(enumerate(texts)), "sample_id long, text string")
    grams = lm.bigrams(df, "sample_id", F.col("text"))
    counts = lm.Counts(grams)
    found = counts.perplexity()
    want = {r["id"]: r["ppl"] for r in lm.perplexity(counts.probability(grams)).collect()}
    assert {r["id"]: r["ppl"] for r in found.collect()} == {k: pytest.approx(v, rel=1e-12) for k, v in want.items()} and len(want) == 5
    assert not any("hashpartitioning(id" in line and ("w#" in line or "v#" in line) for line in found._jdf.queryExecution().executedPlan().toString().split("\n"))
