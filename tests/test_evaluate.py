"""Selectors and stand-in learners on small tables."""

import pytest
from pyspark.sql import functions as F

from salvage.plans import evaluate, lm, select


@pytest.fixture(scope="module")
def rows(spark):
    return spark.createDataFrame([(i, "word " * (i % 7 + 1) + f"tail{i}", i % 3) for i in range(40)], "sample_id long, text string, raw_score int")


def test_take_is_exact_and_stable(rows):
    got = select.take(rows, F.col("raw_score"), 20).orderBy("rank").collect()
    assert [r["rank"] for r in got] == list(range(1, 21)) and [r["score"] for r in got] == sorted((r["score"] for r in got), reverse=True)
    assert got == select.take(rows.repartition(5), F.col("raw_score"), 20).orderBy("rank").collect()
    assert {r["sample_id"] for r in got} <= {r["sample_id"] for r in select.take(rows, F.col("raw_score"), 30).collect()}
    assert select.take(rows.limit(0), F.col("raw_score"), 5).count() == 0
    ends = [select.by_perplexity(rows.select("sample_id", F.col("sample_id").cast("double").alias("ppl")), 3, e) for e in ("low", "high", "middle")]
    assert [sorted(r["sample_id"] for r in e.collect()) for e in ends][:2] == [[0, 1, 2], [37, 38, 39]]


def test_target_turns(spark):
    pool = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.9, 0.1]), (3, [0.0, 1.0]), (4, [0.1, 0.9])], "sample_id long, vec array<float>")
    targets = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 1.0])], "target_id long, tvec array<float>")
    assert [r["sample_id"] for r in select.by_target(pool, targets, 3).orderBy("rank").collect()] == [1, 3, 2]


def test_overlap(spark):
    s = spark.createDataFrame([("a", 1), ("a", 2), ("b", 2), ("b", 3), ("c", 9)], "method string, sample_id long")
    got = {(r["a"], r["b"]): (r["common"], r["jaccard"]) for r in select.overlap(s).collect()}
    assert got == {("a", "b"): (1, 0.333333), ("a", "c"): (0, 0.0), ("b", "c"): (0, 0.0)}


def test_perplexity_prefers_what_was_seen(spark):
    texts = spark.createDataFrame([(i, "the cat sat on the mat") for i in range(9)] + [(9, "quartz jumble vexed wolf")], "i long, text string")
    grams = lm.bigrams(texts, "i", F.col("text"))
    ppl = {r["id"]: r["ppl"] for r in lm.perplexity(lm.Counts(grams).probability(grams)).collect()}
    assert ppl[9] > ppl[0] > 1


@pytest.mark.parametrize("learner", ["bayes", "centroid", "logistic", "least_squares"])
def test_learners_tell_languages_apart(spark, sf, learner):
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    facts = evaluate.targets(docs, labels).withColumn("test", evaluate.held_out(F.col("text")))
    both = F.when(F.col("T1") == 1, F.array(F.lit("all"), F.lit("english"))).otherwise(F.array(F.lit("all")))
    train = facts.where("not test").select(both.alias("methods"), "text", *evaluate.TASKS)
    scores = {(r["method"], r["task"]): r["score"] for r in evaluate.compare(train, facts.where("test"), ["all", "english"], learner).collect()}
    assert scores["all", "T1"] > 90 and scores["all", "T1"] > scores["english", "T1"]  # a set of one language can't teach four
    assert set(t for _, t in scores) == {"T1", "T2", "T3", "T4", "T5"}


def test_all_held_out_rows_are_scored(spark):
    train = spark.createDataFrame([(["a"], "Yes my first sentence. red fox"), (["a", "b"], "Zoo closed again today! red")], "methods array<string>, text string")
    test = spark.range(2500).select(F.col("id").alias("sample_id"), F.when(F.col("id") < 1000, "Yes my first sentence. red fox").otherwise("Zoo closed again today! red").alias("text"))
    got = {r["method"]: (r["n"], r["score"]) for r in evaluate.nearest_texts(train, test, ["a", "b", "none"]).collect()}
    assert got == {"a": (2500, 100.0), "b": (2500, round(100 * (1000 * 2 / 3 + 1500) / 2500, 1)), "none": (2500, 0.0)}
    assert evaluate.nearest_texts(train, test.limit(0), ["a", "b"]).count() == 0


def test_selectors_fill_their_budget(spark):
    scored = spark.createDataFrame([(1, 0.9), (2, 0.5), (3, 1.2), (4, 1.1), (5, None)], "sample_id long, difficulty double")
    order = [r["sample_id"] for r in select.select(scored, "difficulty", 5).orderBy("rank").collect()]
    assert order == [1, 2, 4, 3, 5]
    with pytest.raises(ValueError):
        select.select(scored, "unknown", 1)
    rows = spark.createDataFrame([(i, 10 - i) for i in range(6)], "sample_id long, s int")
    near = spark.createDataFrame([(0, 1, 0.95), (1, 2, 0.95)], "a long, b long, sim double")
    assert [r["sample_id"] for r in select.score_diverse(rows, near, F.col("s"), 6).orderBy("rank").collect()] == [0, 2, 3, 4, 5, 1]
