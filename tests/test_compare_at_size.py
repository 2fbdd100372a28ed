"""What no learner takes part in is worked out once for all of them."""

import threading
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from salvage.functions.stages import Stages
from salvage.functions.together import together
from salvage.plans import evaluate, lm
from salvage.plans.chain import Chain
from salvage.plans.fuse import loop
from salvage.plans.rating import rubric


def test_learners_share_the_continuations(spark, monkeypatch):
    texts = ["one two. three four", "five six. seven eight", "nine ten. three four"]
    train = spark.createDataFrame([(["a"] if i else ["a", "b"], t, i % 2, 0, 1, 1) for i, t in enumerate(texts)], "methods array<string>, text string, T1 int, T2 int, T3 int, T4 int")
    test = spark.createDataFrame([(9, "one two. three five", 0, 0, 1, 1), (8, "five six. seven", 1, 0, 1, 1)], "sample_id long, text string, T1 int, T2 int, T3 int, T4 int")
    key = lambda r: (r["method"], r["task"], r["n"], r["score"])
    want = sorted((learner, *key(r)) for learner in ("bayes", "centroid") for r in evaluate.compare(train, test, ["a", "b"], learner, ("T1", "T5")).collect())
    calls, real = [], evaluate.nearest_texts
    monkeypatch.setattr(evaluate, "nearest_texts", lambda *a: calls.append(1) or real(*a))
    monkeypatch.setattr(evaluate.neighbors, "SLICE_ROWS", 1)
    got = evaluate.compare_learners(train, test, ["a", "b"], ("bayes", "centroid"), ("T1", "T5"))
    assert sorted((r["learner"], *key(r)) for r in got.collect()) == want and len(calls) == 1


def test_steps_run_together_and_share_a_stage(spark, sf):
    """Steps of one call meet, an error comes through, and a stage that two of them need is built once."""
    met, built = threading.Barrier(2, timeout=30), []

    def build():
        built.append(1)
        time.sleep(0.2)
        return spark.range(3)

    def step():
        met.wait()
        return Stages(spark, sf).table("test-together", build).count()

    assert together(step, step) == [3, 3] and built == [1]
    with pytest.raises(ZeroDivisionError):
        together(lambda: 1 // 0, lambda: 1)


def test_continuations_do_not_wait_for_the_learner(spark, monkeypatch):
    """Both meet at a barrier; one after the other they would not."""
    met, learn, nearest = threading.Barrier(2, timeout=60), evaluate.learn, evaluate.nearest_texts
    monkeypatch.setattr(evaluate, "learn", lambda *a: met.wait() * 0 or learn(*a))
    monkeypatch.setattr(evaluate, "nearest_texts", lambda *a: met.wait() * 0 or nearest(*a))
    train = spark.createDataFrame([(["a"], "one two. three", 0, 0, 1, 1)], "methods array<string>, text string, T1 int, T2 int, T3 int, T4 int")
    test = spark.createDataFrame([(9, "one two. three", 0, 0, 1, 1)], "sample_id long, text string, T1 int, T2 int, T3 int, T4 int")
    assert {r["task"]: r["score"] for r in evaluate.compare(train, test, ["a"], "centroid").collect()} == dict.fromkeys(("T1", "T2", "T3", "T4", "T5"), 100.0)


def test_logistic_weights_are_those_of_plain_steps(spark):
    """Against the steps written out for one training set and task at a time, with labels that are not known."""
    texts = [f"word{i % 5} text{i} more{i * i}" for i in range(20)]
    rows = [((["a"] if i % 3 else ["b", "a"]) + ["other"] * (i % 2), t, i % 4 if i % 7 else None, i % 2, i % 10, None) for i, t in enumerate(texts)]
    train = spark.createDataFrame(rows, "methods array<string>, text string, T1 int, T2 int, T3 int, T4 int")
    got = evaluate.learn(train, ["a", "b", "none"], "logistic")
    x = np.hstack([evaluate._features(texts)[0].astype(np.float32).astype(float), np.ones((20, 1))])
    for m in ("a", "b", "none"):
        for at, (t, k) in enumerate(evaluate.TASKS.items(), 2):
            own = [i for i, r in enumerate(rows) if m in r[0] and r[at] is not None]
            w = ahead = np.zeros((k, x.shape[1]))
            for step in range(evaluate.STEPS if own else 0):
                z = np.exp(x[own] @ ahead.T)
                p = z / z.sum(1, keepdims=True) - np.eye(k)[[rows[i][at] for i in own]]
                moved = ahead - 2.0 * (p.T @ x[own] / len(own) + evaluate.PENALTY * ahead)
                ahead, w = moved + step / (step + 3) * (moved - w), moved
            assert np.allclose(got[m, t], w, atol=1e-9)


def test_no_round_of_the_loop_is_without_pairs(spark, monkeypatch):
    """The first draft of clean short texts has no loss, so there is one draft and one check."""
    calls, real = [], loop.RuleOperators.draft
    monkeypatch.setattr(loop.RuleOperators, "draft", lambda self, df: calls.append(1) or real(self, df))
    pairs = spark.createDataFrame([("p", "1", "2", "apple trees grow.", "stone walls stand.")], "pair_id string, a string, b string, text_a string, text_b string")
    merged, trace = loop.fuse(pairs)
    assert len(calls) == 1 and merged.first()["loss1"] == 0 and trace.where("op = 'draft'").count() == 1


def test_word_counts_are_those_of_the_pairs(spark):
    docs = spark.createDataFrame(list(enumerate(["the cat the", "cat", "", "a the a", "rare cat"])), "id long, t string")
    grams = lm.bigrams(docs, "id", F.col("t"))
    plain, counted = lm.Counts(grams), lm.Counts(grams, lm.words(docs, F.col("t")))
    for name in ("left", "word", "total"):
        assert sorted(map(tuple, getattr(plain, name).collect())) == sorted(map(tuple, getattr(counted, name).collect()))
    some = lm.bigrams(docs.where("id in (0, 4)"), "id", F.col("t"))
    want = {r["id"]: round(r["ppl"], 9) for r in plain.perplexity().collect()}
    assert {r["id"]: round(r["ppl"], 9) for r in counted.perplexity(some).collect()} == {i: want[i] for i in (0, 4)}


def test_low_documents_are_kept_and_rated_alone(spark, sf):
    """They are written once with their texts, and their complexity is that among all documents."""
    low = Chain(spark, sf).low_documents()
    assert "documents.parquet" not in low._jdf.queryExecution().executedPlan().toString()
    assert all("chain-low-documents" in f for f in low.inputFiles())
    score = lambda df: {r["doc_id"]: r["complexity"] for r in rubric(df).collect()}
    every = score(spark.read.parquet(f"{sf}/documents.parquet"))
    assert score(low) == {r["doc_id"]: every[r["doc_id"]] for r in low.select("doc_id").collect()}


def test_equal_first_sentences_are_compared_once(spark, monkeypatch):
    """Against all pairs one by one, with copies, ties, a method without rows and texts without a continuation."""
    starts, ends = ["red apples grow.", "stone walls stand.", "red apples fall."], [" one two", " two three four", "", " five"]
    rows = [((["a"] if i % 2 else ["b", "a"]) if i % 5 else ["c"], starts[i % 3] + ends[i % 4], 0, 0, 1, 1) for i in range(24)]
    train = spark.createDataFrame(rows, "methods array<string>, text string, T1 int, T2 int, T3 int, T4 int").coalesce(1)
    asked = [starts[i % 2] + ends[(i + 1) % 4] for i in range(9)]
    test = spark.createDataFrame([(i, t) for i, t in enumerate(asked)], "sample_id long, text string")
    part = lambda t: (t[: t.index(".") + 1], t[t.index(".") + 1 :])
    vec = {s: evaluate.char_vector(s).astype(np.float32).astype(float) for s in starts}
    want = {"none": 0.0}
    for m in "abc":
        own, total = [part(r[1]) for r in rows if m in r[0]], 0.0
        for head, rest in map(part, asked):
            near = max(range(len(own)), key=lambda j: (round(float(vec[own[j][0]] @ vec[head]), 9), -j))
            total += evaluate.token_f1(own[near][1], rest)
        want[m] = round(100 * total / len(asked), 1)
    sizes, real = [], evaluate.neighbors.block_pairs
    monkeypatch.setattr(evaluate.neighbors, "block_pairs", lambda a, b: sizes.append((a.count(), b.count())) or real(a, b))
    assert {r["method"]: r["score"] for r in evaluate.nearest_texts(train, test, ["a", "b", "c", "none"]).collect()} == want
    assert sizes == [(2, 9)]  # of 9 and 24 rows
