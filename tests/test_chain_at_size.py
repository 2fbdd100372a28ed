"""The steps of the chain do their work once: words of a text, terms of a pair, blocks of low rows."""

import time

import numpy as np
from pyspark.sql import functions as F

from salvage.functions.keys import let
from salvage.plans import clusters, neighbors, rating
from salvage.plans.fuse import rules
from salvage.plans.fuse.loop import fuse
from test_clusters import frame


def test_a_grade_looks_for_words_once(spark):
    rows = spark.createDataFrame([(None,), ("",), ("one two ### three",), ("x !! y",), (" ".join(f"w{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(200)),)], "text string")
    graded = rows.select(rating.grade(F.col("text")).alias("g"))
    assert graded._jdf.queryExecution().optimizedPlan().toString().count("[a-zà-ÿ]+") == 1
    assert [r["g"] for r in graded.collect()] == [5, 2, 0, 1, 4]


def test_shared_terms_of_a_pair_are_worked_out_once(spark):
    """Long parents: with the shared terms looked for again at every sentence this took minutes."""
    text = [f"sentence {chr(97 + i % 26) * 5} {chr(97 + i // 26 % 26) * 6} number" for i in range(4000)]
    rows = spark.createDataFrame([(text[:2500], text[1500:])], "a array<string>, b array<string>")
    begin = time.monotonic()
    out = rows.select(F.size(rules.arrange(F.lit("S4"), F.col("a"), F.col("b"))).alias("n")).first()["n"]
    assert out == len(set(text)) and time.monotonic() - begin < 15


def test_let_names_a_value(spark):
    assert spark.range(3).select(let(F.col("id") + 1, lambda x: x * x).alias("y")).agg(F.sum("y")).first()[0] == 14


def test_few_low_rows_are_compared_whole(spark, monkeypatch):
    rng = np.random.default_rng(5)
    base = rng.standard_normal((40, 8))
    v = frame(spark, np.vstack([base, base + 0.05 * rng.standard_normal((40, 8))]))
    strip = lambda df: sorted((r["sample_id"], r["cluster_id"], r["is_centroid"]) for r in df.collect())
    want = strip(clusters.one_hop(v, neighbors.sim_pairs(v, 0.9)))
    monkeypatch.setattr(neighbors, "band_keys", None)
    assert strip(clusters.one_hop_of_copies(v, 0.9, first_rows=15, whole_rows=clusters.WHOLE_ROWS)) == want


def test_a_loop_without_trace_writes_none(spark):
    pairs = spark.createDataFrame([("p", "1", "2", "First words here. More words follow.", "Other words there. Some more.")], "pair_id string, a string, b string, text_a string, text_b string")
    merged, trace = fuse(pairs, traced=False)
    assert trace is None and merged.count() == 1
