"""The loop's bounds, its choice of versions, and the replay of calls."""

import pytest
from pyspark.sql import functions as F

from salvage.plans import evaluate, metrics
from salvage.plans.fuse import rules
from salvage.plans.fuse.backends import EchoModel, HttpModel, call, replay
from salvage.plans.fuse.loop import Options, fuse, fuse_clusters

A = "The river carries water to the valley. Farmers build channels there. BUY!! NOW!! The harvest depends upon rainfall."
B = "Channels need repairs every spring. Stones### block*** the flow. Villages share costs between families."


@pytest.fixture(scope="module")
def pairs(spark):
    rows = [("p1", "1", "2", A, B), ("p2", "3", "4", A, A), ("p3", "5", "6", None, ""), ("p4", "7", "8", " ".join(f"Sentence number {chr(97 + i % 26) * 5}{chr(97 + i // 26) * 4} stands here." for i in range(120)), B)]
    return spark.createDataFrame(rows, "pair_id string, a string, b string, text_a string, text_b string")


def test_loop_bounds_and_best_version(pairs):
    merged, trace = fuse(pairs)
    rows, calls = {r["pair_id"]: r for r in merged.collect()}, trace.collect()
    assert set(rows) == {"p1", "p2", "p3", "p4"} and rows["p1"]["parents"] == ["1", "2"]
    assert rows["p2"]["relation"] == "same" and rows["p1"]["relation"] in ("related", "unrelated")
    assert "###" not in rows["p1"]["assistant"] and "!!" not in rows["p1"]["assistant"]
    for p in rows:
        audits = [r["loss"] for r in calls if r["pair_id"] == p and r["op"] == "audit"]
        assert 1 <= len(audits) <= 4 and rows[p]["loss1"] == min(audits)
        assert 4 <= sum(r["pair_id"] == p for r in calls) <= 16
    assert {rows[p]["strategy"] for p in rows} <= {f"S{k}" for k in range(1, 10)}
    assert all(r["status"] == ("accepted" if r["loss1"] == r["loss2"] == 0 else "exhausted") for r in rows.values())


def test_all_terms_are_audited(pairs):
    row = fuse(pairs.where("pair_id = 'p4'"))[0].first()
    texts = pairs.where("pair_id = 'p4'").first()
    clean = [s for t in (texts["text_a"], texts["text_b"]) for s in t.split(". ") if "###" not in s]
    terms = {w for s in clean for w in s.lower().strip(".").split() if len(w) >= 4}
    said = set(row["assistant"].lower().replace(".", " ").replace(",", " ").split())
    assert len(terms) > 100 and row["loss1"] == 0 and terms - said <= {"stones", "block"} | said


def test_ablations_cost_fewer_calls(pairs):
    full, none = fuse(pairs)[1].count(), fuse(pairs, Options(cycle1=False, cycle2=False))[1].count()
    assert none < full
    assert fuse(pairs, Options(max_regen=0))[1].where("op = 'draft'").count() == 4


def test_each_strategy_drafts_in_its_own_way(spark):
    rows = spark.createDataFrame([(["one short", "a longer sentence here"], ["two things", "a longer sentence here", "the last sentence"])], "a array<string>, b array<string>")
    got = {s: rows.select(rules.arrange(F.lit(s), F.col("a"), F.col("b")).alias("x")).first()["x"] for _, s, _, _ in rules.STRATEGIES}
    assert len({tuple(x) for x in got.values()}) == 9
    assert got["S2"][0] == "a longer sentence here" and got["S3"][0] == "one short" and got["S7"][:2] == ["one short", "two things"] and got["S8"][0] == "As one short, so two things"
    assert got["S9"][0].startswith("Part one: ") and got["S6"][0] == "two things" and got["S5"][-1].startswith("For example: ")


def test_ablations_change_the_answer(pairs):
    text = lambda **o: {r["pair_id"]: r["assistant"] for r in fuse(pairs, Options(**o))[0].collect()}
    full = text()
    assert text(strategies=False) != full and text(purge=False)["p1"] != full["p1"] and text(cycle1=False)["p4"] != full["p4"]


def test_model_is_called_as_often_as_the_trace_says(spark, pairs, tmp_path):
    from salvage.plans.queries_fusion import Merger

    cache = str(tmp_path / "calls")
    merged, trace = fuse(pairs, model=Merger(), cache=cache)
    made = spark.read.parquet(cache).count()
    assert merged.count() == 4 and made <= trace.count() and made == spark.read.parquet(cache).select("key").distinct().count()
    assert trace.groupBy("pair_id").count().agg(F.max("count")).first()[0] <= 16
    again, _ = fuse(pairs, model=Merger(), cache=cache)
    assert spark.read.parquet(cache).count() == made and sorted(map(str, again.collect())) == sorted(map(str, merged.collect()))


def test_clusters_end_with_one_row(spark):
    reps = spark.createDataFrame([(1, i) for i in range(5)] + [(2, 9)], "cluster_id long, sample_id long")
    texts = spark.createDataFrame([(i, f"Topic {i} talks about subject{chr(97 + i)} in detail. It ends.") for i in range(10)], "sample_id long, text string")
    items, merges, rounds = fuse_clusters(reps, texts)
    assert items.count() == 2 and merges.count() == 4 and rounds == 3


def test_patch_and_audit(spark):
    row = spark.createDataFrame([(["a clean line", "junk### line"], ["alpha", "clean", "zeta"])], "answer array<string>, wanted array<string>")
    loss = row.select(rules.audit(F.col("answer"), F.col("wanted")).alias("l")).first()["l"]
    assert loss["missing"] == ["alpha", "zeta"] and loss["drop"] == ["junk### line"] and loss["score"] == 3 and loss["keep"] == ["clean"]
    prompt = row.select(rules.patch(rules.first_prompt(F.lit("S1")), rules.audit(F.col("answer"), F.col("wanted"))).alias("p")).first()["p"]
    assert prompt["version"] == 1 and prompt["must_keep"] == ["alpha", "zeta"] and prompt["must_drop"] == ["junk### line"]


def test_calls_are_cached_and_failures_kept(spark):
    prompts = spark.createDataFrame([(1, "one. two"), (2, "one. two"), (3, ". nothing")], "i int, prompt string")
    _, misses = replay(prompts, spark.createDataFrame([], "key string, reply string"), "draft", {"t": "0.2"})
    cache = call(misses, EchoModel(), {"t": "0.2"})
    assert {r["reply"] for r in cache.collect()} == {"one", None} and cache.count() == 2
    hits, rest = replay(prompts, cache, "draft", {"t": "0.2"})
    assert hits.count() == 3 and rest.count() == 0
    assert replay(prompts, cache, "draft", {"t": "0.4"})[0].count() == 0
    tries = []

    def send(p, o):
        tries.append(p)
        if len(tries) < 2:
            raise OSError
        return "ok"

    assert HttpModel(send, per_second=1000).generate(["x"], {}) == ["ok"] and len(tries) == 2


def test_answer_measures(spark):
    assert evaluate.token_f1("the red fox", "red fox runs") == pytest.approx(2 / 3)
    assert evaluate.token_f1("", "") == 1.0 and evaluate.token_f1("a", "") == 0.0
    rows = spark.createDataFrame([("the red fox", "red fox runs"), ("", ""), ("a", ""), ("x x y", "x y y")], "p string, g string")
    assert [round(r[0], 6) for r in rows.select(metrics.token_f1(F.col("p"), F.col("g"))).collect()] == [0.666667, 1.0, 0.0, 0.666667]
    assert metrics.exact_match(rows, "p", "g").first()["em"] == 25.0
