"""Stand-in learners and tasks that compare training sets. They are proxies: no language model is tuned here.

Tasks on held-out documents: T1 the language, T2 toxicity, T3 a number (the decile of the length), T4 quality, all by
exact match; T5 the continuation: what follows the first sentence of a text, as the training text whose first sentence
is nearest continues, by token F1. Learners: multinomial naive Bayes, nearest centroid, logistic regression and least
squares. All of them need only sums over the training rows, which are gathered in one pass (one a step for the logistic
one) for all training sets at once; only those sums (sets x classes x dimensions) reach the driver.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.functions.keys import uniform
from salvage.functions.materialize import checkpoint
from salvage.functions.together import together
from salvage.functions.vectors import DIMENSIONS, char_vector, encode
from salvage.plans import neighbors

LANGS = ("de", "en", "es", "fr")
CUTS = (200, 400, 700, 1000, 1400, 1900, 2500, 3500, 6000)
TASKS = {"T1": 4, "T2": 2, "T3": 10, "T4": 2}
#: Share of duplicate groups held out; steps and penalty of the logistic learner.
HELD_OUT, STEPS, PENALTY = 0.2, 25, 1e-3


def held_out(text: Column) -> Column:
    """The split is by the text's hash, so copies never straddle it."""
    return uniform(F.md5(text), 7) < HELD_OUT


def targets(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(sample_id, text, T1..T4) of documents; null where a label is not known."""
    lang = F.array_position(F.array(*map(F.lit, LANGS)), F.col("lang")).cast("int") - 1
    decile = sum((F.when(F.length("text") > c, 1).otherwise(0) for c in CUTS), F.lit(0))
    joined = docs.join(labels.groupBy("doc_id").agg(F.max("quality").alias("T4"), F.max("toxic").alias("T2")), "doc_id", "left")
    return joined.select(F.col("doc_id").alias("sample_id"), "text", lang.cast("int").alias("T1"), F.col("T2").cast("int").alias("T2"), decile.cast("int").alias("T3"), F.col("T4").cast("int").alias("T4"))


def _features(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    signed = np.array([char_vector(t) for t in texts]).reshape(len(texts), DIMENSIONS)
    return signed, np.abs(signed) * 100  # weights of the buckets stand in for counts


def _sums(train: DataFrame, methods: list[str]) -> dict:
    """For each method and task: class counts, sums of both kinds of features, and the Gram matrix of each method."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[str, str, int], np.ndarray] = {}

        def add(key: tuple[str, str, int], value: np.ndarray) -> None:
            total[key] = total[key] + value if key in total else value

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                signed, counts = _features(part.column("text").to_pylist())
                y = {t: np.array([-1 if v is None else v for v in part.column(t).to_pylist()]) for t in TASKS}
                belongs = part.column("methods").to_pylist()
                for m in methods:
                    own = np.array([m in b for b in belongs])
                    if not own.any():
                        continue
                    x = np.hstack([signed[own], np.ones((own.sum(), 1))])
                    add((m, "gram", 0), (x.T @ x).ravel())
                    for t, k in TASKS.items():
                        for c in range(k):
                            row = own & (y[t] == c)
                            if row.any():
                                add((m, t, c), np.concatenate([[row.sum()], signed[row].sum(0), counts[row].sum(0)]))
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in total]), pa.array([k[1] for k in total]), pa.array([k[2] for k in total], pa.int32()), pa.array([v.tolist() for v in total.values()], pa.list_(pa.float64()))], ["method", "task", "class", "v"])

    def add_up(rows: pa.Table) -> pa.Table:
        v = np.sum([np.asarray(x, float) for x in rows.column("v").to_pylist()], 0)
        return pa.table({"method": rows.column("method").slice(0, 1), "task": rows.column("task").slice(0, 1), "class": rows.column("class").slice(0, 1), "v": pa.array([v.tolist()], pa.list_(pa.float64()))})

    kind = "method string, task string, class int, v array<double>"
    summed = train.mapInArrow(run, kind).groupBy("method", "task", "class").applyInArrow(add_up, kind)
    return {(r["method"], r["task"], r["class"]): np.array(r["v"]) for r in summed.collect()}


def _logistic(train: DataFrame, methods: list[str]) -> dict[tuple[str, str], np.ndarray]:
    """Weights of multinomial logistic regression by accelerated gradient steps over all rows; a step is one pass that
    returns the gradients of all methods and tasks."""
    d = DIMENSIONS + 1

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                signed = _features(part.column("text").to_pylist())[0].astype(np.float32)
                vec = pa.ListArray.from_arrays(pa.array(np.arange(len(signed) + 1) * DIMENSIONS, pa.int32()), pa.array(signed.ravel()))
                places = pa.array([[places_of[m] for m in own if m in places_of] for own in part.column("methods").to_pylist()], pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays([places, vec, *(part.column(t) for t in TASKS)], ["places", "vec", *TASKS])

    places_of = {m: i for i, m in enumerate(methods)}
    schema = "places array<int>, vec array<float>, " + ", ".join(f"{t} int" for t in TASKS)
    rows = checkpoint(train.select("methods", "text", *TASKS).mapInArrow(encode, schema))
    weights = {(m, t): np.zeros((k, d)) for m in methods for t, k in TASKS.items()}
    ahead = {key: w.copy() for key, w in weights.items()}
    for step in range(STEPS):
        shared = rows.sparkSession.sparkContext.broadcast(ahead)

        def gradient(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[tuple[str, str], list] = {}
            joint = {m: np.vstack([shared.value[m, t] for t in TASKS]) for m in methods}
            for batch in batches:
                values = batch.column("vec").flatten().to_numpy(zero_copy_only=False)
                x = np.hstack([values.reshape(batch.num_rows, -1).astype(float), np.ones((batch.num_rows, 1))]) if len(values) else np.zeros((0, d))
                y = {t: batch.column(t).fill_null(-1).to_numpy(zero_copy_only=False) for t in TASKS}
                places = batch.column("places")
                member = np.zeros((batch.num_rows, len(methods)), bool)
                member[np.repeat(np.arange(batch.num_rows), places.value_lengths().to_numpy(zero_copy_only=False)), places.flatten().to_numpy(zero_copy_only=False)] = True
                for i, m in enumerate(methods):
                    own = np.flatnonzero(member[:, i])
                    if not len(own):
                        continue
                    mine = x if len(own) == len(x) else x[own]
                    p, at = mine @ joint[m].T, 0  # the classes of all tasks side by side
                    for t, k in TASKS.items():
                        z, label = p[:, at : at + k], y[t][own]
                        z -= z.max(1, keepdims=True)
                        np.exp(z, out=z)
                        z /= z.sum(1, keepdims=True)
                        known = np.flatnonzero(label >= 0)
                        z[known, label[known]] -= 1
                        z[label < 0] = 0
                        if len(known):
                            total.setdefault((m, t), [0, np.zeros((k, d))])[0] += len(known)
                        at += k
                    moved, at = p.T @ mine, 0
                    for t, k in TASKS.items():
                        if (m, t) in total:
                            total[m, t][1] += moved[at : at + k]
                        at += k
            yield pa.RecordBatch.from_arrays([pa.array([m for m, _ in total]), pa.array([t for _, t in total]), pa.array([v[0] for v in total.values()], pa.int64()), pa.array([v[1].ravel().tolist() for v in total.values()], pa.list_(pa.float64()))], ["method", "task", "n", "g"])

        sums: dict[tuple[str, str], list] = {}
        for r in rows.mapInArrow(gradient, "method string, task string, n bigint, g array<double>").toLocalIterator():  # a row a method, task and partition
            row = sums.setdefault((r["method"], r["task"]), [0, 0.0])
            row[0], row[1] = row[0] + r["n"], row[1] + np.array(r["g"])
        for key, (n, g) in sums.items():
            moved = ahead[key] - 2.0 * (g.reshape(ahead[key].shape) / n + PENALTY * ahead[key])
            ahead[key] = moved + step / (step + 3) * (moved - weights[key])
            weights[key] = moved
    return weights


def learn(train: DataFrame, methods: list[str], learner: str) -> dict[tuple[str, str], np.ndarray]:
    """(weights of classes x dimensions + bias) by method and task. ``train`` is (methods array, text, T1..T4). A method
    without rows has weights of nought, so that the first class wins."""
    if learner == "logistic":
        return _logistic(train, methods)
    sums, d = _sums(train, methods), DIMENSIONS
    out = {}
    for m in methods:
        for t, k in TASKS.items():
            stats = [sums.get((m, t, c), np.zeros(1 + 2 * d)) for c in range(k)]
            n = np.array([s[0] for s in stats])
            if learner == "bayes":
                like = np.array([np.log(s[1 + d :] + 1) - np.log(s[1 + d :].sum() + d) for s in stats])
                out[m, t] = np.hstack([like, np.log((n + 0.5) / (n.sum() + 0.5 * k))[:, None]])
            elif learner == "centroid":
                mean = np.array([s[1 : 1 + d] / max(s[0], 1) for s in stats])
                out[m, t] = np.hstack([mean, np.where(n > 0, -0.5 * (mean**2).sum(1), -1e9)[:, None]])
            else:
                gram = sums.get((m, "gram", 0), np.zeros((d + 1) ** 2)).reshape(d + 1, d + 1) + np.eye(d + 1)
                out[m, t] = np.array([np.linalg.solve(gram, np.append(s[1 : 1 + d], s[0])) for s in stats])
    return out


def exact_match(test: DataFrame, weights: dict, learner: str) -> DataFrame:
    """(method, task, n, score): share of held-out rows whose class is predicted, in per cent."""
    shared = test.sparkSession.sparkContext.broadcast(weights)  # methods x classes x dimensions numbers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally: dict[tuple[str, str], list[int]] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                signed, counts = _features(part.column("text").to_pylist())
                x = np.hstack([counts if learner == "bayes" else signed, np.ones((len(signed), 1))])
                for (m, t), w in shared.value.items():
                    y = np.array([-1 if v is None else v for v in part.column(t).to_pylist()])
                    hit = (x @ w.T).argmax(1)[y >= 0] == y[y >= 0]
                    row = tally.setdefault((m, t), [0, 0])
                    row[0] += len(hit)
                    row[1] += int(hit.sum())
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in tally]), pa.array([k[1] for k in tally]), pa.array([v[0] for v in tally.values()], pa.int64()), pa.array([v[1] for v in tally.values()], pa.int64())], ["method", "task", "n", "hit"])

    counted = test.mapInArrow(run, "method string, task string, n bigint, hit bigint").groupBy("method", "task").agg(F.sum("n").alias("n"), F.sum("hit").alias("hit"))
    return counted.select("method", "task", "n", F.round(100 * F.col("hit") / F.col("n"), 1).alias("score"))


def parted(text: Column) -> tuple[Column, Column]:
    """A text's first sentence (all of it, if it has one only) and what follows."""
    head = F.regexp_extract(text, r"(?s)^([^.!?]*[.!?])", 1)
    head = F.when(head == "", text).otherwise(head)
    return head, F.substring(text, F.length(head) + 1, F.length(text))


def nearest_texts(train: DataFrame, test: DataFrame, methods: list[str]) -> DataFrame:
    """(method, task, n, score): token F1 of a held-out text's continuation against that of the nearest training text of
    each method, by the vectors of their first sentences; ties to the smaller row number. All held-out rows are scored,
    in pairs of blocks; a method without training rows scores 0. Equal first sentences are compared once (training rows: of
    equal methods, where the smallest row number wins), and two continuations once for all methods that bring them together."""

    def side(df: DataFrame, *more: str) -> DataFrame:
        numbered = df.select(*more, F.coalesce("text", F.lit("")).alias("text")).withColumn("sample_id", F.monotonically_increasing_id())
        head, rest = parted(F.col("text"))
        rows = checkpoint(numbered.select("sample_id", *more, head.alias("head"), rest.alias("rest")))
        alike = checkpoint(rows.groupBy("head", *more).agg(F.min("sample_id").alias("sample_id")))
        return rows, alike, alike.select("sample_id", *more).join(encode(alike, "sample_id", "head"), "sample_id")

    (gold, heads, asked), (known, _, pool) = together(lambda: side(test), lambda: side(train.withColumn("methods", F.sort_array("methods")), "methods"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                a, b = batch.column("a_rows")[i].values, batch.column("b_rows")[i].values
                va, vb = neighbors.matrix(a.field("vec")), neighbors.matrix(b.field("vec")).T
                ids, names, belongs = a.field("sample_id").to_numpy(zero_copy_only=False), b.field("sample_id").to_numpy(zero_copy_only=False), b.field("methods").to_pylist()
                members = {m: own[np.argsort(names[own])] for m in methods if len(own := np.flatnonzero([m in x for x in belongs]))}
                for at_row in range(0, len(ids), neighbors.SLICE_ROWS):  # a slice's products, never a block's, are held
                    part = slice(at_row, at_row + neighbors.SLICE_ROWS)
                    s, asked_ids = np.round(va[part] @ vb, 9), ids[part]
                    for m, own in members.items():
                        at = own[s[:, own].argmax(1)]
                        yield pa.RecordBatch.from_arrays([pa.array([m] * len(asked_ids)), pa.array(asked_ids), pa.array(s[np.arange(len(asked_ids)), at]), pa.array(names[at])], ["method", "sample_id", "sim", "nn_id"])

    near = neighbors.block_pairs(asked, pool).mapInArrow(run, "method string, sample_id bigint, sim double, nn_id bigint")
    best = near.groupBy("method", "sample_id").agg(F.max_by("nn_id", F.struct("sim", -F.col("nn_id"))).alias("nn_id"))
    met = best.groupBy("sample_id", "nn_id").agg(F.collect_list("method").alias("names"))  # all methods at most
    golds = gold.join(heads.select("head", F.col("sample_id").alias("head_id")), "head").select(F.col("head_id").alias("sample_id"), F.col("rest").alias("gold"))
    both = met.join(golds, "sample_id").join(known.select(F.col("sample_id").alias("nn_id"), F.col("rest").alias("said")), "nn_id")

    def f1(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scores = [token_f1(p, g) for p, g in zip(batch.column("said").to_pylist(), batch.column("gold").to_pylist(), strict=True)]
            names = batch.column("names")
            each = np.repeat(np.array(scores, float), names.value_lengths().to_numpy(zero_copy_only=False))
            yield pa.RecordBatch.from_arrays([names.flatten(), pa.array(each)], ["method", "f1"])

    total = gold.agg(F.count("*").alias("n"))
    scored = both.select("names", "said", "gold").mapInArrow(f1, "method string, f1 double").groupBy("method").agg(F.sum("f1").alias("f1"))
    names = gold.sparkSession.createDataFrame([(m,) for m in methods], "method string")
    out = names.join(scored, "method", "left").crossJoin(total).where("n > 0")  # one row each
    return out.select("method", F.lit("T5").alias("task"), "n", F.round(100 * F.coalesce("f1", F.lit(0.0)) / F.col("n"), 1).alias("score"))


@lru_cache(256)
def _bag(text: str) -> Counter:
    return Counter(re.findall(r"\w+", text.lower()))


def token_f1(prediction: str, gold: str) -> float:
    """Overlap of the word bags after lower-casing and removal of punctuation; articles stay. Both empty: 1."""
    p, g = _bag(prediction), _bag(gold)
    if not p or not g:
        return float(p == g)
    common = (p & g).total()
    return 2 * common / (p.total() + g.total()) if common else 0.0


def compare(train: DataFrame, test: DataFrame, methods: list[str], learner: str, tasks: tuple[str, ...] = ("T1", "T2", "T3", "T4", "T5")) -> DataFrame:
    """(method, task, n, score) for all methods; ``train`` is (methods, text, T1..T4), ``test`` (sample_id, text, ...)."""
    if "T5" in tasks:  # the continuations need no learner, so they do not wait for its passes
        weights, continued = together(lambda: learn(train, methods, learner), lambda: checkpoint(nearest_texts(train, test, methods)))
        scored = exact_match(test, weights, learner).union(continued)
    else:
        scored = exact_match(test, learn(train, methods, learner), learner)
    return scored.where(F.col("task").isin(*tasks))


def compare_learners(train: DataFrame, test: DataFrame, methods: list[str], learners: tuple[str, ...], tasks: tuple[str, ...]) -> DataFrame:
    """``compare`` by several learners, with a column ``learner``. No learner takes part in T5, which is worked out once."""
    shared = checkpoint(nearest_texts(train, test, methods)) if "T5" in tasks else None
    out = None
    for learner in learners:
        scored = compare(train, test, methods, learner, tuple(t for t in tasks if t != "T5"))
        scored = (scored if shared is None else scored.union(shared)).withColumn("learner", F.lit(learner))
        out = scored if out is None else out.union(scored)
    return out
