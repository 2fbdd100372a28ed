"""Hand-worked numbers, invariants and planted truth of the rating correction."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from salvage.plans import correction as c


def test_two_classes_by_hand(spark):
    t, p = np.array([[0.8, 0.2], [0.3, 0.7]]), np.array([0.6, 0.4])
    assert np.allclose(p @ t, [0.60, 0.40])
    second = np.einsum("i,ij,ik->jk", p, t, t)
    assert np.allclose(second, [[0.42, 0.18], [0.18, 0.22]])
    rows = spark.createDataFrame([(1, 0, None, None), (2, 1, None, None), (3, 0, 0, 0), (4, None, 0, 0)], "sample_id long, y1 int, y2 int, y3 int")
    own = {r["sample_id"]: r for r in c.correct(rows, t, p, "own").collect()}
    assert own[1]["posterior"][0] == pytest.approx(0.8) and own[2]["posterior"][1] == pytest.approx(0.7)
    near = {r["sample_id"]: r for r in c.correct(rows, t, p).collect()}
    assert near[3]["posterior"][0] == pytest.approx(0.3072 / 0.3180, abs=1e-6) and near[1]["posterior"][0] == pytest.approx(0.8)
    assert near[4]["corrected"] is None and near[4]["posterior"] is None


def test_identity_changes_nothing(spark):
    rows = spark.createDataFrame([(i, i % 3, (i + 1) % 3, i % 3) for i in range(9)], "sample_id long, y1 int, y2 int, y3 int")
    fixed = c.correct(rows, np.eye(3) * 0.999999 + 0.0000003, np.ones(3) / 3, "own").where("corrected <> y1")
    assert fixed.count() == 0


def test_cyclic_shift(spark):
    m = [(1, 2, 3), (4, 5, 6), (7, 8, 9)]
    t = spark.createDataFrame([(i, j, float(m[i][j])) for i in range(3) for j in range(3)], "i int, j int, prob double")
    rows = {(r["i"], r["j"]): r["prob"] for r in c.shift(t, 1, 3).collect()}
    assert [[rows[i, j] for j in range(3)] for i in range(3)] == [[2, 3, 1], [5, 6, 4], [8, 9, 7]]
    assert sorted(map(tuple, c.shift(t, 3, 3).collect())) == sorted(map(tuple, t.collect()))


def test_gradient_is_right_on_an_asymmetric_target():
    rng = np.random.default_rng(0)
    q = rng.random((4, 4, 4))
    q /= q.sum()
    a, b = rng.standard_normal((4, 4)), rng.standard_normal(4)
    for orders in (2, 3):
        _, ga, gb = c.residual_and_gradient(a, b, q, orders)
        for x, g in ((a, ga), (b, gb)):
            for i in np.ndindex(x.shape):
                keep, e = x[i], 1e-6
                x[i] = keep + e
                up = c.residual_and_gradient(a, b, q, orders)[0]
                x[i] = keep - e
                down = c.residual_and_gradient(a, b, q, orders)[0]
                x[i] = keep
                assert abs((up - down) / (2 * e) - g[i]) < 1e-8


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_planted_matrix_is_found(seed):
    rng = np.random.default_rng(seed)
    k, n = 6, 10_000
    t, p = c.planted_matrix(k), rng.dirichlet(np.ones(k) * 5)
    y = rng.choice(k, n, p=p)
    seen = np.array([[rng.choice(k, p=t[i]) for _ in range(3)] for i in y])
    counts = np.zeros((k, k, k))
    np.add.at(counts, tuple(seen.T), 1)
    found = c.solve(counts)
    assert np.abs(found.t - t).max() < 0.08 and np.abs(found.p - p).max() < 0.05 and not found.warnings
    weight = found.p[None] * np.prod([found.t[:, s].T for s in seen.T], axis=0)
    assert (weight.argmax(1) == y).mean() > (seen[:, 0] == y).mean() + 0.05


def test_consensus_is_dense_and_marginal(spark):
    rows = spark.createDataFrame([(i, i % 3, i % 2, 0) for i in range(12)], "sample_id long, y1 int, y2 int, y3 int")
    three = c.consensus(rows, 4, 3).collect()
    assert len(three) == 64 and sum(r["n"] for r in three) == 12 and sum(r["prob"] for r in three) == pytest.approx(1)
    two = {(r["y1"], r["y2"]): r["n"] for r in c.consensus(rows, 4, 2).collect()}
    for (a, b), n in two.items():
        assert n == sum(r["n"] for r in three if (r["y1"], r["y2"]) == (a, b))


def test_no_row_is_dropped_by_the_split(spark):
    rows = spark.createDataFrame([(1, 0), (2, 2), (3, 3), (4, None)], "sample_id long, corrected int")
    assert {r["sample_id"]: r["tier"] for r in c.partition_by_score(rows).collect()} == {1: "low", 2: "low", 3: "high", 4: "unassigned"}


def test_kappa(spark):
    same = spark.createDataFrame([(0, 0), (1, 1), (1, 1)], "a int, b int")
    assert c.rater_agreement(same, "a", "b").first()["kappa"] == 1.0
    half = spark.createDataFrame([(0, 0), (0, 1), (1, 0), (1, 1)], "a int, b int")
    assert c.rater_agreement(half, "a", "b").first()["kappa"] == 0.0


def test_simulated_ratings_follow_the_matrix(spark):
    t = c.planted_matrix(3, 0.7)
    rows = spark.range(6000).select(F.col("id").alias("sample_id"), (F.col("id") % 3).cast("int").alias("y"))
    counted = {(r["i"], r["j"]): r["prob"] for r in c.transition_by_counting(c.simulate_rating(rows, t), 3).collect()}
    assert max(abs(counted[i, j] - t[i, j]) for i in range(3) for j in range(3)) < 0.03


def test_likelihood_finds_planted_classes():
    rng = np.random.default_rng(3)
    t, p = c.planted_matrix(6, 0.75), np.array([0.05, 0.07, 0.04, 0.05, 0.75, 0.04])
    counts = rng.multinomial(20_000, np.einsum("i,ia,ib,ic->abc", p, t, t, t).ravel()).reshape(6, 6, 6)
    found = c.solve_likelihood(counts, steps=200)
    assert np.abs(found.t - t).max() < 0.1 and np.abs(found.p - p).max() < 0.02
