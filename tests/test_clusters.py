"""Clusters, silhouettes and representatives against sequential and hand-worked forms."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from salvage.functions import vectors
from salvage.plans import clusters, neighbors, pairing, representatives


def frame(spark, m):
    return spark.createDataFrame([(i, [float(x) for x in row]) for i, row in enumerate(m)], "sample_id long, vec array<float>")


def sequential(order, sims, t):
    cents, of = [], {}
    for i in order:
        hit = next((c for c in cents if sims[i, c] >= t), None)
        if hit is None:
            cents.append(i)
        of[i] = i if hit is None else hit
    return of


@pytest.mark.parametrize("seed,n,t", [(0, 60, 0.3), (1, 120, 0.5), (2, 120, 0.1), (3, 40, 0.9), (4, 90, -0.2)])
def test_rounds_equal_the_sequential_definition(spark, seed, n, t):
    m = np.random.default_rng(seed).standard_normal((n, 6))
    v = frame(spark, m)
    pairs = neighbors.sim_pairs(v, t, block_rows=32)
    got = {r["sample_id"]: r["cluster_id"] for r in clusters.one_hop(v, pairs).collect()}
    order = [r[0] for r in v.orderBy(__import__("salvage.functions.keys", fromlist=["x"]).order_key("sample_id"), "sample_id").select("sample_id").collect()]
    x = m.astype(np.float32).astype(float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    assert got == sequential(order, np.round(x @ x.T, 6), t)


def test_one_hop_without_rows_or_links(spark):
    v = frame(spark, [[1, 0], [0, 1], [0, 0]])
    none = spark.createDataFrame([], "a long, b long, sim double")
    assert {(r["sample_id"], r["cluster_id"]) for r in clusters.one_hop(v, none).collect()} == {(i, i) for i in range(3)}
    assert clusters.one_hop(v.limit(0), none).count() == 0


def test_components_follow_chains(spark):
    nodes = spark.range(12).select(F.col("id").alias("sample_id"))
    pairs = spark.createDataFrame([(i, i + 1) for i in range(8)] + [(9, 10)], "a long, b long")
    assert {r[0]: r[1] for r in clusters.components(nodes, pairs).collect()} == {**{i: 0 for i in range(9)}, 9: 9, 10: 9, 11: 11}


def test_silhouette_by_hand_and_by_sums():
    x, labels = np.array([[0.0], [1], [10], [11]]), np.array([0, 0, 1, 1])
    assert clusters.silhouette_exact(x, labels, "euclid").mean() == pytest.approx(0.8997, abs=1e-4)
    rng = np.random.default_rng(5)
    x, labels = rng.standard_normal((50, 4)), rng.integers(0, 4, 50)
    x[3] = 0
    for metric in ("cosine", "sqeuclid"):
        assert np.allclose(clusters.silhouette_moment(x, labels, metric), clusters.silhouette_exact(x, labels, metric), atol=1e-9)
    same = np.ones((6, 3))
    assert np.allclose(clusters.silhouette_moment(same, np.array([0, 0, 0, 1, 1, 1])), 0)


def test_best_number_of_cells(spark):
    rng = np.random.default_rng(6)
    m = np.vstack([c + 0.05 * rng.standard_normal((20, 3)) for c in np.eye(3)])
    v = frame(spark, m)
    member = v.select("sample_id", F.lit(7).cast("long").alias("cluster_id"))
    rows = clusters.subcluster(member, v).collect()
    assert {r["k"] for r in rows} == {3} and len({(r["sample_id"] // 20, r["sub_id"]) for r in rows}) == 3
    two = clusters.subcluster(member.limit(2), v).collect()
    assert {r["sub_id"] for r in two} == {0}


def test_representatives_by_hand(spark):
    v = frame(spark, [[1, 0], [0, 1], [0.6, 0.8]])
    cells = v.select("sample_id", F.lit(1).cast("long").alias("cluster_id"), F.lit(0).alias("sub_id"))
    rel = representatives.relevance(cells, v)
    assert representatives.first(rel).first()["sample_id"] == 2
    pick = lambda a: representatives.second(representatives.scores(rel, a)).first()
    assert pick(0.2)["sample_id"] == 0 and pick(0.2)["mmr"] == pytest.approx(-0.347, abs=1e-3) and pick(1.0)["sample_id"] == 1
    assert [r["sample_id"] for r in representatives.greedy(rel, 0.2, 3).orderBy("rep_rank").collect()] == [2, 0, 1]
    with pytest.raises(ValueError):
        representatives.scores(rel, 1.5)
    chosen = representatives.choose(cells.where("sample_id < 2"), v)
    assert {r["rule"] for r in chosen.collect()} == {"all"} and chosen.count() == 2


def test_hyperplane_bands_find_most_pairs(spark):
    rng = np.random.default_rng(8)
    base = rng.standard_normal((40, 16))
    m = np.vstack([base + 0.1 * rng.standard_normal((40, 16)) for _ in range(5)] + [base[:3]])
    v = frame(spark, m)
    exact, found = neighbors.sim_pairs(v, 0.9), neighbors.sim_pairs(v, 0.9, "lsh")
    score = neighbors.recall(found, exact, ["a", "b"]).first()
    assert score["recall"] > 0.97 and score["precision"] == 1.0


def test_no_size_is_refused_and_forms_agree(spark):
    """One window is compared whole; small windows find most; every row gets its k neighbours."""
    m = np.random.default_rng(11).standard_normal((400, 12))
    m[200:240] = m[0]
    v = frame(spark, m)
    exact, whole, small = (neighbors.knn(v, 3, **o) for o in ({"method": "exact", "block_rows": 64}, {}, {"window": 64, "trees": 12}))
    keys = lambda df: sorted((r["sample_id"], r["nn_rank"], r["nn_id"]) for r in df.collect())
    assert keys(exact) == keys(whole) and small.count() == 1200
    assert neighbors.recall(small, exact, ["sample_id", "nn_id"]).first()["recall"] > 0.8


def test_hot_bands_are_split_without_loss(spark):
    rng = np.random.default_rng(12)
    m = np.vstack([c + 0.05 * rng.standard_normal((60, 16)) for c in rng.standard_normal((4, 16))])
    v = frame(spark, m)
    exact = neighbors.sim_pairs(v, 0.9)
    keys = neighbors.band_keys(v.select("sample_id", "vec"), 4, 10, bucket_rows=20)
    assert keys.groupBy("key").count().agg(F.max("count")).first()[0] < 240
    split = neighbors.sim_pairs(v, 0.9, "lsh", bits=4, bands=10, bucket_rows=20)
    assert neighbors.recall(split, exact, ["a", "b"]).first()["recall"] > 0.97


@pytest.mark.parametrize("method", ["exact", "lsh"])
def test_prefixes_equal_the_sequential_definition(spark, method):
    rng = np.random.default_rng(13)
    base = rng.standard_normal((60, 10))
    v = frame(spark, np.vstack([base, base + 0.1 * rng.standard_normal((60, 10)), np.repeat(base[:2], 20, 0)]))
    strip = lambda df: sorted((r["sample_id"], r["cluster_id"], r["is_centroid"]) for r in df.collect())
    want = strip(clusters.one_hop(v, neighbors.sim_pairs(v, 0.9)))
    assert strip(clusters.one_hop_of_copies(v, 0.9, method, first_rows=15)) == want


@pytest.mark.parametrize("metric", ["cosine", "sqeuclid"])
def test_large_clusters_have_the_cells_of_small_ones(spark, metric):
    rng = np.random.default_rng(14)
    m = np.vstack([5 * c + 0.4 * rng.standard_normal((40, 4)) for c in np.eye(4)[:3]] + [rng.standard_normal((50, 4)), np.zeros((2, 4))])
    v = frame(spark, m)
    member = v.select("sample_id", (F.col("sample_id") >= 120).cast("long").alias("cluster_id"))
    rows = [sorted((r["sample_id"], r["sub_id"], r["k"], round(r["silhouette"], 6)) for r in clusters.subcluster(member, v, k_max=5, metric=metric, max_group=g).collect()) for g in (1000, 60, 10)]
    assert rows[0] == rows[1] == rows[2]


def test_knn_of_texts_and_zero_vectors(spark):
    rows = spark.createDataFrame([(1, "the same words here"), (2, "the same words here"), (3, "ab"), (4, None)], "doc_id long, text string")
    v = vectors.encode(rows, "doc_id", "text")
    near = {(r["sample_id"], r["nn_rank"]): r for r in neighbors.knn(v, 1).collect()}
    assert near[1, 1]["nn_id"] == 2 and near[1, 1]["sim"] == 1.0 and near[3, 1]["sim"] == 0.0


def test_merge_schedules(spark):
    reps = spark.createDataFrame([(1, i) for i in range(5)] + [(2, 9)], "cluster_id long, sample_id long")
    fold, tree = pairing.intra_plan(reps, "fold").collect(), pairing.intra_plan(reps).collect()
    assert len(fold) == len(tree) == 4 and max(r["round"] for r in fold) == 4 and max(r["round"] for r in tree) == 3


def test_ring_never_pairs_inside_a_cluster(spark):
    reps = spark.createDataFrame([(i, i % 3) for i in range(21)], "sample_id long, cluster_id long")
    rows = pairing.inter_pairs(reps).collect()
    assert all(r["cluster_a"] != r["cluster_b"] for r in rows) and len({x for r in rows for x in (r["a"], r["b"])}) == 2 * len(rows)


def test_copies_are_linked_once_and_clustered_alike(spark):
    rng = np.random.default_rng(9)
    base = rng.standard_normal((12, 8))
    v = frame(spark, np.vstack([base, base + 0.05 * rng.standard_normal((12, 8)), np.repeat(base[:2], 30, 0)]))
    pairs = neighbors.sim_pairs(v, 0.9, "lsh")
    assert pairs.count() < 150  # stars, not all pairs of the copies
    full = clusters.one_hop(v, neighbors.sim_pairs(v, 0.9))
    strip = lambda df: sorted((r["sample_id"], r["cluster_id"], r["is_centroid"]) for r in df.collect())
    assert strip(clusters.one_hop_of_copies(v, 0.9)) == strip(full)
    near, exact = neighbors.knn(v, 3, method="lsh"), neighbors.knn(v, 3)
    copies = lambda df: sorted((r["sample_id"], r["nn_rank"], r["nn_id"]) for r in df.collect() if r["sample_id"] >= 24)
    assert copies(near) == copies(exact)
