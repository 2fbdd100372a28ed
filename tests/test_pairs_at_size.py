"""Pairs and neighbours of larger tables: counted where blocks meet, with copies, ties and zero vectors."""

import numpy as np
import pytest

from salvage.plans import neighbors


def vectors(spark, m):
    rows = [(i, [float(x) for x in row]) for i, row in enumerate(np.asarray(m, np.float32))]
    return spark.createDataFrame(rows, "sample_id long, vec array<float>")


def cosines(m):
    x = np.asarray(m, np.float32).astype(float)
    return np.round(neighbors.units(x) @ neighbors.units(x).T, 6)


@pytest.fixture(scope="module")
def crowd():
    rng = np.random.default_rng(11)
    m = rng.standard_normal((90, 5)) + 1.5
    return np.vstack([m, m[:7], m[:3], np.zeros((2, 5))])


@pytest.mark.parametrize("block_rows", [16, 8192])
def test_counts_by_threshold(spark, crowd, block_rows):
    grid = (0.2, 0.5, 0.9, 1.5)
    upper = cosines(crowd)[np.triu_indices(len(crowd), 1)]
    got = {r["min_sim"]: r["n_pairs"] for r in neighbors.count_pairs(vectors(spark, crowd), grid, block_rows).collect()}
    assert got == {t: int((upper >= t).sum()) for t in grid}


@pytest.mark.parametrize("block_rows", [16, 8192])
def test_links_and_classes_of_each_row(spark, crowd, block_rows):
    s = cosines(crowd)
    links = (s >= 0.9).sum(1) - (np.diag(s) >= 0.9)
    first = [int(np.flatnonzero((np.float32(crowd) == np.float32(row)).all(1))[0]) for row in crowd]
    got = sorted(map(tuple, neighbors.linked(vectors(spark, crowd), 0.9, block_rows).select("sample_id", "class_id", "links").collect()))
    assert got == [(i, first[i], int(links[i])) for i in range(len(crowd))]


@pytest.mark.parametrize("block_rows", [16, 8192])
def test_links_by_bands_are_counted_without_a_list(spark, crowd, block_rows):
    """As many as the listed pairs of different vectors, fewer than all; with copies, no more than all links."""
    v = vectors(spark, crowd[:90])
    listed = [0] * 90
    for r in neighbors.sim_pairs(v, 0.9, "lsh", bits=4, bands=2).collect():
        listed[r["a"]] += 1
        listed[r["b"]] += 1
    got = {r["sample_id"]: r["links"] for r in neighbors.linked(v, 0.9, block_rows, bands=(4, 2)).collect()}
    every = {r["sample_id"]: r["links"] for r in neighbors.linked(v, 0.9, block_rows).collect()}
    assert got == dict(enumerate(listed)) and 0 < sum(listed) < sum(every.values())
    own = [{r["sample_id"]: r["links"] for r in neighbors.linked(vectors(spark, crowd), 0.9, block_rows, **b).collect()} for b in ({"bands": (4, 2)}, {})]
    assert all(own[0][i] <= own[1][i] for i in own[1]) and own[0][90] == own[0][0] >= 1 and own[0][100] == 0


@pytest.mark.parametrize("name", ["sim_pairs_bands", "knn_recall_measured"])
def test_band_queries_list_no_pairs(spark, sf, monkeypatch, name):
    from salvage import catalog

    monkeypatch.setattr(neighbors, "sim_pairs", None)
    rows = catalog.queries()[name](spark, sf).collect()
    if name == "sim_pairs_bands":
        assert len(rows) == spark.read.parquet(f"{sf}/documents.parquet").count()
    else:
        pairs = next(r for r in rows if r["method"] == "pairs_bands")
        assert 0.99 <= pairs["recall"] <= 1 and pairs["precision"] == 1 and pairs["n_found"] > 0


def test_blocks_are_neither_shuffled_in_copies_nor_broadcast(spark, crowd):
    v = vectors(spark, crowd)
    for met in (neighbors.block_pairs(v, v, 16), neighbors._own_pairs(v, 16)):
        text = met._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" in text and "Exchange" not in text


@pytest.mark.parametrize("metric", ["cosine", "euclid"])
def test_exact_neighbours_with_ties(spark, crowd, metric):
    x = np.float32(crowd).astype(float)
    s = np.round(neighbors.units(x) @ neighbors.units(x).T if metric == "cosine" else -np.sqrt(((x[:, None] - x[None]) ** 2).sum(2)), 9)
    want = {i: [s[i, j] for j in sorted((j for j in range(len(x)) if j != i), key=lambda j: (-s[i, j], j))[:4]] for i in range(len(x))}
    got: dict = {}
    for r in neighbors.knn(vectors(spark, crowd), 4, metric, "exact", block_rows=16).orderBy("sample_id", "nn_rank").collect():
        got.setdefault(r["sample_id"], []).append(r["sim"])
    assert all(np.allclose(got[i], want[i], atol=1e-7) for i in want) and len(got) == len(want)


@pytest.mark.parametrize("name", ["knn_exact", "knn_euclid", "consensus2", "consensus3"])
def test_neighbours_beyond_one_window(spark, tmp_path, name):
    """More rows than the forest compares whole: the queries named exact, and those counted from them, equal SQL."""
    import duckdb

    from salvage import catalog

    m = np.random.default_rng(3).standard_normal((9000, 48)).astype(np.float32)
    m[8900:] = m[:100]
    rows = [(i, row.tolist(), i % 10) for i, row in enumerate(m)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").coalesce(1).write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.execute(f"create view embeddings as select * from '{tmp_path}/embeddings.parquet/*.parquet'")
    df = catalog.queries()[name](spark, str(tmp_path))
    near = lambda row: tuple(round(x, 5) if isinstance(x, float) else x for x in row)
    got, want = (sorted(map(near, r)) for r in (df.collect(), con.execute(f"select {', '.join(df.columns)} from ({catalog.oracle_sql()[name]})").fetchall()))
    assert got == want


def test_recall_is_measured_in_one_meeting(spark, sf, monkeypatch):
    """Exact neighbours and both counts share one product of the blocks, and equal the forms with a product each."""
    from salvage import catalog
    from salvage.plans.fixtures import text_vectors

    made, real, whole = [], neighbors._own_pairs, neighbors.block_pairs
    monkeypatch.setattr(neighbors, "_own_pairs", lambda *a: made.append(1) or real(*a))
    monkeypatch.setattr(neighbors, "block_pairs", lambda *a: made.append(1) or whole(*a))
    rows = {r["method"]: r for r in catalog.queries()["knn_recall_measured"](spark, sf).collect()}
    assert len(made) == 1
    v = neighbors.collapse(text_vectors(spark, sf))[0]
    m = np.array([r["vec"] for r in v.orderBy("sample_id").collect()])
    upper = cosines(m)[np.triu_indices(len(m), 1)]
    assert rows["pairs_bands"]["n_exact"] == int((upper >= 0.9).sum()) and rows["knn_forest"]["n_exact"] == 2 * len(m)


@pytest.mark.parametrize("block_rows", [700, 8192])
def test_a_meeting_equals_the_forms_it_stands_for(spark, monkeypatch, block_rows):
    """Many groups, so that slices are left out; ties, near copies, a zero vector, poor bounds; against all pairs."""
    monkeypatch.setattr(neighbors, "TILE_ROWS", 64)
    rng = np.random.default_rng(5)
    m = np.repeat(rng.standard_normal((40, 48)), 40, 0) + rng.standard_normal((1600, 48)) * np.repeat(rng.random(40), 40)[:, None]
    m = np.float32(np.vstack([m, 2 * m[:9], -m[:4], np.zeros((1, 48)), m[:30] + 1e-4]))
    v, x = vectors(spark, m), neighbors.units(m.astype(float))
    s = np.round(x @ x.T, 9) + 0.0
    np.fill_diagonal(s, -9)
    poor = spark.createDataFrame([(i, r + 1, j, float(s[i, j])) for i in range(len(m)) for r, j in enumerate(sorted(((i + 1) % len(m), (i + 7) % len(m)), key=lambda j: (-s[i, j], j)))], "sample_id long, nn_rank int, nn_id long, sim double")
    for bits, bands in ((4, 3), (20, 5), (40, 2)):
        met = neighbors.meetings(v, 0.9, block_rows, (bits, bands), least=poor, k=2).cache()
        near: dict = {}
        for r in neighbors.knn(v, 2, method="exact", met=met).orderBy("sample_id", "nn_rank").collect():
            near.setdefault(r["sample_id"], []).append(r["sim"])
        assert len(near) == len(m) and all(np.allclose(near[i], np.sort(s[i])[:-3:-1], atol=2e-9) for i in near)
        link = np.round(s, 6) >= 0.9
        words = neighbors._words(m.astype(float), bits, bands, 42)
        both = link & (words[:, None] == words[None]).any(2)
        for want, kind in ((link, {}), (both, {"bands": (bits, bands)})):
            assert {r["sample_id"]: r["links"] for r in neighbors.linked(v, 0.9, met=met, **kind).collect()} == dict(enumerate(want.sum(1)))
        assert 0 < both.sum() < link.sum()
    a, b, _, _ = neighbors._outlined(*(x.astype(np.float32),) * 2)
    assert (a @ b.T >= x @ x.T - 1e-6).all()
