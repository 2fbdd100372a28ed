"""One-hop clusters, sub-clusters and their silhouettes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.functions.keys import order_key
from salvage.functions.materialize import checkpoint
from salvage.functions.vectors import dot, unit
from salvage.plans import neighbors
from salvage.plans.pairing import global_position


def one_hop(nodes: DataFrame, pairs: DataFrame, order: Column | None = None, overlap: bool = False) -> DataFrame:
    """(sample_id, cluster_id, sim_to_centroid, is_centroid): clusters of one hop in a random order of the rows.

    Going through the rows in order, a row that no earlier centroid covers becomes a centroid and takes all uncovered
    rows similar to it. The same result comes from rounds over the links: each undecided row before all its undecided
    neighbours becomes a centroid and its neighbours are decided; the number of rounds is logarithmic. With ``overlap``
    a row belongs to every centroid that is similar to it. ``pairs`` is (a, b, sim).
    """
    order = order_key("sample_id") if order is None else order
    ranked = nodes.select("sample_id", F.struct(order.alias("o"), F.col("sample_id").alias("i")).alias("ord"))
    both = pairs.select(F.col("a").alias("u"), F.col("b").alias("v"), "sim").union(pairs.select(F.col("b").alias("u"), F.col("a").alias("v"), "sim"))
    ords = lambda c: ranked.select(F.col("sample_id").alias(c), F.col("ord").alias(f"{c}_ord"))
    links = checkpoint(both.join(ords("u"), "u").join(ords("v"), "v"))
    open_links, centroids = links, checkpoint(ranked.join(links.select(F.col("u").alias("sample_id")).distinct(), "sample_id", "left_anti").select("sample_id"))  # rows without links
    while not open_links.isEmpty():
        least = open_links.groupBy("u", "u_ord").agg(F.min("v_ord").alias("m"))
        new = checkpoint(least.where("u_ord < m").select(F.col("u").alias("c")))
        covered = open_links.join(new, F.col("u") == F.col("c"), "left_semi").select(F.col("v").alias("d")).distinct()
        decided = new.select(F.col("c").alias("d")).union(covered)
        rest = open_links.join(decided, F.col("u") == F.col("d"), "left_anti")
        after = checkpoint(rest.join(decided, F.col("v") == F.col("d"), "left_anti"))
        alone = rest.select("u").distinct().join(after.select("u").distinct(), "u", "left_anti").select(F.col("u").alias("sample_id"))  # its neighbours were all covered by others
        centroids = checkpoint(centroids.union(new.select(F.col("c").alias("sample_id"))).union(alone))
        open_links = after
    own = centroids.select("sample_id", F.col("sample_id").alias("cluster_id"), F.lit(1.0).alias("sim_to_centroid"), F.lit(True).alias("is_centroid"))
    near = links.join(centroids.withColumnRenamed("sample_id", "v"), "v", "left_semi").join(centroids.withColumnRenamed("sample_id", "u"), "u", "left_anti")
    if overlap:
        members = near.select(F.col("u").alias("sample_id"), F.col("v").alias("cluster_id"), F.col("sim").alias("sim_to_centroid"), F.lit(False).alias("is_centroid"))
    else:
        members = near.groupBy("u").agg(F.min_by(F.struct("v", "sim"), "v_ord").alias("m")).select(F.col("u").alias("sample_id"), F.col("m.v").alias("cluster_id"), F.col("m.sim").alias("sim_to_centroid"), F.lit(False).alias("is_centroid"))
    return own.union(members)


#: Rows of the first prefix of the random order, about; each later prefix is twice as long. Different vectors up to which
#: blocks of rows and centres are compared whole: below that, matrix products cost less than the candidates of bands.
FIRST_ROWS, WHOLE_ROWS = 4096, 1 << 17
_ORDERS = 1 << 60


def one_hop_of_copies(vectors: DataFrame, min_sim: float = 0.9, method: str = "lsh", first_rows: int = FIRST_ROWS, whole_rows: int = 0, order: str | None = None) -> DataFrame:
    """One-hop clusters of rows (sample_id, vec) without the pairs of all rows: prefixes of the random order in turn.

    Rows of a prefix that no earlier centroid covers are clustered among themselves; the new centroids then take what is
    similar to them among all later rows, which leave. So a large group of similar rows is compared with its centroid
    alone, and the number of rounds is logarithmic. The result is that of going through the rows one by one. Equal
    vectors are covered by the same centroids, so a class of them is clustered as its first row in the order, and its
    other rows follow: to that row if it is a centroid, else to the row's centroid. ``exact`` compares all rows with all
    centroids; ``lsh``, above ``whole_rows`` different vectors, only rows that share a band key, and finds RECALL of the
    links at ``min_sim``. With ``order``, a column of ``vectors``, its order takes the place of the random one, ties to
    smaller ids.
    """
    if order is None:
        orders = _ORDERS
        heads, members = neighbors.collapse(vectors, order_key("sample_id"))
        placed = heads.withColumn("o", order_key("sample_id"))
    else:
        rows = global_position(vectors.select("sample_id", "vec", order), F.col(order), F.col("sample_id")).select("sample_id", "vec", F.col("pos").alias("o"))
        orders = rows.count()
        heads, members = neighbors.collapse(rows, F.col("o"))
        placed = heads.join(rows.select("sample_id", "o"), "sample_id")
    n = heads.count()
    ranked = placed.select("sample_id", "vec", F.struct("o", F.col("sample_id").alias("i")).alias("ord"))
    method = "exact" if n <= whole_rows else method
    keys = neighbors.band_keys(heads, *neighbors.plan_bands(n, min_sim)) if method == "lsh" else None
    rest, begin, share = checkpoint(ranked), 0, min(1.0, first_rows / max(n, 1))
    parts = []

    def similar(rows: DataFrame, centres: DataFrame, once: bool = False) -> DataFrame:
        """(a, b, sim): rows and the centres they are similar to; with ``once`` only a < b."""
        small = centres.select("sample_id", "vec")
        if method == "exact":
            if once:
                return neighbors.sim_pairs(small, min_sim, "exact")
            return neighbors.similar_in_blocks(rows.select("sample_id", "vec"), small, min_sim)
        own = keys.join(rows.select("sample_id"), "sample_id", "left_semi").withColumnRenamed("sample_id", "a")
        other = keys.join(small.select("sample_id"), "sample_id", "left_semi").withColumnRenamed("sample_id", "b")
        met = own.join(other, "key").where("a < b" if once else "true").select("a", "b").distinct()
        return neighbors.verified(met, rows, small, min_sim)

    while not rest.isEmpty():
        end = orders if share >= 1 else int(share * orders)
        now = checkpoint(rest.where((F.col("ord.o") >= begin) & (F.col("ord.o") < end)))
        pairs = similar(now, now, once=True)
        hop = checkpoint(one_hop(now, pairs, order=F.col("ord.o")))
        parts.append(hop)
        later = rest.where(F.col("ord.o") >= end)
        if end == orders:
            break
        centres = now.join(hop.where("is_centroid").select("sample_id"), "sample_id", "left_semi")
        met = similar(later, centres).join(centres.select(F.col("sample_id").alias("b"), "ord"), "b")
        taken = checkpoint(met.groupBy("a").agg(F.min_by(F.struct("b", "sim"), "ord").alias("m")))
        parts.append(taken.select(F.col("a").alias("sample_id"), F.col("m.b").alias("cluster_id"), F.col("m.sim").alias("sim_to_centroid"), F.lit(False).alias("is_centroid")))
        rest = checkpoint(later.join(taken.select(F.col("a").alias("sample_id")), "sample_id", "left_anti"))
        begin, share = end, 2 * share
    out = members.sparkSession.createDataFrame([], "head bigint, cluster_id bigint, sim_to_centroid double, is_centroid boolean")
    for part in parts:
        out = out.union(part.select("sample_id", "cluster_id", "sim_to_centroid", "is_centroid"))
    own = F.col("sample_id") == F.col("head")
    return members.join(out, "head").select("sample_id", "cluster_id", "sim_to_centroid", (F.col("is_centroid") & own).alias("is_centroid"))


def components(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """(sample_id, component_id): the smallest id reachable over links; rounds of large and small stars."""

    def star(e: DataFrame, large: bool) -> DataFrame:
        seen = e.union(e.select("v", "u")) if large else e
        least = seen.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        joined = seen.join(least, "u")
        out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")) if large else joined.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
        return out.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()

    edges = checkpoint(pairs.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    mark = lambda e: tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
    seen = mark(edges)
    while seen[0]:
        edges = checkpoint(star(star(edges, True), False))
        if (now := mark(edges)) == seen:
            break
        seen = now
    return nodes.select("sample_id").join(edges.withColumnRenamed("u", "sample_id"), "sample_id", "left").select("sample_id", F.coalesce("v", "sample_id").alias("component_id"))


def cluster_profile(clusters: DataFrame) -> DataFrame:
    """How many clusters there are of each size, and the least and mean similarity of their rows to the centroids, in
    exact millionths."""
    micro = F.round(F.col("sim_to_centroid") * 1_000_000).cast("long")
    sizes = clusters.groupBy("cluster_id").agg(F.count("*").alias("size"), F.min(micro).alias("low"), F.sum(micro).alias("total"))
    return sizes.groupBy("size").agg(F.count("*").alias("n_clusters"), F.min("low").alias("min_micro"), F.expr("sum(total) div (count(*) * first(size))").alias("mean_micro"))


def _normal(m: np.ndarray) -> np.ndarray:
    size = np.linalg.norm(m, axis=1, keepdims=True)
    return np.divide(m, size, out=np.zeros_like(m), where=size > 0)


def lloyd(points: np.ndarray, k: int, iterations: int = 20, metric: str = "cosine") -> np.ndarray:
    """Labels of k-means from a farthest-first start at row 0; ties to lower cells, an empty cell takes the worst row."""
    x = _normal(points) if metric == "cosine" else points
    gap = lambda c: 1 - x @ c.T if metric == "cosine" else ((x[:, None, :] - c[None]) ** 2).sum(2)
    chosen = [0]
    while len(chosen) < k:
        chosen.append(int(gap(x[chosen]).min(1).argmax()))
    centres, labels = x[chosen].copy(), np.full(len(x), -1)
    for _ in range(iterations):
        d = np.round(gap(centres), 12)
        new = d.argmin(1)
        for c in range(k):
            if not (new == c).any():
                new[d[np.arange(len(x)), new].argmax()] = c
        if (new == labels).all():
            break
        labels = new
        centres = np.array([x[labels == c].mean(0) if (labels == c).any() else centres[c] for c in range(k)])
        if metric == "cosine":
            centres = _normal(centres)
    return labels


def silhouette_moment(x: np.ndarray, labels: np.ndarray, metric: str = "cosine") -> np.ndarray:
    """Silhouette of each row in O(m k d): the mean cosine or squared Euclid distance to a cell follows from its sums."""
    cells, at = np.unique(labels, return_inverse=True)
    if metric == "cosine":
        x = _normal(x)
    sums = np.array([x[at == c].sum(0) for c in range(len(cells))])
    square = (x**2).sum(1)
    return silhouette_from_sums(x, at, sums, np.bincount(at).astype(float), np.bincount(at, square), metric)


def silhouette_from_sums(x: np.ndarray, at: np.ndarray, sums: np.ndarray, n: np.ndarray, squares: np.ndarray, metric: str) -> np.ndarray:
    """The same for some rows ``x`` (unit vectors for the cosine) in cells ``at``, from the sums, sizes and sums of
    squares of the cells over all rows."""
    square = (x**2).sum(1)
    if metric == "cosine":
        to = 1 - x @ sums.T / n
    else:
        to = square[:, None] + squares / n - 2 * x @ sums.T / n
    own = to[np.arange(len(x)), at] * n[at] / np.maximum(n[at] - 1, 1)
    if metric == "cosine":  # a zero vector is at distance 1 from itself too, which the sums count once too often
        own = np.where(square == 0, (to[np.arange(len(x)), at] * n[at] - 1) / np.maximum(n[at] - 1, 1), own)
    others = to.copy()
    others[np.arange(len(x)), at] = np.inf
    b = others.min(1) if len(n) > 1 else np.zeros(len(x))
    top = np.maximum(own, b)
    s = np.divide(b - own, top, out=np.zeros(len(x)), where=top > 1e-12)
    return np.where((n[at] == 1) | (len(n) < 2), 0.0, s)


def silhouette_exact(x: np.ndarray, labels: np.ndarray, metric: str = "cosine") -> np.ndarray:
    """Silhouette from all pair distances."""
    if metric == "cosine":
        u = _normal(x)
        d = 1 - u @ u.T
    else:
        d = ((x[:, None] - x[None]) ** 2).sum(2)
        if metric == "euclid":
            d = np.sqrt(np.maximum(d, 0))
    np.fill_diagonal(d, 0)
    out = np.zeros(len(x))
    for i, own in enumerate(labels):
        same = labels == own
        if same.sum() == 1 or same.all():
            continue
        a = d[i, same].sum() / (same.sum() - 1)
        b = min(d[i, labels == c].mean() for c in set(labels.tolist()) - {own})
        out[i] = (b - a) / max(a, b) if max(a, b) > 1e-12 else 0.0
    return out


#: Rows of a cluster that one task may hold, and rows of a slice of a larger one.
MAX_GROUP, SLICE_ROWS = 50_000, 8192
_CELLS = "sample_id bigint, cluster_id bigint, sub_id int, k int, silhouette double"


def _points(rows: pa.Table) -> np.ndarray:
    return rows.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(rows.num_rows, -1).astype(float)


def subcluster(clusters: DataFrame, vectors: DataFrame, k_max: int = 8, metric: str = "cosine", k: int | None = None, max_group: int = MAX_GROUP, iterations: int = 20) -> DataFrame:
    """(sample_id, cluster_id, sub_id, k, silhouette): each cluster's k-means cells for the k in 2..k_max (below its
    size) with the largest mean silhouette; ties to the smaller k. Clusters of fewer than three rows are one cell.

    A cluster of more than ``max_group`` rows never comes to one task: the same start, the same rounds and the same
    silhouette are worked out from sums over slices of it, over all its rows.
    """
    joined = clusters.select("sample_id", "cluster_id").join(vectors.select("sample_id", "vec"), "sample_id")
    sizes = clusters.groupBy("cluster_id").agg(F.count("*").alias("_size"))
    sized = joined.join(sizes, "cluster_id").withColumn("_ord", order_key("sample_id"))
    large = F.col("_size") > max_group

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([("_ord", "ascending"), ("sample_id", "ascending")])
        x = _points(rows)
        labels, n, s = np.zeros(len(x), int), 1, 0.0
        tries = [k] if k else range(2, min(k_max, len(x) - 1) + 1)
        for cells in tries if len(x) >= 3 else []:
            if cells < len(x):
                found = lloyd(x, cells, iterations, metric)
                quality = round(float(silhouette_moment(x, found, metric).mean()), 9)
                if n == 1 or quality > s:
                    labels, n, s = found, cells, quality
        return pa.table({"sample_id": rows.column("sample_id"), "cluster_id": rows.column("cluster_id"), "sub_id": pa.array(labels.astype(np.int32)), "k": pa.array(np.full(len(x), n, np.int32)), "silhouette": pa.array(np.full(len(x), s))})

    small = sized.where(~large).select("sample_id", "cluster_id", "vec", "_ord").groupBy("cluster_id").applyInArrow(run, _CELLS)
    if sizes.where(large).isEmpty():
        return small
    tries = [k] if k else list(range(2, k_max + 1))
    return small.union(_large_cells(sized.where(large), tries, metric, iterations))


def _large_cells(rows: DataFrame, tries: list[int], metric: str, iterations: int) -> DataFrame:
    """Cells of clusters that no task may hold, by rounds over slices of bounded size; all k at once.

    ``state`` has a row a cluster and k: its centres, one after the other. A round joins it to the slices, which give sums
    by cell, and adds these up; the number of rounds depends on k and ``iterations`` only. Every slice keeps its rows in
    the random order, and ties go to the earlier row or the lower cell, as in one task.
    """
    slices = F.ceil(F.col("_size") / SLICE_ROWS).cast("int")
    dealt = rows.withColumn("slice", F.pmod(F.xxhash64("sample_id"), slices)).groupBy("cluster_id", "slice")
    packed = checkpoint(dealt.agg(F.sort_array(F.collect_list(F.struct("_ord", "sample_id", "vec"))).alias("rows")))

    def points(cell: pa.StructArray) -> np.ndarray:
        x = neighbors.matrix(cell.field("vec"))
        return _normal(x) if metric == "cosine" else x

    def gaps(x: np.ndarray, c: np.ndarray) -> np.ndarray:
        return 1 - x @ c.T if metric == "cosine" else ((x[:, None, :] - c[None]) ** 2).sum(2)

    def over(state: DataFrame, f, schema: str) -> DataFrame:
        """``f(points, cell, state row)`` for every slice and every state row of its cluster."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    cell = batch.column("rows")[i].values
                    row = {c: batch.column(c)[i].as_py() for c in batch.schema.names if c != "rows"}
                    yield from f(points(cell), cell, row)

        return packed.join(state, "cluster_id").repartition("cluster_id", "slice").mapInArrow(run, schema)

    def nearest(x: np.ndarray, row: dict) -> tuple[np.ndarray, np.ndarray]:
        d = np.round(gaps(x, np.array(row["centres"]).reshape(row["k"], -1)), 12)
        return d, d.argmin(1)

    # The start: the first row, then the row farthest from those chosen, up to the largest k.
    def first(x, cell, row):
        yield pa.RecordBatch.from_arrays([pa.array([row["cluster_id"]]), cell.field("_ord")[:1], cell.field("sample_id")[:1], pa.array([x[0].tolist()])], ["cluster_id", "o", "i", "v"])

    def farthest(x, cell, row):
        d = gaps(x, np.array(row["centres"]).reshape(-1, x.shape[1])).min(1)
        at = int(d.argmax())
        yield pa.RecordBatch.from_arrays([pa.array([row["cluster_id"]]), pa.array([float(d[at])]), cell.field("_ord")[at : at + 1], cell.field("sample_id")[at : at + 1], pa.array([x[at].tolist()])], ["cluster_id", "d", "o", "i", "v"])

    start = checkpoint(over(packed.select("cluster_id").distinct(), first, "cluster_id bigint, o bigint, i bigint, v array<double>").groupBy("cluster_id").agg(F.min_by("v", F.struct("o", "i")).alias("centres")))
    chosen = [start]
    for _ in range(max(tries) - 1):
        far = over(chosen[-1], farthest, "cluster_id bigint, d double, o bigint, i bigint, v array<double>").groupBy("cluster_id").agg(F.max_by("v", F.struct("d", -F.col("o"), -F.col("i"))).alias("v"))
        chosen.append(checkpoint(chosen[-1].join(far, "cluster_id").select("cluster_id", F.concat("centres", "v").alias("centres"))))
    state = None
    for n in tries:
        own = chosen[n - 1].select("cluster_id", F.lit(n).alias("k"), "centres")
        state = own if state is None else state.union(own)
    state = checkpoint(state.withColumn("mark", F.lit(0).cast("bigint")))

    # Rounds: sums by cell, and the worst row of the cluster for a cell that is empty.
    def assign(x, cell, row):
        d, label = nearest(x, row)
        own = d[np.arange(len(x)), label]
        at = int(own.argmax())
        mark = int(np.bitwise_xor.reduce(_word(cell.field("sample_id").to_numpy(zero_copy_only=False), label)))
        for c in np.unique(label):
            mine = label == c
            yield pa.RecordBatch.from_arrays([pa.array([row["cluster_id"]]), pa.array([row["k"]], pa.int32()), pa.array([int(c)], pa.int32()), pa.array([x[mine].sum(0).tolist()]), pa.array([int(mine.sum())]), pa.array([mark]), pa.array([float(own[at])]), cell.field("_ord")[at : at + 1], pa.array([x[at].tolist()])], ["cluster_id", "k", "c", "s", "n", "mark", "d", "o", "v"])
            mark = 0

    def centre(rows: pa.Table) -> pa.Table:
        cluster, n = rows.column("cluster_id")[0].as_py(), rows.column("k")[0].as_py()
        cells, sums = rows.column("c").to_numpy(), np.array(rows.column("s").to_pylist())
        counts, worst = rows.column("n").to_numpy(), rows.sort_by([("d", "descending"), ("o", "ascending")]).slice(0, 1)
        out = []
        for c in range(n):
            mine = cells == c
            out.append(sums[mine].sum(0) / counts[mine].sum() if mine.any() else np.array(worst.column("v")[0].as_py()))
        out = _normal(np.array(out)) if metric == "cosine" else np.array(out)
        mark = int(np.bitwise_xor.reduce(rows.column("mark").to_numpy()))
        return pa.table({"cluster_id": pa.array([cluster]), "k": pa.array([n], pa.int32()), "centres": pa.array([out.ravel().tolist()]), "mark": pa.array([mark])})

    sums_of = "cluster_id bigint, k int, c int, s array<double>, n bigint, mark bigint, d double, o bigint, v array<double>"
    state_of = "cluster_id bigint, k int, centres array<double>, mark bigint"
    for _ in range(iterations):
        after = checkpoint(over(state, assign, sums_of).groupBy("cluster_id", "k").applyInArrow(centre, state_of))
        same = after.join(state.select("cluster_id", "k", F.col("mark").alias("was")), ["cluster_id", "k"]).where("mark <> was").isEmpty()
        if same:  # no label changed, so the centres before are those of the labels
            break
        state = after

    # Silhouettes from the sums of the last labels, and the best k.
    def label_sums(x, cell, row):
        _, label = nearest(x, row)
        square = (x**2).sum(1)
        for c in np.unique(label):
            mine = label == c
            yield pa.RecordBatch.from_arrays([pa.array([row["cluster_id"]]), pa.array([row["k"]], pa.int32()), pa.array([int(c)], pa.int32()), pa.array([x[mine].sum(0).tolist()]), pa.array([int(mine.sum())]), pa.array([float(square[mine].sum())])], ["cluster_id", "k", "c", "s", "n", "q"])

    def totals(rows: pa.Table) -> pa.Table:
        cells = rows.column("c").to_numpy()
        names = np.unique(cells)
        sums, n, q = np.array(rows.column("s").to_pylist()), rows.column("n").to_numpy(), rows.column("q").to_numpy()
        flat = np.concatenate([np.concatenate([[c, n[cells == c].sum(), q[cells == c].sum()], sums[cells == c].sum(0)]) for c in names])
        return pa.table({"cluster_id": rows.column("cluster_id").slice(0, 1), "k": rows.column("k").slice(0, 1), "totals": pa.array([flat.tolist()])})

    totals_ = over(state, label_sums, "cluster_id bigint, k int, c int, s array<double>, n bigint, q double").groupBy("cluster_id", "k").applyInArrow(totals, "cluster_id bigint, k int, totals array<double>")
    known = checkpoint(state.join(totals_, ["cluster_id", "k"]))

    def widths(x, cell, row):
        _, label = nearest(x, row)
        t = np.array(row["totals"]).reshape(-1, 3 + x.shape[1])
        s = silhouette_from_sums(x, np.searchsorted(t[:, 0], label), t[:, 3:], t[:, 1], t[:, 2], metric)
        yield pa.RecordBatch.from_arrays([pa.array([row["cluster_id"]]), pa.array([row["k"]], pa.int32()), pa.array([float(s.sum())]), pa.array([len(x)])], ["cluster_id", "k", "s", "n"])

    quality = over(known, widths, "cluster_id bigint, k int, s double, n bigint").groupBy("cluster_id", "k").agg(F.round(F.sum("s") / F.sum("n"), 9).alias("silhouette"))
    best = quality.groupBy("cluster_id").agg(F.max_by(F.struct("k", "silhouette"), F.struct("silhouette", -F.col("k"))).alias("b")).select("cluster_id", "b.k", "b.silhouette")
    final = checkpoint(state.join(best, ["cluster_id", "k"]))

    def place(x, cell, row):
        _, label = nearest(x, row)
        yield pa.RecordBatch.from_arrays([cell.field("sample_id"), pa.array(np.full(len(x), row["cluster_id"])), pa.array(label.astype(np.int32)), pa.array(np.full(len(x), row["k"], np.int32)), pa.array(np.full(len(x), row["silhouette"]))], ["sample_id", "cluster_id", "sub_id", "k", "silhouette"])

    return over(final, place, _CELLS)


def _word(ids: np.ndarray, labels: np.ndarray) -> np.ndarray:
    """A number of 62 bits for each id and label; their exclusive or tells assignments apart."""
    x = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + labels.astype(np.uint64) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
    return ((x ^ (x >> np.uint64(32))) >> np.uint64(2)).astype(np.int64)


def silhouettes(cells: DataFrame, vectors: DataFrame) -> DataFrame:
    """(cluster_id, silhouette): mean cosine silhouette of each cluster's cells, by sums, in plain aggregations."""
    x = cells.select("sample_id", "cluster_id", "sub_id").join(vectors.select("sample_id", unit(F.col("vec")).alias("u")), "sample_id")
    parts = x.select("cluster_id", "sub_id", F.posexplode("u").alias("i", "x")).groupBy("cluster_id", "sub_id", "i").agg(F.sum("x").alias("s"))
    sums = parts.groupBy("cluster_id", "sub_id").agg(F.sort_array(F.collect_list(F.struct("i", "s"))).alias("v")).select("cluster_id", "sub_id", F.col("v.s").alias("sums"))
    sums = sums.join(x.groupBy("cluster_id", "sub_id").agg(F.count("*").alias("n")), ["cluster_id", "sub_id"]).withColumnRenamed("sub_id", "cell")
    to = x.join(sums, "cluster_id").withColumn("proj", dot(F.col("u"), F.col("sums")))
    own = F.when((F.col("cell") == F.col("sub_id")) & (F.col("n") > 1), (F.col("n") - F.col("proj")) / (F.col("n") - 1))
    other = F.when(F.col("cell") != F.col("sub_id"), 1 - F.col("proj") / F.col("n"))
    rows = to.groupBy("sample_id", "cluster_id").agg(F.max(own).alias("a"), F.min(other).alias("b"))
    s = F.when(F.col("a").isNull() | F.col("b").isNull() | (F.greatest("a", "b") <= 1e-12), 0.0).otherwise((F.col("b") - F.col("a")) / F.greatest("a", "b"))
    return rows.groupBy("cluster_id").agg(F.count("*").alias("size"), F.round(F.avg(s), 6).alias("silhouette"))


def silhouettes_exact(cells: DataFrame, vectors: DataFrame) -> DataFrame:
    """The same from all pairs inside each cluster; for checks."""

    def run(rows: pa.Table) -> pa.Table:
        x = rows.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(rows.num_rows, -1).astype(float)
        s = silhouette_exact(x, rows.column("sub_id").to_numpy())
        return pa.table({"cluster_id": rows.column("cluster_id").slice(0, 1), "size": pa.array([rows.num_rows], pa.int64()), "silhouette": pa.array([round(float(s.mean()), 6)])})

    return cells.join(vectors, "sample_id").select("cluster_id", "sub_id", "vec").groupBy("cluster_id").applyInArrow(run, "cluster_id bigint, size bigint, silhouette double")
