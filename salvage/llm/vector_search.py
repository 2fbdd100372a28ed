"""Exact top-k inner-product search with a KD-tree per shard.

Vectors are dealt to shards of bounded size; each shard becomes one KD-tree, kept as one binary row: median splits on
the widest dimension, leaves as contiguous rows, and a tight bounding box per node. The best score a box can hold bounds
its node. A query first runs down to its most promising leaf; the kth score of that leaf closes all boxes below it, and
the leaves left open are visited best first. Queries are the stated set and come in blocks. A block searches one home
shard, then the next shard, the next two, four and so on; each round starts from the kth score of all rounds before it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.llm.common import checkpoint

SHARD_ROWS, BLOCK_QUERIES, LEAF_ROWS = 16384, 4096, 256
_LOW, _HIGH = np.iinfo(np.int64).min, np.iinfo(np.int64).max


def scaled(vector: Column) -> Column:
    """floor(64 * x) per component, or null if the vector is null or holds a null or a non-finite component. A component
    beyond the range of a long is the nearest long."""
    x = vector.cast("array<double>")
    fit = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return F.when(fit, F.transform(x, lambda v: F.floor(v * 64)))


class Tree:
    """A KD-tree over integer vectors. Leaves are slices of ``points``; ``low``/``high`` are the nodes' boxes."""

    def __init__(self, ids: np.ndarray, points: np.ndarray):
        rank = np.argsort(ids, kind="stable")  # smaller positions are smaller ids, for ties
        ids, points = ids[rank], points[rank]
        order = np.arange(len(ids))
        spans, low, high, kids = [(0, len(ids))], [], [], []
        at = 0
        while at < len(spans):
            a, b = spans[at]
            own = points[order[a:b]]
            low.append(own.min(0))
            high.append(own.max(0))
            if b - a <= LEAF_ROWS:
                kids.append(-1)
            else:
                m = (b - a) // 2
                order[a:b] = order[a:b][np.argpartition(own[:, np.argmax(high[-1] - low[-1])], m)]
                kids.append(len(spans))
                spans += [(a, a + m), (a + m, b)]
            at += 1
        self.spans, self.kids = np.array(spans), np.array(kids)
        self.low, self.high = np.array(low), np.array(high)
        self.position, self.ids, self.points = order, ids, points[order]

    def bounds(self, queries: np.ndarray, nodes: np.ndarray) -> np.ndarray:
        """The highest score that each node's box allows to each query."""
        return np.maximum(queries, 0) @ self.high[nodes].T + np.minimum(queries, 0) @ self.low[nodes].T

    def search(self, queries: np.ndarray, own: np.ndarray, floor: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row of query, id, score) of up to k best rows each that reach ``floor``; rows with the id ``own`` are left out.

        A score and a position share one integer key, so the greatest keys are the answer with ties to smaller ids.
        Scores are exact, in Python's integers where 53 bits don't hold them; one beyond the range of a long is returned
        as the nearest long.
        """
        n = len(queries)
        limit = float(np.abs(queries).max(initial=0)) * max(np.abs(self.low).max(initial=0), np.abs(self.high).max(initial=0)) * queries.shape[1]
        kind = np.float32 if limit < 2**24 else np.float64 if limit < 2**53 else object
        bits = max(1, len(self.ids) - 1).bit_length()
        wide = object if kind is object or limit >= 2 ** (62 - bits) else np.int64
        q, unit, last = queries.astype(kind), 1 << bits, (1 << bits) - 1
        lowest = _LOW if wide is np.int64 else -(10**60)
        best = np.full((n, k), lowest, wide)  # unordered, the least is the kth
        reach = np.where(floor > -(2.0**62), floor.astype(np.float64), -np.inf)
        skip = np.searchsorted(self.ids, own)
        skip = np.where((skip < len(self.ids)) & (self.ids[np.minimum(skip, len(self.ids) - 1)] == own), skip, -1)
        twice = len(np.unique(self.ids)) < len(self.ids)
        tree, self_low, self_high = self.points.astype(kind), self.low, self.high
        self.low, self.high = self_low.astype(kind), self_high.astype(kind)

        def keys_of(rows: np.ndarray, node: int) -> np.ndarray:
            a, b = self.spans[node]
            where = self.position[a:b]
            keys = (q[rows] @ tree[a:b].T).astype(wide) * unit + (last - where)
            if twice:
                keys[self.ids[where][None, :] == own[rows][:, None]] = lowest
            else:
                keys[where[None, :] == skip[rows][:, None]] = lowest
            return keys

        at = np.zeros(n, np.int64)  # the most promising leaf of each query: its kth score closes boxes from the start
        while len(down := np.flatnonzero(self.kids[at] >= 0)):
            for node in np.unique(at[down]):
                rows = down[at[down] == node]
                kids = np.array([self.kids[node], self.kids[node] + 1])
                at[rows] = kids[self.bounds(q[rows], kids).astype(np.float64).argmax(1)]
        for node in np.unique(at):
            rows = np.flatnonzero(at == node)
            keys = keys_of(rows, node)
            if keys.shape[1] > k:
                kth = np.sort(keys, 1)[:, -k] if wide is object else np.partition(keys, -k, 1)[:, -k]
                full = kth > lowest
                reach[rows[full]] = np.maximum(reach[rows[full]], (kth[full] // unit).astype(np.float64))
        level, leaves = np.array([0]), []
        open_ = np.ones((n, 1), bool)
        while len(level):  # down the tree, with boxes that no query can use left out
            bound = self.bounds(q, level).astype(np.float64)
            open_ &= bound >= reach[:, None]
            used = open_.any(0)
            level, open_, bound = level[used], open_[:, used], bound[:, used]
            is_leaf = self.kids[level] < 0
            leaves += [(node, np.where(open_[:, j], bound[:, j], -np.inf)) for j, node in enumerate(level) if is_leaf[j]]
            level, open_ = level[~is_leaf], open_[:, ~is_leaf]
            level = np.stack([self.kids[level], self.kids[level] + 1], 1).ravel() if len(level) else level
            open_ = np.repeat(open_, 2, 1)
        if leaves:
            nodes, bound = np.array([x for x, _ in leaves]), np.stack([x for _, x in leaves], 1)
            turn = np.argsort(-bound, 1, kind="stable")
            for r in range(len(nodes)):  # each query's next best leaf; queries that share it go together
                pick = turn[:, r]
                live = np.flatnonzero(bound[np.arange(n), pick] >= reach) if r else np.flatnonzero(bound[np.arange(n), pick] > -np.inf)
                if not len(live):
                    break
                live = live[np.argsort(pick[live], kind="stable")]
                cuts = np.flatnonzero(np.diff(pick[live])) + 1
                for rows in np.split(live, cuts):
                    both = np.concatenate([best[rows], keys_of(rows, nodes[pick[rows[0]]])], 1)
                    both = np.partition(both, both.shape[1] - k, 1)[:, -k:] if wide is np.int64 else np.sort(both, 1)[:, -k:]
                    best[rows] = both
                    least = both.min(1)
                    full = least > lowest
                    reach[rows[full]] = np.maximum(reach[rows[full]], (least[full] // unit).astype(np.float64))
        self.low, self.high = self_low, self_high
        row, col = np.nonzero(best > lowest)
        key = best[row, col]
        score = key // unit
        if wide is object:
            score = np.clip(score, _LOW, _HIGH)
        keep = score >= floor[row]
        row, key, score = row[keep], key[keep], score[keep]
        return row, self.ids[(last - key % unit).astype(np.int64)], score.astype(np.int64)


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return np.asarray(column.flatten(), np.int64).reshape(len(column), dim)


def top_k(points: DataFrame, queries: DataFrame, k: int, id_col: str = "vec_id", vector_col: str = "v", shard_rows: int = SHARD_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """(query_id, rank, vec_id, score): for each query its k highest inner products with points of other ids.

    ``vector_col`` is an array of longs; null vectors and null ids take no part, vectors are compared with those of
    the same length only, and rows that repeat an id are candidates each. Fewer than k candidates give fewer rows; an
    empty table gives none; equal scores go to smaller ids; other columns are not read. One tree and one block of
    queries are in memory at a time.
    """
    spark = points.sparkSession
    base = lambda df: df.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<bigint>").alias("v")).where("id is not null and v is not null and size(v) > 0").withColumn("dim", F.size("v"))
    points, queries = base(points), base(queries)
    sizes = {r["dim"]: (r["n"], r["q"]) for r in points.groupBy("dim").agg(F.count("*").alias("n")).join(queries.groupBy("dim").agg(F.count("*").alias("q")), "dim").collect()}
    out = "query_id bigint, vec_id bigint, score bigint"
    if not sizes:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score bigint")

    def per_dim(which: int, rows: int) -> Column:
        parts = F.lit(1)
        for dim, n in sizes.items():
            parts = F.when(F.col("dim") == dim, -(-n[which] // rows)).otherwise(parts)
        return parts

    shards, n_blocks = per_dim(0, shard_rows), per_dim(1, block_queries)

    def build(batch: pa.Table) -> pa.Table:
        dim = batch.column("dim")[0].as_py()
        tree = Tree(batch.column("id").to_numpy(), _matrix(batch.column("v").combine_chunks(), dim))
        import pickle

        return pa.table({"dim": pa.array([dim], pa.int32()), "shard": pa.array([batch.column("shard")[0].as_py()], pa.int32()), "tree": pa.array([pickle.dumps(tree, 5)], pa.binary())})

    trees = points.where(F.col("dim").isin(*sizes)).withColumn("shard", F.pmod(F.xxhash64("id"), shards).cast("int")).groupBy("dim", "shard").applyInArrow(build, "dim int, shard int, tree binary")
    blocks = queries.where(F.col("dim").isin(*sizes)).withColumn("block", F.pmod(F.xxhash64("id", F.lit(7)), n_blocks).cast("int"))
    blocks = blocks.groupBy("dim", "block").agg(F.collect_list(F.struct("id", "v")).alias("q")).withColumn("home", F.pmod("block", shards).cast("int"))

    def search(with_floor: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            import pickle

            for batch in batches:
                for i in range(batch.num_rows):
                    tree, dim = pickle.loads(batch.column("tree")[i].as_py()), batch.column("dim")[i].as_py()
                    q = batch.column("q")[i].values
                    ids = q.field("id").to_numpy(zero_copy_only=False)
                    floor = q.field("floor").to_numpy(zero_copy_only=False) if with_floor else np.full(len(ids), _LOW)
                    row, found, score = tree.search(_matrix(q.field("v"), dim), ids, floor, k)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[row]), pa.array(found), pa.array(score)], ["query_id", "vec_id", "score"])

        return run

    trees = checkpoint(trees)
    found = checkpoint(trees.join(blocks.withColumn("shard", F.col("home")), ["dim", "shard"]).select("dim", "tree", "q").mapInArrow(search(False), out))
    most, begin = max(-(-n // shard_rows) for n, _ in sizes.values()), 1
    while begin < most:  # the next shard, the next two, four ... of each block, from its home on
        best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
        top = found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
        kth = top.groupBy("query_id").agg(F.when(F.count("*") >= k, F.min("score")).otherwise(F.lit(_LOW)).alias("floor"))
        asked = blocks.select("dim", "block", "home", F.explode("q").alias("x")).join(kth.withColumnRenamed("query_id", "x_id"), F.col("x.id") == F.col("x_id"), "left")
        one = F.struct(F.col("x.id").alias("id"), F.col("x.v").alias("v"), F.coalesce("floor", F.lit(_LOW)).alias("floor"))
        asked = asked.groupBy("dim", "block", "home").agg(F.collect_list(one).alias("q"))  # at most block_queries
        step = F.explode(F.sequence(F.lit(begin), F.lit(2 * begin - 1))).alias("step")
        others = asked.select("dim", "block", "q", step, "home").where(F.col("step") < shards).withColumn("shard", F.pmod(F.col("home") + F.col("step"), shards).cast("int"))
        more = trees.join(others, ["dim", "shard"]).repartition("shard", "block").select("dim", "tree", "q").mapInArrow(search(True), out)
        found, begin = checkpoint(top.select("query_id", "vec_id", "score").union(more)), 2 * begin
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def embedding_neighbours(embeddings: DataFrame, k: int = 20, every: int = 20) -> DataFrame:
    """The digest: queries are the rows whose vec_id is divisible by ``every``, candidates all other rows."""
    rows = embeddings.select("vec_id", scaled(F.col("embedding")).alias("v"))
    return top_k(rows, rows.where(F.col("vec_id") % every == 0), k)


NEIGHBOURS_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.v, c.v)::BIGINT AS score
      FROM v q JOIN v c ON c.vec_id <> q.vec_id AND len(c.v) = len(q.v) WHERE q.vec_id % 20 = 0),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20"""
