"""Similarity pairs and nearest neighbours: exact by blocks, and by hyperplane signs for tables of any size."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.functions.materialize import checkpoint

#: Rows of a block of the exact form, most and (where there are fewer blocks than cores) least; rows compared at a time.
BLOCK_ROWS, LEAST_ROWS, SLICE_ROWS = 8192, 512, 1024
#: Share of the pairs at the threshold that bands should find; rows of a band key from which it is split by further bits;
#: how often; bits of a split; sign bits of a vector that splits draw from.
RECALL, BUCKET_ROWS, LEVELS, SPLIT_BITS, POOL_BITS = 0.999, 4096, 3, 6, 1024
#: Trees of the forest, rows of a window of its sorted signatures, rows of a partition (least and most).
TREES, WINDOW, PART_ROWS, MOST_ROWS = 8, 1024, 1 << 14, 1 << 18
#: Rows of a slice that is left out as a whole where outlines allow it, directions of an outline, groups of a block's
#: rows, and rows of a block from which both are taken.
TILE_ROWS, DIRECTIONS, GROUPS, SAMPLE_ROWS = 512, 15, 64, 1024
#: Bytes of the smaller side of a join that may be broadcast.
BROADCAST_BYTES = 64 << 20


def matrix(column: pa.Array) -> np.ndarray:
    values = column.flatten().to_numpy(zero_copy_only=False)
    return values.reshape(len(column), -1).astype(np.float64) if len(values) else np.zeros((len(column), 0))


def round6(x: np.ndarray) -> np.ndarray:
    """Half away from zero, after rounding away the noise of the products; as SQL rounds."""
    return np.sign(x) * np.floor(np.abs(np.round(x, 9)) * 1e6 + 0.5 + 1e-6) / 1e6


def units(m: np.ndarray) -> np.ndarray:
    size = np.linalg.norm(m, axis=1, keepdims=True)
    return np.divide(m, size, out=np.zeros_like(m), where=size > 0)


def _closeness(a: np.ndarray, b: np.ndarray, metric: str) -> np.ndarray:
    """Cosine or negative Euclid distance of all rows of ``a`` to all of ``b``, to nine decimals."""
    if metric == "cosine":
        s = units(a) @ units(b).T
    else:
        s = -np.sqrt(np.maximum((a**2).sum(1)[:, None] + (b**2).sum(1)[None, :] - 2 * a @ b.T, 0))
    return np.round(s, 9) + 0.0


# Exact, by pairs of blocks


def _packed(df: DataFrame, side: str, block_rows: int) -> DataFrame:
    """Rows of bounded blocks as one cell each."""
    n, cores = df.count(), df.sparkSession.sparkContext.defaultParallelism
    blocks = max(1, -(-n // block_rows), min(cores, n // LEAST_ROWS))
    dealt = df.withColumn(side, F.pmod(F.xxhash64("sample_id"), F.lit(blocks)).cast("int"))
    rows = F.collect_list(F.struct(*df.columns)).alias(f"{side}_rows")  # about block_rows of them
    return checkpoint(dealt.repartition(blocks, side).groupBy(side).agg(rows))


def block_pairs(left: DataFrame, right: DataFrame, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(a_rows, b_rows): every block of ``left`` beside every block of ``right``. The work is the product of the rows;
    a task holds two blocks, which it reads where they are written, so no copy of a block is shuffled or broadcast."""
    a, b = _packed(left, "a", block_rows), _packed(right, "b", block_rows)
    return a.hint("shuffle_replicate_nl").crossJoin(b).select("a_rows", "b_rows")


def _own_pairs(df: DataFrame, block_rows: int) -> DataFrame:
    """(same, a_rows, b_rows): every pair of blocks of ``df`` once."""
    a = _packed(df, "a", block_rows)
    b = a.select(F.col("a").alias("b"), F.col("a_rows").alias("b_rows"))
    met = a.hint("shuffle_replicate_nl").crossJoin(b).where("a >= b")
    return met.select((F.col("a") == F.col("b")).alias("same"), "a_rows", "b_rows")


def _unpack(cell: pa.StructArray) -> tuple[np.ndarray, np.ndarray]:
    return cell.field("sample_id").to_numpy(zero_copy_only=False), matrix(cell.field("vec"))


def _slices(n: int) -> Iterator[slice]:
    return (slice(at, at + SLICE_ROWS) for at in range(0, n, SLICE_ROWS))


def _exact_pairs(df: DataFrame, min_sim: float, block_rows: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                (ia, va), (ib, vb) = _unpack(batch.column("a_rows")[i].values), _unpack(batch.column("b_rows")[i].values)
                ub, same = units(vb).T, batch.column("same")[i].as_py()
                for part in _slices(len(ia)):
                    sims = units(va[part]) @ ub
                    r, c = np.nonzero(sims >= min_sim - 5e-7)
                    a, b = ia[part][r], ib[c]
                    low, high, sim = np.minimum(a, b), np.maximum(a, b), round6(sims[r, c])
                    keep = (sim >= min_sim) & ((a < b) if same else (low < high))
                    yield pa.RecordBatch.from_arrays([pa.array(low[keep]), pa.array(high[keep]), pa.array(sim[keep])], ["a", "b", "sim"])

    return _own_pairs(df, block_rows).mapInArrow(run, "a bigint, b bigint, sim double")


def count_pairs(df: DataFrame, grid: tuple[float, ...], block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(min_sim, n_pairs): how many pairs of rows of ``df`` (sample_id, vec) have a cosine of each of ``grid`` at least.
    Pairs are counted where their blocks meet, so none is ever a row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(len(grid), np.int64)
        for batch in batches:
            for i in range(batch.num_rows):
                (ia, va), (ib, vb) = _unpack(batch.column("a_rows")[i].values), _unpack(batch.column("b_rows")[i].values)
                ub, same = units(vb).T, batch.column("same")[i].as_py()
                for part in _slices(len(ia)):
                    sims = units(va[part]) @ ub
                    r, c = np.nonzero(sims >= min(grid) - 5e-7)
                    sim = round6(sims[r, c][(ia[part][r] < ib[c]) if same else (ia[part][r] != ib[c])])
                    n += [int((sim >= t).sum()) for t in grid]
        yield pa.RecordBatch.from_arrays([pa.array(grid, pa.float64()), pa.array(n)], ["min_sim", "n"])

    found = _own_pairs(df, block_rows).mapInArrow(run, "min_sim double, n bigint").groupBy("min_sim").agg(F.sum("n").alias("n"))
    all_ = df.sparkSession.createDataFrame([(t,) for t in grid], "min_sim double")
    return all_.join(found, "min_sim", "left").select("min_sim", F.coalesce("n", F.lit(0)).cast("bigint").alias("n_pairs"))


def _rows_of(cell: pa.StructArray, name: str, dtype: type) -> np.ndarray:
    """A binary field as a matrix, a row each."""
    field = cell.field(name)
    at = np.frombuffer(field.buffers()[1], np.int32)[field.offset : field.offset + len(field) + 1]
    whole = np.frombuffer(field.buffers()[2], np.uint8)[at[0] : at[-1]] if at[-1] > at[0] else np.zeros(0, np.uint8)
    return whole.view(dtype).reshape(len(field), -1)


def _agree(a: np.ndarray, b: np.ndarray, x: np.ndarray, y: np.ndarray, width: int) -> np.ndarray:
    """Which of the pairs (x, y) have an equal word: a line of ``a`` and ``b`` holds 64 / ``width`` words of each row as a
    number, and is looked at only for pairs that no line before it has decided."""
    low = np.uint64(sum(1 << at for at in range(0, 64, width)))
    high, equal, open_ = low << np.uint64(width - 1), np.ones(len(x), bool), np.arange(len(x))
    for of_a, of_b in zip(a, b, strict=True):
        differ = of_a[x] ^ of_b[y]
        none = np.flatnonzero(((differ - low) & ~differ & high) == 0)  # no word of the number is nought
        x, y, open_ = x[none], y[none], open_[none]
    equal[open_] = False
    return equal


def _outlined(ua: np.ndarray, ub: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Outlines of the unit vectors of two blocks, and a group for each row. The product of two outlines is at least that
    of the vectors: it has the vectors' parts along a few common directions, and beside them the lengths of the rest.
    Directions and groups come from some of the rows; they decide how much work is saved, never what is found."""
    some = np.vstack([u[:: max(1, len(u) // SAMPLE_ROWS)] for u in (ua, ub)]).astype(np.float64)
    along = np.linalg.eigh(some.T @ some)[1][:, ::-1][:, :DIRECTIONS].astype(np.float32)

    def outline(u: np.ndarray) -> np.ndarray:
        part = u @ along
        rest = np.einsum("ij,ij->i", u, u) - np.einsum("ij,ij->i", part, part)
        return np.hstack([part, np.sqrt(np.maximum(rest, 0) + 1e-6)[:, None]])

    a, b = outline(ua), outline(ub)
    drawn = np.vstack([a[:: max(1, len(a) // SAMPLE_ROWS)], b[:: max(1, len(b) // SAMPLE_ROWS)]])
    centres = drawn[:: max(1, len(drawn) // GROUPS)]
    for _ in range(4):
        own = (drawn @ centres.T).argmax(1)
        sums = (own[None, :] == np.arange(len(centres))[:, None]).astype(np.float32) @ drawn
        centres = units(np.where((sums == 0).all(1)[:, None], centres, sums)).astype(np.float32)
    return a, b, (a @ centres.T).argmax(1), (b @ centres.T).argmax(1)


def meetings(df: DataFrame, min_sim: float, block_rows: int = BLOCK_ROWS, bands: tuple[int, int] | None = None, seed: int = 42, least: DataFrame | None = None, k: int = 0) -> DataFrame:
    """One meeting of all rows of ``df`` (sample_id, vec and, where a row stands for copies, n), whose vectors differ; for
    a row and a pair of blocks either (sample_id, links, agreed), how many rows, copies too, have a cosine of ``min_sim``
    with it, and how many of them agree on one of ``bands`` (bits and number) too; or (sample_id, nn_id, sim), rows that
    may be among its ``k`` closest: those at least as close as its k-th of ``least`` (sample_id, nn_rank, nn_id, sim),
    which may be any k other rows.

    Every two rows meet once. Slices of rows in groups are first compared by outlines, which never fall short of the
    cosine; what can still reach a limit is multiplied in single precision, and worked out in double precision near
    ``min_sim`` and for the closest rows.
    """
    bits, draws = bands or (0, 0)
    width = next(w for w in (16, 32, 64) if bits <= w)
    lanes = 64 // width

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(at, SLICE_ROWS)
                m = matrix(part.column("vec"))
                words = np.zeros((len(m), -(-draws // lanes) * lanes), f"u{width // 8}")
                if draws and m.size:
                    words[:, :draws] = _words(m, bits, draws, seed)
                cells = [pa.array([row.tobytes() for row in x], pa.binary()) for x in (m.astype(np.float32), words)]
                yield pa.RecordBatch.from_arrays([part.column("sample_id"), part.column("n"), part.column("least"), *cells], ["sample_id", "n", "least", "vec", "words"])

    def close(limits: tuple | float, s: np.ndarray) -> np.ndarray:
        if isinstance(limits, float):
            return s >= np.float32(limits)
        met = s >= limits[0][:, None]
        met |= s >= limits[1][None, :]
        return met

    def closest(row: np.ndarray, other: np.ndarray, sim: np.ndarray) -> tuple[np.ndarray, ...]:
        order = np.lexsort((other, -sim, row))
        row, other, sim = row[order], other[order], sim[order]
        keep = np.arange(len(row)) - np.searchsorted(row, row) < k
        return row[keep], other[keep], sim[keep]

    def foremost(row: np.ndarray, s: np.ndarray) -> np.ndarray:
        """Places of what may be among the k closest by single precision, so that few are worked out in double precision."""
        order = np.lexsort((-s, row))
        row, s = row[order], s[order]
        kth = np.minimum(np.searchsorted(row, row) + k, np.searchsorted(row, row, "right")) - 1
        return order[s >= s[kth] - np.float32(2e-5)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):
                yield from meet(batch.column("a_rows")[at].values, batch.column("b_rows")[at].values, batch.column("same")[at].as_py())

    def meet(a: pa.StructArray, b: pa.StructArray, same: bool) -> Iterator[pa.RecordBatch]:
        u = [units(_rows_of(x, "vec", np.float32).astype(np.float64)) for x in (a, b)]
        narrow = [x.astype(np.float32) for x in u]
        own = [x.field("least").to_numpy(zero_copy_only=False) for x in (a, b)]
        outlines, group = None, [np.zeros(len(x), int) for x in u]
        if u[0].shape[1] > 2 * DIRECTIONS:
            *outlines, group[0], group[1] = _outlined(*narrow)
        order = [np.lexsort((t, g)) for t, g in zip(own, group, strict=True)]
        u, narrow, own = ([x[o] for x, o in zip(xs, order, strict=True)] for xs in (u, narrow, own))
        if outlines:
            outlines = [x[o] for x, o in zip(outlines, order, strict=True)]
        ids = [x.field("sample_id").to_numpy(zero_copy_only=False)[o] for x, o in zip((a, b), order, strict=True)]
        n = [x.field("n").to_numpy(zero_copy_only=False).astype(np.float64)[o] for x, o in zip((a, b), order, strict=True)]
        words = [_rows_of(x, "words", np.uint64)[o] for x, o in zip((a, b), order, strict=True)] if bands else None
        if bands:
            words[1].view(f"u{width // 8}")[:, draws:] = 1  # what fills up the last number of words never agrees
            words = [np.ascontiguousarray(w.T) for w in words]
        counts = [[np.zeros(len(x)) for x in ids] for _ in range(2)]
        near: list[list[tuple]] = [[], []]
        fine = [t.astype(np.float32) - np.float32(1e-5) for t in own]
        low = [np.minimum(t, np.float32(min_sim) - np.float32(1e-5)) for t in fine]
        for i in range(0, len(ids[0]), TILE_ROWS):
            reached: list[tuple] = []
            for j in range(i if same else 0, len(ids[1]), TILE_ROWS):
                si, sj = slice(i, i + TILE_ROWS), slice(j, j + TILE_ROWS)
                limits = (low[0][si], low[1][sj]) if k else float(np.float32(min_sim) - np.float32(1e-5))
                if outlines:
                    may = close(limits, outlines[0][si] @ outlines[1][sj].T)
                    rows, cols = np.flatnonzero(may.any(1)), np.flatnonzero(may.any(0))
                    if not len(rows):
                        continue
                    si, sj = (whole if len(some) > 0.9 * TILE_ROWS else some + whole.start for some, whole in ((rows, si), (cols, sj)))
                    limits = (low[0][si], low[1][sj]) if k else limits
                s = narrow[0][si] @ narrow[1][sj].T
                at = np.flatnonzero(close(limits, s))
                r = at // s.shape[1]
                c = at - r * s.shape[1]
                reached.append((s.ravel()[at], r + i if isinstance(si, slice) else si[r], c + j if isinstance(sj, slice) else sj[c]))
            if not reached:
                continue
            s, x, y = (np.concatenate(part) for part in zip(*reached, strict=True))
            if same:
                once = x < y
                s, x, y = s[once], x[once], y[once]
            link = s >= min_sim
            edge = np.flatnonzero(np.abs(s - np.float32(min_sim)) < 1e-5)
            link[edge] = round6((u[0][x[edge]] * u[1][y[edge]]).sum(1)) >= min_sim
            lx, ly = x[link], y[link]
            both = _agree(*words, lx, ly, width) if bands else slice(0)
            for count, p, q in ((counts[0], lx, ly), (counts[1], lx[both], ly[both])):
                count[0] += np.bincount(p, n[1][q], len(ids[0]))
                count[1] += np.bincount(q, n[0][p], len(ids[1]))
            for side, row, other in ((0, x, y), (1, y, x)) if k else ():
                kept = np.flatnonzero(s >= fine[side][row])
                kept = kept[foremost(row[kept], s[kept])]
                for some in np.split(kept, range(SLICE_ROWS << 4, len(kept), SLICE_ROWS << 4)):
                    sim = np.round((u[side][row[some]] * u[1 - side][other[some]]).sum(1), 9) + 0.0
                    reach = sim >= own[side][row[some]] - 2e-9
                    near[side].append(closest(row[some][reach], ids[1 - side][other[some][reach]], sim[reach]))
                    of, _, sim = near[side][-1]
                    last = np.flatnonzero(np.arange(len(of)) - np.searchsorted(of, of) == k - 1)  # k rows are as close: a better bound
                    own[side][of[last]] = np.maximum(own[side][of[last]], sim[last])
                    fine[side][of[last]] = own[side][of[last]].astype(np.float32) - np.float32(1e-5)
                    low[side][of[last]] = np.minimum(fine[side][of[last]], np.float32(min_sim) - np.float32(1e-5))
        for side in (0, 1):
            links, agreed = (np.round(c[side]).astype(np.int64) for c in counts)
            if same and side == 0:
                continue
            if same:
                links, agreed = (np.round(c[0] + c[1]).astype(np.int64) for c in counts)
            some = np.flatnonzero(links)
            nothing = pa.nulls(len(some))
            yield pa.RecordBatch.from_arrays([pa.array(ids[side][some]), pa.array(links[some]), pa.array(agreed[some]), nothing.cast(pa.int64()), nothing.cast(pa.float64())], ["sample_id", "links", "agreed", "nn_id", "sim"])
        for side in (0, 1):
            if near[side]:
                row, other, sim = closest(*(np.concatenate(c) for c in zip(*near[side], strict=True)))
                nothing = pa.nulls(len(row)).cast(pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(ids[side][row]), nothing, nothing, pa.array(other), pa.array(sim)], ["sample_id", "links", "agreed", "nn_id", "sim"])

    rows = df if "n" in df.columns else df.withColumn("n", F.lit(1).cast("bigint"))
    if least is None:
        rows = rows.withColumn("least", F.lit(2.0))  # no cosine reaches it
    else:
        kth = least.where(F.col("nn_rank") == k).select("sample_id", F.col("sim").alias("least"))
        rows = rows.join(kth, "sample_id", "left").withColumn("least", F.coalesce("least", F.lit(-2.0)))
    packed = rows.select("sample_id", "n", "least", "vec").mapInArrow(pack, "sample_id bigint, n bigint, least double, vec binary, words binary")
    return _own_pairs(packed, block_rows).mapInArrow(run, "sample_id bigint, links bigint, agreed bigint, nn_id bigint, sim double")


def linked(df: DataFrame, min_sim: float = 0.9, block_rows: int = BLOCK_ROWS, bands: tuple[int, int] | None = None, seed: int = 42, met: DataFrame | None = None) -> DataFrame:
    """(sample_id, class_id, links): for each row of ``df`` (sample_id, vec) the smallest id of its vector's copies, and
    how many other rows, copies too, have a cosine of at least ``min_sim`` with it.

    Distinct vectors are compared block by block and counted there with their copies; a zero vector has no link. Single
    precision decides all but cosines near the threshold, which are worked out in double precision. With ``bands`` (bits
    and number; 0 bits: as planned for the rows) only those links of different vectors count that agree on a band of
    hyperplane signs, as ``sim_pairs`` has them by ``lsh``, but without a limit on the rows of a band and without a list.
    ``met``, where several measures share one, is the meeting of the rows of ``df``, whose vectors all differ then.
    """
    if met is None:
        heads, members = collapse(df)
        bands = (bands if bands[0] else plan_bands(heads.count(), min_sim)) if bands else None
        sizes = members.groupBy(F.col("head").alias("sample_id")).agg(F.count("*").alias("n"))
        heads = checkpoint(heads.join(sizes, "sample_id"))
        met = meetings(heads, min_sim, block_rows, bands, seed)
    else:
        heads, members = df.select("sample_id", "vec", F.lit(1).alias("n")), df.select("sample_id", F.col("sample_id").alias("head"))
    found = met.where("links is not null").groupBy("sample_id").agg(F.sum("agreed" if bands else "links").alias("links"))
    own = F.when(F.exists("vec", lambda x: x != 0), F.col("n") - 1).otherwise(0)
    whole = heads.join(found, "sample_id", "left").select(F.col("sample_id").alias("head"), (F.coalesce("links", F.lit(0)) + own).alias("links"))
    return members.join(whole, "head").select("sample_id", F.col("head").alias("class_id"), "links")


def best_in_blocks(left: DataFrame, right: DataFrame, k: int, metric: str = "cosine", apart: str = "sample_id", farthest: bool = False, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(sample_id, nn_rank, nn_id, sim): for each row of ``left`` its k closest (or farthest) rows of ``right`` that differ
    from it in the column ``apart``; ties to smaller ids. A block pair hands on k rows a row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                a, b = batch.column("a_rows")[i].values, batch.column("b_rows")[i].values
                (ia, va), (ib, vb) = _unpack(a), _unpack(b)
                own, other = (x.field(apart).to_numpy(zero_copy_only=False) for x in (a, b))
                by_id = np.argsort(ib, kind="stable")
                ib, vb, other = ib[by_id], vb[by_id], other[by_id]
                for part in _slices(len(ia)):
                    s = _closeness(va[part], vb, metric)
                    rank = s.copy() if farthest else -s
                    rank[own[part][:, None] == other[None, :]] = np.inf
                    wide = min(k, rank.shape[1])
                    kth = np.partition(rank, wide - 1, axis=1)[:, wide - 1 :][:, :1]
                    r, c = np.nonzero((rank <= kth) & (rank < np.inf))  # the k best and all ties with the last
                    order = np.lexsort((c, rank[r, c], r))
                    r, c = r[order], c[order]
                    keep = np.arange(len(r)) - np.searchsorted(r, r) < k
                    r, c = r[keep], c[keep]
                    yield pa.RecordBatch.from_arrays([pa.array(ia[part][r]), pa.array(ib[c]), pa.array(s[r, c])], ["sample_id", "nn_id", "sim"])

    met = block_pairs(left, right, block_rows).mapInArrow(run, "sample_id bigint, nn_id bigint, sim double")
    return _ranked(met, k, F.asc("sim") if farthest else F.desc("sim"))


def similar_in_blocks(left: DataFrame, right: DataFrame, min_sim: float, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(a, b, sim): rows of ``left`` and of ``right`` with a cosine of at least ``min_sim``, from all pairs of blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                (ia, va), (ib, vb) = _unpack(batch.column("a_rows")[i].values), _unpack(batch.column("b_rows")[i].values)
                ub = units(vb).T
                for part in _slices(len(ia)):
                    sims = units(va[part]) @ ub
                    r, c = np.nonzero(sims >= min_sim - 5e-7)
                    sim = round6(sims[r, c])
                    keep = sim >= min_sim
                    yield pa.RecordBatch.from_arrays([pa.array(ia[part][r[keep]]), pa.array(ib[c[keep]]), pa.array(sim[keep])], ["a", "b", "sim"])

    return block_pairs(left, right, block_rows).mapInArrow(run, "a bigint, b bigint, sim double")


def _ranked(met: DataFrame, k: int, order: Column) -> DataFrame:
    ranked = met.withColumn("nn_rank", F.row_number().over(Window.partitionBy("sample_id").orderBy(order, "nn_id")))
    return ranked.where(F.col("nn_rank") <= k).select("sample_id", "nn_rank", "nn_id", "sim")


# Classes of equal vectors


def collapse(df: DataFrame, order: Column | None = None) -> tuple[DataFrame, DataFrame]:
    """One row (sample_id, vec) for each distinct vector, its first row by ``order`` (else the smallest id), and all rows
    as members (sample_id, head). Vectors are told apart by 128 bits of hashes."""
    first = F.struct((F.lit(0) if order is None else order).alias("o"), F.col("sample_id").alias("i"))
    keyed = df.select("sample_id", first.alias("f"), F.xxhash64("vec").alias("h"), F.xxhash64(F.lit(1), F.reverse("vec")).alias("g"))
    least = keyed.groupBy("h", "g").agg(F.min("f").alias("m")).select("h", "g", F.col("m.i").alias("head"))
    members = checkpoint(keyed.join(least, ["h", "g"]).select("sample_id", "head"))
    heads = df.select("sample_id", "vec").join(members.where("sample_id = head").select("sample_id"), "sample_id", "left_semi")
    return checkpoint(heads), members


# Pairs by bands of signs


def plan_bands(n: int, min_sim: float, recall: float = RECALL) -> tuple[int, int]:
    """Bits and number of bands. Bits grow with the logarithm of the rows, so that a key has few of them whatever their
    number; at cosine c a bit agrees with probability 1 - acos(c)/pi, which gives the bands that the recall needs."""
    bits = max(4, min(48, round(math.log2(max(n, 2) / 8))))
    agree = (1 - math.acos(min(1.0, max(-1.0, min_sim))) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(1 - recall) / math.log(max(1e-12, 1 - min(agree, 1 - 1e-9)))))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def _signs(m: np.ndarray, bits: int, seed: int) -> np.ndarray:
    planes = np.random.default_rng((seed, m.shape[1], bits)).standard_normal((m.shape[1], bits))
    return m @ planes > 0


def _words(m: np.ndarray, bits: int, bands: int, seed: int) -> np.ndarray:
    """The signs of each vector in each band, as a number."""
    sign = _signs(m, bits * bands, seed).reshape(len(m), bands, bits)
    return (sign * (np.uint64(1) << np.arange(bits, dtype=np.uint64))).sum(2, dtype=np.uint64)


def band_keys(df: DataFrame, bits: int, bands: int, seed: int = 42, bucket_rows: int = BUCKET_ROWS, levels: int = LEVELS) -> DataFrame:
    """(sample_id, key): the band keys of each vector. A key of more than ``bucket_rows`` rows is split by further bits,
    in as many draws of them as keep the pairs at 0.9 with the planned recall; up to ``levels`` times."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            m = matrix(batch.column("vec"))
            if not m.size:
                continue
            key = _mix(_words(m, bits, bands, seed) + (np.arange(bands, dtype=np.uint64) << np.uint64(48))).view(np.int64)
            keys = pa.ListArray.from_arrays(pa.array(np.arange(len(m) + 1) * bands, pa.int32()), pa.array(key.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column("sample_id"), keys], ["sample_id", "keys"])

    keyed = checkpoint(df.select("sample_id", "vec").mapInArrow(run, "sample_id bigint, keys array<bigint>").select("sample_id", F.explode("keys").alias("key")))
    draws = plan_bands(8 << SPLIT_BITS, 0.9)[1]
    for level in range(levels):
        hot = keyed.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > bucket_rows).select("key")
        if hot.isEmpty():
            break

        def split(batches: Iterator[pa.RecordBatch], level: int = level) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                m = matrix(batch.column("vec"))
                if not m.size:
                    continue
                sign, old = _signs(m, POOL_BITS, seed + 1), batch.column("key").to_numpy(zero_copy_only=False).view(np.uint64)
                parts = []
                for j in range(draws):
                    at = np.random.default_rng((seed, level, j)).choice(POOL_BITS, SPLIT_BITS, replace=False)
                    word = (sign[:, at] * (1 << np.arange(SPLIT_BITS))).sum(1).astype(np.uint64)
                    parts.append(_mix(old ^ _mix(word + np.uint64((level * draws + j + 1) << 8))).view(np.int64))
                ids = np.tile(batch.column("sample_id").to_numpy(zero_copy_only=False), draws)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.concatenate(parts))], ["sample_id", "key"])

        inside = keyed.join(hot, "key", "left_semi").join(df.select("sample_id", "vec"), "sample_id").select("sample_id", "key", "vec")
        keyed = checkpoint(keyed.join(hot, "key", "left_anti").select("sample_id", "key").union(inside.mapInArrow(split, "sample_id bigint, key bigint")))
    return keyed


def verified(pairs: DataFrame, left: DataFrame, right: DataFrame, min_sim: float) -> DataFrame:
    """(a, b, sim): the pairs whose vectors, of ``left`` for a and of ``right`` for b, have a cosine of ``min_sim``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sim = round6((units(matrix(batch.column("va"))) * units(matrix(batch.column("vb")))).sum(1))
            keep = pa.array(sim >= min_sim)
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(keep), batch.column("b").filter(keep), pa.array(sim).filter(keep)], ["a", "b", "sim"])

    own = lambda df, k, v: df.select(F.col("sample_id").alias(k), F.col("vec").alias(v))
    return pairs.join(own(left, "a", "va"), "a").join(own(right, "b", "vb"), "b").select("a", "b", "va", "vb").mapInArrow(run, "a bigint, b bigint, sim double")


def sim_pairs(df: DataFrame, min_sim: float = 0.9, method: str = "exact", block_rows: int = BLOCK_ROWS, bits: int | None = None, bands: int | None = None, seed: int = 42, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """(a, b, sim), a < b: pairs of rows of ``df`` (sample_id, vec) with a cosine of at least ``min_sim``.

    ``exact`` compares all blocks by matrix products. ``lsh`` compares rows that agree on a band of hyperplane signs. Both
    verify. Rows with equal vectors are one class for ``lsh``: pairs are between the classes' smallest ids, and each
    other member is linked to its class's smallest id alone, so a group of copies costs as many pairs as it has rows.
    """
    if method == "exact":
        return _exact_pairs(df, min_sim, block_rows)
    heads, members = collapse(df)
    planned = plan_bands(heads.count(), min_sim)
    keys = band_keys(heads, bits or planned[0], bands or planned[1], seed, bucket_rows)
    x, y = keys.alias("x"), keys.alias("y")
    met = x.join(y, (F.col("x.key") == F.col("y.key")) & (F.col("x.sample_id") < F.col("y.sample_id"))).select(F.col("x.sample_id").alias("a"), F.col("y.sample_id").alias("b")).distinct()
    star = members.where("sample_id <> head").select(F.col("head").alias("a"), F.col("sample_id").alias("b"))
    return verified(met.union(star), df, df, min_sim)


# Neighbours by a forest of sorted signatures


def _forest(heads: DataFrame, k: int, metric: str, trees: int, window: int, seed: int) -> DataFrame:
    """(sample_id, nn_id, sim): candidates for the k closest distinct vectors.

    In each tree the rows are sorted by their signs against one sequence of hyperplanes, so that rows of a long common
    prefix stand together, and each window of rows is compared with itself and the next. A dense region is many windows,
    never one large bucket; a table of one window is compared whole.
    """

    def tag(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            m = matrix(batch.column("vec"))
            if not m.size:
                continue
            for tree in range(trees):
                word = (_signs(m, 62, seed + tree) * (np.int64(1) << np.arange(61, -1, -1))).sum(1)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(m), tree, np.int32)), pa.array(word), batch.column("sample_id"), batch.column("vec")], ["tree", "word", "sample_id", "vec"])

    def top(s: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        wide = min(k + 16, s.shape[1])
        at = np.argpartition(-s, wide - 1, axis=1)[:, :wide]
        order = np.lexsort((ids[at], -np.take_along_axis(s, at, 1)), axis=1)[:, :k]
        at = np.take_along_axis(at, order, 1)
        return np.take_along_axis(s, at, 1), ids[at]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def windows() -> Iterator[list[np.ndarray]]:
            held: list[list[np.ndarray]] = []
            rows = 0
            for batch in batches:
                for at in range(0, batch.num_rows, window):
                    part = batch.slice(at, window)
                    held.append([part.column("sample_id").to_numpy(zero_copy_only=False), matrix(part.column("vec")), part.column("tree").to_numpy(zero_copy_only=False)])
                    rows += part.num_rows
                    if rows >= window:
                        whole = [np.concatenate(c) for c in zip(*held, strict=True)]
                        yield [c[:window] for c in whole]
                        held, rows = [[c[window:] for c in whole]], rows - window
            if rows:
                yield [np.concatenate(c) for c in zip(*held, strict=True)]

        def compared(a: list[np.ndarray], b: list[np.ndarray]) -> np.ndarray:
            """Closeness of two windows' rows; rows of different trees are not compared, so that no row is met twice."""
            s = _closeness(a[1], b[1], metric)
            s[(a[0][:, None] == b[0][None, :]) | (a[2][:, None] != b[2][None, :])] = -np.inf
            return s

        def out(ids: np.ndarray, s: np.ndarray, found: np.ndarray) -> pa.RecordBatch:
            row, col = np.nonzero(s > -np.inf)
            return pa.RecordBatch.from_arrays([pa.array(ids[row]), pa.array(found[row, col]), pa.array(s[row, col])], ["sample_id", "nn_id", "sim"])

        before = None
        for now in windows():
            yield out(now[0], *top(compared(now, now), now[0]))
            if before is not None:
                across = compared(before, now)
                yield out(before[0], *top(across, now[0]))
                yield out(now[0], *top(across.T.copy(), before[0]))
            before = now

    rows = heads.count() * trees
    cores = heads.sparkSession.sparkContext.defaultParallelism
    parts = max(-(-rows // MOST_ROWS), min(cores, -(-rows // max(PART_ROWS, 8 * window))), 1)
    tagged = heads.select("sample_id", "vec").mapInArrow(tag, "tree int, word bigint, sample_id bigint, vec array<float>")
    dealt = tagged.repartitionByRange(parts, "tree", "word", "sample_id").sortWithinPartitions("tree", "word", "sample_id")
    return dealt.mapInArrow(compare, "sample_id bigint, nn_id bigint, sim double")


def knn(df: DataFrame, k: int, metric: str = "cosine", method: str = "forest", block_rows: int = BLOCK_ROWS, trees: int = TREES, window: int = WINDOW, seed: int = 42, met: DataFrame | None = None) -> DataFrame:
    """(sample_id, nn_rank, nn_id, sim): the k nearest other rows; sim is the cosine or the negative Euclid distance, to
    nine decimals, with ties to smaller ids. Every row gets k neighbours if the table has more than k rows.

    ``exact`` compares all pairs of blocks, whatever the number of rows; ``met``, where several measures share one, is the
    meeting of the rows of ``df`` for these k. ``forest`` compares windows of sorted signatures,
    in time that grows with the rows; a table of at most one window is compared whole. Equal vectors are one class
    there, of which the first k + 1 ids stand as neighbours.
    """
    if method == "exact" and met is not None:
        return _ranked(met.where("nn_id is not null").select("sample_id", "nn_id", "sim"), k, F.desc("sim"))
    if method == "exact":
        return best_in_blocks(df.select("sample_id", "vec"), df.select("sample_id", "vec"), k, metric, block_rows=block_rows)
    heads, members = collapse(df)
    near = _ranked(_forest(heads, k, metric, trees, window, seed).groupBy("sample_id", "nn_id").agg(F.max("sim").alias("sim")), k, F.desc("sim"))
    zero = F.forall("vec", lambda x: x == 0)
    own_sim = F.when(zero & F.lit(metric == "cosine"), 0.0).otherwise(1.0 if metric == "cosine" else 0.0)
    classes = near.select(F.col("sample_id").alias("p"), F.col("nn_id").alias("q"), "sim").union(heads.select(F.col("sample_id").alias("p"), F.col("sample_id").alias("q"), own_sim.alias("sim")))
    first = F.row_number().over(Window.partitionBy("head").orderBy("sample_id"))  # Spark limits each part before it moves
    some = members.withColumn("n", first).where(F.col("n") <= k + 1).select(F.col("head").alias("q"), F.col("sample_id").alias("nn_id"))
    wanted = _ranked(classes.join(some, "q").select(F.col("p").alias("sample_id"), "nn_id", "sim"), k + 1, F.desc("sim")).select(F.col("sample_id").alias("head"), "nn_id", "sim")
    met = members.join(wanted, "head").where("sample_id <> nn_id").select("sample_id", "nn_id", "sim")
    return _ranked(met, k, F.desc("sim"))


def recall(found: DataFrame, exact: DataFrame, keys: list[str]) -> DataFrame:
    """Share of the exact rows that were found, and share of the found ones that are exact."""
    hit = found.select(*keys).join(exact.select(*keys), keys, "left_semi").agg(F.count("*").alias("hit"))
    counts = hit.crossJoin(found.agg(F.count("*").alias("n_found"))).crossJoin(exact.agg(F.count("*").alias("n_exact")))  # one row each
    return counts.select("n_found", "n_exact", (F.col("hit") / F.col("n_exact")).alias("recall"), (F.col("hit") / F.col("n_found")).alias("precision"))


def clusterability(neighbours: DataFrame, truth: DataFrame, class_col: str = "y") -> DataFrame:
    """Rows, and the share whose neighbours all have the row's own class."""
    own = truth.select("sample_id", F.col(class_col).alias("c"))
    other = truth.select(F.col("sample_id").alias("nn_id"), F.col(class_col).alias("cn"))
    per_row = neighbours.join(own, "sample_id").join(other, "nn_id").groupBy("sample_id").agg(F.bool_and(F.col("c") == F.col("cn")).alias("agree"))
    return per_row.agg(F.count("*").alias("n"), F.round(F.avg(F.col("agree").cast("int")), 6).alias("share"))
