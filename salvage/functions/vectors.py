"""Vector expressions, and the encoder that turns texts into unit vectors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Length of a hashed text vector, and groups whose sums a task holds before it hands them on.
DIMENSIONS, HELD = 256, 4096


def dot(a: Column, b: Column) -> Column:
    """Inner product as a built-in expression; the products are of doubles."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Cosine; 0 if either vector is zero."""
    size = norm(a) * norm(b)
    return F.when(size > 0, dot(a, b) / size).otherwise(0.0)


def euclid(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x))


def unit(a: Column) -> Column:
    size = norm(a)
    return F.transform(a, lambda x: F.when(size > 0, x.cast("double") / size).otherwise(0.0))


def sum_vectors(df: DataFrame, keys: list[str], vec_col: str = "vec") -> DataFrame:
    """(keys, n, sums): the number and the component sums of the vectors of each group.

    Each task adds up its own rows by group, so one row a group and task moves and its parts are added up. A task holds at most HELD groups at a time.
    """
    kinds = ", ".join(f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keys)

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, list] = {}

        def flush() -> pa.RecordBatch:
            columns = [pa.array([k[i] for k in held], arrow[i]) for i in range(len(keys))]
            out = [*columns, pa.array([v[0] for v in held.values()], pa.int64()), pa.array([v[1].tolist() for v in held.values()], pa.list_(pa.float64()))]
            held.clear()
            return pa.RecordBatch.from_arrays(out, [*keys, "n", "sums"])

        arrow = None
        for batch in batches:
            arrow = [batch.schema.field(i).type for i in range(len(keys))]
            flat = batch.column(len(keys)).flatten().to_numpy(zero_copy_only=False)
            x = flat.reshape(batch.num_rows, -1).astype(float) if len(flat) else np.zeros((batch.num_rows, 0))
            names = list(zip(*(batch.column(i).to_pylist() for i in range(len(keys))), strict=True))
            for name, row in zip(names, x, strict=True):
                if (own := held.get(name)) is None:
                    held[name] = [1, row.copy()]
                else:
                    own[0] += 1
                    own[1] += row
                if len(held) > HELD:
                    yield flush()
        if held:
            yield flush()

    def whole(rows: pa.Table) -> pa.Table:
        total = np.sum([np.asarray(v, float) for v in rows.column("sums").to_pylist()], 0)
        out = {k: rows.column(k).slice(0, 1) for k in keys}
        return pa.table(out | {"n": pa.array([sum(rows.column("n").to_pylist())], pa.int64()), "sums": pa.array([total.tolist()], pa.list_(pa.float64()))})

    schema = f"{kinds}, n bigint, sums array<double>"
    parts = df.select(*keys, vec_col).mapInArrow(part, schema)
    return parts.groupBy(*keys).applyInArrow(whole, schema)


def mean_vectors(df: DataFrame, keys: list[str], vec_col: str = "vec") -> DataFrame:
    """(keys, mean): the mean vector of each group; no group is held in one place."""
    return sum_vectors(df, keys, vec_col).select(*keys, F.transform("sums", lambda x: x / F.col("n")).alias("mean"))


def _hash(grams: np.ndarray) -> np.ndarray:
    x = grams * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def char_vector(text: str | None, dim: int = DIMENSIONS, n: int = 3) -> np.ndarray:
    """Signed hashing of character n-grams with weight 1 + ln(tf), to unit length; a zero vector if there is none."""
    vec = np.zeros(dim)
    codes = np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    if len(codes) < n:
        return vec
    grams = np.zeros(len(codes) - n + 1, np.uint64)
    for i in range(n):
        grams = (grams << np.uint64(21)) | codes[i : len(codes) - n + 1 + i]
    grams.sort()
    first = np.flatnonzero(np.concatenate(([True], grams[1:] != grams[:-1])))
    tf = np.diff(np.append(first, len(grams)))
    h = _hash(grams[first])
    vec = np.bincount((h % np.uint64(dim)).astype(np.int64), np.where(h >> np.uint64(63), -1.0, 1.0) * (1 + np.log(tf)), dim)
    size = np.linalg.norm(vec)
    return vec / size if size else vec


def word_vector(text: str | None, dim: int = DIMENSIONS, n: int = 1) -> np.ndarray:
    """As char_vector, over word n-grams."""
    words = (text or "").lower().split()
    vec = np.zeros(dim)
    if len(words) < n:
        return vec
    tally: dict[str, int] = {}
    for i in range(len(words) - n + 1):
        gram = " ".join(words[i : i + n])
        tally[gram] = tally.get(gram, 0) + 1
    import zlib

    for gram, tf in tally.items():
        h = int(_hash(np.array([zlib.crc32(gram.encode("utf-8", "surrogatepass"))], np.uint64))[0])
        vec[h % dim] += (-1.0 if h >> 63 else 1.0) * (1 + np.log(tf))
    size = np.linalg.norm(vec)
    return vec / size if size else vec


def encode(df: DataFrame, id_col: str, text_col: str, kind: str = "char3", dim: int = DIMENSIONS) -> DataFrame:
    """(sample_id, vec): unit vectors of texts; kind is char3, word1 or word2."""
    make = {"char3": char_vector, "word1": word_vector, "word2": lambda t, d: word_vector(t, d, 2)}[kind]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                rows = np.array([make(t, dim) for t in part.column(1).to_pylist()], np.float32)
                vec = pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1) * dim, pa.int32()), pa.array(rows.ravel()))
                yield pa.RecordBatch.from_arrays([part.column(0), vec], ["sample_id", "vec"])

    return df.select(F.col(id_col).cast("bigint"), text_col).mapInArrow(run, "sample_id bigint, vec array<float>")
