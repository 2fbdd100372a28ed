"""Sharding by a Feistel permutation of global row numbers.

Rows get the numbers 0..n-1 of one total order. A keyed Feistel network permutes the smallest even-bit domain that
holds n, and cycle walking (permute again while the value is n or more) restricts it to 0..n-1. The permuted number p
gives shard ``p mod shards`` and slot ``p div shards``: counts differ by one row at most, slots have no gaps, and both
directions are computable from the row number alone, without a table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.llm.common import checkpoint

_ROW_BITS = 33  # monotonically_increasing_id keeps the row inside its partition in these bits


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


class Permutation:
    """Keyed bijection of 0..n-1; ``forward`` and ``backward`` take arrays."""

    def __init__(self, n: int, seed: int = 42, rounds: int = 6):
        self.n = n
        self.half = max(1, ((max(n, 1) - 1).bit_length() + 1) // 2)
        self.keys = _mix(np.arange(1, rounds + 1, dtype=np.uint64) + (np.uint64(seed) << np.uint64(8)))

    def _step(self, x: np.ndarray, keys: np.ndarray) -> np.ndarray:
        half, mask = np.uint64(self.half), np.uint64((1 << self.half) - 1)
        left, right = x >> half, x & mask
        for key in keys:
            left, right = right, left ^ (_mix(right + key) & mask)
        return (right << half) | left  # halves swapped, so the same code with reversed keys inverts it

    def _walk(self, x: np.ndarray, keys: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            y = self._step(np.asarray(x, np.uint64), keys)
            while (out := y >= np.uint64(self.n)).any():
                y[out] = self._step(y[out], keys)
        return y.astype(np.int64)

    def forward(self, x: np.ndarray) -> np.ndarray:
        return self._walk(x, self.keys)

    def backward(self, y: np.ndarray) -> np.ndarray:
        return self._walk(y, self.keys[::-1])


def number_rows(df: DataFrame, order: list[Column], name: str = "row") -> tuple[DataFrame, int]:
    """``df`` with its global row number under ``order``, and the number of rows.

    A range exchange orders the rows, each partition numbers its own, and the partitions' counts (one row each, which is
    all that reaches the driver) give the offsets. Rows that ``order`` can't tell apart are interchangeable.
    """
    spark = df.sparkSession
    placed = checkpoint(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()))
    part = F.shiftright("_at", _ROW_BITS)
    counts = sorted((r["_part"], r["count"]) for r in placed.groupBy(part.alias("_part")).count().collect())
    starts, total = [], 0
    for p, n in counts:
        starts.append((p, total))
        total += n
    offsets = F.broadcast(spark.createDataFrame(starts, "_part long, _start long"))
    numbered = placed.withColumn("_part", part).join(offsets, "_part").withColumn(name, F.col("_start") + F.col("_at").bitwiseAND((1 << _ROW_BITS) - 1))
    return numbered.drop("_part", "_start", "_at"), total


def shard_rows(df: DataFrame, order: list[Column], shards: int = 8, seed: int = 42, rounds: int = 6) -> DataFrame:
    """``df`` with ``row``, ``shard`` and ``slot``.

    Nulls in any column, repeated rows and ties keep a number each; an empty table gives an empty result. Columns of
    ``df`` named row, shard or slot are replaced.
    """
    numbered, n = number_rows(df.drop("row", "shard", "slot"), order)
    permutation = Permutation(n, seed, rounds)
    fields = [f for f in numbered.schema.fields if f.name != "row"]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = permutation.forward(batch.column("row").to_numpy(zero_copy_only=False))
            arrays = [batch.column(f.name) for f in fields] + [batch.column("row"), pa.array((p % shards).astype(np.int32)), pa.array(p // shards)]
            yield pa.RecordBatch.from_arrays(arrays, [*(f.name for f in fields), "row", "shard", "slot"])

    from pyspark.sql.types import IntegerType, LongType, StructField, StructType

    out = StructType([*fields, StructField("row", LongType()), StructField("shard", IntegerType()), StructField("slot", LongType())])
    return numbered.select(*(f"`{f.name}`" for f in fields), "row").mapInArrow(place, out)


def document_shards(docs: DataFrame, shards: int = 8, seed: int = 42) -> DataFrame:
    """The digest of documents: one row each under the law ``rows``; a null text counts as an empty one."""
    text = F.coalesce("text", F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    placed = shard_rows(rows, [F.col("doc_id"), F.col("text_crc32"), F.col("size")], shards, seed)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "row")
