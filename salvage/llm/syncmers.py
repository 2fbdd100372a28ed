"""Document fingerprints from closed syncmers.

A k-mer of a text's UTF-8 bytes is a closed syncmer if the least of the hashes of its inner s-mers is the first or the
last one. Whether it is one depends on the k-mer alone, so an edit elsewhere never changes it: the anchors are free of
context, and their positions line up two texts. The fingerprint is the bottom sketch of the anchors' hashes, each with
its position. Its likeness to another is the share of anchors that both have at matching positions: an anchor counts
if its shift between the texts is that of most common anchors, give or take an eighth of the texts. With 48 hashes the
estimate of a share p has a standard error of sqrt(p (1 - p) / 48), 0.07 at most.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.llm.common import blocks, short_batches

#: Bytes of a k-mer and of an inner s-mer (fixed at 8, one machine word), hashes in a fingerprint, bytes hashed at once.
K, S, SKETCH, CHUNK = 16, 8, 48, 1 << 20
#: Bytes of text in a range of documents, rows sampled for each cut between ranges, rows of the first sample.
RANGE_BYTES, SAMPLE, FIRST_SAMPLE = 64 << 20, 8, 20_000
#: Shift of an anchor that passes for none: bytes, and the share of the texts.
SHIFT, SHARE = 64, 0.125


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def _chunk_anchors(b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    v = b.astype(np.uint64)
    for step in (1, 2, 4):  # words of 2, 4 and 8 bytes
        v = (v[:-step] << np.uint64(8 * step)) | v[step:]
    h = _mix(v)
    last = K - S
    low, width = h, 1
    while 2 * width <= last + 1:  # the least of 2, 4, 8 neighbours
        low, width = np.minimum(low[:-width], low[width:]), 2 * width
    if width < last + 1:
        low = np.minimum(low[: len(h) - last], low[last + 1 - width :])
    at = np.flatnonzero((low == h[:-last]) | (low == h[last:]))
    return at, _mix(h[at] * np.uint64(0x9E3779B97F4A7C15) + h[at + last])


def anchors(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Byte positions and hashes (uint64) of the closed syncmers of a text."""
    b = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    found = [(a + at, h) for a in range(0, max(0, len(b) - K + 1), CHUNK) for at, h in [_chunk_anchors(b[a : a + CHUNK + K - 1])]]
    if not found:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    return np.concatenate([x for x, _ in found]), np.concatenate([x for _, x in found])


def sketch(text: str, size: int = SKETCH) -> np.ndarray:
    """Rows (hash, position) of the ``size`` smallest distinct anchor hashes, cut to 32 bits, with their first byte
    positions. A text without anchors has its whole hash, an empty one nothing."""
    at, full = anchors(text)
    hashes, first = np.unique((full >> np.uint64(32)).astype(np.uint32), return_index=True)
    if not len(hashes) and text:
        whole = hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=4).digest()
        return np.array([[int.from_bytes(whole, "big"), 0]], np.uint32)
    return np.stack([hashes[:size], at[first[:size]].astype(np.uint32)], 1)


def likeness(a: np.ndarray, b: np.ndarray, size: int = SKETCH) -> float:
    """Estimated share of anchors that two sketched texts have in common at matching positions; two empty sketches are
    alike."""
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    union = np.union1d(a[:, 0], b[:, 0])[:size]
    common, left, right = np.intersect1d(a[:, 0], b[:, 0], assume_unique=True, return_indices=True)
    inside = common <= union[-1]
    if not inside.any():
        return 0.0
    x, y = a[left[inside], 1].astype(np.int64), b[right[inside], 1].astype(np.int64)
    shift = y - x
    aligned = np.abs(shift - np.median(shift)) <= SHIFT + SHARE * max(x.max(), y.max())
    return float(aligned.sum() / len(union))


def match_positions(a: str, b: str) -> list[tuple[int, int]]:
    """Byte positions in ``a`` and ``b`` of anchors that occur once in each: the places where they can be aligned."""
    (pa_, ha), (pb, hb) = anchors(a), anchors(b)

    def once(p: np.ndarray, h: np.ndarray) -> dict[int, int]:
        values, first, counts = np.unique(h, return_index=True, return_counts=True)
        return dict(zip(values[counts == 1].tolist(), p[first[counts == 1]].tolist(), strict=True))

    left, right = once(pa_, ha), once(pb, hb)
    return sorted((left[h], right[h]) for h in left.keys() & right.keys())


def _bucket(value: Column, splits: list[tuple], kind: str) -> Column:
    """How many of the ascending ``splits`` are at most ``value``, by binary search in a constant of the plan."""
    if not splits:
        return F.lit(0)
    id_kind = kind.removeprefix("struct<id:").removesuffix(",nh:bigint>")
    text = lambda i: "null" if i is None else "'" + str(i).replace("\\", "\\\\").replace("'", "\\'") + "'"
    rows = ", ".join(f"named_struct('id', cast({text(i)} as {id_kind}), 'nh', {h}L)" for i, h in splits)
    n, table = len(splits), F.expr(f"array({rows})")  # folded to one constant; a parsed JSON text would be read for every row
    steps = [1 << i for i in reversed(range(n.bit_length()))]
    go = lambda at, step: F.when((at + step <= n) & (F.element_at(table, F.least(at + step, F.lit(n))) <= value), at + step).otherwise(at)
    return F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), go)


def _splits(rows: DataFrame, n: int) -> tuple[list[tuple], int]:
    """Cuts between ranges of (id, nh) of about RANGE_BYTES of text, and the number of ranges, from a sample by hash; at
    least as many ranges as the session has shuffle partitions."""
    parts, size, drawn = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), FIRST_SAMPLE, []
    while True:
        every = max(1, n // size)
        chosen = rows.where(F.pmod(F.xxhash64("id", "nh", F.lit(3)), F.lit(every)) == 0)
        drawn = chosen.select("id", "nh", F.octet_length("text").alias("bytes")).collect()
        parts = max(parts, -(-sum(r["bytes"] for r in drawn) * n // max(1, len(drawn)) // RANGE_BYTES))
        if every == 1 or size >= SAMPLE * parts:
            break
        size = SAMPLE * parts
    marks = sorted({(r["id"] is not None, r["id"], r["nh"]) for r in drawn}, key=lambda m: (m[0], m[1] if m[0] else 0, m[2]))
    cuts = sorted({len(marks) * i // parts for i in range(1, parts)} - {0})
    return [marks[i][1:] for i in cuts if i < len(marks)], parts


def with_successors(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows (bucket, guest, id, text), dealt and sorted so that each row's next document follows it in its bucket.

    The order is descending id (null last), ties by the text's hash; after the last comes the first. Buckets are ranges
    of ids and, where many rows share an id or have none, of text hashes; their number grows with the bytes of text. The
    first row of a bucket is also sent, as a guest, to the end of the bucket before it. So the texts move once, and no
    task sees more than its range.
    """
    spark, kind = docs.sparkSession, docs.schema[id_col].dataType.simpleString()
    text = F.coalesce(text_col, F.lit(""))
    rows = docs.select(F.col(id_col).alias("id"), F.bitwise_not(F.xxhash64(text)).alias("nh"), text.alias("text"))
    splits, parts = _splits(rows, docs.count())
    place = F.struct("id", "nh")
    rows = rows.withColumn("bucket", (F.lit(len(splits)) - _bucket(place, splits, f"struct<id:{kind},nh:bigint>")).cast("int"))
    firsts = sorted((r["bucket"], r["f"]["id"], r["f"]["nh"]) for r in rows.groupBy("bucket").agg(F.max(place).alias("f")).collect())
    before = [(b, firsts[i - 1][0], fid, nh) for i, (b, fid, nh) in enumerate(firsts)]  # one row a bucket
    seats = F.broadcast(spark.createDataFrame(before, f"bucket int, host int, fid {kind}, fnh bigint"))
    first = F.col("id").eqNullSafe(F.col("fid")) & (F.col("nh") == F.col("fnh"))
    seat = lambda b, guest: F.struct(F.col(b).alias("bucket"), F.lit(guest).alias("guest"))
    sent = rows.join(seats, "bucket").withColumn("seat", F.explode(F.when(first, F.array(seat("bucket", False), seat("host", True))).otherwise(F.array(seat("bucket", False)))))
    sent = sent.select("seat.bucket", "seat.guest", "id", "nh", "text")
    return sent.repartition(parts, "bucket").sortWithinPartitions("bucket", "guest", F.desc_nulls_last("id"), F.desc("nh")).select("bucket", "guest", "id", "text")


def edited(text: str, following: str) -> str:
    """The last half of the code points (rounded down) replaced by as many first ones of the following text."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def fingerprint_digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for each document: fingerprints of the text and of its edited text, and their likenesses.

    A null text is an empty one; repeated rows and equal ids are documents of their own; a single document follows
    itself; an empty table gives none; other columns are not read. A task holds two texts at a time, whatever their
    number. A fingerprint is eight hex digits of hash and eight of position for each of its anchors.
    """
    names = [id_col, "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    code = lambda s: s.astype(">u4").tobytes().hex()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # bucket, id, text, sketch of the row before
        for batch in blocks(batches):
            out: list[list] = [[] for _ in names]
            kind = batch.schema.field("id").type
            for bucket, guest, doc, text in zip(*(batch.column(c).to_pylist() for c in ("bucket", "guest", "id", "text")), strict=True):
                if guest and held is None:
                    continue  # a repeated guest
                mark = sketch(text)
                if held is not None and held[0] == bucket:
                    changed = edited(held[2], text)
                    other = sketch(changed)
                    row = (held[1], len(held[2]), hashlib.sha256(changed.encode("utf-8", "surrogatepass")).hexdigest(), code(held[3]), code(other), likeness(held[3], other), likeness(held[3], mark))
                    for column, value in zip(out, row, strict=True):
                        column.append(value)
                held = None if guest else (bucket, doc, text, mark)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], kind), pa.array(out[1], pa.int64()), *(pa.array(x, pa.string()) for x in out[2:5]), *(pa.array(x, pa.float64()) for x in out[5:])], names)

    if docs.isEmpty():
        return docs.sparkSession.createDataFrame([], f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
    kind = docs.schema[id_col].dataType.simpleString()
    return short_batches(with_successors(docs, id_col, text_col)).mapInArrow(run, f"`{id_col}` {kind}, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
