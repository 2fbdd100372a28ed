"""Mixing sources to target weights by pivotal dependent rounding.

A document of a source with target T and size S should appear T/S times: the whole part is certain, the rest is a
probability. Pivotal rounding takes two fractional documents at a time and moves mass between them, in words, until one
of them is 0 or 1; the move is random and keeps both expectations, and it keeps the pair's expected words exactly. What
a block of a source leaves open is one document, which goes up a reduction tree: blocks of blocks, until a source is one
block; the documents that sources leave open are paired last. Hence the words taken from a source miss its target by less
than one document, and so do those of the whole mix. Blocks and their order depend on
ids and texts alone, so reruns agree.
"""

from __future__ import annotations


import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.llm.common import checkpoint

#: Documents a block of the first level should hold, and blocks a block of the next level joins.
BLOCK_ROWS, FAN_IN = 2_000, 256


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def source_targets(sizes: list[tuple[str | None, int]], weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, most: float = 2.0) -> dict[str | None, float]:
    """Target words by source. Sources in code point order, null last, get the weights in turn; what lies above ``most``
    times a source's size is dealt again by weight among the sources below that, until none is above."""
    order = sorted(sizes, key=lambda s: (s[0] is None, s[0] or ""))
    weight = {s: weights[i % len(weights)] for i, (s, _) in enumerate(order)}
    cap = {s: most * n for s, n in order}
    rest, free, target = share * sum(n for _, n in order), dict(cap), {}
    while free:
        unit = rest / sum(weight[s] for s in free)
        full = [s for s in free if unit * weight[s] >= free[s]]
        if not full:
            return target | {s: unit * weight[s] for s in free}
        for s in full:
            target[s] = free.pop(s)
            rest -= target[s]
    return target


def _uniform(a: int, b: int, seed: int) -> float:
    """A number of [0, 1) from two ids."""
    x = (a * 0x9E3779B97F4A7C15 + b * 0xC2B2AE3D27D4EB4F + seed * 0x165667B19E3779F9) & 0xFFFFFFFFFFFFFFFF
    x = ((x ^ (x >> 29)) * 0xBF58476D1CE4E5B9) & 0xFFFFFFFFFFFFFFFF
    x = ((x ^ (x >> 32)) * 0x94D049BB133111EB) & 0xFFFFFFFFFFFFFFFF
    return ((x ^ (x >> 29)) >> 11) / 2.0**53


def pivot(p: np.ndarray, size: np.ndarray, key: np.ndarray, seed: int) -> np.ndarray:
    """Probabilities after pivotal rounding in the given order: all but one at most are 0 or 1."""
    p = p.astype(float).tolist()
    size, key = size.tolist(), key.tolist()
    i = -1  # the fractional document carried along
    for j in range(len(p)):
        if not 0.0 < p[j] < 1.0:
            continue
        if i < 0:
            i = j
            continue
        a, b = size[i], size[j]
        up, down = min((1 - p[i]) * a, p[j] * b), min(p[i] * a, (1 - p[j]) * b)  # words that may move to i, from i
        if _uniform(key[i], key[j], seed) * (up + down) < down:
            gain_full, gain_empty = up == (1 - p[i]) * a, up == p[j] * b
            p[i], p[j] = 1.0 if gain_full else p[i] + up / a, 0.0 if gain_empty else p[j] - up / b
        else:
            lose_empty, lose_full = down == p[i] * a, down == (1 - p[j]) * b
            p[i], p[j] = 0.0 if lose_empty else p[i] - down / a, 1.0 if lose_full else p[j] + down / b
        if not 0.0 < p[i] < 1.0:
            i = j if 0.0 < p[j] < 1.0 else -1
    return np.array(p)


def _round_blocks(df: DataFrame, by: tuple[str, ...], last: bool, seed: int) -> DataFrame:
    """One level of the tree: ``p`` rounded inside each group; the last level also decides what is left open."""

    def run(rows: pa.Table) -> pa.Table:
        key, size = rows.column("key").to_numpy(), rows.column("size").to_numpy()
        order = np.lexsort((size, key, -size))  # long documents first, so that what stays open is short
        p = rows.column("p").to_numpy().copy()
        done = pivot(p[order], size[order], key[order], seed)
        if last:
            done = [x if x in (0.0, 1.0) else float(_uniform(k, 0, seed + 1) < x) for x, k in zip(done.tolist(), key[order].tolist(), strict=True)]
        p[order] = done
        return rows.set_column(rows.schema.get_field_index("p"), "p", pa.array(p, pa.float64()))

    return df.groupBy(*by).applyInArrow(run, df.schema)


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, most: float = 2.0, seed: int = 42, block_rows: int = BLOCK_ROWS, fan_in: int = FAN_IN) -> DataFrame:
    """(id, source, size, source_size, target, copies), a row for each row of ``docs``.

    ``copies`` is a whole number of at most ``most`` rounded up. A null text has size 0 and gets no copies, as has every
    empty text. Rows that repeat an id are documents of their own; a null source is a source. Blocks follow from id and
    text, so null or repeated ids are spread like others. The sources' sizes are one row a source on the driver. An
    empty table gives an empty result.
    """
    size = word_count(F.col(text_col))
    rows = checkpoint(docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), size.alias("size"), F.xxhash64(id_col, text_col, F.lit(seed)).alias("key")))
    sizes = rows.groupBy("source").agg(F.sum("size").alias("n"), F.count("*").alias("rows")).collect()
    target = source_targets([(r["source"], r["n"]) for r in sizes], weights, share, most)
    blocks = {r["source"]: max(1, -(-r["rows"] // block_rows)) for r in sizes}
    facts = [(r["source"], r["n"], float(target[r["source"]]), blocks[r["source"]]) for r in sizes]
    per_source = F.broadcast(rows.sparkSession.createDataFrame(facts, "_source string, source_size long, target double, blocks long"))
    dealt = rows.join(per_source, F.col("source").eqNullSafe(F.col("_source")), "left").drop("_source")
    times = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    dealt = dealt.withColumn("whole", F.when(F.col("size") > 0, F.floor(times)).otherwise(0)).withColumn("p", F.when(F.col("size") > 0, times - F.floor(times)).otherwise(0.0))
    level = dealt.withColumn("block", F.pmod("key", "blocks"))
    most_blocks, parts = max(blocks.values(), default=1), []
    settled = F.col("p").isin(0.0, 1.0)
    while True:
        level = checkpoint(_round_blocks(level, ("source", "block"), False, seed))
        parts.append(level.where(settled))
        if most_blocks == 1:
            break
        most_blocks = -(-most_blocks // fan_in)
        level = level.where(~settled).withColumn("block", F.floor(F.col("block") / fan_in))
    open_ = level.where(~settled).withColumn("block", F.lit(0).cast(level.schema["block"].dataType))  # one row a source at most
    parts.append(checkpoint(_round_blocks(open_, ("block",), True, seed)))
    done = parts[0]
    for part in parts[1:]:
        done = done.union(part)
    return done.select(F.col("id").alias(id_col), F.col("source").alias(source_col), "size", "source_size", "target", (F.col("whole") + F.col("p").cast("long")).alias("copies"))


def mix_digest(docs: DataFrame) -> DataFrame:
    mixed = mix(docs)
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"), "copies", "source")


def mixed_documents(docs: DataFrame) -> DataFrame:
    """The rows of the mix with the columns of ``docs``: a document taken twice is two rows, one not taken is none.

    Rows that agree in id, source and size are one to the mix; their copies are dealt in the order of the text's hash.
    """
    whole = lambda c: F.coalesce(F.concat(F.lit("+"), F.col(c).cast("string")), F.lit("-"))
    key = lambda size, doc, source: F.concat_ws("|", size, whole(doc), whole(source)).alias("key")  # noqa: E731  one column, so that the texts move once
    copies = mix(docs).groupBy(key(F.col("size"), "doc_id", "source")).agg(F.sort_array(F.collect_list("copies"), asc=False).alias("copies"))
    own = docs.select(F.struct(*(f"`{c}`" for c in docs.columns)).alias("d"))  # apart from the names used here
    nth = F.row_number().over(Window.partitionBy("key").orderBy(F.xxhash64("d.text")))
    joined = own.withColumn("key", key(word_count(F.col("d.text")), "d.doc_id", "d.source")).withColumn("nth", nth).join(copies, "key")
    times = joined.withColumn("n", F.element_at("copies", F.col("nth")).cast("int")).where("n > 0")
    return times.select("d", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("i")).select("d.*")
