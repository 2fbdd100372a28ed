"""Text models behind the loop: an interface, a cache of replies, and the node that calls a model in batches.

Nothing here reaches a network by itself. A hosted model is one subclass of TextModel away; the rule operators of
``rules`` are the default and need no calls.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from salvage.functions.materialize import checkpoint


class TextModel:
    """``generate`` gets a batch of prompts and returns as many replies; None is a failed call."""

    def generate(self, prompts: list[str], options: dict[str, str]) -> list[str | None]:
        raise NotImplementedError


class EchoModel(TextModel):
    """A deterministic stand-in for tests: replies with the prompt's first sentence."""

    def generate(self, prompts: list[str], options: dict[str, str]) -> list[str | None]:
        return [p.split(".")[0] or None for p in prompts]


class HttpModel(TextModel):
    """Calls ``send(prompt, options)``, a function the user supplies, with retries and a rate cap for each executor."""

    def __init__(self, send, retries: int = 2, per_second: float = 5.0):
        self.send, self.retries, self.gap = send, retries, 1.0 / per_second

    def generate(self, prompts: list[str], options: dict[str, str]) -> list[str | None]:
        replies: list[str | None] = []
        for p in prompts:
            reply = None
            for attempt in range(self.retries + 1):
                time.sleep(self.gap * 2**attempt)
                try:
                    reply = self.send(p, options)
                    break
                except (OSError, ValueError):
                    continue
            replies.append(reply)
        return replies


def call_key(op: str, prompt, options: dict[str, str]):
    """The key of a call in the cache: the same operator, prompt and options give the same reply."""
    return F.md5(F.concat_ws("|", F.lit(op), prompt, F.lit(repr(sorted(options.items())))))


def replay(df: DataFrame, cache: DataFrame, op: str, options: dict[str, str], prompt_col: str = "prompt") -> tuple[DataFrame, DataFrame]:
    """Rows whose call is in ``cache`` (key, reply), with the reply, and rows whose call is not, with the key."""
    keyed = df.withColumn("key", call_key(op, F.col(prompt_col), options))
    return keyed.join(cache, "key"), keyed.join(cache, "key", "left_anti")


def call(misses: DataFrame, model: TextModel, options: dict[str, str], prompt_col: str = "prompt", batch: int = 64) -> DataFrame:
    """(key, reply): one call for each distinct key; append it to the cache before it is read."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            for at in range(0, rows.num_rows, batch):
                part = rows.slice(at, batch)
                replies = model.generate(part.column("prompt").to_pylist(), options)
                yield pa.RecordBatch.from_arrays([part.column("key"), pa.array(replies, pa.string())], ["key", "reply"])

    once = misses.select("key", F.col(prompt_col).alias("prompt")).dropDuplicates(["key"])
    return once.mapInArrow(run, "key string, reply string")


def ask(df: DataFrame, model: TextModel, op: str, cache: str, options: dict[str, str], prompt_col: str = "prompt") -> DataFrame:
    """``df`` with ``reply``: calls that the cache folder holds are replayed, the others are made, once for each distinct
    prompt, and appended to the folder before anything reads them; a failed call (null) is in the cache too."""
    spark, kind = df.sparkSession, "key string, reply string"
    spark.createDataFrame([], kind).write.mode("append").parquet(cache)  # so that there is a table
    keyed = checkpoint(df)
    _, misses = replay(keyed, spark.read.schema(kind).parquet(cache), op, options, prompt_col)
    call(misses, model, options, prompt_col).write.mode("append").parquet(cache)
    hits, _ = replay(keyed, spark.read.schema(kind).parquet(cache), op, options, prompt_col)
    return hits.drop("key")
