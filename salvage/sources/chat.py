"""A data source for chat records in JSON lines, and their export.

A record is ``{"messages": [{"role": ..., "content": ...}, ...]}``. The writer is Spark's own; the reader is a Python
data source with one partition a file, which reports malformed lines as rows with a null list instead of failing.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

MESSAGES = "array<struct<role:string,content:string>>"


class ChatFile(InputPartition):
    def __init__(self, path: str):
        self.path = path


class ChatReader(DataSourceReader):
    """Reads a folder that every executor sees as a local path, file by file."""

    def __init__(self, path: str):
        self.path = path.removeprefix("file://")

    def partitions(self) -> list[InputPartition]:
        import glob

        return [ChatFile(p) for p in sorted(glob.glob(f"{self.path}/*.json*") + glob.glob(f"{self.path}/*.txt"))]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        with open(partition.path, encoding="utf-8") as f:
            for line in f:
                try:
                    messages = [(m["role"], m["content"]) for m in json.loads(line)["messages"]]
                except (ValueError, KeyError, TypeError):
                    messages = None
                yield messages, line.rstrip("\n") if messages is None else None


class ChatSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "salvage_chat"

    def schema(self) -> str:
        return f"messages {MESSAGES}, broken string"

    def reader(self, schema) -> DataSourceReader:
        return ChatReader(self.options["path"])


def to_chat(samples: DataFrame) -> DataFrame:
    """(value): a JSON line for each sample (instruction, input, response); an input becomes a system message."""
    message = lambda role, c: F.struct(F.lit(role).alias("role"), F.col(c).alias("content"))
    messages = F.filter(F.array(message("system", "input"), message("user", "instruction"), message("assistant", "response")), lambda m: m["content"].isNotNull())
    return samples.select(F.to_json(F.struct(messages.alias("messages"))).alias("value"))
