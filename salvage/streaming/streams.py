"""The event feed as a stream: sources, drains and stateful processors."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from salvage.functions.scratch import scratch

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def replayed(spark: SparkSession, table: DataFrame, files: int = 4, order: str = "ts") -> DataFrame:
    """``table`` as a stream of ``files`` files in the given order, one a trigger; NTZ times become timestamps."""
    path = scratch(spark, "feed")
    cuts = table.agg(F.percentile_approx(F.col(order).cast("timestamp").cast("double") if order == "ts" else F.col(order).cast("double"), [i / files for i in range(1, files)], 10_000).alias("q")).first()["q"]
    value = F.col(order).cast("timestamp").cast("double") if order == "ts" else F.col(order).cast("double")
    part = sum((F.when(value > c, 1).otherwise(0) for c in cuts or []), F.lit(0))
    for i in range(files):  # the files' times give the order of arrival
        table.where(part == i).coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(table.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in table.columns else stream


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table, read as a stream straight from its files."""
    table = spark.read.parquet(f"{sf_dir}/events.parquet")
    return spark.readStream.schema(table.schema).parquet(f"{sf_dir}/[e]vents.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def drain_append(stream: DataFrame, name: str) -> DataFrame:
    """All rows that the stream appends, as a table written by the file sink."""
    spark = stream.sparkSession
    out = scratch(spark, name)
    q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", scratch(spark, "offsets")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def drain_complete(stream: DataFrame, name: str) -> DataFrame:
    """The last state of an aggregation, upserted batch by batch."""
    spark = stream.sparkSession
    out = scratch(spark, name)

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/current")

    q = stream.writeStream.outputMode("complete").foreachBatch(put).option("checkpointLocation", scratch(spark, "offsets")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{out}/current")


def drain_batches(stream: DataFrame, name: str, split: Callable[[DataFrame, int], dict[str, DataFrame]]) -> str:
    """Routes each batch to several tables below the returned folder; a batch that is repeated replaces its own files."""
    spark = stream.sparkSession
    out = scratch(spark, name)

    def put(batch: DataFrame, number: int) -> None:
        for table, rows in split(batch, number).items():
            rows.write.mode("overwrite").parquet(f"{out}/{table}/batch={number}")

    q = stream.writeStream.foreachBatch(put).option("checkpointLocation", scratch(spark, "offsets")).trigger(availableNow=True).start()
    q.awaitTermination()
    return out


class PairCounts(StatefulProcessor):
    """Running counts of (previous type, type) for each user: an incremental table of second order."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "event_type string")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        own = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        before = self.last.get()[0] if self.last.exists() else None
        types = own["event_type"].tolist()
        previous = [before, *types[:-1]]
        self.last.update((types[-1],))
        yield pd.DataFrame({"user_id": key[0], "previous": previous, "event_type": types})

    def close(self) -> None:
        pass


class Leaders(StatefulProcessor):
    """Online one-hop assignment: a vector joins the first leader it is similar to, or becomes one."""

    min_sim = 0.3

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.leaders = handle.getListState("leaders", "vec_id bigint, vec array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        known = [(i, np.array(v)) for i, v in self.leaders.get()] if self.leaders.exists() else []
        fresh, out = [], []
        for vec_id, vec in pd.concat(list(rows)).sort_values("vec_id")[["vec_id", "embedding"]].itertuples(index=False):
            v = np.array(vec, float)
            v /= np.linalg.norm(v) or 1.0
            home = next((i for i, u in known if round(float(u @ v), 6) >= self.min_sim), None)
            if home is None:
                known.append((int(vec_id), v))
                fresh.append((int(vec_id), v.tolist()))
                home = int(vec_id)
            out.append((key[0], int(vec_id), int(home)))
        if fresh:
            self.leaders.appendList(fresh)
        yield pd.DataFrame(out, columns=["label", "vec_id", "leader"])

    def close(self) -> None:
        pass


def stateful(stream: DataFrame, key: str, processor: StatefulProcessor, schema: str) -> DataFrame:
    stream.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKS)
    return stream.groupBy(key).transformWithStateInPandas(processor, schema, "Append", "None")
