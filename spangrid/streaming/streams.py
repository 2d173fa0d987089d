"""Structured Streaming over the events: interval makers, windows, and ingest into a grid."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.grid import Grid, GridSpec, build_grid
from ..operators.maintain import insert
from ..storage import shared_dir, written


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream; its timestamps get the session's zone, as watermarks need one."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there and returns its result table, written to the shared folder."""
    spark = stream.sparkSession
    at = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", f"{at}/out").outputMode("append")
    else:
        writer = stream.writeStream.outputMode(mode).foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(f"{at}/out"))
    writer.option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = events(spark, sf_dir).withWatermark("ts", "1 day")
    out = s.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return drained(out, "complete").select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = events(spark, sf_dir).withWatermark("ts", "1 day")
    out = s.groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return drained(out, "complete").select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n")


def sessions(spark: SparkSession, sf_dir: str, gap: str = "30 minutes") -> DataFrame:
    """Sessions of a user as intervals; the last of each user closes with the stream."""
    s = events(spark, sf_dir).withWatermark("ts", "1 day")
    out = s.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return drained(out, "complete").select("user_id", F.unix_micros("session_window.start").alias("t_lo"), F.unix_micros("session_window.end").alias("t_hi"), "n")


def _closed(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Gaps between a user's successive events; the last event waits in the state."""
    rows = pd.concat(list(parts)).sort_values(["us", "event_id"])
    held = state.get if state.exists else None
    us, ids = rows["us"].tolist(), rows["event_id"].tolist()
    if held is not None:
        us, ids = [held[0], *us], [held[1], *ids]
    state.update((us[-1], ids[-1]))
    out = [(key[0], i, a, b, b - a) for i, a, b in zip(ids, us, us[1:]) if a < b]
    yield pd.DataFrame(out, columns=["user_id", "event_id", "t_lo", "t_hi", "dur"])


def gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From each event to the same user's next one, by a stateful operator. An event older than the last one closed opens no gap."""
    s = events(spark, sf_dir).select("user_id", "event_id", F.unix_micros("ts").alias("us"))
    out = s.groupBy("user_id").applyInPandasWithState(_closed, "user_id long, event_id long, t_lo long, t_hi long, dur long", "us long, event_id long", "append", GroupStateTimeout.NoTimeout)
    return drained(out)


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = events(spark, sf_dir).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return drained(s.select("user_id", "event_type"))


class Ingest:
    """A stream's batches inserted into a grid, each once: a batch id that was taken before is skipped."""

    def __init__(self, spec: GridSpec):
        self.spec, self.grid, self.done = spec, None, set()

    def take(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id in self.done:
            return
        if not batch.isEmpty():
            self.grid = build_grid(batch, self.spec) if self.grid is None else insert(self.grid, batch)
        self.done.add(batch_id)

    def run(self, stream: DataFrame) -> Grid:
        at = f"{shared_dir(stream.sparkSession)}/ingest-{uuid.uuid4().hex}"
        stream.writeStream.foreachBatch(self.take).option("checkpointLocation", at).trigger(availableNow=True).start().awaitTermination()
        return self.grid


def ingest_trips(spark: SparkSession, sf_dir: str, spec: GridSpec) -> Grid:
    minute = F.floor(F.unix_micros("ts") / 60_000_000).cast("long")
    s = events(spark, sf_dir).select(F.col("event_id").alias("iv_id"), minute.alias("t_lo"), (minute + F.floor("value").cast("long") + 1).alias("t_hi"), (F.floor("value").cast("long") + 1).alias("dur"))
    return Ingest(spec).run(s)


def numbered(df: DataFrame, batches: int, order: str = "random") -> DataFrame:
    """df with the batch that each row belongs to: by a hash of the id (random), or by increasing start (append)."""
    if order == "random":
        return df.withColumn("batch", F.pmod(F.xxhash64("iv_id"), F.lit(batches)).cast("int"))
    cuts = df.approxQuantile("t_lo", [i / batches for i in range(1, batches)], 0.001) if batches > 1 else []
    shared = df.sparkSession.sparkContext.broadcast(np.array(cuts, float))  # one number a batch

    @F.pandas_udf("int")
    def place(start: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(shared.value, start.to_numpy(float), "right"))

    return df.withColumn("batch", place("t_lo"))


def in_batches(df: DataFrame, batches: int, order: str = "random") -> list[DataFrame]:
    """df cut into batches, written once in folders by batch; a batch reads its own folder."""
    out = written(numbered(df, batches, order).repartition("batch"), "batches", "batch")
    there = {r[0] for r in out.select("batch").distinct().collect()}  # one row a batch
    spark = df.sparkSession
    return [spark.read.schema(df.schema).parquet(f"{out._spangrid_at}/batch={i}") if i in there else spark.createDataFrame([], df.schema) for i in range(batches)]
