"""Interval relations derived from the given tables, and generated ones."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import axis, to_intervals


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def presc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items as prescriptions: from the ship day, for as many days as their quantity."""
    df = read(spark, sf_dir, "lineitem")
    start = axis(F.col("l_shipdate"), "day")
    return to_intervals(df, start, start + F.col("l_quantity").cast("long"))


def trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as trips at minute grain."""
    df = read(spark, sf_dir, "events")
    start = axis(F.col("ts"), "minute")
    return to_intervals(df, start, start + F.floor("value").cast("long") + 1, F.col("event_id"))


def gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From each event to the same user's next one, in microseconds."""
    df = read(spark, sf_dir, "events")
    nxt = F.lead("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    df = df.withColumn("next_ts", nxt)
    return to_intervals(df, axis(F.col("ts")), axis(F.col("next_ts")), F.col("event_id"))


def order_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From each order to the same customer's next one, in days; empty ones are left out."""
    df = read(spark, sf_dir, "orders")
    nxt = F.lead("o_orderdate").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"))
    df = df.withColumn("next_date", nxt)
    return to_intervals(df, axis(F.col("o_orderdate"), "day"), axis(F.col("next_date"), "day"), F.col("o_orderkey"))


def order_ship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Between the order day and the ship day of each line item, whichever comes first."""
    li, o = read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "orders")
    df = li.join(o.select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    a, b = axis(F.col("o_orderdate"), "day"), axis(F.col("l_shipdate"), "day")
    return to_intervals(df, F.least(a, b), F.greatest(a, b))


def utterances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns of conversations on an axis of characters."""
    df = read(spark, sf_dir, "conversations").withColumn("len", F.length("text").cast("long"))
    upto = F.sum("len").over(Window.partitionBy("conv_id").orderBy("turn"))
    df = df.withColumn("stop", upto)
    return to_intervals(df, F.col("stop") - F.col("len"), F.col("stop"), F.col("conv_id") * 1000 + F.col("turn"))


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first two components of the vectors, as integers."""
    v = read(spark, sf_dir, "embeddings")
    x = lambda i: F.floor(F.element_at("embedding", i).cast("double") * 1000).cast("long")
    return v.select("vec_id", x(1).alias("x"), x(2).alias("y"))


def zipf_cuts(most: int) -> list[int]:
    """Integer cut points, out of 2**31 - 1, of the cumulative weights 1/k for k up to ``most``."""
    w = np.cumsum(1 / np.arange(1, most + 1))
    return [int(x) for x in np.floor(w / w[-1] * 2147483647)]


def synthetic(spark: SparkSession, n: int, starts: str = "uniform", lengths: str = "zipf", most: int = 100, seed: int = 7, ids: DataFrame | None = None) -> DataFrame:
    """n generated intervals on [1, n], or one for each of ``ids`` (id, below 2**31 - 1): uniform or skewed starts, Zipf or uniform
    lengths, from an integer generator."""
    x = lambda salt: (F.col("id") * F.lit(48271) + F.lit(seed * 16807 + salt * 69621)) * F.lit(40692) % F.lit(2147483647)
    df = (spark.range(n) if ids is None else ids).select("id", x(1).alias("u"), x(2).alias("v"))
    lo = F.col("u") % F.lit(n) + 1
    if starts == "skewed":
        lo = F.floor(lo * lo / F.lit(n)).cast("long") + 1
    dur = F.size(F.filter(F.array(*[F.lit(c) for c in zipf_cuts(most)]), lambda c: c < F.col("v"))) + 1 if lengths == "zipf" else F.col("v") % F.lit(most) + 1
    return df.select(F.col("id").alias("iv_id"), lo.alias("t_lo"), dur.cast("long").alias("dur")).select("iv_id", "t_lo", (F.col("t_lo") + F.col("dur")).alias("t_hi"), "dur")


def event_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One id for each event, in the range of the generator."""
    return read(spark, sf_dir, "events").select((F.col("event_id") % 2147483647).alias("id"))


def scale_up(df: DataFrame, eta: int, span: int) -> DataFrame:
    """eta copies of df, the i-th shifted by i * span: the output of queries within the first stays the same."""
    copies = df.sparkSession.range(eta).select(F.col("id").alias("copy"))
    wide = df.crossJoin(F.broadcast(copies))  # a handful of copies
    return wide.withColumns({"t_lo": F.col("t_lo") + F.col("copy") * span, "t_hi": F.col("t_hi") + F.col("copy") * span})


RELATIONS = {"presc": presc, "trips": trips, "gaps": gaps, "order_gaps": order_gaps, "order_ship": order_ship, "utterances": utterances}
