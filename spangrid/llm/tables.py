"""Reading the given tables, and what several operators do with tables."""

from __future__ import annotations

import gc
import time
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import forget, shared_dir, written  # noqa: F401

TEXT_COLUMNS = ("doc_id", "text")
#: Spark's setting by which a query deletes its shuffle files as it ends.
DROP_FILES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Bits of the bitmaps below, at most, as a power of two: as words of 64 bits a million rows.
MOST_BITS = 26


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def remainder(doc_id: Column, by: int) -> Column:
    """crc32 of the id as text, modulo ``by``; a null id counts as 0."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(by)), F.lit(0))


def widened(df: DataFrame, **types: str) -> str:
    """DDL of df's columns and some more; df's own schema stays as it is."""
    return ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields), *(f"{k} {v}" for k, v in types.items())])


def release(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of plans that nothing holds any more: it does so when the driver collects garbage, which
    a driver with little to do may not do for half an hour while executors' disks fill. Python gives plans up in a thread of its
    own, so the collection waits a moment for it."""
    gc.collect()
    time.sleep(0.5)
    spark.sparkContext._jvm.System.gc()


@contextmanager
def files_dropped(spark: SparkSession) -> Iterator[None]:
    """Every query that ends in here deletes its shuffle files at once, without waiting for the driver to collect garbage. For plans that
    are run once, as those that are written: a plan run again makes its files anew."""
    before = spark.conf.get(DROP_FILES, None)
    spark.conf.set(DROP_FILES, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(DROP_FILES)
        else:
            spark.conf.set(DROP_FILES, before)


def flagged(df: DataFrame, column: str, keys: DataFrame, into: str) -> DataFrame:
    """df with ``into``: false only where the long ``column`` is surely none of keys' (one column), by a shared bitmap.

    Keys that meet in a bit let more through, so what must be exact is joined afterwards, by rows that are few unless the keys
    are many. The bitmap grows with the keys up to 2 ** MOST_BITS bits.
    """
    log = min(MOST_BITS, max(10, (16 * keys.count()).bit_length()))

    def place(c: str) -> tuple[Column, Column]:
        at = F.shiftrightunsigned(F.xxhash64(F.col(c).cast("long")), 64 - log)
        return F.shiftright(at, 6), at.bitwiseAND(F.lit(63)).cast("int")

    i, j = place(keys.columns[0])
    words = written(keys.select(i.alias("_i"), F.call_function("shiftleft", F.lit(1).cast("long"), j).alias("_w")).groupBy("_i").agg(F.bit_or("_w").alias("_w")), "bitmap")
    i, j = place(column)
    own = df.withColumns({"_at": i, "_j": j})
    bit = F.call_function("shiftrightunsigned", F.col("_w"), F.col("_j")).bitwiseAND(F.lit(1))
    return own.join(F.broadcast(words), F.col("_at") == F.col("_i"), "left").withColumn(into, F.coalesce(bit == 1, F.lit(False))).drop("_at", "_j", "_i", "_w")


def sifted(df: DataFrame, column: str, keys: DataFrame) -> DataFrame:
    """Rows of df that the bitmap of keys lets through."""
    return flagged(df, column, keys, "_may").filter("_may").drop("_may")
