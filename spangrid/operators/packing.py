"""Packing of keys into groups of a target size that never split equal keys.

Keys come as runs (key, count) in key order. A group takes runs while its rows stay within the budget; a run larger
than the budget stands alone and is heavy. Working on runs makes the cost follow the distinct keys, not the rows,
and one group is found by one binary search in the cumulative counts.

Forms: ``exact`` (one ordered pass over the histogram), ``sharded`` (range shards of the histogram packed independently; at most one
under-full group more a shard) and ``quantile`` (cuts at approximate quantiles of the key). All keep equal keys together.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import written

#: Distinct keys that the exact form takes into one task; beyond it the build uses the sharded form.
EXACT_KEYS = 20_000_000


def groups_of_runs(counts: np.ndarray, budget: int) -> np.ndarray:
    """The group of each run, for runs in key order."""
    if budget < 1:
        raise ValueError("the budget must be at least 1")
    n = len(counts)
    total = np.concatenate([[0], np.cumsum(np.asarray(counts, np.int64))])
    out = np.zeros(n, np.int64)
    i = g = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(total, total[i] + budget, "right")) - 1)
        out[i:j] = g
        i, g = j, g + 1
    return out


def runs(df: DataFrame, key: Column, by: list[str] | None = None) -> DataFrame:
    """Histogram of the key, within the groups of ``by`` if given."""
    return df.groupBy(*(by or []), key.alias("key")).agg(F.count("*").alias("n"))


def pack(histogram: DataFrame, budget: int, by: str | None = None, form: str = "exact", shards: int | None = None) -> DataFrame:
    """histogram (key, n and ``by``) with ``grp``, numbered from 0 in key order within ``by``."""
    if form == "quantile":
        return _quantile(histogram, budget, by)
    if form == "sharded" and by is None:
        return _sharded(histogram, budget, shards or int(histogram.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in histogram.schema.fields)

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("key")
        return pdf.assign(grp=groups_of_runs(pdf["n"].to_numpy(), budget))

    return histogram.groupBy(*([by] if by else [])).applyInPandas(solve, f"{fields}, grp long")


def _sharded(histogram: DataFrame, budget: int, shards: int) -> DataFrame:
    dealt = histogram.select("key", "n").repartitionByRange(shards, "key").sortWithinPartitions("key")

    def solve(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        fill = grp = 0
        for pdf in parts:  # a shard may come in several batches, all in key order
            counts = pdf["n"].to_numpy()
            if fill:  # what the batch before left open is one more run ahead of this one
                g = groups_of_runs(np.concatenate([[fill], counts]), budget)[1:]
            else:
                g = groups_of_runs(counts, budget)
            out = g + grp
            if len(out):
                fill = int(counts[out == out[-1]].sum()) + (fill if out[-1] == grp else 0)
                grp = int(out[-1])
            yield pdf.assign(g=out)

    local = written(dealt.mapInPandas(solve, "key long, n long, g long").withColumn("shard", F.spark_partition_id()), "shards")
    width = local.groupBy("shard").agg((F.max("g") + 1).alias("w"))  # one row a shard
    first = width.select("shard", (F.sum("w").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, 0)) - F.col("w")).alias("first"))
    return local.join(F.broadcast(first), "shard").select("key", "n", (F.col("first") + F.col("g")).alias("grp"))


def _quantile(histogram: DataFrame, budget: int, by: str | None) -> DataFrame:
    """Groups by the rank of a key's first row over the budget: equal keys have one rank, so they stay together."""
    keys = [by] if by else []
    w = Window.partitionBy(*keys).orderBy("key").rowsBetween(Window.unboundedPreceding, -1)
    ranked = histogram.withColumn("slot", F.floor(F.coalesce(F.sum("n").over(w), F.lit(0)) / F.lit(budget)))
    return ranked.withColumn("grp", F.dense_rank().over(Window.partitionBy(*keys).orderBy("slot")) - F.lit(1)).withColumn("grp", F.col("grp").cast("long")).drop("slot")
