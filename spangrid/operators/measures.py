"""Cost and accuracy measures: selectivities, excess, mixes, bounds, sizes, balance, profiles."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.predicates import valid


def selectivity(df: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, n, time_hits, dur_hits, both_hits. Those of a window are rows that begin before its end less those that end by its begin,
    those of a band come from ranks of the lengths, and those of both from a grid, so no row meets every query."""
    from .grid import GridSpec, below, build_grid

    n = df.count()
    asked = queries.select("qid", "q_lo", "q_hi", "d_min", "d_max", valid().alias("ok"))

    def under(keys: str, bound: Column, default: int) -> DataFrame:
        """qid, how many keys lie under the bound; an open bound counts as default."""
        probes = asked.select("qid", bound.cast("long").alias("x"))
        known = below(df.select(F.col(keys).alias("x")), probes.filter("x is not null")).select("qid", F.col("n_below").alias("c"))
        return known.unionByName(probes.filter("x is null").select("qid", F.lit(default).cast("long").alias("c")))

    signs = [(under("t_lo", F.col("q_hi"), n), 1, 0), (under("t_hi", F.col("q_lo") + 1, 0), -1, 0), (under("dur", F.col("d_max") + 1, n), 0, 1), (under("dur", F.col("d_min"), 0), 0, -1)]
    sums = None
    for part, t, d in signs:
        one = part.select("qid", (F.col("c") * t).alias("t"), (F.col("c") * d).alias("d"))
        sums = one if sums is None else sums.unionByName(one)
    sums = sums.groupBy("qid").agg(F.sum("t").alias("t"), F.sum("d").alias("d")).join(asked.select("qid", "ok"), "qid")
    both = build_grid(df, GridSpec(max(2, math.isqrt(math.isqrt(n))))).count_batch(queries)
    some = lambda c: F.when(F.col("ok"), F.col(c)).otherwise(0).cast("long")
    return sums.join(both, "qid").select("qid", F.lit(n).cast("long").alias("n"), some("t").alias("time_hits"), some("d").alias("dur_hits"), F.col("matched").alias("both_hits"))


def window_hits(df: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, time_hits in closed form: rows that begin before the window ends, less those that end by its start."""
    begins, ends = df.groupBy(F.col("t_lo").alias("x")).count(), df.groupBy(F.col("t_hi").alias("x")).count()
    few = F.broadcast(queries.filter(valid() & F.col("q_lo").isNotNull()))
    total = lambda h, cond: few.join(h, cond, "left").groupBy("qid").agg(F.coalesce(F.sum("count"), F.lit(0)).alias("s"))
    a = total(begins, F.col("x") < F.col("q_hi"))
    b = total(ends, F.col("x") <= F.col("q_lo")).withColumnRenamed("s", "e")
    return a.join(b, "qid").select("qid", (F.col("s") - F.col("e")).cast("long").alias("time_hits"))


def accuracy(meter: DataFrame, n: int) -> DataFrame:
    """Adds excess, examined_fraction and precision to metered queries."""
    return meter.withColumns({
        "excess": F.col("examined") - F.col("matched"), "examined_fraction": F.col("examined") / F.lit(float(n)),
        "precision": F.when(F.col("examined") > 0, F.col("matched") / F.col("examined")).otherwise(F.lit(1.0)),
    })


def mixed_rate(rates: list[Column], shares: list[Column]) -> Column:
    """The rate of a mix: the harmonic mean of the rates weighted by their shares."""
    cost = sum((s / r for r, s in zip(rates, shares)), F.lit(0.0))
    return F.lit(1.0) / cost


def lattice(spark, steps: int) -> DataFrame:
    """All mixes (i, j, k) of three shares in steps of 1/steps."""
    i = spark.range(steps + 1).select(F.col("id").alias("i"))
    j = i.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(steps) - F.col("i"))).alias("j"), "i")
    return j.select("i", "j", (F.lit(steps) - F.col("i") - F.col("j")).alias("k"))


def winner_map(rates: DataFrame, steps: int) -> DataFrame:
    """dataset, i, j, k, winner: the best method of each mix. rates: dataset, method, pos, range_only, duration_only, range_duration."""
    mixes = F.broadcast(lattice(rates.sparkSession, steps))  # (steps + 1)(steps + 2) / 2 rows
    share = lambda c: F.col(c) / F.lit(float(steps))
    rate = mixed_rate([F.col("range_only"), F.col("duration_only"), F.col("range_duration")], [share("i"), share("j"), share("k")])
    best = F.max_by("method", F.struct(F.round(rate, 9), -F.col("pos")))
    return rates.join(mixes, how="cross").groupBy("dataset", "i", "j", "k").agg(best.alias("winner"))


def crossover(a_other: Column, a_own: Column, b_other: Column, b_own: Column) -> Column:
    """Share of the ``own`` kind from which b overtakes a, if the rest is the ``other`` kind."""
    d_other, d_own = 1 / b_other - 1 / a_other, 1 / a_own - 1 / b_own
    return d_other / (d_other + d_own)


def query_bound(n: int, s: int, k: int) -> float:
    return n / s**2 * math.log2(max(2, n / s)) + n / s + s**2 + k


def build_bound(n: int) -> float:
    return n * math.log2(max(2, n))


def insert_bound(n: int, s: int) -> float:
    return math.log2(max(2, n / s)) + n / s + s**2 * math.log2(max(2, s))


def remove_bound(n: int, s: int) -> float:
    return math.log2(max(2, n / s)) + n / s


def most_groups(n: int, budget: int) -> int:
    """No packing of n rows at this budget has more groups, as any two neighbours exceed it together."""
    return 2 * n // (budget + 1) + 1


def bytes_per_interval(stored: DataFrame, n: int, entry_bytes: int = 32) -> DataFrame:
    """Two longs for each stored copy and entry_bytes for each directory row, over the intervals."""
    return stored.select(((F.col("stored") * 16 + F.col("entries") * entry_bytes) / F.lit(float(n))).alias("bytes_per_interval"))


def parquet_bytes(df: DataFrame) -> DataFrame:
    """Bytes of the files that df is read from."""
    files = df.select("_metadata.file_path", "_metadata.file_size").distinct()
    return files.agg(F.sum("file_size").alias("bytes"), F.count("*").alias("files"))


def balance(groups: DataFrame) -> DataFrame:
    """Groups, their largest and mean size, and the share of rows in the largest tenth."""
    rank = F.percent_rank().over(Window.orderBy(F.desc("n")))  # over groups only
    top = groups.select("n", rank.alias("p"))
    return top.agg(F.count("*").alias("groups"), F.max("n").alias("largest"), F.avg("n").alias("mean"), (F.max("n") / F.avg("n")).alias("imbalance"), (F.sum(F.when(F.col("p") <= 0.1, F.col("n")).otherwise(0)) / F.sum("n")).alias("top_share"))


def histogram(df: DataFrame, column: str, width: int) -> DataFrame:
    return df.groupBy(F.floor(F.col(column) / F.lit(width)).cast("long").alias("bin")).agg(F.count("*").alias("n"))
