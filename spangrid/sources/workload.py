"""Query sets: random ones from an integer generator that any engine reproduces, and grids of selectivities."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import QUERY_SCHEMA

M = 2147483647


def draw(i, seed: int):
    """The i-th number of the generator."""
    return (i * F.lit(48271) + F.lit(seed * 16807)) % F.lit(M)


def random_queries(spark: SparkSession, kind: str, m: int, seed: int, window: tuple[int, int], lengths: tuple[int, int], band: tuple[int, int], unit: int = 1) -> DataFrame:
    """m queries of a kind: windows of a length in ``lengths`` inside ``window``, bands with both ends in ``band``, all in units."""
    (a, b), (l0, l1), (d0, d1) = window, lengths, band
    x = lambda k: draw(F.col("id") * 5 + k, seed)
    q = spark.range(m).select(F.col("id").alias("qid"), *[x(k).alias(f"x{k}") for k in range(5)])
    length = F.lit(l0) + F.col("x0") % F.lit(l1 - l0 + 1)
    lo = F.lit(a) + F.col("x1") % F.lit(max(1, b - a))
    d, e = F.lit(d0) + F.col("x2") % F.lit(d1 - d0 + 1), F.lit(d0) + F.col("x3") % F.lit(d1 - d0 + 1)
    some = lambda c, on: (c * F.lit(unit) if on else F.lit(None)).cast("long")
    w, h = kind in ("range", "both"), kind in ("duration", "both")
    return q.select("qid", F.lit(kind).alias("kind"), some(lo, w).alias("q_lo"), some(F.least(lo + length, F.lit(b)), w).alias("q_hi"), some(F.least(d, e), h).alias("d_min"), some(F.greatest(d, e), h).alias("d_max"))


def random_queries_sql(kind: str, m: int, seed: int, window: tuple[int, int], lengths: tuple[int, int], band: tuple[int, int], unit: int = 1) -> str:
    """The same set in SQL."""
    (a, b), (l0, l1), (d0, d1) = window, lengths, band
    x = ", ".join(f"((id * 5 + {k}) * 48271 + {seed * 16807}) % {M} AS x{k}" for k in range(5))
    w, h = kind in ("range", "both"), kind in ("duration", "both")
    lo, d, e = f"{a} + x1 % {max(1, b - a)}", f"{d0} + x2 % {d1 - d0 + 1}", f"{d0} + x3 % {d1 - d0 + 1}"
    some = lambda v, on: f"CAST({f'({v}) * {unit}' if on else 'NULL'} AS BIGINT)"
    return f"SELECT id AS qid, '{kind}' AS kind, {some(lo, w)} AS q_lo, {some(f'least({lo} + {l0} + x0 % {l1 - l0 + 1}, {b})', w)} AS q_hi, {some(f'least({d}, {e})', h)} AS d_min, {some(f'greatest({d}, {e})', h)} AS d_max FROM (SELECT id, {x} FROM range({m}) r(id))"


def query_set(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, QUERY_SCHEMA)


def selectivity_grid(df: DataFrame, side: int) -> DataFrame:
    """side * side queries over (time, length) selectivity; ties make targets unreachable, so achieved ones are measured apart.

    Windows are centred on the median start and widen by quantiles of the starts; bands do the same on lengths.
    """
    spark = df.sparkSession

    def cuts(column: str) -> DataFrame:
        h = df.groupBy(F.col(column).alias("v")).agg(F.count("*").alias("c"))
        upto = F.sum("c").over(Window.orderBy("v").rowsBetween(Window.unboundedPreceding, 0))  # over distinct values
        n = df.count()
        ranked = h.select("v", (upto / F.lit(float(n))).alias("r"))
        k = F.broadcast(spark.range(1, side + 1).select(F.col("id").alias("k")))
        half = F.col("k") / F.lit(2.0 * side)
        both = k.join(ranked, how="cross")
        return both.groupBy("k").agg(F.min(F.when(F.col("r") >= 0.5 - half, F.col("v"))).alias("lo"), F.min(F.when(F.col("r") >= F.least(0.5 + half, F.lit(1.0)) - 1e-12, F.col("v"))).alias("hi"))

    t, d = cuts("t_lo"), cuts("dur")
    return t.select(F.col("k").alias("i"), F.col("lo").alias("q_lo"), (F.col("hi") + 1).alias("q_hi")).crossJoin(d.select(F.col("k").alias("j"), F.col("lo").alias("d_min"), F.col("hi").alias("d_max"))).select(
        ((F.col("i") - 1) * side + F.col("j")).alias("qid"), F.lit("both").alias("kind"), "q_lo", "q_hi", "d_min", "d_max"
    )
