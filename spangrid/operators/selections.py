"""The three selections by scan, and their counts: the truth every index is held against."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import at_least, at_most, implied_bounds, polygon
from ..model import Query


def select(df: DataFrame, q: Query) -> DataFrame:
    return df.filter(polygon(q)).filter(implied_bounds(q))


def select_by_row(df: DataFrame, q: Query) -> DataFrame:
    """The same rows as select, found by testing each: its common part with the window, and its length. Also where the query alone
    tells that none match."""
    lo = F.col("t_lo") if q.q_lo is None else F.greatest(F.col("t_lo"), F.lit(q.q_lo))
    hi = F.col("t_hi") if q.q_hi is None else F.least(F.col("t_hi"), F.lit(q.q_hi))
    return df.filter(lo < hi).filter(at_least(F.col("dur"), F.lit(q.d_min).cast("long")) & at_most(F.col("dur"), F.lit(q.d_max).cast("long")))


def select_range(df: DataFrame, q_lo: int | None, q_hi: int | None) -> DataFrame:
    return select(df, Query(q_lo, q_hi))


def select_duration(df: DataFrame, d_min: int | None, d_max: int | None) -> DataFrame:
    return select(df, Query(None, None, d_min, d_max))


def select_range_duration(df: DataFrame, q: Query) -> DataFrame:
    return select(df, q)


def count_matches(df: DataFrame, q: Query) -> DataFrame:
    return select(df, q).agg(F.count("*").alias("matched"))
