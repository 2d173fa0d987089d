"""Predicates over intervals as columns: the three selections, and the relations between two intervals."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..model import Query


def _all(parts: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, parts) if parts else F.lit(True)


def polygon(q: Query) -> Column:
    """The rows of a query, as a conjunction on bare columns so that scans can prune."""
    if q.empty:
        return F.lit(False)
    parts = []
    if q.q_hi is not None:
        parts.append(F.col("t_lo") < F.lit(q.q_hi))
    if q.q_lo is not None:
        parts.append(F.col("t_hi") > F.lit(q.q_lo))
    if q.d_min is not None:
        parts.append(F.col("dur") >= F.lit(q.d_min))
    if q.d_max is not None:
        parts.append(F.col("dur") <= F.lit(q.d_max))
    return _all(parts)


def implied_bounds(q: Query) -> Column:
    """What window and band say together about starts: a match begins after q_lo - d_max."""
    return F.col("t_lo") > F.lit(q.q_lo - q.d_max) if q.q_lo is not None and q.d_max is not None else F.lit(True)


def valid(prefix: str = "") -> Column:
    """The query in columns q_lo, q_hi, d_min, d_max can have matches."""
    c = lambda n: F.col(prefix + n)
    return F.coalesce(c("q_lo") < c("q_hi"), F.lit(True)) & F.coalesce(c("d_min") <= c("d_max"), F.lit(True))


def after(x: Column, bound: Column) -> Column:
    return bound.isNull() | (x > bound)


def before(x: Column, bound: Column) -> Column:
    return bound.isNull() | (x < bound)


def at_least(x: Column, bound: Column) -> Column:
    return bound.isNull() | (x >= bound)


def at_most(x: Column, bound: Column) -> Column:
    return bound.isNull() | (x <= bound)


def matches() -> Column:
    """A row (t_lo, t_hi, dur) beside a query (q_lo, q_hi, d_min, d_max) answers it."""
    c = F.col
    return valid() & before(c("t_lo"), c("q_hi")) & after(c("t_hi"), c("q_lo")) & at_least(c("dur"), c("d_min")) & at_most(c("dur"), c("d_max"))


def in_window() -> Column:
    return valid() & before(F.col("t_lo"), F.col("q_hi")) & after(F.col("t_hi"), F.col("q_lo"))


def in_band() -> Column:
    return valid() & at_least(F.col("dur"), F.col("d_min")) & at_most(F.col("dur"), F.col("d_max"))


def relation(a_lo: Column, a_hi: Column, b_lo: Column, b_hi: Column) -> Column:
    """The name of the one relation, of thirteen, that holds between two intervals."""
    return (
        F.when(a_hi < b_lo, "before").when(a_hi == b_lo, "meets").when(b_hi < a_lo, "after").when(b_hi == a_lo, "met_by")
        .when((a_lo == b_lo) & (a_hi == b_hi), "equals").when((a_lo == b_lo) & (a_hi < b_hi), "starts").when(a_lo == b_lo, "started_by")
        .when((a_hi == b_hi) & (a_lo > b_lo), "finishes").when(a_hi == b_hi, "finished_by")
        .when((a_lo > b_lo) & (a_hi < b_hi), "during").when((a_lo < b_lo) & (a_hi > b_hi), "contains")
        .when(a_lo < b_lo, "overlaps").otherwise("overlapped_by")
    )
