"""Intervals, queries and normalisation.

A row's interval is the half-open [t_lo, t_hi) of a discrete ordered axis held as longs; dur = t_hi - t_lo is stored
with it, as it is a clustering key. Rows with null, inverted or empty intervals never enter an index.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UNITS = {"us": 1, "second": 1_000_000, "minute": 60_000_000, "day": 86_400_000_000}
INTERVAL_FIELDS = ("iv_id", "t_lo", "t_hi", "dur")
QUERY_SCHEMA = "qid long, kind string, q_lo long, q_hi long, d_min long, d_max long"


@dataclass(frozen=True)
class Query:
    """A window [q_lo, q_hi) and a closed band [d_min, d_max]; None is unbounded."""

    q_lo: int | None = None
    q_hi: int | None = None
    d_min: int | None = None
    d_max: int | None = None

    @property
    def kind(self) -> str:
        window = self.q_lo is not None or self.q_hi is not None
        band = self.d_min is not None or self.d_max is not None
        return "both" if window and band else "range" if window else "duration" if band else "all"

    @property
    def empty(self) -> bool:
        """No row can match: an empty or inverted window, or an inverted band."""
        window = None not in (self.q_lo, self.q_hi) and self.q_lo >= self.q_hi
        return window or (None not in (self.d_min, self.d_max) and self.d_min > self.d_max)

    def frame(self, spark, qid: int = 0) -> DataFrame:
        return spark.createDataFrame([(qid, self.kind, self.q_lo, self.q_hi, self.d_min, self.d_max)], QUERY_SCHEMA)


def axis(ts: Column, unit: str = "us") -> Column:
    """A timestamp without time zone as a long in the unit, floored."""
    micros = F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), ts)
    return micros if unit == "us" else F.floor(micros / F.lit(UNITS[unit])).cast("long")


def to_intervals(df: DataFrame, lo: Column, hi: Column, iv_id: Column | None = None) -> DataFrame:
    """df with the normalised interval columns in front; what cannot be an interval is left out (see quarantined)."""
    out = _with_ends(df, lo, hi, iv_id).filter("t_lo < t_hi")
    payload = [c for c in df.columns if c not in INTERVAL_FIELDS]
    return out.select("iv_id", "t_lo", "t_hi", (F.col("t_hi") - F.col("t_lo")).alias("dur"), *payload)


def quarantined(df: DataFrame, lo: Column, hi: Column) -> DataFrame:
    """The rows to_intervals leaves out, with the reason."""
    out = _with_ends(df, lo, hi, None)
    why = F.when(F.col("t_lo").isNull() | F.col("t_hi").isNull(), "null").when(F.col("t_lo") == F.col("t_hi"), "empty").when(F.col("t_lo") > F.col("t_hi"), "inverted")
    return out.withColumn("reason", why).filter("reason is not null")


def _with_ends(df: DataFrame, lo: Column, hi: Column, iv_id: Column | None) -> DataFrame:
    key = F.xxhash64(*[F.col(c) for c in df.columns]) if iv_id is None else iv_id
    return df.withColumns({"iv_id": key.cast("long"), "t_lo": lo.cast("long"), "t_hi": hi.cast("long")})


def length_of(lo: Column, hi: Column) -> Column:
    return hi - lo


def meet(a_lo: Column, a_hi: Column, b_lo: Column, b_hi: Column) -> tuple[Column, Column]:
    """Ends of the common part; it is empty unless the first is below the second."""
    return F.greatest(a_lo, b_lo), F.least(a_hi, b_hi)


def overlap_len(a_lo: Column, a_hi: Column, b_lo: Column, b_hi: Column) -> Column:
    lo, hi = meet(a_lo, a_hi, b_lo, b_hi)
    return F.greatest(hi - lo, F.lit(0))
