"""What every index here is: rows that carry group ids, and a rule that says which groups a query visits.

A layout answers queries by an equi-join of visited groups with rows and a residual test; one meter therefore counts, for all of
them, the rows read in visited groups (up to the stop its order allows) beside the rows that answer.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.predicates import matches, valid
from ..model import QUERY_SCHEMA

QUERY_COLUMNS = ["qid", "kind", "q_lo", "q_hi", "d_min", "d_max"]
ROW_COLUMNS = ["iv_id", "t_lo", "t_hi", "dur"]


#: Queries that are shared with all tasks; a larger set is dealt out instead.
SHARED_QUERIES = 1_000_000


def small(queries: DataFrame) -> DataFrame:
    """The queries as a broadcast side, once they are known to be few."""
    return F.broadcast(queries) if queries.limit(SHARED_QUERIES + 1).count() <= SHARED_QUERIES else queries


class Layout:
    """rows (with the columns ``gid``), groups (``gid``, n, and what visiting needs), and how a visit reads a group."""

    name = "layout"
    replicates = False

    def __init__(self, rows: DataFrame, groups: DataFrame, gid: list[str]):
        self.rows, self.groups, self.gid = rows, groups, gid

    def settled(self) -> Layout:
        """The layout with its rows written in the order of their groups, and its groups: what building it costs."""
        from ..storage import written

        n = int(self.rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        self.rows = written(self.rows.repartitionByRange(n, *self.gid).sortWithinPartitions(*self.gid), self.name)
        self.groups = written(self.groups, f"{self.name}-groups")
        return self

    def meets(self) -> Column:
        """Whether a query (its columns) visits a group (its columns)."""
        return F.lit(True)

    def reads(self) -> Column:
        """Whether a row of a visited group is read before the group's stop."""
        return F.lit(True)

    def visit(self, queries: DataFrame) -> DataFrame:
        """Query columns, gid and n of each visited group. Queries are few against groups, so they are what is broadcast."""
        few = small(queries.filter(valid()))
        return self.groups.join(few, self.meets()).select(*QUERY_COLUMNS, *self.gid, "n")

    def find_batch(self, queries: DataFrame) -> DataFrame:
        """(qid, row) of every answer, each once."""
        own = self.rows.join(self.visit(queries).drop("n"), self.gid).filter(matches())
        return self.once(own).drop(*QUERY_COLUMNS[1:])

    def once(self, answers: DataFrame) -> DataFrame:
        return answers

    def count_batch(self, queries: DataFrame) -> DataFrame:
        """qid and matched, also of queries without answers."""
        got = self.find_batch(queries).groupBy("qid").agg(F.count("*").alias("c"))
        return queries.select("qid").join(got, "qid", "left").select("qid", F.coalesce("c", F.lit(0)).cast("long").alias("matched"))

    def visited_columns(self) -> Column:
        return F.lit(1)

    def meter(self, queries: DataFrame) -> DataFrame:
        """qid, columns_visited, cells_visited, examined, examined_incl_stop and matched of every query."""
        seen = self.visit(queries)
        per_group = (
            self.rows.join(seen, self.gid)
            .groupBy("qid", *self.gid)
            .agg(F.first("n").alias("n"), F.count_if(self.reads()).alias("hits"), F.count_if(self.answers()).alias("ok"))
        )
        sums = per_group.groupBy("qid").agg(
            F.count_distinct(self.visited_columns()).alias("columns_visited"), F.count("*").alias("cells_visited"), F.sum("hits").alias("examined"),
            F.sum(F.least("n", F.col("hits") + 1)).alias("examined_incl_stop"), F.sum("ok").alias("matched"),
        )
        names = ["columns_visited", "cells_visited", "examined", "examined_incl_stop", "matched"]
        return queries.select("qid").join(sums, "qid", "left").select("qid", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in names])

    def answers(self) -> Column:
        return matches()

    def stored(self) -> DataFrame:
        """stored: rows held, copies included; entries: rows of the directory."""
        return self.groups.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("stored"), F.count("*").alias("entries"))


def no_queries(spark) -> DataFrame:
    return spark.createDataFrame([], QUERY_SCHEMA)


def ordinal(df: DataFrame, keys: list[str], into: str, parts: int | None = None) -> DataFrame:
    """df with the 0-based position in the order of the keys, without bringing all rows to one task."""
    from ..storage import written

    parts = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = written(df.repartitionByRange(parts, *keys).withColumn("_p", F.spark_partition_id()), "ordinal")
    within = Window.partitionBy("_p").orderBy(*keys)
    size = dealt.groupBy("_p").agg(F.count("*").alias("_c"))
    start = size.select("_p", (F.sum("_c").over(Window.orderBy("_p")) - F.col("_c")).alias("_s"))  # one row a partition
    return dealt.withColumn("_r", F.row_number().over(within) - 1).join(F.broadcast(start), "_p").withColumn(into, F.col("_s") + F.col("_r")).drop("_p", "_r", "_s")
