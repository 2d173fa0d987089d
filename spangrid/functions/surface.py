"""SQL names for intervals: functions built from expressions, table functions, and a balance aggregate."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession) -> None:
    """interval_meets, length_in, interval_overlap and the table functions lattice and grid_count, as temporary functions of the session."""
    for text in (
        "interval_meets(lo BIGINT, hi BIGINT, q_lo BIGINT, q_hi BIGINT) RETURNS BOOLEAN RETURN lo < q_hi AND hi > q_lo",
        "length_in(lo BIGINT, hi BIGINT, d_min BIGINT, d_max BIGINT) RETURNS BOOLEAN RETURN hi - lo BETWEEN d_min AND d_max",
        "interval_overlap(a BIGINT, b BIGINT, c BIGINT, d BIGINT) RETURNS BIGINT RETURN greatest(least(b, d) - greatest(a, c), 0)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    spark.udtf.register("lattice", Lattice)
    spark.udtf.register("grid_count", GridCount)


@F.udtf(returnType="i: bigint, j: bigint, k: bigint")
class Lattice:
    """All mixes of three shares in steps of 1 / steps."""

    def eval(self, steps: int):
        for i in range(steps + 1):
            for j in range(steps - i + 1):
                yield i, j, steps - i - j


@F.udtf(returnType="matched: bigint, pages: bigint")
class GridCount:
    """Answers to one query counted on the grid saved at a path, and the pages it meets: pages that the query covers are counted
    from the directory, the rows of the others are read and tested. Null bounds are open. The path must be one that workers can open."""

    def eval(self, path: str, q_lo: int, q_hi: int, d_min: int, d_max: int):
        import pyarrow.dataset as ds
        from pyarrow import fs

        if (None not in (q_lo, q_hi) and q_lo >= q_hi) or (None not in (d_min, d_max) and d_min > d_max):
            yield 0, 0
            return
        store, at = fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path.removeprefix("file:"))
        bounds = ((q_hi, "t_lo", "lo", False, False), (q_lo, "t_hi", "hi", True, False), (d_max, "dur", "dur", False, True), (d_min, "dur", "dur", True, True))
        test = met = covered = ds.scalar(True)
        for v, row, page, above, closed in bounds:
            if v is not None:
                ok = lambda c, v=v, above=above, closed=closed: (ds.field(c) >= v if closed else ds.field(c) > v) if above else (ds.field(c) <= v if closed else ds.field(c) < v)
                test = test & ok(row)
                met = met & ok(f"{'max' if above else 'min'}_{page}")
                covered = covered & ok(f"{'min' if above else 'max'}_{page}")
        directory = ds.dataset(f"{at}/pages", filesystem=store, format="parquet")
        pages = directory.to_table(columns={"col_id": ds.field("col_id"), "cell_id": ds.field("cell_id"), "n": ds.field("n"), "covered": covered}, filter=met).to_pandas()
        matched = int(pages.loc[pages["covered"], "n"].sum())
        for column, cells in pages[~pages["covered"]].groupby("col_id")["cell_id"]:
            rows = ds.dataset(f"{at}/rows/col_id={column}", filesystem=store, format="parquet")
            matched += rows.count_rows(filter=ds.field("cell_id").isin(cells.tolist()) & test)
        yield matched, len(pages)


def balance_score(n: Column) -> Column:
    """Largest over mean of group sizes, as a grouped aggregate."""

    @F.pandas_udf("double")
    def score(v: pd.Series) -> float:
        return float(v.max() / v.mean()) if len(v) else 0.0

    return score(n)
