"""The insertion study."""

import pytest
from pyspark.sql import functions as F


@pytest.mark.parametrize("name", ["study_insertion_append", "study_insertion_random"])
def test_every_method_takes_every_row(spark, sf, name):
    from spangrid.plans import catalog

    got = {r["method"]: r["n"] for r in catalog.QUERIES[name](spark, sf).groupBy("method").agg(F.sum("rows").alias("n")).collect()}
    assert got == dict.fromkeys(["start_first", "duration_first", "ordered_duration", "interval_tree", "inserting_tree"], 1000)


@pytest.mark.parametrize("order", ["random", "append"])
def test_batches_are_written_once(spark, sf, order):
    """Each row is in one batch, the one its id's hash or its start tells, and a batch reads only its own files."""
    from spangrid.plans.catalog import slim
    from spangrid.streaming.streams import in_batches

    df = slim(spark, sf, "trips")
    parts = in_batches(df, 5, order)
    files = [set(p.inputFiles()) for p in parts]
    assert all(files) and sum(map(len, files)) == len(set.union(*files)) and not any(f.endswith("events.parquet") for f in set.union(*files))
    if order == "random":
        assert [p.count() for p in parts] == [df.filter(F.pmod(F.xxhash64("iv_id"), F.lit(5)) == i).count() for i in range(5)]
    else:
        spans = [p.agg(F.count("*"), F.min("t_lo"), F.max("t_lo")).first() for p in parts]
        assert sum(s[0] for s in spans) == 1000 and all(a[2] < b[1] for a, b in zip(spans, spans[1:]))


def test_small_columns_share_files(spark):
    """A batch that touches every column of a grid of small pages doesn't write a file for each; its cuts keep to the sizes."""
    from spangrid.operators import maintain
    from spangrid.operators.grid import DURATION_FIRST, START_FIRST, GridSpec, build_grid

    rows = spark.range(2000).selectExpr("id AS iv_id", "id * 7919 % 3001 AS t_lo", "id * 7919 % 3001 + 1 + id % 97 AS t_hi", "1 + id % 97 AS dur")
    for order in (START_FIRST, DURATION_FIRST):
        some, rest, none = rows.filter("iv_id % 4 > 0"), rows.filter("iv_id % 4 = 0"), rows.filter("iv_id < 0")
        grid = maintain.insert(build_grid(some, GridSpec(5, order=order)), rest)
        assert len(grid.cuts.ids) > 60 and len(grid.rows.inputFiles()) <= 16
        assert grid.rows.count() == 2000 == grid.pages.agg(F.sum("n")).first()[0]
        assert not grid.pages.filter("n > 5 and min_lo < max_lo and min_dur < max_dur").count()
        assert maintain.insert(grid, none).moved == []
