import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["worked_example_13", "packing_example", "presc_q3", "grid_df_q3", "pages_duration_first", "meter_start_first_presc", "winner_counts", "stream_gaps", "rel_join_asof"]


def plain(v):
    return round(v, 6) if isinstance(v, float) else tuple(map(plain, v)) if isinstance(v, list) else v


@pytest.mark.parametrize("name", SOME)
def test_twin(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = entry.queries()[name](spark, sf)
    want = con.sql(entry.oracle_sql()[name])
    order = sorted(got.columns)
    assert order == sorted(want.columns)
    rows = lambda it, cols: sorted((tuple(plain(r[cols.index(c)]) for c in order) for r in it), key=repr)
    assert rows(map(tuple, got.collect()), got.columns) == rows(want.fetchall(), want.columns)


def test_entry(spark):
    assert [tuple(r) for r in entry.entry(spark).collect()] == [(0, 72)]


def test_published_winners(spark, sf):
    got = {(r["dataset"], r["winner"]): r["count"] for r in entry.queries()["winner_map"](spark, sf).groupBy("dataset", "winner").count().collect()}
    assert got[("synthetic", "duration_first")] == 185 and got[("flights", "ordered_duration")] == 76 and got[("clinical", "start_first")] == 63


GIVEN = ["crossover_duration_share", "empty_window", "inverted_band", "mixed_rate_center", "packing_example", "rel_udtf_lattice", "synthetic_profile", "synthetic_skewed_uniform_rows", "synthetic_uniform_zipf_rows", "winner_counts"]


@pytest.mark.parametrize("name", GIVEN)
def test_reads_a_given_table(spark, sf, name):
    """The optimized plan still scans a table, and the results are those of the SQL."""
    got = entry.queries()[name](spark, sf)
    assert " parquet" in got._jdf.queryExecution().optimizedPlan().toString()
    if name in entry.oracle_sql():
        test_twin(spark, sf, name)
