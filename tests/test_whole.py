"""Queries over whole tables, against their SQL and brute force."""

import duckdb
import pytest
from test_entry import TABLES

import __spark_entry__ as entry
from spangrid.operators import grid as g


def twin(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = entry.queries()[name](spark, sf)
    want = con.sql(entry.oracle_sql()[name])
    order = sorted(got.columns)
    assert order == sorted(want.columns)
    rows = lambda it, cols: sorted((tuple(r[cols.index(c)] for c in order) for r in it), key=repr)
    found = rows(map(tuple, got.collect()), got.columns)
    assert found == rows(want.fetchall(), want.columns)
    return con, found


@pytest.mark.parametrize("name, table", [("interval_overlap_counts", "trips"), ("event_in_any_interval_join", "gaps")])
def test_joins_of_every_length(spark, sf, name, table):
    from spangrid.plans import twins

    con, found = twin(spark, sf, name)
    assert len(found) == con.sql(f"SELECT count(*) FROM ({twins.RELATIONS[table]})").fetchall()[0][0]  # each meets itself or its own event


def test_below(spark):
    keys, probes = [5, 5, 7, -3, 10**12], [(1, 5), (2, 6), (3, -9), (4, 10**13), (5, 5), (6, 10**12)]
    for buckets in (1, 2, 4096):
        got = g.below(spark.createDataFrame([(k,) for k in keys], "x long"), spark.createDataFrame(probes, "id int, x long"), buckets).collect()
        assert sorted((r["id"], r["n_below"]) for r in got) == [(i, sum(k < x for k in keys)) for i, x in probes]
    assert [r["n_below"] for r in g.below(spark.createDataFrame([], "x long"), spark.createDataFrame([(1, 5)], "id int, x long")).collect()] == [0]


def test_unpivot_of_all_events(spark, sf):
    con, found = twin(spark, sf, "rel_unpivot_whole")
    assert len(found) == 2 * con.sql("SELECT count(*) FROM events").fetchall()[0][0]


def test_days_of_all_intervals(spark, sf):
    from spangrid.plans import twins

    con, found = twin(spark, sf, "rel_explode_days_whole")
    assert sum(n for _, n in found) == con.sql(f"SELECT sum(dur) FROM ({twins.RELATIONS['presc']})").fetchall()[0][0]


def test_grid_count(spark, sf, tmp_path):
    """Boundary pages count too, also for a query that covers no page."""
    from spangrid.functions import surface
    from spangrid.plans import catalog
    from spangrid.sources.intervals import presc

    _, found = twin(spark, sf, "grid_count")
    assert any(n for _, n in found)
    df = catalog.slim(spark, sf, "presc")
    one = presc(spark, sf).select("t_lo", "dur").first()
    surface.register(spark)
    for order in (g.START_FIRST, g.DURATION_FIRST):
        at = str(tmp_path / order)
        g.build_grid(df, g.GridSpec(50, order=order)).save(f"file://{at}")
        for path in (at, f"file://{at}"):
            for q in ((one["t_lo"], one["t_lo"] + 1, one["dur"], one["dur"]), (9770, 9952, None, None), (None, None, None, None), (None, 9770, 30, None), (5, 5, None, None)):
                lo, hi, a, b = ("NULL" if v is None else v for v in q)
                got = spark.sql(f"SELECT * FROM grid_count('{path}', {lo}, {hi}, {a}, {b})").collect()
                ok = " AND ".join(["TRUE", *(f"{c} {v}" for c, v in (("t_lo <", q[1]), ("t_hi >", q[0]), ("dur >=", q[2]), ("dur <=", q[3])) if v is not None)])
                assert [r["matched"] for r in got] == [0 if q[0] == q[1] == 5 else df.filter(ok).count()]
