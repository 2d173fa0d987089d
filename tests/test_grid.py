import pytest
from pyspark.sql import functions as F

from spangrid.model import Query
from spangrid.operators import baselines, maintain
from spangrid.operators.grid import DURATION_FIRST, START_FIRST, GridSpec, build_grid, open_grid
from spangrid.operators.selections import select
from spangrid.sources.intervals import presc
from spangrid.sources.workload import query_set, random_queries

ROWS = "iv_id long, t_lo long, t_hi long, dur long"


@pytest.fixture(scope="module")
def df(spark, sf):
    return presc(spark, sf).select("iv_id", "t_lo", "t_hi", "dur").cache()


@pytest.fixture(scope="module")
def queries(spark):
    args = ((9132, 11680), (1, 300), (1, 50))
    q = random_queries(spark, "both", 12, 3, *args)
    for i, kind in enumerate(("range", "duration"), 1):
        q = q.unionByName(random_queries(spark, kind, 6, 3, *args).withColumn("qid", F.col("qid") + 100 * i))
    return q.cache()


def counts(layout, queries):
    return sorted(tuple(r) for r in layout.count_batch(queries).collect())


@pytest.mark.parametrize("order, shape", [(START_FIRST, (16, 378, 0, 0, 20)), (DURATION_FIRST, (17, 308, 0, 0, 20))])
def test_shape_and_answers(spark, df, queries, order, shape):
    grid = build_grid(df, GridSpec(20, order=order))
    d = grid.describe().first()
    assert (d["columns"], d["cells"], d["heavy_columns"], d["heavy_cells"], d["largest_cell"]) == shape
    assert grid.rows.select("iv_id", "t_lo", "t_hi", "dur").exceptAll(df).isEmpty() and df.exceptAll(grid.rows.select("iv_id", "t_lo", "t_hi", "dur")).isEmpty()
    assert grid.rows.groupBy(GridSpec(20, order=order).keys[0]).agg(F.count_distinct("col_id").alias("c")).filter("c > 1").isEmpty()
    assert counts(grid, queries) == counts(baselines.Scan(df), queries)
    for r in grid.meter(queries).collect():
        assert r["matched"] <= r["examined"] <= r["examined_incl_stop"]


def test_saved_and_pruned(spark, df, tmp_path):
    grid = build_grid(df, GridSpec(20)).save(f"file://{tmp_path}/g")
    again = open_grid(spark, f"file://{tmp_path}/g")
    q = Query(9770, 9952, 7, 14)
    assert again.find(q).count() == select(df, q).count() == 72
    assert again.count(q).first()["matched"] == 72
    plan = again.find(q)._jdf.queryExecution().toString()
    assert "PartitionFilters: [" in plan and "col_id" in plan.split("PartitionFilters: [")[1].split("]")[0]
    assert again.find(Query(5, 5)).isEmpty() and again.find(Query(None, None, 9, 8)).isEmpty()
    from spangrid.sources.datasource import read_grid

    assert read_grid(spark, f"file://{tmp_path}/g").filter("t_lo < 9952 and t_hi > 9770 and dur >= 7 and dur <= 14").count() == 72
    assert grid.spec == again.spec


@pytest.mark.parametrize("name", ["ordered_duration", "ordered_start", "two_indexes", "interval_tree", "uniform_grid", "replicating", "packed_tree"])
def test_baselines_agree(df, queries, name):
    assert counts(baselines.all_layouts(df)[name](), queries) == counts(baselines.Scan(df), queries)


@pytest.mark.parametrize("order", [START_FIRST, DURATION_FIRST])
def test_insert_and_remove(df, queries, order):
    some, rest = df.filter("pmod(iv_id, 3) <> 0"), df.filter("pmod(iv_id, 3) = 0")
    grid = maintain.insert(build_grid(some, GridSpec(20, order=order)), rest)
    assert counts(grid, queries) == counts(baselines.Scan(df), queries)
    assert grid.pages.filter("n > 20").isEmpty()
    assert counts(maintain.remove(grid, rest), queries) == counts(baselines.Scan(some), queries)


def test_appends_leave_the_files_of_earlier_columns(spark):
    """Rows by increasing start restructure only the last column; the others stay in the files they are in."""
    rows = lambda a, b: spark.range(a, b).select(F.col("id").alias("iv_id"), F.col("id").alias("t_lo"), (F.col("id") + 1 + F.col("id") % 7).alias("t_hi"), (1 + F.col("id") % 7).alias("dur"))
    grid = maintain.insert(build_grid(rows(0, 200), GridSpec(5, order=START_FIRST)), rows(200, 210))
    ids = lambda g: [r[0] for r in g.columns.orderBy("min_key").select("col_id").collect()]
    last = ids(grid)[-1]
    files = lambda g, cols: {r[0] for r in g.rows.filter(F.col("col_id").isin(cols)).select(F.input_file_name()).distinct().collect()}
    before = {c: files(grid, [c]) for c in ids(grid)}
    after = maintain.insert(grid, rows(210, 230))
    fresh = set(ids(after)) - set(before)
    assert set(after.moved) <= fresh | {last} and {r[0] for r in maintain.rewritten(grid, after).collect()} <= fresh | {last}
    assert all(files(after, [c]) == before[c] for c in before if c != last)
    assert counts(after, query_set(spark, [(1, "range", 0, 500, None, None), (2, "both", 100, 215, 2, 3)])) == [(1, 230), (2, len([i for i in range(230) if i < 215 and i + 1 + i % 7 > 100 and 2 <= 1 + i % 7 <= 3]))]
    less = maintain.remove(after, rows(0, 10))
    assert last not in less.moved and counts(less, query_set(spark, [(1, "range", 0, 500, None, None)])) == [(1, 220)]
    for _ in range(2):
        maintain.MOST_LAYERS, was = 1, maintain.MOST_LAYERS
        try:
            less = maintain.insert(less, rows(230, 232).withColumn("iv_id", F.col("iv_id") + 1000))
        finally:
            maintain.MOST_LAYERS = was
    assert less.layers == 1 and counts(less, query_set(spark, [(1, "range", 0, 500, None, None)])) == [(1, 224)]


def test_examined_rows_stay_within_the_bound(df, queries):
    """Rows read and pages compared, against the bound of a query, with its constant."""
    from spangrid.operators.measures import query_bound

    n = df.count()
    for s in (5, 20):
        for r in build_grid(df, GridSpec(s)).meter(queries).collect():
            assert r["examined"] + r["cells_visited"] <= 4 * query_bound(n, s, r["matched"]) + 50 * s


def test_identical_rows_and_a_new_key(spark):
    rows = [(i, 10, 13, 3) for i in range(5)]
    grid = maintain.insert(build_grid(spark.createDataFrame(rows, ROWS), GridSpec(2)), spark.createDataFrame([(6, 10, 13, 3), (7, 10, 14, 4), (8, 2, 3, 1)], ROWS))
    q = query_set(spark, [(1, "duration", None, None, 3, 3), (2, "duration", None, None, 4, 4), (3, "range", 2, 3, None, None)])
    assert counts(grid, q) == [(1, 6), (2, 1), (3, 1)]
    assert not grid.pages.filter("heavy and min_dur < max_dur").count()


def test_empty_table(spark):
    grid = build_grid(spark.createDataFrame([], ROWS), GridSpec(5))
    assert grid.find(Query(1, 5)).isEmpty()
    assert counts(grid, query_set(spark, [(1, "range", 1, 5, None, None)])) == [(1, 0)]


def test_inserting_tree():
    tree = baselines.InsertingTree(8)
    pts = [((i * 7919) % 1000, 1 + (i * 104729) % 50) for i in range(600)]
    for p in pts:
        tree.insert(*p)
    want = sorted(p for p in pts if p[0] < 400 and p[0] + p[1] > 300 and 5 <= p[1] <= 20)
    assert sorted(tree.find(300, 400, 5, 20)) == want and tree.splits > 0


def test_two_indexes_intersect_only_where_both_bound(spark, df, queries):
    """A query of one dimension takes the candidates of its own order and meets no other row."""
    index = baselines.TwoIndexes(df)
    for kind in ("range", "duration"):
        one = queries.filter(F.col("kind") == kind)
        assert "replicaterows" not in index.find_batch(one)._jdf.queryExecution().optimizedPlan().toString().lower()
        assert counts(index, one) == counts(baselines.Scan(df), one)
    assert counts(index, queries) == counts(baselines.Scan(df), queries)


def test_removals_cut_all_merged_columns_in_one_job(spark, monkeypatch):
    rows = spark.range(3000).selectExpr("id AS iv_id", "id AS t_lo", "id + 1 + id % 7 AS t_hi", "1 + id % 7 AS dur")
    grid = build_grid(rows, GridSpec(6, order=START_FIRST))
    packs = []
    pack = maintain.pack
    monkeypatch.setattr(maintain, "pack", lambda *a, **k: packs.append(1) or pack(*a, **k))
    less = maintain.remove(grid, rows.filter("iv_id % 5 <> 0"))
    assert less.columns.count() < grid.columns.count() and len(packs) == 1
    assert less.rows.count() == 600 and less.pages.agg(F.sum("n")).first()[0] == 600


def test_sweep_holds_one_grid_at_a_time(spark, sf):
    """What is returned reads six written answers; no joins of six grids are planned at once."""
    from spangrid.plans import catalog

    assert "Join" not in catalog.QUERIES["page_sweep_examined"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
