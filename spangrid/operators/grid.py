"""The adaptive grid: rows in columns of the first key and, within each, cells of the second, at cuts read off the data.

Both keys are the start and the length, in either order. Cuts come from histograms packed so that equal keys stay together;
rows find their cell by binary search in the shared cuts, and one range shuffle clusters them by column, cell and
descending end. A directory of columns and of pages (cells) says which a query may skip.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.predicates import after, at_least, at_most, before, implied_bounds, matches, polygon, valid
from ..model import Query
from ..storage import forget, shared_dir, written
from .layouts import QUERY_COLUMNS, Layout, small
from .packing import EXACT_KEYS, pack, runs

START_FIRST, DURATION_FIRST = "start_first", "duration_first"
#: Ranges of cells named in a scan's predicate; beyond it the scan joins the directory.
NAMED_RANGES = 2000
#: Pages of a directory that the driver holds as arrays (about 100 bytes a page); beyond it a query asks the directory in a job.
HELD_PAGES = 2_000_000


@dataclass(frozen=True)
class GridSpec:
    """cell_rows is the page size s; column_rows defaults to s * s, and must be given apart from it once s * s nears the rows."""

    cell_rows: int
    column_rows: int | None = None
    order: str = DURATION_FIRST
    packing: str = "auto"
    payload: str = "rows"

    @property
    def budget(self) -> int:
        return self.column_rows or self.cell_rows**2

    @property
    def keys(self) -> tuple[str, str]:
        return ("t_lo", "dur") if self.order == START_FIRST else ("dur", "t_lo")

    @staticmethod
    def at_scale(rows: int, cell_rows: int = 2_000_000, order: str = DURATION_FIRST) -> GridSpec:
        """Sizes for very many rows: about as many columns as cells in a column."""
        return GridSpec(cell_rows, int(np.ceil(np.sqrt(rows * cell_rows))), order)


class Cuts:
    """First keys of the columns, and of each column's cells."""

    def __init__(self, columns: np.ndarray, cells: list[np.ndarray], ids: np.ndarray | None = None):
        self.columns = columns
        self.ids = np.arange(len(columns)) if ids is None else ids  # ids keep their rows' place when columns split
        self.first = np.concatenate([[0], np.cumsum([len(c) for c in cells])]).astype(np.int64)
        self.cells = np.concatenate(cells) if cells else np.zeros(0, np.int64)

    def cells_of(self, place: int) -> np.ndarray:
        return self.cells[self.first[place] : self.first[place + 1]]

    def column_of(self, key: np.ndarray) -> np.ndarray:
        """A key below the first cut goes to the first column."""
        return np.maximum(np.searchsorted(self.columns, key, "right") - 1, 0)

    def cell_of(self, column: np.ndarray, key: np.ndarray) -> np.ndarray:
        """Binary search in each row's own column, all rows at once."""
        lo, hi = self.first[column], self.first[column + 1]
        base = lo.copy()
        while (lo < hi).any():
            mid = (lo + hi) // 2
            right = (lo < hi) & (self.cells[np.minimum(mid, len(self.cells) - 1)] <= key)
            left = (lo < hi) & ~right
            lo, hi = np.where(right, mid + 1, lo), np.where(left, mid, hi)
        return np.maximum(lo - base - 1, 0)


def route(df: DataFrame, cuts: Cuts, spec: GridSpec) -> DataFrame:
    """df with col_id and cell_id of the cell each row belongs to."""
    shared = df.sparkSession.sparkContext.broadcast(cuts)  # one number a page

    @F.pandas_udf("col_id int, cell_id int")
    def find(first: pd.Series, second: pd.Series) -> pd.DataFrame:
        c = shared.value
        column = c.column_of(first.to_numpy())
        return pd.DataFrame({"col_id": c.ids[column].astype(np.int32), "cell_id": c.cell_of(column, second.to_numpy()).astype(np.int32)})

    key = spec.keys
    return df.withColumn("_at", find(F.col(key[0]), F.col(key[1]))).select(*df.columns, "_at.col_id", "_at.cell_id")


def cut(df: DataFrame, spec: GridSpec) -> Cuts:
    """The cuts for df: two histograms, of the first key and of the second key within columns, both from one table of pairs."""
    first, second = spec.keys
    pairs = written(df.groupBy("t_lo", "dur").agg(F.count("*").alias("c")), "pairs")
    histogram = written(pairs.groupBy(F.col(first).alias("key")).agg(F.sum("c").alias("n")), "histogram")
    form = spec.packing
    if form == "auto":
        form = "exact" if histogram.count() <= EXACT_KEYS else "sharded"
    columns = np.array([r[0] for r in pack(histogram, spec.budget, form=form).groupBy("grp").agg(F.min("key").alias("k")).select("k").orderBy("k").collect()], np.int64)
    if not len(columns):
        return Cuts(columns, [])
    placed = route(pairs, Cuts(columns, [np.zeros(1, np.int64)] * len(columns)), spec)
    inner = pack(placed.groupBy("col_id", F.col(second).alias("key")).agg(F.sum("c").alias("n")), spec.cell_rows, by="col_id", form="quantile" if form == "quantile" else "exact")
    cells = inner.groupBy("col_id", "grp").agg(F.min("key").alias("k")).orderBy("col_id", "k").toPandas()  # one row a page
    forget(pairs, histogram)
    return Cuts(columns, [g["k"].to_numpy(np.int64) for _, g in cells.groupby("col_id")])


def page_stats(rows: DataFrame) -> DataFrame:
    """n and the spans of starts, ends and lengths of each page of routed rows."""
    spans = [f(c).alias(f"{f.__name__}_{n}") for n, c in (("lo", "t_lo"), ("hi", "t_hi"), ("dur", "dur")) for f in (F.min, F.max)]
    return rows.groupBy("col_id", "cell_id").agg(F.count("*").alias("n"), *spans)


def running(pages: DataFrame, spec: GridSpec) -> DataFrame:
    """Pages with the running maximum of the ends within their column."""
    second = "min_dur" if spec.order == START_FIRST else "min_lo"
    upto = Window.partitionBy("col_id").orderBy(second).rowsBetween(Window.unboundedPreceding, 0)
    return pages.withColumn("run_max_hi", F.max("max_hi").over(upto)).withColumn("heavy", F.col("n") > F.lit(spec.cell_rows))


def directory(rows: DataFrame, spec: GridSpec) -> tuple[DataFrame, DataFrame]:
    """(pages, columns) of routed rows, with running maxima of the ends."""
    pages = written(running(page_stats(rows), spec), "pages")
    return pages, column_stats(pages, spec)


def column_stats(pages: DataFrame, spec: GridSpec) -> DataFrame:
    key = "lo" if spec.order == START_FIRST else "dur"
    columns = pages.groupBy("col_id").agg(
        F.sum("n").alias("n"), F.min(f"min_{key}").alias("min_key"), F.max(f"max_{key}").alias("max_key"), F.max("max_hi").alias("max_hi"), F.count("*").alias("n_cells")
    )
    whole = Window.orderBy("min_key").rowsBetween(Window.unboundedPreceding, 0)  # over columns only, which are few
    columns = columns.withColumn("run_max_hi", F.max("max_hi").over(whole)).withColumn("heavy", F.col("n") > F.lit(spec.budget))
    return written(columns, "columns")


class Grid(Layout):
    """A built grid; ``rows`` carry col_id and cell_id."""

    name = "grid"

    def __init__(self, rows: DataFrame, pages: DataFrame, columns: DataFrame, spec: GridSpec, cuts: Cuts):
        self.pages, self.columns, self.spec, self.cuts = pages, columns, spec, cuts
        self._held: dict[str, np.ndarray] | None = None
        self.layers, self.moved, self.parts = 0, [], []  # writes its rows lie in, columns the last batch changed, what that batch wrote
        bounds = columns.select("col_id", F.col("min_key").alias("c_min"), F.col("max_key").alias("c_max"), F.col("run_max_hi").alias("c_run"))
        super().__init__(rows, pages.join(F.broadcast(bounds), "col_id"), ["col_id", "cell_id"])

    def column_meets(self) -> Column:
        if self.spec.order == START_FIRST:
            return before(F.col("c_min"), F.col("q_hi")) & after(F.col("c_run"), F.col("q_lo"))
        return at_most(F.col("c_min"), F.col("d_max")) & at_least(F.col("c_max"), F.col("d_min"))

    def cell_meets(self) -> Column:
        if self.spec.order == START_FIRST:
            return at_most(F.col("min_dur"), F.col("d_max")) & at_least(F.col("max_dur"), F.col("d_min"))
        return before(F.col("min_lo"), F.col("q_hi")) & after(F.col("run_max_hi"), F.col("q_lo"))

    def meets(self) -> Column:
        return self.column_meets() & self.cell_meets()

    def reads(self) -> Column:
        return after(F.col("t_hi"), F.col("q_lo"))

    def visited_columns(self) -> Column:
        return F.col("col_id")

    def visit(self, queries: DataFrame) -> DataFrame:
        return self._visited(queries).select(*QUERY_COLUMNS, *self.gid, "n")

    def _visited(self, queries: DataFrame) -> DataFrame:
        """Columns first, so the comparison of queries with pages stays within the columns they touch."""
        few = small(queries.filter(valid()))
        bounds = self.columns.select("col_id", F.col("min_key").alias("c_min"), F.col("max_key").alias("c_max"), F.col("run_max_hi").alias("c_run"))
        return bounds.join(few, self.column_meets()).join(self.pages, "col_id").filter(self.cell_meets())

    def classify(self, q: Query, prune: str = "running") -> DataFrame:
        """Visited pages with their class: covered, duration_cut, start_cut or corner. prune='zone' also uses each page's own ends."""
        seen = self.visit(q.frame(self.pages.sparkSession)).select("col_id", "cell_id")
        pages = self.pages.join(F.broadcast(seen), ["col_id", "cell_id"])
        if prune == "zone":
            p = Query(q.q_lo, q.q_hi)
            pages = pages.filter(F.lit(True) if p.q_hi is None else F.col("min_lo") < p.q_hi).filter(F.lit(True) if p.q_lo is None else F.col("max_hi") > p.q_lo)
        yes = F.lit(True)
        start = (yes if q.q_hi is None else F.col("max_lo") < q.q_hi) & (yes if q.q_lo is None else F.col("min_hi") > q.q_lo)
        band = (yes if q.d_min is None else F.col("min_dur") >= q.d_min) & (yes if q.d_max is None else F.col("max_dur") <= q.d_max)
        return pages.withColumn("cls", F.when(start & band, "covered").when(start, "duration_cut").when(band, "start_cut").otherwise("corner"))

    def held(self) -> dict[str, np.ndarray] | None:
        """The directory as arrays, fetched once; None if it is too large for the driver."""
        if self._held is None and len(self.cuts.cells) <= HELD_PAGES:
            table = self.groups.toArrow()
            self._held = {c: table.column(c).to_numpy() for c in table.column_names if c != "heavy"}
        return self._held

    def _seen(self, p: dict[str, np.ndarray], q: Query, prune: str) -> tuple[np.ndarray, np.ndarray]:
        """Of the pages p: which a query visits, and which of them it covers."""
        seen, sure = np.ones(len(p["n"]), bool), np.ones(len(p["n"]), bool)
        by_start = self.spec.order == START_FIRST
        if q.q_hi is not None:
            seen &= p["c_min" if by_start else "min_lo"] < q.q_hi
            sure &= p["max_lo"] < q.q_hi
        if q.q_lo is not None:
            seen &= p["c_run" if by_start else "run_max_hi"] > q.q_lo
            sure &= p["min_hi"] > q.q_lo
        if q.d_max is not None:
            seen &= p["min_dur" if by_start else "c_min"] <= q.d_max
            sure &= p["max_dur"] <= q.d_max
        if q.d_min is not None:
            seen &= p["max_dur" if by_start else "c_max"] >= q.d_min
            sure &= p["min_dur"] >= q.d_min
        if prune == "zone":
            seen &= (True if q.q_hi is None else p["min_lo"] < q.q_hi) & (True if q.q_lo is None else p["max_hi"] > q.q_lo)
        return seen, seen & sure

    def find(self, q: Query, prune: str = "running") -> DataFrame:
        """The rows of one query: literal column and cell ranges for the scan, and the residual test."""
        if q.empty:
            return self.rows.filter(F.lit(False))
        p = self.held()
        if p is None:
            rows = self.rows.join(self.classify(q, prune).select("col_id", "cell_id"), ["col_id", "cell_id"], "left_semi")
        else:
            seen, _ = self._seen(p, q, prune)
            rows = self._scan(p["col_id"][seen], p["cell_id"][seen], whole=True)
        return rows.filter(polygon(q)).filter(implied_bounds(q))

    def _scan(self, columns: np.ndarray, cells: np.ndarray, whole: bool = False) -> DataFrame | None:
        """The rows of some pages, by the columns' ids and ranges of cells. ``whole`` takes all cells of a column between its first
        and last one, which a residual test must then sort out; else None if there are too many ranges."""
        order = np.lexsort((cells, columns))
        c, x = columns[order].astype(np.int64), cells[order].astype(np.int64)
        new = np.ones(len(c), bool)
        new[1:] = c[1:] != c[:-1]
        if not whole:
            new[1:] |= x[1:] != x[:-1] + 1
        first = np.flatnonzero(new)
        last = np.append(first[1:], len(c)) - 1 if len(first) else first
        if not len(first):
            return self.rows.filter(F.lit(False))
        if len(first) > NAMED_RANGES:
            return self.rows.filter(F.col("col_id").between(int(c[0]), int(c[-1]))) if whole else None
        by_range: dict[tuple[int, int], list[int]] = {}
        for i, a, b in zip(c[first].tolist(), x[first].tolist(), x[last].tolist()):
            by_range.setdefault((a, b), []).append(i)
        inner = None
        for (a, b), ids in by_range.items():
            part = F.col("col_id").isin(ids) & F.col("cell_id").between(a, b)
            inner = part if inner is None else inner | part
        return self.rows.filter(F.col("col_id").isin(sorted(set(c.tolist())))).filter(inner)

    def count(self, q: Query, use_directory: bool = True) -> DataFrame:
        """matched, in one job; pages the query covers are counted from the directory and not read."""
        p = self.held() if use_directory and not q.empty else None
        if p is not None:
            seen, sure = self._seen(p, q, "running")
            rest = self._scan(p["col_id"][seen & ~sure], p["cell_id"][seen & ~sure])
            if rest is not None:
                return rest.filter(polygon(q)).agg((F.count("*") + F.lit(int(p["n"][sure].sum()))).cast("long").alias("matched"))
        return self.find(q).agg(F.count("*").alias("matched"))

    def count_batch(self, queries: DataFrame) -> DataFrame:
        """qid and matched, also of queries without answers: covered pages add what the directory says, and only rows of pages that
        a query cuts meet that query."""
        inside = before(F.col("max_lo"), F.col("q_hi")) & after(F.col("min_hi"), F.col("q_lo")) & at_least(F.col("min_dur"), F.col("d_min")) & at_most(F.col("max_dur"), F.col("d_max"))
        seen = written(self._visited(queries).withColumn("covered", inside).select(*QUERY_COLUMNS, *self.gid, "n", "covered"), "visits")
        sure = seen.filter("covered").groupBy("qid").agg(F.sum("n").alias("c"))
        cut_pages = seen.filter("not covered").drop("n", "covered")
        got = self.rows.select(*self.gid, "t_lo", "t_hi", "dur").join(cut_pages, self.gid).filter(matches()).groupBy("qid").agg(F.count("*").alias("c"))
        both = sure.unionByName(got).groupBy("qid").agg(F.sum("c").alias("c"))
        return queries.select("qid").join(both, "qid", "left").select("qid", F.coalesce("c", F.lit(0)).cast("long").alias("matched"))

    def describe(self) -> DataFrame:
        """columns, cells, heavy columns and cells, rows of the largest cell, and largest over mean."""
        p = self.pages.agg(F.count("*").alias("cells"), F.count_if("heavy").alias("heavy_cells"), F.max("n").alias("largest_cell"), F.sum("n").alias("total"))
        c = self.columns.agg(F.count("*").alias("columns"), F.count_if("heavy").alias("heavy_columns"))
        return c.crossJoin(p).select("columns", "cells", "heavy_columns", "heavy_cells", "largest_cell", (F.col("largest_cell") * F.col("cells") / F.col("total")).alias("imbalance"), (F.col("columns") <= 1).alias("degenerate"))

    def clustered(self, parts: int | None = None) -> DataFrame:
        """rows in one range shuffle by column, cell and descending end; a heavy cell may fill several partitions."""
        return clustered(self.rows, parts)

    def save(self, path: str, max_rows: int = 5_000_000) -> Grid:
        """Writes rows (one folder a column, files of bounded rows), then the directory, then the manifest."""
        _write_rows(self.rows, path, max_rows)
        return _commit(self.rows.sparkSession, path, self.pages, self.columns, self.spec)


def clustered(rows: DataFrame, parts: int | None = None) -> DataFrame:
    n = parts or int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = [F.col("col_id"), F.col("cell_id"), F.col("t_hi").desc()]
    return rows.repartitionByRange(n, *order).sortWithinPartitions(*order)


def _write_rows(rows: DataFrame, path: str, max_rows: int) -> None:
    clustered(rows).write.option("maxRecordsPerFile", max_rows).partitionBy("col_id").mode("overwrite").parquet(f"{path}/rows")


def _commit(spark, path: str, pages: DataFrame, columns: DataFrame, spec: GridSpec) -> Grid:
    pages.write.mode("overwrite").parquet(f"{path}/pages")
    columns.write.mode("overwrite").parquet(f"{path}/columns")
    spark.createDataFrame([(json.dumps(asdict(spec)),)], "spec string").coalesce(1).write.mode("overwrite").json(f"{path}/manifest")
    return open_grid(spark, path)


def open_grid(spark, path: str) -> Grid:
    spec = GridSpec(**json.loads(spark.read.json(f"{path}/manifest").first()["spec"]))
    pages, columns = spark.read.parquet(f"{path}/pages"), spark.read.parquet(f"{path}/columns")
    return Grid(spark.read.parquet(f"{path}/rows"), pages, columns, spec, cuts_of(pages, columns, spec))


def cuts_of(pages: DataFrame, columns: DataFrame, spec: GridSpec) -> Cuts:
    """The cuts a directory stands for: least keys of its columns and cells."""
    second = "min_dur" if spec.order == START_FIRST else "min_lo"
    own = columns.orderBy("min_key").toPandas()
    cells = {c: g[second].to_numpy(np.int64) for c, g in pages.select("col_id", "cell_id", second).orderBy("col_id", "cell_id").toPandas().groupby("col_id")}
    return Cuts(own["min_key"].to_numpy(np.int64), [cells[c] for c in own["col_id"]], own["col_id"].to_numpy(np.int64))


def build_grid(df: DataFrame, spec: GridSpec) -> Grid:
    """The grid over df (normalised intervals). Nothing but histograms moves until the grid is saved or clustered."""
    rows, cuts = _routed(df, spec)
    return Grid(rows, *directory(rows, spec), spec, cuts)


def _routed(df: DataFrame, spec: GridSpec) -> tuple[DataFrame, Cuts]:
    if spec.payload == "ref":
        df = df.select("iv_id", "t_lo", "t_hi", "dur")
    cuts = cut(df, spec)
    empty = F.lit(0).cast("int")
    return (route(df, cuts, spec) if len(cuts.columns) else df.withColumns({"col_id": empty, "cell_id": empty})), cuts


def build_saved(df: DataFrame, spec: GridSpec, path: str, max_rows: int = 5_000_000) -> Grid:
    """build_grid and save in one: rows are routed once, as they are written, and the directory is read off what is written."""
    rows, _ = _routed(df, spec)
    _write_rows(rows, path, max_rows)
    there = df.sparkSession.read.schema(rows.schema).parquet(f"{path}/rows")
    return _commit(df.sparkSession, path, *directory(there, spec), spec)


def saved_grid(df: DataFrame, spec: GridSpec, name: str) -> Grid:
    """A grid in the shared folder."""
    import uuid

    out = build_saved(df, spec, f"{shared_dir(df.sparkSession)}/grid-{name}-{uuid.uuid4().hex}")
    out.layers = 1  # its files are nobody else's, so a batch can leave them as they are
    return out


def fetch(base: DataFrame, thin: DataFrame) -> DataFrame:
    """Rows of the base table that a thin grid's answers refer to."""
    return base.join(thin.select("iv_id"), "iv_id", "left_semi")


def tune(df: DataFrame, queries: DataFrame, sizes: list[int], orders: tuple[str, ...] = (START_FIRST, DURATION_FIRST), visit_cost: float = 1.0) -> DataFrame:
    """Page sizes and orders by examined rows plus visit_cost for each cell visited, best first."""
    out = None
    for order in orders:
        for s in sizes:
            m = build_grid(df, GridSpec(s, order=order)).meter(queries).agg(F.sum("examined").alias("examined"), F.sum("cells_visited").alias("cells_visited"))
            m = m.select(F.lit(order).alias("grid_order"), F.lit(s).alias("cell_rows"), "examined", "cells_visited", (F.col("examined") + visit_cost * F.col("cells_visited")).alias("cost"))
            out = m if out is None else out.unionByName(m)
    return out.orderBy("cost", "grid_order", "cell_rows")


def advise_order(df: DataFrame, queries: DataFrame, cell_rows: int) -> DataFrame:
    return tune(df, queries, [cell_rows])


def interval_join(a: DataFrame, b: DataFrame, width: int, d_min: int | None = None, d_max: int | None = None) -> DataFrame:
    """(a_id, b_id) of intersecting intervals, optionally of rows in a band, by time slots of a width.

    Both sides are copied to the slots they meet; a pair is kept in the slot where its common part begins, so it appears once.
    """
    slot = lambda x: F.floor(F.col(x) / F.lit(width))
    keep = at_least(F.col("dur"), F.lit(d_min).cast("long")) & at_most(F.col("dur"), F.lit(d_max).cast("long"))
    side = lambda df, p: df.filter(keep).select(F.col("iv_id").alias(f"{p}_id"), F.col("t_lo").alias(f"{p}_lo"), F.col("t_hi").alias(f"{p}_hi"), F.explode(F.sequence(slot("t_lo"), F.floor((F.col("t_hi") - 1) / F.lit(width)))).alias("slot"))
    both = side(a, "a").join(side(b, "b"), "slot").filter((F.col("a_lo") < F.col("b_hi")) & (F.col("b_lo") < F.col("a_hi")))
    return both.filter(F.floor(F.greatest("a_lo", "b_lo") / F.lit(width)) == F.col("slot")).select("a_id", "b_id")


def below(keys: DataFrame, probes: DataFrame, buckets: int = 4096) -> DataFrame:
    """probes (x and other columns) with n_below, how many of keys (x) are smaller: exact at every size, as keys are counted by
    value, ranked within buckets of the axis and carried over from bucket to bucket."""
    from pyspark.sql import Window

    ends = keys.agg(F.min("x").alias("a"), F.max("x").alias("b")).first()
    if ends["a"] is None:
        return probes.withColumn("n_below", F.lit(0).cast("long"))
    width = max(1, -(-(ends["b"] - ends["a"] + 1) // buckets))
    bucket = F.least(F.lit(buckets), F.greatest(F.lit(-1), F.floor((F.col("x") - F.lit(ends["a"])) / F.lit(width)))).cast("int").alias("_b")
    counted = written(keys.groupBy("x").agg(F.count("*").alias("_c")).select("x", "_c", bucket), "keys")
    before = counted.groupBy("_b").agg(F.sum("_c").alias("_n"))  # at most ``buckets`` rows
    every = keys.sparkSession.range(-1, buckets + 1).select(F.col("id").cast("int").alias("_b")).join(F.broadcast(before), "_b", "left")
    ahead = every.select("_b", F.coalesce(F.sum("_n").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_ahead"))
    own = probes.select(F.struct(*probes.columns).alias("_p"), "x").groupBy("x").agg(F.collect_list("_p").alias("_p"))
    asked = own.select("x", "_p", bucket, F.lit(0).cast("long").alias("_c"))
    both = asked.unionByName(counted.withColumn("_p", F.lit(None).cast(asked.schema["_p"].dataType)))
    w = Window.partitionBy("_b").orderBy("x", F.col("_p").isNull()).rowsBetween(Window.unboundedPreceding, 0)  # probes before keys of their value
    ranked = both.withColumn("_r", F.sum("_c").over(w)).filter("_p is not null").join(F.broadcast(ahead), "_b")
    return ranked.select(F.explode("_p").alias("_p"), (F.col("_r") + F.col("_ahead")).cast("long").alias("n_below")).select("_p.*", "n_below")


def _differences(parts: list[tuple[DataFrame, DataFrame, int]]) -> DataFrame:
    out = None
    for keys, probes, sign in parts:
        one = below(keys, probes).select("interval_id", (F.lit(sign) * F.col("n_below")).alias("n"))
        out = one if out is None else out.unionByName(one)
    return out.groupBy("interval_id").agg(F.sum("n").cast("long").alias("n")).filter("n > 0")


def points_within(intervals: DataFrame, points: DataFrame) -> DataFrame:
    """(interval_id, n): how many points (x) lie in each interval of any length, where there are some."""
    at = lambda c: intervals.select(F.col("iv_id").alias("interval_id"), F.col(c).alias("x"))
    return _differences([(points.select("x"), at("t_hi"), 1), (points.select("x"), at("t_lo"), -1)])


def overlap_counts(a: DataFrame, b: DataFrame) -> DataFrame:
    """(interval_id, n): how many intervals of b each interval of a meets, where there are some, without forming pairs: those
    that begin before its end less those that end by its begin."""
    at = lambda c: a.select(F.col("iv_id").alias("interval_id"), c.alias("x"))
    return _differences([(b.select(F.col("t_lo").alias("x")), at(F.col("t_hi")), 1), (b.select(F.col("t_hi").alias("x")), at(F.col("t_lo") + 1), -1)])


def build_point_grid(points: DataFrame, axes: list[str], sizes: list[int]) -> DataFrame:
    """points with cell_0, cell_1 ...: the packing applied axis by axis, within the cells of the axes before."""
    out, by = points, []
    for i, (x, size) in enumerate(zip(axes, sizes)):
        keyed = out.withColumn("_by", F.concat_ws(",", F.lit(""), *by))
        packed = written(pack(runs(keyed, F.col(x), ["_by"]), size, by="_by").select("_by", F.col("key").alias(x), F.col("grp").alias(f"cell_{i}")), "points")
        out = keyed.join(packed, ["_by", x]).drop("_by")
        by.append(f"cell_{i}")
    return out

