"""Inserts and removals on a grid, by batches: only columns that change are read and rewritten.

A batch is routed by the cuts, and the files of columns that it does not touch stay as they are. A cell or column above its size is packed anew at half the size plus one if it holds more than one key; one
of a single key is heavy and only grows. After removals a cell joins a neighbour if both together stay below the size, and a
column below half the size joins one if both together do; the smaller neighbour is taken, then the left one. A
column's cells are cut anew when it splits or merges. Column ids stay with their rows; order is by key.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import forget, written
from .grid import Cuts, Grid, GridSpec, clustered, column_stats, page_stats, route, running
from .packing import groups_of_runs, pack, runs


#: Writes whose files a grid's rows may lie in.
MOST_LAYERS = 16
#: Rows of a column from which on columns lie in folders of their own; smaller ones share sorted files, as a folder costs more than its rows.
FOLDER_ROWS = 100_000
#: Rows of columns to be cut that go into one share.
SHARE_ROWS = 500_000


def among(ids) -> Column:
    """Whether a row's column is one of these ids; as text, as each value of a list would be a call of its own."""
    return F.expr(f"col_id IN ({', '.join(str(int(i)) for i in sorted(ids))})") if len(ids) else F.lit(False)


def split_sizes(counts: np.ndarray, size: int) -> np.ndarray:
    """Groups of an over-full group's runs at half the size plus one."""
    return groups_of_runs(counts, size // 2 + 1)


def merge_plan(sizes: list[int], touched: set[int], limit: int, only_below: int | None = None) -> list[list[int]]:
    """Neighbouring groups to join: a touched group joins a neighbour while both together stay below the limit."""
    groups = [[i] for i in range(len(sizes))]
    held = list(sizes)
    marked = [i in touched for i in range(len(sizes))]
    i = 0
    while i < len(groups):
        if marked[i] and (only_below is None or held[i] < only_below):
            near = [j for j in (i - 1, i + 1) if 0 <= j < len(groups) and held[i] + held[j] < limit]
            if near:
                j = min(near, key=lambda k: (held[k], k))
                a, b = min(i, j), max(i, j)
                groups[a] += groups[b]
                held[a] += held[b]
                marked[a] = True
                del groups[b], held[b], marked[b]
                i = a
                continue
        i += 1
    return groups


def _with(cuts: Cuts, changed: dict[int, list[tuple[int, int, np.ndarray]]]) -> Cuts:
    """cuts with the columns of the given ids replaced by (id, first key, cells' first keys)."""
    rows = []
    for place, cid in enumerate(cuts.ids):
        rows += changed.get(int(cid), [(int(cid), int(cuts.columns[place]), cuts.cells_of(place))])
    rows.sort(key=lambda r: r[1])
    return Cuts(np.array([r[1] for r in rows], np.int64), [r[2] for r in rows], np.array([r[0] for r in rows], np.int64))


def _first_keys(packed: DataFrame, by: list[str]) -> dict:
    out: dict = {}
    for r in packed.groupBy(*by, "grp").agg(F.min("key").alias("k")).orderBy(*by, "k").collect():  # one row a group
        out.setdefault(tuple(r[b] for b in by), []).append(r["k"])
    return out


def _put(rows: DataFrame, spec: GridSpec) -> DataFrame:
    return written(clustered(rows), "rows", "col_id" if spec.budget >= FOLDER_ROWS else None)


def _settled(grid: Grid) -> Grid:
    """The grid with its rows written by column, so that a batch can leave columns as they are."""
    if not grid.layers:
        grid.rows = _put(grid.rows, grid.spec).select(*grid.rows.columns)
        grid.layers, grid.moved = 1, []
    return grid


def _renewed(grid: Grid, rows: DataFrame, cuts: Cuts, redo: set[int], touched: set[int]) -> Grid:
    """The grid over rows, where those of the columns ``redo`` find their cells anew and ``touched`` have changed. Only these are
    written: the others stay in the files they are in, until MOST_LAYERS writes lie on each other and all are written anew."""
    names = rows.columns
    cols = [c for c in names if c not in ("col_id", "cell_id")]
    again = rows.filter(among(redo)).select(*cols)
    fresh = {int(i) for i in cuts.ids} - {int(i) for i in grid.cuts.ids}
    old = touched | redo
    changed = rows.filter(among(touched - redo))
    changed = changed.unionByName(route(again, cuts, grid.spec).select(*names)) if redo else changed
    wrote = _put(changed, grid.spec)
    changed = wrote.select(*names)
    if old >= {int(i) for i in grid.cuts.ids}:  # nothing of the older layers is left
        rows, layers, parts = changed, 1, [wrote]
    else:
        rows, layers, parts = grid.rows.filter(~among(old)).unionByName(changed), grid.layers + 1, [*grid.parts, wrote]
    if layers > MOST_LAYERS:
        wrote = _put(rows, grid.spec)
        rows, layers, parts = wrote.select(*names), 1, [wrote]
    dirty = list(old | fresh)
    pages = running(page_stats(changed), grid.spec)
    pages = written(grid.pages.filter(~among(dirty)).unionByName(pages), "pages")
    out = Grid(rows, pages, column_stats(pages, grid.spec), grid.spec, cuts)
    out.layers, out.moved, out.parts = layers, sorted(dirty), parts
    return out


def let_go(before: Grid, after: Grid) -> None:
    """Deletes what a grid has written that the one after it does not read. Only for a caller that holds no other of the two's kin."""
    forget(*(t for t in [*before.parts, before.pages, before.columns] if all(t is not u for u in after.parts) and t is not after.pages and t is not after.columns))


def _found(grid: Grid, rows: DataFrame, split: set[int], thin: dict[int, list[int]], n: int) -> list:
    """(col_id, part, key, cell) of the cuts to come: the columns in ``split`` fall into parts that begin at ``key``, with cells
    that begin at ``cell``; the cells in ``thin`` (part -1) get more cells of their column. One job: distinct pairs of keys are dealt
    out by column. ``n``: rows of these columns."""
    spec = grid.spec
    first, second = spec.keys
    place = {int(c): i for i, c in enumerate(grid.cuts.ids)}
    marks = [(c, i) for c in split for i in range(len(grid.cuts.cells_of(place[c])))] + [(c, i) for c, own in thin.items() for i in own]
    spark = rows.sparkSession
    near = rows.filter(among([*split, *thin])).join(F.broadcast(spark.createDataFrame(marks, "col_id int, cell_id int")), ["col_id", "cell_id"], "left_semi")  # one row a page
    wide = spark.sparkContext.broadcast(split)
    shares = 2 * int(spark.conf.get("spark.sql.shuffle.partitions")) + n // SHARE_ROWS

    def starts(keys: np.ndarray, n: np.ndarray, size: int) -> np.ndarray:
        own, at = np.unique(keys, return_inverse=True)
        group = groups_of_runs(np.bincount(at, n).astype(np.int64), size)
        return own[np.flatnonzero(np.diff(group, prepend=-1))]

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        c, i, x, y, n = (pdf[k].to_numpy() for k in ("col_id", "cell_id", "x", "y", "n"))
        i = np.where(np.isin(c, list(wide.value)), -1, i)
        order = np.lexsort((i, c))
        c, i, x, y, n = c[order], i[order], x[order], y[order], n[order]
        edges = [*np.flatnonzero((np.diff(c, prepend=c[0] - 1) != 0) | (np.diff(i, prepend=i[0] - 1) != 0)), len(c)]
        out = []
        for a, b in zip(edges, edges[1:]):
            if i[a] < 0:
                keys = starts(x[a:b], n[a:b], spec.budget // 2 + 1)
                at = np.searchsorted(keys, x[a:b], "right") - 1
                for part, key in enumerate(keys):
                    own = at == part
                    out += [(c[a], part, key, cell) for cell in starts(y[a:b][own], n[a:b][own], spec.cell_rows)]
            else:
                out += [(c[a], -1, 0, cell) for cell in starts(y[a:b], n[a:b], spec.cell_rows // 2 + 1)[1:]]
        return pd.DataFrame(out, columns=["col_id", "part", "key", "cell"])

    pairs = near.groupBy("col_id", "cell_id", F.col(first).alias("x"), F.col(second).alias("y")).agg(F.count("*").alias("n"))
    return pairs.groupBy(F.col("col_id") % shares).applyInPandas(solve, "col_id int, part int, key long, cell long").orderBy("col_id", "part", "cell").collect()  # one row a page that is new


def insert(grid: Grid, batch: DataFrame) -> Grid:
    """The grid with the rows of the batch (the same columns as the grid's rows, but for their place). The directory and the batch
    tell which columns and cells grow too large; only rows of these are looked at to cut them."""
    spec = grid.spec
    first, second = ("lo", "dur") if spec.keys[0] == "t_lo" else ("dur", "lo")
    if not len(grid.cuts.ids):
        from .grid import build_grid

        out = build_grid(batch, spec)
        out.moved = [int(i) for i in out.cuts.ids]
        return out
    cols = [c for c in grid.rows.columns if c not in ("col_id", "cell_id")]
    grid = _settled(grid)
    cuts = grid.cuts
    new = written(route(batch.select(*cols), cuts, spec), "batch")
    added = page_stats(new)
    names = added.columns[3:]
    sizes = grid.pages.select(*added.columns, F.lit(0).alias("hit")).unionByName(added.withColumn("hit", F.lit(1)))
    sizes = sizes.groupBy("col_id", "cell_id").agg(F.sum("n").alias("n"), F.max("hit").alias("hit"), *[getattr(F, x[:3])(x).alias(x) for x in names])
    over = F.when((F.col("n") > spec.cell_rows) & (F.col(f"min_{second}") < F.col(f"max_{second}")), F.col("cell_id"))
    grown = sizes.groupBy("col_id").agg(F.max("hit").alias("hit"), F.sum("n").alias("n"), F.min(f"min_{first}").alias("a"), F.max(f"max_{first}").alias("b"), F.collect_list(over).alias("over")).filter("hit = 1").collect()  # one row a column
    if not grown:
        out = Grid(grid.rows, grid.pages, grid.columns, spec, cuts)
        out.layers, out.parts = grid.layers, grid.parts
        return out
    low = min(r["a"] for r in grown)
    if low < cuts.columns[0]:
        cuts = Cuts(np.concatenate([[low], cuts.columns[1:]]), [cuts.cells_of(i) for i in range(len(cuts.ids))], cuts.ids)
    touched = {r["col_id"] for r in grown}
    rows = grid.rows.unionByName(new)
    split = {r["col_id"] for r in grown if r["n"] > spec.budget and r["a"] < r["b"]}
    thin = {r["col_id"]: r["over"] for r in grown if r["over"] and r["col_id"] not in split}
    changed: dict[int, list] = {}
    if split or thin:
        place = {int(c): i for i, c in enumerate(cuts.ids)}
        next_id = int(max(cuts.ids)) + 1
        found: dict[tuple[int, int, int], list] = {}
        for c, part, key, cell in _found(grid, rows, split, thin, sum(r["n"] for r in grown if r["col_id"] in split or r["col_id"] in thin)):
            found.setdefault((c, part, key), []).append(cell)
        for (c, part, key), cells in found.items():
            start = int(cuts.columns[place[c]])
            if part < 0:
                changed[c] = [(c, start, np.union1d(cuts.cells_of(place[c]), np.array(cells, np.int64)))]
            elif part == 0:
                changed[c] = [(c, min(key, start), np.array(cells, np.int64))]
            else:
                changed[c].append((next_id, key, np.array(cells, np.int64)))
                next_id += 1
    out = _renewed(grid, rows, _with(cuts, changed), set(changed), touched)
    forget(new)
    return out


def remove(grid: Grid, gone: DataFrame) -> Grid:
    """The grid without the rows whose iv_id is in ``gone``. Where gone names their t_lo and dur too, only the columns these lie in
    are read; else the ids are looked for in all."""
    spec = grid.spec
    first, second = spec.keys
    grid = _settled(grid)
    ids = written(gone.select("iv_id").distinct(), "gone")
    near = grid.rows
    if {"t_lo", "dur"} <= set(gone.columns):
        at = [r[0] for r in route(gone.select("t_lo", "dur"), grid.cuts, spec).select("col_id").distinct().collect()]  # columns
        near = near.filter(among(at))
    lost = {(r[0], r[1]) for r in near.join(ids, "iv_id", "left_semi").select("col_id", "cell_id").distinct().collect()}  # groups, not rows
    touched = {c for c, _ in lost}
    if not touched:
        return grid
    rows = grid.rows.filter(among(touched)).join(ids, "iv_id", "left_anti").select(*grid.rows.columns)
    left = rows.groupBy("col_id", "cell_id").agg(F.count("*").alias("n"), F.min(second).alias("k"))
    left = {(r["col_id"], r["cell_id"]): (r["n"], r["k"]) for r in left.collect()}
    counts = {r["col_id"]: r["n"] for r in grid.columns.select("col_id", "n").collect()} | dict.fromkeys(touched, 0)
    for (c, _), (n, _) in left.items():
        counts[c] += n
    cuts, changed, redo = grid.cuts, {}, set()
    order = [int(c) for c in cuts.ids]
    place = {c: i for i, c in enumerate(order)}
    plan = merge_plan([counts[c] for c in order], {i for i, c in enumerate(order) if c in touched}, (spec.budget + 1) // 2, (spec.budget + 1) // 2)
    merged = [[order[i] for i in sorted(g)] for g in plan if len(g) > 1]
    beside = {c for g in merged for c in g} - touched
    if beside:  # a neighbour that lost nothing is rewritten with the column that joins it
        rows = rows.unionByName(grid.rows.filter(among(beside)))
    if merged:  # all of them are cut in one job
        joins = rows.sparkSession.createDataFrame([(c, i) for i, g in enumerate(merged) for c in g], "col_id int, _g int")
        some = rows.select("col_id", second).join(F.broadcast(joins), "col_id")  # one row a column
        keys = _first_keys(pack(runs(some, F.col(second), ["_g"]), spec.cell_rows, by="_g"), ["_g"])
        for i, group in enumerate(merged):
            changed[group[0]] = [(group[0], int(cuts.columns[place[group[0]]]), np.array(keys.get((i,), [0]), np.int64))]
            changed |= {c: [] for c in group[1:]}
            redo |= set(group)
    lost_of: dict[int, set[int]] = {}
    for c, i in lost:
        lost_of.setdefault(c, set()).add(i)
    for c in touched - redo:
        cells = cuts.cells_of(place[c])
        sizes = [left.get((c, i), (0, 0))[0] for i in range(len(cells))]
        plan = merge_plan(sizes, lost_of[c], spec.cell_rows)
        if len(plan) < len(cells):
            changed[c] = [(c, int(cuts.columns[place[c]]), cells[[min(g) for g in plan]])]
            redo.add(c)
    return _renewed(grid, rows, _with(cuts, changed), redo, touched)


def rewritten(before: Grid, after: Grid) -> DataFrame:
    """Columns whose cells differ between two states: what a batch restructured."""
    key = ["col_id", "cell_id", "n", "min_lo", "max_lo", "min_dur", "max_dur", "max_hi"]
    return after.pages.select(*key).exceptAll(before.pages.select(*key)).select("col_id").distinct()


def rebuild(grid: Grid) -> Grid:
    """The grid built anew from its rows."""
    from .grid import build_grid

    return build_grid(grid.rows.drop("col_id", "cell_id"), grid.spec)
