"""The methods the grid is compared with, as layouts: they differ only in their groups and in what a visit reads."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.predicates import after, at_least, at_most, before, in_band, in_window, matches, valid
from ..storage import written
from .layouts import QUERY_COLUMNS, Layout, ordinal
from .packing import pack, runs


class Scan(Layout):
    """Every row is read: the truth."""

    name = "scan"

    def __init__(self, df: DataFrame):
        super().__init__(df.withColumn("g", F.lit(0)), df.agg(F.count("*").alias("n")).withColumn("g", F.lit(0)), ["g"])


class Ordered(Layout):
    """Rows ordered by length (a B-tree on duration) or by start: a query reads its key range, page by page."""

    def __init__(self, df: DataFrame, key: str = "dur", page_rows: int = 1000):
        self.key, self.name = key, "ordered_duration" if key == "dur" else "ordered_start"
        pages = written(pack(runs(df, F.col(key)), page_rows).select(F.col("key").alias(key), F.col("grp").alias("g"), F.col("n").alias("c")), "ordered")
        rows = df.join(pages.drop("c"), key)
        super().__init__(rows, pages.groupBy("g").agg(F.sum("c").alias("n"), F.min(key).alias("k_min"), F.max(key).alias("k_max")), ["g"])

    def meets(self) -> Column:
        if self.key == "dur":
            return at_most(F.col("k_min"), F.col("d_max")) & at_least(F.col("k_max"), F.col("d_min"))
        return before(F.col("k_min"), F.col("q_hi"))

    def reads(self) -> Column:
        return in_band() if self.key == "dur" else before(F.col("t_lo"), F.col("q_hi"))


class TwoIndexes:
    """Both orders used at once, row ids intersected: reads the candidates of either."""

    name = "two_indexes"

    def __init__(self, df: DataFrame, page_rows: int = 1000):
        self.by_dur, self.by_start = Ordered(df, "dur", page_rows), Ordered(df, "t_lo", page_rows)

    def settled(self) -> TwoIndexes:
        self.by_dur.settled()
        self.by_start.settled()
        return self

    def find_batch(self, queries: DataFrame) -> DataFrame:
        """Only queries with a window and a band have candidates to intersect: an order that a query leaves open would offer it every
        row, so the other order's candidates are its answers."""
        window, band = F.col("q_lo").isNotNull() | F.col("q_hi").isNotNull(), F.col("d_min").isNotNull() | F.col("d_max").isNotNull()
        kinds = {(r["w"], r["b"]) for r in queries.select(window.alias("w"), band.alias("b")).distinct().collect()}  # at most four
        out = None
        for w, b in sorted(kinds):
            some = queries.filter((window == F.lit(w)) & (band == F.lit(b)))
            one = self._candidates(self.by_dur, some, in_band()) if b else self._candidates(self.by_start, some, in_window())
            if w and b:
                one = one.intersectAll(self._candidates(self.by_start, some, in_window()))
            out = one if out is None else out.unionByName(one)
        return self._candidates(self.by_dur, queries, in_band()) if out is None else out

    @staticmethod
    def _candidates(index: Ordered, queries: DataFrame, test: Column) -> DataFrame:
        seen = index.visit(queries).select("qid", "d_min", "d_max", "q_lo", "q_hi", "g")
        return index.rows.join(seen, "g").filter(test).select("qid", "iv_id", "t_lo", "t_hi", "dur")

    def count_batch(self, queries: DataFrame) -> DataFrame:
        got = self.find_batch(queries).groupBy("qid").agg(F.count("*").alias("c"))
        return queries.select("qid").join(got, "qid", "left").select("qid", F.coalesce("c", F.lit(0)).cast("long").alias("matched"))

    def meter(self, queries: DataFrame) -> DataFrame:
        a, b = self.by_dur.meter(queries), self.by_start.meter(queries)
        both = a.unionByName(b).groupBy("qid").agg(*[F.sum(c).alias(c) for c in ("columns_visited", "cells_visited", "examined", "examined_incl_stop")])
        return both.join(a.select("qid", "matched"), "qid")


class IntervalTree(Layout):
    """An interval sits at the highest node of a fixed binary backbone inside it; a window reads one path and the nodes inside it."""

    name = "interval_tree"

    def __init__(self, df: DataFrame):
        low = df.agg(F.min("t_lo").alias("a"), F.max("t_hi").alias("b")).first()
        self.a, top = (low["a"] or 0), (low["b"] or 1)
        self.height = max(1, int(top - self.a).bit_length())
        x, y = F.col("t_lo") - F.lit(self.a) + 1, F.col("t_hi") - F.lit(self.a)
        h = F.length(F.bin((x - 1).bitwiseXOR(y))) - 1  # the exact highest differing bit
        rows = df.withColumn("_y", y).withColumn("_h", h.cast("int")).withColumn("node", F.expr("shiftleft(shiftright(_y, _h), _h)")).drop("_y", "_h")
        self.top = int(top - self.a)
        super().__init__(rows, rows.groupBy("node").agg(F.count("*").alias("n")), ["node"])

    def reads(self) -> Column:
        return in_window()

    def visit(self, queries: DataFrame) -> DataFrame:
        q = queries.filter(valid())
        p = F.greatest(F.coalesce(F.col("q_lo") - self.a + 1, F.lit(1)), F.lit(1))
        z = F.least(F.coalesce(F.col("q_hi") - self.a, F.lit(self.top)), F.lit(self.top))
        q = q.withColumns({"p": p, "z": z})
        level = F.explode(F.sequence(F.lit(0), F.lit(self.height))).alias("k")
        at = lambda v: F.expr(f"shiftleft(shiftright({v}, CAST(k + 1 AS INT)), CAST(k + 1 AS INT)) + shiftleft(1L, CAST(k AS INT))")
        left = q.select("*", level).withColumn("node", at("p")).filter("node < p")
        right = q.select("*", level).withColumn("node", at("z")).filter("node > z")
        path = left.unionByName(right).select(*QUERY_COLUMNS, "node").distinct()
        inside = self.groups.join(F.broadcast(q), F.col("node").between(F.col("p"), F.col("z"))).select(*QUERY_COLUMNS, "node", "n", F.lit(False).alias("path"))
        return inside.unionByName(self.groups.join(F.broadcast(path), "node").select(*QUERY_COLUMNS, "node", "n", F.lit(True).alias("path")))

    def meter(self, queries: DataFrame) -> DataFrame:
        """A path node's list costs one more row unless it is exhausted; nodes inside the window are read whole."""
        seen = self.visit(queries)
        per = self.rows.join(seen, "node").groupBy("qid", "node", "path").agg(F.first("n").alias("n"), F.count_if(in_window()).alias("hits"), F.count_if(matches()).alias("ok"))
        stop = F.when(F.col("path"), F.least("n", F.col("hits") + 1)).otherwise(F.col("hits"))
        sums = per.groupBy("qid").agg(F.lit(1).alias("columns_visited"), F.count("*").alias("cells_visited"), F.sum("hits").alias("examined"), F.sum(stop).alias("examined_incl_stop"), F.sum("ok").alias("matched"))
        names = ["columns_visited", "cells_visited", "examined", "examined_incl_stop", "matched"]
        return queries.select("qid").join(sums, "qid", "left").select("qid", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in names])


class UniformGrid(Layout):
    """Cells of equal width over starts and lengths; static, and it needs the data's range beforehand."""

    name = "uniform_grid"

    def __init__(self, df: DataFrame, g: int = 20):
        r = df.agg(F.min("t_lo").alias("a"), F.max("t_lo").alias("b"), F.min("dur").alias("c"), F.max("dur").alias("d")).first()
        self.x0, self.y0 = r["a"] or 0, r["c"] or 0
        self.wx, self.wy = max(1, math.ceil(((r["b"] or 0) - self.x0 + 1) / g)), max(1, math.ceil(((r["d"] or 0) - self.y0 + 1) / g))
        rows = df.withColumns({"cx": F.floor((F.col("t_lo") - self.x0) / self.wx).cast("long"), "cy": F.floor((F.col("dur") - self.y0) / self.wy).cast("long")})
        super().__init__(rows, rows.groupBy("cx", "cy").agg(F.count("*").alias("n")), ["cx", "cy"])

    def meets(self) -> Column:
        x, y = F.col("cx") * self.wx + self.x0, F.col("cy") * self.wy + self.y0
        x1, y1 = x + self.wx - 1, y + self.wy - 1
        return before(x, F.col("q_hi")) & after(x1 + y1, F.col("q_lo")) & at_most(y, F.col("d_max")) & at_least(y1, F.col("d_min"))


class Replicating(Layout):
    """Buckets of the timeline adapted to starts, levels by length in each, slots in each level; a row is copied to all slots it meets."""

    name = "replicating"
    replicates = True

    def __init__(self, df: DataFrame, buckets: int = 20, levels: int = 5, dedupe: bool = True):
        self.dedupe = dedupe
        n = df.count()
        cuts = pack(runs(df, F.col("t_lo")), max(1, -(-n // buckets))).groupBy("grp").agg(F.min("key").alias("b_lo")).orderBy("b_lo")
        first = [r["b_lo"] for r in cuts.collect()]  # one a bucket
        end = df.agg(F.max("t_hi")).first()[0]
        spans = [(i, int(a), int(b)) for i, (a, b) in enumerate(zip(first, [*first[1:], end]))]
        spark = df.sparkSession
        table = [(i, a, b, lv, max(1, math.ceil((b - a) / 2**lv))) for i, a, b in spans for lv in range(levels)]
        self.slots = spark.createDataFrame(table, "bucket int, b_lo long, b_hi long, level int, w long")
        by_bucket = F.broadcast(self.slots.groupBy("bucket", "b_lo", "b_hi").agg(F.sort_array(F.collect_list("w"), False).alias("ws")))  # as many rows as buckets
        met = df.join(by_bucket, (F.col("t_lo") < F.col("b_hi")) & (F.col("t_hi") > F.col("b_lo")))
        fits = F.greatest(F.size(F.filter("ws", lambda w: w >= F.col("dur"))) - 1, F.lit(0))
        met = met.withColumn("level", fits.cast("int")).withColumn("w", F.element_at("ws", F.col("level") + 1))
        lo, hi = F.greatest("t_lo", "b_lo"), F.least("t_hi", "b_hi")
        slots = F.sequence(F.floor((lo - F.col("b_lo")) / F.col("w")), F.floor((hi - 1 - F.col("b_lo")) / F.col("w")))
        rows = met.withColumn("slot", F.explode(slots)).drop("ws")
        rows = written(rows, "replicated")
        groups = rows.groupBy("bucket", "level", "slot").agg(F.count("*").alias("n"), F.first("b_lo").alias("g_lo"), F.first("b_hi").alias("g_hi"), F.first("w").alias("g_w"))
        band = rows.groupBy("bucket", "level").agg(F.min("dur").alias("l_min"), F.max("dur").alias("l_max"))
        super().__init__(rows, groups.join(F.broadcast(band), ["bucket", "level"]), ["bucket", "level", "slot"])

    def meets(self) -> Column:
        a = F.col("g_lo") + F.col("slot") * F.col("g_w")
        b = F.least(a + F.col("g_w"), F.col("g_hi"))
        return before(a, F.col("q_hi")) & after(b, F.col("q_lo")) & at_most(F.col("l_min"), F.col("d_max")) & at_least(F.col("l_max"), F.col("d_min"))

    def once(self, answers: DataFrame) -> DataFrame:
        return answers.filter(self._owner()) if self.dedupe else answers

    def _owner(self) -> Column:
        """The copy in the slot where the row, cut to the window, begins."""
        at = F.greatest(F.col("t_lo"), F.coalesce("q_lo", F.col("t_lo")))
        a = F.col("b_lo") + F.col("slot") * F.col("w")
        return (at >= a) & (at < F.least(a + F.col("w"), F.col("b_hi")))

    def answers(self) -> Column:
        return matches() & self._owner() if self.dedupe else matches()


class PackedTree(Layout):
    """Leaves of M points tiled by start, then length; refine=False visits by the query's bounding box alone."""

    name = "packed_tree"

    def __init__(self, df: DataFrame, m: int = 50, refine: bool = True):
        self.refine = refine
        n = df.count()
        slices = max(1, math.ceil(math.sqrt(n / m)))
        per = max(1, math.ceil(n / slices))
        tie = ["iv_id"]
        tiled = ordinal(df, ["t_lo", "dur", *tie], "_o").withColumn("slice", F.floor(F.col("_o") / per).cast("long"))
        within = F.row_number().over(Window.partitionBy("slice").orderBy("dur", "t_lo", *tie)) - 1  # a slice holds sqrt(n * m) rows
        rows = written(tiled.withColumn("leaf", F.floor(within / m).cast("long")).drop("_o"), "leaves")
        spans = [f(c).alias(f"{f.__name__}_{k}") for k, c in (("lo", "t_lo"), ("hi", "t_hi"), ("dur", "dur")) for f in (F.min, F.max)]
        super().__init__(rows, rows.groupBy("slice", "leaf").agg(F.count("*").alias("n"), *spans), ["slice", "leaf"])

    def meets(self) -> Column:
        box = before(F.col("min_lo"), F.col("q_hi")) & after(F.col("max_lo"), F.col("q_lo") - F.col("d_max")) & at_most(F.col("min_dur"), F.col("d_max")) & at_least(F.col("max_dur"), F.col("d_min"))
        return box & after(F.col("max_hi"), F.col("q_lo")) if self.refine else box


class InsertingTree:
    """A small in-memory tree of rectangles over (start, length) that grows by single inserts, for the insertion study.

    A full node splits along the axis and at the place of least total margin, then least overlap; the first overflow on a level
    reinserts the entries farthest from the node's centre instead. A node holds its entries' rectangles in one array, in their order.
    """

    def __init__(self, fan_out: int = 32):
        self.m = fan_out
        self.root = _Node(fan_out, None)
        self.splits = self.reinserted = 0

    def insert(self, start: int, dur: int) -> None:
        self._again = True
        todo = [(start, dur, start, dur)]
        while todo:
            extra = self._into(self.root, todo.pop(), todo)
            if extra is not None:
                old = self.root
                self.root = _Node(self.m, [])
                self.root.add(old.box, old)
                self.root.add(extra.box, extra)

    def _into(self, node: _Node, box: tuple, todo: list) -> _Node | None:
        a, b, c, d = box
        if node.kids is None:
            node.add(box)
        else:
            x0, y0, x1, y1 = node.entries[:, : node.n]
            was = node.areas[: node.n]
            more = (np.maximum(x1, c) - np.minimum(x0, a) + 1.0) * (np.maximum(y1, d) - np.minimum(y0, b) + 1.0) - was
            at = int(more.argmin())
            ties = more == more[at]
            if np.count_nonzero(ties) > 1:
                at = int(np.where(ties, was, np.inf).argmin())
            best = node.kids[at]
            extra = self._into(best, box, todo)
            node.put(at, best.box)
            node.box = _join(node.box, box)
            if extra is not None:
                node.add(extra.box, extra)
        if node.n <= self.m:
            return None
        if node.kids is None and self._again and node is not self.root:
            self._again = False
            b = node.box
            cx, cy = (b[0] + b[2]) / 2, (b[1] + b[3]) / 2
            own = node.entries[:, : node.n]
            order = np.argsort((own[0] - cx) ** 2 + (own[1] - cy) ** 2, kind="stable")
            cut = max(1, self.m * 3 // 10)
            todo.extend(map(tuple, own[:, order[-cut:]].T.tolist()))
            node.fill(own[:, order[:-cut]])
            self.reinserted += cut
            return None
        return self._split(node)

    def _split(self, node: _Node) -> _Node:
        self.splits += 1
        n = node.n
        least, best = max(1, self.m * 4 // 10), None
        own = node.entries[:, :n].copy()
        at = np.arange(least, n - least + 1)
        for ax in (0, 1):
            order = np.lexsort((own[ax + 2], own[ax]))
            x0, y0, x1, y1 = own[:, order]
            low, high = np.minimum.accumulate, np.maximum.accumulate
            a = np.array([low(x0), low(y0), high(x1), high(y1)])[:, at - 1]
            b = np.array([low(x0[::-1]), low(y0[::-1]), high(x1[::-1]), high(y1[::-1])])[:, n - at - 1]
            margin = a[2] - a[0] + a[3] - a[1] + b[2] - b[0] + b[3] - b[1]
            overlap = np.maximum(0, np.minimum(a[2], b[2]) - np.maximum(a[0], b[0]) + 1) * np.maximum(0, np.minimum(a[3], b[3]) - np.maximum(a[1], b[1]) + 1)
            i = int(np.lexsort((overlap, margin))[0])
            found = (int(margin[i]), int(overlap[i]))
            if best is None or found < best[0]:
                best = (found, order[: at[i]], order[at[i] :])
        kids = node.kids
        node.fill(own[:, best[1]], kids and [kids[i] for i in best[1]])
        other = _Node(self.m, kids and [])
        other.fill(own[:, best[2]], kids and [kids[i] for i in best[2]])
        return other

    def find(self, q_lo: int, q_hi: int, d_min: int, d_max: int) -> list[tuple[int, int]]:
        out, todo = [], [self.root]
        while todo:
            node = todo.pop()
            b = node.box
            if b is None or b[0] >= q_hi or b[2] <= q_lo - d_max or b[1] > d_max or b[3] < d_min:
                continue
            if node.kids is None:
                out += [(s, d) for s, d, _, _ in node.entries[:, : node.n].T.tolist() if s < q_hi and s + d > q_lo and d_min <= d <= d_max]
            else:
                todo += node.kids
        return out


def _join(a: tuple | None, b: tuple) -> tuple:
    return b if a is None else (min(a[0], b[0]), min(a[1], b[1]), max(a[2], b[2]), max(a[3], b[3]))


class _Node:
    """A node of the inserting tree: the rectangles of its entries, their areas, and its children, None in a leaf."""

    __slots__ = ("areas", "box", "entries", "kids", "n")

    def __init__(self, fan_out: int, kids: list | None):
        self.kids, self.n, self.box = kids, 0, None
        self.entries = np.zeros((4, fan_out + 1), np.int64)
        self.areas = None if kids is None else np.zeros(fan_out + 1)

    def put(self, at: int, box: tuple) -> None:
        self.entries[:, at] = box
        if self.areas is not None:
            self.areas[at] = (box[2] - box[0] + 1.0) * (box[3] - box[1] + 1)

    def add(self, box: tuple, kid: _Node | None = None) -> None:
        self.put(self.n, box)
        self.n += 1
        self.box = _join(self.box, box)
        if kid is not None:
            self.kids.append(kid)

    def fill(self, entries: np.ndarray, kids: list | None = None) -> None:
        """The node with these entries alone."""
        self.n = entries.shape[1]
        self.entries[:, : self.n] = entries
        self.box = (int(entries[0].min()), int(entries[1].min()), int(entries[2].max()), int(entries[3].max()))
        if kids is not None:
            self.kids = kids
            self.areas[: self.n] = (entries[2] - entries[0] + 1.0) * (entries[3] - entries[1] + 1.0)


def all_layouts(df: DataFrame, cell_rows: int = 50, g: int = 20, buckets: int = 20, levels: int = 5, m: int = 50) -> dict:
    """Every compared method over df with the given parameters, by name."""
    from .grid import DURATION_FIRST, START_FIRST, GridSpec, build_grid

    return {
        "scan": lambda: Scan(df), "start_first": lambda: build_grid(df, GridSpec(cell_rows, order=START_FIRST)), "duration_first": lambda: build_grid(df, GridSpec(cell_rows, order=DURATION_FIRST)),
        "ordered_duration": lambda: Ordered(df, "dur"), "ordered_start": lambda: Ordered(df, "t_lo"), "two_indexes": lambda: TwoIndexes(df), "interval_tree": lambda: IntervalTree(df),
        "uniform_grid": lambda: UniformGrid(df, g), "replicating": lambda: Replicating(df, buckets, levels), "replicating_copies": lambda: Replicating(df, buckets, levels, dedupe=False), "packed_tree": lambda: PackedTree(df, m), "packed_tree_box": lambda: PackedTree(df, m, refine=False),
    }

