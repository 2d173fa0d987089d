"""The query catalogue: every method, baseline, measure and workload as (spark, sf_dir) -> DataFrame, with its SQL twin where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.predicates import relation
from ..model import Query, axis, quarantined
from ..operators import baselines as b
from ..operators import grid as g
from ..operators import maintain, measures
from ..operators.packing import pack, runs
from ..operators.selections import count_matches, select, select_by_row
from ..sources import intervals as src
from ..sources import workload as wl
from ..storage import written
from ..streaming import streams
from . import published, studies, twins

QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}

PRESC = {"q1": Query(9770, 9952), "q2": Query(None, None, 5, 8), "q3": Query(9770, 9952, 7, 14)}
MID = {
    "presc": [(1, "both", 10151, 10406, 10, 20), (2, "range", 10151, 10406, None, None), (3, "duration", None, None, 10, 20), (4, "range", 10406, 10151, None, None), (5, "duration", None, None, 20, 10)],
    "trips": [(1, "both", 28418464, 28422800, 12, 26), (2, "range", 28418464, 28422800, None, None), (3, "duration", None, None, 12, 26)],
}
OUT = {"presc": ["l_orderkey", "l_linenumber", "l_partkey"], "trips": ["event_id"], "gaps": ["event_id"], "order_gaps": ["o_orderkey"]}
PAGE, G, NB, LEV, LEAF = 50, 20, 20, 5, 50
R = twins.RELATIONS
_kept: dict = {}


def add(name: str, sql: str | None = None):
    def put(f: Callable) -> Callable:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def kept(spark: SparkSession, key: tuple, make: Callable):
    """What several entries build alike, once for a Spark application."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _kept:
        _kept[key] = make()
    return _kept[key]


def slim(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return src.RELATIONS[name](spark, sf).select("iv_id", "t_lo", "t_hi", "dur")


def built(spark: SparkSession, sf: str, name: str, s: int, order: str, **more) -> g.Grid:
    return kept(spark, ("grid", sf, name, s, order, *more.items()), lambda: g.build_grid(slim(spark, sf, name), g.GridSpec(s, order=order, **more)))


def stored(spark: SparkSession, sf: str, order: str, **more) -> g.Grid:
    """The prescriptions with payload, saved as a grid and opened."""
    keys = ["iv_id", "t_lo", "t_hi", "dur", *OUT["presc"]]
    return kept(spark, ("saved", sf, order, *more.items()), lambda: g.saved_grid(src.presc(spark, sf).select(*keys), g.GridSpec(PAGE, order=order, **more), order))


def layout(spark: SparkSession, sf: str, name: str, method: str):
    return kept(spark, ("layout", sf, name, method), lambda: b.all_layouts(slim(spark, sf, name), PAGE, G, NB, LEV, LEAF)[method]())


def where(q: Query) -> str:
    parts = [f"t_lo < {q.q_hi}" if q.q_hi is not None else "", f"t_hi > {q.q_lo}" if q.q_lo is not None else "", f"dur >= {q.d_min}" if q.d_min is not None else "", f"dur <= {q.d_max}" if q.d_max is not None else ""]
    return " AND ".join(p for p in parts if p)


def longs(df: DataFrame, *names: str) -> DataFrame:
    return df.select(*[F.col(c).cast("long").alias(c) for c in names])


# worked examples ------------------------------------------------------------------------------------------------------------

WORKED = [(1, 8, 14), (2, 10, 12), (3, 20, 35), (4, 24, 34)]  # days of a month and the next


def _worked(top: int):
    def f(spark: SparkSession, sf: str) -> DataFrame:
        df = spark.createDataFrame(WORKED, "iv_id long, t_lo long, t_hi long").withColumn("dur", F.col("t_hi") - F.col("t_lo"))
        return select(df, Query(15, 45, 5, top))

    return f


for _top in (13, 15):
    _rows = ", ".join(f"({i}, {x}, {y}, {y - x})" for i, x, y in WORKED)
    add(f"worked_example_{_top}", f"SELECT * FROM (VALUES {_rows}) v(iv_id, t_lo, t_hi, dur) WHERE t_lo < 45 AND t_hi > 15 AND dur BETWEEN 5 AND {_top}")(_worked(_top))

ORDERS_A_GROUP = 200


@add("packing_example", f"""WITH RECURSIVE base AS (SELECT epoch_us(o_orderdate) // {twins.DAY} AS k FROM orders), {twins.packed("p", "base", "k", ORDERS_A_GROUP)}
SELECT CAST(p.g AS BIGINT) AS grp, count(*) AS n, CAST(min(k) AS BIGINT) AS min_key, CAST(max(k) AS BIGINT) AS max_key, count(*) > {ORDERS_A_GROUP} AS heavy FROM base JOIN p ON p.key = base.k GROUP BY 1""")  # fmt: skip
def packing_example(spark, sf):
    """The days of orders in groups that no day is split between."""
    days = src.read(spark, sf, "orders").select(axis(F.col("o_orderdate"), "day").alias("k"))
    out = pack(runs(days, F.col("k")), ORDERS_A_GROUP).groupBy("grp").agg(F.sum("n").alias("n"), F.min("key").alias("min_key"), F.max("key").alias("max_key"))
    return out.withColumn("heavy", F.col("n") > ORDERS_A_GROUP)


# selections ------------------------------------------------------------------------------------------------------------------

SCANS = {f"presc_{k}": ("presc", q) for k, q in PRESC.items()} | {
    "trips_range": ("trips", Query(28418464, 28422800)), "trips_duration": ("trips", Query(None, None, 12, 26)), "trips_both": ("trips", Query(28418464, 28422800, 12, 26)),
    "gaps_both": ("gaps", Query(1705103937185369, 1705363119686818, 8523370342, 19634278547)), "order_gaps_both": ("order_gaps", Query(10092, 10333, 49, 111)),
    "stab_point": ("presc", Query(10000, 10001)), "empty_window": ("presc", Query(10000, 10000)), "inverted_band": ("presc", Query(None, None, 9, 8)),
}

for _name, (_rel, _q) in SCANS.items():
    _cols = ["t_lo", "t_hi", "dur", *OUT[_rel]]
    add(_name, f"SELECT {', '.join(_cols)} FROM ({R[_rel]}) WHERE {'FALSE' if _q.empty else where(_q)}")(
        lambda spark, sf, rel=_rel, q=_q, cols=_cols: (select_by_row if q.empty else select)(src.RELATIONS[rel](spark, sf), q).select(*cols)
    )


@add("count_form", f"SELECT count(*) AS matched FROM ({R['presc']}) WHERE {where(PRESC['q3'])}")
def count_form(spark, sf):
    return count_matches(src.presc(spark, sf), PRESC["q3"])


for _short, _order in (("sf", g.START_FIRST), ("df", g.DURATION_FIRST)):
    for _k, _q in PRESC.items():
        _cols = ["t_lo", "t_hi", "dur", *OUT["presc"]]
        add(f"grid_{_short}_{_k}", SQL[f"presc_{_k}"])(lambda spark, sf, order=_order, q=_q, cols=_cols: stored(spark, sf, order).find(q).select(*cols))

for _k, _q in PRESC.items():
    add(f"grid_covered_count_{_k}", f"SELECT count(*) AS matched FROM ({R['presc']}) WHERE {where(_q)}")(lambda spark, sf, q=_q: stored(spark, sf, g.DURATION_FIRST).count(q))

for _form in ("sharded", "quantile"):
    add(f"grid_{_form}_q3", SQL["presc_q3"])(lambda spark, sf, form=_form: stored(spark, sf, g.START_FIRST, packing=form).find(PRESC["q3"]).select("t_lo", "t_hi", "dur", *OUT["presc"]))


@add("grid_ref_join_q3", SQL["presc_q3"])
def grid_ref_join_q3(spark, sf):
    base = src.presc(spark, sf)
    thin = built(spark, sf, "presc", PAGE, g.DURATION_FIRST, payload="ref")
    return g.fetch(base, thin.find(PRESC["q3"])).select("t_lo", "t_hi", "dur", *OUT["presc"])


@add("grid_zone_prune_q3", SQL["presc_q3"])
def grid_zone_prune_q3(spark, sf):
    return stored(spark, sf, g.START_FIRST).find(PRESC["q3"], prune="zone").select("t_lo", "t_hi", "dur", *OUT["presc"])


@add("page_classes_q3", f"""{twins.grid(R['presc'], PAGE, 'duration_first')} SELECT cls, count(*) AS pages, CAST(sum(n) AS BIGINT) AS held FROM (SELECT p.n, CASE WHEN max_lo < 9952 AND min_hi > 9770 AND min_dur >= 7 AND max_dur <= 14 THEN 'covered'
WHEN max_lo < 9952 AND min_hi > 9770 THEN 'duration_cut' WHEN min_dur >= 7 AND max_dur <= 14 THEN 'start_cut' ELSE 'corner' END AS cls FROM pages p JOIN cols c ON c.col_id = p.col_id WHERE c.min_key <= 14 AND c.max_key >= 7 AND min_lo < 9952 AND p.run_max_hi > 9770) GROUP BY cls""")  # fmt: skip
def page_classes_q3(spark, sf):
    return built(spark, sf, "presc", PAGE, g.DURATION_FIRST).classify(PRESC["q3"]).groupBy("cls").agg(F.count("*").alias("pages"), F.sum("n").alias("held"))


# structure -------------------------------------------------------------------------------------------------------------------

_PAGES = ["col_id", "cell_id", "n", "min_lo", "max_lo", "min_hi", "max_hi", "min_dur", "max_dur", "run_max_hi"]
_COLS = ["col_id", "n", "min_key", "max_key", "max_hi", "n_cells", "run_max_hi"]


def _described(spark, sf, name, s, order):
    d = built(spark, sf, name, s, order).describe()
    return d.select(F.lit(s).cast("long").alias("cell_rows"), F.lit(order).alias("grid_order"), "columns", "cells", "heavy_columns", "heavy_cells", F.col("largest_cell").cast("long").alias("largest_cell"))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


for _order in (g.START_FIRST, g.DURATION_FIRST):
    add(f"pages_{_order}", twins.pages(R["presc"], PAGE, _order))(lambda spark, sf, o=_order: built(spark, sf, "presc", PAGE, o).pages.select(*[F.col(c).cast("long").alias(c) for c in _PAGES], "heavy"))
    add(f"columns_{_order}", twins.columns(R["presc"], PAGE, _order))(lambda spark, sf, o=_order: built(spark, sf, "presc", PAGE, o).columns.select(*[F.col(c).cast("long").alias(c) for c in _COLS], "heavy"))
    add(f"grid_shape_{_order}", twins.describe(R["presc"], 70, _order))(lambda spark, sf, o=_order: _described(spark, sf, "presc", 70, o))
    add(f"grid_degenerate_big_s_{_order}", twins.describe(R["presc"], 300, _order))(lambda spark, sf, o=_order: _described(spark, sf, "presc", 300, o))
    add(f"grid_describe_trips_{_order}", twins.describe(R["trips"], 20, _order))(lambda spark, sf, o=_order: _described(spark, sf, "trips", 20, o))
    add(f"grid_describe_order_gaps_{_order}", twins.describe(R["order_gaps"], 50, _order))(lambda spark, sf, o=_order: _described(spark, sf, "order_gaps", 50, o))
add("grid_degenerate_s1", f"SELECT count(*) AS cells FROM (SELECT DISTINCT t_lo, dur FROM ({R['presc']}))")(lambda spark, sf: built(spark, sf, "presc", 1, g.DURATION_FIRST).pages.agg(F.count("*").alias("cells")))
add("heavy_groups", f"{twins.grid(R['presc'], PAGE, 'start_first')} SELECT CAST(col_id AS BIGINT) AS col_id, CAST(cell_id AS BIGINT) AS cell_id, n FROM pages WHERE heavy")(
    lambda spark, sf: built(spark, sf, "presc", PAGE, g.START_FIRST).pages.filter("heavy").select(F.col("col_id").cast("long").alias("col_id"), F.col("cell_id").cast("long").alias("cell_id"), "n")
)
add("grid_two_sizes", f"{twins.grid(R['presc'], 100, 'duration_first', 2500)} SELECT count(*) AS cells, CAST(max(n) AS BIGINT) AS largest_cell FROM pages")(
    lambda spark, sf: built(spark, sf, "presc", 100, g.DURATION_FIRST, column_rows=2500).pages.agg(F.count("*").alias("cells"), F.max("n").cast("long").alias("largest_cell"))
)

# batches ---------------------------------------------------------------------------------------------------------------------

BATCH = {"range": 11, "duration": 12, "both": 13}
_ARGS = ((9132, 11680), (1, 120), (1, 50))
METHODS = ("scan", "start_first", "duration_first", "ordered_duration", "two_indexes", "interval_tree", "uniform_grid", "replicating", "packed_tree")


def batch(spark, kind: str, m: int = 40) -> DataFrame:
    return wl.random_queries(spark, kind, m, BATCH[kind], *_ARGS)


for _kind, _seed in BATCH.items():
    _qsql = wl.random_queries_sql(_kind, 40, _seed, *_ARGS)
    add(f"workload_{_kind}", _qsql)(lambda spark, sf, kind=_kind: batch(spark, kind))
    for _m in METHODS:
        add(f"batch_counts_{_kind}__{_m}", twins.counts(R["presc"], _qsql))(lambda spark, sf, kind=_kind, m=_m: layout(spark, sf, "presc", m).count_batch(batch(spark, kind)))

# robustness: every method on the other relations, with the ranges of their workloads -----------------------------------------

SYNTHETIC = {"synthetic_uniform_zipf": ("uniform", "zipf"), "synthetic_skewed_uniform": ("skewed", "uniform")}
SYNTHETIC_ROWS = 20_000
RANGES = {  # window, its lengths, band, and the unit
    "trips": ((28401120, 28444480), (1440, 44640), (1, 1440), 1), "gaps": ((1704067200, 1706745600), (60, 864000), (1, 518400), 1_000_000), "order_gaps": ((9131, 11535), (1, 365), (1, 1095), 1),
    **dict.fromkeys(SYNTHETIC, ((1, SYNTHETIC_ROWS), (1, 2000), (1, 100), 1)),
}


def relation_of(spark, sf, name: str) -> DataFrame:
    if name in SYNTHETIC:
        return src.synthetic(spark, SYNTHETIC_ROWS, *SYNTHETIC[name])
    return slim(spark, sf, name)


def asked(spark, name: str, kind: str, m: int = 20) -> DataFrame:
    *args, unit = RANGES[name]
    return wl.random_queries(spark, kind, m, BATCH[kind], *args, unit=unit)


def _every_method(spark, sf, name: str, kind: str) -> DataFrame:
    q = asked(spark, name, kind)
    make = lambda m: kept(spark, ("robust", sf, name, m), lambda: b.all_layouts(kept(spark, ("robust", sf, name), lambda: written(relation_of(spark, sf, name), name)), PAGE, G, NB, LEV, LEAF)[m]())
    return _union([make(m).count_batch(q).select(F.lit(m).alias("method"), "qid", "matched") for m in METHODS])


_EACH = ", ".join(f"('{m}')" for m in METHODS)
for _rel in RANGES:
    _relation = twins.synthetic(SYNTHETIC_ROWS, *SYNTHETIC[_rel]) if _rel in SYNTHETIC else R[_rel]
    for _kind, _seed in BATCH.items():
        *_args, _unit = RANGES[_rel]
        _qsql = wl.random_queries_sql(_kind, 20, _seed, *_args, unit=_unit)
        add(f"robust_counts_{_rel}_{_kind}", f"SELECT method, qid, matched FROM ({twins.counts(_relation, _qsql)}), (VALUES {_EACH}) m(method)")(lambda spark, sf, rel=_rel, kind=_kind: _every_method(spark, sf, rel, kind))
for _rel, _shape in SYNTHETIC.items():
    add(f"{_rel}_rows", f"SELECT t_lo, t_hi, dur, count(*) AS n FROM ({twins.synthetic(SYNTHETIC_ROWS, *_shape, ids=twins.EVENT_IDS)}) GROUP BY ALL")(
        lambda spark, sf, shape=_shape: src.synthetic(spark, SYNTHETIC_ROWS, *shape, ids=src.event_ids(spark, sf)).groupBy("t_lo", "t_hi", "dur").agg(F.count("*").alias("n"))
    )

# meters ----------------------------------------------------------------------------------------------------------------------

for _rel in ("presc", "trips"):
    _q = twins.literal(MID[_rel])
    for _order in (g.START_FIRST, g.DURATION_FIRST):
        add(f"meter_{_order}_{_rel}", twins.meter_grid(R[_rel], _q, PAGE, _order))(lambda spark, sf, rel=_rel, m=_order: layout(spark, sf, rel, m).meter(wl.query_set(spark, MID[rel])))
    _uniform = twins.meter_uniform(R[_rel], _q, G)
    add(f"meter_uniform_grid_{_rel}", _uniform)(lambda spark, sf, rel=_rel: layout(spark, sf, rel, "uniform_grid").meter(wl.query_set(spark, MID[rel])))
    for _m, _refine in (("packed_tree", True), ("packed_tree_box", False)):
        add(f"meter_{_m}_{_rel}", twins.meter_packed(R[_rel], _q, LEAF, _refine))(lambda spark, sf, rel=_rel, m=_m: layout(spark, sf, rel, m).meter(wl.query_set(spark, MID[rel])))
    for _m, _reads, _twice in (
        ("scan", twins.VALID, None), ("ordered_duration", twins.BAND, None), ("ordered_start", f"{twins.VALID} AND (q_hi IS NULL OR t_lo < q_hi)", None),
        ("two_indexes", twins.BAND, f"{twins.VALID} AND (q_hi IS NULL OR t_lo < q_hi)"), ("interval_tree", twins.WINDOW, None),
    ):
        add(f"meter_{_m}_{_rel}", twins.meter_simple(R[_rel], _q, _reads, _twice))(lambda spark, sf, rel=_rel, m=_m: layout(spark, sf, rel, m).meter(wl.query_set(spark, MID[rel])).select("qid", "examined", "matched"))
    add(f"meter_replicating_{_rel}", twins.meter_replicating(R[_rel], twins.literal(MID[_rel][:3]), NB, LEV))(
        lambda spark, sf, rel=_rel: layout(spark, sf, rel, "replicating").meter(wl.query_set(spark, MID[rel][:3])).select("qid", "examined", "matched")
    )

for _rel in ("presc", "trips"):
    add(f"replicating_copies_{_rel}", twins.meter_replicating(R[_rel], twins.literal(MID[_rel][:3]), NB, LEV, once=False))(
        lambda spark, sf, rel=_rel: layout(spark, sf, rel, "replicating_copies").meter(wl.query_set(spark, MID[rel][:3])).select("qid", "examined", "matched")
    )
add("grid_few_keys", twins.describe(R["presc"], 10, "duration_first"))(lambda spark, sf: _described(spark, sf, "presc", 10, g.DURATION_FIRST))
_POOR = twins.literal(MID["presc"][:3])
add("poor_page_size_meter", twins.meter_grid(R["presc"], _POOR, 10, "start_first"))(lambda spark, sf: built(spark, sf, "presc", 10, g.START_FIRST).meter(wl.query_set(spark, MID["presc"][:3])))


@add("precision_by_method")
def precision_by_method(spark, sf):
    """Examined, excess and precision of all methods over a mixed query set."""
    q = written(_union([batch(spark, k, 20).withColumn("qid", F.col("qid") + 100 * i) for i, k in enumerate(BATCH)]), "queries")
    n = slim(spark, sf, "presc").count()
    parts = [measures.accuracy(written(layout(spark, sf, "presc", m).meter(q), "meter"), n).join(q.select("qid", "kind"), "qid").withColumn("method", F.lit(m)) for m in METHODS]
    return _union(parts).groupBy("method", "kind").agg(F.sum("examined").alias("examined"), F.sum("excess").alias("excess"), F.avg("examined_fraction").alias("examined_fraction"), F.avg("precision").alias("precision"))


@add("examined_vs_selectivity")
def examined_vs_selectivity(spark, sf):
    """Each query of a selectivity grid with its achieved selectivities and examined fraction, on the duration-first grid."""
    df = slim(spark, sf, "presc")
    q = written(wl.selectivity_grid(df, 8), "queries")
    s = measures.selectivity(df, q)
    m = built(spark, sf, "presc", PAGE, g.DURATION_FIRST).meter(q)
    return s.join(m, "qid").select("qid", *[(F.col(c) / F.col("n")).alias(c.replace("hits", "selectivity")) for c in ("time_hits", "dur_hits", "both_hits")], (F.col("examined") / F.col("n")).alias("examined_fraction"))


# selectivity -----------------------------------------------------------------------------------------------------------------

add("selectivities", f"""SELECT CAST(qid AS BIGINT) AS qid, count(*) AS n, count(*) FILTER (WHERE {twins.WINDOW}) AS time_hits, count(*) FILTER (WHERE {twins.BAND}) AS dur_hits, count(*) FILTER (WHERE {twins.MATCH}) AS both_hits
FROM ({twins.literal(MID['presc'])}) q, ({R['presc']}) r GROUP BY qid""")(lambda spark, sf: measures.selectivity(slim(spark, sf, "presc"), wl.query_set(spark, MID["presc"])))  # fmt: skip
add("selectivity_identity", f"SELECT CAST(qid AS BIGINT) AS qid, count(*) FILTER (WHERE {twins.WINDOW}) AS time_hits FROM ({wl.random_queries_sql('range', 40, 11, *_ARGS)}) q, ({R['presc']}) r WHERE q_lo < q_hi GROUP BY qid")(
    lambda spark, sf: measures.window_hits(slim(spark, sf, "presc"), batch(spark, "range"))
)


@add("selectivity_grid_achieved")
def selectivity_grid_achieved(spark, sf):
    df = slim(spark, sf, "presc")
    return measures.selectivity(df, written(wl.selectivity_grid(df, 32), "queries"))


# mixes -----------------------------------------------------------------------------------------------------------------------

_RATES = published.values_sql()
_MIX = "1.0 / ((i / 20.0) / range_only + (j / 20.0) / duration_only + (k / 20.0) / range_duration)"
_LATTICE = "SELECT i, j, 20 - i - j AS k FROM range(21) a(i), range(21) b(j) WHERE i + j <= 20"


def rates(spark) -> DataFrame:
    return spark.createDataFrame(published.rows(), "dataset string, method string, pos int, range_only double, duration_only double, range_duration double")


# Rates of methods on the given relations, as queries of MID (range, duration, both) per million rows read. What a method reads
# of a query (q_lo, q_hi, d_min, d_max), in SQL that both engines take.
_READS = {
    "interval_tree": lambda a, b, c, d: "TRUE" if a is None else f"t_lo < {b} AND t_hi > {a}",
    "ordered_duration": lambda a, b, c, d: "TRUE" if c is None else f"dur BETWEEN {c} AND {d}",
    "ordered_start": lambda a, b, c, d: "TRUE" if b is None else f"t_lo < {b}",
    "scan": lambda a, b, c, d: "TRUE",
}
_KINDS = (("range_only", "range"), ("duration_only", "duration"), ("range_duration", "both"))


def _read_by(rel: str, method: str) -> dict[str, str]:
    """What the method reads of the relation's first query of each kind."""
    return {out: next(_READS[method](*q[2:]) for q in MID[rel] if q[1] == kind) for out, kind in _KINDS}


def read_rates(spark, sf) -> DataFrame:
    """dataset, method, pos, range_only, duration_only, range_duration; each relation is read once."""
    parts = []
    for rel in MID:
        rate = lambda cond: F.lit(1e6) / (F.count_if(F.expr(cond)) + 1)
        of = [F.struct(F.lit(rel).alias("dataset"), F.lit(m).alias("method"), F.lit(i).alias("pos"), *[rate(cond).alias(c) for c, cond in _read_by(rel, m).items()]) for i, m in enumerate(_READS)]
        parts.append(slim(spark, sf, rel).agg(F.array(*of).alias("r")).select(F.inline("r")))
    return _union(parts)


_READ_RATES = " UNION ALL ".join(
    f"SELECT '{rel}' AS dataset, '{m}' AS method, {i} AS pos, {', '.join(f'1e6 / (count(*) FILTER (WHERE {cond}) + 1) AS {c}' for c, cond in _read_by(rel, m).items())} FROM ({R[rel]})" for rel in MID for i, m in enumerate(_READS)
)

add("mixed_rate_center", f"SELECT dataset, method, round(1.0 / ((1/3.0) / range_only + (1/3.0) / duration_only + (1/3.0) / range_duration), 4) AS rate FROM ({_READ_RATES})")(
    lambda spark, sf: read_rates(spark, sf).select("dataset", "method", F.round(measures.mixed_rate([F.col("range_only"), F.col("duration_only"), F.col("range_duration")], [F.lit(1 / 3)] * 3), 4).alias("rate"))
)
def _win(rates_sql: str) -> str:
    return f"SELECT dataset, CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(k AS BIGINT) AS k, method AS winner FROM (SELECT *, row_number() OVER (PARTITION BY dataset, i, j, k ORDER BY round({_MIX}, 9) DESC, pos) AS r FROM ({rates_sql}) v, ({_LATTICE}) l) WHERE r = 1"


add("winner_map", _win(_RATES))(lambda spark, sf: measures.winner_map(rates(spark), 20))
add("winner_counts", f"SELECT dataset, winner, count(*) AS points FROM ({_win(_READ_RATES)}) GROUP BY 1, 2")(lambda spark, sf: measures.winner_map(read_rates(spark, sf), 20).groupBy("dataset", "winner").agg(F.count("*").alias("points")))


def _cross(other: str) -> str:
    return f"round((1 / b.{other} - 1 / a.{other}) / ((1 / b.{other} - 1 / a.{other}) + (1 / a.duration_only - 1 / b.duration_only)), 6)"


@add("crossover_duration_share", f"SELECT a.dataset, {_cross('range_only')} AS rest_range_only, {_cross('range_duration')} AS rest_range_duration FROM ({_READ_RATES}) a JOIN ({_READ_RATES}) b ON a.dataset = b.dataset WHERE a.method = 'interval_tree' AND b.method = 'ordered_duration'")
def crossover_duration_share(spark, sf):
    """The share of duration-only queries from which the ordered table reads fewer rows than the interval tree."""
    a, c = read_rates(spark, sf).filter("method = 'interval_tree'").alias("a"), read_rates(spark, sf).filter("method = 'ordered_duration'").alias("b")
    cut = lambda other: F.round(measures.crossover(F.col(f"a.{other}"), F.col("a.duration_only"), F.col(f"b.{other}"), F.col("b.duration_only")), 6)
    return a.join(c, "dataset").select("dataset", cut("range_only").alias("rest_range_only"), cut("range_duration").alias("rest_range_duration"))


# sweeps and scale ------------------------------------------------------------------------------------------------------------

SIZES = (20, 70, 300)
add("page_sweep_shape", " UNION ALL ".join(f"SELECT * FROM ({twins.describe(R['presc'], s, o)})" for s in SIZES for o in ("start_first", "duration_first")))(
    lambda spark, sf: _union([_described(spark, sf, "presc", s, o) for s in SIZES for o in (g.START_FIRST, g.DURATION_FIRST)])
)


@add("page_sweep_examined", " UNION ALL ".join(f"SELECT CAST({s} AS BIGINT) AS cell_rows, '{o}' AS grid_order, qid, examined, cells_visited FROM ({twins.meter_grid(R['presc'], twins.literal(MID['presc'][:3]), s, o)})" for s in SIZES for o in ("start_first", "duration_first")))
def page_sweep_examined(spark, sf):
    q = wl.query_set(spark, MID["presc"][:3])
    named = lambda s, o: built(spark, sf, "presc", s, o).meter(q).select(F.lit(s).cast("long").alias("cell_rows"), F.lit(o).alias("grid_order"), "qid", "examined", "cells_visited")
    return _union([written(named(s, o), "sweep") for s in SIZES for o in (g.START_FIRST, g.DURATION_FIRST)])  # one at a time: the driver plans and holds one grid's joins, not all six


@add("page_sweep_relative")
def page_sweep_relative(spark, sf):
    """Examined rows of each size and order over the best of the same query."""
    from pyspark.sql import Window

    m = page_sweep_examined(spark, sf)
    return m.withColumn("relative", F.min("examined").over(Window.partitionBy("qid")) / F.col("examined"))


add("order_advice")(lambda spark, sf: g.advise_order(slim(spark, sf, "presc"), wl.query_set(spark, MID["presc"][:3]), PAGE))
SPAN = 2600


def scaled(spark, sf, eta):
    return src.scale_up(slim(spark, sf, "presc"), eta, SPAN)


_SCALED = f"SELECT t_lo + c * {SPAN} AS t_lo, t_hi + c * {SPAN} AS t_hi, dur FROM ({R['presc']}), range(5) x(c)"
add("scale_up_rows", f"SELECT count(*) AS n, CAST(min(t_lo) AS BIGINT) AS first, CAST(max(t_hi) AS BIGINT) AS last FROM ({_SCALED})")(lambda spark, sf: scaled(spark, sf, 5).agg(F.count("*").alias("n"), F.min("t_lo").alias("first"), F.max("t_hi").alias("last")))
add("scale_up_constant_output", twins.counts(_SCALED, twins.literal([MID["presc"][0]])))(lambda spark, sf: g.build_grid(scaled(spark, sf, 5), g.GridSpec(PAGE)).count_batch(wl.query_set(spark, [MID["presc"][0]])))
add("scale_up_ordered_examined", twins.meter_simple(_SCALED, twins.literal([MID["presc"][0]]), twins.BAND))(lambda spark, sf: b.Ordered(scaled(spark, sf, 5)).meter(wl.query_set(spark, [MID["presc"][0]])).select("qid", "examined", "matched"))

# timed studies: rows and columns are what they are at every run, the seconds are the machine's ---------------------------------


@add("study_robustness")
def study_robustness(spark, sf):
    """Two of the relations and four of the methods; studies.robustness takes any."""
    names = ("trips", "order_gaps")
    queries = {n: {k: asked(spark, n, k) for k in BATCH} for n in names}
    return studies.robustness({n: relation_of(spark, sf, n) for n in names}, queries, ("duration_first", "uniform_grid", "interval_tree", "ordered_duration"), PAGE)


@add("study_time_per_query")
def study_time_per_query(spark, sf):
    methods = ("duration_first", "scan", "ordered_duration")
    return studies.per_query({m: stored(spark, sf, m) if m in studies.GRIDS else layout(spark, sf, "presc", m) for m in methods}, wl.query_set(spark, MID["presc"][:3]), 2)


for _by in ("random", "append"):
    add(f"study_insertion_{_by}")(lambda spark, sf, by=_by: studies.insertion(slim(spark, sf, "trips"), 2500 if by == "append" else 5000, 20, by))


@add("study_scale_up")
def study_scale_up(spark, sf):
    return studies.scale(slim(spark, sf, "trips"), (1, 10), 50_000, wl.query_set(spark, MID["trips"]), ("duration_first", "ordered_duration"), PAGE)


# maintenance -----------------------------------------------------------------------------------------------------------------

_ALL = twins.counts(R["trips"], twins.literal(MID["trips"]))


def _inserted(spark, sf, order, by):
    def make():
        df = slim(spark, sf, "trips")
        parts = streams.in_batches(df, 3, by)
        out = g.build_grid(parts[0], g.GridSpec(20, order=order))
        for p in parts[1:]:
            out = maintain.insert(out, p)
        return out

    return kept(spark, ("inserted", sf, order, by), make)


for _order in (g.START_FIRST, g.DURATION_FIRST):
    for _by in ("random", "append"):
        add(f"insert_{_by}_then_query_{_order}", _ALL)(lambda spark, sf, o=_order, by=_by: _inserted(spark, sf, o, by).count_batch(wl.query_set(spark, MID["trips"])))
add("remove_then_query", twins.counts(f"SELECT * FROM ({R['trips']}) WHERE event_id % 3 <> 0", twins.literal(MID["trips"])))(
    lambda spark, sf: maintain.remove(_inserted(spark, sf, g.DURATION_FIRST, "random"), slim(spark, sf, "trips").filter("iv_id % 3 = 0")).count_batch(wl.query_set(spark, MID["trips"]))
)
add("split_shape")(lambda spark, sf: _inserted(spark, sf, g.START_FIRST, "random").describe())
add("merge_shape")(lambda spark, sf: maintain.remove(_inserted(spark, sf, g.START_FIRST, "random"), slim(spark, sf, "trips").filter("iv_id % 3 <> 0")).describe())


@add("insert_heavy_then_query", "SELECT * FROM (VALUES (1, 6), (2, 1)) v(qid, matched)")
def insert_heavy_then_query(spark, sf):
    """Copies of one interval, another copy, and a new key routed into the heavy group."""
    rows = lambda ids, lo, dur: [(i, lo, lo + dur, dur) for i in ids]
    frame = lambda r: spark.createDataFrame(r, "iv_id long, t_lo long, t_hi long, dur long")
    grid = g.build_grid(frame(rows(range(5), 10, 3)), g.GridSpec(2))
    grid = maintain.insert(grid, frame(rows([5], 10, 3) + rows([6], 10, 4)))
    return longs(grid.count_batch(wl.query_set(spark, [(1, "duration", None, None, 3, 3), (2, "duration", None, None, 4, 4)])), "qid", "matched")


# sizes and profiles ----------------------------------------------------------------------------------------------------------


@add("bytes_per_interval_logical")
def bytes_per_interval_logical(spark, sf):
    n = slim(spark, sf, "presc").count()
    return _union([measures.bytes_per_interval(layout(spark, sf, "presc", m).stored(), n).withColumn("method", F.lit(m)) for m in METHODS if m != "two_indexes"])


add("start_histogram", f"SELECT CAST(t_lo // 100 AS BIGINT) AS bin, count(*) AS n FROM ({R['presc']}) GROUP BY 1")(lambda spark, sf: measures.histogram(src.presc(spark, sf), "t_lo", 100))
add("duration_histogram", f"SELECT CAST(dur // 10 AS BIGINT) AS bin, count(*) AS n FROM ({R['trips']}) GROUP BY 1")(lambda spark, sf: measures.histogram(src.trips(spark, sf), "dur", 10))


@add("cell_balance_uniform_vs_adaptive")
def cell_balance_uniform_vs_adaptive(spark, sf):
    return _union([measures.balance(layout(spark, sf, "trips", m).groups).withColumn("method", F.lit(m)) for m in ("uniform_grid", "start_first", "duration_first")])


@add("synthetic_profile")
def synthetic_profile(spark, sf):
    parts = [src.synthetic(spark, 20000, s, d, ids=src.event_ids(spark, sf)).agg(F.count("*").alias("n"), F.avg("t_lo").alias("mean_start"), F.avg("dur").alias("mean_dur"), F.max("dur").alias("max_dur")).withColumn("shape", F.lit(f"{s}_{d}")) for s, d in (("uniform", "zipf"), ("skewed", "uniform"))]
    return _union(parts)


add("quarantine_order_ship", f"SELECT CASE WHEN a = b THEN 'empty' ELSE 'inverted' END AS reason, count(*) AS n FROM (SELECT epoch_us(o_orderdate) // {twins.DAY} AS a, epoch_us(l_shipdate) // {twins.DAY} AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey) WHERE a >= b GROUP BY 1")(
    lambda spark, sf: _quarantine(spark, sf)
)


def _quarantine(spark, sf):
    from ..model import axis

    li, o = src.read(spark, sf, "lineitem"), src.read(spark, sf, "orders")
    df = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).select("o_orderdate", "l_shipdate")
    return quarantined(df, axis(F.col("o_orderdate"), "day"), axis(F.col("l_shipdate"), "day")).groupBy("reason").agg(F.count("*").alias("n"))


# temporal extras -------------------------------------------------------------------------------------------------------------


@add("concurrency_profile", f"SELECT CAST(x AS BIGINT) AS x, CAST(sum(d) OVER (ORDER BY x) AS BIGINT) AS running FROM (SELECT x, sum(d) AS d FROM (SELECT t_lo AS x, 1 AS d FROM ({R['presc']}) UNION ALL SELECT t_hi, -1 FROM ({R['presc']})) GROUP BY x)")
def concurrency_profile(spark, sf):
    from pyspark.sql import Window

    df = src.presc(spark, sf)
    steps = df.select(F.col("t_lo").alias("x"), F.lit(1).alias("d")).unionByName(df.select(F.col("t_hi").alias("x"), F.lit(-1).alias("d"))).groupBy("x").agg(F.sum("d").alias("d"))
    return steps.select("x", F.sum("d").over(Window.orderBy("x")).cast("long").alias("running"))  # over distinct instants, already aggregated


@add("coalesce_islands", f"""SELECT user_id, CAST(min(t_lo) AS BIGINT) AS t_lo, CAST(max(t_hi) AS BIGINT) AS t_hi, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t_lo, t_hi, event_id ROWS UNBOUNDED PRECEDING) AS island FROM
(SELECT r.*, e.user_id, CASE WHEN r.t_lo <= max(r.t_hi) OVER (PARTITION BY e.user_id ORDER BY r.t_lo, r.t_hi, r.event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) THEN 0 ELSE 1 END AS fresh FROM ({R['trips']}) r JOIN events e USING (event_id))) GROUP BY user_id, island""")  # fmt: skip
def coalesce_islands(spark, sf):
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("t_lo", "t_hi", "event_id")
    top = F.max("t_hi").over(w.rowsBetween(Window.unboundedPreceding, -1))
    df = src.trips(spark, sf).withColumn("fresh", F.when(F.col("t_lo") <= top, 0).otherwise(1))
    df = df.withColumn("island", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return df.groupBy("user_id", "island").agg(F.min("t_lo").alias("t_lo"), F.max("t_hi").alias("t_hi"), F.count("*").alias("n")).drop("island")


_ALLEN = """CASE WHEN a.t_hi < 10406 AND a.t_hi < 10151 THEN 'before' WHEN a.t_hi = 10151 THEN 'meets' WHEN 10406 < a.t_lo THEN 'after' WHEN 10406 = a.t_lo THEN 'met_by' WHEN a.t_lo = 10151 AND a.t_hi = 10406 THEN 'equals'
WHEN a.t_lo = 10151 AND a.t_hi < 10406 THEN 'starts' WHEN a.t_lo = 10151 THEN 'started_by' WHEN a.t_hi = 10406 AND a.t_lo > 10151 THEN 'finishes' WHEN a.t_hi = 10406 THEN 'finished_by'
WHEN a.t_lo > 10151 AND a.t_hi < 10406 THEN 'during' WHEN a.t_lo < 10151 AND a.t_hi > 10406 THEN 'contains' WHEN a.t_lo < 10151 THEN 'overlaps' ELSE 'overlapped_by' END"""
add("allen_relations", f"SELECT {_ALLEN} AS relation, count(*) AS n FROM ({R['presc']}) a GROUP BY 1")(
    lambda spark, sf: src.presc(spark, sf).select(relation(F.col("t_lo"), F.col("t_hi"), F.lit(10151), F.lit(10406)).alias("relation")).groupBy("relation").agg(F.count("*").alias("n"))
)
add("interval_overlap_join", f"SELECT a.event_id AS a_id, b.event_id AS b_id FROM ({R['trips']}) a JOIN ({R['trips']}) b ON a.t_lo < b.t_hi AND b.t_lo < a.t_hi WHERE a.dur BETWEEN 100 AND 500 AND b.dur BETWEEN 100 AND 500")(
    lambda spark, sf: g.interval_join(slim(spark, sf, "trips"), slim(spark, sf, "trips"), 200, 100, 500)
)


@add("event_in_interval_join", f"SELECT r.event_id AS interval_id, count(*) AS n FROM ({R['gaps']}) r JOIN events e ON epoch_us(e.ts) >= r.t_lo AND epoch_us(e.ts) < r.t_hi WHERE r.dur < 2000000000 GROUP BY 1")
def event_in_interval_join(spark, sf):
    from ..model import axis

    slot = 2_000_000_000
    iv = slim(spark, sf, "gaps").filter(F.col("dur") < slot)
    iv = iv.withColumn("slot", F.explode(F.sequence(F.floor(F.col("t_lo") / slot), F.floor((F.col("t_hi") - 1) / slot))))
    ev = src.read(spark, sf, "events").select(axis(F.col("ts")).alias("x")).withColumn("slot", F.floor(F.col("x") / slot))
    return iv.join(ev, "slot").filter((F.col("x") >= F.col("t_lo")) & (F.col("x") < F.col("t_hi"))).groupBy(F.col("iv_id").alias("interval_id")).agg(F.count("*").alias("n"))


@add("grid_count", twins.counts(R["presc"], twins.literal(MID["presc"])))
def grid_count(spark, sf):
    """The table function on a saved grid, once for each query."""
    import uuid

    from ..functions import surface
    from ..storage import shared_dir

    surface.register(spark)
    path = f"{shared_dir(spark)}/grid-count-{uuid.uuid4().hex}"
    g.build_grid(slim(spark, sf, "presc"), g.GridSpec(PAGE)).save(path)
    wl.query_set(spark, MID["presc"]).createOrReplaceTempView("v_queries")
    return spark.sql("SELECT CAST(qid AS BIGINT) AS qid, matched FROM v_queries, LATERAL grid_count(:path, q_lo, q_hi, d_min, d_max)", args={"path": path})


# the two joins above over whole tables, as counts per interval: of the longest gaps and shortest trips too

add("interval_overlap_counts", f"SELECT a.event_id AS interval_id, count(*) AS n FROM ({R['trips']}) a JOIN ({R['trips']}) b ON a.t_lo < b.t_hi AND b.t_lo < a.t_hi GROUP BY 1")(
    lambda spark, sf: g.overlap_counts(slim(spark, sf, "trips"), slim(spark, sf, "trips"))
)


@add("event_in_any_interval_join", f"SELECT r.event_id AS interval_id, count(*) AS n FROM ({R['gaps']}) r JOIN events e ON epoch_us(e.ts) >= r.t_lo AND epoch_us(e.ts) < r.t_hi GROUP BY 1")
def event_in_any_interval_join(spark, sf):
    from ..model import axis

    return g.points_within(slim(spark, sf, "gaps"), src.read(spark, sf, "events").select(axis(F.col("ts")).alias("x")))


add("point_grid", f"""WITH RECURSIVE base AS (SELECT vec_id, CAST(floor(CAST(embedding[1] AS DOUBLE) * 1000) AS BIGINT) AS x, CAST(floor(CAST(embedding[2] AS DOUBLE) * 1000) AS BIGINT) AS y FROM embeddings), {twins.packed("c", "base", "x", 100)},
half AS (SELECT base.*, c.g AS c0 FROM base JOIN c ON c.key = base.x), {twins.packed("d", "half", "y", 10, "c0")} SELECT vec_id, CAST(c0 AS BIGINT) AS cell_0, CAST(d.g AS BIGINT) AS cell_1 FROM half JOIN d ON d.b = half.c0 AND d.key = half.y""")(  # fmt: skip
    lambda spark, sf: g.build_point_grid(src.points(spark, sf), ["x", "y"], [100, 10]).select("vec_id", "cell_0", "cell_1")
)

# streams ---------------------------------------------------------------------------------------------------------------------

add("stream_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")(streams.tumbling)
add("stream_sliding", "SELECT strftime(d, '%Y-%m-%d') AS day, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY 1")(streams.sliding)
add("stream_session", """SELECT user_id, CAST(min(us) AS BIGINT) AS t_lo, CAST(max(us) + 1800000000 AS BIGINT) AS t_hi, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS s FROM
(SELECT user_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")(streams.sessions)  # fmt: skip
add("stream_gaps", f"SELECT e.user_id, r.event_id, r.t_lo, r.t_hi, r.dur FROM ({R['gaps']}) r JOIN events e USING (event_id)")(streams.gaps)
add("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")(streams.deduplicated)
add("stream_ingest_then_query", _ALL)(lambda spark, sf: streams.ingest_trips(spark, sf, g.GridSpec(20)).count_batch(wl.query_set(spark, MID["trips"])))
