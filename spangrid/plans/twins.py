"""SQL twins: the interval relations, packing, grids and meters in the SQL of the checking engine."""

from __future__ import annotations

DAY, MINUTE = 86_400_000_000, 60_000_000

RELATIONS = {
    "presc": f"SELECT * FROM (SELECT epoch_us(l_shipdate) // {DAY} AS t_lo, epoch_us(l_shipdate) // {DAY} + CAST(l_quantity AS BIGINT) AS t_hi, CAST(l_quantity AS BIGINT) AS dur, * FROM lineitem) WHERE dur > 0",
    "trips": f"SELECT epoch_us(ts) // {MINUTE} AS t_lo, epoch_us(ts) // {MINUTE} + CAST(floor(value) AS BIGINT) + 1 AS t_hi, CAST(floor(value) AS BIGINT) + 1 AS dur, event_id FROM events WHERE value >= 0",
    "gaps": "SELECT t_lo, t_hi, t_hi - t_lo AS dur, event_id FROM (SELECT epoch_us(ts) AS t_lo, lead(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS t_hi, event_id FROM events) WHERE t_hi > t_lo",
    "order_gaps": f"SELECT t_lo, t_hi, t_hi - t_lo AS dur, o_orderkey FROM (SELECT epoch_us(o_orderdate) // {DAY} AS t_lo, lead(epoch_us(o_orderdate) // {DAY}) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS t_hi, o_orderkey FROM orders) WHERE t_hi > t_lo",
    "order_ship": f"SELECT least(a, b) AS t_lo, greatest(a, b) AS t_hi, abs(b - a) AS dur FROM (SELECT epoch_us(o_orderdate) // {DAY} AS a, epoch_us(l_shipdate) // {DAY} AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey) WHERE a <> b",
    "utterances": "SELECT t_lo, t_hi, t_hi - t_lo AS dur, conv_id, turn FROM (SELECT conv_id, turn, sum(length(text)) OVER (PARTITION BY conv_id ORDER BY turn) - length(text) AS t_lo, sum(length(text)) OVER (PARTITION BY conv_id ORDER BY turn) AS t_hi FROM conversations) WHERE t_hi > t_lo",
}


def synthetic(n: int, starts: str, lengths: str, most: int = 100, seed: int = 7, ids: str | None = None) -> str:
    """The generated relations, by the same integer generator."""
    from ..sources.intervals import zipf_cuts

    x = lambda salt: f"((id * 48271 + {seed * 16807 + salt * 69621}) * 40692) % 2147483647"
    lo = f"u % {n} + 1"
    lo = f"CAST(floor(({lo}) * ({lo}) / {n}.0) AS BIGINT) + 1" if starts == "skewed" else lo
    dur = f"len([c FOR c IN {zipf_cuts(most)} IF c < v]) + 1" if lengths == "zipf" else f"v % {most} + 1"
    return f"SELECT id AS iv_id, t_lo, t_lo + dur AS t_hi, dur FROM (SELECT id, {lo} AS t_lo, CAST({dur} AS BIGINT) AS dur FROM (SELECT id, {x(1)} AS u, {x(2)} AS v FROM {ids or f'range({n}) r(id)'}))"


EVENT_IDS = "(SELECT event_id % 2147483647 AS id FROM events) r"

VALID = "(q_lo IS NULL OR q_hi IS NULL OR q_lo < q_hi) AND (d_min IS NULL OR d_max IS NULL OR d_min <= d_max)"
WINDOW = f"{VALID} AND (q_hi IS NULL OR t_lo < q_hi) AND (q_lo IS NULL OR t_hi > q_lo)"
BAND = f"{VALID} AND (d_min IS NULL OR dur >= d_min) AND (d_max IS NULL OR dur <= d_max)"
MATCH = f"{WINDOW} AND {BAND}"


def literal(rows: list[tuple]) -> str:
    one = lambda v: "NULL" if v is None else f"'{v}'" if isinstance(v, str) else str(v)
    return "SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(map(one, r)) + ")" for r in rows) + ") v(qid, kind, q_lo, q_hi, d_min, d_max)"


def counts(relation: str, queries: str) -> str:
    return f"SELECT CAST(q.qid AS BIGINT) AS qid, CAST(count(r.t_lo) AS BIGINT) AS matched FROM ({queries}) q LEFT JOIN ({relation}) r ON {MATCH} GROUP BY q.qid"


def packed(out: str, source: str, key: str, budget: int, by: str | None = None) -> str:
    """CTEs that number the packed groups of a key (within ``by``) into table ``out`` (by, key, g)."""
    b = by or "0"
    return f"""{out}_k AS (SELECT b, key, n, row_number() OVER (PARTITION BY b ORDER BY key) AS i FROM (SELECT {b} AS b, {key} AS key, count(*) AS n FROM {source} GROUP BY 1, 2)),
{out}_w AS (SELECT b, i, n AS fill, 0 AS g FROM {out}_k WHERE i = 1 UNION ALL
  SELECT k.b, k.i, CASE WHEN w.fill + k.n > {budget} THEN k.n ELSE w.fill + k.n END, CASE WHEN w.fill + k.n > {budget} THEN w.g + 1 ELSE w.g END FROM {out}_w w JOIN {out}_k k ON k.b = w.b AND k.i = w.i + 1),
{out} AS (SELECT k.b, k.key, w.g FROM {out}_k k JOIN {out}_w w ON w.b = k.b AND w.i = k.i)"""


def grid(relation: str, s: int, order: str, budget: int | None = None) -> str:
    """WITH clause that defines placed (rows with col_id, cell_id), pages and cols."""
    k1, k2 = ("t_lo", "dur") if order == "start_first" else ("dur", "t_lo")
    low1, top1 = ("min(t_lo)", "max(t_lo)") if order == "start_first" else ("min(dur)", "max(dur)")
    second = "min_dur" if order == "start_first" else "min_lo"
    return f"""WITH RECURSIVE base AS ({relation}),
{packed("c", "base", k1, budget or s * s)},
half AS (SELECT base.*, c.g AS col_id FROM base JOIN c ON c.key = base.{k1}),
{packed("d", "half", k2, s, "col_id")},
placed AS (SELECT half.*, d.g AS cell_id FROM half JOIN d ON d.b = half.col_id AND d.key = half.{k2}),
pages0 AS (SELECT col_id, cell_id, count(*) AS n, min(t_lo) AS min_lo, max(t_lo) AS max_lo, min(t_hi) AS min_hi, max(t_hi) AS max_hi, min(dur) AS min_dur, max(dur) AS max_dur FROM placed GROUP BY 1, 2),
pages AS (SELECT *, max(max_hi) OVER (PARTITION BY col_id ORDER BY {second} ROWS UNBOUNDED PRECEDING) AS run_max_hi, n > {s} AS heavy FROM pages0),
cols0 AS (SELECT col_id, count(*) AS n, {low1} AS min_key, {top1} AS max_key, max(t_hi) AS max_hi, count(DISTINCT cell_id) AS n_cells FROM placed GROUP BY 1),
cols AS (SELECT *, max(max_hi) OVER (ORDER BY min_key ROWS UNBOUNDED PRECEDING) AS run_max_hi, n > {budget or s * s} AS heavy FROM cols0)"""


def pages(relation: str, s: int, order: str) -> str:
    names = "col_id, cell_id, n, min_lo, max_lo, min_hi, max_hi, min_dur, max_dur, run_max_hi"
    return f"{grid(relation, s, order)} SELECT {', '.join(f'CAST({c} AS BIGINT) AS {c}' for c in names.split(', '))}, heavy FROM pages"


def columns(relation: str, s: int, order: str) -> str:
    names = "col_id, n, min_key, max_key, max_hi, n_cells, run_max_hi"
    return f"{grid(relation, s, order)} SELECT {', '.join(f'CAST({c} AS BIGINT) AS {c}' for c in names.split(', '))}, heavy FROM cols"


def describe(relation: str, s: int, order: str) -> str:
    return f"""{grid(relation, s, order)} SELECT CAST({s} AS BIGINT) AS cell_rows, '{order}' AS grid_order, (SELECT count(*) FROM cols) AS columns, count(*) AS cells, (SELECT count(*) FROM cols WHERE heavy) AS heavy_columns,
    count(*) FILTER (WHERE heavy) AS heavy_cells, CAST(max(n) AS BIGINT) AS largest_cell FROM pages"""


_SUMS = "CAST(coalesce(sum(hits), 0) AS BIGINT) AS examined, CAST(coalesce(sum(least(n, hits + 1)), 0) AS BIGINT) AS examined_incl_stop, CAST(coalesce(sum(ok), 0) AS BIGINT) AS matched"


def _metered(with_: str, queries: str, source: str, gid: str, groups: str, meets: str, reads: str, ok: str = MATCH, column: str = "1") -> str:
    on = " AND ".join(f"r.{g} = s.{g}" for g in gid.split(", "))
    pick = ", ".join(f"s.{g}" for g in gid.split(", "))
    return f"""{with_} seen AS (SELECT q.*, g.n, {', '.join('g.' + x for x in gid.split(', '))} FROM ({queries}) q JOIN ({groups}) g ON {VALID} AND {meets}),
per AS (SELECT qid, {pick}, min(s.n) AS n, count(*) FILTER (WHERE {reads}) AS hits, count(*) FILTER (WHERE {ok}) AS ok FROM seen s JOIN ({source}) r ON {on} GROUP BY qid, {pick})
SELECT CAST(q.qid AS BIGINT) AS qid, CAST(count(DISTINCT CASE WHEN per.qid IS NOT NULL THEN {column} END) AS BIGINT) AS columns_visited, CAST(count(per.qid) AS BIGINT) AS cells_visited, {_SUMS} FROM ({queries}) q LEFT JOIN per ON per.qid = q.qid GROUP BY q.qid"""


def meter_grid(relation: str, queries: str, s: int, order: str) -> str:
    if order == "start_first":
        meets = "(q_hi IS NULL OR c_min < q_hi) AND (q_lo IS NULL OR c_run > q_lo) AND (d_max IS NULL OR min_dur <= d_max) AND (d_min IS NULL OR max_dur >= d_min)"
    else:
        meets = "(d_max IS NULL OR c_min <= d_max) AND (d_min IS NULL OR c_max >= d_min) AND (q_hi IS NULL OR min_lo < q_hi) AND (q_lo IS NULL OR run_max_hi > q_lo)"
    groups = "SELECT p.*, c.min_key AS c_min, c.max_key AS c_max, c.run_max_hi AS c_run FROM pages p JOIN cols c ON c.col_id = p.col_id"
    return _metered(grid(relation, s, order) + ",", queries, "SELECT * FROM placed", "col_id, cell_id", groups, meets, "q_lo IS NULL OR t_hi > q_lo", column="per.col_id")


def meter_uniform(relation: str, queries: str, g: int) -> str:
    with_ = f"""WITH base AS ({relation}), lim AS (SELECT min(t_lo) AS x0, min(dur) AS y0, CAST(ceil((max(t_lo) - min(t_lo) + 1) / {g}.0) AS BIGINT) AS wx, CAST(ceil((max(dur) - min(dur) + 1) / {g}.0) AS BIGINT) AS wy FROM base),
cells AS (SELECT base.*, (t_lo - x0) // wx AS cx, (dur - y0) // wy AS cy FROM base, lim),"""
    groups = "SELECT cx, cy, count(*) AS n, min(cx * wx + x0) AS x, min(cx * wx + x0 + wx - 1) AS x1, min(cy * wy + y0) AS y, min(cy * wy + y0 + wy - 1) AS y1 FROM cells, lim GROUP BY cx, cy"
    meets = "(q_hi IS NULL OR x < q_hi) AND (q_lo IS NULL OR x1 + y1 > q_lo) AND (d_max IS NULL OR y <= d_max) AND (d_min IS NULL OR y1 >= d_min)"
    return _metered(with_, queries, "SELECT * FROM cells", "cx, cy", groups, meets, "TRUE")


def meter_packed(relation: str, queries: str, m: int, refine: bool) -> str:
    with_ = f"""WITH base AS ({relation}), ord AS (SELECT *, row_number() OVER (ORDER BY t_lo, dur) - 1 AS o FROM base), c AS (SELECT count(*) AS n FROM base),
s1 AS (SELECT ord.*, o // CAST(ceil(c.n / ceil(sqrt(c.n / {m}.0))) AS BIGINT) AS slice FROM ord, c),
tiles AS (SELECT *, (row_number() OVER (PARTITION BY slice ORDER BY dur, t_lo) - 1) // {m} AS leaf FROM s1),"""
    groups = "SELECT slice, leaf, count(*) AS n, min(t_lo) AS a, max(t_lo) AS b, min(dur) AS c, max(dur) AS d, max(t_hi) AS e FROM tiles GROUP BY slice, leaf"
    meets = "(q_hi IS NULL OR a < q_hi) AND (q_lo IS NULL OR d_max IS NULL OR b > q_lo - d_max) AND (d_max IS NULL OR c <= d_max) AND (d_min IS NULL OR d >= d_min)"
    return _metered(with_, queries, "SELECT * FROM tiles", "slice, leaf", groups, meets + (" AND (q_lo IS NULL OR e > q_lo)" if refine else ""), "TRUE")


def meter_simple(relation: str, queries: str, reads: str, twice: str | None = None) -> str:
    """qid, examined, matched of the methods whose examined rows are those with one or two properties."""
    second = f" + count(*) FILTER (WHERE {twice})" if twice else ""
    return f"SELECT CAST(qid AS BIGINT) AS qid, CAST(count(*) FILTER (WHERE {reads}){second} AS BIGINT) AS examined, CAST(count(*) FILTER (WHERE {MATCH}) AS BIGINT) AS matched FROM ({queries}) q, ({relation}) r GROUP BY qid"


def meter_replicating(relation: str, queries: str, buckets: int, levels: int, once: bool = True) -> str:
    """qid, examined (copies read), matched (rows, or copies if not ``once``)."""
    owner = "AND greatest(t_lo, coalesce(q_lo, t_lo)) >= a AND greatest(t_lo, coalesce(q_lo, t_lo)) < b" if once else ""
    return f"""WITH RECURSIVE base AS ({relation}), size AS (SELECT CAST(ceil(count(*) / {buckets}.0) AS BIGINT) AS b FROM base),
c_k AS (SELECT key, n, row_number() OVER (ORDER BY key) AS i FROM (SELECT t_lo AS key, count(*) AS n FROM base GROUP BY 1)),
c_w AS (SELECT i, n AS fill, 0 AS g FROM c_k WHERE i = 1 UNION ALL SELECT k.i, CASE WHEN w.fill + k.n > b THEN k.n ELSE w.fill + k.n END, CASE WHEN w.fill + k.n > b THEN w.g + 1 ELSE w.g END FROM c_w w JOIN c_k k ON k.i = w.i + 1, size),
cuts AS (SELECT g AS bucket, min(key) AS b_lo FROM c_k JOIN c_w USING (i) GROUP BY g),
spans AS (SELECT bucket, b_lo, coalesce(lead(b_lo) OVER (ORDER BY b_lo), (SELECT max(t_hi) FROM base)) AS b_hi FROM cuts),
slots AS (SELECT bucket, b_lo, b_hi, lv AS level, greatest(1, CAST(ceil((b_hi - b_lo) / CAST(2 ** lv AS DOUBLE)) AS BIGINT)) AS w FROM spans, range({levels}) l(lv)),
own AS (SELECT base.t_lo, base.t_hi, base.dur, s.bucket, s.b_lo, s.b_hi, greatest((SELECT count(*) FROM slots z WHERE z.bucket = s.bucket AND z.w >= base.dur) - 1, 0) AS level FROM base JOIN spans s ON base.t_lo < s.b_hi AND base.t_hi > s.b_lo),
copies AS (SELECT own.*, s.w, unnest(range((greatest(t_lo, own.b_lo) - own.b_lo) // s.w, (least(t_hi, own.b_hi) - 1 - own.b_lo) // s.w + 1)) AS slot FROM own JOIN slots s ON s.bucket = own.bucket AND s.level = own.level),
band AS (SELECT bucket, level, min(dur) AS l_min, max(dur) AS l_max FROM copies GROUP BY 1, 2),
slotted AS (SELECT c.*, c.b_lo + slot * w AS a, least(c.b_lo + slot * w + w, c.b_hi) AS b, l_min, l_max FROM copies c JOIN band USING (bucket, level))
SELECT CAST(qid AS BIGINT) AS qid, CAST(count(*) AS BIGINT) AS examined, CAST(count(*) FILTER (WHERE {MATCH} {owner}) AS BIGINT) AS matched
FROM ({queries}) q JOIN slotted ON (q_hi IS NULL OR a < q_hi) AND (q_lo IS NULL OR b > q_lo) AND (d_max IS NULL OR l_min <= d_max) AND (d_min IS NULL OR l_max >= d_min) GROUP BY qid"""
