"""The plain operators that users of interval tables compose with: joins, aggregates, windows, sets, functions, sources."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import surface
from ..sources import intervals as src
from ..storage import shared_dir
from . import twins

QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}
R = twins.RELATIONS


def add(name: str, sql: str | None = None):
    def put(f: Callable) -> Callable:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


t = src.read

# scans and formats


@add("rel_scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1997-02-01' AND l_quantity BETWEEN 5 AND 8")
def scan_pruned(spark: SparkSession, sf: str) -> DataFrame:
    d = lambda x: F.lit(x).cast("timestamp_ntz")
    return t(spark, sf, "lineitem").filter((F.col("l_shipdate") >= d("1997-01-01")) & (F.col("l_shipdate") < d("1997-02-01")) & F.col("l_quantity").between(5, 8)).select("l_orderkey", "l_quantity")


def _round_trip(fmt: str):
    def f(spark, sf):
        at = f"{shared_dir(spark)}/{fmt}-{uuid.uuid4().hex}"
        df = src.trips(spark, sf).select("t_lo", "t_hi", "dur", "event_id")
        df.write.format(fmt).option("header", "true").save(at)
        reader = spark.read.schema(df.schema)
        return (reader.option("header", "true") if fmt == "csv" else reader).format(fmt).load(at)

    return f


for _fmt in ("csv", "json", "orc", "parquet"):
    add(f"rel_round_trip_{_fmt}", f"SELECT t_lo, t_hi, dur, event_id FROM ({R['trips']})")(_round_trip(_fmt))


@add("rel_sql_view", "SELECT r_name, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey WHERE n_name LIKE '%A%' GROUP BY r_name")
def sql_view(spark, sf):
    for name in ("nation", "region"):
        t(spark, sf, name).createOrReplaceTempView(f"v_{name}")
    return spark.sql("SELECT r_name, count(*) AS n FROM v_nation JOIN v_region ON n_regionkey = r_regionkey WHERE n_name LIKE :pattern GROUP BY r_name", args={"pattern": "%A%"})


@add("rel_sql_functions", f"SELECT event_id, greatest(least(t_hi, 28422800) - greatest(t_lo, 28418464), 0) AS inside FROM ({R['trips']}) WHERE t_lo < 28422800 AND t_hi > 28418464 AND dur BETWEEN 12 AND 26")
def sql_functions(spark, sf):
    surface.register(spark)
    src.trips(spark, sf).createOrReplaceTempView("v_trips")
    return spark.sql("SELECT event_id, interval_overlap(t_lo, t_hi, 28418464, 28422800) AS inside FROM v_trips WHERE interval_meets(t_lo, t_hi, 28418464, 28422800) AND length_in(t_lo, t_hi, 12, 26)")


_LINES = "SELECT n, count(*) AS orders FROM (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1) GROUP BY 1"


@add("rel_udtf_lattice", f"SELECT n, orders, CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(n - i - j AS BIGINT) AS k FROM (SELECT n, orders, i, unnest(range(n - i + 1)) AS j FROM (SELECT n, orders, unnest(range(n + 1)) AS i FROM ({_LINES})))")
def udtf_lattice(spark, sf):
    """All ways to deal an order's lines into three parts, beside how many orders have so many."""
    surface.register(spark)
    lines = t(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("orders"))
    lines.createOrReplaceTempView("v_lines")
    return spark.sql("SELECT n, orders, i, j, k FROM v_lines, LATERAL lattice(CAST(n AS INT))")


# joins

_DIM = "FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


@add("rel_join_star", f"SELECT r_name, count(*) AS n, CAST(round(sum(o_totalprice), 2) AS DOUBLE) AS total {_DIM} GROUP BY r_name")
def join_star(spark, sf):
    o, c, n, r = (t(spark, sf, x) for x in ("orders", "customer", "nation", "region"))
    # nation and region are fixed small tables
    j = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


for _hint in ("merge", "shuffle_hash"):
    add(f"rel_join_{_hint}", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")(
        lambda spark, sf, h=_hint: t(spark, sf, "orders").hint(h).join(t(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))
    )

for _kind, _sql in (
    ("left_semi", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45)"),
    ("left_anti", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45)"),
):
    add(f"rel_join_{_kind}", _sql)(lambda spark, sf, k=_kind: t(spark, sf, "orders").join(t(spark, sf, "lineitem").filter("l_quantity > 45"), F.col("o_orderkey") == F.col("l_orderkey"), k).select("o_orderkey"))

for _kind in ("left", "right", "full"):
    add(f"rel_join_{_kind}", f"SELECT o_orderkey, l_linenumber FROM (SELECT * FROM orders WHERE o_totalprice > 200000) {_kind} JOIN (SELECT * FROM lineitem WHERE l_quantity > 48) ON o_orderkey = l_orderkey")(
        lambda spark, sf, k=_kind: t(spark, sf, "orders").filter("o_totalprice > 200000").join(t(spark, sf, "lineitem").filter("l_quantity > 48"), F.col("o_orderkey") == F.col("l_orderkey"), k).select("o_orderkey", "l_linenumber")
    )


@add("rel_join_asof", """SELECT p.event_id, c.event_id AS click_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'click' GROUP BY 1, 2) c ON p.user_id = c.user_id AND p.ts >= c.ts""")
def join_asof(spark, sf):
    """The last click of the user at or before each purchase: union and a running last value, one shuffle."""
    e = t(spark, sf, "events").filter(F.col("event_type").isin("purchase", "click"))
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "purchase", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("click_id", F.last(click, ignorenulls=True).over(w)).filter("event_type = 'purchase'").select("event_id", "click_id")


@add("rel_lateral_top", f"SELECT qid, t_lo, dur FROM (SELECT qid, t_lo, dur, row_number() OVER (PARTITION BY qid ORDER BY dur DESC, t_lo, event_id) AS r FROM ({R['trips']}), (SELECT * FROM (VALUES (1, 28418464, 28422800), (2, 28430000, 28431000)) v(qid, a, b)) WHERE t_lo < b AND t_hi > a) WHERE r <= 5")
def lateral_top(spark, sf):
    """The longest five intervals meeting each window."""
    q = spark.createDataFrame([(1, 28418464, 28422800), (2, 28430000, 28431000)], "qid int, a long, b long")
    j = src.trips(spark, sf).join(F.broadcast(q), (F.col("t_lo") < F.col("b")) & (F.col("t_hi") > F.col("a")))  # a few queries
    r = F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("dur"), "t_lo", "event_id"))
    return j.withColumn("r", r).filter("r <= 5").select("qid", "t_lo", "dur")


# aggregates

_GROUPS = "count(*) AS n, CAST(sum(l_quantity) AS DOUBLE) AS q, GROUPING(l_returnflag) AS gf, GROUPING(l_linestatus) AS gs"
for _kind in ("rollup", "cube"):
    add(f"rel_agg_{_kind}", f"SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS DOUBLE) AS q FROM lineitem GROUP BY {_kind} (l_returnflag, l_linestatus)")(
        lambda spark, sf, k=_kind: getattr(t(spark, sf, "lineitem"), k)("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))
    )


@add("rel_agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark, sf):
    t(spark, sf, "lineitem").createOrReplaceTempView("v_lineitem")
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM v_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


@add("rel_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(*) FILTER (WHERE value > 50) AS big, CAST(min(event_id) AS BIGINT) AS first_id FROM events GROUP BY 1")
def agg_distinct(spark, sf):
    return t(spark, sf, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_if(F.col("value") > 50).alias("big"), F.min("event_id").alias("first_id"))


@add("rel_agg_approx_distinct")
def agg_approx_distinct(spark, sf):
    return t(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


@add("rel_agg_pivot", "SELECT event_type, count(*) FILTER (WHERE user_id % 3 = 0) AS \"0\", count(*) FILTER (WHERE user_id % 3 = 1) AS \"1\", count(*) FILTER (WHERE user_id % 3 = 2) AS \"2\" FROM events GROUP BY 1")
def agg_pivot(spark, sf):
    return t(spark, sf, "events").withColumn("m", F.col("user_id") % 3).groupBy("event_type").pivot("m", [0, 1, 2]).agg(F.count(F.lit(1))).na.fill(0)


@add("rel_unpivot", "SELECT event_id, name, v FROM (SELECT event_id, CAST(user_id AS BIGINT) AS user_id, CAST(event_id * 2 AS BIGINT) AS twice FROM events WHERE event_id < 100) UNPIVOT (v FOR name IN (user_id, twice))")
def unpivot(spark, sf):
    e = t(spark, sf, "events").filter("event_id < 100").select("event_id", "user_id", (F.col("event_id") * 2).alias("twice"))
    return e.unpivot(["event_id"], ["user_id", "twice"], "name", "v")


@add("rel_unpivot_whole", "SELECT event_id, name, v FROM (SELECT event_id, CAST(user_id AS BIGINT) AS user_id, CAST(event_id * 2 AS BIGINT) AS twice FROM events) UNPIVOT (v FOR name IN (user_id, twice))")
def unpivot_whole(spark, sf):
    e = t(spark, sf, "events").select("event_id", "user_id", (F.col("event_id") * 2).alias("twice"))
    return e.unpivot(["event_id"], ["user_id", "twice"], "name", "v")


@add("rel_agg_percentile", f"SELECT quantile_cont(dur, 0.5) AS median, quantile_cont(dur, 0.9) AS p90, arg_max(event_id, dur * 1000000 + event_id) AS longest FROM ({R['trips']})")
def agg_percentile(spark, sf):
    return src.trips(spark, sf).agg(F.percentile("dur", F.lit(0.5)).alias("median"), F.percentile("dur", F.lit(0.9)).alias("p90"), F.max_by("event_id", F.col("dur") * 1000000 + F.col("event_id")).alias("longest"))


@add("rel_agg_quantile_sketch")
def agg_quantile_sketch(spark, sf):
    return src.trips(spark, sf).agg(F.percentile_approx("dur", [0.25, 0.5, 0.75], 10000).alias("quartiles"))


# windows


@add("rel_window_ranks", "SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(cume_dist() OVER w, 9) AS cd, round(percent_rank() OVER w, 9) AS pr FROM (SELECT *, floor(value) AS f FROM events) WINDOW w AS (PARTITION BY event_type ORDER BY f, event_id)")
def window_ranks(spark, sf):
    w = Window.partitionBy("event_type").orderBy(F.floor("value"), "event_id")
    i = lambda c: c.over(w).cast("long")
    return t(spark, sf, "events").select("event_id", i(F.row_number()).alias("rn"), i(F.rank()).alias("rk"), i(F.dense_rank()).alias("dr"), i(F.ntile(4)).alias("nt"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@add("rel_window_frames", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS near, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS f, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS l, max(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS top FROM events")
def window_frames(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = F.col("event_id")
    return t(spark, sf, "events").select("event_id", F.count("*").over(w.rowsBetween(-3, 0)).alias("near"), F.first(e).over(w).alias("f"), F.lag(e).over(w).alias("l"), F.max(e).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("top"))


@add("rel_window_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS day_before FROM events")
def window_range(spark, sf):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)
    return t(spark, sf, "events").select("event_id", F.count("*").over(w).alias("day_before"))


# sort, limit, sets


@add("rel_top_k", f"SELECT event_id, dur FROM ({R['trips']}) ORDER BY dur DESC, event_id LIMIT 20")
def top_k(spark, sf):
    return src.trips(spark, sf).orderBy(F.desc("dur"), "event_id").limit(20).select("event_id", "dur")


@add("rel_offset", f"SELECT event_id, dur FROM ({R['trips']}) ORDER BY dur DESC, event_id LIMIT 10 OFFSET 20")
def offset(spark, sf):
    return src.trips(spark, sf).orderBy(F.desc("dur"), "event_id").offset(20).limit(10).select("event_id", "dur")


_A, _B = "SELECT user_id, event_type FROM events WHERE value > 60", "SELECT user_id, event_type FROM events WHERE value < 20"
for _kind, _word in (("intersect", "INTERSECT"), ("intersectAll", "INTERSECT ALL"), ("exceptAll", "EXCEPT ALL"), ("unionByName", "UNION ALL")):
    add(f"rel_set_{_kind}", f"{_A} {_word} {_B}")(
        lambda spark, sf, k=_kind: getattr(t(spark, sf, "events").filter("value > 60").select("user_id", "event_type"), k)(t(spark, sf, "events").filter("value < 20").select("user_id", "event_type"))
    )

# functions


@add("rel_functions_time", "SELECT event_id, date_trunc('hour', ts) AS hour, CAST(dayofmonth(ts) AS BIGINT) AS day, epoch_us(ts) // 60000000 AS minute, datediff('day', TIMESTAMP '2024-01-01', ts) AS days FROM events")
def functions_time(spark, sf):
    from ..model import axis

    return t(spark, sf, "events").select("event_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour"), F.dayofmonth("ts").cast("long").alias("day"), axis(F.col("ts"), "minute").alias("minute"), F.datediff("ts", F.lit("2024-01-01")).cast("long").alias("days"))


@add("rel_functions_bits", f"SELECT event_id, t_lo >> 3 AS r, t_lo << 2 AS l, xor(t_lo, t_hi) AS x, length(bin(xor(t_lo - 1, t_hi))) - 1 AS h FROM ({R['trips']})")
def functions_bits(spark, sf):
    a, b = F.col("t_lo"), F.col("t_hi")
    return src.trips(spark, sf).select("event_id", F.shiftright(a, 3).alias("r"), F.shiftleft(a, 2).alias("l"), a.bitwiseXOR(b).alias("x"), (F.length(F.bin((a - 1).bitwiseXOR(b))) - 1).cast("long").alias("h"))


@add("rel_functions_string", "SELECT n_nationkey, lower(n_name) AS low, CAST(length(n_name) AS BIGINT) AS len, substr(n_name, 1, 3) AS head, regexp_extract(n_name, '([A-Z]+)', 1) AS letters FROM nation")
def functions_string(spark, sf):
    n = F.col("n_name")
    return t(spark, sf, "nation").select("n_nationkey", F.lower(n).alias("low"), F.length(n).cast("long").alias("len"), F.substring(n, 1, 3).alias("head"), F.regexp_extract(n, "([A-Z]+)", 1).alias("letters"))


@add("rel_functions_array", "SELECT user_id, list_sort(list(DISTINCT event_type)) AS kinds, CAST(len(list(DISTINCT event_type)) AS BIGINT) AS n FROM events GROUP BY user_id")
def functions_array(spark, sf):
    return t(spark, sf, "events").groupBy("user_id").agg(F.array_sort(F.collect_set("event_type")).alias("kinds")).withColumn("n", F.size("kinds").cast("long"))


@add("rel_explode_days", f"SELECT CAST(d AS BIGINT) AS day, count(*) AS n FROM (SELECT unnest(range(t_lo, t_hi)) AS d FROM ({R['presc']}) WHERE dur <= 5) GROUP BY 1")
def explode_days(spark, sf):
    return src.presc(spark, sf).filter("dur <= 5").select(F.explode(F.sequence("t_lo", F.col("t_hi") - 1)).alias("day")).groupBy("day").agg(F.count("*").alias("n"))


@add("rel_explode_days_whole", f"SELECT CAST(d AS BIGINT) AS day, count(*) AS n FROM (SELECT unnest(range(t_lo, t_hi)) AS d FROM ({R['presc']})) GROUP BY 1")
def explode_days_whole(spark, sf):
    return src.presc(spark, sf).select(F.explode(F.sequence("t_lo", F.col("t_hi") - 1)).alias("day")).groupBy("day").agg(F.count("*").alias("n"))


@add("rel_nulls_and_cases", "SELECT l_returnflag, count(*) AS n FROM (SELECT CASE WHEN l_quantity > 40 THEN NULL WHEN l_quantity IN (1, 2, 3) THEN 'few' ELSE l_returnflag END AS l_returnflag FROM lineitem) WHERE coalesce(l_returnflag, 'none') <> 'R' GROUP BY 1")
def nulls_and_cases(spark, sf):
    q = F.col("l_quantity")
    c = F.when(q > 40, F.lit(None)).when(q.isin(1, 2, 3), F.lit("few")).otherwise(F.col("l_returnflag"))
    return t(spark, sf, "lineitem").select(c.alias("l_returnflag")).filter(F.coalesce("l_returnflag", F.lit("none")) != "R").groupBy("l_returnflag").agg(F.count("*").alias("n"))


@add("rel_json", "SELECT count(*) AS n, count(json_extract_string(props, '$.k')) AS with_k FROM events")
def json_fields(spark, sf):
    return t(spark, sf, "events").agg(F.count("*").alias("n"), F.count(F.get_json_object("props", "$.k")).alias("with_k"))


@add("rel_balance_udaf")
def balance_udaf(spark, sf):
    return src.trips(spark, sf).groupBy("event_type", "dur").count().groupBy("event_type").agg(surface.balance_score(F.col("count")).alias("balance"))
