"""Relational operators around the methods: sinks, conditions, windows, functions and stream joins, with SQL counterparts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

import uuid

from .functions import udfs
from .operators import eliminate, pipeline, potentials
from .sources import datasource, store
from .sources.tables import table
from .streaming import potentials as streams
from .workloads import JOINS, OUT, _folder, _nest, _q, w01, w10

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _query(sql: str) -> Callable:
    """Register a query under the name of its function."""

    def keep(run: Callable) -> Callable:
        QUERIES[run.__name__], ORACLES[run.__name__] = run, sql
        return run

    return keep


_COUNTS = "SELECT l_suppkey AS supp, l_returnflag AS flag, count(*) AS n FROM lineitem GROUP BY 1, 2"


def _counts(s: SparkSession, d: str) -> DataFrame:
    items = table(s, d, "lineitem", ["l_suppkey", "l_returnflag"]).toDF("supp", "flag")
    return potentials.build(items, ["supp", "flag"])


def _round_trip(s: SparkSession, d: str, kind: str) -> DataFrame:
    path, phi = _folder(s, kind), _counts(s, d)
    phi.write.format(kind).save(path)
    return s.read.schema(phi.schema).format(kind).load(path)


@_query(_COUNTS)
def e03_json_round_trip(s, d):
    return _round_trip(s, d, "json")


@_query(_COUNTS)
def e03_orc_round_trip(s, d):
    return _round_trip(s, d, "orc")


@_query(_COUNTS)
def e02_csv_round_trip(s, d):
    path, phi = _folder(s, "csv"), _counts(s, d)
    store.write_csv(phi, path)
    return store.csv(s, path, "supp long, flag string, n long")


@_query("SELECT o_orderkey, o_orderstatus FROM orders WHERE o_orderstatus = 'F'")
def e06_partitioned_sink(s, d):
    """Only the folder of one status is read back."""
    path = _folder(s, "orders")
    table(s, d, "orders", ["o_orderkey", "o_orderstatus"]).write.partitionBy("o_orderstatus").parquet(path)
    return s.read.parquet(path).filter("o_orderstatus = 'F'")


@_query("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS revenue FROM lineitem")
def e08_computed_columns(s, d):
    items = table(s, d, "lineitem", ["l_orderkey", "l_linenumber", "l_extendedprice", "l_discount"])
    return items.withColumn("revenue", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4)).drop("l_extendedprice", "l_discount")


@_query("SELECT p_partkey FROM part WHERE (p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#23')) OR (p_type LIKE '%A%' AND NOT regexp_matches(p_name, '[0-4]$') AND p_retailprice IS NOT NULL)")
def e09_conditions(s, d):
    c = F.col
    small = c("p_size").between(5, 20) & c("p_brand").isin("Brand#11", "Brand#12", "Brand#23")
    other = c("p_type").like("%A%") & ~c("p_name").rlike("[0-4]$") & c("p_retailprice").isNotNull()
    return table(s, d, "part").filter(small | other).select("p_partkey")


@_query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT user_id FROM events)")
def e14_semi_join(s, d):
    users = table(s, d, "events", ["user_id"])
    return table(s, d, "customer", ["c_custkey"]).join(users, F.col("c_custkey") == F.col("user_id"), "left_semi")


@_query("SELECT o_orderkey, event_id FROM orders JOIN events ON user_id = o_custkey AND ts >= o_orderdate + INTERVAL 23 YEAR AND ts < o_orderdate + INTERVAL 23 YEAR + INTERVAL 5 DAY")
def e16_interval_join(s, d):
    """The equated user drives the join, the time window is a condition on its matches."""
    moved = F.col("o_orderdate") + F.expr("INTERVAL 23 YEARS")  # the tables' years do not meet
    on = (F.col("user_id") == F.col("o_custkey")) & (F.col("ts") >= moved) & (F.col("ts") < moved + F.expr("INTERVAL 5 DAYS"))
    return table(s, d, "orders").join(table(s, d, "events"), on).select("o_orderkey", "event_id")


@_query("SELECT s_suppkey, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY floor(s_acctbal / 1000))")
def e26_ranks(s, d):
    w = Window.partitionBy("s_nationkey").orderBy(F.floor(F.col("s_acctbal") / 1000))
    ranks = [F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr")]
    shares = [F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd")]
    return table(s, d, "supplier").select("s_suppkey", *ranks, *shares)


@_query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS near, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS within, first_value(event_type) OVER w AS first_type, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def e28_frames(s, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    one = F.count(F.lit(1))
    return table(s, d, "events").select(
        "event_id", one.over(w.rowsBetween(-2, 0)).alias("near"), one.over(w.rangeBetween(-100, 0)).alias("within"),
        F.first("event_type").over(whole).alias("first_type"), F.nth_value("event_id", 2).over(whole).alias("second"),
    )


@_query(f"{_COUNTS} ORDER BY n DESC, supp, flag LIMIT 20")
def e30_sorted_top(s, d):
    """A sort that a limit follows keeps twenty rows a task."""
    return _counts(s, d).orderBy(F.desc("n"), "supp", "flag").limit(20)


@_query("SELECT n_nationkey AS k FROM nation UNION SELECT r_regionkey FROM region")
def e33_union(s, d):
    return table(s, d, "nation").select(F.col("n_nationkey").alias("k")).unionByName(table(s, d, "region").select(F.col("r_regionkey").alias("k"))).distinct()


@_query("SELECT p_partkey, lower(substr(p_brand, 1, 3)) AS stem, concat_ws('-', p_type, p_brand) AS label, string_split(p_name, ' ')[1] AS head, length(p_name) AS size FROM part")
def e35_strings(s, d):
    return table(s, d, "part").select(
        "p_partkey", F.lower(F.substring("p_brand", 1, 3)).alias("stem"), F.concat_ws("-", "p_type", "p_brand").alias("label"),
        F.split("p_name", " ")[0].alias("head"), F.length("p_name").cast("long").alias("size"),
    )


@_query("SELECT o_orderkey, round(ln(o_totalprice + 1), 6) AS logged, round(pow(o_totalprice, 0.5), 6) AS root, CAST(floor(o_totalprice) AS BIGINT) AS whole FROM orders")
def e37_numbers(s, d):
    price = F.col("o_totalprice")
    return table(s, d, "orders").select("o_orderkey", F.round(F.log(price + 1), 6).alias("logged"), F.round(F.pow(price, F.lit(0.5)), 6).alias("root"), F.floor(price).alias("whole"))


@_query("SELECT l_suppkey AS supp, l_returnflag AS flag, count(*) * 2 AS twice FROM lineitem GROUP BY 1, 2")
def e38_nested(s, d):
    """A conditional nested by its key, changed inside the array, and laid flat again."""
    nested = _counts(s, d).groupBy("supp").agg(F.collect_list(F.struct("flag", "n")).alias("items"))
    doubled = nested.select("supp", F.transform("items", lambda x: F.struct(x["flag"].alias("flag"), (x["n"] * 2).alias("twice"))).alias("items"))
    return doubled.select("supp", F.inline("items"))


@_query("SELECT event_id, CASE WHEN value > 50 THEN 'high' WHEN value > 10 THEN 'middle' ELSE 'low' END AS band, coalesce(nullif(event_type, 'view'), 'seen') AS kind, nullif(event_type, 'view') IS NOT DISTINCT FROM NULL AS viewed FROM events")
def e40_conditions_and_nulls(s, d):
    kind = F.nullif(F.col("event_type"), F.lit("view"))
    band = F.when(F.col("value") > 50, "high").when(F.col("value") > 10, "middle").otherwise("low")
    return table(s, d, "events").select("event_id", band.alias("band"), F.coalesce(kind, F.lit("seen")).alias("kind"), kind.eqNullSafe(F.lit(None)).alias("viewed"))


@_query("SELECT a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def e45_stream_interval_join(s, d):
    """Purchases within an hour of a view of the same user; the watermarks bound what either side remembers."""

    def side(kind: str, name: str) -> DataFrame:
        rows = streams.events(s, d).filter(F.col("event_type") == kind).withWatermark("ts", "1 hour")
        return rows.select(F.col("user_id").alias(f"{name}_user"), F.col("ts").alias(f"{name}_ts"), F.col("event_id").alias(f"{name}_id"))

    soon = (F.col("view_user") == F.col("purchase_user")) & F.expr("purchase_ts >= view_ts AND purchase_ts <= view_ts + INTERVAL 1 HOUR")
    return streams.drained(side("view", "view").join(side("purchase", "purchase"), soon).select("view_id", "purchase_id"), "append")


@_query("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey WHERE event_type = 'purchase'")
def e45_stream_static_join(s, d):
    bought = streams.events(s, d).filter("event_type = 'purchase'")
    return streams.drained(bought.join(table(s, d, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"), "append")


@_query(f"SELECT segment, CAST(sum(length(priority)) AS BIGINT) AS letters FROM ({JOINS['w10']}) j GROUP BY 1")
def e50_run_sum(s, d):
    """A SQL function over the runs of a summary column."""
    udfs.register(s)
    runs = pipeline.summarise(w10(s, d)).runs("priority")
    pairs = F.collect_list(F.struct(F.length("priority").cast("long").alias("value"), "freq"))
    runs.groupBy("segment").agg(pairs.alias("runs")).createOrReplaceTempView("runs_of_priority")
    return s.sql("SELECT segment, run_sum(runs) AS letters FROM runs_of_priority")


@_query("SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1")
def e06_bucketed_sink(s, d):
    """A table bucketed by its group key is counted without a shuffle."""
    name = f"bucketed_orders_{uuid.uuid4().hex}"
    orders = table(s, d, "orders", ["o_custkey", "o_orderkey"])
    orders.write.bucketBy(8, "o_custkey").sortBy("o_custkey").option("path", _folder(s, "bucketed")).saveAsTable(name)
    return s.table(name).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))


@_query(f"SELECT {_q(OUT['w01'])} FROM {_nest('w01')} j WHERE nation BETWEEN 3 AND 5")
def e05_summary_source_filtered_w01(s, d):
    """Ranges of rows without such nations are not expanded, where the session pushes filters to Python sources."""
    path = _folder(s, "summary")
    pipeline.summarise_to(w01(s, d), path)
    datasource.register(s)
    before = s.conf.get("spark.sql.python.filterPushdown.enabled", "false")
    s.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    try:
        return s.read.format("runsummary").option("rows", 4096).option("push", "true").load(path).filter("nation >= 3 and nation <= 5").checkpoint()
    finally:
        s.conf.set("spark.sql.python.filterPushdown.enabled", before)


@_query("SELECT c_custkey, event_id FROM events RIGHT JOIN customer ON user_id = c_custkey")
def e13_right_join(s, d):
    return table(s, d, "events", ["user_id", "event_id"]).join(table(s, d, "customer", ["c_custkey"]), F.col("user_id") == F.col("c_custkey"), "right").select("c_custkey", "event_id")


@_query("SELECT s_suppkey, c_custkey FROM supplier FULL JOIN customer ON s_nationkey = c_nationkey AND s_acctbal > 9000 AND c_acctbal > 9000")
def e13_full_join(s, d):
    on = (F.col("s_nationkey") == F.col("c_nationkey")) & (F.col("s_acctbal") > 9000) & (F.col("c_acctbal") > 9000)
    return table(s, d, "supplier").join(table(s, d, "customer"), on, "full").select("s_suppkey", "c_custkey")


@_query("SELECT l_suppkey, true AS near FROM lineitem GROUP BY 1")
def e22_approx_distinct(s, d):
    """The sketch's count lies within a fifth of the exact one (its standard error is a twentieth)."""
    counts = table(s, d, "lineitem", ["l_suppkey", "l_partkey"]).groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey").alias("a"), F.countDistinct("l_partkey").alias("n"))
    return counts.select("l_suppkey", (F.abs(F.col("a") - F.col("n")) <= 0.2 * F.col("n")).alias("near"))


@_query(f"SELECT segment, priority, flag, count(*) AS n FROM {_nest('w10')} j GROUP BY GROUPING SETS ((segment, priority), (flag), ())")
def e23_grouping_sets_w10(s, d):
    """Over the runs of the summary, by their lengths."""
    runs = pipeline.summarise(w10(s, d)).deepest
    sets = [["segment", "priority"], ["flag"], []]
    columns = [F.col(c) for c in ("segment", "priority", "flag")]
    return runs.groupingSets([[F.col(c) for c in x] for x in sets], *columns).agg(F.sum("freq").cast("long").alias("n"))


@_query("SELECT event_id, CAST(props ->> '$.k' AS BIGINT) AS k, '{\"twice\":' || 2 * CAST(props ->> '$.k' AS BIGINT) || '}' AS again FROM events")
def e39_json_structs(s, d):
    parsed = F.from_json("props", "k long")["k"]
    return table(s, d, "events").select("event_id", parsed.alias("k"), F.to_json(F.struct((parsed * 2).alias("twice"))).alias("again"))


@_query("SELECT time_bucket(INTERVAL 15 MINUTE, ts) - k * INTERVAL 15 MINUTE AS begins, event_type, count(*) AS n FROM events, range(4) r(k) GROUP BY 1, 2")
def e42_stream_sliding(s, d):
    """Hours that begin every quarter."""
    counts = streams.drained(streams.windowed(streams.events(s, d), ["event_type"], "1 hour", "15 minutes"))
    return counts.select(F.col("window.start").cast("timestamp_ntz").alias("begins"), "event_type", "n")


@_query("WITH o AS (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events), g AS (SELECT *, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 2 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM o) SELECT user_id, min(ts) AS begins, count(*) AS n FROM g GROUP BY user_id, session")
def e42_stream_sessions(s, d):
    """Sessions end after two hours without an event; a watermark of ten years keeps all rows."""
    counts = streams.drained(streams.sessions(streams.events(s, d), ["user_id"], "2 hours", "3650 days"))
    return counts.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("begins"), "n")


@_query("WITH h AS (SELECT date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY 1) SELECT day, n FROM h WHERE day <> (SELECT min(day) FROM h)")
def e42_stream_late_rows(s, d):
    """Three batches: all but the first day, one row far ahead (left out below), and at last the first day's rows: behind the watermark, dropped."""
    events = table(s, d, "events", ["ts", "event_id"]).withColumn("ts", F.col("ts").cast("timestamp"))
    first = events.agg(F.date_trunc("day", F.min("ts")).alias("low")).first()["low"]
    ahead = events.agg((F.max("ts") + F.expr("INTERVAL 40 DAYS")).alias("ts")).withColumn("event_id", F.lit(-1).cast("long"))
    path = _folder(s, "late")
    late = F.date_trunc("day", "ts") == F.lit(first)
    for number, part in enumerate((events.filter(~late), ahead, events.filter(late))):
        part.coalesce(1).write.parquet(f"{path}/in/part={number}")
    stream = s.readStream.schema("ts timestamp, event_id long, part int").option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(f"{path}/in").filter("event_id >= 0 or part = 1")
    counts = streams.drained(streams.windowed(stream, [], "1 day", late="1 hour"), "append")
    return counts.select(F.col("window.start").cast("timestamp_ntz").alias("day"), "n")


@_query("SELECT CAST(2 * count(*) AS BIGINT) AS join_size FROM events JOIN orders ON user_id = o_custkey")
def e43_stream_rebuilt_size(s, d):
    """The size of a join whose one potential has grown by a stream: messages are made anew from the merged potential."""
    ev = table(s, d, "events", ["user_id"]).toDF("cust")
    od = table(s, d, "orders", ["o_custkey", "o_orderpriority"]).toDF("cust", "priority")
    query = pipeline.JoinQuery({"e": ev, "o": od}, ["cust", "priority"])
    base = potentials.of_query(query)
    grown = streams.merged(streams.events(s, d).select(F.col("user_id").alias("cust")), base["e"], ["cust"], _folder(s, "stream"))
    phis = base | {"e": s.read.parquet(grown)}
    return eliminate.join_size(query, phis).select(F.col("join_size").cast("long"))


@_query("SELECT count(*) AS join_size FROM orders JOIN customer ON o_custkey = c_custkey JOIN supplier ON c_nationkey = s_nationkey WHERE c_mktsegment = 'BUILDING'")
def e50_join_size_sql(s, d):
    for t in ("orders", "customer", "supplier"):
        table(s, d, t).createOrReplaceTempView(t)
    sql = "SELECT o.o_orderpriority, s.s_suppkey FROM orders o, customer c, supplier s WHERE o.o_custkey = c.c_custkey AND c.c_nationkey = s.s_nationkey AND c.c_mktsegment = 'BUILDING'"
    return udfs.join_size_sql(s, sql).select(F.col("join_size").cast("long"))
