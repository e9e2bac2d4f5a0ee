"""One query for each operator of the surface: sources, predicates, joins, aggregates, windows, functions, streams, user code."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from pipeflow import functions as fn
from pipeflow import streaming
from pipeflow.grid.regrid import row_major
from pipeflow.operators import aggregates as agg
from pipeflow.operators import joins, relational
from pipeflow.operators import windows as win
from pipeflow.plans import pipeline
from pipeflow.registry import add, query
from pipeflow.session import materialise, partitions
from pipeflow.sources import cells, round_trip, save_clustered, table, through


def dec(c: str):
    """Money as an exact decimal, so that sums don't depend on their order."""
    return F.col(c).cast("decimal(18,2)")


def t(name: str):
    return lambda spark, sf_dir: table(spark, sf_dir, name)


# Sources and sinks

add("scan_parquet", t("region"), "SELECT * FROM region")
add("scan_csv_roundtrip", lambda s, d: through(table(s, d, "nation"), "csv", header="true"), "SELECT * FROM nation")
add("scan_json_roundtrip", lambda s, d: through(table(s, d, "region"), "json"), "SELECT * FROM region")
add("scan_orc_roundtrip", lambda s, d: through(table(s, d, "supplier"), "orc"), "SELECT * FROM supplier")
add("scan_text_roundtrip", lambda s, d: through(table(s, d, "documents").select(F.md5(F.col("text").cast("binary")).alias("value")), "text"), "SELECT md5(text) AS value FROM documents")
add("scan_range", lambda s, d: cells(s, 1000), "SELECT CAST(range AS BIGINT) AS cell FROM range(1000)")
add("sink_partitioned", lambda s, d: through(table(s, d, "lineitem").select("l_orderkey", "l_quantity", "l_returnflag"), "parquet", ["l_returnflag"]).where("l_returnflag = 'R'"), "SELECT l_orderkey, l_quantity, l_returnflag FROM lineitem WHERE l_returnflag = 'R'")


@query("scan_clustered", "SELECT o_orderkey, o_custkey FROM orders")
def scan_clustered(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.table(save_clustered(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_orderkey", 4))


@query("sink_grid_roundtrip", "SELECT o_orderkey AS tgt, o_totalprice AS v FROM orders")
def sink_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("tgt"), F.col("o_totalprice").alias("v"))
    return round_trip(row_major(a, a.count()))


add("materialise_events", lambda s, d: materialise(table(s, d, "events").select("event_id", "user_id", "value")), "SELECT event_id, user_id, value FROM events")

# Projection and predicates

add("project_arith", lambda s, d: relational.project(table(s, d, "lineitem"), "l_orderkey", "l_linenumber", net=F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4), twice=F.col("l_quantity") * 2), "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net, l_quantity * 2 AS twice FROM lineitem")
add("filter_range", lambda s, d: relational.keep(table(s, d, "lineitem"), (F.col("l_quantity").between(10, 20)) & ~(F.col("l_discount") > 0.05) | (F.col("l_tax") == 0)).select("l_orderkey", "l_quantity", "l_discount", "l_tax"), "SELECT l_orderkey, l_quantity, l_discount, l_tax FROM lineitem WHERE (l_quantity BETWEEN 10 AND 20 AND NOT l_discount > 0.05::DOUBLE) OR l_tax = 0")
add("filter_in_like", lambda s, d: relational.keep(table(s, d, "part"), F.col("p_size").isin(1, 5, 9) & (F.col("p_type").like("%E%") | F.col("p_brand").rlike("#[12]$"))), "SELECT * FROM part WHERE p_size IN (1, 5, 9) AND (p_type LIKE '%E%' OR regexp_matches(p_brand, '#[12]$'))")


@query("filter_null", "SELECT c_custkey, coalesce(b, -1.0::DOUBLE) AS v, b IS NULL AS gone, b IS NOT DISTINCT FROM NULL AS same FROM (SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN NULL ELSE c_acctbal END AS b FROM customer)")
def filter_null(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = F.when(F.col("c_acctbal") >= 0, F.col("c_acctbal"))
    return table(spark, sf_dir, "customer").select("c_custkey", F.coalesce(b, F.lit(-1.0)).alias("v"), b.isNull().alias("gone"), b.eqNullSafe(F.lit(None).cast("double")).alias("same"))


add("case_when", lambda s, d: table(s, d, "orders").select("o_orderkey", relational.case(F.col("o_orderstatus"), {"F": "full", "O": "open"}, "other").alias("state")), "SELECT o_orderkey, CASE o_orderstatus WHEN 'F' THEN 'full' WHEN 'O' THEN 'open' ELSE 'other' END AS state FROM orders")
add("explode_embeddings", lambda s, d: relational.fan(table(s, d, "embeddings").select("vec_id", "embedding"), "embedding").select("vec_id", F.col("k").cast("long").alias("k"), F.col("item").cast("double").alias("item")), "SELECT vec_id, CAST(i - 1 AS BIGINT) AS k, CAST(embedding[i] AS DOUBLE) AS item FROM embeddings, range(1, 65) r(i)")
add("sample_events", lambda s, d: relational.sample(table(s, d, "events"), 0.1, 7))

# Joins

_OL = "FROM orders JOIN lineitem ON l_orderkey = o_orderkey"


def orders_lines(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    o, li = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey"), table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_partkey", "l_linenumber")
    return {"merge": joins.merge, "hash": joins.hashed}[how](o, li, "k")


for _h, _n in (("merge", "join_sort_merge"), ("hash", "join_shuffle_hash")):
    add(_n, partial(orders_lines, how=_h), f"SELECT o_orderkey AS k, o_custkey, l_partkey, l_linenumber {_OL}")
add("join_broadcast", lambda s, d: joins.broadcast(table(s, d, "supplier").withColumnRenamed("s_nationkey", "k"), table(s, d, "nation").withColumnRenamed("n_nationkey", "k"), "k").select("s_suppkey", "k", "n_name"), "SELECT s_suppkey, s_nationkey AS k, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey")
add("join_theta", lambda s, d: joins.theta(table(s, d, "nation"), table(s, d, "region"), F.col("n_regionkey") < F.col("r_regionkey")).select("n_name", "r_name"), "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey < r_regionkey")
add("join_cross", lambda s, d: joins.cross(table(s, d, "region"), table(s, d, "nation")).select("r_name", "n_name"), "SELECT r_name, n_name FROM region CROSS JOIN nation")


def halves(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    """Customers, their keys moved by seven, against orders: the least keys of orders and the greatest of customers have no partner."""
    c = table(spark, sf_dir, "customer").select((F.col("c_custkey") + 7).alias("k"), "c_nationkey")
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k"), "o_orderkey")
    return joins.merge(c, o, "k", how)


_HALVES = "(SELECT c_custkey + 7 AS k, c_nationkey FROM customer) c {} JOIN (SELECT o_custkey AS k, o_orderkey FROM orders) o USING (k)"
for _h in ("left", "right", "full"):
    add(f"join_{_h}", partial(halves, how=_h), "SELECT k, c_nationkey, o_orderkey FROM " + _HALVES.format(_h.upper()))
for _h in ("semi", "anti"):
    add(f"join_{_h}", partial(halves, how=f"left_{_h}"), "SELECT k, c_nationkey FROM " + _HALVES.format(_h.upper()))


@query("join_range", "SELECT o_orderkey, b AS band FROM orders JOIN (SELECT CAST(range AS BIGINT) AS b, range * 12500.0::DOUBLE AS low, (range + 1) * 12500.0::DOUBLE AS high FROM range(50)) ON o_totalprice >= low AND o_totalprice < high")
def join_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    bands = spark.range(50).select(F.col("id").alias("band"), (F.col("id") * 12500.0).alias("low"), ((F.col("id") + 1) * 12500.0).alias("high"))
    return joins.in_band(table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice"), "o_totalprice", bands, "low", "high", 10000.0).select("o_orderkey", "band")


@query("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND epoch(date_trunc('second', b.ts)) >= epoch(date_trunc('second', a.ts)) AND epoch(date_trunc('second', b.ts)) < epoch(date_trunc('second', a.ts)) + 86400")
def join_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_timestamp("ts").alias("s"))
    a = e.where("event_type = 'view'").select(F.col("event_id").alias("a"), "user_id", F.col("s").alias("a_s"))
    b = e.where("event_type = 'click'").select(F.col("event_id").alias("b"), "user_id", F.col("s").alias("b_s"))
    return joins.within(a, b, "user_id", "a_s", "b_s", 86400).select("a", "b")


@query("join_asof", "SELECT e.event_id, c.event_id AS last_click FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON e.user_id = c.user_id AND e.ts >= c.ts")
def join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    out = joins.asof(e.where("event_type = 'error'"), e.where("event_type = 'click'"), "user_id", "ts", "event_id", "last_click", F.to_date("ts"))
    return out.select("event_id", "last_click")


@query("join_zip", "SELECT event_id AS pos, user_id, value FROM events")
def join_zip(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pipeflow.streams.ordered import zip_streams

    e = table(spark, sf_dir, "events").withColumnRenamed("event_id", "pos")
    return zip_streams(e.select("pos", "user_id"), e.select("pos", "value"))


@query("merge_union", "SELECT l_orderkey, l_partkey FROM lineitem")
def merge_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    return joins.merge_union([li.where("l_orderkey % 2 = 0"), li.where("l_orderkey % 2 != 0")], ["l_orderkey", "l_partkey"], partitions(spark))


@query("join_star", "SELECT n_name, p_brand, count(*) AS n, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS money FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN part ON p_partkey = l_partkey JOIN region ON r_regionkey = n_regionkey WHERE r_name = 'ASIA' GROUP BY ALL")
def join_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, n, r, p = (table(spark, sf_dir, x) for x in ("supplier", "nation", "region", "part"))
    dims = [(s.select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("nk")), "l_suppkey"), (n.select(F.col("n_nationkey").alias("nk"), "n_name", F.col("n_regionkey").alias("rk")), "nk"), (r.where("r_name = 'ASIA'").select(F.col("r_regionkey").alias("rk")), "rk"), (p.select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey")]
    out = joins.star(table(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey", dec("l_extendedprice").alias("m")), dims)
    return agg.by(out, ["n_name", "p_brand"], n=F.count("*"), money=F.sum("m").cast("double"))


# Aggregates

add("agg_hash", lambda s, d: agg.by(table(s, d, "lineitem"), ["l_returnflag", "l_linestatus"], n=F.count("*"), qty=F.sum(dec("l_quantity")).cast("double"), price=F.sum(dec("l_extendedprice")).cast("double"), low=F.min("l_shipdate"), high=F.max("l_shipdate")), "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS price, min(l_shipdate) AS low, max(l_shipdate) AS high FROM lineitem GROUP BY ALL")


@query("agg_segmented_scan", "SELECT l_orderkey, count(*) AS n, max(l_partkey) AS high FROM lineitem GROUP BY 1")
def agg_segmented(spark: SparkSession, sf_dir: str) -> DataFrame:
    name = save_clustered(table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey"), "l_orderkey", 4)
    return agg.segmented(spark.table(name), "l_orderkey", n=F.count("*"), high=F.max("l_partkey"))


add("agg_sorted_list", lambda s, d: agg.ordered_list(table(s, d, "conversations"), "conv_id", "turn", "role", "r").select("conv_id", F.array_join("r", ",").alias("roles")), "SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles FROM conversations GROUP BY 1")
add("agg_count_distinct", lambda s, d: agg.by(table(s, d, "events"), ["event_type"], users=F.count_distinct("user_id"), days=F.count_distinct(F.to_date("ts"))), "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT CAST(ts AS DATE)) AS days FROM events GROUP BY 1")
add("agg_approx", lambda s, d: agg.by(table(s, d, "events"), ["event_type"], users=F.approx_count_distinct("user_id"), middle=F.percentile_approx("value", 0.5)))


def grouped(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    df, n = table(spark, sf_dir, "lineitem"), F.count("*")
    keys = ["l_returnflag", "l_linestatus"]
    if how == "sets":
        return agg.sets(df, [keys, ["l_linestatus"]], keys, n=n)
    return {"rollup": agg.rollup, "cube": agg.cube}[how](df, keys, n=n)


for _h, _g in (("rollup", "ROLLUP (l_returnflag, l_linestatus)"), ("cube", "CUBE (l_returnflag, l_linestatus)"), ("sets", "GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus))")):
    add(f"agg_{'grouping_sets' if _h == 'sets' else _h}", partial(grouped, how=_h), f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {_g}")
add("agg_pivot", lambda s, d: agg.pivot(table(s, d, "events"), ["user_id"], "event_type", ["click", "view"], F.count(F.lit(1))).fillna(0), "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY 1")
add("agg_filtered", lambda s, d: agg.by(table(s, d, "orders"), ["o_orderpriority"], big=F.count_if(F.col("o_totalprice") > 100000), n=F.count("*")), "SELECT o_orderpriority, count(*) FILTER (WHERE o_totalprice > 100000) AS big, count(*) AS n FROM orders GROUP BY 1")
add("agg_having", lambda s, d: agg.by(table(s, d, "orders"), ["o_custkey"], n=F.count("*")).where("n > 12"), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")
add("agg_arg_max", lambda s, d: agg.by(table(s, d, "events"), ["user_id"], last=F.max_by("event_type", "event_id")), "SELECT user_id, arg_max(event_type, event_id) AS last FROM events GROUP BY 1")
add("agg_moments", lambda s, d: agg.by(table(s, d, "lineitem"), ["l_returnflag"], sd=F.round(F.stddev_samp("l_quantity"), 4), r=F.round(F.corr("l_quantity", "l_extendedprice"), 4), m=F.round(F.avg("l_discount"), 6)), "SELECT l_returnflag, round(stddev_samp(l_quantity), 4) AS sd, round(corr(l_quantity, l_extendedprice), 4) AS r, round(avg(l_discount), 6) AS m FROM lineitem GROUP BY 1")

# Windows, order, sets

add("win_rank", lambda s, d: win.over(table(s, d, "orders").select("o_custkey", "o_orderkey"), ["o_custkey"], ["o_orderkey"], rn=F.row_number(), rk=F.rank(), dr=F.dense_rank(), nt=F.ntile(3), pr=F.percent_rank(), cd=F.cume_dist()), "SELECT o_custkey, o_orderkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(3) OVER w AS INTEGER) AS nt, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
add("win_offset", lambda s, d: win.over(table(s, d, "events").select("user_id", "event_id", "value"), ["user_id"], ["event_id"], before=F.lag("value"), after=F.lead("value", 2), first=F.first("value"), second=F.nth_value("value", 2)), "SELECT user_id, event_id, value, lag(value) OVER w AS before, lead(value, 2) OVER w AS after, first_value(value) OVER w AS first, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
add("win_rows_frame", lambda s, d: win.rows(table(s, d, "events").select("user_id", "event_id", dec("value").alias("v")), ["user_id"], ["event_id"], -2, 1, m=F.sum("v")).select("event_id", F.col("m").cast("double").alias("m")), "SELECT event_id, CAST(sum(CAST(value AS DECIMAL(18,2))) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS DOUBLE) AS m FROM events")
add("win_range_frame", lambda s, d: win.ranged(table(s, d, "events").select("user_id", "event_id"), ["user_id"], "event_id", -500, 500, n=F.count("*")), "SELECT user_id, event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS n FROM events")
add("win_prefix_sum", lambda s, d: win.prefix_sum(table(s, d, "orders").select("o_custkey", "o_orderkey", dec("o_totalprice").alias("v")), ["o_custkey"], ["o_orderkey"], "v", "s").select("o_orderkey", F.col("s").cast("double").alias("s")), "SELECT o_orderkey, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS DOUBLE) AS s FROM orders")
add("win_sessions", lambda s, d: win.sessions(table(s, d, "events").select("user_id", "event_id", F.unix_timestamp("ts").alias("s")), "user_id", "s", 36000).select("event_id", F.col("session").cast("long").alias("session")), "SELECT event_id, CAST(sum(n) OVER (PARTITION BY user_id ORDER BY s ROWS UNBOUNDED PRECEDING) AS BIGINT) AS session FROM (SELECT *, CASE WHEN s - lag(s) OVER (PARTITION BY user_id ORDER BY s) > 36000 THEN 1 ELSE 0 END AS n FROM (SELECT user_id, event_id, CAST(floor(epoch(ts)) AS BIGINT) AS s FROM events))")


@query("sort_total_rank", "SELECT CAST(row_number() OVER (ORDER BY b DESC NULLS LAST, c_custkey) - 1 AS BIGINT) AS pos, c_custkey FROM (SELECT c_custkey, CASE WHEN c_acctbal >= 0 THEN c_acctbal END AS b FROM customer)")
def sort_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pipeflow.streams.ordered import with_positions

    # positions follow ascending keys: nulls last and descending as a pair of keys
    b = F.when(F.col("c_acctbal") >= 0, F.col("c_acctbal"))
    c = table(spark, sf_dir, "customer").select("c_custkey", b.isNull().alias("last"), (-b).alias("down"))
    return with_positions(c, "last", "down", "c_custkey").select("pos", "c_custkey")


add("limit_offset", lambda s, d: win.total(table(s, d, "orders"), F.col("o_orderkey")).offset(100).limit(50).select("o_orderkey", "o_custkey"), "SELECT o_orderkey, o_custkey FROM orders ORDER BY o_orderkey LIMIT 50 OFFSET 100")
add("topk_global", lambda s, d: win.total(table(s, d, "orders"), F.col("o_totalprice").desc(), F.col("o_orderkey")).limit(25).select("o_orderkey", "o_totalprice"), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
add("topk_group", lambda s, d: win.topk_by(table(s, d, "events").select("user_id", "event_id", "value"), ["user_id"], [F.col("value").desc(), "event_id"], 3), "SELECT user_id, event_id, value FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) <= 3")
add("sort_local", lambda s, d: win.local(table(s, d, "orders").select("o_orderkey", "o_custkey"), "o_custkey"), "SELECT o_orderkey, o_custkey FROM orders")


def nations(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return table(spark, sf_dir, "customer").where("c_nationkey < 20").select(F.col("c_nationkey").alias("n")), table(spark, sf_dir, "supplier").where("s_nationkey > 4").select(F.col("s_nationkey").alias("n"))


_A, _B = "SELECT c_nationkey AS n FROM customer WHERE c_nationkey < 20", "SELECT s_nationkey AS n FROM supplier WHERE s_nationkey > 4"
for _q, _f, _s in (("union_all", relational.union, "UNION ALL"), ("union", relational.union_distinct, "UNION"), ("intersect", relational.intersect, "INTERSECT"), ("intersect_all", partial(relational.intersect, every=True), "INTERSECT ALL"), ("except", relational.subtract, "EXCEPT"), ("except_all", partial(relational.subtract, every=True), "EXCEPT ALL")):
    add(f"set_{_q}", lambda s, d, f=_f: f(*nations(s, d)), f"{_A} {_s} {_B}")
add("set_distinct", lambda s, d: table(s, d, "lineitem").select("l_returnflag", "l_linestatus").distinct(), "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")

# Scalar functions


def columns(df: DataFrame, keep: str, cols: dict) -> DataFrame:
    return df.select(keep, *(c.alias(n) for n, c in cols.items()))


add("fn_string", lambda s, d: columns(table(s, d, "part"), "p_partkey", fn.string_columns(F.col("p_name"))), "SELECT p_partkey, upper(p_name) AS up, lower(trim(p_name)) AS low, substring(p_name, 1, 4) AS head, replace(p_name, 'a', 'o') AS swapped, regexp_extract(p_name, '^([A-Za-z]+)', 1) AS first_word, regexp_replace(p_name, '[0-9]+', '#', 'g') AS no_digits, CAST(len(string_split(p_name, ' ')) AS BIGINT) AS parts, concat_ws('-', p_name, 'x') AS joined, length(p_name) AS n, CAST(instr(p_name, 'e') AS BIGINT) AS at, lpad(CAST(length(p_name) AS VARCHAR), 5, '0') AS padded, translate(p_name, 'abc', 'xyz') AS moved, reverse(p_name) AS back FROM part")
add("fn_date", lambda s, d: columns(table(s, d, "orders"), "o_orderkey", fn.date_columns(F.col("o_orderdate"))), "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month_start, datediff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)) AS days, strftime(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH, '%Y-%m-%d') AS later, strftime(last_day(o_orderdate), '%Y-%m-%d') AS last, strftime(o_orderdate, '%Y/%m/%d') AS day, strftime(CAST(o_orderdate AS DATE) + 1, '%Y-%m-%d') AS next FROM orders")
add("fn_math", lambda s, d: columns(table(s, d, "lineitem"), "l_orderkey", fn.math_columns(F.col("l_quantity"), F.col("l_partkey"))), "SELECT l_orderkey, CAST(floor(l_quantity) AS BIGINT) AS down, CAST(ceil(l_quantity) AS BIGINT) AS up, round(sqrt(l_quantity), 6) AS rooted, round(ln(l_quantity + 1), 6) AS logged, round(pow(l_quantity, 2), 4) AS squared, abs(l_quantity - 25) AS size, CAST(sign(l_quantity - 25) AS DOUBLE) AS side, l_partkey % 7 AS rest, greatest(l_quantity, 10.0::DOUBLE) AS most, least(l_quantity, 10.0::DOUBLE) AS least, l_partkey & 15 AS bits FROM lineitem")
add("fn_trig", lambda s, d: columns(table(s, d, "orders").withColumnRenamed("o_orderkey", "a"), "a", fn.trig_columns((F.col("a") % 360).cast("double") + 0.25)), "SELECT a, round(sin(r), 6) AS s, round(cos(r), 6) AS c, round(tan(r / 4), 6) AS t, round(asin(sin(r) / 2), 6) AS as_, round(acos(cos(r) / 2), 6) AS ac, round(atan2(sin(r), cos(r) + 2), 6) AS at, round(degrees(r / 3), 6) AS deg FROM (SELECT o_orderkey AS a, radians(o_orderkey % 360 + 0.25::DOUBLE) AS r FROM orders)")
add("fn_array", lambda s, d: columns(table(s, d, "embeddings"), "vec_id", fn.array_columns(F.col("embedding"))), "SELECT vec_id, CAST(len(e) AS BIGINT) AS n, e[1] AS first, CAST(len(list_filter(e, lambda x: x > 0)) AS BIGINT) AS positive, round(list_reduce(list_prepend(0.0::DOUBLE, e), lambda a, x: a + x), 6) AS total, len(list_filter(e, lambda x: x > 0.5::DOUBLE)) > 0 AS any_large, list_min(e) AS low, CAST(len(e[60:64]) AS BIGINT) AS tail, round(list_reduce(list_prepend(0.0::DOUBLE, list_transform(range(1, 65), lambda i: e[i] * e[65 - i])), lambda a, x: a + x), 6) AS dot FROM (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings)")


@query("fn_map", "SELECT n_nationkey, n_name AS name, CAST(n_regionkey AS VARCHAR) AS region, 'name,region' AS keys, CAST(CASE WHEN n_regionkey > 1 THEN 2 ELSE 1 END AS BIGINT) AS kept FROM nation")
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = F.map_from_arrays(F.array(F.lit("name"), F.lit("region")), F.array("n_name", F.col("n_regionkey").cast("string")))
    df = table(spark, sf_dir, "nation").select("n_nationkey", m.alias("m"), F.struct(F.col("n_regionkey").alias("r")).alias("s"), "n_regionkey")
    kept = F.size(F.map_filter("m", lambda k, v: (k == "name") | (F.col("s.r") > 1))).cast("long")
    return df.select("n_nationkey", F.element_at("m", "name").alias("name"), F.col("m")["region"].alias("region"), F.array_join(F.array_sort(F.map_keys("m")), ",").alias("keys"), kept.alias("kept"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, '{\"k\":' || json_extract_string(props, '$.k') || '}' AS again FROM events")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").withColumn("p", F.from_json("props", "k long"))
    return e.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.to_json("p").alias("again"))


add("fn_url", lambda s, d: table(s, d, "pages").select("page_id", F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("n")), "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n FROM pages")
add("fn_hash", lambda s, d: table(s, d, "customer").select("c_custkey", F.md5(F.col("c_name").cast("binary")).alias("m"), F.sha2(F.col("c_name").cast("binary"), 256).alias("s")), "SELECT c_custkey, md5(c_name) AS m, sha256(c_name) AS s FROM customer")
add("fn_hash_spark", lambda s, d: table(s, d, "customer").select("c_custkey", F.xxhash64("c_name").alias("x"), F.crc32(F.col("c_name").cast("binary")).alias("c")))
add("fn_cast", lambda s, d: table(s, d, "orders").select("o_orderkey", F.col("o_totalprice").cast("decimal(18,2)").cast("string").alias("money"), F.expr("try_cast(o_orderstatus as int)").alias("none"), F.col("o_orderkey").cast("string").alias("text"), F.expr("try_cast(cast(o_custkey as string) as bigint)").alias("key")), "SELECT o_orderkey, CAST(CAST(o_totalprice AS DECIMAL(18,2)) AS VARCHAR) AS money, TRY_CAST(o_orderstatus AS INTEGER) AS none, CAST(o_orderkey AS VARCHAR) AS text, o_custkey AS key FROM orders")

# Streams. Event times are whole; windows close as the watermark passes, so the last ones stay open in append mode and complete mode gives all.

_DAY = "CAST(floor(epoch(ts) / {0}) * {0} AS BIGINT)"


def stream_windows(spark: SparkSession, sf_dir: str, size: str, slide: str | None) -> DataFrame:
    out = streaming.windowed(streaming.events(spark, sf_dir), size, slide, ["event_type"]).select(F.unix_timestamp("window.start").alias("start"), "event_type", "n")
    return streaming.collect(out, "complete")


add("stream_tumbling", partial(stream_windows, size="1 day", slide=None), f"SELECT {_DAY.format(86400)} AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
add("stream_sliding", partial(stream_windows, size="2 days", slide="1 day"), "SELECT start, event_type, count(*) AS n FROM (SELECT CAST(floor(epoch(ts) / 86400) * 86400 - k * 86400 AS BIGINT) AS start, event_type FROM events, (VALUES (0), (1)) v(k)) GROUP BY ALL")


@query("stream_session", "SELECT user_id, min(s) AS start, count(*) AS n FROM (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT user_id, ts, event_id, CAST(floor(epoch(ts)) AS BIGINT) AS s, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 6 HOUR THEN 1 ELSE 0 END AS b FROM events)) GROUP BY user_id, k")
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = streaming.sessions(streaming.events(spark, sf_dir), "6 hours", "user_id").select("user_id", F.unix_timestamp("session_window.start").alias("start"), "n")
    return streaming.collect(out, "complete")


add("stream_dedup", lambda s, d: streaming.collect(streaming.distinct(streaming.events(s, d), ["user_id", "event_type"], "365 days").select("user_id", "event_type")), "SELECT DISTINCT user_id, event_type FROM events")


@query("stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return streaming.collect(streaming.events(spark, sf_dir).join(c, "user_id").select("event_id", "c_mktsegment"))


@query("stream_interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def stream_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = streaming.events(spark, sf_dir)
    a = e.where("event_type = 'view'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("time").alias("ta")).withWatermark("ta", "1 hour")
    b = streaming.events(spark, sf_dir).where("event_type = 'click'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("time").alias("tb")).withWatermark("tb", "1 hour")
    return streaming.collect(a.join(b, F.expr("ua = ub and tb >= ta and tb <= ta + interval 1 day")).select("a", "b"))


@query("stream_pipeline", "SELECT event_type, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) AS total FROM events WHERE value > 10 GROUP BY 1")
def stream_pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A pipeline of components over each micro-batch; the batches' sums are added up at the end."""

    def one(batch: DataFrame, i: int) -> DataFrame:
        chain = pipeline.Source(batch, "read") | pipeline.Map(lambda d: d.where("value > 10"), "dear") | pipeline.Map(lambda d: d.groupBy("event_type").agg(F.count("*").alias("n"), F.sum(dec("value")).alias("total")), "sum")
        return next(iter(pipeline.Pipeline(chain).run(batch.sparkSession)[0].values()))

    parts = streaming.per_batch(streaming.events(spark, sf_dir), one, "event_type string, n long, total decimal(28,2), batch int")
    return parts.groupBy("event_type").agg(F.sum("n").alias("n"), F.sum("total").cast("double").alias("total"))


@query("stream_state_runs", "SELECT event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY 1")
def stream_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """State of one key, updated over micro-batches; the last update of each key counts."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        stream = streaming.events(spark, sf_dir).select("event_type", "value")
        out = streaming.stateful_sums(stream)
        rows = streaming.updates(out)
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)
    return rows.groupBy("event_type").agg(F.max_by("n", "n").alias("n"), F.round(F.max_by("total", "n"), 2).alias("total"))


# User code

add("component_columns", lambda s, d: next(iter(pipeline.Pipeline(pipeline.Source(table(s, d, "events"), "read") | pipeline.Map(lambda x: x.select("event_id", (F.col("user_id") * 2 + 1).alias("odd")), "f")).run(s)[0].values())), "SELECT event_id, user_id * 2 + 1 AS odd FROM events")


@F.pandas_udf(DoubleType())
def plus_one(v: pd.Series) -> pd.Series:
    return v + 1


@F.pandas_udf(DoubleType())
def plus_opened(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
    shift = 2.0  # made once when the component opens
    for v in batches:
        yield v + shift


add("udf_scalar", lambda s, d: table(s, d, "events").select("event_id", plus_one("value").alias("v")), "SELECT event_id, value + 1 AS v FROM events")
add("udf_iter", lambda s, d: table(s, d, "events").select("event_id", plus_opened("value").alias("v")), "SELECT event_id, value + 2 AS v FROM events")


@query("component_arrow", "SELECT 'item' AS kind, count(*) AS n, CAST(sum(user_id) AS BIGINT) AS total FROM events")
def component_arrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A component that keeps a sum and gives it as it closes."""

    def run(batches):
        n = total = 0
        for b in batches:
            n, total = n + b.num_rows, total + (pc.sum(b.column(0)).as_py() or 0)
        yield pa.RecordBatch.from_pydict({"kind": ["item"], "n": [n], "total": [total]})

    parts = table(spark, sf_dir, "events").select("user_id").mapInArrow(run, "kind string, n long, total long")
    return parts.groupBy("kind").agg(F.sum("n").alias("n"), F.sum("total").alias("total"))


def spread(pdf: pd.DataFrame) -> pd.DataFrame:
    return pd.DataFrame({"user_id": [pdf["user_id"].iloc[0]], "spread": [float(pdf["value"].max() - pdf["value"].min())]})


add("udf_grouped", lambda s, d: table(s, d, "events").select("user_id", "value").groupBy("user_id").applyInPandas(spread, "user_id long, spread double").withColumn("spread", F.round("spread", 4)), "SELECT user_id, round(max(value) - min(value), 4) AS spread FROM events GROUP BY 1")


def sizes(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
    k = a["k"].iloc[0] if len(a) else b["k"].iloc[0]
    return pd.DataFrame({"k": [k], "left": [len(a)], "right": [len(b)]})


@query("udf_cogrouped", "SELECT k, coalesce(l, 0) AS left, coalesce(r, 0) AS right FROM (SELECT c_nationkey AS k, count(*) AS l FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey AS k, count(*) AS r FROM supplier GROUP BY 1) USING (k)")
def udf_cogrouped(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    return a.groupBy("k").cogroup(b.groupBy("k")).applyInPandas(sizes, "k int, left long, right long")


@F.pandas_udf(DoubleType())
def geo_mean(v: pd.Series) -> float:
    import numpy as np

    return float(np.exp(np.log(v).mean()))


add("udaf_geo_mean", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(geo_mean("l_quantity"), 4).alias("g")), "SELECT l_returnflag, round(exp(avg(ln(l_quantity))), 4) AS g FROM lineitem GROUP BY 1")


class Pieces:
    def eval(self, text: str):
        for i, x in enumerate((text or "").split(" ")):
            yield i, x


@query("udtf_split", "SELECT p_partkey, CAST(i - 1 AS INTEGER) AS i, string_split(p_name, ' ')[i] AS word FROM part, range(1, 20) r(i) WHERE i <= len(string_split(p_name, ' '))")
def udtf_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = F.udtf(Pieces, returnType="i int, word string")
    name = streaming.unique_name("pieces")
    spark.udtf.register(name, f)
    table(spark, sf_dir, "part").createOrReplaceTempView(f"{name}_part")
    return spark.sql(f"SELECT p_partkey, i, word FROM {name}_part, LATERAL {name}(p_name)")


@query("sql_recursive_phases", "WITH RECURSIVE t(node, depth) AS (SELECT 0::BIGINT, 0 UNION ALL SELECT 2 * node + c, depth + 1 FROM t, (VALUES (1), (2)) v(c) WHERE 2 * node + c < 500) SELECT node, depth FROM t")
def sql_recursive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.sql("WITH RECURSIVE t(node, depth) AS (SELECT 0L, 0 UNION ALL SELECT 2 * node + c, depth + 1 FROM t CROSS JOIN (VALUES (1L), (2L)) v(c) WHERE 2 * node + c < 500) SELECT node, depth FROM t")
