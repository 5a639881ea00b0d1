"""The series of the workloads, built from the given tables, and the same in SQL for the oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from halo.operators import grid
from halo.sources.ingest import SeriesSpec, micros, read

HOUR, DAY = 3_600_000_000, 86_400_000_000
JAN_2024 = 1_704_067_200_000_000
JAN_1995 = 788_918_400_000_000
TYPES = ("click", "error", "purchase", "signup", "view")
GROUPS = ("AF", "AO", "NF", "NO", "RF", "RO")
N_E, D_E, N_L, D_L, N_O = 720, 5, 2499, 6, 2405


def position(col, names):
    return F.array_position(F.array(*[F.lit(n) for n in names]), col).cast("int") - 1


def events_long(spark: SparkSession, d: str) -> DataFrame:
    ev = read(spark, d, "events", ["ts", "event_type"])
    return grid.regular(ev, SeriesSpec("ts", HOUR, JAN_2024), position(F.col("event_type"), TYPES))


def events(spark, d):
    return grid.dense(events_long(spark, d), N_E, D_E)


def lineitem(spark, d):
    li = read(spark, d, "lineitem", ["l_shipdate", "l_returnflag", "l_linestatus"])
    long = grid.regular(li, SeriesSpec("l_shipdate", DAY, JAN_1995 + DAY), position(F.concat("l_returnflag", "l_linestatus"), GROUPS))
    return grid.dense(long, N_L, D_L)


def orders(spark, d, fill=None):
    long = grid.regular(read(spark, d, "orders", ["o_orderdate"]), SeriesSpec("o_orderdate", DAY, JAN_1995))
    return grid.dense(long, N_O, 1, fill).select("idx", "v")


def raw_events(spark, d):
    return read(spark, d, "events", ["ts", "value"]).select(micros(F.col("ts")).alias("ts_us"), F.round(F.col("value") * 100).cast("bigint").alias("v"))


def nation_days_long(spark, d):
    """Orders per nation and day, where there are any."""
    o = read(spark, d, "orders", ["o_orderdate", "o_custkey"])
    c = read(spark, d, "customer", ["c_custkey", "c_nationkey"])
    joined = o.join(c, o.o_custkey == c.c_custkey)
    long = grid.regular(joined, SeriesSpec("o_orderdate", DAY, JAN_1995), F.col("c_nationkey"))
    return long.where(F.col("idx").between(0, N_O - 1) & F.col("dim").between(0, 24)).select(F.col("dim").alias("v"), "idx", F.col("v").alias("x"))


def nation_days(spark, d):
    long = nation_days_long(spark, d).select("idx", F.col("v").alias("dim"), F.col("x").alias("v"))
    return grid.dense(long, N_O, 25).select(F.col("dim").alias("v"), "idx", F.col("v").alias("x"))


def nation_edges(spark, d):
    n = read(spark, d, "nation", ["n_nationkey"]).select(F.col("n_nationkey").cast("int").alias("v"))
    return n.select(F.col("v").alias("src"), F.pmod(F.col("v") + 1, F.lit(25)).alias("dst")).unionByName(n.select(F.col("v").alias("src"), F.pmod(F.col("v") + 5, F.lit(25)).alias("dst")))


def supplier_days(spark, d):
    li = read(spark, d, "lineitem", ["l_shipdate", "l_suppkey"])
    return grid.regular(li, SeriesSpec("l_shipdate", DAY, JAN_1995 + DAY), F.col("l_suppkey"))


def quantities(spark, d):
    """Quantities of line items less their mean, in units of their deviation, numbered by order and line: t, e."""
    li = read(spark, d, "lineitem", ["l_orderkey", "l_linenumber", "l_quantity"])
    m, s = li.agg(F.avg("l_quantity"), F.stddev_samp("l_quantity")).head()
    numbered = grid.ordinal_index(li, ["l_orderkey", "l_linenumber", "l_quantity"])
    return numbered.select(F.col("idx").alias("t"), ((F.col("l_quantity") - F.lit(m)) / F.lit(s)).alias("e"))


def users(spark, d):
    """Events per hour and user group."""
    ev = read(spark, d, "events", ["ts", "user_id"])
    return grid.dense(grid.regular(ev, SeriesSpec("ts", HOUR, JAN_2024), (F.col("user_id") % 16).cast("int")), N_E, 16)


def cents(spark, d):
    """Value in cents per hour and type."""
    ev = read(spark, d, "events", ["ts", "event_type", "value"])
    spec = SeriesSpec("ts", HOUR, JAN_2024, how="sum")
    return grid.dense(grid.regular(ev, spec, position(F.col("event_type"), TYPES), F.round(F.col("value") * 100).cast("bigint")), N_E, D_E)


def vectors(spark, d):
    return read(spark, d, "embeddings", ["vec_id", "embedding"]).select(F.col("vec_id").alias("idx"), F.transform("embedding", lambda x: x.cast("double")).alias("x"))


SQL_E = f"""
 se0 AS (SELECT CAST((epoch_us(ts) - {JAN_2024}) // {HOUR} AS BIGINT) AS idx, CAST(CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS INTEGER) AS dim, count(*) AS v FROM events GROUP BY 1, 2),
 se AS (SELECT CAST(a.i AS BIGINT) AS idx, CAST(b.j AS INTEGER) AS dim, CAST(coalesce(se0.v, 0) AS BIGINT) AS v FROM range({N_E}) a(i) CROSS JOIN range({D_E}) b(j) LEFT JOIN se0 ON se0.idx = a.i AND se0.dim = b.j)"""
SQL_U = f"""
 su0 AS (SELECT CAST((epoch_us(ts) - {JAN_2024}) // {HOUR} AS BIGINT) AS idx, CAST(user_id % 16 AS INTEGER) AS dim, count(*) AS v FROM events GROUP BY 1, 2),
 su AS (SELECT CAST(a.i AS BIGINT) AS idx, CAST(b.j AS INTEGER) AS dim, CAST(coalesce(su0.v, 0) AS BIGINT) AS v FROM range({N_E}) a(i) CROSS JOIN range(16) b(j) LEFT JOIN su0 ON su0.idx = a.i AND su0.dim = b.j)"""
SQL_EV = f"""
 sv0 AS (SELECT CAST((epoch_us(ts) - {JAN_2024}) // {HOUR} AS BIGINT) AS idx, CAST(CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS INTEGER) AS dim, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS v FROM events GROUP BY 1, 2),
 sv AS (SELECT CAST(a.i AS BIGINT) AS idx, CAST(b.j AS INTEGER) AS dim, CAST(coalesce(sv0.v, 0) AS BIGINT) AS v FROM range({N_E}) a(i) CROSS JOIN range({D_E}) b(j) LEFT JOIN sv0 ON sv0.idx = a.i AND sv0.dim = b.j)"""
SQL_L = f"""
 sl0 AS (SELECT CAST((epoch_us(l_shipdate) - {JAN_1995 + DAY}) // {DAY} AS BIGINT) AS idx, CAST(CASE l_returnflag || l_linestatus WHEN 'AF' THEN 0 WHEN 'AO' THEN 1 WHEN 'NF' THEN 2 WHEN 'NO' THEN 3 WHEN 'RF' THEN 4 ELSE 5 END AS INTEGER) AS dim, count(*) AS v FROM lineitem GROUP BY 1, 2),
 sl AS (SELECT CAST(a.i AS BIGINT) AS idx, CAST(b.j AS INTEGER) AS dim, CAST(coalesce(sl0.v, 0) AS BIGINT) AS v FROM range({N_L}) a(i) CROSS JOIN range({D_L}) b(j) LEFT JOIN sl0 ON sl0.idx = a.i AND sl0.dim = b.j)"""
SQL_O = f"""
 so0 AS (SELECT CAST((epoch_us(o_orderdate) - {JAN_1995}) // {DAY} AS BIGINT) AS idx, count(*) AS v FROM orders GROUP BY 1),
 so AS (SELECT CAST(a.i AS BIGINT) AS idx, CAST(so0.v AS BIGINT) AS v FROM range({N_O}) a(i) LEFT JOIN so0 ON so0.idx = a.i),
 sz AS (SELECT idx, coalesce(v, 0) AS v FROM so)"""
SQL_R = "sr AS (SELECT epoch_us(ts) AS ts_us, CAST(round(value * 100) AS BIGINT) AS v FROM events)"
SQL_N = f"""
 sn0 AS (SELECT CAST((epoch_us(o_orderdate) - {JAN_1995}) // {DAY} AS BIGINT) AS idx, c_nationkey AS v, count(*) AS x FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2),
 sn AS (SELECT CAST(b.j AS INTEGER) AS v, CAST(a.i AS BIGINT) AS idx, CAST(coalesce(x, 0) AS BIGINT) AS x FROM range({N_O}) a(i) CROSS JOIN range(25) b(j) LEFT JOIN sn0 ON sn0.idx = a.i AND sn0.v = b.j),
 ed AS (SELECT CAST(n_nationkey AS INTEGER) AS src, CAST((n_nationkey + 1) % 25 AS INTEGER) AS dst FROM nation UNION ALL SELECT CAST(n_nationkey AS INTEGER), CAST((n_nationkey + 5) % 25 AS INTEGER) FROM nation)"""
