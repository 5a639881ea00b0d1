"""The registered queries of the engine and their SQL: the Spark side runs on blocks, the SQL side without them."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from halo import baselines, measures, series
from halo.functions import linalg, vec
from halo.models import banded, fit, likelihood, moments, predict
from halo.models.process import Process
from halo.operators import blocks as lay
from halo.operators import difference, graph, grid, irregular, kernels, space
from halo.plans.scratch import folder, stash
from halo.sources.ingest import micros, read
from halo.streaming import stream

ALL: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def mark(f):
        ALL[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return mark


def blocks_e(spark, d, size=48, left=3, right=3) -> DataFrame:
    return lay.time_blocks(grid.to_wide(series.events(spark, d), series.D_E), size, left, right, bounds=(0, series.N_E - 1))


def blocks_o(spark, d, size=128, left=3, right=3) -> DataFrame:
    return lay.time_blocks(series.orders(spark, d, 0), size, left, right, bounds=(0, series.N_O - 1))


def moments_e(spark, d, H=3):
    return moments.Moments.collect(moments.lag_products(blocks_e(spark, d, 48, H, H), H, H))


def moments_o(spark, d, H=3):
    wide = series.orders(spark, d, 0).select("idx", F.array(F.col("v").cast("double")).alias("x"))
    return moments.Moments.collect(moments.lag_products(lay.time_blocks(wide, 128, 0, H), H, H))


def lag_frame(spark, g) -> DataFrame:
    return spark.createDataFrame(moments.rows_of(g), "lag int, i int, j int, value double")


def scratch(spark) -> str:
    return folder(spark)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    g = moments_e(spark, d, 2).autocov()
    return fit.yule_walker(g, 1).to_df(spark)


# ---- layouts and grids

@query("grid_events_hourly", f"WITH {series.SQL_E} SELECT idx, dim, v FROM se0")
def _(spark, d):
    return series.events_long(spark, d)


@query("grid_zero_fill", f"WITH {series.SQL_E} SELECT idx, dim, v FROM se")
def _(spark, d):
    return series.events(spark, d)


@query("gaps_orders_days", f"WITH {series.SQL_O} SELECT idx FROM so WHERE v IS NULL")
def _(spark, d):
    return grid.gaps(series.orders(spark, d).where("v is not null"), series.N_O)


@query("locf_orders", f"WITH {series.SQL_O} SELECT idx, last_value(v IGNORE NULLS) OVER (ORDER BY idx ROWS UNBOUNDED PRECEDING) AS v, v IS NULL AS is_filled FROM so")
def _(spark, d):
    return grid.locf(series.orders(spark, d), 128)


@query("linear_orders", f"""WITH {series.SQL_O},
 k AS (SELECT idx, v, max(CASE WHEN v IS NOT NULL THEN idx END) OVER (ORDER BY idx ROWS UNBOUNDED PRECEDING) AS a, min(CASE WHEN v IS NOT NULL THEN idx END) OVER (ORDER BY idx ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS b FROM so)
 SELECT k.idx, round(CASE WHEN k.v IS NOT NULL THEN CAST(k.v AS DOUBLE) ELSE x.v + (y.v - x.v) * (k.idx - k.a) / CAST(k.b - k.a AS DOUBLE) END, 6) AS v, k.v IS NULL AS is_filled
 FROM k LEFT JOIN so x ON x.idx = k.a LEFT JOIN so y ON y.idx = k.b""")
def _(spark, d):
    return grid.linear(series.orders(spark, d), 128).withColumn("v", F.round("v", 6))


def hours_e(spark, d, size=48, left=3, right=3) -> DataFrame:
    """Blocks of the hours that have events, as they stand in the table."""
    hours = series.events_long(spark, d).where(F.col("idx").between(0, series.N_E - 1))
    return lay.time_blocks(grid.to_wide(hours, series.D_E), size, left, right, bounds=(0, series.N_E - 1))


# The hours with events that each block of 48 stores.
HOURS = f"WITH {series.SQL_E}, hs AS (SELECT DISTINCT idx AS i FROM se0 WHERE idx BETWEEN 0 AND 719), m AS (SELECT CAST(b AS BIGINT) AS block, i AS idx, i // 48 = b AS is_core FROM range(15) x(b), hs WHERE i >= 48 * b - {{left}} AND i < 48 * b + 48 + {{right}})"


@query("time_blocks_membership", HOURS.format(left=3, right=3) + " SELECT block, idx, is_core FROM m")
def _(spark, d):
    return hours_e(spark, d).select("block", "idx", "is_core")


@query("blocks_replication", HOURS.format(left=3, right=3) + " SELECT count(DISTINCT block) AS blocks, count(*) AS stored, count(*) FILTER (is_core) AS core, count(*) / CAST(count(*) FILTER (is_core) AS DOUBLE) AS replication FROM m")
def _(spark, d):
    return lay.replication(hours_e(spark, d))


@query("one_sided_replication", HOURS.format(left=2, right=0) + " SELECT count(*) AS stored, count(*) FILTER (is_core) AS core FROM m")
def _(spark, d):
    return lay.replication(hours_e(spark, d, 48, 2, 0)).select("stored", "core")


@query("time_unit_blocks", f"WITH {series.SQL_R} SELECT CAST(b AS BIGINT) AS block, count(*) AS stored, count(*) FILTER (ts_us // {series.DAY} = b) AS core FROM sr, (SELECT DISTINCT ts_us // {series.DAY} AS b FROM sr) WHERE ts_us >= b * {series.DAY} - {series.HOUR} AND ts_us < (b + 1) * {series.DAY} + {series.HOUR} GROUP BY b")
def _(spark, d):
    return lay.report(lay.time_blocks(series.raw_events(spark, d), series.DAY, series.HOUR, series.HOUR, on="ts_us")).where("core > 0")


@query("ordinal_index_events", "SELECT event_id, CAST(row_number() OVER (ORDER BY ts, event_id) - 1 AS BIGINT) AS idx FROM events")
def _(spark, d):
    return grid.ordinal_index(read(spark, d, "events", ["event_id", "ts"]), ["ts", "event_id"]).select("event_id", "idx")


# ---- statistics

COV = """ st AS (SELECT dim, CAST(sum(v) AS BIGINT) AS s FROM {t} GROUP BY dim),
 pr AS (SELECT h.l AS lag, a.dim AS i, b.dim AS j, CAST(count(*) AS BIGINT) AS n, CAST(sum(a.v * b.v) AS BIGINT) AS p, CAST(sum(a.v) AS BIGINT) AS u, CAST(sum(b.v) AS BIGINT) AS w FROM range({H} + 1) h(l) JOIN {t} a ON true JOIN {t} b ON b.idx = a.idx + h.l GROUP BY 1, 2, 3),
 cv AS (SELECT CAST(lag AS INTEGER) AS lag, i, j, n, CAST(CAST({N} AS HUGEINT) * {N} * p - CAST({N} AS HUGEINT) * (u * y.s + x.s * w) + CAST(n AS HUGEINT) * x.s * y.s AS DOUBLE) / (CAST({N} AS DOUBLE) * {N}) AS c FROM pr JOIN st x ON x.dim = i JOIN st y ON y.dim = j)"""
COV_E = f"WITH {series.SQL_E}, " + COV.format(t="se", H=3, N=720)
COV_L = f"WITH {series.SQL_L}, " + COV.format(t="sl", H=2, N=series.N_L)
COV_O = f"WITH {series.SQL_O}, s1 AS (SELECT idx, CAST(0 AS INTEGER) AS dim, v FROM sz), " + COV.format(t="s1", H=3, N=series.N_O) + ", g AS (SELECT max(CASE WHEN lag = 0 THEN c / (n - 1) END) AS g0, max(CASE WHEN lag = 1 THEN c / (n - 1) END) AS g1, max(CASE WHEN lag = 2 THEN c / (n - 1) END) AS g2, max(CASE WHEN lag = 3 THEN c / (n - 1) END) AS g3 FROM cv)"


@query("mean_events", f"WITH {series.SQL_E} SELECT dim, CAST(sum(v) AS DOUBLE) / count(*) AS mean FROM se GROUP BY dim")
def _(spark, d):
    return moments.mean(series.events(spark, d))


@query("autocov_events_exact", COV_E + " SELECT lag, i, j, c / (n - 1) AS value FROM cv")
def _(spark, d):
    return lag_frame(spark, moments_e(spark, d).autocov())


@query("autocov_lineitem", COV_L + " SELECT lag, i, j, c / n AS value FROM cv")
def _(spark, d):
    b = lay.time_blocks(grid.to_wide(series.lineitem(spark, d), 6), 256, 0, 2)
    return lag_frame(spark, moments.Moments.collect(moments.lag_products(b, 2, 2, fanout=4)).autocov("pairs"))


@query("autocov_sql_backend", f"WITH {series.SQL_E} SELECT CAST(h.l AS INTEGER) AS lag, a.dim AS i, b.dim AS j, CAST(count(*) AS DOUBLE) AS n, CAST(sum(a.v * b.v) AS DOUBLE) AS s FROM range(4) h(l) JOIN se a ON true JOIN se b ON b.idx = a.idx + h.l GROUP BY 1, 2, 3")
def _(spark, d):
    return moments.lag_products(blocks_e(spark, d), 3, 3, backend="sql").select("lag", "i", "j", "n", "s")


@query("autocov_events_window", f"""WITH {series.SQL_E}, m AS (SELECT dim, avg(v) AS m FROM se GROUP BY dim), z AS (SELECT idx, se.dim, v - m AS z FROM se JOIN m USING (dim))
 SELECT CAST(h.l - 2 AS INTEGER) AS lag, a.dim AS i, b.dim AS j, round(sum(a.z * b.z) / (720 - 5), 8) AS value FROM range(5) h(l) JOIN z a ON a.idx BETWEEN 2 AND 717 JOIN z b ON b.idx = a.idx + h.l - 2 GROUP BY 1, 2, 3""")
def _(spark, d):
    m = moments_e(spark, d, 0)
    g = moments.window_form(blocks_e(spark, d, 48, 2, 2), 2, 720, m.mean, 2)
    rows = [(h - 2, i, j, round(float(g[h, i, j]), 8)) for h in range(5) for i in range(5) for j in range(5)]
    return spark.createDataFrame(rows, "lag int, i int, j int, value double")


@query("acf_events", COV_E + ", z AS (SELECT i, c / (n - 1) AS g FROM cv WHERE lag = 0 AND i = j) SELECT lag, cv.i, cv.j, round(c / (n - 1) / sqrt(a.g * b.g), 8) AS value FROM cv JOIN z a ON a.i = cv.i JOIN z b ON b.i = cv.j")
def _(spark, d):
    return lag_frame(spark, moments.acf(moments_e(spark, d).autocov())).withColumn("value", F.round("value", 8))


@query("ccf_events", COV_E + ", z AS (SELECT i, c / (n - 1) AS g FROM cv WHERE lag = 0 AND i = j) SELECT lag, round(c / (n - 1) / sqrt(a.g * b.g), 8) AS value FROM cv JOIN z a ON a.i = cv.i JOIN z b ON b.i = cv.j WHERE cv.i = 0 AND cv.j = 4")
def _(spark, d):
    r = moments.ccf(moments.acf(moments_e(spark, d).autocov()), 0, 4)
    return spark.createDataFrame([(h, round(float(x), 8)) for h, x in enumerate(r)], "lag int, value double")


@query("lag_gram_events", f"WITH {series.SQL_E} SELECT CAST(p.a AS INTEGER) AS a, CAST(q.b AS INTEGER) AS b, x.dim AS i, y.dim AS j, CAST(sum(x.v * y.v) AS DOUBLE) AS s, CAST(count(*) AS DOUBLE) AS n FROM range(3) p(a), range(3) q(b), range(2, 720) t(t) JOIN se x ON x.idx = t.t - p.a JOIN se y ON y.idx = t.t - q.b GROUP BY 1, 2, 3, 4")
def _(spark, d):
    return moments.lag_gram(blocks_e(spark, d, 48, 2, 0), 2, 2)


@query("pacf2_orders", COV_O + " SELECT CAST(1 AS INTEGER) AS p, round(g1 / g0, 8) AS kappa FROM g UNION ALL SELECT 2, round((g2 * g0 - g1 * g1) / (g0 * g0 - g1 * g1), 8) FROM g")
def _(spark, d):
    k = moments.pacf(moments_o(spark, d).autocov(), 2)
    return spark.createDataFrame([(n + 1, round(float(m[0, 0]), 8)) for n, m in enumerate(k)], "p int, kappa double")


@query("ar1_yule_walker", COV_O + " SELECT round(g1 / g0, 8) AS a1, round(g0 - g1 * g1 / g0, 8) AS s FROM g")
def _(spark, d):
    m = fit.yule_walker(moments_o(spark, d).autocov(), 1, "levinson")
    return spark.createDataFrame([(round(float(m.a[0][0, 0]), 8), round(float(m.sigma[0, 0]), 8))], "a1 double, s double")


@query("ar2_yule_walker", COV_O + ", k AS (SELECT *, g1 * (g0 - g2) / (g0 * g0 - g1 * g1) AS a1, (g2 * g0 - g1 * g1) / (g0 * g0 - g1 * g1) AS a2 FROM g) SELECT round(a1, 8) AS a1, round(a2, 8) AS a2, round(g0 - a1 * g1 - a2 * g2, 8) AS s FROM k")
def _(spark, d):
    m = fit.yule_walker(moments_o(spark, d).autocov(), 2)
    return spark.createDataFrame([(round(float(m.a[0][0, 0]), 8), round(float(m.a[1][0, 0]), 8), round(float(m.sigma[0, 0]), 8))], "a1 double, a2 double, s double")


@query("ar_d2_yule_walker", COV_E + """, e AS (SELECT lag, i, j, c / (n - 1) AS g FROM cv WHERE i < 2 AND j < 2 AND lag < 2),
 z AS (SELECT max(CASE WHEN i = 0 AND j = 0 THEN g END) AS a, max(CASE WHEN i = 0 AND j = 1 THEN g END) AS b, max(CASE WHEN i = 1 AND j = 1 THEN g END) AS dd FROM e WHERE lag = 0),
 inv AS (SELECT 0 AS k, 0 AS c, dd / (a * dd - b * b) AS v FROM z UNION ALL SELECT 0, 1, -b / (a * dd - b * b) FROM z UNION ALL SELECT 1, 0, -b / (a * dd - b * b) FROM z UNION ALL SELECT 1, 1, a / (a * dd - b * b) FROM z)
 SELECT CAST(e.j AS INTEGER) AS i, CAST(inv.c AS INTEGER) AS j, round(sum(e.g * inv.v), 8) AS value FROM e JOIN inv ON inv.k = e.i WHERE e.lag = 1 GROUP BY 1, 2""")
def _(spark, d):
    a = fit.yule_walker(moments_e(spark, d, 1).autocov()[:, :2, :2], 1, "block_levinson").a[0]
    return spark.createDataFrame([(i, j, round(float(a[i, j]), 8)) for i in range(2) for j in range(2)], "i int, j int, value double")


@query("ma1_innovations_depth1", COV_O + " SELECT round(g1 / g0, 8) AS b1, round(g0 - g1 * g1 / g0, 8) AS s FROM g")
def _(spark, d):
    m = fit.ma(moments_o(spark, d).autocov(), 1)
    return spark.createDataFrame([(round(float(m.b[0][0, 0]), 8), round(float(m.sigma[0, 0]), 8))], "b1 double, s double")


@query("ma1_innovations_depth2", COV_O + ", k AS (SELECT *, g0 - g1 * g1 / g0 AS s1 FROM g), q AS (SELECT *, g2 / g0 AS t22, (g1 - (g2 / g0) * g0 * (g1 / g0)) / s1 AS t21 FROM k) SELECT round(t21, 8) AS b1, round(g0 - t22 * t22 * g0 - t21 * t21 * s1, 8) AS s FROM q")
def _(spark, d):
    m = fit.ma(moments_o(spark, d).autocov(), 1, 2)
    return spark.createDataFrame([(round(float(m.b[0][0, 0]), 8), round(float(m.sigma[0, 0]), 8))], "b1 double, s double")


@query("ma_order_cutoff", COV_O + f" SELECT CAST(lag AS INTEGER) AS lag, abs(c / (n - 1) / g0) > 1.959963984540054 / sqrt({series.N_O}) AS significant FROM cv, g WHERE lag > 0")
def _(spark, d):
    r = moments.acf(moments_o(spark, d).autocov())
    return spark.createDataFrame([(h, not fit.insignificant(r[h], series.N_O, 0.95)) for h in range(1, 4)], "lag int, significant boolean")


# ---- prediction and likelihood

@query("ar_predict_fixed", f"WITH {series.SQL_O} SELECT idx, 0.5 * v + 0.25 * lag(v) OVER (ORDER BY idx) AS yhat FROM sz QUALIFY lag(v) OVER (ORDER BY idx) IS NOT NULL")
def _(spark, d):
    return predict.fixed_ar(blocks_o(spark, d, 128, 2, 0), [0.5, 0.25])


@query("ar_predict_k3", f"WITH {series.SQL_O}, p AS (SELECT idx, CAST(v AS DOUBLE) AS x0, CAST(lag(v) OVER (ORDER BY idx) AS DOUBLE) AS x1 FROM sz), q AS (SELECT *, 0.5 * x0 + 0.25 * x1 AS f1 FROM p WHERE x1 IS NOT NULL), r AS (SELECT *, 0.5 * f1 + 0.25 * x0 AS f2 FROM q) SELECT idx, 0.5 * f2 + 0.25 * f1 AS yhat FROM r")
def _(spark, d):
    wide = series.orders(spark, d, 0).select("idx", F.array(F.col("v").cast("double")).alias("x"))
    m = Process(a=[np.array([[0.5]]), np.array([[0.25]])], sigma=np.eye(1))
    return predict.k_step(lay.time_blocks(wide, 128, 2, 0), m, np.zeros(1), 3, 2).select("idx", F.col("yhat")[0].alias("yhat"))


@query("arma_predict_fixed", f"""WITH RECURSIVE {series.SQL_O}, r AS (SELECT CAST(0 AS BIGINT) AS idx, CAST(v AS DOUBLE) AS e, CAST(0.0 AS DOUBLE) AS f FROM sz WHERE idx = 0
 UNION ALL SELECT s.idx, s.v - (0.5 * p.v + 0.25 * r.e), 0.5 * p.v + 0.25 * r.e FROM r JOIN sz s ON s.idx = r.idx + 1 JOIN sz p ON p.idx = r.idx) SELECT idx, round(f, 6) AS yhat FROM r""")
def _(spark, d):
    wide = series.orders(spark, d, 0).select("idx", F.array(F.col("v").cast("double")).alias("x"))
    m = Process(a=[np.array([[0.5]])], b=[np.array([[0.25]])], sigma=np.eye(1))
    w = m.warmup(1e-14)
    return predict.arma_blocks(lay.time_blocks(wide, 256, w + 1, 0), m, np.zeros(1), w, w + 1).select("idx", F.round(F.col("forecast")[0], 6).alias("yhat"))


@query("cond_loglik_terms", f"WITH {series.SQL_O} SELECT sum(0.5 * (a.v - b.v) * (a.v - b.v)) / count(*) AS value, count(*) AS n FROM sz a JOIN sz b ON b.idx = a.idx - 1")
def _(spark, d):
    wide = series.orders(spark, d, 0).select("idx", F.array(F.col("v").cast("double")).alias("x"))
    f, _, n = likelihood.pass_over(lay.time_blocks(wide, 128, 1, 0), [np.eye(1)], np.eye(1), 1, 1)[0]
    return spark.createDataFrame([(f, n)], "value double, n bigint")


@query("cond_gradient_fixed", f"WITH {series.SQL_E}, t AS (SELECT a.dim AS i, b.dim AS j, sum((a.v - c.v) * b.v) AS s, count(*) AS n FROM se a JOIN se c ON c.idx = a.idx - 1 AND c.dim = a.dim JOIN se b ON b.idx = a.idx - 1 GROUP BY 1, 2) SELECT i, j, -CAST(s AS DOUBLE) / n AS value FROM t")
def _(spark, d):
    _, g, _ = likelihood.pass_over(blocks_e(spark, d, 48, 1, 0), [np.eye(5)], np.eye(5), 1, 1)[0]
    return spark.createDataFrame([(i, j, float(g[i, j])) for i in range(5) for j in range(5)], "i int, j int, value double")


BAND_SQL = "WITH e AS (SELECT vec_id AS idx, generate_subscripts(embedding, 1) - 1 AS dim, unnest(embedding) AS v FROM embeddings) SELECT a.idx, CAST(a.dim AS INTEGER) AS dim, round(coalesce(0.25 * CAST(b.v AS DOUBLE), 0) + 0.5 * CAST(a.v AS DOUBLE) + coalesce(0.25 * CAST(c.v AS DOUBLE), 0), 8) AS yhat FROM e a LEFT JOIN e b ON b.idx = a.idx AND b.dim = a.dim - 1 LEFT JOIN e c ON c.idx = a.idx AND c.dim = a.dim + 1"


@query("banded_predict_embeddings", BAND_SQL)
def _(spark, d):
    a = banded.stencil_matrix(64, 0.25, 0.5, 0.25)
    return banded.predict(series.vectors(spark, d), a, 1, 8).withColumn("yhat", F.round("yhat", 8))


@query("banded_predict_stencil", BAND_SQL)
def _(spark, d):
    return banded.predict_stencil(series.vectors(spark, d), {-1: 0.25, 0: 0.5, 1: 0.25}).withColumn("yhat", F.round("yhat", 8))


@query("banded_fit_diagonal", f"WITH {series.SQL_L} SELECT a.dim AS i, a.dim AS j, round(CAST(sum(a.v * b.v) AS DOUBLE) / sum(a.v * a.v), 8) AS value FROM sl a JOIN sl b ON b.idx = a.idx + 1 AND b.dim = a.dim GROUP BY 1")
def _(spark, d):
    return banded.fit(grid.to_wide(series.lineitem(spark, d), 6), 6, 0, 3, centre=False).select("i", "j", F.round("value", 8).alias("value"))


# ---- differences

@query("diff1_orders", f"WITH {series.SQL_O} SELECT a.idx, b.v - a.v AS y FROM sz a JOIN sz b ON b.idx = a.idx + 1")
def _(spark, d):
    return difference.diff(blocks_o(spark, d), 1)


@query("diff2_orders", f"WITH {series.SQL_O} SELECT a.idx, c.v - 2 * b.v + a.v AS y FROM sz a JOIN sz b ON b.idx = a.idx + 1 JOIN sz c ON c.idx = a.idx + 2")
def _(spark, d):
    return difference.diff(blocks_o(spark, d), 2)


@query("integrate_orders", f"WITH {series.SQL_O} SELECT idx, v AS y FROM sz WHERE idx > 0")
def _(spark, d):
    b = blocks_o(spark, d)
    first = series.orders(spark, d, 0).where("idx = 0").head().v
    back = lay.time_blocks(difference.diff(b, 1).withColumnRenamed("y", "v"), 128, 0, 0)
    return difference.integrate(back, first)


FRAC = difference.frac_weights(0.5, 16)


@query("fracdiff_half16", f"WITH {series.SQL_O}, w AS (SELECT * FROM (VALUES {', '.join(f'({k}, CAST({x!r} AS DOUBLE))' for k, x in enumerate(FRAC))}) t(k, w)) SELECT a.idx, round(sum(w.w * b.v), 6) AS y FROM sz a JOIN w ON true JOIN sz b ON b.idx = a.idx - w.k WHERE a.idx >= 16 GROUP BY a.idx")
def _(spark, d):
    return difference.frac(blocks_o(spark, d, 128, 16, 0), 0.5, 16).withColumn("y", F.round("y", 6))


# ---- irregular, mesh, points

@query("irregular_window_1h", f"WITH {series.SQL_R} SELECT ts_us, count(*) OVER w AS n, CAST(sum(v) OVER w AS BIGINT) AS total, min(v) OVER w AS least, max(v) OVER w AS largest FROM sr WINDOW w AS (ORDER BY ts_us RANGE BETWEEN {series.HOUR} PRECEDING AND {series.HOUR} FOLLOWING)")
def _(spark, d):
    b = lay.time_blocks(series.raw_events(spark, d), series.DAY, series.HOUR, series.HOUR, on="ts_us")
    return irregular.window_stats(b, series.HOUR)


CENTRES = f"WITH {series.SQL_R}, c AS (SELECT CAST({series.JAN_2024} + i * 600000000 AS BIGINT) AS c FROM range(4175) t(i)) SELECT c, count(v) AS n, CAST(coalesce(sum(v), 0) AS BIGINT) AS total FROM c LEFT JOIN sr ON ts_us BETWEEN c - {series.HOUR} AND c + {series.HOUR} GROUP BY c"


def _centres(method):
    def run(spark, d):
        b = lay.time_blocks(series.raw_events(spark, d), series.DAY, series.HOUR, series.HOUR, on="ts_us")
        c = spark.range(4175).select((F.lit(series.JAN_2024) + F.col("id") * 600_000_000).alias("c"))
        return irregular.at_centres(b, c, series.HOUR, series.DAY, method=method)

    return run


for _m in ("range", "search", "index", "scan"):
    query(f"irregular_centres_{_m}", CENTRES)(_centres(_m))


@query("slot_autocov", f"WITH {series.SQL_R} SELECT CAST((b.ts_us - a.ts_us) // 600000000 AS INTEGER) AS slot, count(*) AS n, CAST(sum(a.v * b.v) AS BIGINT) AS s FROM sr a JOIN sr b ON b.ts_us > a.ts_us AND b.ts_us < a.ts_us + 3600000000 GROUP BY 1")
def _(spark, d):
    b = lay.time_blocks(series.raw_events(spark, d), series.DAY, 0, series.HOUR, on="ts_us")
    return irregular.slot_autocov(b, 600_000_000, 6)


@query("mesh_stencil", f"WITH m AS (SELECT CAST((epoch_us(l_shipdate) - {series.JAN_1995 + series.DAY}) // {7 * series.DAY} AS BIGINT) AS cx, CAST(l_quantity AS BIGINT) AS cy, count(*) AS v FROM lineitem GROUP BY 1, 2) SELECT a.cx, a.cy, CAST(sum(b.v) AS BIGINT) AS y FROM m a JOIN m b ON b.cx BETWEEN a.cx - 1 AND a.cx + 1 AND b.cy BETWEEN a.cy - 1 AND a.cy + 1 GROUP BY 1, 2")
def _(spark, d):
    li = read(spark, d, "lineitem", ["l_shipdate", "l_quantity"])
    mesh = li.groupBy(grid.index(F.col("l_shipdate"), 7 * series.DAY, series.JAN_1995 + series.DAY).alias("cx"), F.col("l_quantity").cast("bigint").alias("cy")).agg(F.count(F.lit(1)).alias("v"))
    return space.stencil(space.mesh_blocks(mesh, ["cx", "cy"], [32, 16], 1), ("cx", "cy"), {(a, b): 1 for a in (-1, 0, 1) for b in (-1, 0, 1)})


@query("points_radius", "WITH p AS (SELECT vec_id AS id, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings) SELECT a.id, count(b.id) AS n FROM p a LEFT JOIN p b ON a.id <> b.id AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 0.05 * 0.05 GROUP BY a.id")
def _(spark, d):
    p = series.vectors(spark, d).select(F.col("idx").alias("id"), F.col("x")[0].alias("px"), F.col("x")[1].alias("py"))
    return space.within_radius(space.point_blocks(p, "px", "py", 0.1, 0.05), "id", "px", "py", 0.05)


# ---- graphs

def _graph_blocks(spark, d, k):
    e = series.nation_edges(spark, d)
    v = e.select(F.col("src").alias("v")).distinct()
    return e, graph.hop_blocks(e, graph.assign(v, "range", 5), k)


@query("hop_membership", f"""WITH RECURSIVE {series.SQL_N}, b AS (SELECT src AS v, dst AS w FROM ed UNION SELECT dst, src FROM ed),
 r AS (SELECT CAST(n_nationkey // 5 AS INTEGER) AS gblk, CAST(n_nationkey AS INTEGER) AS v, 0 AS hop FROM nation UNION SELECT r.gblk, b.w, r.hop + 1 FROM r JOIN b ON b.v = r.v WHERE r.hop < 2)
 SELECT gblk, v, CAST(min(hop) AS INTEGER) AS hop, min(hop) = 0 AS is_core FROM r GROUP BY gblk, v""")
def _(spark, d):
    return _graph_blocks(spark, d, 2)[1]


@query("graph_autocov_hk", f"WITH {series.SQL_N}, p AS (SELECT src AS a, dst AS b, 1 AS hop FROM ed UNION ALL SELECT CAST(n_nationkey AS INTEGER), CAST(n_nationkey AS INTEGER), 0 FROM nation) SELECT CAST(h.h AS INTEGER) AS h, CAST(hop AS INTEGER) AS hop, count(*) AS n, CAST(sum(x.x * y.x) AS BIGINT) AS s FROM range(2) h(h) JOIN p ON true JOIN sn x ON x.v = p.a JOIN sn y ON y.v = p.b AND y.idx = x.idx + h.h GROUP BY 1, 2")
def _(spark, d):
    e, g = _graph_blocks(spark, d, 1)
    cross = graph.cross_blocks(series.nation_days(spark, d), 400, 1, g)
    return graph.pair_sums(cross, graph.block_edges(e, g), 1)


@query("cross_replication", f"WITH {series.SQL_N} SELECT count(*) AS core FROM sn0 WHERE idx BETWEEN 0 AND {series.N_O - 1} AND v BETWEEN 0 AND 24")
def _(spark, d):
    _, g = _graph_blocks(spark, d, 1)
    return graph.cross_blocks(series.nation_days_long(spark, d), 100, 1, g, bounds=(0, series.N_O - 1)).agg(F.count_if(F.col("t_core") & F.col("g_core")).alias("core"))


@query("traffic_one_step", f"""WITH {series.SQL_N}, cap AS (SELECT v, max(x) AS cap FROM sn GROUP BY v), od AS (SELECT src, count(*) AS k FROM ed GROUP BY src), ig AS (SELECT dst, count(*) AS k FROM ed GROUP BY dst),
 f AS (SELECT a.idx, ed.src, ed.dst, greatest(0, least(a.x // od.k, (c.cap - b.x) // ig.k)) AS flow FROM ed JOIN sn a ON a.v = ed.src JOIN sn b ON b.v = ed.dst AND b.idx = a.idx JOIN cap c ON c.v = ed.dst JOIN od ON od.src = ed.src JOIN ig ON ig.dst = ed.dst)
 SELECT sn.idx, sn.v, CAST(sn.x - (SELECT coalesce(sum(flow), 0) FROM f WHERE f.src = sn.v AND f.idx = sn.idx) + (SELECT coalesce(sum(flow), 0) FROM f WHERE f.dst = sn.v AND f.idx = sn.idx) AS BIGINT) AS n FROM sn""")
def _(spark, d):
    s = series.nation_days(spark, d).withColumnRenamed("x", "n")
    cap = s.groupBy("v").agg(F.max("n").alias("cap"))
    return graph.traffic_step(s, series.nation_edges(spark, d), cap, ["idx"]).select("idx", "v", "n")


@query("line_graph", f"WITH {series.SQL_N} SELECT a.src AS a, a.dst AS b, b.dst AS c FROM ed a JOIN ed b ON b.src = a.dst")
def _(spark, d):
    return graph.line_graph(series.nation_edges(spark, d))


# ---- panels, joins, aggregates, sets

@query("conv_panel_lag", "WITH c AS (SELECT conv_id, turn, CAST(length(text) AS BIGINT) AS n FROM conversations) SELECT a.conv_id, CAST(sum(a.n * b.n) AS BIGINT) AS s, count(*) AS pairs FROM c a JOIN c b ON b.conv_id = a.conv_id AND b.turn = a.turn + 1 GROUP BY 1")
def _(spark, d):
    c = read(spark, d, "conversations", ["conv_id", "turn", "text"]).select("conv_id", "turn", F.length("text").cast("bigint").alias("n"))
    w = Window.partitionBy("conv_id").orderBy("turn")
    nxt = c.withColumn("m", F.when(F.lead("turn").over(w) == F.col("turn") + 1, F.lead("n").over(w)))
    return nxt.where("m is not null").groupBy("conv_id").agg(F.sum(F.col("n") * F.col("m")).alias("s"), F.count(F.lit(1)).alias("pairs"))


@query("asof_orders", f"WITH {series.SQL_R}, c AS (SELECT CAST({series.JAN_2024} + i * 3600000000 AS BIGINT) AS t FROM range(720) x(i)) SELECT c.t, (SELECT arg_max(v, ts_us) FROM sr WHERE ts_us <= c.t) AS v FROM c")
def _(spark, d):
    left = spark.range(720).select((F.lit(series.JAN_2024) + F.col("id") * series.HOUR).alias("t"))
    return grid.asof(left, series.raw_events(spark, d).withColumnRenamed("ts_us", "t"), "t", "v", series.DAY)


@query("rollup_region_nation", "SELECT n_regionkey AS region, c_nationkey AS nation, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_nationkey)")
def _(spark, d):
    c, n = read(spark, d, "customer", ["c_nationkey"]), read(spark, d, "nation", ["n_nationkey", "n_regionkey"])
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).rollup(F.col("n_regionkey").alias("region"), F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("n"))


@query("cube_type_day", f"SELECT event_type AS kind, CAST((epoch_us(ts) - {series.JAN_2024}) // {series.DAY} AS BIGINT) AS day, count(*) AS n FROM events GROUP BY CUBE (1, 2)")
def _(spark, d):
    e = read(spark, d, "events", ["ts", "event_type"]).select(F.col("event_type").alias("kind"), grid.index(F.col("ts"), series.DAY, series.JAN_2024).alias("day"))
    return e.cube("kind", "day").agg(F.count(F.lit(1)).alias("n"))


@query("topk_lags", COV_E + " SELECT lag, i, j, c / (n - 1) AS value FROM cv WHERE lag > 0 ORDER BY abs(c / (n - 1)) DESC, lag, i, j LIMIT 10")
def _(spark, d):
    return lag_frame(spark, moments_e(spark, d).autocov()).where("lag > 0").orderBy(F.desc(F.abs("value")), "lag", "i", "j").limit(10)


@query("semi_anti_gaps", f"WITH {series.SQL_O} SELECT (SELECT count(*) FROM so a WHERE v IS NOT NULL AND EXISTS (SELECT 1 FROM so b WHERE b.idx = a.idx + 1 AND b.v IS NOT NULL)) AS with_next, (SELECT count(*) FROM so a WHERE v IS NOT NULL AND NOT EXISTS (SELECT 1 FROM so b WHERE b.idx = a.idx + 1 AND b.v IS NOT NULL)) AS without_next")
def _(spark, d):
    s = series.orders(spark, d).where("v is not null").select("idx")
    nxt = s.select((F.col("idx") - 1).alias("idx"))
    return s.join(nxt, "idx", "left_semi").agg(F.count(F.lit(1)).alias("with_next")).crossJoin(s.join(nxt, "idx", "left_anti").agg(F.count(F.lit(1)).alias("without_next")))


@query("set_ops_index", f"WITH {series.SQL_O}, {series.SQL_E}, a AS (SELECT DISTINCT idx FROM so WHERE v IS NOT NULL), b AS (SELECT DISTINCT idx FROM se0) SELECT 'both' AS part, count(*) AS n FROM (SELECT idx FROM a INTERSECT SELECT idx FROM b) UNION ALL SELECT 'left', count(*) FROM (SELECT idx FROM a EXCEPT SELECT idx FROM b) UNION ALL SELECT 'any', count(*) FROM (SELECT idx FROM a UNION SELECT idx FROM b)")
def _(spark, d):
    a = series.orders(spark, d).where("v is not null").select("idx")
    b = series.events_long(spark, d).select("idx")
    parts = {"both": a.intersect(b), "left": a.exceptAll(b.distinct()), "any": a.union(b).distinct()}
    out = [df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(k).alias("part"), "n") for k, df in parts.items()]
    return out[0].unionByName(out[1]).unionByName(out[2])


@query("session_events", "WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS s FROM events), g AS (SELECT user_id, ts, sum(s) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e), n AS (SELECT user_id, k, count(*) AS v FROM g GROUP BY 1, 2) SELECT user_id, count(*) AS sessions, max(v) AS longest FROM n GROUP BY 1")
def _(spark, d):
    e = read(spark, d, "events", ["ts", "user_id"])
    return stream.sessions(e, "ts", "6 hours", "user_id").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("v").alias("longest"))


@query("sliding_events", f"WITH e AS (SELECT epoch_us(ts) AS t FROM events), k AS (SELECT t, unnest(range(0, 3)) AS o FROM e) SELECT CAST((t // {series.HOUR} - o) * {series.HOUR} AS BIGINT) AS start, count(*) AS v FROM k GROUP BY 1")
def _(spark, d):
    s = stream.sliding(read(spark, d, "events", ["ts"]), "ts", "3 hours", "1 hour")
    return s.select(micros(F.col("window.start")).alias("start"), "v")


@query("props_json_series", f"SELECT CAST((epoch_us(ts) - {series.JAN_2024}) // {series.DAY} AS BIGINT) AS idx, CAST(sum(CAST(json_extract(props, '$.k') AS INTEGER)) AS BIGINT) AS v FROM events GROUP BY 1")
def _(spark, d):
    e = read(spark, d, "events", ["ts", "props"]).withColumn("k", F.from_json("props", "k int")["k"])
    return e.groupBy(grid.index(F.col("ts"), series.DAY, series.JAN_2024).alias("idx")).agg(F.sum("k").alias("v"))


# ---- streams

def _event_stream(spark, d, columns):
    path = scratch(spark)
    src = read(spark, d, "events", columns).withColumn("ts", F.col("ts").cast("timestamp")).repartitionByRange(4, "ts")
    src.write.parquet(f"{path}/in")
    return spark.readStream.schema(src.schema).parquet(f"{path}/in"), path


@query("stream_grid_events", f"SELECT CAST((epoch_us(ts) // {series.HOUR}) * {series.HOUR} AS BIGINT) AS start, event_type, count(*) AS v FROM events GROUP BY 1, 2")
def _(spark, d):
    src, path = _event_stream(spark, d, ["ts", "event_type"])
    got = stream.run(stream.grid(src, "ts", "1 hour", "1 hour", "event_type"), f"{path}/out", f"{path}/cp", "update")
    last = got.groupBy("window", "event_type").agg(F.max_by("v", "batch").alias("v"))
    return last.select(micros(F.col("window.start")).alias("start"), "event_type", "v")


@query("stream_autocov_events", f"WITH {series.SQL_E} SELECT a.dim, CAST(h.l AS INTEGER) AS lag, count(*) AS n, CAST(sum(a.v * b.v) AS BIGINT) AS s FROM range(3) h(l) JOIN se a ON true JOIN se b ON b.dim = a.dim AND b.idx = a.idx + h.l GROUP BY 1, 2")
def _(spark, d):
    path = scratch(spark)
    src = series.events(spark, d)
    src.coalesce(1).write.parquet(f"{path}/in")
    live = spark.readStream.schema(src.schema).parquet(f"{path}/in")
    got = stream.run(stream.autocov(live, "dim", 2), f"{path}/out", f"{path}/cp", "update")
    return got.groupBy("dim", "lag").agg(F.max("n").alias("n"), F.max_by("s", "batch").alias("s"))


# ---- baselines

SELF = f"WITH {series.SQL_E} SELECT CAST(h.l AS INTEGER) AS lag, a.dim AS i, b.dim AS j, count(*) AS n, CAST(sum(a.v * b.v) AS BIGINT) AS s FROM range(4) h(l) JOIN se a ON true JOIN se b ON b.idx = a.idx + h.l GROUP BY 1, 2, 3"
query("baseline_self_join", SELF)(lambda spark, d: baselines.self_join(series.events(spark, d), 3))
query("baseline_by_series", SELF)(lambda spark, d: baselines.by_series(series.events(spark, d), 3))
query("baseline_global_window", f"WITH {series.SQL_E} SELECT CAST(h.l AS INTEGER) AS lag, a.dim AS i, CAST(sum(a.v * b.v) AS BIGINT) AS s FROM range(4) h(l) JOIN se a ON true JOIN se b ON b.idx = a.idx + h.l AND b.dim = a.dim GROUP BY 1, 2")(lambda spark, d: baselines.global_window(series.events(spark, d), 3))


# ---- iterative fits and reports (no SQL)

def _gram_l(spark, d, p=1):
    b = lay.time_blocks(moments.center(grid.to_wide(series.lineitem(spark, d), 6), _mean_l(spark, d)), 256, p, 0)
    return moments.gram_matrix(moments.lag_gram(b, p, p), p, 6)


def _mean_l(spark, d):
    rows = moments.mean(series.lineitem(spark, d)).collect()
    return np.array([r.mean for r in sorted(rows, key=lambda r: r.dim)])


TRACE = "iter int, objective double, grad_norm double, step double, rows_touched bigint"


@query("gradient_fit")
def _(spark, d):
    return spark.createDataFrame(likelihood.gradient_fit(_gram_l(spark, d), 6, 1, np.eye(6))[1], TRACE)


@query("gradient_fit_backtracking")
def _(spark, d):
    return spark.createDataFrame(likelihood.gradient_fit(_gram_l(spark, d), 6, 1, np.eye(6), "backtracking")[1], TRACE)


@query("sgd_fit")
def _(spark, d):
    b = lay.time_blocks(moments.center(grid.to_wide(series.lineitem(spark, d), 6), _mean_l(spark, d)), 256, 1, 0).persist()
    out = likelihood.sgd_fit(b, 6, 1, np.eye(6), 1, rounds=6, rate=0.2, c=0.02)[1]
    b.unpersist()
    return spark.createDataFrame(out, TRACE)


@query("newton_fit")
def _(spark, d):
    t = likelihood.newton(*_gram_l(spark, d))
    return spark.createDataFrame([(i, j, float(t[i, j])) for i in range(6) for j in range(6)], "i int, j int, value double")


@query("alternate_fit")
def _(spark, d):
    _, pi, seen = likelihood.alternate(*_gram_l(spark, d))
    return spark.createDataFrame([(k, float(f)) for k, f in enumerate(seen)], "iter int, objective double")


@query("arma_fit")
def _(spark, d):
    return fit.arma(moments_o(spark, d, 8).autocov("n"), 1, 1, 8).to_df(spark)


@query("order_search")
def _(spark, d):
    g = moments_o(spark, d, 8).autocov("n")
    rows = [(p, q, float(c), k) for k in ("aic", "bic") for p, q, c in fit.search(g, series.N_O, 2, 2, k, 8) if math.isfinite(c)]
    return spark.createDataFrame(rows, "p int, q int, value double, criterion string")


@query("unconditional_fit")
def _(spark, d):
    wide = series.orders(spark, d, 0).select("idx", F.array(F.col("v").cast("double")).alias("x"))
    x = moments.center(wide, np.array([wide.agg(F.avg(F.col("x")[0])).head()[0]]))
    m, n = moments.gram_matrix(moments.lag_gram(lay.time_blocks(x, 128, 1, 0), 1, 1), 1, 1)
    first = np.array([r.x for r in x.orderBy("idx").limit(1).collect()])
    model, ll = likelihood.unconditional_fit(m, n, first)
    return spark.createDataFrame([("conditional", float(likelihood.newton(m, n)[0, 0])), ("unconditional", float(model.a[0][0, 0])), ("loglik", float(ll))], "name string, value double")


def supplier_sql(b: str) -> str:
    """Suppliers on the grid of all days, their means over it, and pairs of days."""
    return f"""WITH s0 AS (SELECT CAST((epoch_us(l_shipdate) - {series.JAN_1995 + series.DAY}) // {series.DAY} AS BIGINT) AS idx, CAST(l_suppkey AS INTEGER) AS dim, count(*) AS v FROM lineitem GROUP BY 1, 2),
 gr AS (SELECT CAST(a.i AS BIGINT) AS idx, d.dim, CAST(coalesce(s0.v, 0) AS DOUBLE) AS v FROM range({series.N_L}) a(i) CROSS JOIN (SELECT DISTINCT dim FROM s0) d LEFT JOIN s0 ON s0.idx = a.i AND s0.dim = d.dim),
 c AS (SELECT idx, dim, v - avg(v) OVER (PARTITION BY dim) AS z FROM gr) {b}"""


def _suppliers(spark, d):
    long = series.supplier_days(spark, d)
    return long, (long.agg(F.max("dim").alias("m")).head().m or 0) + 1


@query("banded_fit_suppliers_diag", supplier_sql("SELECT a.dim AS i, a.dim AS j, round(sum(a.z * b.z) / sum(a.z * a.z), 8) AS value FROM c a JOIN c b ON b.dim = a.dim AND b.idx = a.idx + 1 GROUP BY 1"))
def _(spark, d):
    long, n = _suppliers(spark, d)
    got = banded.fit_sums(long, series.N_L, n, 0, max(2, n // 25)).where("sigma2 > 0")
    return got.select("i", "j", F.round("value", 8).alias("value"))


@query("banded_fit_suppliers")
def _(spark, d):
    long, n = _suppliers(spark, d)
    return banded.fit_sums(long, series.N_L, n, 1, max(2, n // 25))


@query("banded_fit_shared")
def _(spark, d):
    theta, trace = banded.fit_shared(grid.to_wide(series.lineitem(spark, d), 6), 6, 1, 2, steps=6)
    return spark.createDataFrame([(k, float(f)) for k, f in trace], "iter int, objective double")


@query("traffic_simulate")
def _(spark, d):
    root = scratch(spark)
    e = series.nation_edges(spark, d)
    s = stash(series.nation_days(spark, d), f"{root}/days")
    cap = stash(s.groupBy("v").agg((F.max("x") * 2).alias("cap")), f"{root}/cap")
    now = s.where("idx = 0").select(F.lit(0).alias("step"), "v", F.col("x").alias("n"))
    out = now
    for k in range(1, 4):
        # A step reads the one before several times, so each is written once.
        now = stash(graph.traffic_step(now, e, cap, ["step"], seed=17).select((F.lit(k)).alias("step"), "v", "n"), f"{root}/step-{k}")
        out = out.unionByName(now)
    return out


@query("estimator_variance")
def _(spark, d):
    """Variance of the mean over all stretches of n line items, by n: the slope is near -1."""
    rows, e = [], series.quantities(spark, d)
    for n in (8, 32, 128):
        v = e.groupBy(F.expr(f"t div {n}").alias("s")).agg(F.avg("e").alias("m"), F.count(F.lit(1)).alias("n")).where(F.col("n") == n).agg(F.var_samp("m").alias("v")).head().v
        rows.append((n, float(v)))
    return spark.createDataFrame([*[(f"variance_{n}", v, "mean") for n, v in rows], ("slope", measures.slope(*zip(*rows)), "mean")], measures.ROWS)


@query("layout_costs")
def _(spark, d):
    long = series.events(spark, d)
    b = blocks_e(spark, d)
    rows = measures.communication(moments.lag_products(b, 3, 3), "overlap") + measures.communication(baselines.self_join(long, 3), "self_join")
    kept = b.persist()
    kept.count()
    rows += measures.communication(moments.lag_products(kept, 3, 3), "overlap_cached")
    kept.unpersist()
    return measures.table(spark, rows)


def _load() -> None:
    """The modules that add their queries to this registry."""
    from halo import surrounding, workloads  # noqa: F401


def queries() -> dict:
    _load()
    return dict(ALL)


def oracle_sql() -> dict[str, str]:
    _load()
    return dict(SQL)
