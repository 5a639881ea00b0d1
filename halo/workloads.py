"""Registered workloads: long lags and wide series, known-truth series, fits and forecasts on them, networks, measures."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from halo import baselines, measures, series
from halo.functions import linalg
from halo.models import banded, fit, likelihood, moments, predict
from halo.models.process import Process
from halo.operators import blocks as lay
from halo.operators import difference, graph, grid
from halo.plans import audit
from halo.plans.scratch import folder
from halo.registry import COV, COV_E, COV_O, _graph_blocks, _suppliers, blocks_e, lag_frame, moments_e, moments_o, query, supplier_sql
from halo.streaming import stream
from halo.surrounding import folder as _folder  # noqa: F401  (registers its queries first)

N_E, N_O, N_L = series.N_E, series.N_O, series.N_L


# ---- long lags, many dimensions

def _moments(wide, n, H, entries="all"):
    return moments.Moments.collect(moments.lag_products(lay.time_blocks(wide, 96, 0, H, bounds=(0, n - 1)), H, H, entries))


@query("autocov_events_h24", f"WITH {series.SQL_E}, " + COV.format(t="se", H=24, N=N_E) + " SELECT lag, i, j, c / (n - 1) AS value FROM cv")
def _(spark, d):
    return lag_frame(spark, _moments(grid.to_wide(series.events(spark, d), 5), N_E, 24).autocov())


@query("autocov_users_h24", f"WITH {series.SQL_U}, " + COV.format(t="su", H=24, N=N_E) + " SELECT lag, i, j, c / (n - 1) AS value FROM cv")
def _(spark, d):
    return lag_frame(spark, _moments(grid.to_wide(series.users(spark, d), 16), N_E, 24).autocov())


@query("autocov_cents_h24", f"WITH {series.SQL_EV} SELECT CAST(h.l AS INTEGER) AS lag, a.dim AS i, b.dim AS j, count(*) AS n, CAST(sum(a.v * b.v) AS BIGINT) AS s FROM range(25) h(l) JOIN sv a ON true JOIN sv b ON b.idx = a.idx + h.l GROUP BY 1, 2, 3")
def _(spark, d):
    """Lag products of values, summed as integers: products of hourly sums pass 2^53."""
    b = lay.time_blocks(grid.to_wide(series.cents(spark, d), 5), 96, 0, 24, bounds=(0, N_E - 1))
    return moments.whole_lag_products(b, 24, 24)


@query("autocov_suppliers_diag", supplier_sql("SELECT CAST(h.l AS INTEGER) AS lag, a.dim AS i, round(sum(a.z * b.z) / (count(*) - 1), 8) AS value FROM range(25) h(l) JOIN c a ON true JOIN c b ON b.dim = a.dim AND b.idx = a.idx + h.l GROUP BY 1, 2"))
def _(spark, d):
    """Diagonal entries up to lag 24 of as many dimensions as there are suppliers, slab of dimensions by slab: no d x d matrix anywhere."""
    return moments.diagonal_covariances(series.supplier_days(spark, d), N_L, 24).withColumn("value", F.round("value", 8))


@query("autocov_suppliers_tiles", supplier_sql(" SELECT CAST(h.l AS INTEGER) AS lag, a.dim AS i, b.dim AS j, round(sum(a.z * b.z) / (count(*) - 1), 8) AS value FROM range(2) h(l) JOIN c a ON true JOIN c b ON b.idx = a.idx + h.l GROUP BY 1, 2, 3"))
def _(spark, d):
    """All pairs of suppliers, one task for each pair of slabs; entries never meet on the driver."""
    return moments.wide_covariances(series.supplier_days(spark, d), N_L, 1, folder(spark), digits=8)


LAG64 = f"WITH {series.SQL_L} SELECT CAST(h.l AS INTEGER) AS lag, a.dim AS i, b.dim AS j, count(*) AS n, CAST(sum(a.v * b.v) AS BIGINT) AS s FROM range(65) h(l) JOIN sl a ON true JOIN sl b ON b.idx = a.idx + h.l GROUP BY 1, 2, 3"


def _lag64(backend):
    def run(spark, d):
        b = lay.time_blocks(grid.to_wide(series.lineitem(spark, d), 6), 512, 0, 64, bounds=(0, N_L - 1))
        return moments.lag_products(b, 64, 64, backend=backend).select("lag", "i", "j", F.col("n").cast("bigint").alias("n"), F.col("s").cast("bigint").alias("s"))

    return run


query("staged_h64", LAG64)(_lag64("arrow"))
query("unstaged_h64", LAG64)(_lag64("sql"))


@query("staged_costs")
def _(spark, d):
    """Seconds of the staged and the unstaged kernel by reach, over one kept layout."""
    b = lay.time_blocks(grid.to_wide(series.lineitem(spark, d), 6), 512, 0, 64, bounds=(0, N_L - 1)).persist()
    b.count()
    rows = []
    for H in (1, 4, 16, 64):
        sums = {}
        for name in ("arrow", "sql"):
            t = time.perf_counter()
            sums[name] = moments.lag_products(b, H, 64, backend=name).agg(F.sum("s")).head()[0]
            rows.append((f"seconds_{name}", time.perf_counter() - t, f"H={H}"))
        rows.append(("equal", float(sums["arrow"] == sums["sql"]), f"H={H}"))
    b.unpersist()
    return measures.table(spark, rows)


# ---- known-truth series

TRUTH = {
    "white": [1.0], "ma1": [2.0, 1.0], "ma2": [4.0, 2.0, 1.0], "ar1": [2.0**-k for k in range(21)],
    "arma11": [2.0] + [2.0 ** (1 - k) + 2.0 ** (1 - k) for k in range(1, 21)] + [2.0**-20],
}
SQL_W = f"{series.SQL_E}, sw AS (SELECT idx, v FROM se WHERE dim = 0)"


def _fir_sql(name):
    w = TRUTH[name]
    pairs = ", ".join(f"({k}, CAST({x!r} AS DOUBLE))" for k, x in enumerate(w))
    return f"{name} AS (SELECT a.idx, sum(w.w * b.v) AS v FROM sw a JOIN (VALUES {pairs}) w(k, w) ON true JOIN sw b ON b.idx = a.idx - w.k WHERE a.idx >= {len(w) - 1} GROUP BY a.idx)"


SQL_T = ", ".join([SQL_W, *map(_fir_sql, TRUTH), "dif AS (SELECT a.idx, CAST(b.v - a.v AS DOUBLE) AS v FROM sw a JOIN sw b ON b.idx = a.idx + 1)", f"rw AS (SELECT idx, CAST(sum({N_E} * v - (SELECT sum(v) FROM sw)) OVER (ORDER BY idx) AS DOUBLE) AS v FROM sw)"])


def truth(spark, d, name):
    """A known-truth series (idx, v) from the hourly clicks, by blocks."""
    white = series.events(spark, d).where("dim = 0").select("idx", "v")
    if name == "rw":
        total = white.agg(F.sum("v")).head()[0]
        shifted = white.select("idx", (F.lit(N_E) * F.col("v") - F.lit(total)).alias("v"))
        return difference.prefix_sum(lay.time_blocks(shifted, 96, 0, 0, bounds=(0, N_E - 1))).select("idx", F.col("y").cast("double").alias("v"))
    if name == "dif":
        return difference.diff(lay.time_blocks(white, 96, 0, 1, bounds=(0, N_E - 1)), 1).select("idx", F.col("y").cast("double").alias("v"))
    w = TRUTH[name]
    return difference.fir(lay.time_blocks(white, 96, len(w) - 1, 0, bounds=(0, N_E - 1)), w).select("idx", F.col("y").alias("v"))


def _wide(s):
    return s.select("idx", F.array("v").alias("x"))


def truth_moments(spark, d, name, H=2):
    s = truth(spark, d, name)
    return moments.Moments.collect(moments.lag_products(lay.time_blocks(_wide(s), 96, 0, H), H, H))


NAMES = [*TRUTH, "dif", "rw"]


@query("truth_series", f"WITH {SQL_T} " + " UNION ALL ".join(f"SELECT '{n}' AS name, idx, CAST(v AS DOUBLE) AS v FROM {n}" for n in NAMES))
def _(spark, d):
    parts = [truth(spark, d, n).select(F.lit(n).alias("name"), "idx", "v") for n in NAMES]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _g(name, H=2):
    """Covariances about the mean with the length as denominator, in plain SQL."""
    cells = ", ".join(f"(SELECT sum(a.z * b.z) FROM z_{name} a JOIN z_{name} b ON b.idx = a.idx + {h}) / (SELECT count(*) FROM z_{name}) AS g{h}" for h in range(H + 1))
    return f"z_{name} AS (SELECT idx, v - (SELECT avg(v) FROM {name}) AS z FROM {name}), g_{name} AS (SELECT {cells}, (SELECT count(*) FROM z_{name}) AS n)"


@query("ma_order_truth", f"WITH {SQL_T}, {_g('ma1', 4)}, {_g('ma2', 4)} " + " UNION ALL ".join(f"SELECT '{n}' AS name, CAST({h} AS INTEGER) AS lag, round(g{h} / g0, 8) AS r, abs(g{h} / g0) > 1.959963984540054 / sqrt(n) AS significant FROM g_{n}" for n in ("ma1", "ma2") for h in range(1, 5)))
def _(spark, d):
    rows = []
    for name in ("ma1", "ma2"):
        m = truth_moments(spark, d, name, 4)
        r = moments.acf(m.autocov("n"))
        rows += [(name, h, round(float(r[h, 0, 0]), 8), not fit.insignificant(r[h], int(m.n[0]), 0.95)) for h in range(1, 5)]
    return spark.createDataFrame(rows, "name string, lag int, r double, significant boolean")


@query("ar_order_truth", f"WITH {SQL_T}, {_g('ar1')}, {_g('white')}, k AS (" + " UNION ALL ".join(f"SELECT '{n}' AS name, n, g1 / g0 AS k1, (g2 * g0 - g1 * g1) / (g0 * g0 - g1 * g1) AS k2 FROM g_{n}" for n in ("ar1", "white")) + ") SELECT name, round(k1, 8) AS k1, round(k2, 8) AS k2, CAST(CASE WHEN abs(k1) <= 1.959963984540054 / sqrt(n) THEN 0 WHEN abs(k2) <= 1.959963984540054 / sqrt(n) THEN 1 ELSE 2 END AS INTEGER) AS p FROM k")
def _(spark, d):
    rows = []
    for name in ("ar1", "white"):
        m = truth_moments(spark, d, name)
        k = moments.pacf(m.autocov("n"), 2)
        rows.append((name, round(float(k[0][0, 0]), 8), round(float(k[1][0, 0]), 8), fit.ar_order(k, int(m.n[0]))))
    return spark.createDataFrame(rows, "name string, k1 double, k2 double, p int")


DEPTH = "SELECT '{n}' AS name, CAST(1 AS INTEGER) AS depth, round(g1 / g0, 8) AS b1, round(g0 - g1 * g1 / g0, 8) AS s FROM g_{n} UNION ALL SELECT '{n}', 2, round((g1 - g2 * g1 / g0) / (g0 - g1 * g1 / g0), 8), round(g0 - g2 * g2 / g0 - (g1 - g2 * g1 / g0) * (g1 - g2 * g1 / g0) / (g0 - g1 * g1 / g0), 8) FROM g_{n}"


@query("ma_depth_sweep", f"WITH {SQL_T}, {_g('ma1')}, {_g('ma2')}, {_g('dif')} " + " UNION ALL ".join(DEPTH.format(n=n) for n in ("ma1", "ma2", "dif")))
def _(spark, d):
    rows = []
    for name in ("ma1", "ma2", "dif"):
        g = truth_moments(spark, d, name).autocov("n")
        for depth in (1, 2):
            m = fit.ma(g, 1, depth)
            rows.append((name, depth, round(float(m.b[0][0, 0]), 8), round(float(m.sigma[0, 0]), 8)))
    return spark.createDataFrame(rows, "name string, depth int, b1 double, s double")


@query("innovations_depths")
def _(spark, d):
    """Innovations estimates by depth: MA(1) and the ARMA(1,1), whose truths are 0.5 and (0.5, 0.5)."""
    rows = []
    g, h = truth_moments(spark, d, "ma1", 12).autocov("n"), truth_moments(spark, d, "arma11", 12).autocov("n")
    for depth in (2, 4, 8, 12):
        rows.append(("ma1_b", float(fit.ma(g, 1, depth).b[0][0, 0]), f"depth={depth}"))
        m = fit.arma(h, 1, 1, depth)
        rows += [("arma_a", float(m.a[0][0, 0]), f"depth={depth}"), ("arma_b", float(m.b[0][0, 0]), f"depth={depth}"), ("arma_s", float(m.sigma[0, 0]), f"depth={depth}")]
    return measures.table(spark, rows)


@query("integration_order", f"WITH {SQL_T}, d1 AS (SELECT a.idx, b.v - a.v AS v FROM rw a JOIN rw b ON b.idx = a.idx + 1), {_g('rw')}, {_g('d1')} SELECT CAST(0 AS INTEGER) AS k, round(g1 / g0, 8) AS r1, g1 / g0 < 0.9 AS stationary FROM g_rw UNION ALL SELECT 1, round(g1 / g0, 8), g1 / g0 < 0.9 FROM g_d1")
def _(spark, d):
    s = truth(spark, d, "rw")

    def acf_of(k):
        x = s if not k else difference.diff(lay.time_blocks(s, 96, 0, k), k).withColumnRenamed("y", "v")
        g = moments.Moments.collect(moments.lag_products(lay.time_blocks(_wide(x), 96, 0, 1), 1, 1)).autocov("n")
        return float(g[1, 0, 0] / g[0, 0, 0])

    _, seen = difference.integration_order(acf_of)
    return spark.createDataFrame([(k, round(r, 8), r < 0.9) for k, r in seen], "k int, r1 double, stationary boolean")


# ---- ARMA forecasts three ways: A = B = 1/2 on the series that has them

ARMA = f"WITH RECURSIVE {SQL_T}, x AS (SELECT idx - 21 AS t, v FROM arma11), r AS (SELECT t, v AS e, 0.5 * v + 0.5 * v AS f FROM x WHERE t = 0 UNION ALL SELECT x.t, x.v - r.f, 0.5 * x.v + 0.5 * (x.v - r.f) FROM r JOIN x ON x.t = r.t + 1) SELECT t + 21 AS idx, round(f, 6) AS yhat FROM r"
ARMA_MODEL = Process(a=[np.array([[0.5]])], b=[np.array([[0.5]])], sigma=np.eye(1))


@query("arma_serial_truth", ARMA)
def _(spark, d):
    got = sorted((r.idx, r.v) for r in truth(spark, d, "arma11").collect())  # one machine, as the baseline it is
    f, _ = predict.arma_serial(np.array([[v] for _, v in got]), ARMA_MODEL)
    return spark.createDataFrame([(i, round(float(y), 6)) for (i, _), y in zip(got, f[:, 0])], "idx bigint, yhat double")


@query("arma_blocks_truth", ARMA.replace("SELECT t + 21 AS idx, round(f, 6) AS yhat FROM r", "SELECT t + 22 AS idx, round(f, 6) AS yhat FROM r WHERE t < (SELECT max(t) FROM x)"))
def _(spark, d):
    w = ARMA_MODEL.warmup(1e-13)
    b = lay.time_blocks(_wide(truth(spark, d, "arma11")), 128, w + 1, 0)
    # A block's forecast stands at the step that it is of.
    return predict.arma_blocks(b, ARMA_MODEL, np.zeros(1), w, w + 1).where("idx > 21").select("idx", F.round(F.col("forecast")[0], 6).alias("yhat"))


@query("arma_stream_truth", ARMA)
def _(spark, d):
    path, src = folder(spark), truth(spark, d, "arma11").withColumn("key", F.lit(0))
    for k in range(3):  # files in order of time, one a micro-batch
        src.where(F.floor(F.col("idx") * 3 / N_E) == k).coalesce(1).write.mode("append").parquet(f"{path}/in")
    live = spark.readStream.schema(src.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/in")
    got = stream.run(stream.arma_forecast(live, "key", [0.5], [0.5]), f"{path}/out", f"{path}/cp")
    return got.select("idx", F.round("yhat", 6).alias("yhat"))


@query("warmup_error")
def _(spark, d):
    """Largest difference from the serial forecast by warm-up length, with and without data to start from."""
    x = truth(spark, d, "arma11").persist()
    got = sorted((r.idx, r.v) for r in x.collect())
    f, _ = predict.arma_serial(np.array([[v] for _, v in got]), ARMA_MODEL)
    serial = spark.createDataFrame([(i + 1, float(y)) for (i, _), y in zip(got, f[:, 0])], "idx bigint, s double")
    rows = []
    for w in (1, 2, 4, 8, 16, 32):
        b = predict.arma_blocks(lay.time_blocks(_wide(x), 128, w + 1, 0), ARMA_MODEL, np.zeros(1), w, w + 1)
        worst = b.join(serial, "idx").agg(F.max(F.abs(F.col("forecast")[0] - F.col("s")))).head()[0]
        rows.append(("max_error", float(worst), f"warmup={w}"))
    x.unpersist()
    return measures.table(spark, rows)


# ---- forecasts with intervals, fits in closed form

AR2 = COV_O + f", q AS (SELECT max(CASE WHEN lag = 0 THEN c END) / {N_O} AS h0, max(CASE WHEN lag = 1 THEN c END) / {N_O} AS h1, max(CASE WHEN lag = 2 THEN c END) / {N_O} AS h2 FROM cv), k AS (SELECT *, h1 * (h0 - h2) / (h0 * h0 - h1 * h1) AS a1, (h2 * h0 - h1 * h1) / (h0 * h0 - h1 * h1) AS a2 FROM q), m AS (SELECT *, h0 - a1 * h1 - a2 * h2 AS s, (SELECT avg(v) FROM sz) AS mu FROM k), f AS (SELECT a.idx, mu + a1 * (a.v - mu) + a2 * (b.v - mu) AS yhat, 1.959963984540054 * sqrt(s) AS half FROM sz a JOIN sz b ON b.idx = a.idx - 1, m)"


def _ar2_forecast(spark, d):
    m = moments_o(spark, d, 2)
    model = fit.yule_walker(m.autocov("n"), 2)
    wide = series.orders(spark, d, 0).select("idx", F.array(F.col("v").cast("double")).alias("x"))
    f = predict.one_step(lay.time_blocks(wide, 256, 2, 0, bounds=(0, N_O - 1)), model, m.mean, 2)
    return predict.with_interval(f, predict.variance(model, 1)[0]).select("idx", *[F.round(F.col(c)[0], 6).alias(c) for c in ("yhat", "lo", "hi")])


@query("prediction_intervals", AR2 + " SELECT idx, round(yhat, 6) AS yhat, round(yhat - half, 6) AS lo, round(yhat + half, 6) AS hi FROM f")
def _(spark, d):
    return _ar2_forecast(spark, d)


@query("interval_coverage", AR2 + " SELECT count(*) AS n, count(*) FILTER (s.v BETWEEN round(yhat - half, 6) AND round(yhat + half, 6)) AS inside, round(sqrt(avg((round(yhat, 6) - s.v) * (round(yhat, 6) - s.v))), 6) AS rmse FROM f JOIN sz s ON s.idx = f.idx + 1")
def _(spark, d):
    """Forecast errors and the share of next values inside the 95 % interval."""
    actual = series.orders(spark, d, 0).select((F.col("idx") - 1).alias("idx"), "v")
    both = _ar2_forecast(spark, d).join(actual, "idx")
    return both.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("v").between(F.col("lo"), F.col("hi"))).alias("inside"), F.round(F.sqrt(F.avg((F.col("yhat") - F.col("v")) ** 2)), 6).alias("rmse"))


@query("gof_report", AR2 + """, c0 AS (SELECT idx, v - mu AS z FROM sz, m), e AS (SELECT a.idx, a.z - CASE WHEN b.z IS NULL THEN 0 ELSE a1 * b.z END - CASE WHEN c.z IS NULL THEN 0 ELSE a2 * c.z END AS e FROM c0 a LEFT JOIN c0 b ON b.idx = a.idx - 1 LEFT JOIN c0 c ON c.idx = a.idx - 2, m),
 t AS (SELECT count(*) AS n, sum(e * e) / count(*) AS s2 FROM e), l AS (SELECT *, -0.5 * n * (ln(s2) + ln(2 * pi()) + 1) AS ll FROM t)
 SELECT 'n' AS name, CAST(n AS DOUBLE) AS value FROM l UNION ALL SELECT 'loglik', round(ll, 6) FROM l UNION ALL SELECT 'aic', round(2 * 3 - 2 * ll, 6) FROM l UNION ALL SELECT 'bic', round(3 * ln(n) - 2 * ll, 6) FROM l UNION ALL SELECT 'r2_0', round(1 - s2 / h0, 6) FROM l, m""")
def _(spark, d):
    m = moments_o(spark, d, 3)
    g = m.autocov("n")
    model = fit.yule_walker(g, 2)
    wide = series.orders(spark, d, 0).select("idx", F.array(F.col("v").cast("double")).alias("x"))
    res = fit.residuals(lay.time_blocks(wide, 256, 2, 0, bounds=(0, N_O - 1)), model, m.mean)
    return spark.createDataFrame([(k, round(float(v), 6)) for k, v in fit.summary(res, model, np.diag(g[0])).items()], "name string, value double")


PAIR = f"WITH {series.SQL_E}, x AS (SELECT a.idx, a.v AS x0, b.v AS x1 FROM se a JOIN se b ON b.idx = a.idx AND a.dim = 0 AND b.dim = 1), p AS (SELECT a.x0, a.x1, b.x0 AS y0, b.x1 AS y1 FROM x a JOIN x b ON b.idx = a.idx + 1), s AS (SELECT CAST(sum(x0 * x0) AS DOUBLE) AS a, CAST(sum(x0 * x1) AS DOUBLE) AS b, CAST(sum(x1 * x1) AS DOUBLE) AS c, sum(y0 * x0) AS p00, sum(y0 * x1) AS p01, sum(y1 * x0) AS p10, sum(y1 * x1) AS p11 FROM p)"


@query("newton_fit_d2", PAIR + " SELECT 0 AS i, 0 AS j, round((p00 * c - p01 * b) / (a * c - b * b), 8) AS value FROM s UNION ALL SELECT 0, 1, round((p01 * a - p00 * b) / (a * c - b * b), 8) FROM s UNION ALL SELECT 1, 0, round((p10 * c - p11 * b) / (a * c - b * b), 8) FROM s UNION ALL SELECT 1, 1, round((p11 * a - p10 * b) / (a * c - b * b), 8) FROM s")
def _(spark, d):
    return _theta2(spark, likelihood.newton(*_gram2(spark, d)))


def _blocks2(spark, d):
    return lay.time_blocks(grid.to_wide(series.events(spark, d).where("dim < 2"), 2), 96, 1, 0, bounds=(0, N_E - 1))


def _gram2(spark, d):
    return moments.gram_matrix(moments.lag_gram(_blocks2(spark, d), 1, 1), 1, 2)


def _theta2(spark, t):
    return spark.createDataFrame([(i, j, round(float(t[i, j]), 8)) for i in range(2) for j in range(2)], "i int, j int, value double")


NEWTON_ROUNDED = (PAIR + " SELECT 0 AS i, 0 AS j, round((p00 * c - p01 * b) / (a * c - b * b), 5) AS value FROM s UNION ALL SELECT 0, 1, round((p01 * a - p00 * b) / (a * c - b * b), 5) FROM s UNION ALL SELECT 1, 0, round((p10 * c - p11 * b) / (a * c - b * b), 5) FROM s UNION ALL SELECT 1, 1, round((p11 * a - p10 * b) / (a * c - b * b), 5) FROM s")


@query("gradient_fit_blocks", NEWTON_ROUNDED)
def _(spark, d):
    """Full gradient on blocks along conjugate directions: it ends at the least squares optimum, however large the counts."""
    b = _blocks2(spark, d).persist()
    theta, _ = likelihood.gradient_fit(b, 2, 1, np.diag([1.0, 1.0]), "conjugate", halo=1, tol=1e-7, most=80)
    b.unpersist()
    return _theta2(spark, np.round(theta, 5))


@query("cond_gradient_p2", f"WITH {series.SQL_E}, r AS (SELECT a.idx, a.dim, a.v - b.v + c.v AS r FROM se a JOIN se b ON b.dim = a.dim AND b.idx = a.idx - 1 JOIN se c ON c.dim = a.dim AND c.idx = a.idx - 2) SELECT r.dim AS i, CAST(z.dim + 5 * k.k AS INTEGER) AS j, -CAST(sum(r.r * z.v) AS DOUBLE) / count(*) AS value FROM r, range(2) k(k) JOIN se z ON true WHERE z.idx = r.idx - 1 - k.k GROUP BY 1, 2")
def _(spark, d):
    theta = np.hstack([np.eye(5), -np.eye(5)])
    _, g, _ = likelihood.pass_over(blocks_e(spark, d, 48, 2, 0), [theta], np.eye(5), 2, 2)[0]
    return spark.createDataFrame([(i, j, float(g[i, j])) for i in range(5) for j in range(10)], "i int, j int, value double")


@query("optimisers")
def _(spark, d):
    """Gap to the optimum by pass of gradient descent under three step rules, stochastic steps, and one Newton solve."""
    gram, pi = _gram2(spark, d), np.eye(2)
    best = likelihood.gram_gradient(*gram, likelihood.newton(*gram), pi)[0]
    small = 0.2 * likelihood.spectral_step(pi, likelihood.stacked_cov(*gram))[0]
    rows = [("newton", 0.0, "iter=1")]
    for name, how in (("spectral", {}), ("fixed", {"fixed": small}), ("backtracking", {"step": "backtracking"})):
        trace = likelihood.gradient_fit(gram, 2, 1, pi, most=60, **how)[1]
        rows += [(name, max(0.0, f - best), f"iter={k}") for k, f, *_ in trace if k in (0, 1, 2, 5, 10, 20, 40, 59)]
    b = _blocks2(spark, d).persist()
    theta = np.zeros((2, 2))
    for k in range(6):  # the objective of stochastic iterates on all data, not on their sample
        rows.append(("stochastic", max(0.0, likelihood.gram_gradient(*gram, theta, pi)[0] - best), f"iter={k}"))
        _, g, _ = likelihood.pass_over(b, [theta], pi, 1, 1, sample=(k, 0.3))[0]
        theta = theta - 0.4 * small / (1 + 0.2 * k) * g
    b.unpersist()
    return measures.table(spark, rows)


@query("alternate_banded")
def _(spark, d):
    """Alternating fits where the precision matters: coefficients held to a band of width 1."""
    w = grid.to_wide(series.lineitem(spark, d), 6)
    mu = np.array([r.mean for r in sorted(moments.mean(series.lineitem(spark, d)).collect(), key=lambda r: r.dim)])
    g = moments.gram_matrix(moments.lag_gram(lay.time_blocks(moments.center(w, mu), 256, 1, 0, bounds=(0, N_L - 1)), 1, 1), 1, 6)
    _, _, seen = likelihood.alternate(*g, mask=likelihood.band_mask(6, 1, 1))
    return spark.createDataFrame([(k, float(f)) for k, f in enumerate(seen)], "iter int, objective double")


@query("banded_fit_shared_sums")
def _(spark, d):
    long, n = _suppliers(spark, d)
    w = banded.fit_shared_sums(long, N_L, n, 1, max(2, n // 25))
    return spark.createDataFrame([(k - 1, float(x)) for k, x in enumerate(w)], "shift int, value double")


# ---- graphs

def _hop_sql(k):
    return f"p AS (SELECT a, b, min(hop) AS hop FROM (WITH RECURSIVE r AS (SELECT CAST(n_nationkey AS INTEGER) AS a, CAST(n_nationkey AS INTEGER) AS b, 0 AS hop FROM nation UNION SELECT r.a, ed.dst, r.hop + 1 FROM r JOIN ed ON ed.src = r.b WHERE r.hop < {k}) SELECT * FROM r) GROUP BY 1, 2)"


for _k in (2, 3):

    @query(f"graph_autocov_k{_k}", f"WITH {series.SQL_N}, {_hop_sql(_k)} SELECT CAST(h.h AS INTEGER) AS h, CAST(hop AS INTEGER) AS hop, count(*) AS n, CAST(sum(x.x * y.x) AS BIGINT) AS s FROM range(2) h(h) JOIN p ON true JOIN sn x ON x.v = p.a JOIN sn y ON y.v = p.b AND y.idx = x.idx + h.h GROUP BY 1, 2")
    def _(spark, d, k=_k):
        e, g = _graph_blocks(spark, d, k)
        cross = graph.cross_blocks(series.nation_days(spark, d), 400, 1, g, bounds=(0, N_O - 1))
        return graph.pair_sums(cross, graph.block_edges(e, g), 1, k, k)


HOPS = """WITH RECURSIVE {e}, b AS (SELECT src AS v, dst AS w FROM ed UNION SELECT dst, src FROM ed),
 r AS (SELECT {own} AS gblk, v, 0 AS hop FROM (SELECT DISTINCT src AS v FROM ed) UNION SELECT r.gblk, b.w, r.hop + 1 FROM r JOIN b ON b.v = r.v WHERE r.hop < {k})
 SELECT gblk, v, CAST(min(hop) AS INTEGER) AS hop, min(hop) = 0 AS is_core FROM r GROUP BY gblk, v"""
for _k in (1, 3):

    @query(f"hop_membership_k{_k}", HOPS.format(e=series.SQL_N, own="CAST(v // 5 AS INTEGER)", k=_k))
    def _(spark, d, k=_k):
        return _graph_blocks(spark, d, k)[1]


RING = "ed AS (SELECT CAST(s.k AS INTEGER) AS src, CAST((s.k + o.o) % m.m AS INTEGER) AS dst FROM (SELECT s_suppkey - (SELECT min(s_suppkey) FROM supplier) AS k FROM supplier) s, (SELECT count(*) AS m FROM supplier) m, (VALUES (1), (7)) o(o))"


def supplier_ring(spark, d):
    """Suppliers numbered from 0, each with edges to the next and the seventh after it."""
    s = series.read(spark, d, "supplier", ["s_suppkey"])
    lo, m = s.agg(F.min("s_suppkey"), F.count(F.lit(1))).head()
    k = s.select((F.col("s_suppkey") - lo).cast("int").alias("src"))
    return k.select("src", F.explode(F.array(F.lit(1), F.lit(7))).alias("o")).select("src", F.pmod(F.col("src") + F.col("o"), F.lit(m)).cast("int").alias("dst"))


@query("hop_membership_suppliers", HOPS.format(e=RING, own="CAST(v // 10 AS INTEGER)", k=2))
def _(spark, d):
    e = supplier_ring(spark, d)
    own = e.select(F.col("src").alias("v")).distinct().withColumn("gblk", F.expr("CAST(v div 10 AS INT)"))
    return graph.hop_blocks(e, own.select("v", "gblk"), 2)


@query("cross_membership", f"""WITH RECURSIVE {series.SQL_N}, b AS (SELECT src AS v, dst AS w FROM ed UNION SELECT dst, src FROM ed), m AS (SELECT DISTINCT CAST(n_nationkey // 5 AS INTEGER) AS gblk, CAST(n_nationkey AS INTEGER) AS v, true AS g_core FROM nation
 UNION SELECT CAST(n_nationkey // 5 AS INTEGER), b.w, false FROM nation JOIN b ON b.v = n_nationkey WHERE b.w // 5 <> n_nationkey // 5)
 SELECT CAST(t.t AS BIGINT) AS tblk, m.gblk, count(*) AS stored, count(*) FILTER (idx // 400 = t.t AND g_core) AS core, CAST(sum(x) AS BIGINT) AS total FROM range(7) t(t), m JOIN sn ON sn.v = m.v WHERE idx >= 400 * t.t - 1 AND idx < 400 * (t.t + 1) + 1 GROUP BY 1, 2""")
def _(spark, d):
    """Stored and core states of every (time, graph) block, halos included."""
    _, g = _graph_blocks(spark, d, 1)
    cross = graph.cross_blocks(series.nation_days(spark, d), 400, 1, g, bounds=(0, N_O - 1))
    return cross.groupBy("tblk", "gblk").agg(F.count(F.lit(1)).alias("stored"), F.count_if(F.col("t_core") & F.col("g_core")).alias("core"), F.sum("x").alias("total"))


NET = f"WITH {series.SQL_N}, y AS (SELECT a.v, a.idx, a.x, 0.5 * b.x + 0.125 * (SELECT sum(q.x) FROM ed JOIN sn q ON q.v = ed.src WHERE ed.dst = a.v AND q.idx = a.idx - 1) AS y FROM sn a JOIN sn b ON b.v = a.v AND b.idx = a.idx - 1)"


def _network(spark, d):
    e, g = _graph_blocks(spark, d, 1)
    return graph.cross_blocks(series.nation_days(spark, d), 400, 1, g, bounds=(0, N_O - 1)), graph.block_edges(e, g)


@query("network_forecast", NET + " SELECT v, idx, CAST(y AS DOUBLE) AS y FROM y")
def _(spark, d):
    return graph.dbn(*_network(spark, d), lambda own, parents: 0.5 * own + 0.125 * parents.sum(), (1, 1))


@query("network_residuals", NET + " SELECT v, count(*) AS n, round(sum((x - y) * (x - y)), 4) AS ss FROM y GROUP BY v")
def _(spark, d):
    r = graph.retrospective(*_network(spark, d), lambda own, parents: 0.5 * own + 0.125 * parents.sum(), (1, 1))
    return r.groupBy("v").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.col("r") * F.col("r")), 4).alias("ss"))


def _steps_sql(steps):
    one = "s{b} AS (SELECT s.v, CAST(s.n - (SELECT coalesce(sum(greatest(0, least(s.n // od.k, (c.cap - t.n) // ig.k))), 0) FROM ed JOIN s{a} t ON t.v = ed.dst JOIN cap c ON c.v = ed.dst JOIN od ON od.src = ed.src JOIN ig ON ig.dst = ed.dst WHERE ed.src = s.v) + (SELECT coalesce(sum(greatest(0, least(t.n // od.k, (c.cap - s.n) // ig.k))), 0) FROM ed JOIN s{a} t ON t.v = ed.src JOIN cap c ON c.v = ed.dst JOIN od ON od.src = ed.src JOIN ig ON ig.dst = ed.dst WHERE ed.dst = s.v) AS BIGINT) AS n FROM s{a} s)"
    ctes = ", ".join(one.format(a=k, b=k + 1) for k in range(steps))
    rows = " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS step, v, n FROM s{k}" for k in range(steps + 1))
    return f"WITH {series.SQL_N}, cap AS (SELECT v, 2 * max(x) AS cap FROM sn GROUP BY v), od AS (SELECT src, count(*) AS k FROM ed GROUP BY src), ig AS (SELECT dst, count(*) AS k FROM ed GROUP BY dst), s0 AS (SELECT v, CAST(max(x) AS BIGINT) AS n FROM sn GROUP BY v), {ctes} {rows}"


def _traffic(spark, d):
    s = series.nation_days(spark, d).groupBy("v").agg(F.max("x").alias("n"))
    return s, series.nation_edges(spark, d), s.select("v", (2 * F.col("n")).alias("cap"))


@query("traffic_simulate_blocks", _steps_sql(5))
def _(spark, d):
    """Five steps from every vertex's busiest day, two at a time inside blocks with halos of two hops."""
    s, e, cap = _traffic(spark, d)
    owners = graph.assign(e.select(F.col("src").alias("v")).distinct(), "range", 5)
    return graph.simulate_blocks(s, e, cap, owners, 5, 2, folder(spark))


# ---- layouts and measures

@query("window_bias", COV_E + f""", m AS (SELECT dim, avg(v) AS m FROM se GROUP BY dim), z AS (SELECT idx, se.dim, v - m AS z FROM se JOIN m USING (dim)),
 w AS (SELECT h.l AS lag, a.dim AS i, b.dim AS j, sum(a.z * b.z) / ({N_E} - 5) AS value FROM range(3) h(l) JOIN z a ON a.idx BETWEEN 2 AND {N_E - 3} JOIN z b ON b.idx = a.idx + h.l GROUP BY 1, 2, 3)
 SELECT cv.lag, cv.i, cv.j, round(w.value - c / (n - 1), 6) AS bias FROM cv JOIN w ON w.lag = cv.lag AND w.i = cv.i AND w.j = cv.j""")
def _(spark, d):
    """Window form less exact form, by entry."""
    m = moments_e(spark, d, 2)
    g, exact = moments.window_form(blocks_e(spark, d, 48, 2, 2), 2, N_E, m.mean, 2), m.autocov()
    return spark.createDataFrame([(h, i, j, round(float(g[h + 2, i, j] - exact[h, i, j]), 6)) for h in range(3) for i in range(5) for j in range(5)], "lag int, i int, j int, bias double")


@query("layout_memory", f"WITH {series.SQL_E} SELECT CAST(b AS BIGINT) AS block, count(*) AS stored, count(*) FILTER (i // 48 = b) AS core, CAST(count(*) * 5 * 8 AS BIGINT) AS bytes FROM range(15) x(b), range({N_E}) y(i) WHERE i >= 48 * b - 3 AND i < 48 * b + 51 GROUP BY 1")
def _(spark, d):
    """Bytes of observations that each block holds."""
    b = blocks_e(spark, d)
    return b.groupBy("block").agg(F.count(F.lit(1)).alias("stored"), F.count_if("is_core").alias("core"), F.sum(F.size("x") * 8).cast("bigint").alias("bytes"))


@query("layout_comparison", f"WITH {series.SQL_E}, s AS (SELECT CAST(sum(a.v * b.v) AS BIGINT) AS total FROM range(4) h(l) JOIN se a ON true JOIN se b ON b.idx = a.idx + h.l) SELECT layout, total FROM s, (VALUES ('overlap'), ('by_series'), ('self_join')) l(layout)")
def _(spark, d):
    """The sum of all lag products under every layout."""
    long = series.events(spark, d)
    ways = {"overlap": moments.lag_products(blocks_e(spark, d), 3, 3), "by_series": baselines.by_series(long, 3), "self_join": baselines.self_join(long, 3)}
    parts = [x.agg(F.sum("s").cast("bigint").alias("total")).select(F.lit(k).alias("layout"), "total") for k, x in ways.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("layout_exchanges")
def _(spark, d):
    """Exchanges, those of observations, and seconds of each layout on events and on suppliers, over kept inputs."""
    rows = []
    sup, n = _suppliers(spark, d)
    cases = {"events": (series.events(spark, d), 5, 48, N_E), "lineitem": (series.lineitem(spark, d), 6, 256, N_L)}
    for name, (long, dim, size, steps) in cases.items():
        b = lay.time_blocks(grid.to_wide(long, dim), size, 3, 3, bounds=(0, steps - 1)).persist()
        kept = long.persist()
        b.count(), kept.count()
        ways = {"overlap": moments.lag_products(b, 3, 3), "by_series": baselines.by_series(kept, 3), "self_join": baselines.self_join(kept, 3), "global_window": baselines.global_window(kept, 3)}
        for way, x in ways.items():
            t = time.perf_counter()
            x.write.format("noop").mode("overwrite").save()
            rows += [(f"{way}_seconds", time.perf_counter() - t, name), (f"{way}_exchanges", float(audit.exchanges(x)), name), (f"{way}_observation_exchanges", float(audit.observation_exchanges(x)), name)]
        b.unpersist(), kept.unpersist()
    return measures.table(spark, rows)


@query("solve_cost_by_d")
def _(spark, d):
    """Seconds of the dense and of the recursive Yule-Walker solve (order 2) by dimension, on supplier counts, and their difference."""
    long, n = _suppliers(spark, d)
    rows = []
    for k in [x for x in (10, 30, 100, 200) if x <= n]:
        wide = grid.to_wide(grid.dense(long.where(f"dim < {k}"), N_L, k), k)
        b = lay.time_blocks(wide, 512, 0, 2, bounds=(0, N_L - 1))
        g = moments.Moments.collect(moments.lag_products(b, 2, 2)).autocov("n")
        g = g + 1e-9 * np.array([np.eye(k), np.zeros((k, k)), np.zeros((k, k))])
        got = {}
        for solver in ("dense", "block_levinson"):
            t = time.perf_counter()
            got[solver] = fit.yule_walker(g, 2, solver)
            rows.append((f"seconds_{solver}", time.perf_counter() - t, f"d={k}"))
        gap = max(float(np.abs(a - c).max()) for a, c in zip(got["dense"].a, got["block_levinson"].a))
        rows.append(("difference", gap, f"d={k}"))
    return measures.table(spark, rows)


@query("estimator_variances")
def _(spark, d):
    """Variance over all stretches of n line items of mean, covariance, correlation and partial correlation, by n; slopes near -1."""
    rows, names = [], ("mean", "covariance", "correlation", "partial")
    seen = {k: [] for k in names}
    every = series.quantities(spark, d)
    for n in (16, 64, 256):
        x = every.withColumn("s", F.expr(f"t div {n}"))
        w = Window.partitionBy("s").orderBy("t")
        y = x.withColumn("e1", F.lag("e", 1).over(w)).withColumn("e2", F.lag("e", 2).over(w))
        g = y.groupBy("s").agg(F.count(F.lit(1)).alias("n"), F.avg("e").alias("mean"), F.avg(F.col("e") * F.col("e")).alias("g0"), F.avg(F.col("e") * F.col("e1")).alias("g1"), F.avg(F.col("e") * F.col("e2")).alias("g2"))
        g = g.where(F.col("n") == n).select("mean", F.col("g1").alias("covariance"), (F.col("g1") / F.col("g0")).alias("correlation"), ((F.col("g2") * F.col("g0") - F.col("g1") ** 2) / (F.col("g0") ** 2 - F.col("g1") ** 2)).alias("partial"))
        got = g.agg(*[F.var_samp(k).alias(k) for k in names]).head()
        for k in names:
            seen[k].append((n, float(got[k])))
            rows.append((f"variance_{k}", float(got[k]), f"N={n}"))
    return measures.table(spark, rows + [("slope", measures.slope(*zip(*v)), k) for k, v in seen.items()])
