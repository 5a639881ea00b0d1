"""Driver algebra against closed forms and known truth."""

import numpy as np
import pytest

from halo.functions import linalg
from halo.models import fit, likelihood, moments
from halo.models.process import Process, SingularNoise, simulate
from halo.models.predict import arma_serial

A2 = np.array([[0.5, 0.3], [-0.2, 0.4]])
S2 = np.array([[1.0, 0.4], [0.4, 2.0]])


def exact_ma1(b=0.5):
    return np.array([[[1 + b * b]], [[b]], *[[[0.0]]] * 10])


def test_yule_walker_returns_the_model_and_variance_uses_the_right_lag():
    g = Process(a=[A2], sigma=S2).theoretical_autocov(3)
    for kw in ({}, {"orientation": "row"}, {"solver": "block_levinson"}):
        m = fit.yule_walker(g, 1, **kw)
        assert np.allclose(m.a[0], A2) and np.allclose(m.sigma, S2)
    wrong = g[0] - A2 @ g[1].T
    assert not np.allclose(wrong, wrong.T)


def test_solvers_agree_and_pacf_is_last_block():
    g = Process(a=[A2, 0.1 * np.eye(2)], sigma=S2).theoretical_autocov(4)
    dense, (rec, s, last) = linalg.solve_projection(g, 3), linalg.block_levinson(g, 3)
    assert all(np.allclose(x, y) for x, y in zip(dense, rec))
    assert np.allclose(moments.pacf(g, 3, "solve")[2], last[2]) and np.allclose(last[2], 0)
    one = Process(a=[np.array([[0.6]]), np.array([[0.2]])], sigma=np.eye(1)).theoretical_autocov(3)
    assert np.allclose(linalg.levinson(one, 2)[0][1], 0.2)


@pytest.mark.parametrize("depth,b,s", [(1, 0.4, 1.05), (2, 0.47619, 1.0119), (3, 0.49412, 1.00294), (6, 0.49991, None)])
def test_innovations_converge_with_depth(depth, b, s):
    m = fit.ma(exact_ma1(), 1, depth)
    assert abs(m.b[0][0, 0] - b) < 1e-4 and (s is None or abs(m.sigma[0, 0] - s) < 1e-4)


@pytest.mark.parametrize("depth,a,b", [(2, 0.47038, 0.49406), (4, 0.59717, 0.40194), (8, 0.6, 0.4)])
def test_arma_by_innovations(depth, a, b):
    g = Process(a=[np.array([[0.6]])], b=[np.array([[0.4]])], sigma=np.eye(1)).theoretical_autocov(12)
    m = fit.arma(g, 1, 1, depth)
    assert abs(m.a[0][0, 0] - a) < 1e-3 and abs(m.b[0][0, 0] - b) < 1e-3


def test_pure_cases_of_arma():
    g = Process(a=[A2], sigma=S2).theoretical_autocov(8)
    assert np.allclose(fit.arma(g, 1, 0, 6).a[0], A2, atol=1e-2)
    assert np.allclose(fit.arma(exact_ma1(), 0, 1, 6).b[0], fit.ma(exact_ma1(), 1, 6).b[0])


def test_roots_weights_and_companion():
    m = Process(a=[np.array([[0.5]])], b=[np.array([[0.4]])], sigma=np.eye(1))
    assert m.is_causal() and m.is_invertible() and not Process(b=[np.array([[-1.0]])], sigma=np.eye(1)).is_invertible()
    assert np.allclose(m.psi(3)[3], 0.9 * 0.25) and np.allclose(m.pi(2)[1], -0.9 * 0.4)
    with pytest.raises(SingularNoise):
        m.companion_likelihood()
    with pytest.raises(ValueError):
        Process(b=[np.array([[-1.0]])], sigma=np.eye(1)).warmup()
    p = linalg.lyapunov(A2, S2)
    assert np.allclose(p, A2 @ p @ A2.T + S2)


def test_negative_lag_is_the_transpose():
    g = Process(a=[A2], sigma=S2).theoretical_autocov(2)
    assert np.allclose(moments.at(g, -1), g[1].T) and not np.allclose(g[1], g[1].T)


def test_gradients_match_finite_differences_and_descent_is_monotone():
    rng = np.random.default_rng(1)
    x = simulate(rng.normal(size=(400, 2)), Process(a=[A2], sigma=S2))
    n = len(x) - 1
    m = np.array([[x[1:].T @ x[1:], x[1:].T @ x[:-1]], [x[:-1].T @ x[1:], x[:-1].T @ x[:-1]]])
    pi, th = np.linalg.inv(S2), rng.normal(size=(2, 2)) * 0.1
    f, g = likelihood.gram_gradient(m, n, th, pi)
    for k in np.ndindex(2, 2):
        e = np.zeros((2, 2))
        e[k] = 1e-6
        up, down = likelihood.gram_gradient(m, n, th + e, pi)[0], likelihood.gram_gradient(m, n, th - e, pi)[0]
        assert abs((up - down) / 2e-6 - g[k]) < 1e-5
    for family in ("gaussian", "smooth_robust"):
        r = rng.normal(size=(1, 2))
        v, w = likelihood.loss(family, r, pi)
        for j in range(2):
            e = np.zeros((1, 2))
            e[0, j] = 1e-6
            assert abs((likelihood.loss(family, r + e, pi)[0] - likelihood.loss(family, r - e, pi)[0])[0] / 2e-6 - w[0, j]) < 1e-5
    best = likelihood.newton(m, n)
    got, trace = likelihood.gradient_fit((m, n), 2, 1, np.eye(2))
    assert np.allclose(got, best, atol=1e-6) and all(a[1] >= b[1] - 1e-12 for a, b in zip(trace, trace[1:]))
    _, contraction = likelihood.spectral_step(np.eye(2), likelihood.stacked_cov(m, n))
    assert trace[5][2] <= trace[4][2] * (contraction + 1e-9)
    assert np.allclose(likelihood.alternate(m, n)[0], best)


def test_orders_and_serial_forecast():
    rng = np.random.default_rng(2)
    x = simulate(rng.normal(size=(4000, 1)), Process(a=[np.array([[0.6]])], sigma=np.eye(1)))
    g = np.array([(x[: len(x) - h] - x.mean()).T @ (x[h:] - x.mean()) / len(x) for h in range(8)])
    assert fit.ar_order(moments.pacf(g, 5), len(x)) >= 1 and fit.search(g, len(x), 3, 0, "bic")[0][0] == 1
    m = Process(a=[np.array([[0.6]])], b=[np.array([[0.3]])], sigma=np.eye(1))
    e = rng.normal(size=(300, 1))
    f, got = arma_serial(simulate(e, m), m)
    assert np.allclose(got[50:], e[50:], atol=1e-6)
    assert sorted(linalg.reverse_breadth_first([{1}, {0, 2}, {1}])) == [0, 1, 2]


def ar1_by_hand(x):
    """Conditional and unconditional coefficient of a centred series and the likelihood, without Gram matrices or blocks."""

    def value(a):
        r = x[1:] - a * x[:-1]
        s = r @ r / len(r)
        g = s / (1 - a * a)
        return -0.5 * len(r) * (np.log(s) + 1 + np.log(2 * np.pi)) - 0.5 * (np.log(g) + x[0] ** 2 / g + np.log(2 * np.pi))

    lo, hi = -0.99, 0.99
    for _ in range(200):
        a, b = lo + (hi - lo) / 3, hi - (hi - lo) / 3
        lo, hi = (a, hi) if value(a) < value(b) else (lo, b)
    return x[1:] @ x[:-1] / (x[:-1] @ x[:-1]), (lo + hi) / 2, value((lo + hi) / 2)


def test_unconditional_fit_uses_every_day(spark, tiny):
    from halo import registry, series

    x = np.array([r.v for r in series.orders(spark, tiny, 0).orderBy("idx").collect()], float)
    got = {r.name: r.value for r in registry.queries()["unconditional_fit"](spark, tiny).collect()}
    cond, uncond, ll = ar1_by_hand(x - x.mean())
    assert len(x) == series.N_O and abs(got["conditional"] - cond) < 1e-9
    assert abs(got["unconditional"] - uncond) < 1e-5 and abs(got["loglik"] - ll) < 1e-4


def test_unconditional_fit_of_a_short_series(spark, tiny):
    from halo import series

    e = np.array([r.v for r in series.events(spark, tiny).where("dim = 0 and idx < 70").orderBy("idx").collect()], float)
    x = np.array([sum(e[t - k] / 2**k for k in range(21)) for t in range(20, 70)])
    x -= x.mean()
    y, z = x[1:], x[:-1]
    m = np.array([[y @ y, y @ z], [z @ y, z @ z]]).reshape(2, 2, 1, 1)
    model, ll = likelihood.unconditional_fit(m, 49, x[:1, None])
    cond, uncond, want = ar1_by_hand(x)
    assert len(x) == 50 and abs(model.a[0][0, 0] - uncond) < 1e-4 and abs(ll - want) < 1e-6
    assert abs(cond - uncond) > 1e-5 and abs(likelihood.newton(m, 49)[0, 0] - cond) < 1e-9


def test_diagonals_of_wide_series_need_no_wide_rows(spark):
    """A dimension far out costs nothing; a row off the grid names its dimension only."""
    rows = [(0, 3, 2), (2, 3, 1), (1, 40_000_000, 5), (9, 7, 4)]
    got = {(r.lag, r.i): r.value for r in moments.diagonal_covariances(spark.createDataFrame(rows, "idx bigint, dim int, v bigint"), 4, 1).collect()}
    x = {3: [2, 0, 1, 0], 40_000_000: [0, 5, 0, 0], 7: [0, 0, 0, 0]}
    for k, v in x.items():
        z = np.array(v) - np.mean(v)
        assert np.isclose(got[0, k], z @ z / 3) and np.isclose(got[1, k], z[:-1] @ z[1:] / 2)
    assert len(got) == 6


def test_pairs_of_slabs_need_no_wide_rows(spark):
    """All pairs over several slabs and a dimension far out, against numpy."""
    rng = np.random.default_rng(5)
    dims, x = [0, 1, 5, 9, 40_000_000], rng.integers(0, 4, (30, 5))
    rows = [(t, d, int(x[t, k])) for t in range(30) for k, d in enumerate(dims) if x[t, k]]
    root = f"{spark.conf.get('spark.checkpoint.dir')}/slabs-test"
    got = {(r.lag, r.i, r.j): r.value for r in moments.wide_covariances(spark.createDataFrame(rows, "idx bigint, dim int, v bigint"), 30, 1, root, 4).collect()}
    z = x - x.mean(axis=0)
    for h in (0, 1):
        c = z[: 30 - h].T @ z[h:] / (29 - h)
        assert all(np.isclose(got[h, p, q], c[a, b]) for a, p in enumerate(dims) for b, q in enumerate(dims))
    assert len(got) == 50


def test_slabs_are_shuffled_once_not_once_a_pair(spark):
    """Twelve slabs: the shuffles carry cells and slabs, never the 144 pairs; entries are rounded as Spark rounds."""
    from pyspark.sql import functions as F

    x = np.random.default_rng(6).integers(0, 4, (30, 24))
    rows = [(t, 100 * d, int(x[t, d])) for t in range(30) for d in range(24)]
    root = f"{spark.conf.get('spark.checkpoint.dir')}/slabs-once"
    long = spark.createDataFrame(rows, "idx bigint, dim int, v bigint")
    df = moments.wide_covariances(long, 30, 1, root, 200, digits=2)
    got = {(r.lag, r.i, r.j): r.value for r in df.collect()}
    plain = moments.wide_covariances(long, 30, 1, f"{root}-plain", 200).withColumn("value", F.round("value", 2))
    assert len(got) == 2 * 24 * 24 and got == {(r.lag, r.i, r.j): r.value for r in plain.collect()}
    written, plans = [], [df._jdf.queryExecution().executedPlan()]
    while plans:
        p = plans.pop()
        if p.nodeName() == "AdaptiveSparkPlan":
            p = p.executedPlan()
        while p.nodeName().endswith("QueryStage"):
            p = p.plan()
        if p.metrics().contains("shuffleRecordsWritten"):
            written.append(p.metrics().apply("shuffleRecordsWritten").value())
        plans += [p.children().apply(k) for k in range(p.children().size())]
    assert written and sum(written) <= 2 * 12


def test_slabs_keep_counts_of_every_size(spark):
    """Counts from one to four bytes, in long and short slabs, a slab with no cell on the grid."""
    x = {0: [1, 0, 127], 1: [-128, 5, 2], 4: [128, 0, 3], 8: [40_000, 1, 0], 12: [3_000_000, 1, 9], 16: [0, 0, 0]}
    rows = [(t, d, v) for d, c in x.items() for t, v in enumerate(c) if v] + [(99, 16, 7)]
    root = f"{spark.conf.get('spark.checkpoint.dir')}/slabs-sizes"
    got = {(r.lag, r.i, r.j): r.value for r in moments.wide_covariances(spark.createDataFrame(rows, "idx bigint, dim int, v bigint"), 3, 0, root, 4).collect()}
    want = np.cov(np.array(list(x.values()), float))
    assert len(got) == 36 and all(np.isclose(got[0, p, q], want[a, b]) for a, p in enumerate(x) for b, q in enumerate(x))


def test_rounding_is_that_of_spark(spark):
    """Ties of the shortest decimal go away from zero, large and small numbers stay, no negative zero."""
    from pyspark.sql import functions as F

    rng = np.random.default_rng(7)
    x = [0.0, -0.0, 5e-9, -5e-9, 1.5e-8, 0.000000025, -0.123456785, 0.123456775, 2.675, 1.005, -1e-12, 1e17, 4.6e7 + 0.1, 9007199254740993.0, 1e300, *rng.normal(0, 30, 300), *(rng.integers(-999, 999, 300) / 2e3)]
    for digits in (8, 2):
        want = [r.y for r in spark.createDataFrame([(k, float(v)) for k, v in enumerate(x)], "k int, x double").select("k", F.round("x", digits).alias("y")).orderBy("k").collect()]
        got = moments.rounded(np.array(x), digits)
        assert got.tolist() == want and not np.signbit(got[np.array(x) == 0]).any()


def test_lag_products_beyond_doubles_are_exact(spark):
    """Sums of products above 2^53 to the last digit, over several blocks."""
    from halo.operators import blocks as lay

    v = [100_000_007 + 3 * t for t in range(40)]
    b = lay.time_blocks(spark.createDataFrame([(t, [float(x)]) for t, x in enumerate(v)], "idx bigint, x array<double>"), 16, 0, 2)
    got = {r.lag: (r.n, r.s) for r in moments.whole_lag_products(b, 2, 2).collect()}
    assert got == {h: (40 - h, sum(p * q for p, q in zip(v, v[h:]))) for h in range(3)} and got[0][1] > 2**53


def test_conjugate_gradient_ends_where_counts_are_large():
    """Means far above the spread: 80 spectral steps stay short of the optimum, conjugate ones reach it."""
    rng = np.random.default_rng(3)
    x = rng.poisson(1700, (700, 2)).astype(float)
    z, y = x[:-1], x[1:]
    m = np.array([[y.T @ y, y.T @ z], [z.T @ y, z.T @ z]])
    best = np.linalg.solve(z.T @ z, z.T @ y).T
    short, _ = likelihood.gradient_fit((m, 699), 2, 1, np.eye(2), tol=1e-7, most=80)
    theta, trace = likelihood.gradient_fit((m, 699), 2, 1, np.eye(2), "conjugate", tol=1e-7, most=80)
    assert np.abs(short - best).max() > 1e-3 and np.abs(theta - best).max() < 1e-8 and len(trace) < 20
