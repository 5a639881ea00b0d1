"""Layout invariants: ownership, halos, block results equal to unblocked ones, no exchange after the layout."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from halo import baselines, registry
from halo.models import fit, moments, predict
from halo.models.process import Process
from halo.operators import blocks as lay
from halo.operators import difference, graph, grid, irregular, kernels
from halo.plans import audit


def wide(spark, n, d=2, first=0):
    return spark.range(first, first + n).select(F.col("id").alias("idx"), F.array(*[((F.col("id") * (7 + k) + k) % 11).cast("double") for k in range(d)]).alias("x"))


def matrix(n, d=2, first=0):
    i = np.arange(first, first + n)
    return np.stack([(i * (7 + k) + k) % 11 for k in range(d)], 1).astype(float)


@pytest.mark.parametrize("n,size,left,right,first", [(50, 8, 3, 3, 0), (50, 2, 5, 5, -7), (5, 100, 2, 2, 3), (1, 4, 1, 1, 0)])
def test_each_datum_is_core_once_and_halos_are_exact(spark, n, size, left, right, first):
    rows = lay.time_blocks(wide(spark, n, 1, first), size, left, right).select("block", "idx", "is_core").collect()
    core = sorted(r.idx for r in rows if r.is_core)
    assert core == list(range(first, first + n))
    for b in {r.block for r in rows}:
        want = {i for i in range(first, first + n) if b * size - left <= i < (b + 1) * size + right}
        assert {r.idx for r in rows if r.block == b} == want


@pytest.mark.parametrize("size,halo", [(8, 3), (3, 5), (100, 3)])
@pytest.mark.parametrize("backend", ["arrow", "sql"])
def test_lag_products_do_not_depend_on_blocks(spark, size, halo, backend):
    x = matrix(60)
    m = moments.Moments.collect(moments.lag_products(lay.time_blocks(wide(spark, 60).orderBy(F.rand(3)), size, 0, halo), 3, halo, backend=backend))
    assert np.array_equal(m.p, baselines.serial(x, 3))
    z = x - x.mean(axis=0)
    assert np.allclose(m.autocov("n"), [z[: 60 - h].T @ z[h:] / 60 for h in range(4)])
    assert np.allclose(np.diag(moments.acf(m.autocov("n"))[0]), 1)
    assert np.array_equal(m.merge(m).merge(m, -1).p, m.p)


def test_a_short_halo_fails_loudly_and_would_lose_pairs(spark):
    b = lay.time_blocks(wide(spark, 40), 8, 0, 2)
    with pytest.raises(lay.HaloTooShort):
        moments.lag_products(b, 3, 2)
    lost = moments.Moments.collect(moments.lag_products(b, 3, 3))
    assert lost.n[3] < 37


def test_no_exchange_of_observations_after_the_layout(spark):
    b = lay.time_blocks(wide(spark, 100), 16, 3, 3).persist()
    b.count()
    assert audit.observation_exchanges(moments.lag_products(b, 3, 3)) == 0
    b.unpersist()


def test_edge_inputs(spark):
    empty = lay.time_blocks(wide(spark, 0), 8, 1, 1)
    assert empty.count() == 0
    constant = spark.range(20).select(F.col("id").alias("idx"), F.array(F.lit(2.0)).alias("x"))
    g = moments.Moments.collect(moments.lag_products(lay.time_blocks(constant, 8, 0, 1), 1, 1)).autocov("n")
    assert np.isnan(moments.acf(g)[0, 0, 0]) and g[0, 0, 0] == 0


def test_difference_and_inverse(spark):
    s = wide(spark, 50, 1).select("idx", F.col("x")[0].cast("bigint").alias("v"))
    b = lay.time_blocks(s, 8, 3, 3)
    d = difference.diff(b, 1).withColumnRenamed("y", "v")
    back = {r.idx: r.y for r in difference.integrate(lay.time_blocks(d, 8, 0, 0), s.where("idx = 0").head().v).collect()}
    assert back == {r.idx: r.v for r in s.where("idx > 0").collect()}
    one = {r.idx: r.y for r in difference.frac(b, 1.0, 2).collect()}
    assert one == {r.idx + 1: float(r.v) for r in d.collect() if r.idx >= 1}
    assert difference.frac_weights(0.0, 3) == [1.0, 0.0, 0.0, 0.0]


def test_block_forecast_error_decays(spark):
    m = Process(a=[np.array([[0.5]])], b=[np.array([[0.6]])], sigma=np.eye(1))
    x = matrix(120, 1)
    want, _ = predict.arma_serial(x, m)
    errors = []
    for w in (4, 12, 24):
        got = predict.arma_blocks(lay.time_blocks(wide(spark, 120, 1), 32, w + 1, 0), m, np.zeros(1), w, w + 1).collect()
        errors.append(max(abs(r.forecast[0] - want[r.idx - 1, 0]) for r in got if r.idx >= 64))
    assert errors[1] < errors[0] and errors[2] < 1e-3
    with pytest.raises(ValueError):
        predict.arma_blocks(lay.time_blocks(wide(spark, 9, 1), 4, 2, 0), Process(b=[np.array([[-1.0]])], sigma=np.eye(1)), np.zeros(1), 1, 2)


def test_centres_by_every_method_agree(spark):
    data = spark.range(500).select((F.col("id") * F.col("id") * 37 % 100_003).alias("ts_us"), (F.col("id") % 13).alias("v"))
    b = lay.time_blocks(data, 10_000, 2_000, 2_000, on="ts_us")
    c = spark.range(60).select((F.col("id") * 1_500).alias("c"))
    got = [sorted(map(tuple, irregular.at_centres(b, c, 2_000, 10_000, method=m).collect())) for m in ("range", "search", "index", "scan")]
    assert got[0] == got[1] == got[2] == got[3] and len(got[0]) == 60


def test_graph_halos_and_conservation(spark, tiny):
    e, g = registry._graph_blocks(spark, tiny, 2)
    assert g.where("is_core").count() == 25 and g.count() > registry._graph_blocks(spark, tiny, 1)[1].count()
    s = spark.createDataFrame([(0, v, v % 4) for v in range(25)], "step int, v int, n bigint")
    cap = spark.createDataFrame([(v, 5) for v in range(25)], "v int, cap bigint")
    after = graph.traffic_step(s, e, cap, ["step"])
    assert after.agg(F.sum("n")).head()[0] == s.agg(F.sum("n")).head()[0] and after.where("n < 0 or n > 5").isEmpty()
    with pytest.raises(ValueError):
        graph.check_step(1.0, 1.0, 2.0)


def test_graph_kernels_reach_k_hops(spark, tiny):
    e, g = registry._graph_blocks(spark, tiny, 2)
    days = registry.series.nation_days(spark, tiny).where("idx < 90").persist()
    cross, inner = graph.cross_blocks(days, 40, 1, g).persist(), graph.block_edges(e, g).persist()
    x = np.zeros((90, 25))
    for r in days.collect():
        x[r.idx, r.v] = r.x
    arcs = {(r.src, r.dst) for r in e.collect()}
    hop = {(v, v): 0 for v in range(25)}
    for k in (1, 2):
        hop.update({(a, c): k for (a, b), h in list(hop.items()) if h == k - 1 for s, c in arcs if s == b and (a, c) not in hop})
    want = {}
    for (a, b), k in hop.items():
        for h in (0, 1):
            n, s = want.get((h, k), (0, 0.0))
            want[h, k] = n + 90 - h, s + x[: 90 - h, a] @ x[h:, b]
    assert {(r.h, r.hop): (r.n, r.s) for r in graph.pair_sums(cross, inner, 1, 2, 2).collect()} == want

    def kernel(v, idx, core, x, dist):
        out = {k: [] for k in ("h", "hop", "n", "s")}
        for h in (0, 1):
            for k in (0, 1, 2):
                pairs = [x[t, a] * x[t + h, b] for t, a in np.argwhere(core) if t + h < len(idx) for b in np.flatnonzero(dist[a] == k)]
                out["h"].append(h), out["hop"].append(k), out["n"].append(len(pairs)), out["s"].append(float(sum(pairs)))
        return out

    got = graph.map_reduce(cross, inner, kernel, "h int, hop int, n bigint, s double", ("h", "hop"), ("n", "s"), (1, 2), (1, 2))
    assert {(r.h, r.hop): (r.n, r.s) for r in got.collect()} == want
    for order in ((2, 1), (1, 3)):
        with pytest.raises(lay.HaloTooShort):
            graph.map_reduce(cross, inner, kernel, "h int, hop int, n bigint, s double", ("h", "hop"), ("n", "s"), order, (1, 2))
    with pytest.raises(lay.HaloTooShort):
        graph.pair_sums(cross, inner, 1, 2, 3)
    res = graph.retrospective(cross, inner, lambda own, parents: 0.5 * own + 0.25 * parents.sum(), (1, 2))
    parents = np.zeros((25, 25))
    for a, b in arcs:
        parents[a, b] = 1
    r = x[1:] - 0.5 * x[:-1] - 0.25 * x[:-1] @ parents
    assert {(q.v, q.idx): q.r for q in res.collect()} == {(v, t + 1): r[t, v] for t in range(89) for v in range(25)}
    assert abs(graph.residual_loglik(res) + 0.5 * r.size * (np.log(2 * np.pi * (r**2).mean()) + 1)) < 1e-6


def test_alignment(spark):
    s = spark.createDataFrame([(0, None), (1, 4), (2, None), (3, None), (9, 10), (10, None)], "idx bigint, v bigint")
    assert [r.v for r in grid.locf(s, 2).orderBy("idx").collect()] == [None, 4, 4, 4, 10, 10]
    assert [r.v for r in grid.linear(s, 2).orderBy("idx").collect()] == [None, 4.0, 4.75, 5.5, 10.0, None]


def test_save_and_load_without_exchange(spark):
    lay.save(lay.time_blocks(wide(spark, 64), 16, 2, 2), "halo_saved", 4)
    got = moments.lag_products(lay.load(spark, "halo_saved"), 2, 2)
    assert audit.observation_exchanges(got) == 0 and got.count() == 12
    spark.sql("drop table halo_saved")


def test_kernel_reach_is_checked(spark):
    with pytest.raises(lay.HaloTooShort):
        kernels.map_core(lay.time_blocks(wide(spark, 9), 4, 1, 0), lambda w: w.sum(), 2, 0, (1, 0))
    assert lay.plan_size(8, 10) >= 400 and lay.required_halo(2, 1, 5) == 5
    assert fit.default_depth(1000, 2) == 30
