"""Moment fits (Yule-Walker, innovations), order choice, goodness of fit."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halo.functions import linalg
from halo.models.process import Process
from halo.operators import kernels

MAX_DENSE = 10_000


def residual_cov(g: np.ndarray, a: list[np.ndarray]) -> np.ndarray:
    """S = G(0) - sum A_k G(k): with G(-k) in its place the result is not even symmetric."""
    return g[0] - sum((m @ g[k + 1] for k, m in enumerate(a)), np.zeros_like(g[0]))


def yule_walker(g: np.ndarray, p: int, solver: str = "dense", orientation: str = "column", noise: str = "full", ridge: float = 0.0) -> Process:
    if g.shape[1] * p > MAX_DENSE:
        raise ValueError("too many dimensions for a dense solve; use the banded fit")
    if solver == "levinson":
        a, v = linalg.levinson(g, p)
        s = np.array([[v]])
    elif solver == "block_levinson":
        a, s, _ = linalg.block_levinson(g, p)
    else:
        a = linalg.solve_projection(g, p, orientation, ridge)
        s = residual_cov(g, a)
    return Process(a=a, sigma=np.diag(np.diag(s)) if noise == "diag" else s)


def ma(g: np.ndarray, q: int, depth: int | None = None) -> Process:
    """Innovations coefficients at `depth` (default q; deeper recursions come closer to B)."""
    depth = depth or q
    theta, s = linalg.innovations(g, depth)
    return Process(b=[theta[depth, k] for k in range(1, q + 1)], sigma=s[depth])


def arma(g: np.ndarray, p: int, q: int, depth: int | None = None) -> Process:
    depth = max(depth or 0, p + q)
    theta, s = linalg.innovations(g, depth)
    d = g.shape[1]

    def psi(k):
        return np.eye(d) if k == 0 else theta[depth, k] if k > 0 else np.zeros((d, d))

    a: list[np.ndarray] = []
    if p:
        t = np.block([[psi(q + r - c).T for c in range(1, p + 1)] for r in range(1, p + 1)])
        stacked = np.linalg.lstsq(t, np.vstack([psi(q + r).T for r in range(1, p + 1)]), rcond=None)[0]
        a = [stacked[k * d : (k + 1) * d].T for k in range(p)]
    b = [psi(j) - sum((a[i - 1] @ psi(j - i) for i in range(1, min(j, p) + 1)), np.zeros((d, d))) for j in range(1, q + 1)]
    return Process(a=a, b=b, sigma=s[depth])


def default_depth(n: int, q: int) -> int:
    return max(q, math.ceil(10 * math.log10(max(n, 2))))


def ar_order(kappa: list[np.ndarray], n: int, level: float = 0.95) -> int:
    """Last order before the first insignificant partial correlation."""
    for k, m in enumerate(kappa):
        if insignificant(m, n, level):
            return k
    return len(kappa)


def insignificant(m: np.ndarray, n: int, level: float) -> bool:
    if m.size == 1:
        return abs(float(m[0, 0])) <= linalg.normal_quantile(0.5 + level / 2) / math.sqrt(n)
    return n * float((m**2).sum()) <= linalg.chi2_quantile(level, m.size)


def ma_order(r: np.ndarray, n: int, level: float = 0.95) -> int:
    """Last lag with a significant correlation."""
    seen = [h for h in range(1, len(r)) if not insignificant(r[h], n, level)]
    return seen[-1] if seen else 0


def criterion(model: Process, n: int, kind: str) -> float:
    d = model.sigma.shape[0]
    k = d * d * (len(model.a) + len(model.b)) + d * (d + 1) / 2
    sign, logdet = np.linalg.slogdet(model.sigma)
    if sign <= 0:
        return math.inf
    return n * (logdet + d * math.log(2 * math.pi) + d) + (2 * k if kind == "aic" else k * math.log(n))


def search(g: np.ndarray, n: int, pmax: int, qmax: int, kind: str = "aic", depth: int | None = None) -> list[tuple[int, int, float]]:
    """(p, q, criterion) of every candidate, best first, from the same moments."""
    out = []
    for p in range(pmax + 1):
        for q in range(qmax + 1):
            try:
                m = Process(sigma=g[0]) if p == q == 0 else yule_walker(g, p) if q == 0 else arma(g, p, q, depth or min(len(g) - 1, default_depth(n, q)))
                out.append((p, q, criterion(m, n, kind)))
            except np.linalg.LinAlgError:
                continue
    return sorted(out, key=lambda r: r[2])


def innovation_kernel(model: Process, mean: np.ndarray, start: int = 0):
    """Innovations of core data by running the filter over the block, from zero at its first row."""

    def run(idx, core, x):
        z = x - mean
        e, f = np.zeros_like(z), np.zeros_like(z)
        for t in range(len(z)):
            acc = np.zeros(z.shape[1])
            for k, m in enumerate(model.a):
                if t > k:
                    acc += m @ z[t - 1 - k]
            for k, m in enumerate(model.b):
                if t > k:
                    acc += m @ e[t - 1 - k]
            f[t], e[t] = acc + mean, z[t] - acc
        keep = core & (idx - idx[0] >= start) if len(idx) else core
        return {"idx": idx[keep], "forecast": list(f[keep]), "e": list(e[keep])}

    return run


def residuals(blocks: DataFrame, model: Process, mean: np.ndarray) -> DataFrame:
    return kernels.map_groups(blocks, innovation_kernel(model, mean), "idx bigint, forecast array<double>, e array<double>").drop("block")


def portmanteau(r: np.ndarray, n: int, fitted: int, level: float = 0.95) -> tuple[float, int, bool]:
    """Statistic, degrees of freedom, and whether residuals pass as white."""
    stat = n * n * sum(float((r[h] ** 2).sum()) / (n - h) for h in range(1, len(r)))
    df = max(1, (len(r) - 1) * r[0].size - fitted)
    return stat, df, stat <= linalg.chi2_quantile(level, df)


def summary(res: DataFrame, model: Process, variance: np.ndarray) -> dict[str, float]:
    """Log-likelihood, AIC, BIC and R^2 by dimension from residual rows (column e)."""
    d = len(variance)
    pick = [F.sum(F.col("e")[i] * F.col("e")[j]).alias(f"s{i}_{j}") for i in range(d) for j in range(d)]
    row = res.agg(F.count(F.lit(1)).alias("n"), *pick).head()
    n = row.n
    s = np.array([[row[f"s{i}_{j}"] for j in range(d)] for i in range(d)]) / n
    ll = -0.5 * n * (np.linalg.slogdet(s)[1] + d * math.log(2 * math.pi) + d)
    k = d * d * (len(model.a) + len(model.b)) + d * (d + 1) / 2
    return {"n": n, "loglik": ll, "aic": 2 * k - 2 * ll, "bic": k * math.log(n) - 2 * ll} | {f"r2_{i}": 1 - s[i, i] / variance[i] for i in range(d)}
