"""Likelihood fits by first-order methods on overlapping blocks.

Objective (half quadratic form): f = 1/(2n) sum r_t^T Pi r_t - 1/2 log det Pi, r_t = X_t - sum A_k X_{t-k}.
One pass over the blocks evaluates value and gradient for several parameter sets at once.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halo.functions import linalg
from halo.models import moments
from halo.models.process import Process
from halo.operators import kernels


def design(idx, core, x, p):
    t = np.flatnonzero(core)
    t = t[t >= p]
    t = t[idx[t] - idx[t - p] == p]
    return x[t], np.hstack([x[t - k] for k in range(1, p + 1)]) if p else np.zeros((len(t), 0)), idx[t]


def loss(family: str, r: np.ndarray, pi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Value and derivative by residual. smooth_robust: a little quadratic plus log cosh of whitened residuals."""
    if family == "gaussian":
        w = r @ pi
        return 0.5 * (w * r).sum(axis=1), w
    root = np.linalg.cholesky(pi)
    z = r @ root
    return (np.logaddexp(z, -z) - math.log(2) + 0.05 * z * z).sum(axis=1), (np.tanh(z) + 0.1 * z) @ root.T


def pass_over(blocks: DataFrame, thetas: list[np.ndarray], pi: np.ndarray, p: int, halo: int, family: str = "gaussian", sample: tuple[int, float] | None = None) -> list[tuple[float, np.ndarray, int]]:
    """(value, gradient, terms) of each candidate theta (d x pd) in one pass; `sample` = (epoch seed, rate) by hash of the index."""
    kernels.check_reach(p, halo)
    src = blocks
    if sample:
        keep = F.pmod(F.xxhash64(F.lit(sample[0]), "idx"), F.lit(1_000_000)) < int(sample[1] * 1_000_000)
        src = blocks.withColumn("is_core", F.col("is_core") & keep)

    def run(idx, core, x):
        y, z, _ = design(idx, core, x, p)
        out = {"c": [], "k": [], "s": []}
        for c, theta in enumerate(thetas):
            value, w = loss(family, y - z @ theta.T, pi)
            flat = np.concatenate([[value.sum(), len(y)], (-(w.T @ z)).ravel()])
            out["c"].append(np.full(len(flat), c)), out["k"].append(np.arange(len(flat))), out["s"].append(flat)
        return {k: np.concatenate(v) for k, v in out.items()}

    got = kernels.map_reduce(src, run, "c int, k int, s double", ("c", "k"), ("s",)).collect()
    flat = np.zeros((len(thetas), 2 + thetas[0].size))
    for r in got:
        flat[r.c, r.k] = r.s
    half = 0.5 * np.linalg.slogdet(pi)[1]
    return [(float(f[0] / max(f[1], 1) - half), f[2:].reshape(thetas[0].shape) / max(f[1], 1), int(f[1])) for f in flat]


def gram_gradient(m: np.ndarray, n: int, theta: np.ndarray, pi: np.ndarray) -> tuple[float, np.ndarray]:
    """The Gaussian value and gradient from lag Gram matrices: no pass over data."""
    p, d = m.shape[0] - 1, m.shape[2]
    z = np.block([[m[a, b] for b in range(1, p + 1)] for a in range(1, p + 1)]) / n
    yz = np.hstack([m[0, b] for b in range(1, p + 1)]) / n
    s = m[0, 0] / n - theta @ yz.T - yz @ theta.T + theta @ z @ theta.T
    return float(0.5 * np.trace(pi @ s) - 0.5 * np.linalg.slogdet(pi)[1]), -pi @ (yz - theta @ z)


def stacked_cov(m: np.ndarray, n: int) -> np.ndarray:
    p = m.shape[0] - 1
    return np.block([[m[a, b] for b in range(1, p + 1)] for a in range(1, p + 1)]) / n


def spectral_step(pi: np.ndarray, cov: np.ndarray) -> tuple[float, float]:
    """Step 2 / (m + L) and contraction (L - m) / (L + m) from the extremes of both factors."""
    (a, b), (c, e) = linalg.extreme_eigenvalues(pi), linalg.extreme_eigenvalues(cov)
    lo, hi = a * c, b * e
    return 2 / (lo + hi), (hi - lo) / (hi + lo)


def curvature_step(family: str, pi: np.ndarray, cov: np.ndarray) -> float:
    """2 / (m + L) where the loss of whitened residuals curves between two bounds."""
    least, most = {"gaussian": (1.0, 1.0), "smooth_robust": (0.1, 1.1)}[family]
    (a, b), (c, e) = linalg.extreme_eigenvalues(pi), linalg.extreme_eigenvalues(cov)
    return 2 / (least * a * c + most * b * e)


def newton(m: np.ndarray, n: int) -> np.ndarray:
    """Normal equations: the optimum in one solve, cubic in p d."""
    p = m.shape[0] - 1
    return np.linalg.solve(stacked_cov(m, n), (np.hstack([m[0, b] for b in range(1, p + 1)]) / n).T).T


def precision(m: np.ndarray, n: int, theta: np.ndarray, form: str = "full", blocks: list[list[int]] | None = None) -> np.ndarray:
    p = m.shape[0] - 1
    yz = np.hstack([m[0, b] for b in range(1, p + 1)]) / n
    s = m[0, 0] / n - theta @ yz.T - yz @ theta.T + theta @ stacked_cov(m, n) @ theta.T
    if form == "diag":
        return np.diag(1 / np.diag(s))
    if form == "blocks":
        out = np.zeros_like(s)
        for b in blocks:
            out[np.ix_(b, b)] = np.linalg.inv(s[np.ix_(b, b)])
        return out
    return np.linalg.inv(s)


def gradient_fit(source, d: int, p: int, pi: np.ndarray, step="spectral", tol: float = 1e-9, most: int = 2000, halo: int = 0, family: str = "gaussian", fixed: float | None = None) -> tuple[np.ndarray, list[tuple]]:
    """Full gradient descent. `source`: (gram, n), or blocks for one pass a step. Trace: iter, objective, gradient norm, step, rows.

    step 'spectral' takes the extremes of the stacked covariance, which blocks give in one pass of their own; 'backtracking'
    tries several sizes in one pass; 'conjugate' (Gaussian only) needs as many passes as there are coefficients of a row at
    most, whatever the condition of the data; `fixed` is a size of the caller's, who answers for its convergence.
    """
    theta, trace = np.zeros((d, p * d)), []
    on_gram = isinstance(source, tuple)

    def evaluate(ts):
        return [(*gram_gradient(*source, t, pi), source[1]) for t in ts] if on_gram else pass_over(source, ts, pi, p, halo, family)

    if step not in ("spectral", "backtracking", "conjugate") or step == "conjugate" and family != "gaussian":
        raise ValueError("step is 'spectral', 'backtracking' or, for the Gaussian family, 'conjugate'")
    size = fixed or 1.0
    if fixed is None and step == "spectral":
        cov = stacked_cov(*(source if on_gram else moments.gram_matrix(moments.lag_gram(source, p, halo), p, d)))
        size = spectral_step(pi, cov)[0] if family == "gaussian" else curvature_step(family, pi, cov)
    f, g, n = evaluate([theta])[0]
    if step == "conjugate":
        return _conjugate(evaluate, theta, f, g, n, tol, most)
    for k in range(most):
        trace.append((k, f, float(np.linalg.norm(g)), float(size), n))
        if np.linalg.norm(g) < tol:
            break
        if step == "backtracking":  # several step sizes in one pass
            steps = [size * 2.0 ** (1 - j) for j in range(6)]
            options = evaluate([theta - s * g for s in steps])
            best = min(range(6), key=lambda j: options[j][0])
            size = steps[best]
            if f - options[best][0] <= 1e-14 * (1 + abs(f)):  # nothing left to gain at this precision
                break
            theta, (f, g, n) = theta - size * g, options[best]
        else:
            theta = theta - size * g
            f, g, n = evaluate([theta])[0]
    return theta, trace


def _conjugate(evaluate, theta: np.ndarray, f: float, g: np.ndarray, n: int, tol: float, most: int) -> tuple[np.ndarray, list[tuple]]:
    """Conjugate gradients on a quadratic: a gradient a unit step ahead gives the curvature along it, a second one the true gradient where it lands.

    Both come with each pass of its own; a direction that no longer points down starts anew from the gradient.
    """
    trace, p = [], -g
    for k in range(most):
        norm = float(np.linalg.norm(g))
        trace.append((k, f, norm, 0.0, n))
        if norm < tol:
            break
        p = p if float((p * g).sum()) < 0 else -g
        unit = p / np.linalg.norm(p)
        bend = evaluate([theta + unit])[0][1] - g
        curve = float((unit * bend).sum())
        if curve <= 0:  # flat up to rounding
            break
        size = -float((unit * g).sum()) / curve
        landed = theta + size * unit
        f, new, n = evaluate([landed])[0]
        trace[-1] = (k, trace[-1][1], norm, size, n)
        p = -new + max(0.0, float((new * (new - g)).sum()) / float((g * g).sum())) * p
        if np.linalg.norm(new) >= norm and norm < 1e3 * tol:  # rounding: nothing left to gain
            break
        theta, g = landed, new
    return theta, trace


def sgd_fit(blocks: DataFrame, d: int, p: int, pi: np.ndarray, halo: int, rounds: int = 30, rate: float = 0.1, c: float = 1.0, k0: float = 10.0, seed: int = 1) -> tuple[np.ndarray, list[tuple]]:
    """Stochastic steps c / (k0 + k) on a hash sample of core rows; neighbours are in the halo already."""
    theta, trace = np.zeros((d, p * d)), []
    for k in range(rounds):
        f, g, n = pass_over(blocks, [theta], pi, p, halo, sample=(seed + k, rate))[0]
        trace.append((k, f, float(np.linalg.norm(g)), c / (k0 + k), n))
        theta = theta - c / (k0 + k) * g
    return theta, trace


def local_sgd_fit(blocks: DataFrame, d: int, p: int, halo: int, epochs: int = 5, step: float = 0.05) -> np.ndarray:
    """Each block runs its own steps from the average of the last round; one small reduction a round."""
    kernels.check_reach(p, halo)
    theta = np.zeros((d, p * d))
    for _ in range(epochs):
        start = theta

        def run(idx, core, x, start=start):
            y, z, _ = design(idx, core, x, p)
            th = start.copy()
            for s in range(0, len(y), 16):
                r = y[s : s + 16] - z[s : s + 16] @ th.T
                th = th + step / max(1, len(r)) * (r.T @ z[s : s + 16])
            return {"k": np.arange(th.size), "s": th.ravel() * len(y), "w": np.full(th.size, float(len(y)))}

        for r in kernels.map_reduce(blocks, run, "k int, s double, w double", ("k",), ("s", "w")).collect():
            theta.ravel()[r.k] = r.s / max(r.w, 1)
    return theta


def masked_newton(m: np.ndarray, n: int, pi: np.ndarray, mask: np.ndarray) -> np.ndarray:
    """The optimum among coefficients that vanish outside `mask`: rows meet through the precision."""
    p = m.shape[0] - 1
    i, k = np.nonzero(mask)
    z, yz = stacked_cov(m, n), np.hstack([m[0, b] for b in range(1, p + 1)]) / n
    theta = np.zeros(mask.shape)
    theta[i, k] = np.linalg.solve(pi[np.ix_(i, i)] * z[np.ix_(k, k)], (pi @ yz)[i, k])
    return theta


def band_mask(d: int, p: int, bandwidth: int) -> np.ndarray:
    return np.tile(np.abs(np.subtract.outer(np.arange(d), np.arange(d))) <= bandwidth, p)


def alternate(m: np.ndarray, n: int, tol: float = 1e-10, most: int = 50, mask: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, list[float]]:
    """Coefficients given precision, precision given coefficients, until the objective settles.

    Without a mask the coefficients do not depend on the precision and one round is enough; with zeros given by
    `mask` (a band, say) each step changes the other.
    """
    d = m.shape[2]
    pi, theta, seen = np.eye(d), np.zeros((d, d * (m.shape[0] - 1))), []
    for _ in range(most):
        theta = newton(m, n) if mask is None else masked_newton(m, n, pi, mask)
        pi = precision(m, n, theta)
        seen.append(gram_gradient(m, n, theta, pi)[0])
        if len(seen) > 1 and abs(seen[-1] - seen[-2]) < tol:
            break
    return theta, pi, seen


def conditional_loglik(blocks: DataFrame, model: Process, halo: int) -> float:
    p = len(model.a)
    pi = np.linalg.inv(model.sigma)
    f, _, n = pass_over(blocks, [np.hstack(model.a)], pi, p, halo)[0]
    return -n * (f + 0.5 * len(pi) * math.log(2 * math.pi))


def start_term(model: Process, first: np.ndarray, latent: bool = False) -> float:
    """Log density of the first p values under the stationary law; `latent`: at their most likely value (the mean)."""
    p, d = len(model.a), model.d
    g = model.theoretical_autocov(p - 1)
    gamma = np.block([[linalg.at_lag(g, c - r) for c in range(p)] for r in range(p)])
    z = np.zeros(p * d) if latent else first.ravel()
    return float(-0.5 * np.linalg.slogdet(gamma)[1] - 0.5 * z @ np.linalg.solve(gamma, z) - 0.5 * p * d * math.log(2 * math.pi))


def unconditional_fit(m: np.ndarray, n: int, first: np.ndarray, steps: int = 200, latent: bool = False) -> tuple[Process, float]:
    """Numeric gradient ascent on conditional plus stationary start term, from the lag Gram matrices of all terms and the first p values."""
    p, d = m.shape[0] - 1, m.shape[2]
    z, yz = stacked_cov(m, n), np.hstack([m[0, b] for b in range(1, p + 1)]) / n
    theta = newton(m, n)

    def spread(th):
        return m[0, 0] / n - th @ yz.T - yz @ th.T + th @ z @ th.T

    def value(th):
        s = spread(th) + 1e-12 * np.eye(d)
        model = Process(a=[th[:, k * d : (k + 1) * d] for k in range(p)], sigma=s)
        if not model.is_causal():
            return -np.inf
        return -0.5 * n * (np.linalg.slogdet(s)[1] + d + d * math.log(2 * math.pi)) + start_term(model, first, latent)

    now, size = value(theta), 0.1
    for _ in range(steps):
        g = np.zeros_like(theta)
        for k in np.ndindex(theta.shape):
            e = np.zeros_like(theta)
            e[k] = 1e-5
            up, down = value(theta + e), value(theta - e)
            g[k] = (up - down) / 2e-5 if np.isfinite(up) and np.isfinite(down) else 0.0
        trial = theta + size * g / max(np.linalg.norm(g), 1e-12)
        new = value(trial)
        theta, now, size = (trial, new, size * 1.2) if new > now else (theta, now, size / 2)
        if size < 1e-9:
            break
    return Process(a=[theta[:, k * d : (k + 1) * d] for k in range(p)], sigma=spread(theta)), now


def arma_css(x: np.ndarray, p: int, q: int, start: Process, steps: int = 100) -> Process:
    """Conditional sum of squares of a one-dimensional ARMA by numeric descent from a moment fit."""
    par = np.array([float(m[0, 0]) for m in start.a + start.b])

    def sse(v):
        e = np.zeros(len(x))
        for t in range(len(x)):
            e[t] = x[t] - sum(v[k] * x[t - 1 - k] for k in range(p) if t > k) - sum(v[p + k] * e[t - 1 - k] for k in range(q) if t > k)
        return float(e[p:] @ e[p:]), e

    now, size = sse(par)[0], 0.05
    for _ in range(steps):
        g = np.array([(sse(par + h)[0] - sse(par - h)[0]) / 2e-5 for h in 1e-5 * np.eye(len(par))])
        trial = par - size * g / max(np.linalg.norm(g), 1e-12)
        new = sse(trial)[0]
        par, now, size = (trial, new, size * 1.2) if new < now else (par, now, size / 2)
        if size < 1e-8:
            break
    return Process(a=[np.array([[v]]) for v in par[:p]], b=[np.array([[v]]) for v in par[p:]], sigma=np.array([[now / (len(x) - p)]]))
