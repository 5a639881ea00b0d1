"""Small dense algebra on the driver: block Toeplitz systems, recursions, eigenvalue bounds, quantiles.

Convention: G[h] = Cov(X_t, X_{t+h}) = E[X_t X_{t+h}^T], so G(-h) = G(h)^T. C(h) below is its transpose.
"""

from __future__ import annotations

import math

import numpy as np


def at_lag(g: np.ndarray, h: int) -> np.ndarray:
    return g[h] if h >= 0 else g[-h].T


def block_toeplitz(g: np.ndarray, p: int) -> np.ndarray:
    """Block (r, c) is G(r - c), r and c from 0."""
    return np.block([[at_lag(g, r - c) for c in range(p)] for r in range(p)])


def solve_projection(g: np.ndarray, p: int, orientation: str = "column", ridge: float = 0.0) -> list[np.ndarray]:
    """Coefficients A_1..A_p of the best linear prediction of X_t from X_{t-1}..X_{t-p} (dense solve)."""
    d = g.shape[1]
    if orientation == "column":
        t = np.block([[at_lag(g, r - c) for c in range(1, p + 1)] for r in range(1, p + 1)]) + ridge * np.eye(p * d)
        stacked = np.linalg.solve(t, np.vstack([g[r] for r in range(1, p + 1)]))
        return [stacked[k * d : (k + 1) * d].T for k in range(p)]
    t = np.block([[at_lag(g, c - r).T for c in range(1, p + 1)] for r in range(1, p + 1)]).T + ridge * np.eye(p * d)
    rows = np.linalg.solve(t.T, np.hstack([g[r].T for r in range(1, p + 1)]).T).T
    return [rows[:, k * d : (k + 1) * d] for k in range(p)]


def levinson(g: np.ndarray, p: int) -> tuple[list[np.ndarray], float]:
    """One-dimensional recursion in O(p^2): coefficients and residual variance."""
    c = [float(g[h][0, 0]) for h in range(p + 1)]
    a: list[float] = []
    v = c[0]
    for n in range(p):
        k = (c[n + 1] - sum(a[j] * c[n - j] for j in range(n))) / v
        a = [a[j] - k * a[n - 1 - j] for j in range(n)] + [k]
        v *= 1 - k * k
    return [np.array([[x]]) for x in a], v


def block_levinson(g: np.ndarray, p: int) -> tuple[list[np.ndarray], np.ndarray, list[np.ndarray]]:
    """Forward and backward predictors of growing order: A_1..A_p, residual covariance, last blocks of every order."""
    c = [g[h].T for h in range(p + 1)]
    v, w = c[0].copy(), c[0].copy()
    forward: list[np.ndarray] = []
    backward: list[np.ndarray] = []
    last = []
    for n in range(p):
        delta = c[n + 1] - sum((forward[k] @ c[n - k] for k in range(n)), np.zeros_like(v))
        f = np.linalg.solve(w.T, delta.T).T
        b = np.linalg.solve(v.T, delta).T
        grown = [forward[k] - f @ backward[n - 1 - k] for k in range(n)] + [f]
        backward = [backward[k] - b @ forward[n - 1 - k] for k in range(n)] + [b]
        forward = grown
        v, w = v - f @ delta.T, w - b @ delta
        last.append(f)
    return forward, v, last


def innovations(g: np.ndarray, depth: int) -> tuple[dict[tuple[int, int], np.ndarray], list[np.ndarray]]:
    """Theta[m, j] (j = 1..m) and one-step variances S_0..S_depth."""
    c = [g[h].T if h < len(g) else np.zeros_like(g[0]) for h in range(depth + 1)]
    s, theta = [c[0]], {}
    for m in range(1, depth + 1):
        for j in range(m):
            acc = c[m - j] - sum((theta[m, m - i] @ s[i] @ theta[j, j - i].T for i in range(j)), np.zeros_like(c[0]))
            theta[m, m - j] = np.linalg.solve(s[j].T, acc.T).T
        s.append(c[0] - sum((theta[m, m - i] @ s[i] @ theta[m, m - i].T for i in range(m)), np.zeros_like(c[0])))
    return theta, s


def companion(blocks: list[np.ndarray]) -> np.ndarray:
    d, p = blocks[0].shape[0], len(blocks)
    out = np.zeros((p * d, p * d))
    out[:d] = np.hstack(blocks)
    out[d:, : (p - 1) * d] = np.eye((p - 1) * d)
    return out


def spectral_radius(m: np.ndarray, limit: int = 2000) -> float:
    if not m.size:
        return 0.0
    if len(m) <= limit:
        return float(np.abs(np.linalg.eigvals(m)).max())
    x, rate = np.random.default_rng(0).normal(size=len(m)), 0.0
    for _ in range(200):
        y = m @ x
        rate = float(np.linalg.norm(y) / np.linalg.norm(x))
        x = y / max(np.linalg.norm(y), 1e-300)
    return rate


def lyapunov(f: np.ndarray, q: np.ndarray, tol: float = 1e-14) -> np.ndarray:
    """Solution of P = F P F^T + Q by doubling."""
    p, a = q.copy(), f.copy()
    for _ in range(60):
        step = a @ p @ a.T
        p, a = p + step, a @ a
        if np.abs(step).max() <= tol * max(1.0, np.abs(p).max()):
            break
    return p


def extreme_eigenvalues(m: np.ndarray) -> tuple[float, float]:
    w = np.linalg.eigvalsh((m + m.T) / 2)
    return float(w[0]), float(w[-1])


def normal_quantile(p: float) -> float:
    lo, hi = -12.0, 12.0
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if 0.5 * math.erfc(-mid / math.sqrt(2)) < p else (lo, mid)
    return (lo + hi) / 2


def chi2_quantile(p: float, k: int) -> float:
    """Wilson-Hilferty approximation."""
    z = normal_quantile(p)
    return k * (1 - 2 / (9 * k) + z * math.sqrt(2 / (9 * k))) ** 3


def reverse_breadth_first(pattern: list[set[int]]) -> list[int]:
    """An order of the indices that brings neighbours together (smallest degrees first, then reversed)."""
    seen: set[int] = set()
    order: list[int] = []
    for root in sorted(range(len(pattern)), key=lambda k: len(pattern[k])):
        queue = [] if root in seen else [root]
        seen.update(queue)
        while queue:
            k = queue.pop(0)
            order.append(k)
            fresh = sorted((x for x in pattern[k] if x not in seen), key=lambda x: len(pattern[x]))
            seen.update(fresh)
            queue += fresh
    return order[::-1]
