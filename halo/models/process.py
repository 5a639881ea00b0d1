"""AR, MA and ARMA models and their algebra."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from halo.functions import linalg

COEFFICIENTS = "model string, part string, k int, i int, j int, value double"


class SingularNoise(ValueError):
    """The companion form has degenerate noise and no density."""


@dataclass
class Process:
    """X_t = sum A_k X_{t-k} + e_t + sum B_k e_{t-k}, Var e = sigma, about `mean`."""

    a: list[np.ndarray] = field(default_factory=list)
    b: list[np.ndarray] = field(default_factory=list)
    sigma: np.ndarray | None = None
    mean: np.ndarray | None = None
    n: int = 0

    @property
    def d(self) -> int:
        return (self.a + self.b + [self.sigma])[0].shape[0]

    @property
    def kind(self) -> str:
        return {(0, 0): "white", (1, 0): "ar", (0, 1): "ma", (1, 1): "arma"}[bool(self.a), bool(self.b)]

    def companion(self) -> np.ndarray:
        return linalg.companion(self.a)

    def companion_likelihood(self):
        raise SingularNoise("the stacked form has noise in its first block only")

    def ar_radius(self) -> float:
        return linalg.spectral_radius(linalg.companion(self.a)) if self.a else 0.0

    def ma_radius(self) -> float:
        return linalg.spectral_radius(linalg.companion([-m for m in self.b])) if self.b else 0.0

    def is_causal(self) -> bool:
        return self.ar_radius() < 1

    def is_invertible(self) -> bool:
        return self.ma_radius() < 1 - 1e-12

    def psi(self, n: int) -> list[np.ndarray]:
        """Weights of past innovations, psi_0 = I."""
        out = [np.eye(self.d)]
        for k in range(1, n + 1):
            m = self.b[k - 1].copy() if k <= len(self.b) else np.zeros((self.d, self.d))
            out.append(m + sum((self.a[j] @ out[k - 1 - j] for j in range(min(k, len(self.a)))), np.zeros_like(m)))
        return out

    def pi(self, n: int) -> list[np.ndarray]:
        """Weights of past values in e_t = X_t - sum pi_k X_{t-k}."""
        out = [-np.eye(self.d)]
        for k in range(1, n + 1):
            m = self.a[k - 1].copy() if k <= len(self.a) else np.zeros((self.d, self.d))
            out.append(m - sum((self.b[j] @ out[k - 1 - j] for j in range(min(k, len(self.b)))), np.zeros_like(m)))
        return out[1:]

    def theoretical_autocov(self, max_lag: int, tol: float = 1e-16) -> np.ndarray:
        if self.a and not self.is_causal():
            raise ValueError("the model is not causal")
        r = self.ar_radius()
        n = max_lag + len(self.b) + (int(math.ceil(math.log(tol) / math.log(r))) if 0 < r < 1 else 0) + 1
        psi = self.psi(min(n, 20_000))
        return np.array([sum(psi[k] @ self.sigma @ psi[k + h].T for k in range(len(psi) - h)) for h in range(max_lag + 1)])

    def warmup(self, tol: float = 1e-9) -> int:
        """Steps after which a wrong start of the innovations has decayed to `tol`."""
        r = self.ma_radius()
        if r >= 1 - 1e-12:
            raise ValueError("not invertible: a wrong start never decays")
        return 0 if r == 0 else max(1, math.ceil(math.log(tol) / math.log(r)))

    def rows(self) -> list[tuple]:
        parts = [("A", k + 1, m) for k, m in enumerate(self.a)] + [("B", k + 1, m) for k, m in enumerate(self.b)]
        parts += [("Sigma", 0, self.sigma)] if self.sigma is not None else []
        out = [(self.kind, part, k, i, j, float(m[i, j])) for part, k, m in parts for i in range(m.shape[0]) for j in range(m.shape[1])]
        return out + ([(self.kind, "mean", 0, i, 0, float(x)) for i, x in enumerate(self.mean)] if self.mean is not None else [])

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows(), COEFFICIENTS)

    @staticmethod
    def from_df(df: DataFrame) -> "Process":
        rows = df.collect()
        d = max(max(r.i, r.j if r.part != "mean" else 0) for r in rows) + 1
        out = Process()
        for r in sorted(rows, key=lambda r: (r.part, r.k)):
            if r.part in "AB":
                side = out.a if r.part == "A" else out.b
                while len(side) < r.k:
                    side.append(np.zeros((d, d)))
                side[r.k - 1][r.i, r.j] = r.value
            elif r.part == "Sigma":
                out.sigma = np.zeros((d, d)) if out.sigma is None else out.sigma
                out.sigma[r.i, r.j] = r.value
            else:
                out.mean = np.zeros(d) if out.mean is None else out.mean
                out.mean[r.i] = r.value
        return out


def stack(x: np.ndarray, p: int) -> np.ndarray:
    """An AR(p) series as a series of dimension p d that is AR(1)."""
    return np.hstack([x[p - 1 - k : len(x) - k] for k in range(p)])


def uniform(seed: int, *keys: Column) -> Column:
    """A number in (0, 1) that depends on the keys alone: replicas draw the same."""
    return (F.pmod(F.xxhash64(F.lit(seed), *keys), F.lit(1 << 52)) + 0.5) / float(1 << 52)


def noise(seed: int, *keys: Column) -> Column:
    """Standard normal by Box-Muller from counter-based uniforms."""
    return F.sqrt(-2 * F.log(uniform(seed, *keys))) * F.cos(2 * math.pi * uniform(seed + 7919, *keys))


def simulate(e: np.ndarray, model: Process) -> np.ndarray:
    """The series that innovations `e` (rows) drive, starting from rest."""
    x = np.zeros_like(e)
    for t in range(len(e)):
        x[t] = e[t] + sum((m @ x[t - 1 - k] for k, m in enumerate(model.a) if t > k), 0) + sum((m @ e[t - 1 - k] for k, m in enumerate(model.b) if t > k), 0)
    return x
