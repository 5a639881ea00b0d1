"""Forecasts: one and several steps, variances, serial and block-parallel ARMA, baselines."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from halo.functions import linalg
from halo.models.fit import innovation_kernel
from halo.models.process import Process
from halo.operators import kernels
from halo.operators.blocks import lagged


def one_step(blocks: DataFrame, model: Process, mean: np.ndarray, halo: int) -> DataFrame:
    """Forecast of idx + 1 made at idx: idx, yhat (array)."""
    return k_step(blocks, model, mean, 1, halo).select("idx", F.col("yhat").alias("yhat"))


def k_step(blocks: DataFrame, model: Process, mean: np.ndarray, k: int, halo: int) -> DataFrame:
    """Forecasts of idx + k made at idx, by feeding forecasts back."""
    p = len(model.a)
    kernels.check_reach(p - 1, halo)

    def fn(window):
        past = [w - mean for w in window[::-1]]
        for _ in range(k):
            past.insert(0, sum(m @ past[j] for j, m in enumerate(model.a)))
        return past[0] + mean

    return kernels.map_core(blocks, fn, p - 1, 0, (halo, 0), "yhat")


def fixed_ar(blocks: DataFrame, weights: list[float], col: str = "v") -> DataFrame:
    """One-dimensional forecast with given weights inside code generation: idx, yhat for idx + 1."""
    total = sum((lagged(blocks, col, k).cast("double") * F.lit(w) for k, w in enumerate(weights)), F.lit(0.0))
    return blocks.withColumn("yhat", total).where("is_core and yhat is not null").select("idx", "yhat")


def variance(model: Process, k: int) -> list[np.ndarray]:
    """Variances of the forecasts of 1..k steps."""
    psi, out, acc = model.psi(k), [], np.zeros_like(model.sigma)
    for j in range(k):
        acc = acc + psi[j] @ model.sigma @ psi[j].T
        out.append(acc)
    return out


def with_interval(forecast: DataFrame, var: np.ndarray, level: float = 0.95) -> DataFrame:
    z = linalg.normal_quantile(0.5 + level / 2)
    half = F.array(*[F.lit(float(z * np.sqrt(v))) for v in np.diag(var)])
    return forecast.withColumn("lo", F.zip_with("yhat", half, lambda a, b: a - b)).withColumn("hi", F.zip_with("yhat", half, lambda a, b: a + b))


def arma_serial(x: np.ndarray, model: Process) -> tuple[np.ndarray, np.ndarray]:
    """Exact start with innovation coefficients, then the two-sided recursion: forecasts of t + 1 made at t, innovations."""
    n, d = x.shape
    m = max(len(model.a), len(model.b), 1)
    theta, _ = linalg.innovations(model.theoretical_autocov(m), m)
    f, e, last = np.zeros((n, d)), np.zeros((n, d)), np.zeros(d)
    for t in range(n):
        e[t] = x[t] - last  # the forecast of t made at t - 1
        if t + 1 < m:
            last = sum((theta[t + 1, j] @ e[t + 1 - j] for j in range(1, t + 2)), np.zeros(d))
        else:
            last = sum((a @ x[t - k] for k, a in enumerate(model.a)), np.zeros(d)) + sum((b @ e[t - k] for k, b in enumerate(model.b)), np.zeros(d))
        f[t] = last
    return f, e


def arma_blocks(blocks: DataFrame, model: Process, mean: np.ndarray, warmup: int, halo: int) -> DataFrame:
    """Each block starts with zero innovations `warmup` steps early; errors decay with the model's MA radius."""
    if not model.is_invertible():
        raise ValueError("not invertible: blocks cannot forget their start")
    kernels.check_reach(warmup + len(model.a), halo)
    return kernels.map_groups(blocks, innovation_kernel(model, mean), "idx bigint, forecast array<double>, e array<double>").drop("block")


def naive(blocks: DataFrame, col: str = "v", how: str = "last", mean: float = 0.0) -> DataFrame:
    value = F.col(col).cast("double") if how == "last" else F.lit(mean)
    return blocks.where("is_core").select("idx", value.alias("yhat"))


def featurized(blocks: DataFrame, features: dict[str, float], col: str = "v") -> DataFrame:
    """Linear in parameters, not in the past: `features` maps SQL over l0, l1 (last values) to weights."""
    rows = blocks.withColumn("l0", F.col(col).cast("double")).withColumn("l1", lagged(blocks, col, 1).cast("double"))
    total = F.lit(0.0)
    for sql, w in features.items():
        total = total + F.expr(sql) * F.lit(w)
    return rows.where("is_core").select("idx", total.alias("yhat"))


def errors(forecast: DataFrame, actual: DataFrame, step: int = 1) -> DataFrame:
    """Root mean squared error of scalar forecasts of idx + step against (idx, v)."""
    moved = forecast.select((F.col("idx") + step).alias("idx"), "yhat")
    return moved.join(actual.select("idx", "v"), "idx").agg(F.sqrt(F.avg((F.col("yhat") - F.col("v")) ** 2)).alias("rmse"), F.count(F.lit(1)).alias("n"))


def moving(blocks: DataFrame, before: int, after: int, agg: str, col: str = "v", unit: str = "rows") -> DataFrame:
    w = Window.partitionBy("block").orderBy("idx")
    w = w.rowsBetween(-before, after) if unit == "rows" else w.rangeBetween(-before, after)
    return blocks.withColumn("y", getattr(F, agg)(col).over(w)).where("is_core").select("idx", "y")
