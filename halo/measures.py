"""Costs and accuracies as rows (name, value, config)."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from halo.plans import audit

ROWS = "name string, value double, config string"


def timed(name: str, run: Callable[[], object], config: str = "") -> tuple[str, float, str]:
    t = time.perf_counter()
    run()
    return audit.row(name, time.perf_counter() - t, config)


def communication(df: DataFrame, name: str) -> list[tuple[str, float, str]]:
    return [audit.row("exchanges", audit.exchanges(df), name), audit.row("observation_exchanges", audit.observation_exchanges(df), name)]


def slope(x, y) -> float:
    """Slope on log-log axes: -1 for a variance that falls as 1/N."""
    return float(np.polyfit(np.log(x), np.log(y), 1)[0])


def operations(kind: str, **k) -> float:
    """Counted multiply-adds of the recursions."""
    p, q, d, b = k.get("p", 0), k.get("q", 0), k.get("d", 1), k.get("b", 0)
    return float({
        "levinson": 2 * p * p, "block_levinson": 4 * p * p * d**3 / 2, "dense": (p * d) ** 3 / 3, "innovations": sum(m * (m + 1) / 2 for m in range(1, q + 1)) * 2 * d**3,
        "arma": (p + q) ** 2 * d**3, "banded_predict": d * (2 * b + 1), "dense_predict": d * d,
    }[kind])


def table(spark: SparkSession, rows: list[tuple[str, float, str]]) -> DataFrame:
    return spark.createDataFrame(rows, ROWS)
