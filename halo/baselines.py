"""What overlapping blocks are compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from halo.operators import kernels


def self_join(long: DataFrame, max_lag: int, cross_only: bool = False) -> DataFrame:
    """Time partition without overlap: neighbours fetched by a join for each lag. Rows lag, i, j, n, s."""
    a = long.select("idx", F.col("dim").alias("i"), F.col("v").alias("a"))
    lags = a.withColumn("lag", F.explode(F.sequence(F.lit(0), F.lit(max_lag)))).withColumn("k", F.col("idx") + F.col("lag"))
    b = long.select(F.col("idx").alias("k"), F.col("dim").alias("j"), F.col("v").alias("b"))
    both = lags.join(b, (lags["k"] == b["k"]) & (lags["i"] != b["j"])) if cross_only else lags.join(b, "k")
    return both.groupBy("lag", "i", "j").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("a") * F.col("b")).alias("s"))


def global_window(long: DataFrame, max_lag: int) -> DataFrame:
    """One window over the whole series of a dimension: one task a dimension. Rows lag, i, s (diagonal)."""
    w = Window.partitionBy("dim").orderBy("idx")
    lags = F.array(*[F.struct(F.lit(h).alias("lag"), (F.col("v") * F.lead("v", h).over(w)).alias("p")) for h in range(max_lag + 1)])
    return long.select(F.col("dim").alias("i"), lags.alias("l")).select("i", F.explode("l").alias("e")).where("e.p is not null").groupBy(F.col("e.lag").alias("lag"), "i").agg(F.sum("e.p").alias("s"))


def by_series(long: DataFrame, max_lag: int) -> DataFrame:
    """Each series whole in one task: its own lag products need no exchange, cross terms are joined on the timestamp.

    Tasks are as long as the longest series, and no more of them run than there are series. Rows lag, i, j, n, s.
    """

    def run(keys, table):
        idx, v = table.column("idx").to_numpy(), table.column("v").to_numpy()
        order = np.argsort(idx, kind="stable")
        idx, v = idx[order], v[order]
        n, s = [], []
        for h in range(max_lag + 1):
            a, b = kernels.partner(idx, np.arange(len(idx)), h)
            n.append(len(a))
            s.append(int((v[a] * v[b]).sum()))
        k = keys[0].as_py()
        return pa.table({"lag": pa.array(range(max_lag + 1), pa.int32()), "i": pa.array([k] * (max_lag + 1), pa.int32()), "j": pa.array([k] * (max_lag + 1), pa.int32()), "n": pa.array(n, pa.int64()), "s": pa.array(s, pa.int64())})

    own = long.groupBy("dim").applyInArrow(run, "lag int, i int, j int, n bigint, s bigint")
    return own.unionByName(self_join(long, max_lag, cross_only=True))


def serial(x: np.ndarray, max_lag: int) -> np.ndarray:
    """One processor: lag products of a matrix."""
    return np.array([x[: len(x) - h].T @ x[h:] for h in range(max_lag + 1)])


def dense_predict(x: np.ndarray, a: np.ndarray) -> np.ndarray:
    return x @ a.T
