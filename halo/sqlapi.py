"""The engine in SQL: functions, aggregates, table functions and views over a folder of tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType


@F.arrow_udf(DoubleType())
def halo_norm(x: pa.Array) -> pa.Array:
    """Euclidean norm of arrays; null for null, 0 for empty."""
    lists = x if isinstance(x, pa.ListArray) else x.combine_chunks()
    parent, flat = pc.list_parent_indices(lists), lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    total = np.bincount(parent.to_numpy(), flat * flat, len(lists))
    return pa.array(np.sqrt(total), mask=np.asarray(lists.is_null()))


@F.pandas_udf(LongType())
def halo_lag_moment(idx: pd.Series, v: pd.Series, lag: pd.Series) -> int:
    """Sum of v_t v_(t+lag) over the rows of a group (a short series); repeated indexes each count. Native sums are preferred at scale."""
    h, known = int(lag.iloc[0]), {}
    for i, x in zip(idx, v):
        known[i] = known.get(i, 0) + int(x)
    return int(sum(x * known.get(i + h, 0) for i, x in known.items()))


class HaloPsi:
    """Rows k, psi: weights of past innovations of an ARMA(1,1), psi_0 = 1."""

    def eval(self, a: float, b: float, n: int) -> Iterator[tuple[int, float]]:
        psi = 1.0
        for k in range(n + 1):
            yield k, psi
            psi = a + b if k == 0 else a * psi


class HaloLags:
    """Rows lag, s: sums of products of a whole short series given as an array."""

    def eval(self, x: list, max_lag: int) -> Iterator[tuple[int, float]]:
        for h in range(max_lag + 1) if x is not None else []:
            yield h, float(sum(p * q for p, q in zip(x, x[h:])))


def register(spark: SparkSession, tables: dict[str, DataFrame] | None = None, folder: str | None = None, names: tuple[str, ...] = ()) -> None:
    """Functions halo_norm, halo_lag_moment, table functions halo_psi, halo_lags, and temporary views."""
    spark.udf.register("halo_norm", halo_norm)
    spark.udf.register("halo_lag_moment", halo_lag_moment)
    spark.udtf.register("halo_psi", F.udtf(HaloPsi, returnType="k int, psi double"))
    spark.udtf.register("halo_lags", F.udtf(HaloLags, returnType="lag int, s double"))
    for name in names:
        spark.read.parquet(f"{folder}/{name}.parquet").createOrReplaceTempView(f"halo_{name}")
    for name, df in (tables or {}).items():
        df.createOrReplaceTempView(name)
