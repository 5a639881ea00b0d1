"""Differences, their inverse, integration order, truncated fractional differences, prefix sums."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from halo.operators.blocks import lagged
from halo.operators.grid import running


def diff(blocks: DataFrame, order: int = 1, col: str = "v") -> DataFrame:
    """Forward differences of `order`: idx, y (the last `order` steps have none)."""
    total, sign = F.lit(0), 1
    c = 1
    for k in range(order + 1):
        total = total + lagged(blocks, col, -(order - k)) * F.lit(sign * c) if order - k else total + F.col(col) * F.lit(sign * c)
        c, sign = c * (order - k) // (k + 1), -sign
    return blocks.withColumn("y", total).where("is_core and y is not null").select("idx", "y")


def prefix_sum(blocks: DataFrame, col: str = "v") -> DataFrame:
    """Running totals over all blocks: block totals, their prefix (one row a block), running sums inside."""
    core = blocks.where("is_core")
    totals = core.groupBy("block").agg(F.sum(col).alias("t"))
    before = running(totals, "block", "t", "sum").select("block", F.col("before").alias("b"))
    w = Window.partitionBy("block").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return core.withColumn("r", F.sum(col).over(w)).join(before, "block").select("idx", (F.col("r") + F.col("b")).alias("y"))


def integrate(blocks: DataFrame, first, col: str = "v") -> DataFrame:
    """Levels after each forward difference, from the first level."""
    return prefix_sum(blocks, col).select((F.col("idx") + 1).alias("idx"), (F.col("y") + F.lit(first)).alias("y"))


def frac_weights(delta: float, width: int) -> list[float]:
    w = [1.0]
    for k in range(1, width + 1):
        w.append(-w[-1] * (delta - k + 1) / k)
    return w


def frac(blocks: DataFrame, delta: float, width: int, col: str = "v") -> DataFrame:
    """Truncated backward fractional difference: needs `width` steps on the left."""
    total = F.lit(0.0)
    for k, w in enumerate(frac_weights(delta, width)):
        total = total + (lagged(blocks, col, k) if k else F.col(col)).cast("double") * F.lit(w)
    return blocks.withColumn("y", total).where("is_core and y is not null").select("idx", "y")


def fir(blocks: DataFrame, weights: list[float], col: str = "v") -> DataFrame:
    """Weighted sums of the last len(weights) values, newest first: idx, y, where all of them exist in the block."""
    total = F.lit(0.0)
    for k, w in enumerate(weights):
        total = total + (lagged(blocks, col, k) if k else F.col(col)).cast("double") * F.lit(float(w))
    return blocks.withColumn("y", total).where("is_core and y is not null").select("idx", "y")


def frac_tail(delta: float, width: int, far: int = 100_000) -> float:
    """Mass of the weights that truncation drops (those up to `far`)."""
    return sum(abs(x) for x in frac_weights(delta, far)[width + 1 :])


def integration_order(acf_of, most: int = 2, limit: float = 0.9) -> tuple[int, list[tuple[int, float]]]:
    """Difference until the first correlation lies under `limit`. acf_of(order) gives the lag-1 correlation."""
    seen = []
    for k in range(most + 1):
        r = acf_of(k)
        seen.append((k, r))
        if r < limit:
            return k, seen
    return most, seen
