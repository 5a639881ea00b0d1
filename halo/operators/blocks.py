"""Overlapping blocks: every datum is core in one block and copied to the blocks whose halo reaches it."""

from __future__ import annotations

import math
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from halo.operators.grid import floor_div
from halo.plans import scratch


class HaloTooShort(ValueError):
    """A kernel asks for more neighbours than the layout holds."""


def required_halo(p: int = 0, q: int = 0, depth: int | None = None) -> int:
    """AR needs p, MA needs q, ARMA p + q; a deeper recursion needs its depth."""
    return max(p + q, depth or 0)


def plan_size(row_bytes: int, halo: int, target_bytes: int = 128 << 20, max_replication: float = 1.05) -> int:
    """Block length that fits the target and keeps (B + 2H) / B within bounds."""
    least = math.ceil(2 * halo / (max_replication - 1)) if halo else 1
    return max(least, target_bytes // max(1, row_bytes))


def time_blocks(df: DataFrame, size: int, left: int, right: int, origin: int = 0, on: str = "idx", partitions: int | None = None, keys: tuple[str, ...] = (), bounds: tuple[int, int] | None = None) -> DataFrame:
    """`df` with block and is_core; one shuffle, none after it for kernels by block.

    A datum at i lies in block b when b * size - left <= i - origin < (b + 1) * size + right. Blocks
    without a core datum at either end are not made. `on` may be an index or microseconds; rows where it is
    null take no part. `bounds`: first and last index where they are known, which saves a pass over the input.
    """
    low_end, high_end = bounds or df.agg(F.min(on), F.max(on)).head()
    place = F.col(on) - F.lit(origin)
    if low_end is None:
        return df.withColumn("block", F.lit(0).cast("bigint")).withColumn("is_core", F.lit(True))
    first, last = (low_end - origin) // size, (high_end - origin) // size
    low = F.greatest(F.lit(first), floor_div(place - F.lit(right), size))
    high = F.least(F.lit(last), floor_div(place + F.lit(left), size))
    # An empty array, not a filter: the optimizer would carry a filter, and the arithmetic of the index, down to every input row.
    blocks = F.when(low <= high, F.sequence(low.cast("bigint"), high.cast("bigint"))).otherwise(F.array().cast("array<bigint>"))
    out = df.withColumn("block", F.explode(blocks))
    out = out.withColumn("is_core", F.col("block") == floor_div(place, size))
    by = [*keys, "block"]
    return (out.repartition(partitions, *by) if partitions else out.repartition(*by)).sortWithinPartitions(*by, on)


def save(blocks: DataFrame, name: str, buckets: int, on: str = "idx") -> None:
    """A bucketed table: later kernels by block read it without a shuffle."""
    blocks.write.mode("overwrite").bucketBy(buckets, "block").sortBy("block", on).saveAsTable(name)


def load(spark: SparkSession, name: str, between: tuple[int, int] | None = None) -> DataFrame:
    df = spark.table(name)
    return df.where(F.col("block").between(*between)) if between else df


def store(blocks: DataFrame, path: str, group: int = 64) -> None:
    """A layout as files, partitioned by block_group: readers of a range of blocks prune the others."""
    blocks.withColumn("block_group", floor_div(F.col("block"), group)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("block_group").parquet(path)


def stored(spark: SparkSession, path: str, between: tuple[int, int] | None = None, group: int = 64) -> DataFrame:
    """A stored layout, or its blocks first..last."""
    df = spark.read.parquet(path)
    if between is None:
        return df
    first, last = between
    return df.where(F.col("block_group").between(first // group, last // group) & F.col("block").between(first, last))


def append(df: DataFrame, path: str, size: int, left: int, right: int, group: int = 64, origin: int = 0, on: str = "idx") -> None:
    """Add rows of any index to a layout stored at `path`: the result equals the layout of all rows.

    Blocks that the new rows reach, and those that come to be because the series grew, are laid out anew
    from the new rows and the core rows around them, in whole groups; other groups stay untouched. The new
    groups are written beside `path` first and then exchanged from there, so a lost executor repeats its
    task on files that nobody changes. Rows that repeat an index are rows of their own.
    """
    spark = df.sparkSession
    lo, hi = df.agg(F.min(on), F.max(on)).head()
    if lo is None:
        return
    old = spark.read.parquet(path)
    core = old.where("is_core")
    ends = core.agg(F.min(on), F.max(on)).head()
    if ends[0] is None:
        return store(time_blocks(df, size, left, right, origin, on), path, group)
    bounds = min(lo, ends[0]), max(hi, ends[1])
    first, last = (bounds[0] - origin) // size, (bounds[1] - origin) // size
    a, b = (lo - origin - right) // size, (hi - origin + left) // size
    if hi > ends[1]:
        a = min(a, (ends[1] - origin) // size + 1)
    if lo < ends[0]:
        b = max(b, (ends[0] - origin) // size - 1)
    a, b = max(first, a) // group * group, min(last, b) // group * group + group - 1
    near = core.where(F.col(on).between(origin + a * size - left, origin + (b + 1) * size + right - 1))
    reach = floor_div(F.col("block"), group) == F.col("block_group")  # true; keeps the partition column in the plan
    near = near.where(reach & F.col("block_group").between((a - -(-left // size)) // group, (b + -(-right // size)) // group))
    rows = near.select(*df.columns).unionByName(df)
    fresh = time_blocks(rows, size, left, right, origin, on, bounds=bounds).where(F.col("block").between(a, b))
    beside = f"{path.rstrip('/')}-{uuid.uuid4().hex}"
    try:
        store(fresh, beside, group)
        whole = spark.read.parquet(beside)
        whole.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("block_group").parquet(path)
    finally:
        scratch.remove(spark, beside)


def report(blocks: DataFrame) -> DataFrame:
    """Per block: stored and core rows."""
    return blocks.groupBy("block").agg(F.count(F.lit(1)).alias("stored"), F.count_if("is_core").alias("core"))


def replication(blocks: DataFrame) -> DataFrame:
    return report(blocks).agg(F.count(F.lit(1)).alias("blocks"), F.sum("stored").alias("stored"), F.sum("core").alias("core"), (F.sum("stored") / F.sum("core")).alias("replication"))


def lagged(blocks: DataFrame, col: str, lag: int, on: str = "idx") -> Column:
    """Value `lag` steps earlier inside the block (negative: later), null where the grid has no such step."""
    w = Window.partitionBy("block").orderBy(on)
    value, where = F.lag(col, lag).over(w), F.lag(on, lag).over(w)
    return F.when(where == F.col(on) - F.lit(lag), value)
