"""Regular grids from events, dense and wide forms, gaps, alignment, ordinal indexes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from halo.plans import scratch
from halo.sources.ingest import SeriesSpec, micros


def floor_div(a: Column, b: int) -> Column:
    """Integer floor of a / b for negative numbers too."""
    return F.call_function("div", a - F.pmod(a, F.lit(b)), F.lit(b))


def index(ts: Column, step_us: int, origin_us: int) -> Column:
    return floor_div(micros(ts) - F.lit(origin_us), step_us)


def regular(df: DataFrame, spec: SeriesSpec, dim: Column | None = None, value: Column | None = None) -> DataFrame:
    """Rows idx, dim, v: one aggregate for each step and dimension that has data."""
    d = F.lit(0) if dim is None else dim
    agg = F.count(F.lit(1)) if spec.how == "count" else getattr(F, spec.how)(value if value is not None else F.col(spec.value))
    return df.groupBy(index(F.col(spec.time), spec.step_us, spec.origin_us).alias("idx"), d.cast("int").alias("dim")).agg(agg.alias("v"))


def dense(long: DataFrame, n: int, d: int, fill=0, first: int = 0) -> DataFrame:
    """Every (idx, dim) of the grid; absent cells get `fill` (None keeps them null)."""
    spark = long.sparkSession
    cells = spark.range(first, first + n).select(F.col("id").alias("idx"), F.explode(F.sequence(F.lit(0), F.lit(d - 1))).alias("dim"))
    kind = dict(long.dtypes)["v"]
    out = cells.join(long, ["idx", "dim"], "left")
    return out if fill is None else out.withColumn("v", F.coalesce("v", F.lit(fill).cast(kind)))


def to_wide(long: DataFrame, d: int, fill: float = 0.0) -> DataFrame:
    """Rows idx, x. Few dimensions are conditional sums; many are gathered sparse and scattered once in an Arrow batch."""
    if d <= 64:
        cells = [F.sum(F.when(F.col("dim") == k, F.col("v").cast("double"))) for k in range(d)]
        return long.groupBy("idx").agg(F.transform(F.array(*cells), lambda x: F.coalesce(x, F.lit(fill))).alias("x"))
    per = long.groupBy("idx", "dim").agg(F.sum(F.col("v").cast("double")).alias("v")).where("v is not null")
    packed = per.groupBy("idx").agg(F.collect_list("dim").alias("dims"), F.collect_list("v").alias("vals"))  # both in the same order
    return scatter(packed, d, fill)


def scatter(packed: DataFrame, d: int, fill: float = 0.0) -> DataFrame:
    """Rows idx, x of length d from sparse rows idx, dims, vals; entries outside 0..d-1 are an error."""

    def run(batches):
        for batch in batches:
            for s in range(0, batch.num_rows, max(1, 4_000_000 // d)):
                part = batch.slice(s, max(1, 4_000_000 // d))
                dims, vals = part.column(1), part.column(2).flatten().to_numpy(zero_copy_only=False)
                n = np.diff(dims.offsets.to_numpy())
                at = dims.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
                if len(at) and (at.min() < 0 or at.max() >= d):
                    raise ValueError(f"a dimension lies outside 0..{d - 1}")
                x = np.full((part.num_rows, d), fill)
                x[np.repeat(np.arange(part.num_rows), n), at] = vals
                rows = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, d), pa.int32()), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([part.column(0), rows], ["idx", "x"])

    return packed.select("idx", "dims", "vals").mapInArrow(run, f"idx {dict(packed.dtypes)['idx']}, x array<double>")


def to_long(wide: DataFrame) -> DataFrame:
    return wide.select("idx", F.posexplode("x").alias("dim", "v"))


def gaps(long: DataFrame, n: int, first: int = 0) -> DataFrame:
    """Steps of the grid without a row."""
    return long.sparkSession.range(first, first + n).select(F.col("id").alias("idx")).join(long.select("idx").distinct(), "idx", "left_anti")


SUPER = 4096


def running(rows: DataFrame, key: str, value: str, how: str, reverse: bool = False) -> DataFrame:
    """Over one row for each integer `key`: what comes strictly before it (after it, if reversed): key, before.

    how 'last': the nearest value that is not null; 'sum': the total. Keys are taken in groups of SUPER, and only
    one row a group is ordered in a single task.
    """
    order = F.desc(key) if reverse else F.col(key)
    grouped = rows.select(key, value, floor_div(F.col(key), SUPER).alias("_g"))
    inside = Window.partitionBy("_g").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    across = Window.orderBy(F.desc("_g") if reverse else F.col("_g")).rowsBetween(Window.unboundedPreceding, -1)
    if how == "sum":
        ends = grouped.groupBy("_g").agg(F.sum(value).alias("_e")).select("_g", F.sum("_e").over(across).alias("_c"))
        near = grouped.withColumn("_n", F.sum(value).over(inside)).join(ends, "_g")
        zero = F.lit(0)
        return near.select(key, (F.coalesce("_n", zero) + F.coalesce("_c", zero)).alias("before"))
    pick = F.min_by if reverse else F.max_by
    known = grouped.where(F.col(value).isNotNull()).groupBy("_g").agg(pick(value, key).alias("_e"))
    ends = grouped.select("_g").distinct().join(known, "_g", "left").select("_g", F.last("_e", ignorenulls=True).over(across).alias("_c"))
    near = grouped.withColumn("_n", F.last(value, ignorenulls=True).over(inside)).join(ends, "_g")
    return near.select(key, F.coalesce("_n", "_c").alias("before"))


def _block_edge(df: DataFrame, size: int, last: bool) -> DataFrame:
    """Per block: nearest known value before (or after) it, from the table of block ends (one row a block)."""
    b = df.where("v is not null").groupBy(floor_div(F.col("idx"), size).alias("block"))
    pick = F.max_by if last else F.min_by
    ends = b.agg(pick(F.struct("idx", "v"), "idx").alias("e"))
    every = df.select(floor_div(F.col("idx"), size).alias("block")).distinct().join(ends, "block", "left")
    return running(every, "block", "e", "last", not last).select("block", F.col("before").alias("carry"))


def locf(long: DataFrame, size: int = 256) -> DataFrame:
    """Last value carried forward within blocks, with the carry-in of earlier blocks: idx, v, is_filled."""
    rows = long.withColumn("block", floor_div(F.col("idx"), size))
    carry = _block_edge(long, size, True)
    w = Window.partitionBy("block").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    out = rows.withColumn("_l", F.last("v", ignorenulls=True).over(w)).join(carry, "block", "left")
    return out.select("idx", F.coalesce("_l", F.col("carry.v")).alias("v"), (F.col("v").isNull()).alias("is_filled"))


def linear(long: DataFrame, size: int = 256) -> DataFrame:
    """Linear interpolation between the known neighbours; ends stay null."""
    rows = long.withColumn("block", floor_div(F.col("idx"), size)).withColumn("_e", F.when(F.col("v").isNotNull(), F.struct("idx", "v")))
    before, after = _block_edge(long, size, True).withColumnRenamed("carry", "cb"), _block_edge(long, size, False).withColumnRenamed("carry", "ca")
    up = Window.partitionBy("block").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    down = Window.partitionBy("block").orderBy("idx").rowsBetween(0, Window.unboundedFollowing)
    out = rows.withColumn("_a", F.last("_e", ignorenulls=True).over(up)).withColumn("_b", F.first("_e", ignorenulls=True).over(down))
    out = out.join(before, "block", "left").join(after, "block", "left")
    a, b = F.coalesce("_a", "cb"), F.coalesce("_b", "ca")
    span = b["idx"] - a["idx"]
    value = F.when(F.col("v").isNotNull(), F.col("v").cast("double")).otherwise(a["v"] + (b["v"] - a["v"]) * (F.col("idx") - a["idx"]) / span)
    return out.select("idx", value.alias("v"), F.col("v").isNull().alias("is_filled"))


def ordinal_index(df: DataFrame, order: list[str], partitions: int | None = None) -> DataFrame:
    """Dense 0-based idx by `order` (ties in any order): one range shuffle, written once and numbered where it lies.

    The written table fixes which row is in which range, so counts and numbers agree after a lost executor too.
    """
    spark = df.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
    placed = df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_m", F.monotonically_increasing_id())
    placed = scratch.stash(placed, scratch.folder(spark) + "/placed")
    part, row = F.shiftright("_m", 33), F.col("_m").bitwiseAND(F.lit((1 << 33) - 1))
    offsets = running(placed.groupBy(part.alias("_p")).agg(F.count(F.lit(1)).alias("n")), "_p", "n", "sum")  # one row a partition
    both = placed.withColumn("_p", part).join(F.broadcast(offsets), "_p")
    return both.withColumn("idx", (F.col("before") + row).cast("bigint")).drop("_m", "_p", "before")


def resolve_duplicates(long: DataFrame, how: str = "last", order: str | None = None) -> DataFrame:
    """One row for each (idx, dim): by 'sum', 'mean', 'min', 'max', or the 'first' / 'last' by column `order` (ties: the larger v)."""
    if how in ("first", "last"):
        pick = F.max_by if how == "last" else F.min_by
        return long.groupBy("idx", "dim").agg(pick("v", F.struct(order, "v") if order else F.struct("v")).alias("v"))
    return long.groupBy("idx", "dim").agg(getattr(F, {"mean": "avg"}.get(how, how))("v").alias("v"))


def clip(df: DataFrame, col: str, low: float = 0.001, high: float = 0.999) -> DataFrame:
    """Values outside two quantiles moved onto them."""
    a, b = df.approxQuantile(col, [low, high], 0.0005)
    return df.withColumn(col, F.greatest(F.lit(a), F.least(F.lit(b), F.col(col))))


def asof(left: DataFrame, right: DataFrame, on: str, value: str, size: int) -> DataFrame:
    """Last `value` of `right` at or before each row of `left`: union, last known inside blocks, carry-in between them."""
    rows = left.select(F.col(on).alias("t"), F.struct(*left.columns).alias("l"), F.lit(None).cast(right.schema[value].dataType).alias("v"), F.lit(1).alias("side"))
    known = right.select(F.col(on).alias("t"), F.lit(None).cast(rows.schema["l"].dataType).alias("l"), F.col(value).alias("v"), F.lit(0).alias("side"))
    both = rows.unionByName(known).withColumn("block", floor_div(F.col("t"), size))
    ends = known.where("v is not null").groupBy(floor_div(F.col("t"), size).alias("block")).agg(F.max_by("v", "t").alias("e"))
    every = both.select("block").distinct().join(ends, "block", "left")
    carry = running(every, "block", "e", "last").select("block", F.col("before").alias("carry"))
    w = Window.partitionBy("block").orderBy("t", "side").rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn("_v", F.last("v", ignorenulls=True).over(w)).where("side = 1").join(carry, "block", "left")
    return out.select("l.*", F.coalesce("_v", "carry").alias(value))
