"""Meshes with cell halos, map points with radius halos, time by dimension products."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halo.operators.blocks import time_blocks
from halo.operators.grid import floor_div


def mesh_blocks(df: DataFrame, axes: list[str], sizes: list[int], halo: int) -> DataFrame:
    """One explode an axis: block_<axis> columns and is_core. Blocks without core rows are dropped by the kernel's core filter."""
    out, core = df, F.lit(True)
    for a, size in zip(axes, sizes):
        lo, hi = floor_div(F.col(a) - halo, size), floor_div(F.col(a) + halo, size)
        out = out.withColumn(f"block_{a}", F.explode(F.sequence(lo, hi)))
        core = core & (F.col(f"block_{a}") == floor_div(F.col(a), size))
    return out.withColumn("is_core", core).repartition(*[f"block_{a}" for a in axes])


def stencil(blocks: DataFrame, axes: tuple[str, str], offsets: dict[tuple[int, int], int], value: str = "v") -> DataFrame:
    """Weighted sums over neighbour cells that exist, inside each block: no exchange after the layout.

    Rows that repeat a cell add up for its neighbours and get a result each; a null value counts as 0.
    """
    bx, by = f"block_{axes[0]}", f"block_{axes[1]}"
    whole = dict(blocks.dtypes)[value] in ("tinyint", "smallint", "int", "bigint") and all(isinstance(w, int) for w in offsets.values())
    kind = "bigint" if whole else "double"

    def run(table: pa.Table) -> pa.Table:
        x, y = (table.column(a).to_numpy().astype(np.int64) for a in axes)
        v = np.nan_to_num(table.column(value).to_numpy(zero_copy_only=False).astype(np.float64))
        core = table.column("is_core").to_numpy(zero_copy_only=False).astype(bool)
        reach = max(max(abs(a), abs(b)) for a, b in offsets) + 1
        width = int(y.max() - y.min()) + 2 * reach
        cell = (x - x.min()) * width + (y - y.min())
        names, place = np.unique(cell, return_inverse=True)
        total = np.bincount(place, v)
        out = np.zeros(int(core.sum()))
        for (a, b), w in offsets.items():
            want = cell[core] + a * width + b
            at = np.minimum(np.searchsorted(names, want), len(names) - 1)
            out += w * np.where(names[at] == want, total[at], 0.0)
        result = out.astype(np.int64) if whole else out
        return pa.table({axes[0]: table.column(axes[0]).filter(pa.array(core)), axes[1]: table.column(axes[1]).filter(pa.array(core)), "y": pa.array(result)})

    kinds = dict(blocks.dtypes)
    needed = blocks.select(bx, by, *axes, value, "is_core")
    return needed.groupBy(bx, by).applyInArrow(run, f"{axes[0]} {kinds[axes[0]]}, {axes[1]} {kinds[axes[1]]}, y {kind}")


def point_blocks(df: DataFrame, x: str, y: str, cell: float, radius: float) -> DataFrame:
    """Grid cells with copies of the points whose distance to the cell's box is within the radius."""
    cx, cy = F.floor(F.col(x) / cell), F.floor(F.col(y) / cell)
    reach = int(-(-radius // cell))
    near = F.sequence(F.lit(-reach), F.lit(reach))
    out = df.withColumn("_cx", cx).withColumn("_cy", cy).withColumn("bx", F.explode(F.transform(near, lambda o: F.col("_cx") + o)))
    out = out.withColumn("by", F.explode(F.transform(near, lambda o: F.col("_cy") + o)))
    dx = F.greatest(F.lit(0.0), F.col("bx") * cell - F.col(x), F.col(x) - (F.col("bx") + 1) * cell)
    dy = F.greatest(F.lit(0.0), F.col("by") * cell - F.col(y), F.col(y) - (F.col("by") + 1) * cell)
    out = out.where(dx * dx + dy * dy <= radius * radius)
    return out.withColumn("is_core", (F.col("bx") == F.col("_cx")) & (F.col("by") == F.col("_cy"))).drop("_cx", "_cy")


def within_radius(blocks: DataFrame, key: str, x: str, y: str, radius: float) -> DataFrame:
    """Neighbours of each core point within the radius: key, n."""
    a = blocks.where("is_core").select("bx", "by", F.col(key).alias("a"), F.col(x).alias("ax"), F.col(y).alias("ay"))
    b = blocks.select("bx", "by", F.col(key).alias("b"), F.col(x).alias("qx"), F.col(y).alias("qy"))
    near = (F.col("ax") - F.col("qx")) * (F.col("ax") - F.col("qx")) + (F.col("ay") - F.col("qy")) * (F.col("ay") - F.col("qy")) <= radius * radius
    pairs = a.join(b, ["bx", "by"]).where(near & (F.col("a") != F.col("b"))).groupBy("a").agg(F.count(F.lit(1)).alias("n"))
    return a.select("a").join(pairs, "a", "left").select(F.col("a").alias(key), F.coalesce("n", F.lit(0)).cast("bigint").alias("n"))


def cross_time_dim(wide: DataFrame, size: int, left: int, right: int, plan) -> DataFrame:
    """Time blocks of dimension blocks: keys (block, dblk)."""
    from halo.models.banded import cut_dims

    cut = cut_dims(wide, plan)
    return time_blocks(cut, size, left, right, keys=("dblk",))
