"""Windows in time units on irregular data: around every datum, around given centres, pair products by lag slot."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from halo.operators.grid import floor_div


def window_stats(blocks: DataFrame, half: int, on: str = "ts_us", col: str = "v") -> DataFrame:
    """n, total, least, largest of rows within `half` of each core datum."""
    w = Window.partitionBy("block").orderBy(on).rangeBetween(-half, half)
    out = blocks.select("*", F.count(col).over(w).alias("n"), F.sum(col).over(w).alias("total"), F.min(col).over(w).alias("least"), F.max(col).over(w).alias("largest"))
    return out.where("is_core").select(on, "n", "total", "least", "largest")


def at_centres(blocks: DataFrame, centres: DataFrame, half: int, size: int, origin: int = 0, method: str = "range", stride: int = 32, on: str = "ts_us", col: str = "v") -> DataFrame:
    """n and total of data within `half` of arbitrary centres (column c).

    'range': centres join their block's rows in one range window. 'search', 'index', 'scan': block-local
    sorted arrays with binary search, with a sampled index and a short scan, or with a full scan.
    """
    placed = centres.select(F.col("c"), floor_div(F.col("c") - F.lit(origin), size).alias("block"))
    if method == "range":
        data = blocks.select("block", F.col(on).alias("t"), F.col(col).alias("v"), F.lit(0).alias("q"))
        asked = placed.select("block", F.col("c").alias("t"), F.lit(None).cast(dict(data.dtypes)["v"]).alias("v"), F.lit(1).alias("q"))
        w = Window.partitionBy("block").orderBy("t").rangeBetween(-half, half)
        out = data.unionByName(asked).select("t", "q", F.count("v").over(w).alias("n"), F.sum("v").over(w).alias("total"))
        return out.where("q = 1").select(F.col("t").alias("c"), "n", F.coalesce("total", F.lit(0)).alias("total"))

    def run(keys: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        t, v, c = left.column(on).to_numpy(), left.column(col).to_numpy(), right.column("c").to_numpy()
        o = np.argsort(t, kind="stable")
        t, v = t[o], v[o]
        sums = np.concatenate([[0], np.cumsum(v)])
        if method == "scan":
            lo = np.array([(t < x - half).sum() for x in c], int)
            hi = np.array([(t <= x + half).sum() for x in c], int)
        elif method == "index":
            marks = t[::stride]

            def place(x, right_side):
                k = max(0, int(np.searchsorted(marks, x, "right" if right_side else "left")) - 1) * stride
                while k < len(t) and (t[k] <= x if right_side else t[k] < x):
                    k += 1
                return k

            lo = np.array([place(x - half, False) for x in c], int)
            hi = np.array([place(x + half, True) for x in c], int)
        else:
            lo, hi = np.searchsorted(t, c - half, "left"), np.searchsorted(t, c + half, "right")
        return pa.table({"c": pa.array(c, pa.int64()), "n": pa.array(hi - lo, pa.int64()), "total": pa.array((sums[hi] - sums[lo]).astype(np.int64), pa.int64())})

    return blocks.groupBy("block").cogroup(placed.groupBy("block")).applyInArrow(run, "c bigint, n bigint, total bigint")


def slot_autocov(blocks: DataFrame, bin_us: int, n_bins: int, on: str = "ts_us", col: str = "v") -> DataFrame:
    """Sums of products of pairs i < j by floor((t_j - t_i) / bin): slot, n, s. The pair belongs to its first datum."""
    reach = bin_us * n_bins

    def run(keys: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        t, v = table.column(on).to_numpy(), table.column(col).to_numpy().astype(np.int64)
        core = table.column("is_core").to_numpy(zero_copy_only=False)
        o = np.argsort(t, kind="stable")
        t, v, core = t[o], v[o], core[o]
        n, s = np.zeros(n_bins, np.int64), np.zeros(n_bins, np.int64)
        for i in np.flatnonzero(core):
            j = np.arange(i + 1, np.searchsorted(t, t[i] + reach, "left"))
            b = (t[j] - t[i]) // bin_us
            n += np.bincount(b, minlength=n_bins)
            np.add.at(s, b, v[i] * v[j])
        return pa.table({"slot": pa.array(np.arange(n_bins), pa.int32()), "n": pa.array(n, pa.int64()), "s": pa.array(s, pa.int64())})

    return blocks.groupBy("block").applyInArrow(run, "slot int, n bigint, s bigint").groupBy("slot").agg(F.sum("n").alias("n"), F.sum("s").alias("s"))
