"""Kernels that see a block as one matrix, and reductions of what they give.

A kernel gets (index, core mask, matrix) of a block, sorted by index, and knows nothing of partitions:
the same function serves one serial block, Arrow groups and micro-batches.

Defined results: a datum whose index or vector is null, or that holds a null, NaN or infinite component, is
absent, like a gap of the series; two data of one index in a block raise RepeatedIndex, vectors of different
lengths ValueError.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import _parse_datatype_string

from halo.operators.blocks import HaloTooShort

class RepeatedIndex(ValueError):
    """Pairs by lag are not defined where an index has two data."""


Kernel = Callable[[np.ndarray, np.ndarray, np.ndarray], dict[str, np.ndarray]]


def check_reach(reach: int, halo: int) -> None:
    if reach > halo:
        raise HaloTooShort(f"kernel reaches {reach}, halo holds {halo}")


def unpack(table: pa.Table, on: str = "idx") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    there = pc.and_(pc.is_valid(table.column(on)), pc.is_valid(table.column("x")))
    if not pc.all(there).as_py():
        table = table.filter(there)
    idx = table.column(on).to_numpy()
    core = table.column("is_core").to_numpy(zero_copy_only=False) if "is_core" in table.column_names else np.ones(len(idx), bool)
    x = table.column("x").combine_chunks()
    if len(idx) and len(set(np.diff(x.offsets.to_numpy()).tolist())) > 1:
        raise ValueError("vectors of different lengths")
    m = x.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(idx), -1) if len(idx) else np.zeros((0, 0))
    finite = np.isfinite(m).all(axis=1)
    if not finite.all():
        idx, core, m = idx[finite], core[finite], m[finite]
    order = np.argsort(idx, kind="stable")
    idx = idx[order]
    if (np.diff(idx) == 0).any():
        raise RepeatedIndex(f"index {int(idx[np.flatnonzero(np.diff(idx) == 0)[0]])} has several data")
    return idx, core[order].astype(bool), m[order]


def partner(idx: np.ndarray, at: np.ndarray, lag: int) -> tuple[np.ndarray, np.ndarray]:
    """Those positions `at` whose datum `lag` steps on exists, and its position; gaps of the index are allowed."""
    where = np.searchsorted(idx, idx[at] + lag)
    found = where < len(idx)
    found[found] = idx[where[found]] == idx[at][found] + lag
    return at[found], where[found]


def map_groups(blocks: DataFrame, kernel: Kernel, schema: str, on: str = "idx", by: tuple[str, ...] = ("block",)) -> DataFrame:
    """One call of `kernel` for each block; its arrays become rows, with the block's keys in front."""
    full = ", ".join(f"{k} {dict(blocks.dtypes)[k]}" for k in by) + ", " + schema
    target = to_arrow_schema(_parse_datatype_string(full))

    def run(keys: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        out = kernel(*unpack(table, on))
        n = len(next(iter(out.values()))) if out else 0
        columns = {k: pa.array([v.as_py()] * n, v.type) for k, v in zip(by, keys)}
        columns |= {k: pa.array(v if not isinstance(v, np.ndarray) or v.ndim == 1 else list(v)) for k, v in out.items()}
        return pa.table(columns).cast(target)

    return blocks.groupBy(*by).applyInArrow(run, full)


def map_core(blocks: DataFrame, fn: Callable[[np.ndarray], np.ndarray], left: int, right: int, halo: tuple[int, int], out: str = "y") -> DataFrame:
    """fn on the window (x_{t-left}..x_{t+right}) of every core datum whose window exists: idx and an array."""
    check_reach(left, halo[0])
    check_reach(right, halo[1])

    def kernel(idx, core, x):
        keep, values = [], []
        for k in np.flatnonzero(core):
            lo, hi = k - left, k + right
            if lo >= 0 and hi < len(idx) and idx[hi] - idx[lo] == left + right:
                keep.append(idx[k])
                values.append(np.atleast_1d(fn(x[lo : hi + 1])).astype(float))
        return {"idx": np.array(keep, np.int64), out: values}

    return map_groups(blocks, kernel, f"idx bigint, {out} array<double>").select("idx", out)


def map_reduce(blocks: DataFrame, kernel: Kernel, schema: str, keys: tuple[str, ...], sums: tuple[str, ...], reach: int = 0, halo: int | None = None, fanout: int = 0) -> DataFrame:
    """Sum of what `kernel` gives over all blocks, by `keys`; in two levels when `fanout` is given."""
    if halo is not None:
        check_reach(reach, halo)
    parts = map_groups(blocks, kernel, schema)
    return tree_reduce(parts, keys, sums, fanout) if fanout else parts.groupBy(*keys).agg(*[F.sum(s).alias(s) for s in sums])


def tree_reduce(parts: DataFrame, keys: tuple[str, ...], sums: tuple[str, ...], fanout: int) -> DataFrame:
    half = parts.groupBy(*keys, F.pmod("block", F.lit(fanout)).alias("_t")).agg(*[F.sum(s).alias(s) for s in sums])
    return half.groupBy(*keys).agg(*[F.sum(s).alias(s) for s in sums])


def apply_estimator(blocks: DataFrame, fit: Callable[[np.ndarray], np.ndarray], merge: str = "averaged") -> DataFrame:
    """An estimator that knows nothing of blocks, run on each block's core; results averaged by core size.

    Averages of estimates are not the estimate from all data: the result says so in `how`.
    """

    def kernel(idx, core, x):
        est = np.ravel(fit(x[core]))
        return {"part": np.arange(len(est), dtype=np.int64), "w": np.full(len(est), float(core.sum())), "s": est * core.sum()}

    got = map_groups(blocks, kernel, "part bigint, w double, s double")
    return got.groupBy("part").agg((F.sum("s") / F.sum("w")).alias("value")).withColumn("how", F.lit(merge))
