"""Banded one-step models over dimension blocks: prediction, likelihood and fits by rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dim_blocks(d: int, n_blocks: int, bandwidth: int) -> list[tuple[int, int, int, int, int]]:
    """(block, first, last, halo first, halo last) of row blocks; last is exclusive."""
    edges = [d * k // n_blocks for k in range(n_blocks + 1)]
    return [(k, edges[k], edges[k + 1], max(0, edges[k] - bandwidth), min(d, edges[k + 1] + bandwidth)) for k in range(n_blocks)]


def cut_dims(wide: DataFrame, plan: list[tuple[int, int, int, int, int]]) -> DataFrame:
    """One row for each (row of `wide`, dimension block) with the slice the block needs, and its core limits."""
    parts = F.array(*[F.struct(F.lit(b).alias("dblk"), F.lit(f).alias("first"), F.lit(t).alias("last"), F.lit(lo).alias("lo"), F.slice("x", lo + 1, hi - lo).alias("x")) for b, f, t, lo, hi in plan])
    keep = [c for c in wide.columns if c != "x"]
    return wide.select(*keep, F.explode(parts).alias("p")).select(*keep, "p.*")


def stencil_matrix(d: int, left: float, centre: float, right: float) -> np.ndarray:
    """Tridiagonal transition of an explicit scheme (advection and diffusion)."""
    return np.diag(np.full(d, centre)) + np.diag(np.full(d - 1, right), 1) + np.diag(np.full(d - 1, left), -1)


def predict(wide: DataFrame, a: np.ndarray, bandwidth: int, n_blocks: int) -> DataFrame:
    """Rows idx, dim, yhat of A x by row blocks: O(d (2b + 1)) products, no exchange."""
    d = len(a)
    cut = cut_dims(wide, dim_blocks(d, n_blocks, bandwidth))

    def run(batches):
        for batch in batches:
            cols = {n: batch.column(k) for k, n in enumerate(batch.schema.names)}
            idx, dims, out = [], [], []
            for k in range(batch.num_rows):
                f, t, lo = (cols[n][k].as_py() for n in ("first", "last", "lo"))
                x = np.asarray(cols["x"][k].values)
                idx.append(np.full(t - f, cols["idx"][k].as_py()))
                dims.append(np.arange(f, t))
                out.append(a[f:t, lo : lo + len(x)] @ x)
            if idx:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(idx), pa.int64()), pa.array(np.concatenate(dims), pa.int32()), pa.array(np.concatenate(out), pa.float64())], ["idx", "dim", "yhat"])

    return cut.select("idx", "first", "last", "lo", "x").mapInArrow(run, "idx bigint, dim int, yhat double")


def predict_stencil(wide: DataFrame, weights: dict[int, float]) -> DataFrame:
    """The same with constant bands, inside code generation: sum of shifted entries."""
    rows = wide.select("idx", "x", F.posexplode("x").alias("dim", "_v"))
    total = F.lit(0.0)
    for o, w in sorted(weights.items()):
        inside = (F.col("dim") + o >= 0) & (F.col("dim") + o < F.size("x"))
        total = total + F.when(inside, F.get("x", F.col("dim") + o) * F.lit(w)).otherwise(0.0)
    return rows.select("idx", "dim", total.alias("yhat"))


def predict_fn(wide: DataFrame, fn, d: int, bandwidth: int, n_blocks: int) -> DataFrame:
    """A general local map: fn(block, slice) gives the core values of the next step."""
    cut = cut_dims(wide, dim_blocks(d, n_blocks, bandwidth))

    def run(keys, table):
        b, f = keys[0].as_py(), table.column("first")[0].as_py()
        got = [np.asarray(fn(b, np.asarray(v.values))) for v in table.column("x")]
        idx = table.column("idx").to_numpy()
        n = len(got[0])
        return pa.table({"idx": pa.array(np.repeat(idx, n), pa.int64()), "dim": pa.array(np.tile(np.arange(f, f + n), len(idx)), pa.int32()), "yhat": pa.array(np.concatenate(got), pa.float64())})

    return cut.groupBy("dblk").applyInArrow(run, "idx bigint, dim int, yhat double")


def _matrix(table: pa.Table):
    idx = table.column("idx").to_numpy()
    x = table.column("x").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(idx), -1)
    o = np.argsort(idx)
    return idx[o], x[o], table.column("first")[0].as_py(), table.column("last")[0].as_py(), table.column("lo")[0].as_py()


def fit(wide: DataFrame, d: int, bandwidth: int, n_blocks: int, method: str = "normal", steps: int = 200, centre: bool = True) -> DataFrame:
    """Own parameters by row block: the whole fit inside one group, no communication. Rows dblk, i, j, value, sigma2.

    method 'normal' solves each row's regression on its 2b + 1 columns; 'gradient' descends on the masked block.
    """
    cut = cut_dims(wide, dim_blocks(d, n_blocks, bandwidth))

    def run(keys, table):
        idx, x, f, t, lo = _matrix(table)
        x = x - x.mean(axis=0) if centre else x
        pair = np.flatnonzero(np.diff(idx) == 1)
        z, y = x[pair], x[pair + 1][:, f - lo : t - lo]
        rows, cols, vals, var = [], [], [], []
        for r in range(t - f):
            i = f + r
            near = [c for c in range(max(0, i - bandwidth), min(d, i + bandwidth + 1))]
            q = z[:, [c - lo for c in near]]
            if method == "normal":
                w = np.linalg.lstsq(q, y[:, r], rcond=None)[0]
            else:
                w, g = np.zeros(len(near)), q.T @ q / max(1, len(q))
                e = np.linalg.eigvalsh(g)
                for _ in range(steps):
                    w = w + 2 / (e[0] + e[-1]) * (q.T @ y[:, r] / len(q) - g @ w)
            s2 = float(((y[:, r] - q @ w) ** 2).mean()) if len(q) else 0.0
            rows += [i] * len(near)
            cols += near
            vals += w.tolist()
            var += [s2] * len(near)
        return pa.table({"dblk": pa.array([keys[0].as_py()] * len(rows), pa.int32()), "i": pa.array(rows, pa.int32()), "j": pa.array(cols, pa.int32()), "value": pa.array(vals, pa.float64()), "sigma2": pa.array(var, pa.float64())})

    return cut.groupBy("dblk").applyInArrow(run, "dblk int, i int, j int, value double, sigma2 double")


def sums_by_block(long: DataFrame, n: int, plan: list[tuple[int, int, int, int, int]], d: int, bandwidth: int, size: int) -> DataFrame:
    """Regression sums of every row over time blocks of `size` by dimension blocks: dblk, i, k, s.

    `long` (idx, dim, v) is a grid of steps 0..n-1 whose absent cells are 0. One shuffle deals the sparse cells to
    (time, dimension) blocks with their halos; a block holds size x |P_i+| numbers, whatever n and d are. Sums of row
    i over its w = 2 b + 1 columns, in order of k: products of columns (w x w), products with the next value (w), its
    square, sums of columns over pairs (w), of next values, and over all steps (w).
    """
    edges = F.array(*[F.lit(f) for _, f, _, _, _ in plan])
    own = F.size(F.filter(edges, lambda e: e <= F.col("dim"))) - 1
    near = F.array_distinct(F.transform(F.sequence(F.greatest(F.col("dim") - bandwidth, F.lit(0)), F.least(F.col("dim") + bandwidth, F.lit(d - 1))), lambda c: F.size(F.filter(edges, lambda e: e <= c)) - 1))
    cells = long.where((F.col("idx") >= 0) & (F.col("idx") < n) & F.col("v").isNotNull())
    cells = cells.withColumn("dblk", F.explode(F.when(F.lit(bandwidth) > 0, near).otherwise(F.array(own))))
    tblk = F.call_function("div", F.col("idx"), F.lit(size))
    first = F.call_function("div", F.greatest(F.col("idx") - 1, F.lit(0)), F.lit(size))
    dealt = cells.select("idx", "dim", F.col("v").cast("double").alias("v"), "dblk", F.explode(F.sequence(first, tblk)).alias("tblk"))
    w = 2 * bandwidth + 1

    def run(keys, table):
        b, t = keys[0].as_py(), keys[1].as_py()
        _, f, last, lo, hi = plan[b]
        steps = min(size + 1, n - t * size)  # one step of halo on the right
        x = np.zeros((steps, hi - lo + 2 * bandwidth))  # columns beyond the series are 0
        np.add.at(x, (table.column("idx").to_numpy() - t * size, table.column("dim").to_numpy() - lo + bandwidth), table.column("v").to_numpy())
        past, nxt, core = x[:-1], x[1:], x[: min(size, steps)]
        rows, sums = [], []
        for i in range(f, last):
            at = slice(i - lo, i - lo + w)
            z, y = past[:, at], nxt[:, i - lo + bandwidth]
            s = np.concatenate([(z.T @ z).ravel(), z.T @ y, [y @ y], z.sum(axis=0), [y.sum()], core[:, at].sum(axis=0)])
            rows.append(np.full(len(s), i))
            sums.append(s)
        s = np.concatenate(sums)
        return pa.table({"dblk": pa.array(np.full(len(s), b), pa.int32()), "i": pa.array(np.concatenate(rows), pa.int32()), "k": pa.array(np.tile(np.arange(len(sums[0])), len(sums)), pa.int32()), "s": pa.array(s, pa.float64())})

    parts = dealt.groupBy("dblk", "tblk").applyInArrow(run, "dblk int, i int, k int, s double")
    return parts.groupBy("dblk", "i", "k").agg(F.sum("s").alias("s"))


def fit_sums(long: DataFrame, n: int, d: int, bandwidth: int, n_blocks: int, size: int = 256, centre: bool = True) -> DataFrame:
    """Own parameters of every row from sums over (time, dimension) blocks: rows dblk, i, j, value, sigma2.

    Equal to `fit` on the whole grid of n steps, but no task holds a dimension block's whole time axis. Rows whose
    columns are all 0 get 0; a row of dimensions without any data in its block is not listed.
    """
    plan, w = dim_blocks(d, n_blocks, bandwidth), 2 * bandwidth + 1
    sums = sums_by_block(long, n, plan, d, bandwidth, size)

    def solve(keys, table):
        i, k, s = (table.column(c).to_numpy() for c in ("i", "k", "s"))
        names, place = np.unique(i, return_inverse=True)
        flat = np.zeros((len(names), int(k.max(initial=0)) + 1))
        flat[place, k] = s
        out = {c: [] for c in ("i", "j", "value", "sigma2")}
        for r, own in zip(names.tolist(), flat):
            zz, zy, yy, sz, sy, total = np.split(own, np.cumsum([w * w, w, 1, w, 1]))
            zz, m = zz.reshape(w, w), total / n * float(centre)
            mu, pairs = m[bandwidth], n - 1
            zz = zz - np.outer(m, sz) - np.outer(sz, m) + pairs * np.outer(m, m)
            zy = zy - m * sy[0] - mu * sz + pairs * mu * m
            yy = yy[0] - 2 * mu * sy[0] + pairs * mu * mu
            inside = [c for c in range(w) if 0 <= r + c - bandwidth < d]
            a = np.linalg.lstsq(zz[np.ix_(inside, inside)], zy[inside], rcond=None)[0]
            s2 = max(0.0, float(yy - 2 * a @ zy[inside] + a @ zz[np.ix_(inside, inside)] @ a)) / max(pairs, 1)
            out["i"] += [r] * len(inside)
            out["j"] += [r + c - bandwidth for c in inside]
            out["value"] += a.tolist()
            out["sigma2"] += [s2] * len(inside)
        kinds = {"i": pa.int32(), "j": pa.int32(), "value": pa.float64(), "sigma2": pa.float64()}
        return pa.table({"dblk": pa.array([keys[0].as_py()] * len(out["i"]), pa.int32()), **{c: pa.array(v, kinds[c]) for c, v in out.items()}})

    return sums.groupBy("dblk").applyInArrow(solve, "dblk int, i int, j int, value double, sigma2 double")


def fit_shared_sums(long: DataFrame, n: int, d: int, bandwidth: int, n_blocks: int, size: int = 256) -> np.ndarray:
    """One weight for each offset, shared by all rows, about the means: its normal equations are the rows' sums added up."""
    w = 2 * bandwidth + 1
    sums = sums_by_block(long, n, dim_blocks(d, n_blocks, bandwidth), d, bandwidth, size)
    # About the mean each row's sums need their own corrections, so they are made row by row before the total.
    spread = [F.sum(F.when(F.col("k") == k, F.col("s"))).alias(f"s{k}") for k in range(w * w + 3 * w + 2)]
    rows = sums.groupBy("i").agg(*spread)
    zy0, sz0, t0 = w * w, w * w + w + 1, w * w + 2 * w + 2
    mean = [F.col(f"s{t0 + a}") / n for a in range(w)]
    cells = []
    for a in range(w):
        for b in range(w):
            c = F.col(f"s{a * w + b}") - mean[a] * F.col(f"s{sz0 + b}") - mean[b] * F.col(f"s{sz0 + a}") + (n - 1) * mean[a] * mean[b]
            cells.append(F.sum(c).alias(f"zz{a}_{b}"))
        y = F.col(f"s{zy0 + a}") - mean[a] * F.col(f"s{t0 - 1}") - mean[bandwidth] * F.col(f"s{sz0 + a}") + (n - 1) * mean[bandwidth] * mean[a]
        cells.append(F.sum(y).alias(f"zy{a}"))
    got = rows.agg(*cells).head()
    zz = np.array([[got[f"zz{a}_{b}"] for b in range(w)] for a in range(w)])
    return np.linalg.solve(zz, np.array([got[f"zy{a}"] for a in range(w)]))


def reorder(wide: DataFrame, order: list[int]) -> DataFrame:
    """Dimensions in the given order (from linalg's reverse breadth-first ordering, say), so that couplings lie near the diagonal."""
    return wide.withColumn("x", F.array(*[F.col("x")[k] for k in order]))


def fit_shared(wide: DataFrame, d: int, bandwidth: int, n_blocks: int, steps: int = 30, centre: bool = True) -> tuple[np.ndarray, list[tuple[int, float]]]:
    """One weight for each offset, shared by all rows: gradients of the blocks are added, weights sent back."""
    cut = cut_dims(wide, dim_blocks(d, n_blocks, bandwidth)).persist()
    theta, trace, size = np.zeros(2 * bandwidth + 1), [], None
    for k in range(steps):

        def run(keys, table):
            idx, x, f, t, lo = _matrix(table)
            x = x - x.mean(axis=0) if centre else x
            pair = np.flatnonzero(np.diff(idx) == 1)
            z = np.zeros((len(pair), t - f, 2 * bandwidth + 1))
            for o in range(-bandwidth, bandwidth + 1):
                for r in range(t - f):
                    c = f + r + o
                    if 0 <= c < d:
                        z[:, r, o + bandwidth] = x[pair][:, c - lo]
            y = x[pair + 1][:, f - lo : t - lo]
            r = y - z @ theta
            flat = np.concatenate([[0.5 * (r**2).sum(), len(pair) * (t - f)], -np.einsum("nr,nrk->k", r, z), np.einsum("nra,nrb->ab", z, z).ravel()])
            return pa.table({"k": pa.array(np.arange(len(flat)), pa.int32()), "s": pa.array(flat, pa.float64())})

        got = cut.groupBy("dblk").applyInArrow(run, "k int, s double").groupBy("k").agg(F.sum("s").alias("s")).collect()
        flat = np.zeros(len(got))
        for r in got:
            flat[r.k] = r.s
        n, w = flat[1], len(theta)
        if size is None:
            e = np.linalg.eigvalsh(flat[2 + w :].reshape(w, w) / n)
            size = 2 / (e[0] + e[-1])
        trace.append((k, flat[0] / n))
        theta = theta - size * flat[2 : 2 + w] / n
    cut.unpersist()
    return theta, trace


def loglik(wide: DataFrame, a: np.ndarray, pi_blocks: list[np.ndarray], bandwidth: int) -> DataFrame:
    """Block-diagonal precision: the likelihood splits over blocks. Rows dblk, quad, n, logdet."""
    d, n_blocks = len(a), len(pi_blocks)
    cut = cut_dims(wide, dim_blocks(d, n_blocks, bandwidth))

    def run(keys, table):
        idx, x, f, t, lo = _matrix(table)
        pair = np.flatnonzero(np.diff(idx) == 1)
        r = x[pair + 1][:, f - lo : t - lo] - x[pair] @ a[f:t, lo : lo + x.shape[1]].T
        pi = pi_blocks[keys[0].as_py()]
        return pa.table({"dblk": pa.array([keys[0].as_py()], pa.int32()), "quad": pa.array([float(np.einsum("ni,ij,nj->", r, pi, r))], pa.float64()), "n": pa.array([len(pair)], pa.int64()), "logdet": pa.array([float(np.linalg.slogdet(pi)[1])], pa.float64())})

    return cut.groupBy("dblk").applyInArrow(run, "dblk int, quad double, n bigint, logdet double")
