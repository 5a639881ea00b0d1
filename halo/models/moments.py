"""Means, covariances and correlations from block-local lag products; exact when the data are integers.

For each lag h: P_h = sum x_k x_{k+h}^T over core k whose partner exists, n_h pairs, u_h and v_h the
sums of the two sides. Everything else is algebra on these. They add up over blocks, batches and streams.
"""

from __future__ import annotations

from dataclasses import dataclass
from decimal import ROUND_HALF_UP, Context, Decimal
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import _parse_datatype_string

from halo.functions import linalg
from halo.operators import kernels
from halo.plans import scratch

LAG_ROWS = "lag int, i int, j int, n double, s double, u double, v double"
WIDE = Context(prec=400)  # digits for any finite double


def lag_kernel(max_lag: int, entries: str | tuple = "all"):
    """Staged kernel: the block is one contiguous matrix, each lag one product of two slices of it."""

    def run(idx, core, x):
        d = x.shape[1] if x.size else 0
        out = {k: [] for k in ("lag", "i", "j", "n", "s", "u", "v")}
        for h in range(max_lag + 1):
            a, b = kernels.partner(idx, np.flatnonzero(core), h)
            left, right = x[a], x[b]
            u, v = left.sum(axis=0), right.sum(axis=0)
            if entries == "diag":
                i = j = np.arange(d)
                s = np.einsum("ti,ti->i", left, right)
            elif isinstance(entries, tuple):
                i, j = np.nonzero(np.abs(np.subtract.outer(np.arange(d), np.arange(d))) <= entries[1])
            else:
                i, j = (m.ravel() for m in np.indices((d, d)))
            if entries != "diag":
                s = (left.T @ right)[i, j]
            out["lag"].append(np.full(len(i), h)), out["i"].append(i), out["j"].append(j), out["n"].append(np.full(len(i), float(len(a))))
            out["s"].append(s), out["u"].append(u[i]), out["v"].append(v[j])
        return {k: np.concatenate(c) if c else np.zeros(0) for k, c in out.items()}

    return run


def lag_products(blocks: DataFrame, max_lag: int, halo: int, entries="all", backend: str = "arrow", fanout: int = 0) -> DataFrame:
    """Rows lag, i, j, n, s, u, v summed over all blocks."""
    kernels.check_reach(max_lag, halo)
    if backend == "arrow":
        return kernels.map_reduce(blocks, lag_kernel(max_lag, entries), LAG_ROWS, ("lag", "i", "j"), ("n", "s", "u", "v"), fanout=fanout)
    w = Window.partitionBy("block").orderBy("idx")
    lags = F.array(*[F.when(F.lead("idx", h).over(w) == F.col("idx") + h, F.lead("x", h).over(w)) if h else F.col("x") for h in range(max_lag + 1)])
    rows = blocks.withColumn("y", lags).where("is_core").select("x", F.posexplode("y").alias("lag", "z")).where("z is not null")
    pairs = rows.select("lag", F.posexplode("x").alias("i", "a"), "z").select("lag", "i", "a", F.posexplode("z").alias("j", "b"))
    if entries == "diag":
        pairs = pairs.where("i = j")
    return pairs.groupBy("lag", "i", "j").agg(F.count(F.lit(1)).cast("double").alias("n"), F.sum(F.col("a") * F.col("b")).alias("s"), F.sum("a").alias("u"), F.sum("b").alias("v"))


def whole_lag_products(blocks: DataFrame, max_lag: int, halo: int) -> DataFrame:
    """Rows lag, i, j, n, s of series of whole numbers as 64-bit integers: exact where sums of doubles are not.

    A component that is no whole number below 2^53 and a sum beyond 64 bits are errors, never rounded.
    """
    kernels.check_reach(max_lag, halo)

    def run(idx, core, x):
        if (np.abs(x) >= 2**53).any() or (x != np.floor(x)).any():
            raise ValueError("a component is no whole number below 2^53")
        z = x.astype(np.int64)
        out = {k: [] for k in ("lag", "i", "j", "n", "s")}
        for h in range(max_lag + 1):
            a, b = kernels.partner(idx, np.flatnonzero(core), h)
            if (np.abs(x[a]).T @ np.abs(x[b])).max(initial=0) >= 2**62:
                raise OverflowError("a block's lag product is beyond 64 bits")
            i, j = (m.ravel() for m in np.indices((x.shape[1], x.shape[1])))
            out["lag"].append(np.full(len(i), h)), out["i"].append(i), out["j"].append(j), out["n"].append(np.full(len(i), len(a)))
            out["s"].append((z[a].T @ z[b]).ravel())
        return {k: np.concatenate(c) for k, c in out.items()}

    parts = kernels.map_groups(blocks, run, "lag int, i int, j int, n bigint, s bigint")
    return parts.groupBy("lag", "i", "j").agg(F.sum("n").alias("n"), F.sum(F.col("s").cast("decimal(38,0)")).cast("bigint").alias("s"))


def lag_tiles(blocks: DataFrame, max_lag: int, halo: int, tile: int = 128) -> DataFrame:
    """Lag products of wide series by square tiles: lag, ti, tj, n and matrices s (tile x tile), u, v as bytes.

    What a block gives is added up inside each partition before the one small shuffle by tile, so that shuffle
    grows with partitions and d^2, not with blocks, and no row stands for a single entry.
    """
    kernels.check_reach(max_lag, halo)
    schema = "lag int, ti int, tj int, n double, s binary, u binary, v binary"
    target = to_arrow_schema(_parse_datatype_string(schema))
    names = target.names

    def kernel(table: pa.Table) -> pa.Table:
        idx, core, x = kernels.unpack(table)
        rows = []
        cuts = range(0, x.shape[1] if x.size else 0, tile)
        for h in range(max_lag + 1):
            a, b = kernels.partner(idx, np.flatnonzero(core), h)
            left, right = x[a], x[b]
            for p in cuts:
                for q in cuts:
                    y, z = left[:, p : p + tile], right[:, q : q + tile]
                    rows.append((h, p // tile, q // tile, float(len(a)), (y.T @ z).tobytes(), y.sum(axis=0).tobytes(), z.sum(axis=0).tobytes()))
        return pa.table([pa.array(c) for c in zip(*rows)] if rows else [pa.array([])] * 7, names).cast(target)

    def added(tables) -> dict:
        total: dict[tuple, list] = {}
        for table in tables:
            for h, p, q, n, *parts in zip(*(c.to_pylist() for c in table.columns)):
                own = total.setdefault((h, p, q), [0.0, 0.0, 0.0, 0.0])
                own[0] += n
                for k, part in enumerate(parts, 1):
                    own[k] = own[k] + np.frombuffer(part)
        return total

    def batch(total: dict) -> pa.RecordBatch:
        rows = [(*k, v[0], *(np.asarray(m).tobytes() for m in v[1:])) for k, v in total.items()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), target.types)], names)

    def combine(batches):
        total = added(batches)
        if total:
            yield batch(total)

    def final(table: pa.Table) -> pa.Table:
        return pa.Table.from_batches([batch(added([table]))])

    parts = blocks.groupBy("block").applyInArrow(kernel, schema).mapInArrow(combine, schema)
    return parts.groupBy("lag", "ti", "tj").applyInArrow(final, schema)


def tile_covariances(tiles: DataFrame, mean: np.ndarray, length: int, denom: str = "printed", tile: int = 128) -> DataFrame:
    """Covariances lag, i, j, value of all tiles; a tile's entries never meet on the driver."""

    def run(batches):
        for b in batches:
            for h, p, q, n, s, u, v in zip(*(c.to_pylist() for c in b.columns)):
                u, v = np.frombuffer(u), np.frombuffer(v)
                s, mu, nu = np.frombuffer(s).reshape(len(u), len(v)), mean[p * tile :][: len(u)], mean[q * tile :][: len(v)]
                c = (s - np.outer(u, nu) - np.outer(mu, v) + n * np.outer(mu, nu)) / {"printed": n - 1, "pairs": n, "n": length}[denom]
                i, j = (m.ravel() for m in np.indices(c.shape))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(c.size, h), pa.int32()), pa.array(i + p * tile, pa.int32()), pa.array(j + q * tile, pa.int32()), pa.array(c.ravel(), pa.float64())], ["lag", "i", "j", "value"])

    return tiles.mapInArrow(run, "lag int, i int, j int, value double")


def _slab(idx, dim, v, length: int) -> tuple[np.ndarray, np.ndarray]:
    """The dimensions of some rows and their series of whole numbers, absent cells zero; rows off the grid name a dimension only."""
    names, column = np.unique(dim, return_inverse=True)
    x, on = np.zeros((length, len(names)), np.int64), (idx >= 0) & (idx < length)
    np.add.at(x, (idx[on], column[on]), v[on])
    return names, x


def _centred(s, n: int, u, v, left, right, length: int) -> np.ndarray:
    """Covariances (printed form) of whole numbers: exact up to one division."""
    top = length * length * float(np.abs(s).max(initial=0)) + 2 * length * float(np.abs(u).max(initial=0)) * float(np.abs(right).max(initial=0)) + 2 * length * float(np.abs(left).max(initial=0)) * float(np.abs(v).max(initial=0)) + n * float(np.abs(left).max(initial=0)) * float(np.abs(right).max(initial=0))
    kind = np.int64 if top < 2**62 else object
    s, u, v, left, right = (np.asarray(a).astype(kind) for a in (s, u, v, left, right))
    return (length * length * s - length * (u * right + left * v) + n * left * right).astype(float) / (float(length * length) * (n - 1))


def diagonal_covariances(long: DataFrame, length: int, max_lag: int, width: int = 256) -> DataFrame:
    """Covariances lag, i, value of every dimension of `long` (idx, dim, v: counts) with itself on the grid 0..length-1.

    The series are cut along dimensions: entries of two slabs never meet, and a task holds length x width numbers however
    many dimensions there are.
    """
    schema = "lag int, i int, value double"
    target = to_arrow_schema(_parse_datatype_string(schema))

    def run(table: pa.Table) -> pa.Table:
        names, x = _slab(*(table.column(k).to_numpy() for k in ("idx", "dim", "v")), length)
        whole, out = x.sum(axis=0), {"lag": [], "i": [], "value": []}
        for h in range(max_lag + 1):
            a, b = x[: length - h], x[h:]
            out["lag"].append(np.full(len(names), h)), out["i"].append(names)
            out["value"].append(_centred(np.einsum("ti,ti->i", a, b), length - h, a.sum(axis=0), b.sum(axis=0), whole, whole, length))
        return pa.table({k: pa.array(np.concatenate(c)) for k, c in out.items()}).cast(target)

    rows = long.where("dim is not null and v is not null").select(F.floor(F.col("dim") / F.lit(width)).cast("bigint").alias("slab"), "idx", "dim", "v")
    return rows.groupBy("slab").applyInArrow(run, schema)


def rounded(x: np.ndarray, digits: int) -> np.ndarray:
    """What Spark's round gives: the shortest decimal of each double, half away from zero."""
    y = x * 10.0**digits
    r = np.rint(y)
    out = r / 10.0**digits + 0.0  # no negative zero
    near = np.abs(np.abs(y - r) - 0.5) <= np.abs(y) * 2.0**-50  # a tie, but for the error of the product
    out[near] = [float(Decimal(repr(v)).quantize(Decimal(1).scaleb(-digits), ROUND_HALF_UP, WIDE)) for v in x[near].tolist()]
    return out


def wide_covariances(long: DataFrame, length: int, max_lag: int, root: str, width: int = 1024, digits: int | None = None) -> DataFrame:
    """Covariances lag, i, j, value of all pairs of dimensions of `long` (idx, dim, v: counts) on the grid 0..length-1.

    A slab of `width` dimensions is packed into one sparse row, and each pair of slabs is one task of its own: it holds
    two length x width matrices and width x width products, however many dimensions there are. Slabs are dealt once, one
    to a partition, and a task reads its two from there: what lies on disk grows with the slabs, not with their pairs.
    """
    names = ["dims", "at", "dim", "v"]
    short = {k: "<u2" if top <= 2**16 else "<i4" for k, top in (("at", length), ("dim", width))}

    def pack(table: pa.Table) -> pa.Table:
        idx, dim, v = (table.column(k).to_numpy() for k in ("idx", "dim", "v"))
        dims, column = np.unique(dim, return_inverse=True)
        on = (idx >= 0) & (idx < length)
        counts = v[on]
        kind = next(k for k in ("<i1", "<i2", "<i4", "<i8") if len(counts) == 0 or np.iinfo(k).min <= counts.min() and counts.max() <= np.iinfo(k).max)
        parts = dims.astype("<i8"), idx[on].astype(short["at"]), column[on].astype(short["dim"]), counts.astype(kind)
        return pa.table({"slab": table.column("slab").slice(0, 1), **{k: pa.array([p.tobytes()], pa.binary()) for k, p in zip(names, parts)}})

    rows = long.where("dim is not null and v is not null").select(F.floor(F.col("dim") / F.lit(width)).cast("bigint").alias("slab"), "idx", "dim", "v")
    packed = scratch.stash(rows.groupBy("slab").applyInArrow(pack, "slab bigint, " + ", ".join(f"{k} binary" for k in names)), f"{root}/slabs")
    places = [(r.slab, k) for k, r in enumerate(packed.select("slab").collect())]
    place = packed.sparkSession.createDataFrame(places, "slab bigint, place int")
    dealt = packed.join(F.broadcast(place), "slab").repartitionById(max(1, len(places)), "place")
    left, right = (dealt.select(*[F.col(k).alias(side + k) for k in names]) for side in ("x_", "y_"))
    schema = "lag int, i int, j int, value double"
    target = to_arrow_schema(_parse_datatype_string(schema))

    def matrix(row: dict, side: str) -> tuple[np.ndarray, np.ndarray]:
        dims = np.frombuffer(row[side + "dims"], "<i8")
        at, dim = (np.frombuffer(row[side + k], short[k]) for k in ("at", "dim"))
        x = np.zeros((length, len(dims)))
        np.add.at(x, (at, dim), np.frombuffer(row[side + "v"], f"<i{max(1, len(row[side + 'v']) // max(1, len(at)))}"))
        return dims.astype(np.int32), x

    def entries(row: dict):
        (i, x), (j, y) = matrix(row, "x_"), matrix(row, "y_")
        if length * float(np.abs(x).max(initial=0)) * float(np.abs(y).max(initial=0)) >= 2**53:
            raise ValueError("lag products of these counts are not exact in doubles")
        sx, sy = x.sum(axis=0), y.sum(axis=0)
        for h in range(max_lag + 1):
            a, b = x[: length - h], y[h:]
            s, u, v = a.T @ b, a.sum(axis=0), b.sum(axis=0)
            for k in range(0, len(i), 64):
                part = slice(k, k + 64)
                c = _centred(s[part], length - h, u[part, None], v[None, :], sx[part, None], sy[None, :], length).ravel()
                c = c if digits is None else rounded(c, digits)
                columns = np.full(c.size, h, np.int32), np.repeat(i[part], len(j)), np.tile(j, len(i[part])), c
                yield pa.RecordBatch.from_arrays([pa.array(z) for z in columns], schema=target)

    def run(batches):
        for batch in batches:
            for k in range(batch.num_rows):
                yield from entries(batch.slice(k, 1).to_pylist()[0])

    return left.hint("shuffle_replicate_nl").crossJoin(right).mapInArrow(run, schema)


@dataclass
class Moments:
    """Lag products on the driver: p, n, u, v by lag; merge adds two disjoint parts."""

    p: np.ndarray
    n: np.ndarray
    u: np.ndarray
    v: np.ndarray

    @staticmethod
    def collect(rows: DataFrame) -> "Moments":
        got = rows.select("lag", "i", "j", "n", "s", "u", "v").toArrow()
        lag, i, j, count, s, left, right = (got.column(k).to_numpy() for k in range(7))
        H, d = int(lag.max(initial=0)) + 1, int(i.max(initial=-1)) + 1
        p, n, u, v = np.zeros((H, d, d)), np.zeros(H), np.zeros((H, d)), np.zeros((H, d))
        p[lag, i, j], n[lag], u[lag, i], v[lag, j] = s, count, left, right
        return Moments(p, n, u, v)

    def merge(self, other: "Moments", sign: int = 1) -> "Moments":
        return Moments(*(a + sign * b for a, b in zip((self.p, self.n, self.u, self.v), (other.p, other.n, other.u, other.v))))

    @property
    def mean(self) -> np.ndarray:
        return self.u[0] / self.n[0]

    def autocov(self, denom: str = "printed") -> np.ndarray:
        """G(0..H). denom: 'printed' n_h - 1, 'pairs' n_h, 'n' the length of the series."""
        N, total, out = int(self.n[0]), self.u[0], []
        whole = all(float(x).is_integer() for x in self.u[0]) and np.abs(self.p).max(initial=0) < 2**52
        for h in range(len(self.p)):
            den = {"printed": self.n[h] - 1, "pairs": self.n[h], "n": N}[denom]
            if whole:  # exact integers up to one division by N^2
                S, u, v = [int(x) for x in total], [int(x) for x in self.u[h]], [int(x) for x in self.v[h]]
                c = [[N * N * int(self.p[h, i, j]) - N * (u[i] * S[j] + S[i] * v[j]) + int(self.n[h]) * S[i] * S[j] for j in range(len(S))] for i in range(len(S))]
                out.append(np.array([[float(Fraction(x)) / (float(N) * N) / den for x in row] for row in c]))
            else:
                mu = self.mean
                out.append((self.p[h] - np.outer(self.u[h], mu) - np.outer(mu, self.v[h]) + self.n[h] * np.outer(mu, mu)) / den)
        return np.array(out)


def at(g: np.ndarray, h: int) -> np.ndarray:
    return linalg.at_lag(g, h)


def rows_of(g: np.ndarray) -> list[tuple[int, int, int, float]]:
    return [(h, i, j, float(g[h, i, j])) for h in range(g.shape[0]) for i in range(g.shape[1]) for j in range(g.shape[2])]


def window_form(blocks: DataFrame, H: int, N: int, mean: np.ndarray, halo: int, denom: str = "printed") -> np.ndarray:
    """All lags -H..H from centres with a whole window: biased, asymptotically unbiased. Shape (2H+1, d, d)."""
    kernels.check_reach(H, halo)

    def run(idx, core, x):
        z = x - mean
        out = {k: [] for k in ("lag", "i", "j", "s")}
        a = np.flatnonzero(core)
        a = a[(a >= H) & (a + H < len(idx))]
        a = a[idx[a + H] - idx[a - H] == 2 * H]
        for h in range(-H, H + 1):
            i, j = (m.ravel() for m in np.indices((x.shape[1], x.shape[1])))
            out["lag"].append(np.full(len(i), h)), out["i"].append(i), out["j"].append(j), out["s"].append((z[a].T @ z[a + h])[i, j])
        return {k: np.concatenate(v) for k, v in out.items()}

    got = kernels.map_reduce(blocks, run, "lag int, i int, j int, s double", ("lag", "i", "j"), ("s",)).collect()
    d = len(mean)
    g = np.zeros((2 * H + 1, d, d))
    for r in got:
        g[r.lag + H, r.i, r.j] = r.s / (N - (2 * H + 1) if denom == "printed" else N - 2 * H)
    return g


def mean(long: DataFrame) -> DataFrame:
    return long.groupBy("dim").agg(F.avg("v").alias("mean"))


def center(wide: DataFrame, mu: np.ndarray) -> DataFrame:
    return wide.withColumn("x", F.zip_with("x", F.array(*[F.lit(float(m)) for m in mu]), lambda a, b: a - b))


def acf(g: np.ndarray) -> np.ndarray:
    """Correlations; a constant dimension gives NaN."""
    s = np.sqrt(np.diag(g[0]))
    with np.errstate(divide="ignore", invalid="ignore"):
        return g / np.outer(s, s)


def ccf(r: np.ndarray, i: int, j: int) -> np.ndarray:
    return r[:, i, j]


def pacf(g: np.ndarray, top: int, method: str = "recursive") -> list[np.ndarray]:
    if method == "recursive":
        return linalg.block_levinson(g, top)[2]
    return [linalg.solve_projection(g, p)[-1] for p in range(1, top + 1)]


def projection(g: np.ndarray, p: int) -> list[np.ndarray]:
    return linalg.solve_projection(g, p)


def band(n: int, level: float = 0.95) -> float:
    return linalg.normal_quantile(0.5 + level / 2) / np.sqrt(n)


def gram_kernel(p: int):
    """M_jk = sum over t of x_{t-j} x_{t-k}^T for core t with p predecessors."""

    def run(idx, core, x):
        t = np.flatnonzero(core)
        t = t[t >= p]
        t = t[idx[t] - idx[t - p] == p]
        d = x.shape[1]
        out = {k: [] for k in ("a", "b", "i", "j", "s", "n")}
        for a in range(p + 1):
            for b in range(p + 1):
                i, j = (m.ravel() for m in np.indices((d, d)))
                out["a"].append(np.full(d * d, a)), out["b"].append(np.full(d * d, b)), out["i"].append(i), out["j"].append(j)
                out["s"].append((x[t - a].T @ x[t - b]).ravel()), out["n"].append(np.full(d * d, float(len(t))))
        return {k: np.concatenate(v) for k, v in out.items()}

    return run


def lag_gram(blocks: DataFrame, p: int, halo: int) -> DataFrame:
    kernels.check_reach(p, halo)
    return kernels.map_reduce(blocks, gram_kernel(p), "a int, b int, i int, j int, s double, n double", ("a", "b", "i", "j"), ("s", "n"))


def gram_matrix(rows: DataFrame, p: int, d: int) -> tuple[np.ndarray, int]:
    m, n = np.zeros((p + 1, p + 1, d, d)), 0.0
    for r in rows.collect():
        m[r.a, r.b, r.i, r.j], n = r.s, r.n
    return m, int(n)
