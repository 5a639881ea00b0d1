"""Graph blocks with hop halos, time by graph products, statistics and traffic kernels on them."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import _parse_datatype_string

from halo.models.process import uniform
from halo.operators.blocks import HaloTooShort, time_blocks
from halo.operators.kernels import check_reach as check_lag, partner
from halo.plans import scratch

Kernel = Callable[[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray], dict[str, np.ndarray]]


def assign(vertices: DataFrame, policy: str, n: int, edges: DataFrame | None = None, rounds: int = 3) -> DataFrame:
    """v, gblk by 'hash', 'range', a column 'region', or 'spread' (labels flow along edges to the majority)."""
    if policy == "hash":
        return vertices.select("v", F.pmod(F.xxhash64("v"), F.lit(n)).cast("int").alias("gblk"))
    if policy == "range":
        top = vertices.agg(F.max("v").alias("m")).head().m or 0
        return vertices.select("v", F.floor(F.col("v") * n / (top + 1)).cast("int").alias("gblk"))
    if policy == "region":
        return vertices.select("v", F.col("region").cast("int").alias("gblk"))
    out = assign(vertices, "range", n)
    both = edges.select("src", "dst").union(edges.select("dst", "src"))
    for _ in range(rounds):
        votes = both.join(out.withColumnRenamed("v", "src"), "src").groupBy("dst", "gblk").agg(F.count(F.lit(1)).alias("m"))
        best = votes.groupBy(F.col("dst").alias("v")).agg(F.max_by("gblk", F.struct("m", -F.col("gblk"))).alias("g"))
        out = out.join(best, "v", "left").select("v", F.coalesce("g", "gblk").alias("gblk"))
    return out


def hop_blocks(edges: DataFrame, owners: DataFrame, k: int, directed: str = "both") -> DataFrame:
    """gblk, v, hop, is_core: own vertices and everything within k hops (least hop)."""
    step = {"parents": edges.select(F.col("dst").alias("v"), F.col("src").alias("w")), "children": edges.select(F.col("src").alias("v"), F.col("dst").alias("w"))}
    step["both"] = step["parents"].union(step["children"])
    nxt = step[directed].distinct()
    seen = owners.select("gblk", "v", F.lit(0).alias("hop"))
    front = seen
    for h in range(1, k + 1):
        reached = front.join(nxt, "v").select("gblk", F.col("w").alias("v")).distinct().withColumn("hop", F.lit(h))
        front = reached.join(seen.select("gblk", "v"), ["gblk", "v"], "left_anti")
        seen = seen.union(front)
    return seen.withColumn("is_core", F.col("hop") == 0)


def cross_blocks(states: DataFrame, size: int, h: int, gblocks: DataFrame, bounds: tuple[int, int] | None = None) -> DataFrame:
    """(tblk, gblk) blocks of states (v, idx, x): both halos, both core flags."""
    t = time_blocks(states, size, h, h, bounds=bounds).withColumnsRenamed({"block": "tblk", "is_core": "t_core"})
    out = t.join(gblocks.select("gblk", "v", F.col("is_core").alias("g_core"), "hop"), "v")
    return out.repartition("tblk", "gblk")


def block_edges(edges: DataFrame, gblocks: DataFrame) -> DataFrame:
    """Edges with both ends in a block."""
    a = gblocks.select("gblk", F.col("v").alias("src"))
    b = gblocks.select("gblk", F.col("v").alias("dst"))
    return edges.join(a, "src").join(b, ["gblk", "dst"]).select("gblk", "src", "dst")


def check_reach(hops: int, halo: int) -> None:
    if hops > halo:
        raise HaloTooShort(f"kernel reaches {hops} hops, halo holds {halo}")


def pair_sums(cross: DataFrame, edges_in: DataFrame, lags: int, reach: int = 1, hops: int = 1, halo: int | None = None) -> DataFrame:
    """Sums of x_t^v x_{t+h}^u over vertices u that are 0..hops directed edges from v: h, hop, n, s.

    Runs inside the (time, graph) blocks; one state for each (v, idx). s has the type of a sum of x.
    """

    def kernel(v, idx, core, x, dist):
        out = {k: [] for k in ("h", "hop", "n", "s")}
        own, there, value = core & ~np.isnan(x), ~np.isnan(x), np.nan_to_num(x)
        for h in range(lags + 1):
            a, b = partner(idx, np.arange(len(idx)), h)
            count, total = own[a].astype(float).T @ there[b].astype(float), np.where(own, value, 0.0)[a].T @ value[b]
            for k in range(hops + 1):
                near = dist == k
                out["h"].append(h), out["hop"].append(k), out["n"].append(int(count[near].sum())), out["s"].append(float(total[near].sum()))
        return {k: np.array(c, np.float64 if k == "s" else np.int64) for k, c in out.items()}

    kind = cross.select(F.sum("x")).dtypes[0][1]
    got = map_reduce(cross, edges_in, kernel, "h int, hop int, n bigint, s double", ("h", "hop"), ("n", "s"), (lags, hops), (lags if halo is None else halo, reach))
    return got.where("n > 0").select("h", "hop", "n", F.col("s").cast(kind).alias("s"))


#: Edges of all blocks up to this many travel with the kernel; more are brought to the blocks by a cogroup.
CLOSURE_EDGES = 200_000


def distances(v: np.ndarray, src: np.ndarray, dst: np.ndarray, own: np.ndarray, hops: int) -> np.ndarray:
    """Directed distances up to `hops` between vertices v (sorted) of which one end is `own`, else -1."""
    there = np.isin(src, v) & np.isin(dst, v)
    step = np.zeros((len(v), len(v)), bool)
    step[np.searchsorted(v, src[there]), np.searchsorted(v, dst[there])] = True
    dist = np.where(np.eye(len(v), dtype=bool), 0, -1)
    front = np.eye(len(v), dtype=bool)
    for k in range(1, hops + 1):
        front = ((front.astype(np.float32) @ step.astype(np.float32)) > 0) & (dist < 0)
        dist[front] = k
    dist[~(own[:, None] | own[None, :])] = -1
    return dist


def map_blocks(cross: DataFrame, edges_in: DataFrame, kernel: Kernel, schema: str, order: tuple[int, int], halo: tuple[int, int]) -> DataFrame:
    """One call of kernel(v, idx, core, x, dist) for each (time, graph) block; its arrays become rows.

    x[t, k] is the state of v[k] at idx[t], NaN where absent; core marks what the block owns; dist[a, b] is the
    directed distance where it is at most K and one end is core, else -1. `order` is the kernel's (H, K). Paths are
    followed inside the block, from its edges (gblk, src, dst): states are not exchanged again.
    """
    check_lag(order[0], halo[0])
    check_reach(order[1], halo[1])
    target = to_arrow_schema(_parse_datatype_string(schema))
    wires = edges_in.select("gblk", "src", "dst")

    def result(states: pa.Table, src: np.ndarray, dst: np.ndarray) -> pa.Table:
        at, t = states.column("v").to_numpy(), states.column("idx").to_numpy()
        v, idx = np.unique(at), np.unique(t)
        place = np.searchsorted(idx, t), np.searchsorted(v, at)
        x, core, own = np.full((len(idx), len(v)), np.nan), np.zeros((len(idx), len(v)), bool), np.zeros(len(v), bool)
        x[place] = states.column("x").to_numpy()
        mine = states.column("g_core").to_numpy(zero_copy_only=False).astype(bool)
        core[place] = states.column("t_core").to_numpy(zero_copy_only=False).astype(bool) & mine
        own[place[1][mine]] = True
        return pa.table({k: pa.array(c) for k, c in kernel(v, idx, core, x, distances(v, src, dst, own, order[1])).items()}).cast(target)

    few = wires.limit(CLOSURE_EDGES + 1).toArrow()
    if few.num_rows <= CLOSURE_EDGES:
        gblk, src, dst = (few.column(c).to_numpy() for c in ("gblk", "src", "dst"))

        def run(keys: tuple[pa.Scalar, ...], states: pa.Table) -> pa.Table:
            here = gblk == keys[1].as_py()
            return result(states, src[here], dst[here])

        return cross.groupBy("tblk", "gblk").applyInArrow(run, schema)

    def run_far(states: pa.Table, near: pa.Table) -> pa.Table:
        return result(states, near.column("src").to_numpy(), near.column("dst").to_numpy()) if states.num_rows else target.empty_table()

    tiles = cross.select("tblk", "gblk").distinct().join(wires, "gblk").withColumnsRenamed({"tblk": "t", "gblk": "g"})
    return cross.groupBy("tblk", "gblk").cogroup(tiles.groupBy("t", "g")).applyInArrow(run_far, schema)


def map_reduce(cross: DataFrame, edges_in: DataFrame, kernel: Kernel, schema: str, keys: tuple[str, ...], sums: tuple[str, ...], order: tuple[int, int], halo: tuple[int, int]) -> DataFrame:
    """Sum of what `kernel` gives over all (time, graph) blocks, by `keys`."""
    return map_blocks(cross, edges_in, kernel, schema, order, halo).groupBy(*keys).agg(*[F.sum(c).alias(c) for c in sums])


def retrospective(cross: DataFrame, edges_in: DataFrame, predict: Callable[[float, np.ndarray], float], halo: tuple[int, int]) -> DataFrame:
    """Residuals v, idx, r of the (1, 1) network on observed states: x_t^v - predict(x_{t-1}^v, states of its parents at t-1).

    Parents come in the order of their ids. A state without an observed predecessor, or with a parent's missing, has no residual.
    """

    def kernel(v, idx, core, x, dist):
        out = {"v": [], "idx": [], "r": []}
        for t, k in np.argwhere(core):
            if t == 0 or idx[t] - idx[t - 1] != 1:
                continue
            before, parents = x[t - 1, k], x[t - 1, dist[:, k] == 1]
            if not (np.isnan(before) or np.isnan(parents).any()):
                out["v"].append(v[k]), out["idx"].append(idx[t]), out["r"].append(x[t, k] - predict(before, parents))
        return {"v": np.array(out["v"], np.int32), "idx": np.array(out["idx"], np.int64), "r": np.array(out["r"], np.float64)}

    return map_blocks(cross, edges_in, kernel, "v int, idx bigint, r double", (1, 1), halo)


def residual_loglik(residuals: DataFrame) -> float:
    """Gaussian log-likelihood of residuals at their own variance about 0."""
    n, s = residuals.agg(F.count("r"), F.avg(F.col("r") * F.col("r"))).head()
    return -0.5 * n * (math.log(2 * math.pi * s) + 1)


def line_graph(edges: DataFrame) -> DataFrame:
    """Links become vertices: (a, b) -> (b, c)."""
    first = edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    second = edges.select(F.col("src").alias("b"), F.col("dst").alias("c"))
    return first.join(second, "b").select("a", "b", "c")


def check_step(dx: float, dt: float, v: float) -> None:
    """A vehicle must not cross a link within one step."""
    if v * dt > dx:
        raise ValueError("the step is too long: dx >= v dt must hold")


def flows(states: DataFrame, edges: DataFrame, capacity: DataFrame, keys: list[str], qmax: int = 1 << 30, seed: int | None = None) -> DataFrame:
    """Flow of every edge from the states (v, n) of its ends: min of what the tail sends and what the head has room for."""
    out_deg = edges.groupBy("src").agg(F.count(F.lit(1)).alias("od"))
    in_deg = edges.groupBy("dst").agg(F.count(F.lit(1)).alias("id"))
    send = states.select(*keys, F.col("v").alias("src"), F.least("n", F.lit(qmax)).alias("sn"))
    room = states.join(capacity, "v").select(*keys, F.col("v").alias("dst"), (F.col("cap") - F.col("n")).alias("rm"))
    e = edges.join(out_deg, "src").join(in_deg, "dst")  # broadcast by Spark where their size allows
    both = send.join(e, "src").join(room, [*keys, "dst"])
    flow = F.greatest(F.lit(0), F.least(F.call_function("div", F.col("sn"), F.col("od")), F.call_function("div", F.col("rm"), F.col("id"))))
    if seed is not None:  # thinning by a draw that replicas repeat
        flow = F.floor(flow * uniform(seed, F.col("src"), F.col("dst"), *[F.col(k) for k in keys]))
    return both.select(*keys, "src", "dst", flow.cast("bigint").alias("flow"))


def traffic_step(states: DataFrame, edges: DataFrame, capacity: DataFrame, keys: list[str], **options) -> DataFrame:
    """Next state by conservation: what flows in minus what flows out."""
    f = flows(states, edges, capacity, keys, **options)
    moved = f.select(*keys, F.col("src").alias("v"), (-F.col("flow")).alias("m")).unionByName(f.select(*keys, F.col("dst").alias("v"), F.col("flow").alias("m")))
    net = moved.groupBy(*keys, "v").agg(F.sum("m").alias("m"))
    return states.join(net, [*keys, "v"], "left").select(*keys, "v", (F.col("n") + F.coalesce("m", F.lit(0))).alias("n"))


def simulate(states: dict[int, int], edges: list[tuple[int, int]], cap: dict[int, int], steps: int, seed: int, draw) -> list[dict[int, int]]:
    """The same update on one machine; draw(seed, src, dst, step) in (0, 1)."""
    od, idg = {}, {}
    for a, b in edges:
        od[a], idg[b] = od.get(a, 0) + 1, idg.get(b, 0) + 1
    out, now = [], dict(states)
    for s in range(steps):
        nxt = dict(now)
        for a, b in edges:
            if a in now and b in now:
                f = int(max(0, min(now[a] // od[a], (cap[b] - now[b]) // idg[b])) * draw(seed, a, b, s))
                nxt[a] -= f
                nxt[b] += f
        now = nxt
        out.append(now)
    return out


def _steps(k: int, done: int, qmax: int, thinned: bool):
    """k steps of a block and its halo; the states of its core after each."""

    def run(cells: pa.Table, wires: pa.Table) -> pa.Table:
        v, n = cells.column("v").to_numpy(), cells.column("n").to_numpy().astype(np.int64)
        core, cap = cells.column("is_core").to_numpy(zero_copy_only=False).astype(bool), cells.column("cap").to_numpy()
        order = np.argsort(v)
        v, n, core, cap = v[order], n[order], core[order], cap[order]
        src, dst, od, ig = (wires.column(c).to_numpy() for c in ("src", "dst", "od", "ig"))
        both = np.isin(src, v) & np.isin(dst, v)
        a, b, od, ig = np.searchsorted(v, src[both]), np.searchsorted(v, dst[both]), od[both], ig[both]
        draw = wires.column("draw").combine_chunks().flatten().to_numpy().reshape(-1, k)[both] if len(src) else np.zeros((0, k))
        parts = []
        for s in range(k):
            flow = np.maximum(0, np.minimum(np.minimum(n[a], qmax) // od, (cap[b] - n[b]) // ig))
            flow = np.floor(flow * draw[:, s]).astype(np.int64) if thinned else flow
            n = n - np.bincount(a, flow, len(v)).astype(np.int64) + np.bincount(b, flow, len(v)).astype(np.int64)
            parts.append(pa.table({"step": pa.array(np.full(int(core.sum()), done + s + 1), pa.int32()), "v": pa.array(v[core], pa.int32()), "n": pa.array(n[core], pa.int64())}))
        return pa.concat_tables(parts)

    return run


def simulate_blocks(states: DataFrame, edges: DataFrame, capacity: DataFrame, owners: DataFrame, steps: int, hops: int, root: str, seed: int | None = None, qmax: int = 1 << 30) -> DataFrame:
    """The network's next states step, v, n (steps 0..steps) from states (v, n), block by block.

    Every block holds its vertices and those within `hops` edges, and runs `hops` steps alone: what the rim gets
    wrong moves one edge a step and does not reach the core. Then cores are written and halos filled anew. Draws
    belong to (src, dst, step), so all replicas of an edge draw the same; without a seed nothing is thinned.
    """
    degrees = edges.join(edges.groupBy("src").agg(F.count(F.lit(1)).alias("od")), "src").join(edges.groupBy("dst").agg(F.count(F.lit(1)).alias("ig")), "dst")
    gblocks = scratch.stash(hop_blocks(edges, owners, hops), f"{root}/members")
    inside = scratch.stash(block_edges(degrees, gblocks).join(degrees, ["src", "dst"]), f"{root}/edges")
    schema = "step int, v int, n bigint"
    now = scratch.stash(states.select(F.lit(0).alias("step"), F.col("v").cast("int").alias("v"), F.col("n").cast("bigint").alias("n")), f"{root}/step-0")
    out, done = now, 0
    while done < steps:
        k = min(hops, steps - done)
        last = now.where(F.col("step") == done).select("v", "n")
        held = gblocks.select("gblk", "v", "is_core").join(last, "v").join(capacity, "v")
        draws = [F.lit(1.0) if seed is None else uniform(seed, F.col("src"), F.col("dst"), F.lit(done + s)) for s in range(k)]
        wires = inside.select("gblk", "src", "dst", "od", "ig", F.array(*draws).alias("draw"))

        now = scratch.stash(held.groupBy("gblk").cogroup(wires.groupBy("gblk")).applyInArrow(_steps(k, done, qmax, seed is not None), schema), f"{root}/step-{done + 1}")
        out, done = out.unionByName(now), done + k
    return out


def network_kernel(fn: Callable[[float, np.ndarray], float], min_parents: int = 0):
    """A sparse dynamic network as a block kernel: fn(own last state, parents' last states) for every core (v, idx) that has them."""

    def kernel(v, idx, core, x, dist):
        out = {"v": [], "idx": [], "y": []}
        parents = [np.flatnonzero(dist[:, k] == 1) for k in range(len(v))]
        for t, k in np.argwhere(core):
            if t and idx[t] - idx[t - 1] == 1 and len(parents[k]) >= min_parents and not np.isnan(x[t - 1, [k, *parents[k]]]).any():
                out["v"].append(v[k]), out["idx"].append(idx[t]), out["y"].append(fn(x[t - 1, k], x[t - 1, parents[k]]))
        return {"v": np.array(out["v"], np.int32), "idx": np.array(out["idx"], np.int64), "y": np.array(out["y"], np.float64)}

    return kernel


def dbn(cross: DataFrame, edges_in: DataFrame, fn: Callable[[float, np.ndarray], float], halo: tuple[int, int]) -> DataFrame:
    """Forecast v, idx, y of a dynamic network in which a vertex depends on itself and its parents one step earlier."""
    return map_blocks(cross, edges_in, network_kernel(fn), "v int, idx bigint, y double", (1, 1), halo)
