"""Exact top-k inner products by columnar branch and bound.

Candidates of a batch are laid out vertically, one row for each dimension, heaviest blocks of dimensions
first. For a tile of queries, products are accumulated one block of dimensions after another; after each
block a candidate can gain at most the product of the norms of what is left of query and candidate
(Cauchy-Schwarz). Candidates whose bound lies under the query's k-th best score so far are dropped; once
few are left of a tile, the survivors of each query are compacted and go on alone. Bounds only prune;
scores are exact integers (float64 sums below 2^53, else Python integers).

Queries are handled in blocks of QUERY_BLOCK rows, one after another, each collected (a bounded block) and
sent to every task; candidates are never shuffled. Each task keeps k rows a query; the rows of a block are
written before the next block is collected, and a window over all of them finishes.

Defined results: vectors that are null, empty or hold null, NaN or infinite components take no part;
vectors of another length than the query's are not its candidates; rows that share the query's id are
its own; rows that repeat an id are candidates each; ties go to the smaller id. A query id with several
vectors asks with each different one, and its result is the k best pairs of one of them and a candidate.
Integers of any size are summed exactly; a score outside the range of a long counts as the nearest long.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from halo.llm.common import scratch_root, stash

QUERY_BLOCK = 4096
CANDIDATE_BLOCK = 8192
DIM_BLOCK = 16
TILE = 64
RESULT = "query_id bigint, vec_id bigint, score bigint"
LEAST, MOST = -(1 << 63), (1 << 63) - 1


def usable(vec: Column) -> Column:
    bad = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    return vec.isNotNull() & (F.size(vec) > 0) & ~F.coalesce(bad, F.lit(True))


def whole(x: float, scale: int) -> int:
    """floor(scale * x) as an integer of any size."""
    p = scale * x
    return math.floor(p) if math.isfinite(p) else int(x) * scale


def search_block(ids: np.ndarray, matrix: np.ndarray, qids: np.ndarray, queries: np.ndarray, k: int, floor: np.ndarray, dims: int = DIM_BLOCK, tile: int = TILE):
    """The k best candidates of each query among the columns of `matrix` (dimension x candidate).

    `floor` holds the k-th best score of each query so far and is raised in place.
    Yields (query position, candidate positions, scores, components read so far).
    """
    d, n = matrix.shape
    cuts = [np.arange(s, min(d, s + dims)) for s in range(0, d, dims)]
    mass = np.stack([(matrix[b] ** 2).sum(axis=0) for b in cuts])
    order = np.argsort(-mass.sum(axis=1), kind="stable")
    rows = [cuts[b] for b in order]
    # After step s: norm of what is left of each candidate, and of each query.
    rest = np.sqrt(np.vstack([np.cumsum(mass[order][::-1], axis=0)[::-1][1:], np.zeros((1, n))]))
    own = np.stack([(queries[:, b] ** 2).sum(axis=1) for b in rows])
    left = np.sqrt(np.vstack([np.cumsum(own[::-1], axis=0)[::-1][1:], np.zeros((1, len(qids)))]))
    parts, last, visited = [np.ascontiguousarray(matrix[r]) for r in rows], len(rows) - 1, 0

    def bar(q: int, low: np.ndarray) -> float:
        """No candidate under it is among the k best: `low` are sums that candidates reach for certain."""
        best = floor[q]
        if not np.isfinite(best) and len(low) > k:
            best = np.partition(low, len(low) - k)[len(low) - k]
        return best - 1e-6 * (1 + abs(best)) if np.isfinite(best) else -np.inf

    for at in range(0, len(qids), tile):
        qs = np.arange(at, min(len(qids), at + tile))
        total, step = np.zeros((len(qs), n)), 0
        total[ids[None, :] == qids[qs][:, None]] = -np.inf
        while True:  # dense steps, until a tenth of the tile or less is alive
            total += queries[np.ix_(qs, rows[step])] @ parts[step]
            visited += len(qs) * parts[step].size
            slack = left[step][qs][:, None] * rest[step][None, :]
            bars = np.array([bar(q, total[i] - slack[i]) for i, q in enumerate(qs)])
            alive = (total + slack >= bars[:, None]) & (total > -np.inf)
            if step == last or alive.mean() <= 0.1:
                break
            step += 1
        for i, q in enumerate(qs):
            some = np.flatnonzero(alive[i])
            sums = total[i, some]
            for s in range(step + 1, last + 1):
                if not len(some):
                    break
                sums = sums + queries[q, rows[s]] @ parts[s][:, some]
                visited += len(rows[s]) * len(some)
                slack = left[s, q] * rest[s, some]
                stay = sums + slack >= bar(q, sums - slack)
                some, sums = some[stay], sums[stay]
            if len(some):
                best = np.lexsort((ids[some], -sums))[:k]
                if len(best) == k:
                    floor[q] = max(floor[q], sums[best[-1]])
                yield int(q), some[best], sums[best], visited


def _search(qids: np.ndarray, queries: np.ndarray, k: int, scale: int):
    d = queries.shape[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        floor = np.full(len(qids), -np.inf)
        kept_q, kept_id, kept_s = [], [], []
        for batch in batches:
            flat = batch.column(1).flatten().to_numpy(zero_copy_only=False)
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            matrix = np.floor(scale * np.ascontiguousarray(flat.reshape(len(ids), d).T))
            for s in range(0, len(ids), CANDIDATE_BLOCK):
                part_ids = ids[s : s + CANDIDATE_BLOCK]
                for q, where, score, _ in search_block(part_ids, matrix[:, s : s + CANDIDATE_BLOCK], qids, queries, k, floor):
                    kept_q.append(np.full(len(where), qids[q]))
                    kept_id.append(part_ids[where])
                    kept_s.append(score)
            if sum(map(len, kept_q)) > 4 * k * max(1, len(qids)):
                kept_q, kept_id, kept_s = ([x] for x in _best(np.concatenate(kept_q), np.concatenate(kept_id), np.concatenate(kept_s), k))
        if kept_q:
            q, i, s = _best(np.concatenate(kept_q), np.concatenate(kept_id), np.concatenate(kept_s), k)
            yield pa.RecordBatch.from_arrays([pa.array(q, pa.int64()), pa.array(i, pa.int64()), pa.array(s.astype(np.int64), pa.int64())], ["query_id", "vec_id", "score"])

    return run


def _search_wide(asked: list[tuple[int, list[float]]], k: int, scale: int):
    """Components too large for float64 sums: the same scores with Python integers."""
    queries = [(q, [whole(x, scale) for x in v]) for q, v in asked]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: list[list[tuple[int, int]]] = [[] for _ in queries]
        for batch in batches:
            rows = [(i, [whole(x, scale) for x in v]) for i, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())]
            for at, (q, query) in enumerate(queries):
                found = [(-min(MOST, max(LEAST, sum(a * b for a, b in zip(query, v)))), i) for i, v in rows if i != q]
                best[at] = sorted(best[at] + found)[:k]
        for (q, _), found in zip(queries, best):
            yield pa.RecordBatch.from_arrays([pa.array([q] * len(found), pa.int64()), pa.array([i for _, i in found], pa.int64()), pa.array([-s for s, _ in found], pa.int64())], ["query_id", "vec_id", "score"])

    return run


def _best(q: np.ndarray, ids: np.ndarray, score: np.ndarray, k: int):
    order = np.lexsort((ids, -score, q))
    q, ids, score = q[order], ids[order], score[order]
    new = np.concatenate([[True], q[1:] != q[:-1]]) if len(q) else np.zeros(0, bool)
    first = np.maximum.accumulate(np.where(new, np.arange(len(q)), 0)) if len(q) else np.zeros(0, int)
    stay = np.arange(len(q)) - first < k
    return q[stay], ids[stay], score[stay]


def top_k(vectors: DataFrame, is_query: Column, k: int, scale: int = 256, id_col: str = "vec_id", vec_col: str = "embedding", query_block: int = QUERY_BLOCK) -> DataFrame:
    """Rows query_id, rank, vec_id, score for every row of `vectors` that is a query, against all rows."""
    spark = vectors.sparkSession
    rows = vectors.where(usable(F.col(vec_col)) & F.col(id_col).isNotNull())
    rows = rows.select(F.col(id_col).cast("bigint").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("v"), is_query.alias("is_query"))
    asked = rows.where("is_query").select("vec_id", "v").dropDuplicates(["vec_id", "v"])
    largest = rows.agg(F.max(F.array_max(F.transform("v", lambda x: F.abs(x * F.lit(float(scale)))))).alias("m"), F.max(F.size("v")).alias("d"), F.count_if("is_query").alias("n")).head()
    parts: list[DataFrame] = []
    if largest.n:
        most = float(largest.m) + 1
        exact, root = most * most * largest.d < 2**53, scratch_root(spark)
        n_blocks = -(-largest.n // query_block)
        for b in range(n_blocks):
            block = asked.where(F.pmod(F.xxhash64("vec_id", "v"), F.lit(n_blocks)) == b).collect() if n_blocks > 1 else asked.collect()
            for d in sorted({len(r.v) for r in block}):
                same = sorted((r.vec_id, r.v) for r in block if len(r.v) == d)
                if exact:
                    search = _search(np.array([i for i, _ in same], np.int64), np.floor(scale * np.array([v for _, v in same], np.float64)), k, scale)
                else:
                    search = _search_wide(same, k, scale)
                found = rows.where(F.size("v") == d).select("vec_id", "v").mapInArrow(search, RESULT)
                parts.append(found if n_blocks == 1 else stash(found, f"{root}/found/block={b}-{d}"))
        if n_blocks > 1:  # one table of all blocks, whatever their number
            parts = [spark.read.schema(RESULT).parquet(f"{root}/found").select("query_id", "vec_id", "score")]
    if not parts:
        parts = [spark.createDataFrame([], RESULT)]
    found = parts[0]
    for p in parts[1:]:
        found = found.unionByName(p)
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
