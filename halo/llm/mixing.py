"""Mixing sources to target weights by blocks, per-shard draws and index permutations.

The words of a source, document after document in pseudorandom order, are packed into blocks of
`block_words`. The mix has as many words as the corpus. Targets share them by weight, no source above
`most_epochs` times its size, the excess going to the others by weight. Each target is turned into a
number of slots; output shards draw their source counts one after another from a multinomial over the
slots that each source has left, so all draws together meet the targets. The j-th slot of a source takes
the block at position j of a fresh pseudorandom permutation of its blocks for each pass over it (a
Feistel network on index pairs with cycle walking: nothing is stored or sorted). Slots and blocks are
joined by (source, block index).

Positions of documents in their source come from (source, bucket) totals and running sums inside each
bucket; a bucket holds BUCKET_ROWS rows of all sources on average, so a source with a third of all rows is
spread over as many tasks as its size asks for. Blocks and their uses meet by a shuffle at every size. The
driver holds one row a source and one a (shard, source).

Defined results: null text has size 0 and is never taken; a null source is a source of its own, last in
order; rows that repeat an id are mixed each; an empty table gives an empty result; other columns are
not read. The same rows, in any order and partitioning, give the same result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from halo.llm.common import WORD_PATTERN, fresh_name, scratch_root, shuffle_partitions, stash, stash_rows

LEAST_BUCKETS, BUCKET_ROWS = 128, 100_000
CHUNK = 65_536


@dataclass(frozen=True)
class MixConfig:
    weights: tuple[float, ...] = (5.0, 2.0, 1.0)
    most_epochs: int = 3
    block_words: int = 128
    shards: int = 64
    seed: int = 11


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_PATTERN)), F.lit(0)).cast("bigint")


def targets(sizes: list[int], weights: list[float], most: int) -> list[float]:
    """Shares of sum(sizes) by weight, none above most * its size, the excess reshared by weight."""
    capped: dict[int, float] = {}
    while True:
        free = [k for k in range(len(sizes)) if k not in capped]
        left, w = sum(sizes) - sum(capped.values()), sum(weights[k] for k in free)
        over = [k for k in free if left * weights[k] / w > most * sizes[k]]
        if not over:
            return [float(capped[k]) if k in capped else left * weights[k] / w for k in range(len(sizes))]
        capped.update((k, most * sizes[k]) for k in over)


def draw(slots: np.ndarray, shards: int, seed: int) -> np.ndarray:
    """Source counts of every shard (rows); columns sum to `slots`."""
    rng, left, rows = np.random.Generator(np.random.PCG64(seed)), slots.astype(np.int64).copy(), []
    for k in range(shards):
        need = int(left.sum()) // (shards - k) if k < shards - 1 else int(left.sum())
        got = np.zeros_like(left)
        while need > 0:
            room = left - got
            more = np.minimum(rng.multinomial(need, room / room.sum()), room)
            got += more
            need -= int(more.sum())
        rows.append(got)
        left -= got
    return np.array(rows).reshape(shards, len(slots))


def _mix64(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def permute(index: np.ndarray, n: int, key: np.ndarray, rounds: int = 4) -> np.ndarray:
    """Positions of `index` (< n) under the permutation of 0..n-1 that `key` (one number an index) names."""
    if n <= 1:
        return np.zeros_like(index)
    p = int(np.ceil(np.sqrt(n)))
    q = -(-n // p)
    P, Q = np.uint64(p), np.uint64(q)
    out, todo = index.astype(np.uint64), np.arange(len(index))
    key = key.astype(np.uint64)
    with np.errstate(over="ignore"):
        while len(todo):
            a, b = out[todo] % P, out[todo] // P
            for r in range(rounds):
                salt = key[todo] + np.uint64(0x9E3779B97F4A7C15) * np.uint64(2 * r + 1)
                a = (a + _mix64(b + salt) % P) % P
                b = (b + _mix64(a ^ (salt + np.uint64(0xA5A5)) ) % Q) % Q
            out[todo] = b * P + a
            todo = todo[out[todo] >= np.uint64(n)]
    return out.astype(np.int64)


@dataclass
class Mix:
    """rows: sized documents with their place; sources: one row each; slots: shard, slot, sidx, block."""

    rows: DataFrame
    sources: DataFrame
    slots: DataFrame
    config: MixConfig

    def blocks(self) -> DataFrame:
        """Document spans of every block: sidx, block, doc columns, first word in the document, number of words."""
        L = self.config.block_words
        some = self.rows.where("size > 0")
        span = F.explode(F.sequence(F.expr(f"start div {L}"), F.expr(f"(start + size - 1) div {L}"))).alias("block")
        out = some.select("doc_id", "content", "sidx", "size", "start", span)
        lo = F.greatest(F.col("block") * L, F.col("start"))
        hi = F.least((F.col("block") + 1) * L, F.col("start") + F.col("size"))
        return out.withColumn("first", lo - F.col("start")).withColumn("words", hi - lo)

    def uses(self) -> DataFrame:
        """How often each drawn block is used."""
        return self.slots.groupBy("sidx", "block").agg(F.count(F.lit(1)).alias("uses"))

    def spans(self) -> DataFrame:
        return self.blocks().join(self.uses().hint("merge"), ["sidx", "block"], "left").withColumn("uses", F.coalesce("uses", F.lit(0)))

    def output(self) -> DataFrame:
        """The mixed corpus as spans: shard, slot, doc_id, first word, number of words."""
        return self.slots.join(self.blocks().hint("merge"), ["sidx", "block"]).select("shard", "slot", "doc_id", "content", "first", "words")

    def taken(self) -> DataFrame:
        """Per document: doc_id, size, source_size, target, taken."""
        some = self.spans().groupBy("doc_id", "sidx", "size", "start").agg(F.sum(F.col("words") * F.col("uses")).cast("bigint").alias("taken"))
        none = self.rows.where("size = 0").select("doc_id", "sidx", "size", "start", F.lit(0).cast("bigint").alias("taken"))
        out = some.unionByName(none).join(self.sources, "sidx")
        return out.select("doc_id", "size", "source_size", "target", "taken")


def _slots(seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, sidx, first_slot, j, count, blocks in zip(*(c.to_pylist() for c in batch.columns)):
                at = np.arange(j, j + count)
                with np.errstate(over="ignore"):
                    key = _mix64(np.uint64(seed) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(sidx) * np.uint64(0xC2B2AE3D27D4EB4F) + (at // blocks).astype(np.uint64))
                block = permute(at % blocks, blocks, key)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(count, shard), pa.int32()), pa.array(np.arange(first_slot, first_slot + count), pa.int64()), pa.array(np.full(count, sidx), pa.int32()), pa.array(block, pa.int64())],
                    ["shard", "slot", "sidx", "block"],
                )

    return run


def mix(docs: DataFrame, config: MixConfig = MixConfig(), text_col: str = "text", id_col: str = "doc_id", source_col: str = "source") -> Mix:
    spark, root = docs.sparkSession, scratch_root(docs.sparkSession)
    text = F.col(text_col).cast("string")
    base = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(source_col).cast("string").alias("source"), word_count(text).alias("size"), F.xxhash64(text).alias("content"))
    written = stash(base, f"{root}/sized")
    buckets = max(LEAST_BUCKETS, -(-written.count() // BUCKET_ROWS))
    sized = written.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "content", F.lit(config.seed)), F.lit(buckets)).cast("int"))
    totals = stash(sized.groupBy("source", "bucket").agg(F.sum("size").alias("n")), f"{root}/totals")
    found = sorted(((r.source, r.n) for r in totals.groupBy("source").agg(F.sum("n").alias("n")).collect()), key=lambda r: (r[0] is None, (r[0] or "").encode()))
    sizes = [n for _, n in found]
    goal = targets(sizes, [config.weights[k % len(config.weights)] for k in range(len(found))], config.most_epochs)
    L = config.block_words
    n_blocks = np.array([-(-n // L) for n in sizes], np.int64)
    slots = np.array([min(config.most_epochs * int(b), round(t * int(b) / n)) if n else 0 for t, b, n in zip(goal, n_blocks, sizes)], np.int64)
    counts = draw(slots, config.shards, config.seed)
    plan, done = [], np.zeros(len(found), np.int64)
    for shard in range(config.shards):
        place = 0
        for k, c in enumerate(counts[shard].tolist() if len(found) else []):
            if c:
                plan.append((shard, k, place, int(done[k]), c, int(n_blocks[k])))
                place, done[k] = place + c, done[k] + c
    sources = stash_rows(spark, [(k, s, n, t) for k, ((s, n), t) in enumerate(zip(found, goal))], "sidx int, source string, source_size bigint, target double", f"{root}/sources")
    table = stash_rows(spark, plan, "shard int, sidx int, place bigint, j bigint, n bigint, blocks bigint", f"{root}/plan")
    step = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("n") - 1, F.lit(CHUNK).cast("bigint"))).alias("o")
    chunks = table.select("*", step).select("shard", "sidx", (F.col("place") + F.col("o")).alias("slot"), (F.col("j") + F.col("o")).alias("j"), F.least(F.lit(CHUNK), F.col("n") - F.col("o")).alias("count"), "blocks")
    drawn = chunks.repartition(shuffle_partitions(spark), "shard", "sidx", "j").mapInArrow(_slots(config.seed), "shard int, slot bigint, sidx int, block bigint")
    before = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    firsts = totals.select("source", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_first"))
    firsts = firsts.join(sources.select("source", "sidx"), firsts["source"].eqNullSafe(sources["source"])).select("sidx", firsts["source"].alias("_source"), F.col("bucket").alias("_bucket"), "_first")
    inside = Window.partitionBy("source", "bucket").orderBy("doc_id", "content").rowsBetween(Window.unboundedPreceding, -1)
    running = sized.withColumn("_before", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    rows = running.join(firsts, F.col("source").eqNullSafe(F.col("_source")) & (F.col("bucket") == F.col("_bucket")))
    placed = rows.select("doc_id", "content", "sidx", "size", (F.col("_first") + F.col("_before")).alias("start"))
    return Mix(stash(placed, f"{root}/placed"), sources, drawn, config)


def mixed_texts(docs: DataFrame, mixed: Mix, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """The mixed corpus with the columns of `docs`.

    Pass e over a document holds the words whose block is used at least e times (its words in one run
    stay one stretch of the text, with what stood between them; runs are joined by a line feed). A
    document with all its blocks used appears whole. Rows equal in id and text carry their spans together,
    and the columns of one of them. Columns of `docs` may have any names.
    """
    names = docs.columns
    own_id, own_key, content, its_spans, its_size = (fresh_name(names, x) for x in ("id", "key", "content", "spans", "size"))
    spans = mixed.spans().where("uses > 0").groupBy(F.col("doc_id").alias(own_id), F.col("content").alias(own_key))
    named = spans.agg(F.array_sort(F.collect_list(F.struct("start", "first", "words", "uses"))).alias(its_spans), F.max("size").alias(its_size))
    plain = docs.withColumn(content, F.xxhash64(F.col(text_col).cast("string")))
    if not mixed.rows.groupBy("doc_id", "content").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty():
        plain = plain.dropDuplicates([id_col, content])
    both = plain.join(named.hint("merge"), F.col(id_col).cast("bigint").eqNullSafe(F.col(own_id)) & (F.col(content) == F.col(own_key)))
    at = names.index(text_col)
    has_chars = "n_chars" in names
    pattern = WORD_PATTERN

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import re

        word = re.compile(pattern)
        for batch in batches:
            rows, texts = [], []
            texts_in, spans_in, size_in = batch.column(at), batch.column(len(names)), batch.column(len(names) + 1)
            for k in range(batch.num_rows):
                by_copy: dict[int, list] = {}
                for s in spans_in[k].as_py():
                    by_copy.setdefault(s["start"], []).append((s["first"], s["words"], s["uses"]))
                text, size, places = texts_in[k].as_py(), size_in[k].as_py(), None
                for parts in by_copy.values():
                    for e in range(1, max(u for _, _, u in parts) + 1):
                        runs: list[list[int]] = []
                        for first, n, u in sorted(parts):
                            if u >= e:
                                if runs and runs[-1][1] == first:
                                    runs[-1][1] = first + n
                                else:
                                    runs.append([first, first + n])
                        rows.append(k)
                        if runs == [[0, size]]:
                            texts.append(text)
                        else:
                            places = places or [m.span() for m in word.finditer(text)]
                            texts.append("\n".join(text[places[a][0] : places[b - 1][1]] for a, b in runs))
            columns = [c.take(pa.array(rows, pa.int64())) for c in batch.columns[: len(names)]]
            columns[at] = pa.array(texts, pa.string())
            if has_chars:
                c = names.index("n_chars")
                columns[c] = pa.array([len(t) for t in texts], pa.int64()).cast(columns[c].type)
            yield pa.RecordBatch.from_arrays(columns, names)

    return both.select(*names, its_spans, its_size).mapInArrow(run, docs.schema)
