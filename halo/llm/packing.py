"""Vector best-fit packing of documents into sequences under token, document and attention capacities.

Every demand of a piece (tokens, one document, attention cost length squared) is a function of its
length, so pieces of one length are interchangeable. The packing is therefore planned on the histogram
of lengths, at most one row for each length, which is exact over all data and does not grow with it:
lengths are taken in descending order; open bins with the same contents form a class; a length goes to
the class that the weighted dot product or the residual norm prefers among those that fit under every
constraint; new bins are opened only when none fits. The plan is a list of rank ranges: the r-th piece
of a length goes to a given sequence at a given offset. Pieces get their rank within their length from
(length, bucket) counts and a row number inside each bucket, so a length shared by a third of all
pieces is still dealt over many tasks. The planned table is of bounded size and is broadcast.

Defined results: null text counts as empty (the end id alone); documents longer than the capacity are
cut, the first piece taking the remainder; a null id and rows that repeat an id are packed like others;
an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from halo.llm.common import scratch_root, shuffle_partitions, stash, stash_rows
from halo.llm.tokenise import PieceEncoder, slices
from halo.llm.token_output import Vocabulary

PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"


@dataclass(frozen=True)
class Capacities:
    """What a sequence holds at most. By default documents and attention are bounded by the tokens alone."""

    tokens: int = 2048
    documents: int | None = None
    attention: int | None = None

    def vector(self) -> np.ndarray:
        return np.array([self.tokens, self.documents or self.tokens, self.attention or self.tokens**2], np.float64)


def cut(n: int, most: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n ids; only the first may be shorter than `most`."""
    first = n % most or most
    return [(0, min(n, first))] + [(s, most) for s in range(first, n, most)]


def pieces_of(docs: DataFrame, vocab: Vocabulary, most: int, text_col: str = "text", id_col: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """The pieces of every document, with their ids if asked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = PieceEncoder.of(vocab.path, vocab.keeps_space)
        for batch in batches:
            keys, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in slices(texts):
                rows: list[tuple] = []
                for key, raw in zip(keys[a:b], encoder.encode(texts[a:b], vocab.end_id)):
                    for k, (start, length) in enumerate(cut(len(raw) // 4, most)):
                        part = raw[4 * start : 4 * (start + length)]
                        rows.append((key, k, start, length, zlib.crc32(part)) + ((part,) if with_ids else ()))
                columns = list(zip(*rows))
                kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
                names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], names[: len(columns)])

    pairs = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return pairs.mapInArrow(run, PIECES + (", ids binary" if with_ids else ""))


def plan(histogram: dict[int, int], capacities: Capacities, rule: str = "norm", weights: tuple[float, float, float] = (1.0, 1.0, 1.0)) -> list[tuple[int, int, int, int, int]]:
    """Rank ranges (length, rank_from, rank_to, sequence, offset): piece of rank r goes to sequence + r - rank_from."""
    if rule not in ("norm", "dot"):
        raise ValueError("rule is 'norm' or 'dot'")
    cap, w = capacities.vector(), np.asarray(weights, np.float64)
    out: list[tuple[int, int, int, int, int]] = []
    bins: dict[tuple[int, int, int], list[list[int]]] = {}  # contents -> ranges of sequences
    opened = 0

    def add(key, first, last):
        ranges = bins.setdefault(key, [])
        if ranges and ranges[-1][1] == first:
            ranges[-1][1] = last
        else:
            ranges.append([first, last])

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        item = np.array([length, 1, length * length], np.float64)
        if (item > cap).any():
            raise ValueError(f"a piece of {length} ids exceeds the capacities")
        per_bin = int((cap // item).min())

        def place(key, first, last):
            """One piece to each of the sequences first..last-1."""
            nonlocal left, rank
            n = last - first
            out.append((length, rank, rank + n, first, key[0]))
            left, rank = left - n, rank + n
            add((key[0] + length, key[1] + 1, key[2] + length * length), first, last)

        while left and bins:
            keys = np.array(list(bins), np.float64)
            rest = cap - keys - item
            fits = np.flatnonzero((rest >= 0).all(axis=1))
            if not len(fits):
                break
            if rule == "norm":
                score = (w * (rest[fits] / cap) ** 2).sum(axis=1)
            else:
                score = -(w * (item / cap) * ((cap - keys[fits]) / cap)).sum(axis=1)
            names = list(bins)
            for k in fits[np.argsort(score, kind="stable")].tolist():
                ranges = bins.pop(names[k])
                while ranges and left:
                    first, last = ranges.pop()
                    n = min(left, last - first)
                    place(names[k], first, first + n)
                    if first + n < last:
                        ranges.append([first + n, last])
                if ranges:
                    bins[names[k]] = ranges + bins.get(names[k], [])
                if not left:
                    break
        if left:
            whole, over = divmod(left, per_bin)
            first = opened
            opened += whole + (over > 0)
            for r in range(per_bin if whole else 0):
                out.append((length, rank, rank + whole, first, r * length))
                rank += whole
            for r in range(over):
                out.append((length, rank, rank + 1, first + whole, r * length))
                rank += 1
            if whole:
                add((per_bin * length, per_bin, per_bin * length * length), first, first + whole)
            if over:
                add((over * length, over, over * length * length), first + whole, first + whole + 1)
        for k in [k for k in bins if k[0] >= capacities.tokens]:
            del bins[k]
    return out


def pack(pieces: DataFrame, capacities: Capacities, rule: str = "norm", weights: tuple[float, float, float] = (1.0, 1.0, 1.0), buckets: int | None = None, root: str | None = None) -> DataFrame:
    """`pieces` (a table that can be read again) with sequence_id and offset."""
    spark = pieces.sparkSession
    root = root or scratch_root(spark)
    buckets = buckets or max(64, shuffle_partitions(spark))
    order = ["doc_id", "piece", "ids_crc32"]
    dealt = pieces.withColumn("_bucket", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(buckets)).cast("int"))
    counts = stash(dealt.groupBy("length", "_bucket").agg(F.count(F.lit(1)).alias("n")), f"{root}/counts")
    histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    rows = plan(histogram, capacities, rule, weights)
    ranges = stash_rows(spark, rows, "length bigint, rank_from bigint, rank_to bigint, sequence bigint, offset bigint", f"{root}/plan")
    before = Window.partitionBy("length").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    firsts = counts.select("length", "_bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_first"))
    inside = Window.partitionBy("length", "_bucket").orderBy(*order)
    ranked = dealt.withColumn("_nth", F.row_number().over(inside)).join(firsts, ["length", "_bucket"])
    ranked = ranked.withColumn("_rank", F.col("_first") + F.col("_nth") - 1).withColumnRenamed("length", "_length")
    at = (F.col("_length") == F.col("length")) & (F.col("_rank") >= F.col("rank_from")) & (F.col("_rank") < F.col("rank_to"))
    placed = ranked.join(F.broadcast(ranges), at)
    keep = [c for c in pieces.columns]
    return placed.select(*keep, (F.col("sequence") + F.col("_rank") - F.col("rank_from")).alias("sequence_id"), "offset")


def sequences(placed: DataFrame) -> DataFrame:
    """The packed sequences themselves, from placed pieces that carry their ids: ids, document starts and ids of documents."""
    parts = F.array_sort(F.collect_list(F.struct("offset", "doc_id", "length", F.hex("ids").alias("ids"))))
    joined = placed.groupBy("sequence_id").agg(parts.alias("parts"))
    return joined.select(
        "sequence_id",
        F.unhex(F.array_join(F.col("parts.ids"), "")).alias("ids"),
        F.col("parts.offset").alias("offsets"),
        F.col("parts.doc_id").alias("doc_ids"),
        F.aggregate("parts.length", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("n_tokens"),
    )


def fill_report(placed: DataFrame, capacity: int) -> DataFrame:
    """Sequences used, the least possible number by tokens, and the share of places filled."""
    per = placed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    return per.agg(
        F.count(F.lit(1)).alias("sequences"),
        F.ceil(F.sum("n") / F.lit(capacity)).cast("bigint").alias("least"),
        (F.sum("n") / (F.count(F.lit(1)) * F.lit(float(capacity)))).alias("filled"),
    )
