"""Token ids of a corpus in compressed block files, in ascending order of document id, and their reader.

Layout of an output folder:
  table/   one row: the shared frequency table (bytes of rans.Table)
  blocks/  one row a block: file_no, block_no, start_in_file, n_tokens, doc_ids (int64), lengths (uint32), data
Parquet is only the container that any store can hold and that Spark commits file by file; `data` is a
self-contained block of halo.llm.rans. File f holds the f-th range of ids, its blocks follow one another.

Steps: range partition by id and a hash of the text, and encode to ids (written once, so a lost executor
repeats its range only); count all ids (a table bounded by the vocabulary goes to the driver); code block by block; read
back block by block. A block holds whole documents, at least BLOCK_IDS ids but for the last of a file.

Defined results: null and empty texts give the end id alone; rows that repeat an id follow one another
in the order of that hash, over as many files as they fill; a null id sorts first and comes back as null; an empty table gives no blocks; other columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from halo.llm import rans
from halo.llm.common import scratch_root, shuffle_partitions, stash, stash_rows
from halo.llm.tokenise import PieceEncoder, slices

BLOCK_IDS = 1 << 19
#: Characters encoded at once: a word that comes again among them is looked up once.
SLICE_CHARS = 8_000_000
NO_ID = -(1 << 63)
RAW = "file_no int, block_no int, start_in_file bigint, n_tokens bigint, doc_ids binary, lengths binary, data binary"


@dataclass(frozen=True)
class Vocabulary:
    path: str
    size: int
    end_id: int
    keeps_space: bool


def _raw_blocks(vocab: Vocabulary, block_ids: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, file_no = PieceEncoder.of(vocab.path, vocab.keeps_space), TaskContext.get().partitionId()
        held: list[tuple[int, bytes]] = []
        size, block, begun = 0, 0, 0

        def flush():
            nonlocal held, size, block, begun
            ids = np.frombuffer(b"".join(x for _, x in held), "<u4")
            out = pa.RecordBatch.from_arrays(
                [
                    pa.array([file_no], pa.int32()), pa.array([block], pa.int32()), pa.array([begun], pa.int64()), pa.array([len(ids)], pa.int64()),
                    pa.array([np.array([d for d, _ in held], "<i8").tobytes()], pa.binary()),
                    pa.array([np.array([len(x) // 4 for _, x in held], "<u4").tobytes()], pa.binary()),
                    pa.array([ids.astype("<u2" if vocab.size <= 65536 else "<u4").tobytes()], pa.binary()),
                ],
                ["file_no", "block_no", "start_in_file", "n_tokens", "doc_ids", "lengths", "data"],
            )
            begun, block, held, size = begun + len(ids), block + 1, [], 0
            return out

        for batch in batches:
            keys, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in slices(texts, SLICE_CHARS):
                for key, ids in zip(keys[a:b], encoder.encode(texts[a:b], vocab.end_id)):
                    held.append((NO_ID if key is None else key, ids))
                    size += len(ids) // 4
                    if size >= block_ids:
                        yield flush()
        if held:
            yield flush()

    return run


def _count_ids(size: int):
    kind = "<u2" if size <= 65536 else "<u4"

    def run(batches):
        total = np.zeros(size, np.int64)
        for batch in batches:
            for data in batch.column(0):
                total += np.bincount(np.frombuffer(data.as_py(), kind), minlength=size)
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used, pa.int32()), pa.array(total[used], pa.int64())], ["token", "n"])

    return run


def _code(size: int, table_bytes: bytes):
    kind = "<u2" if size <= 65536 else "<u4"

    def run(batches):
        table = rans.Table.from_bytes(table_bytes)
        for batch in batches:
            for k in range(batch.num_rows):
                one = batch.slice(k, 1)
                data = rans.encode_block(np.frombuffer(one.column(6)[0].as_py(), kind).astype(np.uint32), table)
                yield pa.RecordBatch.from_arrays([*one.columns[:6], pa.array([data], pa.binary())], batch.schema.names)

    return run


def write_corpus(docs: DataFrame, path: str, vocab: Vocabulary, text_col: str = "text", id_col: str = "doc_id", files: int | None = None, block_ids: int = BLOCK_IDS, scale_bits: int = 20) -> None:
    """Encode, code and write `docs` below `path`."""
    spark, root = docs.sparkSession, scratch_root(docs.sparkSession)
    files = files or shuffle_partitions(spark)
    pairs = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text"))
    # The hash splits the rows of an id that many of them share.
    ranged = pairs.withColumn("h", F.xxhash64("text")).repartitionByRange(files, "id", "h")
    placed = ranged.sortWithinPartitions("id", "h", "text").select("id", "text")
    raw = stash(placed.mapInArrow(_raw_blocks(vocab, block_ids), RAW), f"{root}/ids", "zstd")
    counts = np.zeros(vocab.size, np.int64)
    for r in raw.select("data").mapInArrow(_count_ids(vocab.size), "token int, n bigint").groupBy("token").agg(F.sum("n").alias("n")).collect():
        counts[r.token] = r.n
    table = rans.Table(rans.scaled_table(counts, scale_bits), scale_bits)
    stash_rows(spark, [(bytearray(table.to_bytes()), vocab.size)], "data binary, vocabulary int", f"{path}/table")
    raw.mapInArrow(_code(vocab.size, table.to_bytes()), RAW).write.mode("overwrite").option("compression", "uncompressed").parquet(f"{path}/blocks")


def read_blocks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(RAW).parquet(f"{path}/blocks")


def file_starts(blocks: DataFrame) -> dict[int, int]:
    """Ids before each file: one number a file."""
    ends = sorted((r.file_no, r.n) for r in blocks.groupBy("file_no").agg(F.sum("n_tokens").alias("n")).collect())
    starts, total = {}, 0
    for f, n in ends:
        starts[f], total = total, total + n
    return starts


def read_corpus(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """Per document of the files under `path`: doc_id, start, n_tokens, ids_crc32 and, if asked for, ids."""
    table_bytes = bytes(spark.read.parquet(f"{path}/table").select("data").head().data)
    blocks = read_blocks(spark, path)
    starts = file_starts(blocks)

    def run(batches):
        table = rans.Table.from_bytes(table_bytes)
        for batch in batches:
            for k in range(batch.num_rows):
                file_no, _, begun, n, keys, lengths, data = (c[k].as_py() for c in batch.columns)
                ids = rans.decode_block(data, table).astype("<u4")
                keys, lengths = np.frombuffer(keys, "<i8"), np.frombuffer(lengths, "<u4").astype(np.int64)
                ends = np.cumsum(lengths)
                if len(ids) != n or (len(ends) and ends[-1] != n):
                    raise ValueError("block and document lengths differ")
                raw, first = ids.tobytes(), starts[file_no] + begun
                parts = [raw[4 * (e - m) : 4 * e] for e, m in zip(ends.tolist(), lengths.tolist())]
                columns = [
                    pa.array(keys, pa.int64(), mask=keys == NO_ID), pa.array(first + ends - lengths, pa.int64()), pa.array(lengths, pa.int64()),
                    pa.array([zlib.crc32(p) for p in parts], pa.int64()),
                ]
                names = ["doc_id", "start", "n_tokens", "ids_crc32"]
                if with_ids:
                    columns.append(pa.array([np.frombuffer(p, "<u4").astype(np.int64) for p in parts], pa.list_(pa.int64())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)

    schema = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint" + (", ids array<bigint>" if with_ids else "")
    return blocks.mapInArrow(run, schema)
