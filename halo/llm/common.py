"""Shared helpers of the training-data operators: scratch tables, ASCII folding, word splitting."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from halo.plans import scratch

# The letters folded by ASCII-only lower-casing, and the separators of words.
ASCII_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ASCII_LOWER = "abcdefghijklmnopqrstuvwxyz"
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def scratch_root(spark: SparkSession) -> str:
    """A new folder below spark.checkpoint.dir, deleted when the driver's JVM ends; a local one only for a local master without that setting."""
    return scratch.folder(spark, "llm")


def stash(df: DataFrame, path: str, compression: str = "snappy") -> DataFrame:
    """Write `df` as Parquet and read it back: a cut of the lineage that outlives executors."""
    df.write.mode("overwrite").option("compression", compression).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stash_rows(spark: SparkSession, rows: list, schema: str, path: str) -> DataFrame:
    """A small driver-side table as a shared file, so that joins on it read a table and not an RDD."""
    return stash(spark.createDataFrame(rows, schema).coalesce(1), path)


def hash_sample(rows: DataFrame, key: str, most: int) -> DataFrame:
    """One row for each of the `most` keys with the smallest hash; of repeated keys the smallest other columns.

    Keys are counted first, and a threshold on the hash keeps some more than needed. Only those are
    shuffled and sorted, so what one task receives is bounded by `most` and not by the input.
    """
    n = rows.agg(F.approx_count_distinct(key)).first()[0]
    share, h = (1.5 * most + 1000) / max(n, 1), F.xxhash64(key)
    few = rows if share >= 1 else rows.where(h <= F.lit(min(2**63 - 1, int(share * 2**64) - 2**63)))
    others = [F.min(c).alias(c) for c in rows.columns if c != key]
    once = few.groupBy(key).agg(*others) if others else few.distinct()
    return once.orderBy(h, key).limit(most)


def ascii_lower(col: Column) -> Column:
    """Lower-case A-Z only. Pure ASCII text takes the byte-wise path of lower()."""
    return F.when(F.length(col) == F.octet_length(col), F.lower(col)).otherwise(
        F.translate(col, ASCII_UPPER, ASCII_LOWER)
    )


def fresh_name(taken: list[str], base: str) -> str:
    """`base`, prefixed until no name of `taken` equals it in any case."""
    names, out = {n.lower() for n in taken}, f"_{base}"
    while out.lower() in names:
        out = f"_{out}"
    return out


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def ascii_words(text: str | None) -> list[bytes]:
    """Words of WORD_PATTERN as UTF-8 bytes. bytes.split() separates at exactly those six characters."""
    return text.encode("utf-8", "surrogatepass").split() if text else []
