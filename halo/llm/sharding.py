"""Placement of documents on shards through a permutation-filled lookup table.

Every shard has its own preference order over the slots of a prime-sized table (a start and a stride
taken from a digest of its name). Shards claim slots in turns, each the first free slot of its order,
until the table is full. A document goes to the shard that owns the slot of its key's digest. Filling
is O(M log M) on the driver for a table of M slots, which does not depend on the data; placement is a
join with the broadcast table of at most MAX_SLOTS rows, so constant time and without a shuffle.

Defined results: a null key counts as the empty string; equal keys share a shard; an empty table gives
an empty result; other columns pass through untouched (the two new columns replace equal names).
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MAX_SLOTS = 655_373


def is_prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, int(n**0.5) + 1))


def next_prime(n: int) -> int:
    while not is_prime(n):
        n += 1
    return n


def _digest(text: str) -> int:
    return int.from_bytes(hashlib.sha256(text.encode()).digest()[:8], "big")


def lookup_table(shards: list[str], size: int, weights: dict[str, int] | None = None) -> list[int]:
    """Owner (position in `shards`) of every slot. A shard of weight w takes w turns in each round."""
    if not shards or len(set(shards)) != len(shards):
        raise ValueError("shard names must be given and distinct")
    if not is_prime(size) or size > MAX_SLOTS or size < len(shards):
        raise ValueError(f"table size must be a prime between the number of shards and {MAX_SLOTS}")
    starts = [_digest("start/" + s) % size for s in shards]
    strides = [_digest("stride/" + s) % (size - 1) + 1 for s in shards]
    turns = [max(1, (weights or {}).get(s, 1)) for s in shards]
    owner, free, tried = [-1] * size, size, [0] * len(shards)
    while free:
        for k in range(len(shards)):
            for _ in range(min(turns[k], free)):
                slot = (starts[k] + tried[k] * strides[k]) % size
                while owner[slot] >= 0:
                    tried[k] += 1
                    slot = (starts[k] + tried[k] * strides[k]) % size
                owner[slot] = k
                tried[k] += 1
                free -= 1
    return owner


def key_slot(key: Column, size: int) -> Column:
    digest = F.md5(F.coalesce(key.cast("string"), F.lit("")))
    return F.pmod(F.conv(F.substring(digest, 1, 15), 16, 10).cast("bigint"), F.lit(size))


def place(df: DataFrame, key: str, shards: list[str], size: int | None = None, weights: dict[str, int] | None = None) -> DataFrame:
    """`df` with columns slot and shard."""
    size = size or next_prime(100 * len(shards))
    owner = lookup_table(shards, size, weights)
    text = ",".join(map(str, owner))
    names = F.array(*[F.lit(s) for s in shards])
    table = df.sparkSession.range(1).select(F.posexplode(F.split(F.lit(text), ",")).alias("slot", "owner"))
    table = table.select(F.col("slot").cast("bigint").alias("slot"), F.element_at(names, F.col("owner").cast("int") + 1).alias("shard"))
    keyed = df.drop("slot", "shard").withColumn("slot", key_slot(df[key], size))
    return keyed.join(F.broadcast(table), "slot")


def balance(placed: DataFrame, weight: Column | None = None) -> DataFrame:
    """Rows and weight of every shard."""
    w = F.lit(1) if weight is None else weight
    return placed.groupBy("shard").agg(F.count(F.lit(1)).alias("n_rows"), F.sum(w).cast("bigint").alias("weight"))


def write_shards(placed: DataFrame, path: str, files_per_shard: int = 4) -> None:
    """One folder a shard, several files each, so that no shard is one task."""
    salt = F.pmod(F.xxhash64(*placed.columns), F.lit(files_per_shard))
    placed.repartition(F.col("shard"), salt).write.mode("overwrite").partitionBy("shard").parquet(path)
