"""Exact deduplication with keyed streaming state.

The table is reduced to keys (digest of the normalised text, id), and the keys are read as a stream
whose aggregation state, kept in RocksDB without watermark or expiry, retains per digest the stable id
of the row to keep, the locator of its content (file and row of the key table) and the number of rows.
Whatever the state calls a hit is checked on its full bytes: the smallest and the largest normalised
text under a digest must be the same. That check aggregates inside each task before it shuffles, so a
text with millions of copies moves once a task. Should a digest ever hold two texts, the rows under it
are keyed by their whole text and the stream runs again.

Everything is DataFrame code. Skew: the aggregation combines before its shuffle; the join that carries
the decision back moves keys only (no text) and can be split by adaptive execution.

Defined results: null text equals empty text; of equal texts the largest id stays, a null id being the
smallest; of rows that repeat one id and text exactly one stays (the later locator); an empty table
gives an empty result. Other columns are never read here.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from halo.llm.common import ascii_lower, fresh_name, scratch_root, stash, text_or_empty

#: Digests of repeated texts up to this many rows (about 100 bytes each) are broadcast to the byte check.
BROADCAST_HITS = 200_000

Digest = Callable[[Column], Column]


def sha256(text: Column) -> Column:
    return F.sha2(text, 256)


def stream_session(spark: SparkSession) -> SparkSession:
    """A session of its own for the state store's settings; the caller's session stays as it is."""
    own = spark.newSession()
    own.conf.set("spark.sql.shuffle.partitions", spark.conf.get("spark.sql.shuffle.partitions"))
    own.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    own.conf.set("spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled", "true")
    # Each state partition would reserve 4 MB of disk for a log of a few hundred bytes.
    own.conf.set("spark.sql.streaming.stateStore.rocksdb.allowFAllocate", "false")
    own.conf.set("spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage", "true")
    own.conf.set("spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB", "256")
    return own


def _locator() -> Column:
    return F.concat(F.col("_metadata.file_name"), F.lit("#"), F.lpad(F.col("_metadata.row_index").cast("string"), 12, "0"))


def run_state(spark: SparkSession, keys_path: str, schema, root: str, files_per_batch: int | None = None) -> DataFrame:
    """Feed the key files through the keyed state; per digest: what stays, where it lies, how many rows."""
    own = stream_session(spark)
    reader = own.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    state = (
        reader.parquet(keys_path)
        .select("digest", F.struct("doc_id", _locator().alias("locator")).alias("row"))
        .groupBy("digest")
        .agg(F.max("row").alias("keep"), F.count(F.lit(1)).alias("group_size"))
    )

    def sink(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/state/batch={number}")

    query = (
        state.writeStream.outputMode("update")
        .option("checkpointLocation", f"{root}/stream")
        .trigger(availableNow=True)
        .foreachBatch(sink)
        .start()
    )
    query.awaitTermination()
    # Later batches repeat a digest with a larger or equal row and count, so the maxima are the final state.
    return spark.read.parquet(f"{root}/state").groupBy("digest").agg(F.max("keep").alias("keep"), F.max("group_size").alias("group_size"))


def byte_collisions(docs: DataFrame, state: DataFrame, key: Column, text: Column) -> DataFrame:
    """Digests whose rows do not all hold the same bytes. Only rows under repeated digests are compared."""
    hits = state.where("group_size > 1").select("digest")
    if hits.count() <= BROADCAST_HITS:
        hits = F.broadcast(hits)
    rows = docs.select(key.alias("digest"), text.alias("norm")).join(hits, "digest", "left_semi")
    ends = rows.groupBy("digest").agg(F.min("norm").alias("low"), F.max("norm").alias("high"))
    return ends.where(F.col("low") != F.col("high")).select("digest")


def exact_dedup(
    docs: DataFrame,
    text_col: str = "text",
    id_col: str = "doc_id",
    digest: Digest = sha256,
    normalise: Callable[[Column], Column] = ascii_lower,
    files_per_batch: int | None = None,
) -> DataFrame:
    """Per row of `docs`: doc_id, keep_id, group_size, kept, text_sha256, locator (of the row kept)."""
    spark, root = docs.sparkSession, scratch_root(docs.sparkSession)
    text = normalise(text_or_empty(text_col))
    narrow = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias(text_col))
    key, attempt = digest(text), 0
    while True:
        base = f"{root}/{attempt}"
        content = sha256(text)
        columns = [F.col("doc_id"), key.alias("digest")] + ([] if digest is sha256 and not attempt else [content.alias("text_sha256")])
        keys = stash(narrow.select(*columns), f"{base}/keys")
        if keys.isEmpty():
            return keys.select(
                "doc_id", F.col("doc_id").alias("keep_id"), F.lit(0).cast("bigint").alias("group_size"), F.lit(True).alias("kept"),
                F.col("digest").alias("text_sha256"), F.col("digest").alias("locator"),
            )
        state = stash(run_state(spark, f"{base}/keys", keys.schema, base, files_per_batch), f"{base}/final")
        clash = byte_collisions(narrow, state, key, text)
        if attempt or clash.isEmpty():
            break
        bad = [r.digest for r in clash.limit(100_000).collect()]
        # Two texts under one SHA-256 have never been seen; a weaker digest given by the caller may clash.
        whole = F.concat(digest(text), F.lit(":"), text)
        key, attempt = (F.when(digest(text).isin(bad), whole).otherwise(digest(text)) if len(bad) < 100_000 else whole), 1
    located = keys.withColumn("locator", _locator())
    hash_col = F.col("text_sha256") if "text_sha256" in keys.columns else F.col("digest")
    return located.join(state, "digest").select(
        "doc_id",
        F.col("keep.doc_id").alias("keep_id"),
        "group_size",
        (F.col("locator") == F.col("keep.locator")).alias("kept"),
        hash_col.alias("text_sha256"),
        F.col("keep.locator").alias("locator"),
    )


def drop_copies(docs: DataFrame, decisions: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """The rows of `docs` that stay, each once, with the columns of `docs`.

    Only the keys of dropped rows are joined. Rows that repeat an id and text are thinned afterwards,
    and only where the decisions show that there are any.
    """
    names = docs.columns
    own_id, own_sha, sha = (fresh_name(names, x) for x in ("id", "sha", "text_sha"))
    columns = [F.col("doc_id").alias(own_id), F.col("text_sha256").alias(own_sha)]
    gone = decisions.where("not kept").select(*columns).distinct()
    repeated = decisions.where("not kept and doc_id <=> keep_id").select(*columns).distinct()
    gone = gone.join(repeated, gone[own_id].eqNullSafe(repeated[own_id]) & (gone[own_sha] == repeated[own_sha]), "left_anti")
    named = docs.withColumn(sha, sha256(ascii_lower(text_or_empty(text_col))))
    kept = named.join(gone, F.col(id_col).cast("bigint").eqNullSafe(F.col(own_id)) & (F.col(sha) == F.col(own_sha)), "left_anti")
    if not repeated.isEmpty():
        kept = kept.dropDuplicates([id_col, sha])
    return kept.select(*names)
