"""Registered queries of the training-data operators, one for each, and their SQL where SQL can say it."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from halo.llm import exact_dedup, mixing, near_dedup, packing, quality, sharding, token_output, topk_search, toxicity, url_filter
from halo.llm.common import scratch_root, stash

TOXIC_AT = 0.3
SHARDS = [f"shard-{k:03d}" for k in range(64)]
URL_RULES = [("org/", "allow"), ("example.org/es/", "block"), ("example.org/en/1", "block"), ("com/fr/", "allow"), ("com/de/", "block")]


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def word_vocabulary() -> token_output.Vocabulary:
    return token_output.Vocabulary(public_tokenizers.path("word_bpe_49k.json"), 49_408, 2, False)


def byte_vocabulary() -> token_output.Vocabulary:
    return token_output.Vocabulary(public_tokenizers.path("byte_bpe_50k.json"), 50_257, 0, True)


def held_out(col):
    return F.pmod(F.crc32(col.cast("string").cast("binary")), F.lit(4)) == 2


def toxic_model(docs: DataFrame, labels: DataFrame) -> toxicity.SubwordModel:
    return toxicity.train_task(toxicity.training_rows(docs, labels, ~held_out(F.col("id"))))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents")
    scored = toxicity.score_documents(docs, toxic_model(docs, _read(spark, sf_dir, "labels")))
    return scored.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= TOXIC_AT).cast("int").alias("predicted"))


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _read(spark, sf_dir, "pages")
    label = url_filter.seed_label(F.col("url"))
    counts = url_filter.corpus_counts(pages, label, scratch_root(spark))
    model = url_filter.UrlModel.train_on_corpus(url_filter.sample_rows(pages, label), counts)
    return url_filter.judge(pages, URL_RULES, model, counts=counts)


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents").select("doc_id", "source")
    return sharding.place(docs, "doc_id", SHARDS).select("doc_id", "source", "slot", "shard")


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = exact_dedup.exact_dedup(_read(spark, sf_dir, "documents"))
    return found.select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op5_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch_root(spark) + "/corpus"
    token_output.write_corpus(_read(spark, sf_dir, "documents"), path, word_vocabulary())
    return token_output.read_corpus(spark, path)


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    root = scratch_root(spark)
    pieces = stash(packing.pieces_of(_read(spark, sf_dir, "documents"), byte_vocabulary(), 2048), f"{root}/pieces")
    return packing.pack(pieces, packing.Capacities(2048), root=root)


def op7_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_search.top_k(_read(spark, sf_dir, "embeddings"), F.pmod(F.col("vec_id"), F.lit(50)) == 0, 5)


def op8_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_groups(_read(spark, sf_dir, "documents"), near_dedup.NearConfig(words=2))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_read(spark, sf_dir, "documents")).taken()


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(_read(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    ops = [op1_toxicity, op2_url_filter, op3_sharding, op4_exact_dedup, op5_token_output, op6_packing, op7_topk_search, op8_near_dedup, op9_mixing, op10_quality, pipeline]
    return {f.__name__: f for f in ops}


def oracle_sql() -> dict[str, str]:
    size = sharding.next_prime(100 * len(SHARDS))
    owners = ",".join(map(str, sharding.lookup_table(SHARDS, size)))
    return {
        "op3_sharding": f"""
            WITH t AS (SELECT string_split('{owners}', ',') AS owner),
            d AS (SELECT doc_id, source, CAST(CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) % {size} AS BIGINT) AS slot FROM documents)
            SELECT d.doc_id, d.source, d.slot, 'shard-' || lpad(t.owner[CAST(d.slot AS INTEGER) + 1], 3, '0') AS shard FROM d, t""",
        "op4_exact_dedup": """
            WITH n AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents),
            g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
            SELECT n.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, n.doc_id = g.keep_id AS kept, sha256(n.t) AS text_sha256
            FROM n JOIN g ON n.t = g.t""",
        "op7_topk_search": """
            WITH v AS (SELECT vec_id, [CAST(floor(256 * CAST(x AS DOUBLE)) AS DOUBLE) for x in embedding] AS e FROM embeddings
                       WHERE embedding IS NOT NULL AND len([x for x in embedding if x IS NULL OR isnan(x) OR isinf(x)]) = 0),
            s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.e, c.e) AS BIGINT) AS score
                  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id),
            r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
            SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 5""",
    }
