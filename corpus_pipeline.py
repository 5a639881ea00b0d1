"""From raw documents to packed training sequences: five stages, each written and read again before the next.

All stages: extra columns of any name pass through to the mix, an empty table gives an empty one, nulls in
columns other than text and doc_id have no effect, and texts are read whole.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from halo.llm import exact_dedup, mixing, near_dedup, packing, toxicity
from halo.llm.common import fresh_name, scratch_root, stash
from halo.llm.queries import TOXIC_AT, byte_vocabulary, toxic_model


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score under the threshold. The model learns from the labelled rows of `docs`.

    Null and empty texts score as texts without evidence; rows that repeat an id are judged each by their own text.
    """
    model = toxic_model(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    score = fresh_name(docs.columns, "score")
    scored = toxicity.score_documents(docs, model, "text", tuple(docs.columns), score)
    return scored.where(F.col(score) < TOXIC_AT).select(*docs.columns)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of equal texts: that with the largest id.

    Null text equals empty text, so one of all such rows stays; a null id is the smallest; of repeated rows one stays.
    """
    return exact_dedup.drop_copies(docs, exact_dedup.exact_dedup(docs))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies, that with the smallest id: five-word shingles, similarity 0.8.

    Documents without words or without an id are linked with nothing and stay.
    """
    return near_dedup.keep_one(docs, near_dedup.near_groups(docs, near_dedup.NearConfig()))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The words that the mix takes, in documents of the same columns; a document taken again appears again.

    Documents without words are never taken; a null source is a source of its own; ties of the draw go by (id, text).
    """
    return mixing.mixed_texts(docs, mixing.mix(docs))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents placed in sequences of at most 2048 tokens.

    Null text counts as empty (the end id alone); longer documents are cut; rows that repeat an id are packed each.
    """
    root = scratch_root(spark)
    pieces = stash(packing.pieces_of(docs, byte_vocabulary(), 2048), f"{root}/pieces")
    return packing.pack(pieces, packing.Capacities(2048), root=root)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_exact_copies),
    ("near_dedup", drop_near_copies),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: SQL cannot express the trained filter, the signatures, the draws and the packing; tests use brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of `sf_dir`."""
    root = scratch_root(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        docs = stash(out, f"{root}/{k}-{name}")
    return docs
