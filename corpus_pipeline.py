"""A corpus pipeline in five stages: toxicity, near-duplicates, secrets, mixing, packing.

Each stage works on all rows that the one before kept, and its result is written as Parquet and read
again. All but the last return the columns of ``documents`` as they came (extra ones included).

Defined cases: a null or empty text is scored as one blank word, is a near copy of the other empty ones,
has no secrets, takes no words of the mix and so leaves there; rows without an id stay through the
near-duplicate stage; rows that repeat an id stay if their texts are unlike; rows of a null language
use the common threshold and those of a null source are a source of their own; ties fall to the
smallest id; texts of any length are taken whole; an empty table gives no rows.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsync.llm import mixing, nearcopies, packing, secrets, shared, toxicity


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose score stays under the threshold of their language."""
    model = toxicity.train(docs, shared.table(spark, sf_dir, "labels"))
    score, lang = toxicity.score_column(model, spark)(F.col("text")), F.col("lang") if "lang" in docs.columns else F.lit(None)
    name = shared.spare_name(docs, "score")
    kept = docs.withColumn(name, score)
    return kept.where(~F.coalesce(toxicity.flagged(F.col(name), lang, model), F.lit(False))).drop(name)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies (SimHash radius, or similarity 0.8 of five-word shingles): that of the smallest id; rows without an id stay."""
    return nearcopies.keep_one(docs)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows; each secret that is found, however it is wrapped, gives way to a mark."""
    shared.bounded_batches(spark)
    masked = docs.withColumn("text", secrets.masked_column(F.col("text")))
    return masked.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else masked


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The words that the mix takes: whole rows once for each pass, parts of rows that a block's border cuts."""
    return mixing.mixed_rows(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every piece with its ids and its place in a sequence of 4,096 tokens."""
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_duplicates", drop_near_copies),
    ("secrets", mask_secrets),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Training, fingerprints and tokens have no SQL form; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = shared.table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = shared.stored(stage(spark, docs, sf_dir))
    return docs
