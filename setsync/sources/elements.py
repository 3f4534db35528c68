"""Elements of a set: digests and sizes of rows; payloads stay where they are until the last step."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS, canonical

LEFT, RIGHT = -1, 1


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def digests(df: DataFrame, key: list[str] | None = None, dialect: str = "fast", payload: bool = False, multiset: bool = False) -> DataFrame:
    """Distinct ``digest, payload_bytes`` (and ``payload``) of a frame's rows.

    ``key`` names the columns that make an element (default: all). ``multiset`` counts a row's copies
    as elements of their own by adding their number to the text.
    """
    text = canonical(df, key)
    rows = df.select(text.alias("payload"))
    if multiset:
        counted = rows.groupBy("payload").count()
        rows = counted.select(F.explode(F.transform(F.sequence(F.lit(1), F.col("count").cast("int")), lambda k: F.concat_ws("#", "payload", k.cast("string")))).alias("payload"))
    rows = rows.select(DIALECTS[dialect].digest(F.col("payload")).alias("digest"), F.octet_length("payload").alias("payload_bytes"), *(["payload"] if payload else []))
    return rows.dropDuplicates(["digest"])


def wide_digests(df: DataFrame, key: list[str] | None = None) -> DataFrame:
    """128-bit digests ``struct<hi, lo>`` for sets where 64 bits would meet by chance."""
    text = canonical(df, key)
    half = lambda at: F.conv(F.substring(F.md5(text), at, 16), 16, -10).cast("long")
    return df.select(F.struct(half(1).alias("hi"), half(17).alias("lo")).alias("digest"), F.octet_length(text).alias("payload_bytes")).distinct()


def shard_of(shards: int):
    return F.pmod(F.xxhash64("digest", F.lit(5)), F.lit(shards)).cast("int")


def tagged(left: DataFrame, right: DataFrame, run_id: str = "run", shards: int = 1) -> DataFrame:
    """Both sides' digests as one frame: ``run_id, side, shard, digest, payload_bytes``."""
    both = left.withColumn("side", F.lit(LEFT)).unionByName(right.withColumn("side", F.lit(RIGHT)))
    return both.select(F.lit(run_id).alias("run_id"), "side", shard_of(shards).alias("shard"), "digest", "payload_bytes")
