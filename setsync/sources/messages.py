"""Messages as files: cells and elements in Parquet, CSV, JSON or ORC, and tables in the shared folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

ELEMENTS = "run_id string, side int, shard int, digest long, payload_bytes int"
CELLS = "run_id string, shard int, side int, cell long, id_xor long, check_xor long, cnt long"


def shared_table(spark: SparkSession, name: str) -> str:
    """A fresh path in the folder of ``spark.checkpoint.dir``; a local one only where that is unset."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = known.get() if known.isDefined() else None
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="setsync-")
        spark.sparkContext.setCheckpointDir(folder)
    return f"{folder}/{name}-{uuid.uuid4().hex}"


def settled(df: DataFrame, name: str = "part", files: int | None = None) -> DataFrame:
    """``df`` written to the shared folder and read back: later steps plan on a scan, not on all that led here.

    Meant for narrow tables (digests, statuses, counts); ``files`` joins small ones up. What is stored
    outlives lost executors.
    """
    path = shared_table(df.sparkSession, name)
    (df.coalesce(files) if files else df).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """Rows dealt by key over as many tasks as the cluster has use for.

    For scopes whose work is not in their bytes: without a number of its own the shuffle's small
    partitions are joined up by size, and a few tasks do everything.
    """
    spark = df.sparkSession
    return df.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism), *keys)


def ensure_checkpoints(spark: SparkSession) -> None:
    """``checkpoint()`` needs a folder; only local sessions without one get their own."""
    shared_table(spark, "unused")


def write_elements(df: DataFrame, path: str, kind: str = "parquet") -> None:
    df.select("run_id", "side", "shard", "digest", "payload_bytes").write.mode("overwrite").format(kind).save(path)


def read_elements(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    return spark.read.schema(ELEMENTS).format(kind).load(path)


def write_cells(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").partitionBy("run_id").parquet(path)


def read_cells(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(CELLS).parquet(path)
