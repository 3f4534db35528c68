"""What every message of a run costs: one row per class of messages, and the sums over them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

A, B = -1, 1
COLUMNS = ["run_id", "method", "phase", "sender", "kind", "messages", "bytes", "is_metadata"]
#: Kinds shown apart from the core of the metadata.
EXTRAS = ("wanted_digests", "estimator", "size_header", "stop", "slice_request")


def lines(runs: DataFrame, method: str, entries: list[tuple[int, int, str, Column, Column, bool]]) -> DataFrame:
    """A row per entry (phase, sender, kind, messages, bytes, metadata) and row of ``runs``; zero messages leave none."""
    each = [
        F.struct(F.lit(p).alias("phase"), F.lit(s).alias("sender"), F.lit(k).alias("kind"), n.cast("long").alias("messages"), b.cast("double").alias("bytes"), F.lit(m).alias("is_metadata"))
        for p, s, k, n, b, m in entries
    ]
    rows = runs.select("run_id", F.explode(F.array(*each)).alias("e")).where("e.messages > 0")
    return rows.select("run_id", F.lit(method).alias("method"), "e.*")


def summarise(ledger: DataFrame) -> DataFrame:
    """``run_id, method, metadata_bytes, metadata_core_bytes, payload_sent, total_bytes``."""
    meta = F.col("is_metadata")
    core = meta & ~F.col("kind").isin(*EXTRAS)
    return ledger.groupBy("run_id", "method").agg(
        F.sum(F.when(meta, F.col("bytes")).otherwise(0)).alias("metadata_bytes"),
        F.sum(F.when(core, F.col("bytes")).otherwise(0)).alias("metadata_core_bytes"),
        F.sum(F.when(~meta, F.col("bytes")).otherwise(0)).alias("payload_sent"),
        F.sum("bytes").alias("total_bytes"),
    )


def by_kind(ledger: DataFrame) -> DataFrame:
    """Bytes by method, phase and kind with subtotals."""
    return ledger.rollup("method", "phase", "kind").agg(F.sum("bytes").alias("bytes"), F.sum("messages").alias("messages"))
