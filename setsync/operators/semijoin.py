"""Semijoins by keys, by a filter, by slices with a cost stop, and the whole relation; with what each ships.

The sending side is ``left``: its rows without a partner in ``right`` should stay at home.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS, canonical
from setsync.operators.filters import build_filter, probe_filter, sizes_for
from setsync.operators.slices import build_slices, rejects_by_slice, sized, stop_slice, test_slices
from setsync.plans.costs import prefix_length
from setsync.sources.messages import settled


@dataclass
class Shipped:
    """Rows of ``left`` that travel, and the bytes of keys or filters sent for it and of the rows."""

    rows: DataFrame
    traffic: DataFrame


def keyed(df: DataFrame, on: str, dialect: str) -> DataFrame:
    return df.select(F.lit("join").alias("run_id"), F.lit(0).alias("shard"), DIALECTS[dialect].digest(F.col(on).cast("string")).alias("digest"))


def traffic(spark, kind: str, sent: DataFrame | float, rows: DataFrame) -> DataFrame:
    """``method, sent_bytes, rows_shipped, row_bytes, total_bytes``."""
    weights = rows.agg(F.count("*").alias("rows_shipped"), F.coalesce(F.sum(F.octet_length(canonical(rows))), F.lit(0)).alias("row_bytes"))
    other = sent if isinstance(sent, DataFrame) else spark.range(1).select(F.lit(float(sent)).alias("sent_bytes"))
    return weights.join(F.broadcast(other)).select(F.lit(kind).alias("method"), "sent_bytes", "rows_shipped", "row_bytes", (F.col("sent_bytes") + F.col("row_bytes")).alias("total_bytes"))


def ship_all(left: DataFrame, right: DataFrame, on: str) -> Shipped:
    return Shipped(left, traffic(left.sparkSession, "ship_all", 0.0, left))


def key_semijoin(left: DataFrame, right: DataFrame, on: str, key_bytes: int = 8) -> Shipped:
    """Ships every distinct key one way and exactly the matching rows the other."""
    keys = right.select(on).where(F.col(on).isNotNull()).distinct()
    rows = left.join(keys, on, "left_semi")
    return Shipped(rows, traffic(left.sparkSession, "key_semijoin", keys.agg((F.count("*") * key_bytes).cast("double").alias("sent_bytes")), rows))


def filter_semijoin(left: DataFrame, right: DataFrame, on: str, eps: float, dialect: str = "fast") -> Shipped:
    """Ships a filter of the right side's keys; all rows that pass travel, the few wrong ones too."""
    source = keyed(right.where(F.col(on).isNotNull()).select(on).distinct(), on, dialect)
    keys = left.where(F.col(on).isNotNull()).select(on).distinct()
    sizes = sizes_for(source, [eps])
    probed = probe_filter(keyed(keys, on, dialect), build_filter(source, sizes, dialect=dialect), sizes, dialect=dialect).where("passes").select("digest")
    rows = left.withColumn("digest", DIALECTS[dialect].digest(F.col(on).cast("string"))).join(probed, "digest", "left_semi").drop("digest")
    bits = sizes.agg(F.coalesce(F.sum(F.ceil(F.col("m") / 8)), F.lit(0)).cast("double").alias("sent_bytes"))
    return Shipped(rows, traffic(left.sparkSession, f"filter_semijoin_{eps:g}", bits, rows))


def sliced_trace(left: DataFrame, right: DataFrame, on: str, dialect: str = "fast", row_bits: float | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(tested keys, rejected rows by slice, stop). An element here is a row of ``left``, its cost the mean row."""
    source = keyed(right.where(F.col(on).isNotNull()).select(on).distinct(), on, dialect)
    rows = left.where(F.col(on).isNotNull())
    counts = rows.groupBy(on).agg(F.count("*").alias("copies"))
    keys = counts.select(F.lit("join").alias("run_id"), F.lit(0).alias("shard"), DIALECTS[dialect].digest(F.col(on).cast("string")).alias("digest"), "copies")
    sizes = sized(source)
    stats = rows.agg(F.count("*").alias("n"), F.avg(F.octet_length(canonical(rows))).alias("w")).first()
    cost = row_bits or max(1.0, 8.0 * (stats.w or 1.0))
    last = prefix_length(max(1, source.count()), stats.n, cost) - 1
    tested = test_slices(keys, build_slices(source, 0, last, 1, sizes, dialect), sizes, 0, last, 1, dialect)
    tested = settled(tested, "tested-keys")
    histogram = rejects_by_slice(tested, sizes, last, weight="copies")
    return tested, histogram, stop_slice(histogram, cost)


def sliced_semijoin(left: DataFrame, right: DataFrame, on: str, mode: str = "turn_based", dialect: str = "fast") -> Shipped:
    """Ships slices until one keeps fewer rows at home than its bits would carry; then all that still pass."""
    tested, _, stops = sliced_trace(left, right, on, dialect)
    passing = tested.join(F.broadcast(stops.select("run_id", "stop")), "run_id", "left").where("first_miss is null or first_miss > stop").select("digest")
    rows = left.withColumn("digest", DIALECTS[dialect].digest(F.col(on).cast("string"))).join(passing, "digest", "left_semi").drop("digest")
    per_slice = F.ceil(F.col("m") / 8) + (1 if mode == "turn_based" else 0)
    sent = stops.agg(F.coalesce(F.sum((F.col("stop") + 1) * per_slice), F.lit(0)).cast("double").alias("sent_bytes"))
    return Shipped(rows, traffic(left.sparkSession, f"sliced_semijoin_{mode}", sent, rows))


def joined(shipped: Shipped, right: DataFrame, on: str) -> DataFrame:
    """The join itself, from what was shipped: equal for every way of shipping."""
    return shipped.rows.join(right, on)
