"""Pairs of replicas with a set size and similarity, cut from a table; whole sweeps in one frame."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS
from setsync.sources.elements import LEFT, RIGHT, digests, table
from setsync.sources.messages import settled

#: Columns that make lineitem's rows distinct.
LINE_KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate"]
FULL_RANGE = [float(s) for s in range(0, 101, 5)]
HIGH_RANGE = [85 + 0.5 * k for k in range(31)]
PUBLISHED_SIZE = 100_000


def difference_per_side(n: int, similarity_pct: float) -> int:
    """u with (n - u) / (n + u) nearest to the similarity."""
    s = similarity_pct / 100
    return int(n * (1 - s) / (1 + s) + 0.5)


def runs_table(spark: SparkSession, n: int, similarities: list[float], trials: int = 1, smaller: float = 1.0) -> DataFrame:
    """``run_id, similarity_pct, trial, n, u, u_left``: one row per point. ``smaller`` shrinks the left side's own part."""
    rows = [(f"{s:g}/{t}", s, t, n, u := difference_per_side(n, s), int(u * smaller)) for s in similarities for t in range(trials)]
    return spark.createDataFrame(rows, "run_id string, similarity_pct double, trial int, n long, u long, u_left long")


def lowest(turns: DataFrame, wanted: int, about: int, trials: int, dialect: str) -> DataFrame:
    """The rows of every trial up to some order, at least the ``wanted`` lowest where there are as many.

    What no rank asks for is neither dealt nor sorted. ``about`` rows a trial are only a guess that sets the
    bound: rows are counted, and where they don't suffice the bound doubles, up to taking all of them.
    """
    share = (wanted + 8 * wanted**0.5 + 64) / max(1, about)
    while share < 0.5:
        low = settled(turns.where(order_of(F.col("digest"), F.col("trial"), dialect) < int(share * (1 << 60))), "lowest")
        met = low.groupBy("trial").count().agg(F.count("*").alias("trials"), F.min("count").alias("fewest")).first()
        if met.trials == trials and met.fewest >= wanted:
            return low
        share *= 2
    return turns


def ranked(elements: DataFrame, order: Column, buckets: int = 256) -> DataFrame:
    """Adds ``rank`` from 0 within a ``trial`` by ``order`` (a non-negative 60-bit hash), counted bucket by bucket: no single task sorts all."""
    width = (1 << 60) // buckets
    keyed = elements.withColumn("_order", order).withColumn("_bucket", F.floor(F.col("_order") / width).cast("int"))
    sizes = keyed.groupBy("trial", "_bucket").agg(F.count("*").alias("_n"))
    before = W.partitionBy("trial").orderBy("_bucket").rowsBetween(W.unboundedPreceding, -1)
    starts = sizes.withColumn("_start", F.coalesce(F.sum("_n").over(before), F.lit(0)))
    local = F.row_number().over(W.partitionBy("trial", "_bucket").orderBy("_order", "digest"))
    # One row a trial and bucket: at most ``trials * buckets`` rows to broadcast.
    known = keyed.join(F.broadcast(starts.select("trial", "_bucket", "_start")), ["trial", "_bucket"])
    return known.withColumn("rank", F.col("_start") + local - 1).drop("_bucket", "_start", "_order")


def order_of(digest: Column, trial: Column | int, dialect: str) -> Column:
    """A seeded order in 60 bits."""
    mixed = DIALECTS[dialect].mix(digest, 31, trial)
    return mixed if dialect == "portable" else F.shiftrightunsigned(mixed, 4)


def replica_pairs(elements: DataFrame, runs: DataFrame, dialect: str = "fast", trials: int = 1, about: int | None = None) -> DataFrame:
    """Both replicas of every run: ``run_id, side, shard, digest, payload_bytes``.

    Ranks below n - u are common, the next u are the left side's own, the next u the right side's.
    ``about`` how many elements there are (counted if not given): with it only those that can get such a rank are ranked.
    """
    wanted = runs.agg(F.max(F.col("n") + F.col("u"))).first()[0] or 0
    turns = elements.withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))
    turns = lowest(turns, wanted, elements.count() if about is None else about, trials, dialect)
    inside = (F.col("rank") < F.col("n") + F.col("u")) & (F.col("trial") == F.col("_trial"))
    rows = ranked(turns, order_of(F.col("digest"), F.col("trial"), dialect)).join(F.broadcast(runs.withColumnRenamed("trial", "_trial")), inside)
    common, r = F.col("n") - F.col("u"), F.col("rank")
    sides = (
        F.when(r < common, F.array(F.lit(LEFT), F.lit(RIGHT)))
        .when(r < common + F.col("u_left"), F.array(F.lit(LEFT)))
        .when(r >= F.col("n"), F.array(F.lit(RIGHT)))
    )
    return rows.select("run_id", F.explode(sides).alias("side"), F.lit(0).alias("shard"), "digest", "payload_bytes")


def threshold_pair(elements: DataFrame, similarity_pct: float, trial: int = 0, run_id: str = "run") -> DataFrame:
    """A pair by hash thresholds: no sort at all, sizes then vary by chance. For sets too large to rank."""
    s = similarity_pct / 100
    own = (1 - s) / 2
    x = F.shiftrightunsigned(F.xxhash64("digest", F.lit(31), F.lit(trial)), 11) * F.lit(2.0**-53)
    sides = F.when(x < own, F.array(F.lit(LEFT))).when(x < 2 * own, F.array(F.lit(RIGHT))).otherwise(F.array(F.lit(LEFT), F.lit(RIGHT)))
    return elements.select(F.lit(run_id).alias("run_id"), F.explode(sides).alias("side"), F.lit(0).alias("shard"), "digest", "payload_bytes")


def lineitem_sweep(spark: SparkSession, folder: str, similarities: list[float], trials: int = 1, dialect: str = "fast", n: int | None = None, element_bytes: tuple[int, int] | None = (8, 80)) -> tuple[DataFrame, DataFrame]:
    """(elements, runs) of a similarity sweep over lineitem: n is a third of its rows, 100,000 (the published size) at most; pass ``n`` for more.

    ``element_bytes``: sizes drawn uniformly from the digest; None keeps those of the rows.
    """
    base = digests(table(spark, folder, "lineitem"), LINE_KEY, dialect)
    if element_bytes:
        low, high = element_bytes
        base = base.withColumn("payload_bytes", (low + DIALECTS[dialect].below(high - low + 1, F.col("digest"), 91)).cast("int"))
    about = table(spark, folder, "lineitem").count()
    if n is None:
        n = min(PUBLISHED_SIZE, about // 3)
    runs = runs_table(spark, n, similarities, trials)
    return replica_pairs(base, runs, dialect, trials, about), runs


def lagging_pair(events: DataFrame, cut_off: str, dialect: str = "fast") -> DataFrame:
    """A replica that missed everything from ``cut_off`` on (left) against the whole (right)."""
    old = digests(events.where(F.col("ts") < F.lit(cut_off).cast("timestamp")), ["event_id"], dialect)
    new = digests(events, ["event_id"], dialect)
    from setsync.sources.elements import tagged

    return tagged(old, new, f"before {cut_off}")


def outage_pair(events: DataFrame, lost_left: tuple[str, str], lost_right: tuple[str, str]) -> DataFrame:
    """Two replicas, each of which lost the events of its own window."""
    from setsync.sources.elements import tagged

    without = lambda w: events.where(~((F.col("ts") >= F.lit(w[0]).cast("timestamp")) & (F.col("ts") < F.lit(w[1]).cast("timestamp"))))
    return tagged(digests(without(lost_left), ["event_id"]), digests(without(lost_right), ["event_id"]), "outages")


def key_ranges(keys: DataFrame, name: str, lacks: int = 2) -> DataFrame:
    """Two runs of whole numbers from one column: the left one lacks its greatest values, the right one its smallest."""
    each = keys.select(F.col(name).cast("long").alias("digest")).where("digest is not null").distinct()
    side = lambda order, s: each.join(F.broadcast(each.orderBy(order).limit(lacks)), "digest", "left_anti").select(F.lit("ranges").alias("run_id"), F.lit(s).alias("side"), F.lit(0).alias("shard"), "digest", F.lit(8).alias("payload_bytes"))
    return side(F.desc("digest"), LEFT).unionByName(side(F.asc("digest"), RIGHT))


def integer_ranges(spark: SparkSession, left: tuple[int, int], right: tuple[int, int]) -> DataFrame:
    """Two runs of whole numbers (ends included) as their own digests."""
    side = lambda r, s: spark.range(r[0], r[1] + 1).select(F.lit("ranges").alias("run_id"), F.lit(s).alias("side"), F.lit(0).alias("shard"), F.col("id").alias("digest"), F.lit(8).alias("payload_bytes"))
    return side(left, LEFT).unionByName(side(right, RIGHT))
