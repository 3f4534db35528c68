"""Ground truth and the plain baselines: exact difference, every digest, everything."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsync.plans import ledger


def exact_difference(elements: DataFrame) -> DataFrame:
    """``run_id, digest, payload_bytes, side`` of the elements one side alone has: one aggregation of digests."""
    per = elements.groupBy("run_id", "digest").agg(F.sum(F.col("side").cast("long")).alias("side"), F.max("payload_bytes").alias("payload_bytes"))
    return per.where("side <> 0").select("run_id", "digest", "payload_bytes", F.col("side").cast("int").alias("side"))


def set_sizes(elements: DataFrame) -> DataFrame:
    """``run_id, n_a, n_b, a_only, b_only, common, d, jaccard`` and the bytes of each part."""
    per = elements.groupBy("run_id", "digest").agg(F.min("side").alias("low"), F.max("side").alias("high"), F.max("payload_bytes").alias("bytes"))
    a, b = (F.col("high") < 0), (F.col("low") > 0)
    both = ~a & ~b
    count = lambda c: F.sum(F.when(c, 1).otherwise(0)).cast("long")
    size = lambda c: F.sum(F.when(c, F.col("bytes")).otherwise(0)).cast("long")
    sums = per.groupBy("run_id").agg(
        count(a | both).alias("n_a"), count(b | both).alias("n_b"), count(a).alias("a_only"), count(b).alias("b_only"), count(both).alias("common"),
        size(a).alias("a_only_bytes"), size(b).alias("b_only_bytes"), size(both).alias("common_bytes"),
    )
    union = F.col("a_only") + F.col("b_only") + F.col("common")
    return sums.withColumn("d", F.col("a_only") + F.col("b_only")).withColumn("jaccard", F.col("common") / union)


def full_transfer_ledger(sizes: DataFrame) -> DataFrame:
    """The sender ships its whole set; the receiver answers with what that lacks."""
    return ledger.lines(sizes, "full_transfer", [
        (1, ledger.A, "payload", F.col("a_only"), F.col("a_only_bytes"), False),
        (1, ledger.A, "payload_common", F.col("common"), F.col("common_bytes"), True),
        (1, ledger.B, "payload", F.col("b_only"), F.col("b_only_bytes"), False),
    ])


def payload_lines(sizes: DataFrame) -> list:
    return [(9, ledger.A, "payload", F.col("a_only"), F.col("a_only_bytes"), False), (9, ledger.B, "payload", F.col("b_only"), F.col("b_only_bytes"), False)]


def digest_exchange_ledger(sizes: DataFrame) -> DataFrame:
    """The sender ships every digest; the receiver knows the difference and asks for what it lacks."""
    return ledger.lines(sizes, "digest_exchange", [
        (1, ledger.A, "digests", F.col("n_a"), 8 * F.col("n_a"), True),
        (1, ledger.B, "wanted_digests", F.col("a_only"), 8 * F.col("a_only"), True), *payload_lines(sizes),
    ])


def united(elements: DataFrame) -> DataFrame:
    """The union that both sides must end with."""
    return elements.groupBy("run_id", "digest").agg(F.max("payload_bytes").alias("payload_bytes"))
