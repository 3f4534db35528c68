"""Estimates of the number of differences before it is known."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS
from setsync.operators.cells import hit_rates
from setsync.sources.elements import LEFT, RIGHT

#: Fixed values from the literature on the sign-sum estimator: sums and safety factor.
SUMS, INFLATE = 128, 1.38
BITS = 48


def sign_sum_estimate(elements: DataFrame, sums: int = SUMS, inflate: float = INFLATE, dialect: str = "fast") -> DataFrame:
    """``run_id, d_hat, d_safe``: mean squared gap of ``sums`` random-sign sums, in one pass of fixed-size state."""
    words = -(-sums // BITS)
    mixed = elements
    for w in range(words):
        mixed = mixed.withColumn(f"_h{w}", DIALECTS[dialect].mix(F.col("digest"), 700, w))
    sign = lambda j: 1 - 2 * F.shiftrightunsigned(F.col(f"_h{j // BITS}"), j % BITS).bitwiseAND(F.lit(1).cast("long"))
    gaps = mixed.groupBy("run_id").agg(*[F.sum(sign(j) * F.col("side")).alias(f"y{j}") for j in range(sums)])
    total = sum((F.col(f"y{j}") * F.col(f"y{j}") for j in range(1, sums)), F.col("y0") * F.col("y0"))
    return gaps.select("run_id", (total / F.lit(float(sums))).alias("d_hat"), F.ceil(total / F.lit(float(sums)) * F.lit(inflate)).cast("long").alias("d_safe"))


def estimator_bytes(n: Column, sums: int = SUMS) -> Column:
    return sums * F.ceil(F.log2(2 * n + 1)) / 8


def cell_moment_estimate(diff: DataFrame, cells: int) -> DataFrame:
    """``run_id, d_hat``: squared cell counts of a difference prefix against the exact hit rates.

    The gap of the set sizes stands in cell 0 and is taken out of the others at their rate. Empty cells
    count too, so the calendar of cells (``cells`` small rows) is joined in.
    """
    spark = diff.sparkSession
    rates = F.broadcast(spark.createDataFrame([(i, float(r)) for i, r in enumerate(hit_rates(cells)) if i], "cell long, rate double"))
    gap = diff.groupBy("run_id").agg(F.max(F.when(F.col("cell") == 0, F.col("cnt"))).alias("g")).na.fill(0, ["g"])
    full = gap.join(rates).join(diff.select("run_id", "cell", "cnt"), ["run_id", "cell"], "left").na.fill(0, ["cnt"])
    off = F.col("cnt") - F.col("g") * F.col("rate")
    sums = full.groupBy("run_id").agg(F.sum(off * off).alias("x"), F.sum(F.col("rate") * (1 - F.col("rate"))).alias("y"))
    return sums.select("run_id", (F.col("x") / F.col("y")).alias("d_hat"))


def hll_difference_estimate(elements: DataFrame, lg_k: int = 14) -> DataFrame:
    """d from distinct-count sketches: twice the union less both sides. Weak where d is small."""
    per = elements.groupBy("run_id").agg(
        F.hll_sketch_estimate(F.hll_sketch_agg(F.col("digest"), F.lit(lg_k))).alias("u"),
        F.count(F.when(F.col("side") == LEFT, 1)).alias("a"), F.count(F.when(F.col("side") == RIGHT, 1)).alias("b"),
    )
    return per.select("run_id", (2 * F.col("u") - F.col("a") - F.col("b")).cast("double").alias("d_hat"))


def theta_difference_estimate(elements: DataFrame, lg_k: int = 14) -> DataFrame:
    """d from theta sketches of both sides: A minus B plus B minus A."""
    side = lambda test: F.expr(f"theta_sketch_agg(case when {test} then digest end, {lg_k})")
    per = elements.groupBy("run_id").agg(side("side < 0").alias("a"), side("side > 0").alias("b"))
    both = F.expr("theta_sketch_estimate(theta_difference(a, b)) + theta_sketch_estimate(theta_difference(b, a))")
    return per.select("run_id", both.cast("double").alias("d_hat"))


def subset_difference_size(elements: DataFrame) -> DataFrame:
    """Exact d where one side is known to hold the other: the gap of their sizes."""
    return elements.groupBy("run_id").agg(F.abs(F.sum(F.col("side").cast("long"))).cast("double").alias("d_hat"))
