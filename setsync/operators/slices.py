"""One-hash filter slices: building, testing, and the stop rule as a query.

All slices of a prefix follow from the elements, so streaming them one by one until the gain falls
under the cost equals this: give each receiving element the first slice that rejects it, count by
slice, and stop at the first slice whose count is under m / C. Elements first rejected after the stop
were never tested by the protocol and stay suspects.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS, mixed_np
from setsync.plans.costs import slice_bits
from setsync.sources.messages import spread

SCOPE = ["run_id", "shard"]


def sized(elements: DataFrame, scope: list[str] = SCOPE) -> DataFrame:
    """``scope, n, m``: how many elements a scope has and the bits of its slices."""
    return elements.groupBy(*scope).agg(F.count("*").alias("n")).withColumn("m", slice_bits(F.col("n")))


def placed(elements: DataFrame, sizes: DataFrame, first: int, last: int, phase: int, dialect: str) -> DataFrame:
    """A row for each element and slice in [first, last], with its bit position."""
    each = elements.join(sizes.select(*SCOPE, "m"), SCOPE).withColumn("slice", F.explode(F.sequence(F.lit(first), F.lit(last))))
    return each.withColumn("pos", DIALECTS[dialect].below(F.col("m"), F.col("digest"), phase, F.col("slice")))


def build_slices(elements: DataFrame, first: int, last: int, phase: int = 1, sizes: DataFrame | None = None, dialect: str = "fast") -> DataFrame:
    """Slices as words of 64 bits: ``run_id, shard, slice, m, word_no, bits``."""
    spots = placed(elements, sizes if sizes is not None else sized(elements), first, last, phase, dialect)
    bit = F.expr("shiftleft(1L, cast(pmod(pos, 64) as int))")
    return spots.groupBy(*SCOPE, "slice", "m", F.floor(F.col("pos") / 64).alias("word_no")).agg(F.bit_or(bit).alias("bits"))


def test_slices(suspects: DataFrame, slices: DataFrame, sizes: DataFrame, first: int, last: int, phase: int = 1, dialect: str = "fast") -> DataFrame:
    """``first_miss`` of every suspect: the lowest slice in [first, last] that rejects it, else null.

    A scope without slices (an empty source) rejects everything at once: ``first_miss`` is -1.
    """
    known = suspects.join(sizes.select(*SCOPE, "m"), SCOPE, "left")
    probes = known.where("m > 0").withColumn("slice", F.explode(F.sequence(F.lit(first), F.lit(last))))
    probes = probes.withColumn("pos", DIALECTS[dialect].below(F.col("m"), F.col("digest"), phase, F.col("slice")))
    probes = probes.withColumn("word_no", F.floor(F.col("pos") / 64))
    words = slices.select(*SCOPE, "slice", "word_no", "bits")
    met = probes.join(words, [*SCOPE, "slice", "word_no"], "left")
    miss = F.expr("bits is null or getbit(bits, cast(pmod(pos, 64) as int)) = 0")
    tested = met.groupBy(*suspects.columns).agg(F.min(F.when(miss, F.col("slice"))).alias("first_miss"))
    return tested.unionByName(known.where("m is null or m = 0").select(*suspects.columns, F.lit(-1).alias("first_miss")))


def shard_kernel(first: int, last: int, phase: int, dialect: str = "fast"):
    """Both steps for one scope in memory, slice by slice over what still passes; equal to the joins."""

    def run(source: pd.DataFrame, receiver: pd.DataFrame) -> pd.DataFrame:
        left, right = source.digest.to_numpy(np.int64), receiver.digest.to_numpy(np.int64)
        miss = np.full(len(right), -1 if not len(left) else last + 1, np.int64)
        waiting = np.arange(len(right)) if len(left) else np.zeros(0, int)
        m = int(np.ceil(len(left) / np.log(2)))
        for k in range(first, last + 1):
            if not len(waiting):
                break
            bits = np.zeros(m, bool)
            bits[mixed_np(dialect, left, phase, k) % m] = True
            hit = bits[mixed_np(dialect, right[waiting], phase, k) % m]
            miss[waiting[~hit]] = k
            waiting = waiting[hit]
        return receiver.assign(first_miss=pd.Series(miss, receiver.index, "Int32").mask(miss > last))

    return run


def test_in_shards(source: DataFrame, suspects: DataFrame, first: int, last: int, phase: int = 1, dialect: str = "fast") -> DataFrame:
    """``test_slices`` over the slices of ``source`` without exploding: scopes meet in one task each, bits stay in memory.

    For sharded sets: a shard's slice is n / ln 2 bits and its elements are 8 bytes each.
    """
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in suspects.schema.fields) + ", first_miss int"
    kernel = shard_kernel(first, last, phase, dialect)

    def grouped(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return kernel(a, b)

    # Fresh names, as both sides may come from one frame.
    apart = spread(source.select(*SCOPE, "digest").toDF("run_id_", "shard_", "digest"), "run_id_", "shard_").groupBy("run_id_", "shard_")
    return apart.cogroup(spread(suspects, *SCOPE).groupBy(*SCOPE)).applyInPandas(grouped, schema)


def rejects_by_slice(tested: DataFrame, sizes: DataFrame, last: int, per: list[str] = ["run_id"], weight: str | None = None) -> DataFrame:
    """``per, slice, m, new_rejects, cum_rejects, cum_bits``: a row for each slice, those without rejects too.

    ``weight``: a column with the number of elements that a row stands for.

    With ``per = [run_id]`` shards decide together (their bits and rejects add up); with the scope each decides alone.
    """
    bits = sizes.groupBy(*per).agg(F.sum("m").alias("m"))
    calendar = bits.where("m > 0").withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(last))))
    counts = tested.where("first_miss >= 0").groupBy(*per, F.col("first_miss").alias("slice")).agg((F.sum(weight) if weight else F.count("*")).cast("long").alias("new_rejects"))
    full = calendar.join(counts, [*per, "slice"], "left").withColumn("new_rejects", F.coalesce("new_rejects", F.lit(0)))
    upto = W.partitionBy(*per).orderBy("slice").rowsBetween(W.unboundedPreceding, 0)
    return full.select(*per, "slice", "m", "new_rejects", F.sum("new_rejects").over(upto).alias("cum_rejects"), (F.col("m") * (F.col("slice") + 1)).alias("cum_bits"))


def stop_slice(histogram: DataFrame, cost_bits: float, per: list[str] = ["run_id"]) -> DataFrame:
    """``per, m, stop, new_at_stop``: the first slice that gained less than it cost; null where the prefix is too short.

    Costs count in tenths of a bit, so the strict test is exact.
    """
    tenths = int(round(cost_bits * 10))
    under = F.col("new_rejects") * tenths < F.col("m") * 10
    return histogram.groupBy(*per).agg(
        F.max("m").alias("m"),
        F.min(F.when(under, F.col("slice"))).alias("stop"),
        F.min_by(F.when(under, F.col("new_rejects")), F.when(under, F.col("slice"))).alias("new_at_stop"),
    )
