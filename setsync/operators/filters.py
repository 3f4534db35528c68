"""Static membership filters: one bit space with k hashes, and the form split into k blocks."""

from __future__ import annotations

from math import log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS, LN2
from setsync.operators.slices import SCOPE, build_slices, sized, test_slices


def bits_for(n: Column, eps: Column) -> Column:
    """m for a target rate: -n ln(eps) / (ln 2)^2."""
    return F.ceil(-n * F.log(eps) / F.lit(LN2 * LN2)).cast("long")


def hashes_for(eps: Column) -> Column:
    return F.greatest(F.lit(1), F.round(-F.log(eps) / F.lit(LN2)).cast("int"))


def size_filter(n: int, eps: float) -> tuple[int, int]:
    return int(-(-(-n * log(eps) / LN2**2) // 1)), max(1, round(-log(eps) / LN2))


def size_filter_k(n: int, k: int) -> int:
    """Bits with k hashes at half fill."""
    return int(-(-n * k / LN2 // 1))


def sizes_for(elements: DataFrame, eps: list[float], scope: list[str] = SCOPE) -> DataFrame:
    """``scope, eps, n, m, k`` for each target rate."""
    n = elements.groupBy(*scope).agg(F.count("*").alias("n"))
    each = n.withColumn("eps", F.explode(F.array(*map(F.lit, eps))))
    return each.withColumn("m", bits_for(F.col("n"), F.col("eps"))).withColumn("k", hashes_for(F.col("eps")))


def spots(elements: DataFrame, sizes: DataFrame, phase: int, dialect: str) -> DataFrame:
    """A row for each element, filter of its scope and hash, with the bit position."""
    keys = [c for c in sizes.columns if c in elements.columns and c not in ("n", "m", "k")]
    each = elements.join(sizes.drop("n"), keys).withColumn("hash", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    return each.withColumn("pos", DIALECTS[dialect].below(F.col("m"), F.col("digest"), 500 + phase, F.col("hash")))


def build_filter(elements: DataFrame, sizes: DataFrame, phase: int = 1, dialect: str = "fast") -> DataFrame:
    """Filters as words: the columns of ``sizes`` but n, and ``word_no, bits``."""
    bit = F.expr("shiftleft(1L, cast(pmod(pos, 64) as int))")
    keys = [c for c in sizes.columns if c != "n"]
    return spots(elements, sizes, phase, dialect).groupBy(*keys, F.floor(F.col("pos") / 64).alias("word_no")).agg(F.bit_or(bit).alias("bits"))


def probe_filter(elements: DataFrame, words: DataFrame, sizes: DataFrame, phase: int = 1, dialect: str = "fast") -> DataFrame:
    """``passes`` for each element and filter of its scope: all of its bits are set."""
    keys = [c for c in sizes.columns if c not in ("n", "m", "k")]
    probes = spots(elements, sizes, phase, dialect).withColumn("word_no", F.floor(F.col("pos") / 64))
    met = probes.join(words.select(*keys, "word_no", "bits"), [*keys, "word_no"], "left")
    hit = F.expr("coalesce(getbit(bits, cast(pmod(pos, 64) as int)), 0)")
    own = [c for c in elements.columns if c not in keys]
    return met.groupBy(*keys, *own).agg((F.min(hit) == 1).alias("passes"))


def build_partitioned(elements: DataFrame, k: int, dialect: str = "fast") -> DataFrame:
    """The filter of k blocks is the first k slices of the element's slice sequence."""
    return build_slices(elements, 0, k - 1, dialect=dialect)


def probe_partitioned(elements: DataFrame, source: DataFrame, k: int, dialect: str = "fast") -> DataFrame:
    sizes = sized(source)
    tested = test_slices(elements, build_partitioned(source, k, dialect), sizes, 0, k - 1, dialect=dialect)
    return tested.withColumn("passes", F.col("first_miss").isNull())
