"""XOR cells: the endless cell sequence of an element, its prefix sums, and their upkeep.

Every element is in cell 0. From cell i the next one lies ceil((i + 1.5) (1/sqrt(1 - u) - 1)) further,
at least 1, with u drawn from the digest; so cell i holds an element with a chance near 1 / (1 + i/2).
The steps are correctly rounded operations in a fixed order: the column form and the numpy form agree.
"""

from __future__ import annotations

from math import log

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS, check_np, draw_np

def enough_steps(cells: int) -> int:
    """Draws after which a sequence has left the prefix: about 2 ln M on average; to need this many has a chance under 1e-12."""
    return min(cells, 24 + int(6 * log(cells / 2 + 1)))


def cell_positions(digest: Column, cells: Column | int, dialect: str = "fast", steps: int | None = None) -> Column:
    """The digest's cells below ``cells``, rising, as an array."""
    steps = steps or (80 if isinstance(cells, Column) else enough_steps(cells))
    limit = (cells if isinstance(cells, Column) else F.lit(cells)).cast("long")
    draw = DIALECTS[dialect].draw

    def go(state: Column, k: Column) -> Column:
        i = state["at"]
        gap = (i.cast("double") + F.lit(1.5)) * (F.lit(1.0) / F.sqrt(F.lit(1.0) - draw(digest, k)) - F.lit(1.0))
        after = i + F.greatest(F.lit(1).cast("long"), F.ceil(gap).cast("long"))
        return F.when(i >= limit, state).otherwise(F.struct(after.alias("at"), F.when(after < limit, F.array_append(state["cells"], after)).otherwise(state["cells"]).alias("cells")))

    start = F.struct(F.lit(0).cast("long").alias("at"), F.array(F.lit(0).cast("long")).alias("cells"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, go, lambda s: s["cells"])


def positions_np(digests: np.ndarray, cells: int) -> tuple[np.ndarray, np.ndarray]:
    """(index of the digest, cell) pairs of all cells below ``cells``; the fast dialect's twin."""
    alive = np.arange(len(digests))
    at = np.zeros(len(digests), np.int64)
    who, where, step = [alive], [at], 0
    while len(alive):
        step += 1
        u = draw_np(digests[alive], step)
        gap = (at.astype(np.float64) + 1.5) * (1.0 / np.sqrt(1.0 - u) - 1.0)
        with np.errstate(over="ignore", invalid="ignore"):
            after = at + np.maximum(1, np.minimum(np.ceil(gap), 2.0**62)).astype(np.int64)
        inside = after < cells
        alive, at = alive[inside], after[inside]
        who.append(alive)
        where.append(at)
    return np.concatenate(who), np.concatenate(where)


def hit_rates(cells: int) -> np.ndarray:
    """The exact chance of each cell below ``cells`` to hold an element, by forward recursion over the steps."""
    rate = np.zeros(cells)
    if cells:
        rate[0] = 1.0
    for i in range(cells - 1):
        k = np.arange(0, cells - i, dtype=float)
        beyond = ((i + 1.5) / (i + 1.5 + k)) ** 2  # chance of a step longer than k
        rate[i + 1 :] += rate[i] * (beyond[:-1] - beyond[1:])
    return rate


def contributions(elements: DataFrame, cells: Column | int, dialect: str = "fast", low: int = 0) -> DataFrame:
    """A row for each element and cell in [low, cells): ``run_id, shard, cell, digest, chk, side``."""
    spots = cell_positions(F.col("digest"), cells, dialect)
    if low:
        spots = F.filter(spots, lambda c: c >= low)
    return elements.withColumn("chk", DIALECTS[dialect].check(F.col("digest"))).withColumn("cell", F.explode(spots)).select("run_id", "shard", "cell", "digest", "chk", "side")


def build_cells(elements: DataFrame, low: int, high: Column | int, dialect: str = "fast") -> DataFrame:
    """Cells [low, high) of each side's set: ``run_id, shard, side, cell, id_xor, check_xor, cnt``."""
    rows = contributions(elements, high, dialect, low)
    return rows.groupBy("run_id", "shard", "side", "cell").agg(F.bit_xor("digest").alias("id_xor"), F.bit_xor("chk").alias("check_xor"), F.count("*").alias("cnt"))


def subtract_cells(left: DataFrame, right: DataFrame) -> DataFrame:
    """Receiver minus sender, cell by cell."""
    keys = ["run_id", "shard", "cell"]
    zero = F.lit(0).cast("long")
    a = left.select(*keys, F.col("id_xor").alias("ia"), F.col("check_xor").alias("ca"), F.col("cnt").alias("na"))
    b = right.select(*keys, F.col("id_xor").alias("ib"), F.col("check_xor").alias("cb"), F.col("cnt").alias("nb"))
    both = a.join(b, keys, "full_outer")
    xor = lambda x, y: F.coalesce(x, zero).bitwiseXOR(F.coalesce(y, zero))
    return both.select(*keys, xor("ia", "ib").alias("id_xor"), xor("ca", "cb").alias("check_xor"), (F.coalesce("nb", zero) - F.coalesce("na", zero)).alias("cnt"))


def summed(digests: np.ndarray, signs: np.ndarray, high: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(cell, XOR of digests, XOR of checks, sum of signs) of the cells below ``high`` that anything falls in."""
    who, where = positions_np(digests, high)
    order = np.argsort(where, kind="stable")
    who, where = who[order], where[order]
    starts = np.flatnonzero(np.diff(where, prepend=-1))
    if not len(starts):
        return (np.zeros(0, np.int64),) * 4
    fold = lambda x, how: how.reduceat(x[who], starts)
    return where[starts], fold(digests, np.bitwise_xor), fold(check_np(digests).view(np.int64), np.bitwise_xor), fold(signs, np.add)


def cell_kernel(high: int):
    """Partial difference cells of each batch and scope: what would be a row per contribution is added up before it moves."""

    def run(batches):
        for batch in batches:
            pdf = batch.to_pandas()
            for (run_id, shard), own in pdf.groupby(["run_id", "shard"], sort=False):
                at, ids, checks, counts = summed(own.digest.to_numpy(np.int64), own.side.to_numpy(np.int64), high)
                yield pa.record_batch(
                    [pa.array([run_id] * len(at), pa.string()), pa.array(np.full(len(at), shard, np.int32)), pa.array(at, pa.int64()), pa.array(ids), pa.array(checks), pa.array(counts)],
                    names=["run_id", "shard", "cell", "id_xor", "check_xor", "cnt"],
                )

    return run


def difference_cells(elements: DataFrame, high: Column | int, dialect: str = "fast") -> DataFrame:
    """The same in one aggregation over both sides: common elements cancel.

    With a fixed prefix and the fast dialect each batch adds its elements up in memory first.
    """
    if dialect == "fast" and isinstance(high, int):
        parts = elements.select("run_id", "shard", "digest", F.col("side").cast("int").alias("side")).mapInArrow(cell_kernel(high), "run_id string, shard int, cell long, id_xor long, check_xor long, cnt long")
        return parts.groupBy("run_id", "shard", "cell").agg(F.bit_xor("id_xor").alias("id_xor"), F.bit_xor("check_xor").alias("check_xor"), F.sum("cnt").alias("cnt"))
    rows = contributions(elements, high, dialect)
    return rows.groupBy("run_id", "shard", "cell").agg(F.bit_xor("digest").alias("id_xor"), F.bit_xor("chk").alias("check_xor"), F.sum(F.col("side").cast("long")).alias("cnt"))


def maintain_cells(cells: DataFrame, changes: DataFrame, high: int, dialect: str = "fast") -> DataFrame:
    """A kept prefix brought up to date: ``changes`` has elements and ``change`` (+1 insert, -1 delete)."""
    spots = changes.withColumn("chk", DIALECTS[dialect].check(F.col("digest"))).withColumn("cell", F.explode(cell_positions(F.col("digest"), high, dialect)))
    keys = ["run_id", "shard", "side", "cell"]
    new = spots.select(*keys, F.col("digest").alias("id_xor"), F.col("chk").alias("check_xor"), F.col("change").cast("long").alias("cnt"))
    merged = cells.select(*new.columns).unionByName(new).groupBy(*keys).agg(F.bit_xor("id_xor").alias("id_xor"), F.bit_xor("check_xor").alias("check_xor"), F.sum("cnt").alias("cnt"))
    return merged.where("id_xor <> 0 or check_xor <> 0 or cnt <> 0")
