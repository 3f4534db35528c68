"""Peeling: from difference cells to the elements in them, in memory per scope or as rounds of joins."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS, check_np
from setsync.operators.cells import cell_positions, positions_np
from setsync.sources.messages import ensure_checkpoints, spread

SCHEMA = "run_id string, shard int, digest long, side int, decoded boolean, cells_used long"


class Cells:
    """Cells [0, size) in memory with the signed sums of a set of digests."""

    def __init__(self, size: int):
        self.ids, self.checks, self.counts = np.zeros(size, np.uint64), np.zeros(size, np.uint64), np.zeros(size, np.int64)

    def add(self, digests: np.ndarray, signs: np.ndarray, positions=positions_np) -> None:
        """Adds with the sign; adding the opposite sign removes."""
        digests = np.asarray(digests, np.int64)
        who, where = positions(digests, len(self.ids))
        np.bitwise_xor.at(self.ids, where, digests.view(np.uint64)[who])
        np.bitwise_xor.at(self.checks, where, check_np(digests)[who])
        np.add.at(self.counts, where, np.asarray(signs, np.int64)[who])

    def empty(self) -> bool:
        return not (self.ids.any() or self.checks.any() or self.counts.any())

    def prefix(self, size: int) -> "Cells":
        out = Cells(0)
        out.ids, out.checks, out.counts = self.ids[:size].copy(), self.checks[:size].copy(), self.counts[:size].copy()
        return out


def peel(cells: Cells, positions=positions_np) -> tuple[np.ndarray, np.ndarray, bool]:
    """(digests, signs, all found). Empties ``cells`` as far as it goes.

    Each round takes every pure cell at once: count one either way and a check that fits the sum.
    Cells of count 0 with something in their sums are neither pure nor empty.
    """
    found, owners = np.zeros(0, np.int64), np.zeros(0, np.int64)  # ``found`` stays sorted
    while True:
        at = np.flatnonzero(np.abs(cells.counts) == 1)
        if len(at):
            at = at[check_np(cells.ids[at].view(np.int64)) == cells.checks[at]]
        ids, first = np.unique(cells.ids[at].view(np.int64), return_index=True)
        signs = cells.counts[at][first]
        new = ~np.isin(ids, found, assume_unique=True)
        ids, signs = ids[new], signs[new]
        if not len(ids):
            break
        cells.add(ids, -signs, positions)
        found, owners = np.concatenate([found, ids]), np.concatenate([owners, signs])
        order = np.argsort(found)
        found, owners = found[order], owners[order]
    return found, owners, cells.empty()


def empties(who: np.ndarray, where: np.ndarray, n: int, size: int) -> bool:
    """Whether peeling takes all ``n`` elements out of cells [0, size): cells of one element are pure, whoever owns it."""
    inside = where < size
    who, where = who[inside], where[inside]
    load = np.bincount(where, minlength=size)
    names = np.zeros(size, np.int64)  # XOR of the elements in a cell: of a lone one, itself
    np.bitwise_xor.at(names, where, who)
    first = np.searchsorted(who, np.arange(n + 1))
    gone = np.zeros(n, bool)
    lone = names[load == 1]
    while len(lone):
        lone = np.unique(lone[~gone[lone]])
        gone[lone] = True
        counts = first[lone + 1] - first[lone]
        own = np.repeat(first[lone] - np.cumsum(counts) + counts, counts) + np.arange(counts.sum())
        spots, elements = where[own], who[own]
        np.subtract.at(load, spots, 1)
        np.bitwise_xor.at(names, spots, elements)
        spots = np.unique(spots)
        lone = names[spots[load[spots] == 1]]
    return bool(gone.all())


def least_prefix(digests: np.ndarray, enough: int) -> int:
    """The smallest prefix that decodes; more cells never hurt, so it is bisected below one that does."""
    who, where = positions_np(digests, enough)
    order = np.argsort(who, kind="stable")
    who, where = who[order], where[order]
    low, high = 0, enough
    likely = [k for k in (int(1.25 * len(digests)), int(1.5 * len(digests)) + 8) if k < enough]
    while low < high:
        mid = likely.pop() if likely else (low + high) // 2
        if not low <= mid < high:
            continue
        if empties(who, where, len(digests), mid):
            high = mid
        else:
            low = mid + 1
    return low


def peel_local(cells: DataFrame, size: int | None = None, exact_prefix: bool = False) -> DataFrame:
    """Peels each scope's difference cells (fast dialect) in one task: ``run_id, shard, digest, side, decoded, cells_used``.

    A scope without a difference gives one row with a null digest, and so does one that fails (decoded
    false). ``cells_used`` is the prefix length; with ``exact_prefix`` the least one that decodes.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        m = size or int(pdf.m.iloc[0])
        box = Cells(m)
        at = pdf.cell.to_numpy(np.int64)
        box.ids[at], box.checks[at], box.counts[at] = pdf.id_xor.to_numpy(np.int64).view(np.uint64), pdf.check_xor.to_numpy(np.int64).view(np.uint64), pdf.cnt
        ids, signs, decoded = peel(box)
        used = least_prefix(ids, m) if exact_prefix and decoded else m
        n = max(1, len(ids)) if decoded else 1
        none = not decoded or not len(ids)
        return pd.DataFrame(
            {
                "run_id": [pdf.run_id.iloc[0]] * n, "shard": [pdf.shard.iloc[0]] * n,
                "digest": pd.array([None] if none else ids.tolist(), "Int64"), "side": pd.array([None] if none else signs.tolist(), "Int32"),
                "decoded": [bool(decoded)] * n, "cells_used": [used] * n,
            }
        )

    return spread(cells, "run_id", "shard").groupBy("run_id", "shard").applyInPandas(run, SCHEMA)


def peel_relational(cells: DataFrame, size: int, dialect: str = "fast", max_rounds: int = 60) -> DataFrame:
    """The same as rounds of joins, for scopes no task can hold: pure cells, their elements once each,
    minus their contributions. Each round is cut by a checkpoint; the driver reads one number. Each round
    finds something, so there are as many rounds as the longest chain of peels: about log d if it decodes,
    and an error beyond ``max_rounds``."""
    spark = cells.sparkSession
    ensure_checkpoints(spark)
    hashing = DIALECTS[dialect]
    left = cells.select("run_id", "shard", "cell", "id_xor", "check_xor", "cnt")
    found = None
    for turn in range(max_rounds + 1):
        if turn == max_rounds:
            raise RuntimeError(f"peeling goes on after {max_rounds} rounds")
        pure = left.where((F.abs("cnt") == 1) & (hashing.check(F.col("id_xor")) == F.col("check_xor")))
        pure = pure.groupBy("run_id", "shard", F.col("id_xor").alias("digest")).agg(F.first("cnt").cast("int").alias("side"))
        pure = pure.join(found, ["run_id", "shard", "digest"], "left_anti") if found is not None else pure
        pure = pure.checkpoint()
        if not pure.limit(1).count():
            break
        found = pure if found is None else found.unionByName(pure)
        out = pure.withColumn("cell", F.explode(cell_positions(F.col("digest"), size, dialect)))
        out = out.select("run_id", "shard", "cell", F.col("digest").alias("id_xor"), hashing.check(F.col("digest")).alias("check_xor"), (-F.col("side")).cast("long").alias("cnt"))
        left = left.unionByName(out).groupBy("run_id", "shard", "cell").agg(F.bit_xor("id_xor").alias("id_xor"), F.bit_xor("check_xor").alias("check_xor"), F.sum("cnt").alias("cnt")).checkpoint()
    if found is None:
        found = spark.createDataFrame([], "run_id string, shard int, digest long, side int")
    stuck = left.where("id_xor <> 0 or check_xor <> 0 or cnt <> 0").select("run_id", "shard").distinct().withColumn("_stuck", F.lit(True))
    return found.join(stuck, ["run_id", "shard"], "left").select("run_id", "shard", "digest", "side", F.col("_stuck").isNull().alias("decoded"))
