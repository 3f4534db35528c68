"""Static invertible tables: k hashes, one position in each of k equal blocks."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS, below_np
from setsync.operators.peel import SCHEMA, Cells, peel
from setsync.sources.messages import spread


def table_spots(elements: DataFrame, cells: int, k: int, dialect: str = "fast", salt: int = 900) -> DataFrame:
    block = cells // k
    spot = F.col("_h") * block + DIALECTS[dialect].below(block, F.col("digest"), salt, F.col("_h"))
    return elements.withColumn("_h", F.explode(F.sequence(F.lit(0), F.lit(k - 1)))).withColumn("cell", spot.cast("long")).drop("_h")


def build_table(elements: DataFrame, cells: int, k: int = 3, dialect: str = "fast") -> DataFrame:
    """``run_id, shard, side, cell, id_xor, check_xor, cnt`` of the cells that hold anything."""
    spots = table_spots(elements, cells, k, dialect).withColumn("chk", DIALECTS[dialect].check(F.col("digest")))
    return spots.groupBy("run_id", "shard", "side", "cell").agg(F.bit_xor("digest").alias("id_xor"), F.bit_xor("chk").alias("check_xor"), F.count("*").alias("cnt"))


def table_delete(table: DataFrame, elements: DataFrame, cells: int, k: int = 3, dialect: str = "fast") -> DataFrame:
    """The table without ``elements``: the same XOR, counts down."""
    gone = build_table(elements, cells, k, dialect).withColumn("cnt", -F.col("cnt"))
    keys = ["run_id", "shard", "side", "cell"]
    merged = table.unionByName(gone).groupBy(*keys).agg(F.bit_xor("id_xor").alias("id_xor"), F.bit_xor("check_xor").alias("check_xor"), F.sum("cnt").alias("cnt"))
    return merged.where("id_xor <> 0 or check_xor <> 0 or cnt <> 0")


def is_pure(dialect: str = "fast"):
    """One element, either owner's, and sums that fit together."""
    return (F.abs("cnt") == 1) & (DIALECTS[dialect].check(F.col("id_xor")) == F.col("check_xor"))


def block_positions(k: int, salt: int = 900):
    def positions(digests: np.ndarray, cells: int) -> tuple[np.ndarray, np.ndarray]:
        block = cells // k
        who = np.tile(np.arange(len(digests)), k)
        return who, np.concatenate([h * block + below_np(block, digests, salt, h) for h in range(k)]) if len(digests) else np.zeros(0, np.int64)

    return positions


def list_table(table: DataFrame, cells: int, k: int = 3, salt: int = 900) -> DataFrame:
    """Peels a table (of one set, or a difference): digests with signs, ``decoded`` false where cells remain."""
    size = cells // k * k

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        box = Cells(size)
        at = pdf.cell.to_numpy(np.int64)
        box.ids[at], box.checks[at], box.counts[at] = pdf.id_xor.to_numpy(np.int64).view(np.uint64), pdf.check_xor.to_numpy(np.int64).view(np.uint64), pdf.cnt
        ids, signs, decoded = peel(box, block_positions(k, salt))
        n = max(1, len(ids))
        return pd.DataFrame(
            {
                "run_id": [pdf.run_id.iloc[0]] * n, "shard": [pdf.shard.iloc[0]] * n, "digest": pd.array(ids.tolist() or [None], "Int64"),
                "side": pd.array(signs.tolist() or [None], "Int32"), "decoded": [bool(decoded)] * n, "cells_used": [size] * n,
            }
        )

    return spread(table, "run_id", "shard").groupBy("run_id", "shard").applyInPandas(run, SCHEMA)


def table_reconcile(elements: DataFrame, cells: int, k: int = 3, salt: int = 900) -> DataFrame:
    """The difference of both sides through one static table a scope; common elements cancel. ``salt`` draws other positions."""
    spots = table_spots(elements, cells, k, salt=salt).withColumn("chk", DIALECTS["fast"].check(F.col("digest")))
    diff = spots.groupBy("run_id", "shard", "cell").agg(F.bit_xor("digest").alias("id_xor"), F.bit_xor("chk").alias("check_xor"), F.sum(F.col("side").cast("long")).alias("cnt"))
    return list_table(diff, cells, k, salt)
