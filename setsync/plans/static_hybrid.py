"""The static hybrid: one filter of a fixed target rate each way, then cells; and its best rate."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setsync.functions.hashing import mixed_np
from setsync.operators.filters import build_filter, probe_filter, size_filter, sizes_for
from setsync.operators.slices import SCOPE
from setsync.operators.transfer import payload_lines, set_sizes
from setsync.plans import ledger
from setsync.plans.costs import CELLS_PER_DIFFERENCE
from setsync.plans.hybrid import reconcile_cells
from setsync.sources.elements import LEFT, RIGHT
from setsync.sources.messages import settled, spread

GRID = [k / 200 for k in range(1, 101)]


def rate_kernel(rates: list[float], dialect: str = "fast"):
    """Both static filters of every rate for one scope in memory: bits, leaks and digests wanted back.

    A hash of an element serves all rates; only its remainder by a filter's length is their own.
    """
    most = max(size_filter(1000, r)[1] for r in rates)

    def passing(source: list[np.ndarray], receiver: list[np.ndarray], m: int, k: int) -> np.ndarray:
        bits = np.zeros(m, bool)
        for h in source[:k]:
            bits[h % m] = True
        ok = np.ones(len(receiver[0]), bool)
        for h in receiver[:k]:
            ok &= bits[h % m]
        return ok

    def run(left: np.ndarray, right: np.ndarray) -> list[tuple[float, int, int, int, int]]:
        own_right, own_left = ~np.isin(right, left), ~np.isin(left, right)
        hashed = {(s, p): [mixed_np(dialect, x, 500 + p, h) for h in range(most)] for s, x in ((0, left), (1, right)) for p in (1, 2)}
        out = []
        for r in rates:
            m, k = size_filter(len(left), r)
            ok = passing(hashed[0, 1], hashed[1, 1], m, k) if m else np.zeros(len(right), bool)
            m2, k2 = size_filter(int(ok.sum()), r)
            back = passing([h[ok] for h in hashed[1, 2][:k2]], hashed[0, 2], m2, k2) if m2 else np.zeros(len(left), bool)
            wanted = int((back & own_left).sum())
            out.append((r, m, m2, int((ok & own_right).sum()) + wanted, wanted))
        return out

    return run


def static_counts(elements: DataFrame, eps: list[float], dialect: str = "fast") -> DataFrame:
    """``run_id, eps, bits_1, bits_2, leaks, wanted``: both filters really built and probed for all rates, scope by scope."""
    kernel = rate_kernel(eps, dialect)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        side, ids = pdf.side.to_numpy(), pdf.digest.to_numpy(np.int64)
        rows = kernel(ids[side == LEFT], ids[side == RIGHT])
        return pd.DataFrame([(pdf.run_id.iloc[0], *r) for r in rows], columns=["run_id", "eps", "bits_1", "bits_2", "leaks", "wanted"])

    each = spread(elements.select(*SCOPE, "side", "digest"), *SCOPE).groupBy(*SCOPE).applyInPandas(run, "run_id string, eps double, bits_1 long, bits_2 long, leaks long, wanted long")
    return settled(each.groupBy("run_id", "eps").agg(*[F.sum(c).alias(c) for c in ("bits_1", "bits_2", "leaks", "wanted")]), "rates", 1)


def static_ledger(elements: DataFrame, eps: list[float], cells_per_diff: float = CELLS_PER_DIFFERENCE, cell_bytes: int = 24, dialect: str = "fast") -> DataFrame:
    """Bytes of both filters and of the cells for their leaks, one method a rate."""
    sizes = set_sizes(elements)
    counts = static_counts(elements, eps, dialect).join(sizes, "run_id")
    named = counts.withColumn("method", F.concat(F.lit("static_"), F.format_string("%.1f", F.col("eps") * 100)))
    per = named.withColumn("run_id", F.concat_ws("|", "run_id", "method"))
    rows = ledger.lines(per, "", [
        (1, ledger.A, "filter", F.lit(1), F.ceil(F.col("bits_1") / 8), True), (2, ledger.B, "filter", (F.col("bits_2") > 0).cast("int"), F.ceil(F.col("bits_2") / 8), True),
        (3, ledger.A, "cell", F.ceil(F.col("leaks") * cells_per_diff), F.ceil(F.col("leaks") * cells_per_diff) * cell_bytes, True),
        (3, ledger.B, "wanted_digests", F.col("wanted"), 8 * F.col("wanted"), True), *payload_lines(per),
    ])
    return rows.withColumn("method", F.substring_index("run_id", "|", -1)).withColumn("run_id", F.substring_index("run_id", "|", 1))


def best_static(elements: DataFrame, grid: list[float] = GRID, dialect: str = "fast") -> DataFrame:
    """The rate of the least metadata for each run: ``run_id, eps, metadata_bytes``."""
    counts = static_counts(elements, grid, dialect)
    cost = F.ceil(F.col("bits_1") / 8) + F.ceil(F.col("bits_2") / 8) + F.ceil(F.col("leaks") * CELLS_PER_DIFFERENCE) * 24
    each = counts.withColumn("metadata_bytes", cost.cast("double"))
    ranked = each.withColumn("_r", F.row_number().over(W.partitionBy("run_id").orderBy("metadata_bytes", "eps")))
    return ranked.where("_r = 1").select("run_id", "eps", "metadata_bytes")


def static_hybrid(elements: DataFrame, eps: float) -> DataFrame:
    """The difference by the static protocol, exactly: ``run_id, digest, side``. Pass a stored frame."""
    left, right = elements.where(F.col("side") == LEFT), elements.where(F.col("side") == RIGHT)
    sizes = settled(sizes_for(left, [eps]), "sizes", 1)
    tested = settled(probe_filter(right, build_filter(left, sizes), sizes), "passed")
    passed = tested.where("passes").drop("passes", "eps")
    back = settled(sizes_for(passed, [eps]), "sizes", 1)
    returned = settled(probe_filter(left, build_filter(passed, back, 2), back, 2), "returned")
    kept = returned.where("passes").drop("passes", "eps")
    # Where nothing passed there is no filter to send back, and the whole left side is its own.
    lone = left.join(back.select("run_id", "shard"), ["run_id", "shard"], "left_anti")
    gone = right.join(sizes.select("run_id", "shard"), ["run_id", "shard"], "left_anti")
    columns = elements.columns
    leaks = reconcile_cells(passed.select(*columns).unionByName(kept.select(*columns)), 64).where("digest is not null").select("run_id", "digest", "side")
    sure = tested.where("not passes").select("run_id", "digest", "side").unionByName(returned.where("not passes").select("run_id", "digest", "side"))
    sure = sure.unionByName(lone.select("run_id", "digest", "side")).unionByName(gone.select("run_id", "digest", "side"))
    return sure.withColumn("side", F.col("side").cast("int")).unionByName(leaks)
