"""Which method for which regime: predicted bytes by method, and the cell-first protocol that decides by itself."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsync.operators import cells as cell_ops

from setsync.operators.estimators import cell_moment_estimate
from setsync.plans.costs import predict_cells, predict_hybrid, predict_parity, predict_sketch, predict_static
from setsync.plans.hybrid import difference_found, reconcile_cells, synchronise
from setsync.sources.messages import settled

#: Rough work per method in element operations, for weighing CPU against bytes.
WORK = {"sliced_hybrid": lambda n, d: 12 * n, "parity_groups": lambda n, d: 2 * n + 6 * d, "cell_stream": lambda n, d: 2 * n * max(1, d).bit_length(), "syndrome_sketch": lambda n, d: n * d + d * d, "static_1": lambda n, d: 14 * n, "full_transfer": lambda n, d: n}


def predictions(n: int, d: int, mean_bytes: float = 44.0, d_known: bool = False) -> dict[str, float]:
    """Metadata bytes of each method that may be used for sides of n elements with d differences."""
    out = {"sliced_hybrid": predict_hybrid(n, n, d)["metadata_bytes"], "cell_stream": predict_cells(d), "static_1": predict_static(n, n, d, 0.01), "full_transfer": (n - d / 2) * mean_bytes}
    if d_known:
        out |= {"syndrome_sketch": predict_sketch(d), "parity_groups": predict_parity(d)}
    return out


def advise(n: int, d_hat: int | None, cpu_s_per_op: float = 0.0, bytes_per_s: float = 1.0, subset: bool = False, mean_bytes: float = 44.0) -> tuple[str, float]:
    """(method, predicted metadata bytes) of the least time; without an estimate, the best worst case."""
    if d_hat is None:
        return "sliced_hybrid", max(predict_hybrid(n, n, d)["metadata_bytes"] for d in (0, n // 10, n, 2 * n))
    if subset:  # sizes give d, so the filter's rate can be set right
        rate = min((k / 200 for k in range(1, 101)), key=lambda e: predict_static(n, n, d_hat, e))
        return f"static_{rate * 100:g}", predict_static(n, n, d_hat, rate)
    each = predictions(n, d_hat, mean_bytes, d_known=True)
    if cpu_s_per_op:
        time = {k: v / bytes_per_s + cpu_s_per_op * WORK[k](n, d_hat) for k, v in each.items()}
    else:
        time = each
    # The sketch decodes in the square of d: only for very few.
    usable = {k: v for k, v in time.items() if k != "syndrome_sketch" or d_hat <= 100}
    best = min(usable, key=lambda k: (usable[k], k))
    return best, each[best]


def probe_then_sync(elements: DataFrame, prefix: int = 256, switch_at: float = 0.05) -> tuple[DataFrame, DataFrame]:
    """Cells first: (difference ``run_id, digest, side``, choice ``run_id, n, d_hat, intersection, method``).

    A prefix of cells gives an estimate of d; runs under ``switch_at`` of their size go on with cells,
    the rest turn to slices. A prefix that decodes already is final for its run. Pass a stored frame.
    """
    diff = settled(cell_ops.difference_cells(elements, prefix), "prefix")
    sizes = elements.groupBy("run_id").agg(F.count("*").alias("n"))
    d_hat = cell_moment_estimate(diff, prefix)
    choice = sizes.join(d_hat, "run_id").select(
        "run_id", "n", "d_hat", ((F.col("n") - F.col("d_hat")) / 2).alias("intersection"), F.when(F.col("d_hat") <= F.col("n") / 2 * switch_at, "cell_stream").otherwise("sliced_hybrid").alias("method")
    )
    choice = settled(choice, "choice", 1)
    small = elements.join(choice.where("method = 'cell_stream'").select("run_id"), "run_id", "left_semi")
    large = elements.join(choice.where("method <> 'cell_stream'").select("run_id"), "run_id", "left_semi")
    out = None
    if small.limit(1).count():
        out = reconcile_cells(small, prefix, exact_prefix=False).where("digest is not null").select("run_id", "digest", "side")
    if large.limit(1).count():
        more = difference_found(synchronise(large)).select("run_id", "digest", "side")
        out = more if out is None else out.unionByName(more)
    return out, choice


