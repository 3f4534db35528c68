"""Cost model: what an element costs in the last phase, what a slice is worth, what a run will send."""

from __future__ import annotations

from math import ceil, log, log2

from pyspark.sql import Column
from pyspark.sql import functions as F

from setsync.functions.hashing import LN2

#: Field widths in bits and cells per difference in the limit.
ID_BITS = CHECK_BITS = COUNT_BITS = 64
CELLS_PER_DIFFERENCE = 1.35
DIGEST_BYTES = 8


def leak_cost_bits(kind: str = "cells", id_bits: int = ID_BITS, check_bits: int = CHECK_BITS, count_bits: int = COUNT_BITS, cells_per_diff: float = CELLS_PER_DIFFERENCE) -> float:
    """Bits to reconcile one element after the filters: a digest in a sketch, or its share of cells."""
    return float(id_bits) if kind == "sketch" else cells_per_diff * (id_bits + check_bits + count_bits)


def slice_bits(n: Column) -> Column:
    """Bits of a one-hash slice over n elements, half of them set."""
    return F.ceil(n / F.lit(LN2)).cast("long")


def slice_bits_of(n: int) -> int:
    return ceil(n / LN2)


def prefix_length(source: int, receiver: int, cost_bits: float, spare: int = 4) -> int:
    """Slices that hold the stop but for bad luck: each halves what is left of at most ``receiver`` elements."""
    if not source or not receiver:
        return 1
    return max(1, ceil(log2(max(1.0, receiver / source * LN2 * cost_bits)))) + 1 + spare


def expected_stop(u: float, m: float, cost_bits: float) -> int:
    """Slice number (from 0) after which the expected gain falls below the cost."""
    k = 0
    while u * 0.5 ** (k + 1) >= m / cost_bits:
        k += 1
    return k


def predict_hybrid(n_left: int, n_right: int, d: int, cost_bits: float | None = None, cell_bytes: float = 24.0) -> dict[str, float]:
    """Expected slices, leaks and bytes of the sliced hybrid for ``d`` differences split evenly."""
    cost = cost_bits or leak_cost_bits()
    u = d / 2
    m1 = n_left / LN2
    k1 = expected_stop(u, m1, cost)
    leaks_right = u * 0.5 ** (k1 + 1)
    suspects = n_right - u + leaks_right
    m2 = suspects / LN2
    k2 = expected_stop(u, m2, cost) if suspects else -1
    leaks_left = u * 0.5 ** (k2 + 1)
    filters = ((k1 + 1) * m1 + (k2 + 1) * m2) / 8
    leaks = leaks_left + leaks_right
    return {"slices_1": k1 + 1, "slices_2": k2 + 1, "filter_bytes": filters, "leaks": leaks, "metadata_bytes": filters + leaks * CELLS_PER_DIFFERENCE * cell_bytes}


def predict_static(n_left: int, n_right: int, d: int, eps: float, cell_bytes: float = 24.0) -> float:
    u = d / 2
    bits = -log(eps) / LN2**2
    positives = n_right - u + u * eps
    return (n_left + positives) * bits / 8 + 2 * u * eps * CELLS_PER_DIFFERENCE * cell_bytes


def predict_cells(d: int, cell_bytes: float = 24.0) -> float:
    """Between 1.72 cells a difference for few and 1.35 for many."""
    per = CELLS_PER_DIFFERENCE + 0.37 / (1 + d / 60) if d else 0
    return d * per * cell_bytes


def predict_sketch(d: int) -> float:
    return DIGEST_BYTES * d


def predict_parity(d: int) -> float:
    return 1.6 * DIGEST_BYTES * d
