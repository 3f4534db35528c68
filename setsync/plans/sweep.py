"""Experiment runner: all methods over a similarity sweep, measures and crossovers."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsync.operators.estimators import sign_sum_estimate
from setsync.operators.parity import parity_groups, parity_ledger
from setsync.operators.syndrome import sketch_ledger
from setsync.operators.transfer import digest_exchange_ledger, exact_difference, full_transfer_ledger, payload_lines, set_sizes
from setsync.plans import ledger
from setsync.plans.hybrid import Phase, difference_found, filter_phases, hybrid_ledger, reconcile_cells, synchronise
from setsync.plans.costs import CELLS_PER_DIFFERENCE, DIGEST_BYTES, leak_cost_bits
from setsync.plans.static_hybrid import static_counts, static_ledger
from setsync.sources.elements import LEFT, RIGHT
from setsync.sources.messages import settled, spread

STATIC_RATES = [0.01, 0.05, 0.10, 0.25]


def cell_stream_ledger(elements: DataFrame, start: int | None = None, cell_bytes: int = 24) -> DataFrame:
    """The pure cell stream's least decoding prefix and the digests wanted back."""
    sizes = set_sizes(elements)
    start = start or int(1.5 * (sizes.agg(F.max("d")).first()[0] or 0)) + 16
    got = reconcile_cells(elements, start)
    used = got.groupBy("run_id", "shard").agg(F.max("cells_used").alias("c"), F.sum(F.when(F.col("side") < 0, 1).otherwise(0)).alias("w")).groupBy("run_id").agg(F.sum("c").alias("cells"), F.sum("w").alias("wanted"))
    per = sizes.join(used, "run_id", "left").na.fill(0)
    return ledger.lines(per, "cell_stream", [
        (3, ledger.A, "cell", F.col("cells"), F.col("cells") * cell_bytes, True), (3, ledger.B, "stop", F.lit(1), F.lit(1), True),
        (3, ledger.B, "wanted_digests", F.col("wanted"), 8 * F.col("wanted"), True), *payload_lines(per),
    ])


def all_ledgers(elements: DataFrame, rates: list[float] = STATIC_RATES) -> DataFrame:
    """Ledger rows of every method over all runs in ``elements`` (fast dialect; a stored frame)."""
    sizes = settled(set_sizes(elements), "sizes", 1)
    trace = synchronise(elements)
    _, parity_costs = parity_groups(elements, sign_sum_estimate(elements).select("run_id", F.col("d_safe").alias("d_hat")))
    parts = [
        hybrid_ledger(elements, trace), static_ledger(elements, rates), cell_stream_ledger(elements), sketch_ledger(sizes),
        parity_ledger(sizes, parity_costs), full_transfer_ledger(sizes), digest_exchange_ledger(sizes),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def measures(summary: DataFrame, elements: DataFrame, runs: DataFrame) -> DataFrame:
    """``method, similarity_pct, trial, d, metadata_bytes, total_bytes, minimum_bytes, overhead_ratio``; no ratio without a difference."""
    sizes = set_sizes(elements).select("run_id", "d", (F.col("a_only_bytes") + F.col("b_only_bytes")).alias("minimum_bytes"))
    rows = summary.join(sizes, "run_id").join(F.broadcast(runs.select("run_id", "similarity_pct", "trial")), "run_id")
    return rows.withColumn("overhead_ratio", F.when(F.col("minimum_bytes") > 0, F.col("total_bytes") / F.col("minimum_bytes")))


def over_trials(rows: DataFrame, names: list[str] = ["metadata_bytes", "metadata_core_bytes", "total_bytes", "overhead_ratio"], places: int = 9) -> DataFrame:
    """Mean and standard deviation of every measure by method and similarity."""
    each = [F.round(f(n), places).alias(f"{n}_{k}") for n in names for k, f in (("mean", F.avg), ("sd", F.stddev_samp))]
    return rows.groupBy("method", "similarity_pct").agg(F.avg("d").alias("d"), *each, F.count("*").alias("trials"))


def beside(rows: DataFrame, measure: str = "metadata_bytes") -> DataFrame:
    """Similarities down, methods across."""
    return rows.groupBy("similarity_pct").pivot("method").agg(F.avg(measure))


def crossover(rows: DataFrame, method: str, other: str, measure: str = "total_bytes") -> DataFrame:
    """``method, other, crossover_similarity``: the highest similarity from which down ``method`` never costs more."""
    a = rows.where(F.col("method") == method).groupBy("similarity_pct").agg(F.avg(measure).alias("x"))
    b = rows.where(F.col("method") == other).groupBy("similarity_pct").agg(F.avg(measure).alias("y"))
    both = a.join(b, "similarity_pct")
    worse = both.agg(F.min(F.when(F.col("x") > F.col("y"), F.col("similarity_pct"))).alias("w"))
    below = both.join(F.broadcast(worse)).where("w is null or similarity_pct < w").agg(F.max("similarity_pct").alias("crossover_similarity"))
    return below.select(F.lit(method).alias("method"), F.lit(other).alias("other"), "crossover_similarity")


def savings(rows: DataFrame, method: str = "sliced_hybrid", measure: str = "metadata_bytes") -> DataFrame:
    """What ``method`` saves against each other one, in per cent of theirs."""
    own = rows.where(F.col("method") == method).groupBy("similarity_pct").agg(F.avg(measure).alias("own"))
    rest = rows.where(F.col("method") != method).groupBy("method", "similarity_pct").agg(F.avg(measure).alias("theirs"))
    return rest.join(own, "similarity_pct").select(F.col("method").alias("other"), "similarity_pct", F.when(F.col("theirs") != 0, (F.col("theirs") - F.col("own")) / F.col("theirs") * 100).alias("saving_pct"))


def leaks_of(first: Phase, second: Phase) -> DataFrame:
    """``run_id, leaks, wanted``: what both filter phases let through, and the left side's part of it."""
    kept = [p.status.where("suspect").select("run_id", "digest", F.lit(s).alias("s")) for p, s in ((first, 1), (second, -1))]
    one_sided = kept[0].unionByName(kept[1]).groupBy("run_id", "digest").agg(F.sum("s").alias("s")).where("s <> 0")
    return one_sided.groupBy("run_id").agg(F.count("*").alias("leaks"), F.sum(F.when(F.col("s") < 0, 1).otherwise(0)).alias("wanted"))


def charged_hybrid(first: Phase, second: Phase, cost_bits: float | None = None) -> DataFrame:
    """``run_id, slices_1, bytes_1, slices_2, bytes_2, leaks, metadata_bytes``: slices as sent, leaks at their cost in cells."""
    sent = lambda p, k: p.stops.select("run_id", (F.col("stop") + 1).alias(f"slices_{k}"), ((F.col("stop") + 1) * F.ceil(F.col("m") / 8)).cast("long").alias(f"bytes_{k}"))
    per = sent(first, 1).join(sent(second, 2), "run_id", "left").join(leaks_of(first, second).drop("wanted"), "run_id", "left").na.fill(0)
    return per.withColumn("metadata_bytes", F.round(F.col("bytes_1") + F.col("bytes_2") + F.col("leaks") * (cost_bits or leak_cost_bits()) / 8, 3))


def charged_rows(elements: DataFrame, runs: DataFrame, methods: list[str], rates: list[float] = [], dialect: str = "portable") -> DataFrame:
    """``method, run_id, similarity_pct, trial, d, metadata_bytes, total_bytes, minimum_bytes, overhead_ratio`` with the exact step charged.

    Filters are built and tested; what they leave costs its share of cells, and the methods without
    filters what their formulas say for the true d. ``elements``: a stored frame.
    """
    sizes = settled(set_sizes(elements), "sizes", 1)
    formulas = {
        "cell_stream": F.ceil(F.col("d") * CELLS_PER_DIFFERENCE) * 24, "syndrome_sketch": DIGEST_BYTES * F.col("d"),
        "digest_exchange": DIGEST_BYTES * F.col("n_a"), "full_transfer": F.col("common_bytes"),
    }
    parts = [sizes.select("run_id", F.lit(k).alias("method"), v.cast("double").alias("metadata_bytes")) for k, v in formulas.items() if k in methods]
    if "sliced_hybrid" in methods:
        parts.append(charged_hybrid(*filter_phases(elements, dialect=dialect)).select("run_id", F.lit("sliced_hybrid").alias("method"), "metadata_bytes"))
    if rates:
        cost = F.ceil(F.col("bits_1") / 8) + F.ceil(F.col("bits_2") / 8) + F.ceil(F.col("leaks") * CELLS_PER_DIFFERENCE) * 24
        parts.append(static_counts(elements, rates, dialect).select("run_id", F.concat(F.lit("static_"), (F.col("eps") * 100).cast("int").cast("string")).alias("method"), cost.cast("double").alias("metadata_bytes")))
    rows = parts[0]
    for more in parts[1:]:
        rows = rows.unionByName(more)
    minimum = (F.col("a_only_bytes") + F.col("b_only_bytes")).alias("minimum_bytes")
    known = rows.join(sizes.select("run_id", "d", minimum), "run_id").join(F.broadcast(runs.select("run_id", "similarity_pct", "trial")), "run_id")
    total = F.round(F.col("metadata_bytes") + F.col("minimum_bytes"), 3)
    ratio = F.when(F.col("minimum_bytes") > 0, F.round(total / F.col("minimum_bytes"), 6))
    return known.select("method", "run_id", "similarity_pct", "trial", "d", "metadata_bytes", total.alias("total_bytes"), "minimum_bytes", ratio.alias("overhead_ratio"))


def operation_counts(elements: DataFrame, dialect: str = "portable") -> DataFrame:
    """Deterministic effort of the hybrid by run: bits set and tested, cell updates, elements peeled.

    An element updates about 1 + 2 ln(c / 2 + 1) of c cells, and c is what the leaks are charged.
    """
    first, second = filter_phases(elements, dialect=dialect)
    tests = lambda p: p.status.join(p.stops.select("run_id", "stop"), "run_id", "left").groupBy("run_id").agg(F.sum(F.coalesce(F.least(F.col("first_miss"), F.col("stop")), F.col("stop"), F.lit(-1)) + 1).alias("t"))
    builds = lambda p: p.sizes.groupBy("run_id").agg(F.sum("n").alias("n")).join(p.stops, "run_id").select("run_id", (F.col("n") * (F.col("stop") + 1)).alias("t"))
    left = leaks_of(first, second).select("run_id", "leaks")
    suspects = first.status.where("suspect").select("run_id").unionByName(second.status.where("suspect").select("run_id")).groupBy("run_id").agg(F.count("*").alias("n"))
    cells = F.ceil(F.coalesce("leaks", F.lit(0)) * CELLS_PER_DIFFERENCE)
    updates = suspects.join(left, "run_id", "left").select("run_id", F.round(F.col("n") * (1 + 2 * F.log(cells / 2 + 1)), 3).alias("t"))
    parts = [(tests(first), "test_1"), (tests(second), "test_2"), (builds(first), "set_1"), (builds(second), "set_2"), (updates, "cell_update"), (left.select("run_id", F.col("leaks").alias("t")), "peel")]
    out = None
    for df, name in parts:
        row = df.select("run_id", F.lit(name).alias("operation"), F.col("t").cast("double").alias("times"))
        out = row if out is None else out.unionByName(row)
    return out


def method_times(elements: DataFrame, cost_bits: float | None = None, rate: float = 0.01, sketch_limit: int = 64) -> DataFrame:
    """``run_id, method, encode_ms, decode_ms, compute_ms``: each protocol run by one task for each run, as two peers on one machine would.

    Encoding builds what is sent; decoding tests and peels it. The sketch decodes in the square of d, so
    it is run up to ``sketch_limit`` differences and left out beyond.
    """
    from setsync.functions.hashing import mixed_np
    from setsync.operators.cells import summed
    from setsync.operators.filters import size_filter
    from setsync.operators.peel import Cells, peel
    from setsync.operators.syndrome import decode, sketch

    cost = cost_bits or leak_cost_bits()

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        side, ids = pdf.side.to_numpy(), pdf.digest.to_numpy(np.int64)
        left, right = ids[side == LEFT], ids[side == RIGHT]
        clock, spent = time.perf_counter, {}

        def charge(method: str, step: int, began: float) -> None:
            spent.setdefault(method, [0.0, 0.0])[step] += (clock() - began) * 1000

        def cells(method: str, a: np.ndarray, b: np.ndarray, start: int) -> int:
            size = max(8, start)
            while True:
                began = clock()
                both = [summed(x, np.full(len(x), s), size) for x, s in ((a, -1), (b, 1))]
                charge(method, 0, began)
                began, box = clock(), Cells(size)
                for at, sums, checks, counts in both:
                    box.ids[at] ^= sums.view(np.uint64)
                    box.checks[at] ^= checks.view(np.uint64)
                    box.counts[at] += counts
                found, _, done = peel(box)
                charge(method, 1, began)
                if done:
                    return len(found)
                size *= 2

        def slices(source: np.ndarray, receiver: np.ndarray, phase: int) -> np.ndarray:
            waiting, m, k = receiver, int(np.ceil(len(source) / np.log(2))), 0
            while m:
                began, bits = clock(), np.zeros(m, bool)
                bits[mixed_np("fast", source, phase, k) % m] = True
                charge("sliced_hybrid", 0, began)
                began = clock()
                ok = bits[mixed_np("fast", waiting, phase, k) % m]
                gained, waiting, k = int((~ok).sum()), waiting[ok], k + 1
                charge("sliced_hybrid", 1, began)
                if gained * cost < m:
                    return waiting
            return waiting[:0]

        def filtered(source: np.ndarray, receiver: np.ndarray, phase: int) -> np.ndarray:
            (m, k), began = size_filter(len(source), rate), clock()
            bits, ok = np.zeros(max(1, m), bool), np.full(len(receiver), m > 0)
            for h in range(k if m else 0):
                bits[mixed_np("fast", source, 500 + phase, h) % m] = True
            charge("static", 0, began)
            began = clock()
            for h in range(k if m else 0):
                ok &= bits[mixed_np("fast", receiver, 500 + phase, h) % m]
            charge("static", 1, began)
            return receiver[ok]

        d = cells("cell_stream", left, right, 1 + int(1.5 * (len(left) + len(right) - 2 * len(np.intersect1d(left, right)))))
        for method, kept in (("sliced_hybrid", slices), ("static", filtered)):
            right_kept = kept(left, right, 1)
            left_kept = kept(right_kept, left, 2)
            cells(method, left_kept, right_kept, 64)
        if d <= sketch_limit:
            began = clock()
            sums = [sketch(x, max(1, d)) for x in (left, right)]
            charge("syndrome_sketch", 0, began)
            began = clock()
            decode([x ^ y for x, y in zip(*sums)])
            charge("syndrome_sketch", 1, began)
        return pd.DataFrame([(pdf.run_id.iloc[0], k, a, b, a + b) for k, (a, b) in spent.items()], columns=["run_id", "method", "encode_ms", "decode_ms", "compute_ms"])

    return spread(elements.select("run_id", "side", "digest"), "run_id").groupBy("run_id").applyInPandas(run, "run_id string, method string, encode_ms double, decode_ms double, compute_ms double")


def converged(elements: DataFrame, trace) -> DataFrame:
    """``run_id, converged, false_rejects``: the found difference against the true one."""
    truth = exact_difference(elements).select("run_id", "digest", F.col("side").alias("truth"))
    got = difference_found(trace).select("run_id", "digest", F.col("side").alias("got"), "found_by")
    both = truth.join(got, ["run_id", "digest"], "full_outer")
    per = both.groupBy("run_id").agg(F.min((F.coalesce("truth", F.lit(0)) == F.coalesce("got", F.lit(0))).cast("int")).alias("ok"), F.sum(F.when((F.col("found_by") == "filter") & F.col("truth").isNull(), 1).otherwise(0)).alias("false_rejects"))
    all_runs = elements.select("run_id").distinct()
    return all_runs.join(per, "run_id", "left").select("run_id", F.coalesce(F.col("ok") == 1, F.lit(True)).alias("converged"), F.coalesce("false_rejects", F.lit(0)).alias("false_rejects"))


def experiment(spark: SparkSession, folder: str, similarities: list[float], trials: int = 1, n: int | None = None) -> DataFrame:
    """Measures of all methods over a lineitem sweep."""
    from setsync.sources.workloads import lineitem_sweep

    elements, runs = lineitem_sweep(spark, folder, similarities, trials, n=n)
    elements = settled(elements, "sweep")
    return measures(ledger.summarise(all_ledgers(elements)), elements, runs)


