"""The sliced hybrid: two streams of one-hash slices, then cells for what they let through."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsync.operators import cells as cell_ops
from setsync.operators import peel
from setsync.operators.slices import SCOPE, build_slices, rejects_by_slice, sized, stop_slice, test_in_shards, test_slices
from setsync.operators.transfer import payload_lines, set_sizes
from setsync.plans import ledger
from setsync.plans.costs import leak_cost_bits, prefix_length
from setsync.sources.elements import LEFT, RIGHT, digests, shard_of, tagged
from setsync.sources.messages import settled


@dataclass
class Phase:
    """One direction's outcome. ``status``: every receiver element with ``first_miss`` and ``suspect``."""

    status: DataFrame
    histogram: DataFrame
    stops: DataFrame
    sizes: DataFrame


def stop_scope(stop: str) -> list[str]:
    return SCOPE if stop == "shard" else ["run_id"]


def run_phase(source: DataFrame, receiver: DataFrame, phase: int, cost_bits: float | None = None, dialect: str = "fast", stop: str = "global", in_shards: bool = True, prefix: int | None = None) -> Phase:
    """Streams slices of ``source`` past ``receiver`` until a slice gains less than it costs.

    The prefix that surely holds the stop follows from the two sizes (one small row is read for it);
    runs that need more are continued over their survivors only. Every step's narrow outcome (sizes,
    first misses, stops) is stored, so no later plan holds an earlier one. Both inputs are read several
    times: pass stored frames. ``in_shards`` tests a scope in one task's memory, else slices are joined.
    """
    cost = cost_bits or leak_cost_bits()
    per = stop_scope(stop)
    sizes = settled(sized(source), "sizes", 1)
    if prefix is None:
        met = sizes.groupBy("run_id").agg(F.sum("n").alias("n")).join(receiver.groupBy("run_id").agg(F.count("*").alias("r")), "run_id")
        need = met.select("n", "r").agg(F.min(F.struct((F.col("n") / F.col("r")).alias("x"), "n", "r")).alias("w")).first().w
        prefix = prefix_length(need.n, need.r, cost) if need else 1

    def probe(waiting: DataFrame, first: int, last: int) -> DataFrame:
        if in_shards:
            return test_in_shards(source, waiting, first, last, phase, dialect)
        return test_slices(waiting, build_slices(source, first, last, phase, sizes, dialect), sizes, first, last, phase, dialect)

    tested, last = settled(probe(receiver, 0, prefix - 1), "tested"), prefix - 1
    while True:
        histogram = rejects_by_slice(tested, sizes, last, per)
        stops = settled(stop_slice(histogram, cost, per), "stops", 1)
        open_runs = stops.where("stop is null and m > 0")
        if not open_runs.limit(1).count():
            break
        more = tested.where("first_miss is null").drop("first_miss").join(open_runs.select(*per), per, "left_semi")
        done = tested.join(open_runs.select(*per, F.lit(True).alias("_open")), per, "left").where("first_miss is not null or _open is null").drop("_open")
        tested, last = settled(done.unionByName(probe(more, last + 1, last + 8)), "tested"), last + 8
    status = tested.join(stops.select(*per, "stop"), per, "left")
    # Without slices (empty source) everything is rejected at once.
    rejected = F.col("first_miss").isNotNull() & ((F.col("first_miss") < 0) | (F.col("first_miss") <= F.col("stop")))
    status = status.withColumn("suspect", ~F.coalesce(rejected, F.lit(False))).drop("stop")
    return Phase(status, histogram, stops, sizes)


@dataclass
class Trace:
    """Both phases and the decoded leaks (``run_id, shard, digest, side, decoded, cells_used``)."""

    first: Phase
    second: Phase
    leaks: DataFrame
    suspects: DataFrame


def filter_phases(elements: DataFrame, cost_bits: float | None = None, dialect: str = "fast", stop: str = "global", in_shards: bool = True, prefixes: tuple[int | None, int | None] = (None, None)) -> tuple[Phase, Phase]:
    """Phase 1: the left side's slices against the right side; phase 2: slices of the right's suspects against the left."""
    left, right = elements.where(F.col("side") == LEFT), elements.where(F.col("side") == RIGHT)
    first = run_phase(left, right, 1, cost_bits, dialect, stop, in_shards, prefixes[0])
    suspects = first.status.where("suspect").drop("first_miss", "suspect")
    second = run_phase(suspects, left, 2, cost_bits, dialect, stop, in_shards, prefixes[1])
    # A scope whose right side has no suspects sends nothing back: the left side rejects everything.
    return first, second


def suspects_of(first: Phase, second: Phase) -> DataFrame:
    keep = ["run_id", "side", "shard", "digest"]
    return first.status.where("suspect").select(*keep).unionByName(second.status.where("suspect").select(*keep))


#: Cells of one scope at most; beyond that split into more shards, or peel with ``peel_relational``.
MOST_CELLS = 1 << 26


def reconcile_cells(elements: DataFrame, start: int, growth: float = 2.0, exact_prefix: bool = True, limit: int = MOST_CELLS) -> DataFrame:
    """The difference of both sides through the cell stream: prefixes grow, for undecoded scopes alone, until all decode."""
    size, left, found = max(8, start), elements, None
    while True:
        got = settled(peel.peel_local(cell_ops.difference_cells(left, size), size, exact_prefix), "peeled")
        fine = got.where("decoded")
        found = fine if found is None else found.unionByName(fine)
        failed = got.where("not decoded").select(*SCOPE).distinct()
        if not failed.limit(1).count():
            return found
        if size > limit:
            raise RuntimeError(f"no prefix of {size} cells decodes: split into more shards, or peel with peel_relational")
        left, size = left.join(failed, SCOPE, "left_semi"), int(size * growth)


def synchronise(elements: DataFrame, cost_bits: float | None = None, stop: str = "global", in_shards: bool = True) -> Trace:
    """All three phases over ``run_id, side, shard, digest, payload_bytes`` (fast dialect), which are read several times: pass a stored frame."""
    first, second = filter_phases(elements, cost_bits, "fast", stop, in_shards)
    suspects = suspects_of(first, second)
    # What is left after the stop is about what the last slice found; one number sizes the first prefix.
    gains = [p.stops.agg(F.max(F.coalesce("new_at_stop", F.lit(0)))).first()[0] or 0 for p in (first, second)]
    leaks = reconcile_cells(suspects, int(1.7 * sum(gains)) + 32)
    return Trace(first, second, leaks, suspects)


def difference_found(trace: Trace) -> DataFrame:
    """Rejects of both sides and decoded leaks: ``run_id, digest, side, found_by``."""
    pick = lambda p: p.status.where("not suspect").select("run_id", "digest", F.col("side").cast("int").alias("side"), F.lit("filter").alias("found_by"))
    leaks = trace.leaks.where("digest is not null").select("run_id", "digest", "side", F.lit("cells").alias("found_by"))
    return pick(trace.first).unionByName(pick(trace.second)).unionByName(leaks)


def hybrid_ledger(elements: DataFrame, trace: Trace, latency_slices: int = 0, mode: str = "continuous", cell_bytes: int = 24) -> DataFrame:
    """Bytes of every message class of the hybrid. ``turn_based`` asks for each slice; ``continuous`` may overshoot."""
    size = set_sizes(elements)
    slices = lambda p, k: p.stops.groupBy("run_id").agg(
        F.sum(F.coalesce(F.col("stop") + 1, F.lit(0)) * F.ceil(F.col("m") / 8)).alias(f"bytes_{k}"), F.max(F.coalesce(F.col("stop") + 1, F.lit(0))).alias(f"slices_{k}"), F.sum(F.ceil(F.col("m") / 8)).alias(f"one_{k}")
    )
    used = trace.leaks.groupBy("run_id", "shard").agg(F.max("cells_used").alias("c"), F.sum(F.when(F.col("side") == LEFT, 1).otherwise(0)).alias("w")).groupBy("run_id").agg(F.sum("c").alias("cells"), F.sum("w").alias("wanted"))
    per = size.join(slices(trace.first, 1), "run_id", "left").join(slices(trace.second, 2), "run_id", "left").join(used, "run_id", "left").na.fill(0)
    entries = [
        (1, ledger.A, "size_header", F.lit(1), F.lit(8), True), (2, ledger.B, "size_header", F.lit(1), F.lit(8), True),
        (1, ledger.A, "slice", F.col("slices_1"), F.col("bytes_1"), True), (2, ledger.B, "slice", F.col("slices_2"), F.col("bytes_2"), True),
        (1, ledger.B, "stop", F.lit(1), F.lit(1), True), (2, ledger.A, "stop", F.lit(1), F.lit(1), True), (3, ledger.B, "stop", F.lit(1), F.lit(1), True),
        (3, ledger.A, "cell", F.col("cells"), F.col("cells") * cell_bytes, True), (3, ledger.B, "wanted_digests", F.col("wanted"), 8 * F.col("wanted"), True),
        *payload_lines(size),
    ]
    if mode == "turn_based":
        entries += [(1, ledger.B, "slice_request", F.col("slices_1"), F.col("slices_1"), True), (2, ledger.A, "slice_request", F.col("slices_2"), F.col("slices_2"), True)]
    elif latency_slices:
        entries += [(1, ledger.A, "slice_overshoot", F.lit(latency_slices), latency_slices * F.col("one_1"), True), (2, ledger.B, "slice_overshoot", F.lit(latency_slices), latency_slices * F.col("one_2"), True)]
    return ledger.lines(per, "sliced_hybrid", entries)


def effective_rate(phase: Phase) -> DataFrame:
    """About 2^-slices of the others pass a stream that has stopped."""
    return phase.stops.select("run_id", "stop", F.pow(F.lit(0.5), F.col("stop") + 1).alias("effective_rate"))


@dataclass
class SyncResult:
    only_left: DataFrame
    only_right: DataFrame
    left_out: DataFrame
    right_out: DataFrame
    ledger: DataFrame
    trace: Trace


#: Elements of a shard: their digests, one slice and the cells of their suspects fit a task's memory.
SHARD_ELEMENTS = 1 << 21


def sliced_hybrid(left: DataFrame, right: DataFrame, key: list[str] | None = None, shards: int | None = None, stop: str = "global", cost: str = "cells", in_shards: bool = True) -> SyncResult:
    """Brings two frames of one schema to their union. Payloads are touched by the last step alone.

    ``shards`` splits digests so that no task holds more than a share (by default ``SHARD_ELEMENTS``);
    ``stop`` decides for all shards together or for each. Rows that repeat are one element.
    """
    both = settled(tagged(digests(left, key), digests(right, key)), "elements")
    shards = shards or -(-both.count() // SHARD_ELEMENTS) or 1
    elements = both.withColumn("shard", shard_of(shards))
    trace = synchronise(elements, leak_cost_bits(cost), stop, in_shards)
    found = settled(difference_found(trace), "difference")
    only = lambda df, side: with_digest(df, key).join(found.where(F.col("side") == side).select(F.col("digest").alias("_digest")), F.col("_digest_of_row") == F.col("_digest"), "left_semi").drop("_digest_of_row").dropDuplicates()
    only_left, only_right = only(left, LEFT), only(right, RIGHT)
    return SyncResult(only_left, only_right, left.unionByName(only_right), right.unionByName(only_left), hybrid_ledger(elements, trace), trace)


def with_digest(df: DataFrame, key: list[str] | None) -> DataFrame:
    from setsync.functions.hashing import Fast, canonical

    return df.withColumn("_digest_of_row", Fast.digest(canonical(df, key)))
