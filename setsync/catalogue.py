"""All queries of the engine by name, each (spark, folder) -> DataFrame, and their SQL twins.

Queries that other engines check use the portable dialect; those that decode use portable digests as
elements and the fast dialect inside, so their results are comparable too.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsync import oracles
from setsync.operators import cells, estimators, filters, parity, peel, semijoin, slices, syndrome, transfer, xortable
from setsync.plans import advisor, hybrid, ledger, static_hybrid, sweep
from setsync.plans.costs import leak_cost_bits
from setsync.sources import workloads
from setsync.sources.elements import LEFT, RIGHT, digests, table, tagged
from setsync.sources.messages import settled
from setsync.streaming import cell_stream, slice_stream

POINTS = [0.0, 20.0, 50.0, 85.0, 95.0, 100.0]
FEW = [50.0, 95.0]
CLOSE = [95.0, 99.0]
PREFIX_1, PREFIX_2 = 13, 24
RATES = [0.01, 0.25]
TRIALS, TRIAL_POINTS = 30, [50.0, 90.0]
CHARGED = ["sliced_hybrid", "cell_stream", "syndrome_sketch", "digest_exchange", "full_transfer"]
COSTS = [("cells, all fields", leak_cost_bits()), ("cells, no count", leak_cost_bits(count_bits=0)), ("sketch", leak_cost_bits("sketch"))]
CELLS = 32
MOMENT_CELLS = 64
SKETCH_POINTS, SKETCH_SIZE = [85.0, 90.0, 95.0, 99.0], 2000
ROUTINE = [99.5, 99.9, 100.0]
CUTS = ["2024-01-10", "2024-01-20", "2024-01-29"]
NATURAL = {"orders": None, "part": None, "documents": None, "pages": None, "conversations": None, "embeddings": None}


def swept(points: list[float]):
    def pair(spark: SparkSession, folder: str, n: int | None = None) -> DataFrame:
        return workloads.lineitem_sweep(spark, folder, points, dialect="portable", n=n)[0]

    return pair


def stored(points: list[float], n: int | None = None):
    """The same, written to the shared folder: for queries that read it several times."""
    return lambda spark, folder: settled(swept(points)(spark, folder, n), "sweep")


def replica_pair_sizes(spark, folder):
    return transfer.set_sizes(swept(POINTS)(spark, folder))


def jaccard_sweep(spark, folder):
    pair, runs = workloads.lineitem_sweep(spark, folder, workloads.FULL_RANGE, dialect="portable")
    return transfer.set_sizes(pair).join(F.broadcast(runs.select("run_id", "similarity_pct")), "run_id").select("similarity_pct", "d", "jaccard")


def exact_difference(spark, folder):
    return transfer.exact_difference(swept(FEW)(spark, folder))


def slice_bits(spark, folder):
    left = swept(FEW)(spark, folder).where(F.col("side") == LEFT)
    return slices.build_slices(left, 0, 1, 1, dialect="portable").drop("shard")


def slice_fill(spark, folder):
    left = swept(FEW)(spark, folder).where(F.col("side") == LEFT)
    words = slices.build_slices(left, 0, 3, 1, dialect="portable")
    per = words.groupBy("run_id", "slice", "m").agg(F.sum(F.bit_count("bits")).cast("long").alias("set_bits"))
    return per.withColumn("fill", F.round(F.col("set_bits") / F.col("m"), 6))


def first_phase(spark, folder, points=POINTS):
    pair = stored(points)(spark, folder)
    left, right = pair.where(F.col("side") == LEFT), pair.where(F.col("side") == RIGHT)
    return left, hybrid.run_phase(left, right, 1, dialect="portable", prefix=PREFIX_1, in_shards=False)


def second_phase(spark, folder, points=POINTS):
    left, first = first_phase(spark, folder, points)
    suspects = first.status.where("suspect").drop("first_miss", "suspect")
    return first, hybrid.run_phase(suspects, left, 2, dialect="portable", prefix=PREFIX_2)


def phase1_histogram(spark, folder):
    return first_phase(spark, folder)[1].histogram


def leak_cost_stops(spark, folder):
    histogram = settled(first_phase(spark, folder)[1].histogram, "histogram", 1)
    each = [slices.stop_slice(histogram, cost).withColumn("cost", F.lit(name)) for name, cost in COSTS]
    return each[0].unionByName(each[1]).unionByName(each[2])


def phase1_stop(spark, folder):
    return first_phase(spark, folder)[1].stops


def phase2_histogram(spark, folder):
    return second_phase(spark, folder)[1].histogram


def phase2_stop(spark, folder):
    return second_phase(spark, folder)[1].stops


def hybrid_metadata(spark, folder):
    return sweep.charged_hybrid(*second_phase(spark, folder))


def differences(found: DataFrame) -> DataFrame:
    return found.select("run_id", F.col("digest").cast("long").alias("digest"), F.col("side").cast("int").alias("side"))


def hybrid_result(spark, folder):
    return differences(hybrid.difference_found(hybrid.synchronise(stored(POINTS)(spark, folder))))


def converged_union(spark, folder):
    pair = stored(POINTS)(spark, folder)
    found = hybrid.difference_found(hybrid.synchronise(pair)).select("run_id", "digest", "side")
    both = pair.select("run_id", "digest", F.col("side").cast("int").alias("side")).unionByName(found.withColumn("side", -F.col("side")))
    per = both.distinct().groupBy("run_id", "side").agg(F.count("*").alias("n"), F.sum(F.pmod("digest", F.lit(1_000_003))).alias("digest_sum"))
    return per


def hybrid_sharded(spark, folder):
    pair = stored(FEW)(spark, folder).withColumn("shard", F.pmod("digest", F.lit(8)).cast("int"))
    return differences(hybrid.difference_found(hybrid.synchronise(pair, stop="shard", in_shards=True)))


def hybrid_natural(spark, folder):
    parts = []
    for name in NATURAL:
        base = digests(table(spark, folder, name), None, "fast")
        parts.append(workloads.threshold_pair(base, 80.0, run_id=name))
    pair = parts[0]
    for p in parts[1:]:
        pair = pair.unionByName(p)
    pair = settled(pair, "natural")
    return sweep.converged(pair, hybrid.synchronise(pair))


def hybrid_bytes(spark, folder):
    pair = stored(POINTS)(spark, folder)
    return ledger.summarise(hybrid.hybrid_ledger(pair, hybrid.synchronise(pair)))


def hybrid_turn_based(spark, folder):
    """Both ways of sending slices: a byte asks for each, or they flow on and one more is under way when the stop arrives."""
    phases = hybrid.filter_phases(stored(FEW)(spark, folder), dialect="portable")
    parts = []
    for number, phase in enumerate(phases, 1):
        k, one = F.col("stop") + 1, F.ceil(F.col("m") / 8)
        asked = F.struct(F.lit("turn_based").alias("mode"), (2 * k).cast("long").alias("messages"), (k * one + k).cast("long").alias("bytes"))
        flowing = F.struct(F.lit("continuous").alias("mode"), (k + 2).cast("long").alias("messages"), ((k + 1) * one + 1).cast("long").alias("bytes"))
        parts.append(phase.stops.select("run_id", F.lit(number).alias("phase"), F.explode(F.array(asked, flowing)).alias("x")).select("run_id", "phase", "x.*"))
    return parts[0].unionByName(parts[1])


def effective_rates(spark, folder):
    return hybrid.effective_rate(first_phase(spark, folder)[1])


def static_filter_fpr(spark, folder):
    pair = swept([0.0, 50.0])(spark, folder)
    left, right = pair.where(F.col("side") == LEFT), pair.where(F.col("side") == RIGHT)
    sizes = filters.sizes_for(left, RATES)
    probed = filters.probe_filter(right, filters.build_filter(left, sizes, 1, "portable"), sizes, 1, "portable")
    outside = probed.join(left.select("run_id", "digest"), ["run_id", "digest"], "left_anti")
    return outside.groupBy("run_id", "eps").agg(F.count("*").alias("non_members"), F.sum(F.col("passes").cast("long")).alias("passed"))


def static_hybrid_bytes(spark, folder):
    return static_hybrid.static_counts(swept(FEW)(spark, folder), RATES, "portable").select("run_id", "eps", "bits_1", "bits_2", "leaks", "wanted")


def best_static_eps(spark, folder):
    return static_hybrid.best_static(swept(FEW)(spark, folder), static_hybrid.GRID, "portable")


def best_static_sweep(spark, folder):
    return static_hybrid.best_static(swept(workloads.FULL_RANGE)(spark, folder))


def static_hybrid_result(spark, folder):
    return differences(static_hybrid.static_hybrid(stored(FEW)(spark, folder), 0.05))


def partitioned_equals_slices(spark, folder):
    pair = swept(FEW)(spark, folder)
    left, right = pair.where(F.col("side") == LEFT), pair.where(F.col("side") == RIGHT)
    probed = filters.probe_partitioned(right, left, 3, "portable")
    return probed.groupBy("run_id").agg(F.count("*").alias("tested"), F.sum(F.col("passes").cast("long")).alias("passed"))


def xortable_cells(spark, folder):
    return xortable.build_table(swept(CLOSE)(spark, folder), 300, 3, "portable").drop("shard")


def xortable_result(spark, folder):
    # Twice as many cells as the 5,128 and 1,006 differences at most; the table is sized by the known d.
    return differences(xortable.table_reconcile(swept(CLOSE)(spark, folder), 9000, 3).where("decoded and digest is not null"))


def cell_prefix(spark, folder):
    return cells.difference_cells(swept(CLOSE)(spark, folder), CELLS, "portable").drop("shard")


def cell_stream_result(spark, folder):
    pair = stored(CLOSE)(spark, folder)
    return differences(hybrid.reconcile_cells(pair, 2000, exact_prefix=False).where("digest is not null"))


def relational_peel_result(spark, folder):
    pair = stored([99.0])(spark, folder)
    size = 4096
    return differences(peel.peel_relational(cells.difference_cells(pair, size), size).where("decoded"))


def cells_per_diff(spark, folder):
    pair = stored([90.0, 95.0, 98.0, 99.0, 99.9])(spark, folder)
    got = hybrid.reconcile_cells(pair, 4000)
    per = got.groupBy("run_id").agg(F.max("cells_used").alias("cells"), F.count("digest").alias("d"))
    return per.withColumn("cells_per_diff", F.col("cells") / F.col("d"))


def maintained_cells(spark, folder):
    left = swept([95.0])(spark, folder).where(F.col("side") == LEFT).drop("payload_bytes")
    leaves = F.pmod("digest", F.lit(10)) == 0
    old = cells.build_cells(left.where(F.pmod("digest", F.lit(7)) != 0), 0, CELLS, "portable")
    changes = left.where(leaves).where(F.pmod("digest", F.lit(7)) != 0).withColumn("change", F.lit(-1))
    changes = changes.unionByName(left.where(~leaves).where(F.pmod("digest", F.lit(7)) == 0).withColumn("change", F.lit(1)))
    return cells.maintain_cells(old, changes, CELLS, "portable").drop("shard")


def syndrome_bytes(spark, folder):
    sizes = transfer.set_sizes(swept(POINTS)(spark, folder))
    return ledger.summarise(syndrome.sketch_ledger(sizes))


def syndrome_result(spark, folder):
    """Whole sets at 98 %: shards of about 8 differences, those above the capacity once more with twice as much."""
    pair = stored([98.0])(spark, folder)
    d = transfer.set_sizes(pair).agg(F.max("d")).first()[0] or 1
    pair = pair.withColumn("shard", F.pmod("digest", F.lit(-(-d // 8))).cast("int"))
    return differences(syndrome.syndrome_complete(pair, 14).where("digest is not null"))


def parity_round1_bins(spark, folder):
    return parity.parity_bins(swept(CLOSE)(spark, folder), 200, 127, 1, "portable").where("parity = 1").select("run_id", "grp", "bin", "id_xor")


def estimated(spark, folder, points):
    pair = stored(points)(spark, folder)
    return pair, estimators.sign_sum_estimate(pair).select("run_id", F.col("d_safe").alias("d_hat"))


def parity_result(spark, folder):
    pair, d_hat = estimated(spark, folder, POINTS)
    return differences(parity.parity_groups(pair, d_hat)[0])


def parity_bytes(spark, folder):
    pair, d_hat = estimated(spark, folder, [50.0, 85.0, 95.0])
    return ledger.summarise(parity.parity_ledger(transfer.set_sizes(pair), parity.parity_groups(pair, d_hat)[1]))


def sign_sum_estimate(spark, folder):
    return estimators.sign_sum_estimate(swept(POINTS)(spark, folder), dialect="portable")


def cell_moment_estimate(spark, folder):
    diff = cells.difference_cells(swept(FEW)(spark, folder), MOMENT_CELLS, "portable")
    return estimators.cell_moment_estimate(diff, MOMENT_CELLS).select("run_id", F.round("d_hat", 3).alias("d_hat"))


def sketch_estimates(spark, folder):
    pair = stored(POINTS)(spark, folder)
    both = estimators.hll_difference_estimate(pair).withColumn("estimator", F.lit("hll"))
    return both.unionByName(estimators.theta_difference_estimate(pair).withColumn("estimator", F.lit("theta")))


def subset_difference(spark, folder):
    events = table(spark, folder, "events")
    pair = None
    for c in CUTS:
        one = workloads.lagging_pair(events, c, "portable")
        pair = one if pair is None else pair.unionByName(one)
    return estimators.subset_difference_size(pair)


def full_transfer_bytes(spark, folder):
    return ledger.summarise(transfer.full_transfer_ledger(transfer.set_sizes(swept(POINTS)(spark, folder))))


def digest_exchange_bytes(spark, folder):
    return ledger.summarise(transfer.digest_exchange_ledger(transfer.set_sizes(swept(POINTS)(spark, folder))))


def plain_measures(spark, folder):
    pair, runs = workloads.lineitem_sweep(spark, folder, workloads.FULL_RANGE, dialect="portable")
    sizes = settled(transfer.set_sizes(pair), "sizes", 1)
    rows = transfer.full_transfer_ledger(sizes).unionByName(transfer.digest_exchange_ledger(sizes)).unionByName(syndrome.sketch_ledger(sizes))
    return sweep.measures(ledger.summarise(rows), pair, runs)


def overhead_by_similarity(spark, folder):
    return plain_measures(spark, folder).select("method", "similarity_pct", "d", "total_bytes", "minimum_bytes", F.round("overhead_ratio", 6).alias("overhead_ratio"))


def crossover(spark, folder):
    rows = settled(plain_measures(spark, folder), "measures", 1)
    return sweep.crossover(rows, "full_transfer", "syndrome_sketch").unionByName(sweep.crossover(rows, "full_transfer", "digest_exchange"))


def bytes_by_kind(spark, folder):
    sizes = settled(transfer.set_sizes(swept(POINTS)(spark, folder)), "sizes", 1)
    return ledger.by_kind(transfer.full_transfer_ledger(sizes).unionByName(syndrome.sketch_ledger(sizes)))


def charged(spark, folder, points, methods, rates=[], trials=1):
    pair, runs = workloads.lineitem_sweep(spark, folder, points, trials, dialect="portable")
    return sweep.charged_rows(settled(pair, "sweep"), runs, methods, rates)


def experiment_static(spark, folder):
    return charged(spark, folder, workloads.FULL_RANGE, ["sliced_hybrid"], sweep.STATIC_RATES)


def experiment_charged(spark, folder):
    return charged(spark, folder, workloads.FULL_RANGE, CHARGED)


def experiment_charged_high(spark, folder):
    return charged(spark, folder, workloads.HIGH_RANGE, CHARGED)


def savings(spark, folder):
    rows = settled(experiment_charged(spark, folder), "measures", 1)
    parts = [sweep.savings(rows, measure=m).select("other", "similarity_pct", F.lit(m).alias("measure"), F.round("saving_pct", 6).alias("saving_pct")) for m in ("metadata_bytes", "total_bytes")]
    return parts[0].unionByName(parts[1])


def crossover_hybrid(spark, folder):
    rows = settled(charged(spark, folder, sorted({*workloads.FULL_RANGE, *workloads.HIGH_RANGE}), CHARGED), "measures", 1)
    parts = [sweep.crossover(rows, "sliced_hybrid", other) for other in CHARGED[1:]]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


def trials_summary(spark, folder):
    rows = charged(spark, folder, TRIAL_POINTS, ["sliced_hybrid", "full_transfer"], trials=TRIALS)
    return sweep.over_trials(rows, ["metadata_bytes", "total_bytes", "overhead_ratio"], 4)


def trials_full(spark, folder):
    """All similarities and trials, every step of the hybrid really run."""
    pair, runs = workloads.lineitem_sweep(spark, folder, workloads.FULL_RANGE, trials=TRIALS)
    pair = settled(pair, "sweep")
    return sweep.over_trials(sweep.measures(ledger.summarise(hybrid.hybrid_ledger(pair, hybrid.synchronise(pair))), pair, runs))


def experiment_all(spark, folder):
    return sweep.experiment(spark, folder, workloads.FULL_RANGE)


def experiment_high(spark, folder):
    return sweep.experiment(spark, folder, workloads.HIGH_RANGE)


def operation_counts(spark, folder):
    return sweep.operation_counts(stored(POINTS)(spark, folder))


def method_times(spark, folder):
    """Wall times, which differ from run to run: ``run_id, method, encode_ms, decode_ms, compute_ms``."""
    return sweep.method_times(swept(POINTS)(spark, folder))


def sketch_decode_result(spark, folder):
    """The sketch workload: sets of 2,000, small enough for a sketch to decode, 128 shards of capacity 30."""
    pair = swept(SKETCH_POINTS)(spark, folder, n=SKETCH_SIZE).withColumn("shard", F.pmod("digest", F.lit(128)).cast("int"))
    return differences(syndrome.syndrome_complete(pair, 14).where("digest is not null"))


def routine_sync(spark, folder):
    """Frequent small updates, and none: identical sets included."""
    base = digests(table(spark, folder, "events"), ["event_id"], "portable")
    n = base.count() * 9 // 10
    pair = settled(workloads.replica_pairs(base, workloads.runs_table(spark, n, ROUTINE), "portable"), "routine")
    return differences(hybrid.difference_found(hybrid.synchronise(pair)))


def uneven_sets(spark, folder):
    """Copies on one side, one side a tenth of the other, nothing in common: elements found on each side."""
    texts, items = table(spark, folder, "documents").select("doc_id", "text"), table(spark, folder, "benchmark").select("text")
    orders = table(spark, folder, "orders").select("o_orderkey")
    pairs = {
        "copies": (texts.select("text"), texts.where("doc_id % 3 <> 0").select("text")),
        "unequal": (orders.where("o_orderkey % 10 = 0"), orders), "disjoint": (texts.select("text"), items),
    }
    out = None
    for name, (left, right) in pairs.items():
        one = tagged(digests(left, None), digests(right, None), name)
        out = one if out is None else out.unionByName(one)
    return hybrid.difference_found(hybrid.synchronise(settled(out, "uneven"))).groupBy("run_id", "side").agg(F.count("*").alias("n"))


def joins(spark, folder):
    urgent = table(spark, folder, "orders").where("o_orderpriority = '1-URGENT'").select(F.col("o_orderkey").alias("k"))
    lines = table(spark, folder, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber", "l_partkey", "l_suppkey")
    return lines, urgent


def key_semijoin(spark, folder):
    lines, urgent = joins(spark, folder)
    return semijoin.ship_all(lines, urgent, "k").traffic.unionByName(semijoin.key_semijoin(lines, urgent, "k").traffic)


def semijoin_traffic(spark, folder):
    """The other two joins: orders of one customer segment, lines of one brand of parts."""
    customers = table(spark, folder, "customer").where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("k"))
    orders = table(spark, folder, "orders").select(F.col("o_custkey").alias("k"), "o_orderkey")
    parts = table(spark, folder, "part").where("p_size <= 10").select(F.col("p_partkey").alias("k"))
    lines = table(spark, folder, "lineitem").select(F.col("l_partkey").alias("k"), "l_orderkey", "l_linenumber", "l_suppkey")
    out = None
    for name, left, right in (("orders of customers", orders, customers), ("lines of parts", lines, parts)):
        for shipped in (semijoin.ship_all(left, right, "k"), semijoin.key_semijoin(left, right, "k")):
            row = shipped.traffic.withColumn("joined", F.lit(name))
            out = row if out is None else out.unionByName(row)
    return out


def filter_semijoin(spark, folder):
    lines, urgent = joins(spark, folder)
    return semijoin.filter_semijoin(lines, urgent, "k", 0.01, "portable").traffic.unionByName(semijoin.filter_semijoin(lines, urgent, "k", 0.25, "portable").traffic)


def sliced_semijoin_trace(spark, folder):
    lines, urgent = joins(spark, folder)
    _, histogram, stops = semijoin.sliced_trace(lines, urgent, "k", "portable")
    return histogram.join(F.broadcast(stops.select("stop"))).where("slice <= stop").drop("run_id")


def sliced_semijoin_join(spark, folder):
    lines, urgent = joins(spark, folder)
    return semijoin.joined(semijoin.sliced_semijoin(lines, urgent, "k"), urgent, "k")


def lagging_replica_events(spark, folder):
    events = table(spark, folder, "events")
    pair = None
    for c in CUTS:
        one = workloads.lagging_pair(events, c, "portable")
        pair = one if pair is None else pair.unionByName(one)
    return transfer.set_sizes(pair).select("run_id", "n_a", "n_b", "d", F.round("jaccard", 9).alias("jaccard"))


def outage_events(spark, folder):
    pair = workloads.outage_pair(table(spark, folder, "events"), ("2024-01-05", "2024-01-08"), ("2024-01-20", "2024-01-22"))
    pair = settled(pair, "outage")
    found = hybrid.difference_found(hybrid.synchronise(pair))
    return found.groupBy("side").agg(F.count("*").alias("n"))


def worked_ranges_six(spark, folder):
    """The same with six cells for four differences, as in the worked example: the first draw of positions that decodes."""
    pair = settled(workloads.integer_ranges(spark, (1, 100_001), (3, 100_003)), "ranges")
    for salt in range(900, 932):
        got = settled(xortable.table_reconcile(pair, 6, 3, salt).where("decoded and digest is not null"), "six", 1)
        if got.limit(1).count():
            return differences(got)
    raise RuntimeError("no draw of positions decodes")


def worked_ranges(spark, folder):
    pair = workloads.key_ranges(table(spark, folder, "orders"), "o_orderkey")
    return differences(xortable.table_reconcile(pair, 60, 3).where("decoded and digest is not null"))


def windowed_cells(spark, folder):
    events = table(spark, folder, "events").select("ts", "event_id")
    both = events.withColumn("side", F.lit(LEFT)).where("event_id % 50 <> 0").unionByName(events.withColumn("side", F.lit(RIGHT)))
    # Cell 0 counts what a window lacks; a window's 64 cells are all empty where it lacks nothing.
    per = cell_stream.windowed_cells(both.withColumn("ts", F.col("ts").cast("timestamp")), 64)
    differs = (F.col("id_xor") != 0) | (F.col("check_xor") != 0) | (F.col("cnt") != 0)
    return per.groupBy("run_id").agg(F.max(F.when(F.col("cell") == 0, F.col("cnt"))).alias("missing"), F.max(differs).alias("differs"))


def session_sizes(spark, folder):
    events = table(spark, folder, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_id", F.lit(RIGHT).alias("side"))
    per = cell_stream.session_sizes(events, "1 hour")
    return per.agg(F.count("*").alias("sessions"), F.sum("n").alias("events"), F.max("n").alias("largest"))


def latest_user_events(spark, folder):
    return cell_stream.latest_state(table(spark, folder, "events"), "user_id", "2024-01-15").select("user_id", "event_id")


def stream_slices(spark, folder):
    from setsync.sources.messages import ensure_checkpoints, shared_table

    ensure_checkpoints(spark)
    pair = stored([50.0])(spark, folder)
    path = shared_table(spark, "sent-slices")
    slice_stream.write_slices(pair.where(F.col("side") == LEFT), path, 0, 9, dialect="portable")
    state = slice_stream.stream_slices(spark, path, pair.where(F.col("side") == RIGHT), leak_cost_bits(), dialect="portable")
    return spark.createDataFrame([(*r, state.stop, state.overshoot) for r in state.trace], "slice int, new_rejects long, m long, stop int, overshoot int")


def probe_then_sync(spark, folder):
    return differences(advisor.probe_then_sync(stored(POINTS)(spark, folder))[0])


def advise(spark, folder):
    """The method for each replica pair of lineitem, with its true difference and (d = -1) without an estimate."""
    sizes = replica_pair_sizes(spark, folder).select("run_id", "n_a", "d").collect()  # one row a point
    rows = [(r.run_id, r.n_a, d, *advisor.advise(r.n_a, None if d < 0 else d)) for r in sizes for d in (r.d, -1)]
    return spark.createDataFrame([(*r[:4], float(r[4])) for r in rows], "run_id string, n long, d long, method string, metadata_bytes double")


def wide_digest_difference(spark, folder):
    from setsync.sources.elements import wide_digests

    orders = table(spark, folder, "orders").select("o_orderkey", "o_custkey")
    old, new = wide_digests(orders.where("o_orderkey % 10 <> 0")), wide_digests(orders)
    return new.join(old, "digest", "left_anti").agg(F.count("*").alias("only_right"))


def sql_functions(spark, folder):
    from setsync.functions.sqlapi import register

    register(spark)
    table(spark, folder, "orders").createOrReplaceTempView("sql_orders")
    return spark.sql("""
        with e as (select element_digest_portable(cast(o_orderkey as string)) digest from sql_orders), m as (select slice_bits(count(*)) m from e)
        select k as slice, m, count(distinct slice_pos_portable(digest, 1, k, m)) set_bits from e cross join m lateral view explode(sequence(0L, 2L)) t as k group by k, m""")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        replica_pair_sizes, jaccard_sweep, exact_difference, slice_bits, slice_fill, phase1_histogram, phase1_stop, phase2_histogram, phase2_stop, leak_cost_stops,
        hybrid_metadata, hybrid_result, converged_union, hybrid_sharded, hybrid_natural, hybrid_bytes, hybrid_turn_based, effective_rates,
        static_filter_fpr, static_hybrid_bytes, best_static_eps, best_static_sweep, static_hybrid_result, partitioned_equals_slices, xortable_cells, xortable_result,
        cell_prefix, cell_stream_result, relational_peel_result, cells_per_diff, maintained_cells, syndrome_bytes, syndrome_result,
        parity_round1_bins, parity_result, parity_bytes, sign_sum_estimate, cell_moment_estimate, sketch_estimates, subset_difference,
        full_transfer_bytes, digest_exchange_bytes, overhead_by_similarity, crossover, bytes_by_kind, experiment_static, experiment_charged, experiment_charged_high, savings, crossover_hybrid,
        trials_summary, trials_full, experiment_all, experiment_high, method_times, sketch_decode_result, routine_sync, uneven_sets, semijoin_traffic, worked_ranges_six,
        operation_counts, key_semijoin, filter_semijoin, sliced_semijoin_trace, sliced_semijoin_join, lagging_replica_events, outage_events,
        worked_ranges, windowed_cells, session_sizes, latest_user_events, stream_slices, probe_then_sync, advise, wide_digest_difference, sql_functions,
    )
}


def queries() -> dict[str, Callable]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return oracles.all_sql()
