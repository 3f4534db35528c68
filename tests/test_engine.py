"""The engine against independent SQL, brute force and its own invariants."""

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from setsync import catalogue
from setsync.functions.hashing import Fast, below_np, canonical, check_np, draw_np, mix_np
from setsync.operators import cells, filters, peel, slices, transfer, xortable
from setsync.plans import hybrid, ledger, sweep
from setsync.plans.costs import leak_cost_bits
from setsync.sources import messages, workloads
from setsync.sources.elements import LEFT, RIGHT, digests, table, tagged
from setsync.streaming import cell_stream, slice_stream

CHECKED = ["replica_pair_sizes", "slice_fill", "phase1_histogram", "phase1_stop", "phase2_stop", "hybrid_metadata", "hybrid_result", "static_hybrid_bytes", "cell_prefix", "xortable_cells", "sign_sum_estimate", "crossover", "filter_semijoin", "sliced_semijoin_trace", "leak_cost_stops", "effective_rates", "hybrid_turn_based", "operation_counts", "stream_slices", "experiment_static", "savings", "crossover_hybrid", "static_hybrid_result", "probe_then_sync", "parity_result", "syndrome_result", "routine_sync", "uneven_sets", "semijoin_traffic", "worked_ranges_six", "hybrid_natural", "windowed_cells"]


def cells_of(frame: pd.DataFrame) -> list[tuple]:
    columns = sorted(frame.columns)
    spell = lambda v: "null" if pd.isna(v) else f"{float(v):.9g}" if isinstance(v, (int, float, np.number)) and abs(v) < 2**50 else str(v)
    return sorted(tuple(spell(v) for v in row) for row in frame[columns].itertuples(index=False))


@pytest.fixture(scope="module")
def duck(smoke):
    con = duckdb.connect()
    for name in ("lineitem", "orders", "events", "customer", "part", "documents", "benchmark"):
        con.sql(f"create view {name} as select * from '{smoke}/{name}.parquet'")
    return con


@pytest.mark.parametrize("name", CHECKED)
def test_queries_equal_their_sql(spark, smoke, duck, name):
    got, want = catalogue.queries()[name](spark, smoke).toPandas(), duck.sql(catalogue.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert cells_of(got) == cells_of(want)
    spark.catalog.clearCache()


def frame(spark, left, right, shards=1):
    rows = [("r", s, int(x) % shards, int(x), 10) for s, xs in ((LEFT, left), (RIGHT, right)) for x in xs]
    return spark.createDataFrame(rows, "run_id string, side int, shard int, digest long, payload_bytes int")


def test_numpy_hashes_equal_sparks(spark):
    ids = [0, 1, -1, 2**62, -(2**63), 123456789]
    df = spark.createDataFrame([(x,) for x in ids], "digest long")
    d = F.col("digest")
    got = df.select("digest", Fast.mix(d, 3, 4).alias("m"), Fast.below(1000, d, 1, 2).alias("b"), Fast.draw(d, F.lit(5)).alias("u"), Fast.check(d).alias("c")).collect()
    a = np.array([r.digest for r in got], np.int64)
    assert [r.m for r in got] == mix_np(a, 3, 4).view(np.int64).tolist()
    assert [r.b for r in got] == below_np(1000, a, 1, 2).tolist()
    assert [r.u for r in got] == draw_np(a, 5).tolist()
    assert [r.c for r in got] == check_np(a).view(np.int64).tolist()


def test_cell_positions_agree_bit_for_bit(spark):
    ids = np.random.default_rng(1).integers(-(2**62), 2**62, 300)
    df = spark.createDataFrame([(int(x),) for x in ids], "digest long").select("digest", cells.cell_positions(F.col("digest"), 5000).alias("c"))
    who, where = cells.positions_np(ids, 5000)
    want = {int(x): sorted(where[who == k].tolist()) for k, x in enumerate(ids)}
    assert {r.digest: r.c for r in df.collect()} == want


def test_canonical_text_tells_rows_apart(spark):
    rows = spark.createDataFrame([("ab", "c"), ("a", "bc"), (None, "c"), ("", "c"), ("~", "c")], "x string, y string")
    assert rows.select(canonical(rows).alias("t")).distinct().count() == 5


@pytest.mark.parametrize("left,right", [([], [1, 2]), ([1, 2], []), ([], []), ([7], [7]), ([7], [8]), (range(500), range(500)), (range(20), range(400)), (range(400), range(20)), (range(300), range(300, 600)), (range(0, 900), range(100, 1000))])
def test_hybrid_reaches_the_exact_difference(spark, left, right):
    pair = frame(spark, left, right, shards=3).persist()
    trace = hybrid.synchronise(pair)
    got = {(r.digest, r.side) for r in hybrid.difference_found(trace).collect()}
    assert got == {(x, -1) for x in set(left) - set(right)} | {(x, 1) for x in set(right) - set(left)}
    assert all(r.converged and not r.false_rejects for r in sweep.converged(pair, trace).collect())


def test_in_shards_and_joins_agree(spark):
    pair = frame(spark, range(0, 700), range(200, 900), shards=4)
    left, right = pair.where("side < 0"), pair.where("side > 0")
    sizes = slices.sized(left)
    joined = slices.test_slices(right, slices.build_slices(left, 0, 9, 1, sizes), sizes, 0, 9)
    kernel = slices.test_in_shards(left, right, 0, 9)
    read = lambda df: sorted((r.digest, -9 if r.first_miss is None else r.first_miss) for r in df.collect())
    assert read(joined) == read(kernel)


def test_kernels_agree_in_both_dialects(spark):
    pair = frame(spark, range(0, 300), range(90, 400), shards=2)
    left, right = pair.where("side < 0"), pair.where("side > 0")
    sizes = slices.sized(left)
    joined = slices.test_slices(right, slices.build_slices(left, 0, 6, 1, sizes, "portable"), sizes, 0, 6, 1, "portable")
    read = lambda df: sorted((r.digest, -9 if r.first_miss is None else r.first_miss) for r in df.collect())
    assert read(joined) == read(slices.test_in_shards(left, right, 0, 6, 1, "portable"))


def test_plans_stay_small(spark, smoke):
    for name in ("hybrid_result", "static_hybrid_result", "hybrid_bytes", "probe_then_sync"):
        assert len(catalogue.queries()[name](spark, smoke)._jdf.queryExecution().toString()) < 300_000


def test_least_prefix_is_what_peeling_finds():
    rng = np.random.default_rng(3)
    for n in (1, 2, 7, 60):
        ids = rng.integers(-(2**62), 2**62, n)
        signs = rng.choice([-1, 1], n)
        full = peel.Cells(4 * n + 16)
        full.add(ids, signs)
        fine = [peel.peel(full.prefix(m))[2] for m in range(4 * n + 17)]
        found, owners, done = peel.peel(full.prefix(4 * n + 16))
        assert done and sorted(zip(found.tolist(), owners.tolist())) == sorted(zip(ids.tolist(), signs.tolist()))
        least = peel.least_prefix(ids, 4 * n + 16)
        assert fine[least] and not any(fine[1:least])  # no cells at all hold nothing that is left


def test_method_times_cover_every_method(spark):
    rows = sweep.method_times(frame(spark, range(500), range(20, 520))).collect()
    assert {r.method for r in rows} == {"sliced_hybrid", "static", "cell_stream", "syndrome_sketch"} and all(r.compute_ms > 0 for r in rows)


def test_no_member_is_rejected(spark):
    pair = frame(spark, range(1000), range(1000))
    left, right = pair.where("side < 0"), pair.where("side > 0")
    sizes = filters.sizes_for(left, [0.01, 0.3])
    assert filters.probe_filter(right, filters.build_filter(left, sizes), sizes).where("not passes").count() == 0
    assert filters.probe_partitioned(right, left, 3).where("not passes").count() == 0


def test_sync_of_frames_ends_in_the_union(spark, smoke):
    rows = table(spark, smoke, "orders")
    left, right = rows.where("o_orderkey % 9 <> 0"), rows.where("o_orderkey % 7 <> 0")
    done = hybrid.sliced_hybrid(left, right, shards=2)
    want = sorted(r.o_orderkey for r in rows.where("o_orderkey % 63 <> 0").collect())
    assert sorted(r.o_orderkey for r in done.left_out.collect()) == sorted(r.o_orderkey for r in done.right_out.collect()) == want
    kinds = {r.kind for r in done.ledger.collect()}
    assert {"slice", "cell", "stop", "payload"} <= kinds


def test_kept_cells_equal_rebuilt_ones(spark):
    old, new = frame(spark, range(300), []), frame(spark, range(50, 400), [])
    changes = frame(spark, range(50), []).withColumn("change", F.lit(-1)).unionByName(frame(spark, range(300, 400), []).withColumn("change", F.lit(1)))
    kept = cells.maintain_cells(cells.build_cells(old, 0, 40), changes.drop("payload_bytes"), 40)
    assert sorted(map(tuple, kept.collect())) == sorted(map(tuple, cells.build_cells(new, 0, 40).collect()))


def test_cell_forms_agree(spark):
    pair = frame(spark, range(100), range(3, 103))
    fast = cells.difference_cells(pair, 64)
    plain = cells.subtract_cells(cells.build_cells(pair.where("side < 0"), 0, 64), cells.build_cells(pair.where("side > 0"), 0, 64))
    full = lambda df: sorted(tuple(r) for r in df.select("cell", "id_xor", "check_xor", "cnt").collect() if any(r[1:]))
    assert full(fast) == full(plain)
    both = peel.peel_relational(cells.difference_cells(pair, 64), 64).collect()
    assert {(r.digest, r.side) for r in both} == {(x, -1) for x in range(3)} | {(x, 1) for x in range(100, 103)} and all(r.decoded for r in both)
    assert not any(r.decoded for r in peel.peel_local(cells.difference_cells(frame(spark, range(50), []), 10), 10).collect())


def test_static_tables(spark):
    pair = frame(spark, range(1, 1001), range(3, 1003))
    got = xortable.table_reconcile(pair, 30).where("decoded").collect()
    assert {(r.digest, r.side) for r in got} == {(1, -1), (2, -1), (1001, 1), (1002, 1)}
    assert not any(r.decoded for r in xortable.table_reconcile(frame(spark, range(60), []), 30).collect())
    few = frame(spark, range(8), []).withColumn("side", F.lit(1))
    gone = xortable.table_delete(xortable.build_table(few, 60), few.where("digest < 3"), 60)
    assert sorted(r.digest for r in xortable.list_table(gone, 60).collect()) == list(range(3, 8))


def test_multisets_and_empty_frames(spark):
    rows = spark.createDataFrame([(1,), (1,), (2,)], "x int")
    assert digests(rows).count() == 2 and digests(rows, multiset=True).count() == 3
    assert digests(rows.limit(0)).count() == 0


def test_stream_stops_where_the_batch_does(spark, tmp_path):
    messages.ensure_checkpoints(spark)
    pair = frame(spark, range(2000), range(700, 2700)).persist()
    left, right = pair.where("side < 0"), pair.where("side > 0")
    batch = hybrid.run_phase(left, right, 1)
    path = str(tmp_path / "slices")
    for first, last in ((2, 3), (0, 1), (0, 0), (4, 9)):  # early, then in order, once more, then the rest
        slice_stream.write_slices(left, path, first, last)
    state = slice_stream.stream_slices(spark, path, right, leak_cost_bits(), checkpoint=str(tmp_path / "progress"))
    stop = batch.stops.first().stop
    assert state.stop == stop and state.overshoot == 9 - stop
    want = {r.slice: r.new_rejects for r in batch.histogram.collect() if r.slice <= stop}
    assert {k: n for k, n, _ in state.trace} == want
    assert state.suspects.count() == batch.status.where("suspect").count()


def test_stream_waits_for_all_files_of_a_slice(spark, tmp_path):
    messages.ensure_checkpoints(spark)
    pair = frame(spark, range(2000), range(700, 2700)).persist()
    left, right = pair.where("side < 0"), pair.where("side > 0")
    batch = hybrid.run_phase(left, right, 1)
    whole, path = str(tmp_path / "whole"), str(tmp_path / "parts")
    slice_stream.write_slices(left, whole, 0, 9)
    spark.read.schema(slice_stream.SLICE_SCHEMA).parquet(whole).repartition(3, "word_no").withColumn("part", F.col("slice")).write.partitionBy("part").parquet(path)
    state = slice_stream.stream_slices(spark, path, right, leak_cost_bits(), checkpoint=str(tmp_path / "progress"))
    stop = batch.stops.first().stop
    assert state.stop == stop and state.overshoot == 9 - stop
    assert {k: n for k, n, _ in state.trace} == {r.slice: r.new_rejects for r in batch.histogram.collect() if r.slice <= stop}


def test_advice_and_ranges_read_their_tables(spark, smoke):
    advice = catalogue.queries()["advise"](spark, smoke).collect()
    sizes = {r.run_id: r for r in catalogue.queries()["replica_pair_sizes"](spark, smoke).collect()}
    assert {(r.run_id, r.n, r.d) for r in advice if r.d >= 0} == {(k, r.n_a, r.d) for k, r in sizes.items()} and len(advice) == 12
    keys = sorted({r[0] for r in table(spark, smoke, "orders").select("o_orderkey").collect()})
    got = {(r.digest, r.side) for r in catalogue.queries()["worked_ranges"](spark, smoke).collect()}
    assert got == {(keys[0], -1), (keys[1], -1), (keys[-2], 1), (keys[-1], 1)}


def test_pairs_rank_only_the_lowest_orders(spark):
    base = spark.range(40_000).select(F.col("id").alias("digest"), F.lit(8).alias("payload_bytes"))
    runs = workloads.runs_table(spark, 300, [50.0, 90.0], 3)
    for dialect in ("fast", "portable"):
        order = workloads.order_of(F.col("digest"), F.col("trial"), dialect)
        turns = base.withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(2))))
        brute = workloads.ranked(turns, order).where("rank < 400").select("trial", "digest", "rank")
        for about in (40_000, 10_000_000):  # a bad guess is mended
            low = workloads.lowest(turns, 400, about, 3, dialect)
            assert 1200 <= low.count() < 6000
            assert low.join(brute, ["trial", "digest"]).count() == 1200
        got = workloads.replica_pairs(base, runs, dialect, 3).select("run_id", "side", "digest").collect()
        ranks = {(r.trial, r["rank"]): r.digest for r in brute.collect()}
        want = {(x.run_id, side, ranks[x.trial, k]) for x in runs.collect() for side in (-1, 1) for k in range(x.n + x.u) if k < x.n - x.u or (k < x.n) == (side < 0)}
        assert set(map(tuple, got)) == want and len(got) == len(want)


def test_change_feed_keeps_cells(spark, tmp_path):
    left = frame(spark, range(100), []).drop("payload_bytes")
    feed = str(tmp_path / "feed")
    for k, (ids, change) in enumerate(((range(10), -1), (range(100, 130), 1))):
        frame(spark, ids, []).drop("payload_bytes").withColumn("change", F.lit(change)).coalesce(1).write.mode("append").parquet(feed)
    got = cell_stream.follow_changes(spark, feed, cells.build_cells(left, 0, 30), 30)
    want = cells.build_cells(frame(spark, range(10, 130), []).drop("payload_bytes"), 0, 30)
    columns = want.columns
    assert sorted(map(tuple, got.select(columns).collect())) == sorted(map(tuple, want.collect()))


def test_payloads_stay_out_of_the_digest_plan(spark, smoke):
    orders = table(spark, smoke, "orders")
    pair = tagged(digests(orders, ["o_orderkey"]), digests(orders, ["o_orderkey"]))
    plan = transfer.exact_difference(pair)._jdf.queryExecution().toString()
    assert "o_orderpriority" not in plan.split("== Physical Plan ==")[1] and "Python" not in plan


def test_measures_have_no_ratio_without_a_difference(spark, smoke):
    pair, runs = workloads.lineitem_sweep(spark, smoke, [50.0, 100.0], n=500)
    rows = sweep.measures(ledger.summarise(transfer.full_transfer_ledger(transfer.set_sizes(pair))), pair, runs)
    assert {r.similarity_pct: r.overhead_ratio is None for r in rows.collect()} == {50.0: False, 100.0: True}
