"""Worked examples and kernels that need no cluster."""

import random

import numpy as np
import pytest

from setsync.functions.hashing import check_np
from setsync.operators import parity, syndrome
from setsync.operators.cells import hit_rates, positions_np
from setsync.operators.filters import size_filter, size_filter_k
from setsync.operators.peel import Cells, least_prefix, peel
from setsync.operators.slices import shard_kernel
from setsync.operators.xortable import block_positions
from setsync.plans import advisor, costs


def some(n, seed=0):
    return np.random.default_rng(seed).integers(-(2**62), 2**62, n)


def test_filter_sizes():
    assert size_filter_k(100_000, 1) == costs.slice_bits_of(100_000) == 144_270
    m, k = size_filter(100_000, 0.01)
    assert m == 958_506 and k == 7


def test_expected_bytes_match_the_derived_table():
    # similarity -> slices and metadata bytes for n = 100,000 (expected values of the cost model)
    table = {0: (1, 1, 36_067), 1006: (1, 1, 52_319), 2532: (2, 2, 92_301), 5128: (3, 3, 127_757), 10_526: (4, 4, 162_025), 66_666: (6, 7, 218_329), 200_000: (8, 16, 158_102)}
    for d, (k1, k2, size) in table.items():
        got = costs.predict_hybrid(100_000, 100_000, d)
        assert (got["slices_1"], got["slices_2"]) == (k1, k2)
        assert got["metadata_bytes"] == pytest.approx(size, rel=2e-4)
    assert costs.predict_static(100_000, 100_000, 0, 0.01) == pytest.approx(239_626, rel=1e-4)
    assert costs.predict_static(100_000, 100_000, 200_000, 0.25) == pytest.approx(1_665_084, rel=1e-4)


def test_table_of_four_elements_is_listed_by_a_cascade():
    for seed in range(40):
        ids = some(4, seed)
        box = Cells(9)
        box.add(ids, np.ones(4, int), block_positions(3))
        found, signs, decoded = peel(box, block_positions(3))
        if decoded:
            assert sorted(found) == sorted(ids) and (signs == 1).all()
            return
    raise AssertionError("no seed decodes")


def test_signs_tell_the_owner_and_small_tables_fail_cleanly():
    a, b = np.arange(1, 100_002), np.arange(3, 100_004)
    outcomes = set()
    for cells in (2, 6, 60):
        box = Cells(cells)
        box.add(a, np.full(len(a), -1), block_positions(2))
        box.add(b, np.ones(len(b), int), block_positions(2))
        found, signs, decoded = peel(box, block_positions(2))
        outcomes.add(decoded)
        if decoded:
            assert dict(zip(found.tolist(), signs.tolist())) == {1: -1, 2: -1, 100_002: 1, 100_003: 1}
    assert outcomes == {True, False}


def test_cells_per_difference_fall_with_size():
    ratios = [least_prefix(some(d, d), np.ones(d, int), 4 * d + 20) / d for d in (10, 200, 5000)]
    assert ratios[0] > ratios[2] and 1.3 < ratios[2] < 1.45


def test_cancelled_counts_are_not_empty():
    box = Cells(1)
    box.add(some(2), np.array([1, -1]))
    assert not box.empty() and not peel(box)[2]


def test_hit_rates_are_those_of_the_walk():
    who, where = positions_np(some(40_000, 5), 32)
    assert np.allclose(np.bincount(where, minlength=32) / 40_000, hit_rates(32), atol=0.01)
    assert hit_rates(3)[1] == pytest.approx(0.64)


def sequential(left, right, cost, phase=1, most=60):
    """The protocol as told: slice by slice until one gains less than it costs."""
    import pandas as pd

    m, waiting, k = costs.slice_bits_of(len(left)), right, 0
    while True:
        tested = shard_kernel(k, k, phase)(pd.DataFrame({"digest": left}), pd.DataFrame({"digest": waiting}))
        gone = tested.first_miss.notna().to_numpy()
        waiting = waiting[~gone]
        if gone.sum() < m / cost or k > most:
            return k, waiting
        k += 1


@pytest.mark.parametrize("seed", range(50))
def test_one_pass_equals_the_sequential_protocol(seed):
    import pandas as pd

    rng = random.Random(seed)
    n, u = rng.randrange(1, 800), rng.randrange(0, 300)
    pool = some(n + u, seed)
    left, right = pool[:n], pool[min(u, n - 1) :]
    tested = shard_kernel(0, 40, 1)(pd.DataFrame({"digest": left}), pd.DataFrame({"digest": right})).first_miss
    cost, m = costs.leak_cost_bits(), costs.slice_bits_of(n)
    stop = next(k for k in range(41) if (tested == k).sum() < m / cost)
    k, waiting = sequential(left, right, cost)
    assert stop == k and sorted(right[(tested.isna() | (tested > stop)).to_numpy()]) == sorted(waiting)


@pytest.mark.parametrize("width", [16, 32, 64])
def test_syndrome_sketch_decodes_or_says_so(width):
    rng = random.Random(width)
    for d in (0, 1, 3, 6):
        ids = np.array([rng.getrandbits(width) for _ in range(d)], np.uint64)
        sums = syndrome.sketch(ids.view(np.int64), 6, width)
        assert sorted(syndrome.decode(sums, width)) == sorted(ids.tolist())
    many = np.array([rng.getrandbits(width) for _ in range(9)], np.uint64)
    assert syndrome.decode(syndrome.sketch(many.view(np.int64), 6, width), width) is None


def test_parity_tuner_stays_in_the_published_band():
    for d in (500, 5000, 50_000):
        groups, q, t = parity.tune_parity(d)
        bits = groups * (q * t + 64) + d * (q + 64)
        assert 1.4 < bits / (64 * d) < 2.1


def test_advice_follows_the_regimes():
    assert advisor.advise(100_000, 10)[0] == "syndrome_sketch"
    assert advisor.advise(100_000, 2000)[0] == "parity_groups"
    assert advisor.advise(100_000, 40_000)[0] == "sliced_hybrid"
    assert advisor.advise(100_000, None)[0] == "sliced_hybrid"
    assert advisor.advise(100_000, 40_000, subset=True)[0].startswith("static_")


def test_check_hash_tells_sums_apart():
    ids = some(1000)
    assert len(set(check_np(ids).tolist())) == 1000
