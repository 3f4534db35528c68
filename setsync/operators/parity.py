"""Parity bitmap groups: bins of small groups compared by parity, differing bins resolved by XOR.

Elements hash into groups of about five differences and, round by round with fresh hashes, into the
bins of their group. A sketch of the group's parity bitmap over a field as small as the bitmap tells
the bins that differ; a bin with one differing element has it as the XOR of both sides. Two in a bin
hide from each other until the next round; a group whose sketch does not decode is split in three; a
group checksum ends it (and undoes what a sketch decoded wrongly).
"""

from __future__ import annotations

from functools import lru_cache
from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS
from setsync.operators.syndrome import small_field
from setsync.operators.transfer import payload_lines
from setsync.plans import ledger
from setsync.sources.messages import settled, spread

PER_GROUP, ROUNDS, TARGET = 5, 3, 0.99
WIDTHS = range(6, 12)


@lru_cache(maxsize=None)
def hidden_chances(load: int, bins: int) -> tuple[float, ...]:
    """Chances that 0, 1, ... of ``load`` elements in ``bins`` bins stay hidden (they share a bin with another)."""
    chance = {(0, 0): 1.0}  # (bins with one, elements in shared bins)
    for k in range(load):
        after: dict[tuple[int, int], float] = {}
        for (ones, shared), p in chance.items():
            used_shared = min(shared // 2, bins - ones)
            for move, q in (((ones + 1, shared), (bins - ones - used_shared) / bins), ((ones - 1, shared + 2), ones / bins), ((ones, shared + 1), used_shared / bins)):
                if q > 0:
                    after[move] = after.get(move, 0) + p * q
        chance = after
    out = [0.0] * (load + 1)
    for (_, shared), p in chance.items():
        out[min(load, shared)] += p
    return tuple(out)


def done_within(load: int, bins: int, rounds: int) -> float:
    if load == 0:
        return 1.0
    if rounds == 0:
        return 0.0
    return sum(p * done_within(left, bins, rounds - 1) for left, p in enumerate(hidden_chances(load, bins)) if p > 1e-12)


@lru_cache(maxsize=None)
def tune_parity(d_hat: int, per_group: int = PER_GROUP, rounds: int = ROUNDS, target: float = TARGET) -> tuple[int, int, int]:
    """(groups, q, t): the cheapest bin width 2^q - 1 and sketch capacity t that end all groups in time.

    Group loads are binomial; overflow costs a round. Bits of a group: t q for the sketch, then q and a
    digest for each difference, and a checksum.
    """
    groups = max(1, -(-max(1, d_hat) // per_group))
    share, best = 1 / groups, None
    most = min(d_hat, 40)
    loads = [comb(d_hat, k) * share**k * (1 - share) ** (d_hat - k) if d_hat < 500 else 0 for k in range(most + 1)]
    if d_hat >= 500:
        from math import exp, lgamma, log

        mean = d_hat / groups
        loads = [exp(k * log(mean) - mean - lgamma(k + 1)) for k in range(most + 1)]
    for q in WIDTHS:
        bins = (1 << q) - 1
        ends = [done_within(k, bins, rounds) for k in range(min(most, 24) + 1)]
        late = [done_within(k, bins, rounds - 1) for k in range(min(most, 24) + 1)]
        for t in range(per_group, 25):
            fine = sum(p * (ends[k] if k <= t else late[min(k, len(late) - 1)]) for k, p in enumerate(loads) if k < len(ends))
            if fine**groups < target and not (q == WIDTHS[-1] and t == 24):
                continue
            bits = t * q + per_group * (q + 64) + 64
            if best is None or bits < best[0]:
                best = (bits, q, t)
            break
    return groups, best[1], best[2]


def parity_bins(elements: DataFrame, groups: int, bins: int, round_no: int, dialect: str = "fast") -> DataFrame:
    """``run_id, grp, bin, id_xor, parity`` over both sides: what is common cancels in both columns."""
    h = DIALECTS[dialect]
    spots = elements.withColumn("grp", h.below(groups, F.col("digest"), 300)) if "grp" not in elements.columns else elements
    spots = spots.withColumn("bin", h.below(bins, F.col("digest"), 310, round_no, F.col("split")) if "split" in spots.columns else h.below(bins, F.col("digest"), 310, round_no))
    return spots.groupBy("run_id", "grp", "bin").agg(F.bit_xor("digest").alias("id_xor"), F.pmod(F.count("*"), F.lit(2)).alias("parity"))


def decoded_bins(differing: DataFrame, keys: list[str]) -> DataFrame:
    """``keys, bin``: what each group's sketch of its differing bins decodes to; ``bin`` is null where it does not.

    Power sums of both sides' bitmaps cancel in the bins that agree, so those of the others are all there is to add up.
    """
    names = [*keys, "bin"]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(keys[1:])
        grp, split, bins = (pdf[c].to_numpy() for c in (*keys[1:], "bin"))
        starts = np.flatnonzero((np.diff(grp, prepend=-1) != 0) | (np.diff(split, prepend=-1) != 0))
        field, t, out = small_field(int(pdf.q.iloc[0])), int(pdf.t.iloc[0]), []
        for a, b in zip(starts.tolist(), [*starts[1:].tolist(), len(pdf)]):
            found = field.decode(field.sums(bins[a:b], t))
            out += [(grp[a], split[a], x) for x in (found.tolist() if found is not None else [None])]
        made = pd.DataFrame(out, columns=names[1:])
        made.insert(0, "run_id", pdf.run_id.iloc[0])
        return made.astype({"bin": "Int64"})

    # Some groups to a task: a hash of the group deals them out, a thousand or so together.
    dealt = differing.withColumn("_deal", F.pmod(F.xxhash64("grp"), F.ceil((F.col("groups") + 1) / 1024).cast("long")))
    kept = dealt.select("run_id", "_deal", *keys[1:], "q", "t", "bin")
    return spread(kept, "run_id", "_deal").groupBy("run_id", "_deal").applyInPandas(run, "run_id string, grp long, split long, bin long")


def parity_groups(elements: DataFrame, d_hat: DataFrame, per_group: int = PER_GROUP, rounds: int = ROUNDS, target: float = TARGET, dialect: str = "fast", most_rounds: int = 12) -> tuple[DataFrame, DataFrame]:
    """(differences ``run_id, digest, side``, costs ``run_id, round, groups, bits``).

    ``d_hat``: ``run_id, d_hat``; one small row a run is read to tune it. Common elements cancel in the
    first aggregation; from then on only bins that differ are carried, so a round costs what is left.
    ``elements`` is read several times: pass a stored frame. Groups left after ``most_rounds`` are an error.
    """
    spark, h = elements.sparkSession, DIALECTS[dialect]
    tuned = [(r.run_id, *tune_parity(max(1, int(r.d_hat)), per_group, rounds, target)) for r in d_hat.collect()]
    setup = F.broadcast(spark.createDataFrame(tuned, "run_id string, groups long, q int, t int"))
    own = elements.select("run_id", "digest", F.col("side").cast("int").alias("side")).join(setup, "run_id")
    own = own.withColumn("grp", h.below(F.col("groups"), F.col("digest"), 300)).withColumn("split", F.lit(0).cast("long")).withColumn("bins", F.expr("shiftleft(1L, q) - 1"))
    keys = ["run_id", "grp", "split"]
    left, found, costs = own, None, None
    for r in range(1, most_rounds + 1):
        group_count = left.select(*keys).distinct().groupBy("run_id").agg(F.count("*").alias("now"))
        binned = left.withColumn("bin", h.below(F.col("bins"), F.col("digest"), 310, r, F.col("split")))
        odd = binned.groupBy(*keys, "q", "t", "bins", "groups", "bin").agg(F.bit_xor("digest").alias("digest"), F.pmod(F.count("*"), F.lit(2)).alias("parity"))
        differing = settled(odd.where("parity = 1"), "differing")
        shown = settled(decoded_bins(differing, keys), "decoded")
        # A bin that was decoded wrongly is not among those that differ; a sum that does not hash back to its bin holds several elements.
        known = differing.join(shown.where("bin is not null"), [*keys, "bin"], "left_semi")
        known = known.where(h.below(F.col("bins"), F.col("digest"), 310, r, F.col("split")) == F.col("bin"))
        sides = binned.join(known.select(*keys, "digest"), [*keys, "digest"], "left_semi").select(*keys, "digest", "side")
        new = settled(sides.select("run_id", *keys[1:], "digest", "side"), "found")
        bits = shown.where("bin is not null").groupBy("run_id").agg(F.count("*").alias("shown"))
        cost = group_count.join(bits, "run_id", "left").join(setup, "run_id").na.fill(0, ["shown"])
        cost = cost.select("run_id", F.lit(r).alias("round"), F.col("now").alias("groups"), (F.col("now") * (F.col("q") * F.col("t") + 64) + F.col("shown") * (F.col("q") + 64)).alias("bits"))
        cost = settled(cost, "costs", 1)
        costs = cost if costs is None else costs.unionByName(cost)
        found = new if found is None else found.unionByName(new)
        rest = left.join(new.select("run_id", "digest"), ["run_id", "digest"], "left_anti")
        # The checksum: what is common cancels; a group with anything left goes on.
        sums = rest.groupBy(*keys).agg(F.bit_xor(h.check(F.col("digest"))).alias("sum")).where("sum <> 0").select(*keys)
        over = shown.where("bin is null").select(*keys, F.lit(True).alias("_over"))
        rest = rest.join(sums, keys, "left_semi").join(over, keys, "left")
        third = F.when(F.col("_over"), F.col("split") * 3 + 1 + h.below(3, F.col("digest"), 320, r)).otherwise(F.col("split"))
        left = rest.withColumn("split", third).drop("_over")
        left = settled(left, "left")
        if not left.limit(1).count():
            return found.select("run_id", "digest", "side"), costs
    raise RuntimeError(f"groups are left after {most_rounds} rounds")


def parity_ledger(sizes: DataFrame, costs: DataFrame, sums: int = 128) -> DataFrame:
    """The rounds' bits, the estimator (apart) and the payload."""
    per = costs.groupBy("run_id").agg(F.max("round").alias("rounds"), F.ceil(F.sum("bits") / 8).alias("bytes"))
    rows = sizes.join(per, "run_id", "left").na.fill(0, ["rounds", "bytes"])
    return ledger.lines(rows, "parity_groups", [
        (0, ledger.A, "estimator", F.lit(1), sums * F.ceil(F.log2(2.0 * F.col("n_a") + 1)) / 8, True),
        (1, ledger.A, "parity", F.greatest(F.lit(1), F.col("rounds")), F.col("bytes"), True),
        (2, ledger.B, "wanted_digests", F.col("a_only"), 8 * F.col("a_only"), True), *payload_lines(rows),
    ])
