"""SimHash near-duplicates, linked exactly within a Hamming radius by a generalised pigeonhole search.

A pair within ``radius`` bits must, for some part i of any split of the bits, differ in fewer than
``share_i`` bits of it when the shares add up to ``radius + 1``. The planner groups correlated bits
into parts and gives out the shares by dynamic programming over estimated costs, so a part may be
probed exactly, through a small ball, or not at all. Distinct fingerprints alone are searched;
copies come back by a join.

Defined cases: a null or wordless text has fingerprint zero and is linked like any other; texts with
fewer words than a shingle use the whole sequence; repeated rows share their fingerprint and group;
an empty table gives no rows; a null id keeps its row and never names a component.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from setsync.llm.shared import bounded_batches, connected_components, cut, join_heavy, spare_name, table

WORDS = 4
RADIUS = 4
SEED = 42
#: Distinct fingerprints that the planner looks at, and the most of one bucket that a task holds.
PLAN_SAMPLE = 2048
BUCKET = 20_000
#: Cost of checking a pair against that of shuffling a probe row.
PAIR_COST = 0.05


def shingle_hashes(text: str | None, width: int = WORDS, seed: int = SEED) -> np.ndarray:
    """Hashes of ASCII-lower-cased word shingles in order; a text with fewer words has one, the whole sequence."""
    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    line = b" ".join(words)
    hashing = xxhash.xxh64_intdigest
    if len(words) <= width:
        return np.array([hashing(line, seed)], np.uint64)
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = [0, *ends[:-width].tolist()]
    return np.array([hashing(line[i : j - 1], seed) for i, j in zip(starts, ends[width - 1 :].tolist())], np.uint64)


def fingerprint(text: str | None, width: int = WORDS, seed: int = SEED) -> int:
    """Unsigned 64-bit SimHash of ASCII-lower-cased word shingles, each occurrence counted."""
    values = shingle_hashes(text, width, seed)
    if len(values) <= 1:
        return int(values.sum())
    counts = np.zeros(64, np.int64)
    for at in range(0, len(values), 1 << 16):
        block = values[at : at + (1 << 16)]
        counts += np.unpackbits(block.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    bits = np.packbits((2 * counts > len(values)).astype(np.uint8), bitorder="little")
    return int(bits.view(np.uint64)[0])


@F.pandas_udf(T.LongType())
def fingerprint_column(text: pd.Series) -> pd.Series:
    values = np.array([fingerprint(t) for t in text], np.uint64)
    return pd.Series(values.view(np.int64))


def group_bits(sample: np.ndarray, parts: int) -> list[list[int]]:
    """Splits the 64 bits into ``parts`` groups of near-equal size, correlated bits together."""
    bits = ((sample[:, None] >> np.arange(64, dtype=np.uint64)) & np.uint64(1)).astype(float)
    centred = bits - bits.mean(0)
    scale = np.sqrt((centred**2).mean(0))
    scale[scale == 0] = 1
    tied = np.abs(centred.T @ centred / max(1, len(sample)) / np.outer(scale, scale))
    left, groups = list(range(64)), []
    for k in range(parts):
        room = (64 * (k + 1)) // parts - (64 * k) // parts
        first = max(left, key=lambda i: (tied[i, left].sum(), -i))
        group = [first]
        left.remove(first)
        while len(group) < room:
            nearest = max(left, key=lambda i: (tied[i, group].sum(), -i))
            group.append(nearest)
            left.remove(nearest)
        groups.append(sorted(group))
    return groups


def plan_parts(sample: np.ndarray, rows: int, radius: int = RADIUS) -> list[tuple[int, int]]:
    """(bit mask, share) of every probed part; the shares add up to ``radius + 1``.

    Chosen over all splits into 2 to ``radius + 1`` parts by the least estimated cost: probe rows
    plus candidate pairs, the latter carried from the sample's pair distances to ``rows``.
    """
    need, best, rows = radius + 1, None, max(1, rows)
    i, j = np.triu_indices(len(sample), 1)
    apart = sample[i] ^ sample[j]
    for parts in range(2, need + 1):
        groups = group_bits(sample, parts) if len(sample) else [list(range(64))[k::parts] for k in range(parts)]
        masks = [sum(1 << b for b in g) for g in groups]
        costs = []
        for g, mask in zip(groups, masks):
            far = np.bincount(np.bitwise_count(apart & np.uint64(mask)), minlength=65) if len(apart) else np.zeros(65)
            costs.append([0.0])
            for share in range(1, need + 1):
                ball = sum(comb(len(g), k) for k in range(share))
                probes = rows * (1 + ball if share > 1 else 1)
                pairs = (far[:share].sum() + 0.5) / max(1, len(apart)) * rows * rows / 2
                costs[-1].append(probes + PAIR_COST * pairs)
        table_ = {0: (0.0, [])}
        for cost in costs:
            step: dict[int, tuple[float, list[int]]] = {}
            for used, (paid, shares) in table_.items():
                for share in range(need - used + 1):
                    new = (paid + cost[share], [*shares, share])
                    if used + share not in step or new < step[used + share]:
                        step[used + share] = new
            table_ = step
        paid, shares = table_[need]
        if best is None or paid < best[0]:
            best = (paid, [(m, s) for m, s in zip(masks, shares) if s])
    return best[1]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def spot(part: int, bucket: Column, probe: bool) -> Column:
    return F.struct(F.lit(part).alias("part"), bucket.alias("bucket"), F.lit(probe).alias("probe"))


def around(part: int, home: Column):
    """Spark counts a lambda's parameters, defaults included, so what a part binds is bound here."""
    return lambda x: spot(part, home.bitwiseXOR(x), True)


def probe_rows(prints: DataFrame, plan: list[tuple[int, int]]) -> DataFrame:
    """``part, bucket, fp, probe``: each fingerprint at home in every part, and as a probe around it."""
    parts = []
    for part, (mask, share) in enumerate(plan):
        bits = [b for b in range(64) if mask >> b & 1]
        flips = [signed(sum(1 << b for b in some)) for k in range(1, share) for some in combinations(bits, k)]
        home = F.col("fp").bitwiseAND(F.lit(signed(mask)))
        parts.append(F.array(spot(part, home, False)))
        if flips:  # one literal, however large the ball
            ball = F.split(F.lit(",".join(map(str, flips))), ",").cast("array<long>")
            parts.append(F.transform(ball, around(part, home)))
    return prints.select("fp", F.explode(F.concat(*parts)).alias("s")).select("s.part", "s.bucket", "fp", "s.probe")


def spanning(home: np.ndarray, probe: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Links of one bucket that connect what all its links connect: breadth first, at most one per member."""
    waiting = np.concatenate([home, probe])
    side = np.concatenate([np.zeros(len(home), bool), np.ones(len(probe), bool)])
    out: list[tuple[int, int]] = []
    while len(waiting):
        queue = [(waiting[0], side[0])]
        waiting, side = waiting[1:], side[1:]
        while queue and len(waiting):
            x, probing = queue.pop()
            near = np.bitwise_count(waiting ^ x) <= radius
            if probing:
                near &= ~side
            if near.any():
                out += [(x, y) for y in waiting[near]]
                queue += list(zip(waiting[near], side[near]))
                waiting, side = waiting[~near], side[~near]
    return out


def bucket_links(radius: int, limit: int, keys: tuple[str, ...]):
    """Kernel over rows sorted by bucket: links between members, or the rows of a bucket above ``limit`` handed on."""

    def links(fp: np.ndarray, group: np.ndarray, probe: np.ndarray) -> tuple[list, list]:
        left, right = [], []
        sizes = np.bincount(group)
        small = sizes[group] <= 48
        f, g, p = fp[small], group[small], probe[small]
        alive = np.arange(len(f))
        step = 1
        while len(alive):
            alive = alive[alive + step < len(f)]
            alive = alive[g[alive] == g[alive + step]]
            x, y = f[alive], f[alive + step]
            hit = (np.bitwise_count(x ^ y) <= radius) & ~(p[alive] & p[alive + step]) & (x != y)
            left.append(x[hit])
            right.append(y[hit])
            step += 1
        for k in np.flatnonzero(sizes > 48):
            own = group == k
            for x, y in spanning(fp[own & ~probe], fp[own & probe], radius):
                left.append(np.array([x], np.uint64))
                right.append(np.array([y], np.uint64))
        return left, right

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(a, b, deferred):
            n = len(a)
            return pa.record_batch([pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), *(deferred or [pa.nulls(n, pa.int64())] * 2 + [pa.nulls(n, pa.bool_())])], names=["a", "b", "part", "bucket", "probe"])

        held: list[tuple[np.ndarray, ...]] = []
        spilling = None

        def flush(cols, _):
            part, bucket, fp, probe, *more = cols
            if not len(fp):
                return None
            new = np.zeros(len(fp), bool)
            for key in (part, bucket, *more):
                new[1:] |= key[1:] != key[:-1]
            a, b = links(fp, np.cumsum(new), probe)
            return out(np.concatenate(a) if a else np.zeros(0, np.uint64), np.concatenate(b) if b else np.zeros(0, np.uint64), None)

        def hand_on(cols):
            part, bucket, fp, probe, *_ = cols
            return out(fp, fp, [pa.array(part.astype(np.int64)), pa.array(bucket), pa.array(probe)])

        for batch in batches:
            cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(batch.num_columns)]
            cols[2] = cols[2].view(np.uint64)
            if not len(cols[2]):
                continue
            ids = list(zip(*(cols[i][[0, -1]].tolist() for i in (0, 1, *range(4, len(cols))))))
            if spilling is not None:
                same = np.logical_and.reduce([cols[i] == k for i, k in zip((0, 1, *range(4, len(cols))), spilling)])
                if same.any():
                    yield hand_on([c[same] for c in cols])
                    cols = [c[~same] for c in cols]
                if not len(cols[2]):
                    continue
                spilling = None
            held.append(tuple(cols))
            cols = [np.concatenate(c) for c in zip(*held)]
            last = np.logical_and.reduce([cols[i] == cols[i][-1] for i in (0, 1, *range(4, len(cols)))])
            if (done := flush([c[~last] for c in cols], ids)) is not None:
                yield done
            rest = [c[last] for c in cols]
            if limit and len(rest[2]) > limit:
                yield hand_on(rest)
                spilling = tuple(rest[i][-1] for i in (0, 1, *range(4, len(rest))))
                held = []
            else:
                held = [tuple(rest)]
        if held:
            cols = [np.concatenate(c) for c in zip(*held)]
            if (done := flush(cols, None)) is not None:
                yield done

    return run


LINKS = "a long, b long, part long, bucket long, probe boolean"


def near_links(prints: DataFrame, radius: int = RADIUS, bucket_limit: int = BUCKET) -> DataFrame:
    """Links ``a, b`` between distinct fingerprints (column ``fp``) that connect all pairs within ``radius`` bits.

    A bucket above ``bucket_limit`` is handed on and dealt out as pairs of chunks, so no task holds
    more than two chunks and nothing is dropped.
    """
    rows = prints.count()
    sample = prints.orderBy(F.xxhash64("fp"), "fp").limit(PLAN_SAMPLE).collect()
    plan = plan_parts(np.array([r.fp for r in sample], np.int64).view(np.uint64), rows, radius)
    spots = probe_rows(prints, plan)
    dealt = spots.repartition(F.col("part"), F.col("bucket")).sortWithinPartitions("part", "bucket")
    found = cut(dealt.mapInArrow(bucket_links(radius, bucket_limit, ("part", "bucket")), LINKS))
    links = found.where("part is null").select("a", "b")
    large = found.where("part is not null").select("part", "bucket", F.col("a").alias("fp"), "probe")
    if large.limit(1).count():
        sizes = large.groupBy("part", "bucket").agg(F.ceil(F.count("*") / F.lit(bucket_limit / 2)).cast("int").alias("chunks"))
        chunk = F.pmod(F.xxhash64("fp", F.lit(7)), F.col("chunks")).cast("int")
        pairs = (
            large.join(sizes, ["part", "bucket"])
            .withColumn("own", chunk)
            .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
            .select("part", "bucket", "fp", "probe", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"))
        )
        pairs = pairs.repartition("part", "bucket", "low", "high").sortWithinPartitions("part", "bucket", "low", "high")
        links = links.unionByName(cut(pairs.mapInArrow(bucket_links(radius, 0, ()), LINKS)).select("a", "b"))
    return links


def simhash_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, carry: bool = False) -> DataFrame:
    """``doc_id, fp, component_id``: every row with its fingerprint and the smallest id its group reaches.

    ``carry`` adds ``root``, which names the group, and ``tie``, a hash of the row's text.
    """
    bounded_batches(docs.sparkSession)
    extra = [F.xxhash64(text_col).alias("tie")] if carry else []
    prints = cut(docs.select(F.col(id_col).alias("doc_id"), fingerprint_column(F.col(text_col)).alias("fp"), *extra))
    classes = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies")))
    roots = connected_components(near_links(classes.select("fp"), radius))
    named = cut(classes.join(roots, classes.fp == roots.node, "left").select("fp", "rep", "copies", F.coalesce("root", "fp").alias("root")))
    labels = with_smallest(named, "root", "rep").select("fp", "component_id", "copies", *(["root"] if carry else []))
    total = classes.agg(F.sum("copies")).first()[0] or 0
    return join_heavy(prints, labels, "fp", "copies", total).select("doc_id", "fp", "component_id", *(["root", "tie"] if carry else []))


def with_smallest(named: DataFrame, root: str, name: str) -> DataFrame:
    """Adds ``component_id``, the smallest ``name`` of the row's ``root``."""
    first = cut(named.groupBy(root).agg(F.min(name).alias("component_id"), F.count("*").alias("_members")))
    return join_heavy(named, first, root, "_members", first.agg(F.sum("_members")).first()[0] or 0)


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """One row of each group, all columns kept: that of the smallest id. Rows without an id stay."""
    return kept_rows(docs, simhash_groups(docs, id_col, text_col, radius, carry=True), id_col, text_col)


def kept_rows(docs: DataFrame, groups: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Of each group ``root`` the row of the smallest id and, where rows repeat that, the smallest ``tie`` (the hash
    of its text) and row hash. Unlike rows of one id are in groups of their own and both stay."""
    groups = cut(groups.where("doc_id is not null").groupBy("root", "doc_id", "tie").agg(F.count("*").alias("copies")))
    first = groups.groupBy("root").agg(F.min(F.struct("doc_id", "tie", "copies")).alias("w"))
    own_id, tie, copies = (spare_name(docs, n) for n in ("_own_id", "_tie", "_copies"))
    winners = first.select(F.col("w.doc_id").alias(own_id), F.col("w.tie").alias(tie + "_w"), F.col("w.copies").alias(copies))
    # One id may win in several groups: what its rows have in common is the text.
    winners = cut(winners.groupBy(own_id, tie + "_w").agg(F.max(copies).alias(copies)))
    marked = docs.withColumn(tie, F.xxhash64(text_col))
    on = lambda w: (F.col(id_col) == F.col(own_id)) & (F.col(tie) == F.col(tie + "_w"))
    once, repeated = winners.where(F.col(copies) == 1), winners.where(F.col(copies) > 1)
    kept = marked.join(once, on(once), "left_semi").select(*[F.col(f"`{c}`") for c in docs.columns])
    if repeated.limit(1).count():
        again = marked.join(repeated, on(repeated), "left_semi")
        row = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
        order = F.xxhash64(*[F.col(f"`{f.name}`") for f in docs.schema.fields if "map" not in f.dataType.simpleString()])
        chosen = again.groupBy(F.col(id_col).alias(own_id), F.col(tie).alias(tie + "_w")).agg(F.min_by(row, order).alias("_row"))
        kept = kept.unionByName(chosen.select("_row.*"))
    return kept.unionByName(docs.where(F.col(id_col).isNull()))


def op8_simhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash_groups(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
