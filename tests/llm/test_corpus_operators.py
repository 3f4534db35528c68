"""Operators over whole tables against brute force: groups, links, mixing, the pipeline."""

import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from setsync.llm import covertree, mixing, nearcopies, registry, shared, simhash
from tests.llm.test_text_operators import ODD_ROWS, brute_print, odd


def roots(n, links):
    parent = list(range(n))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return [find(x) for x in range(n)]


@pytest.mark.parametrize("small", [shared.SMALL_EDGES, 0])
def test_connected_components(spark, monkeypatch, small):
    monkeypatch.setattr(shared, "SMALL_EDGES", small)
    rng = random.Random(2)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(180)] + [(k, k + 1) for k in range(400, 460)] + [(500, k) for k in range(501, 540)]
    edges = spark.createDataFrame([*pairs, (None, 3), (7, 7)], "a long, b long")
    want = roots(600, pairs)
    got = {r.node: r.root for r in shared.connected_components(edges).collect()}
    assert all(got.get(k, k) == want[k] for k in range(600))
    assert shared.connected_components(edges.limit(0)).count() == 0


def flipped(rng, x, k):
    for b in rng.sample(range(64), k):
        x ^= 1 << b
    return x


@pytest.mark.parametrize("limit", [20_000, 30])
def test_hamming_links_connect_what_brute_force_connects(spark, limit):
    rng = random.Random(limit)
    prints = [rng.getrandbits(64) for _ in range(150)] + [0, (1 << 64) - 1]
    base = rng.getrandbits(64)
    prints += [flipped(rng, rng.choice(prints), rng.randrange(1, 8)) for _ in range(150)]
    prints += [flipped(rng, base, rng.randrange(0, 4)) for _ in range(200)]
    prints = sorted(set(prints))
    df = spark.createDataFrame([(simhash.signed(x),) for x in prints], "fp long")
    at = {x: k for k, x in enumerate(prints)}
    links = [(at[r.a % (1 << 64)], at[r.b % (1 << 64)]) for r in simhash.near_links(df, bucket_limit=limit).collect()]
    assert all((prints[a] ^ prints[b]).bit_count() <= 4 for a, b in links)
    brute = [(i, j) for i in range(len(prints)) for j in range(i) if (prints[i] ^ prints[j]).bit_count() <= 4]
    assert roots(len(prints), links) == roots(len(prints), brute)


def test_plans_always_share_out_the_radius():
    rng = np.random.default_rng(1)
    for rows in (10, 10**5, 10**9, 10**12):
        plan = simhash.plan_parts(rng.integers(0, 2**63, 300).astype(np.uint64), rows)
        assert sum(s for _, s in plan) == simhash.RADIUS + 1
        assert all(not (a & b) for k, (a, _) in enumerate(plan) for b, _ in plan[:k])


@pytest.mark.parametrize("plan", [[((1 << 30) - 1, 3), (((1 << 34) - 1) << 30, 2)], [((1 << 20) - 1, 2), (((1 << 22) - 1) << 20, 2), (((1 << 22) - 1) << 42, 1)]])
def test_ball_probes_lose_no_link(spark, plan, monkeypatch):
    monkeypatch.setattr(simhash, "plan_parts", lambda *a: plan)
    test_hamming_links_connect_what_brute_force_connects(spark, 20_000)


def test_large_tables_are_probed_by_balls(spark):
    rng = np.random.default_rng(3)
    sample = rng.integers(0, 2**63, 2048).astype(np.uint64)
    plan = simhash.plan_parts(sample, 3_000_000)
    assert max(share for _, share in plan) > 1  # as with the fingerprints of 6 GB of documents
    rows = simhash.probe_rows(spark.createDataFrame([(7,), (-1,)], "fp long"), plan).collect()
    for part, (mask, share) in enumerate(plan):
        want = {(fp, bucket) for fp in (7, -1) for bucket in ball(fp % (1 << 64) & mask, mask, share)}
        assert {(r.fp, r.bucket % (1 << 64)) for r in rows if r.part == part} == want


def ball(home, mask, share):
    bits = [b for b in range(64) if mask >> b & 1]
    return [home ^ sum(1 << b for b in some) for k in range(share) for some in combinations(bits, k)]


def test_simhash_groups(spark, smoke):
    docs = shared.table(spark, smoke, "documents")
    rows = docs.orderBy("doc_id").collect()
    prints = [brute_print(r.text) for r in rows]
    want = roots(len(rows), [(i, j) for i in range(len(rows)) for j in range(i) if (prints[i] ^ prints[j]).bit_count() <= 4])
    got = {r.doc_id: r for r in registry.queries()["op8_simhash_neardup"](spark, smoke).collect()}
    assert len(got) == len(rows)
    for k, r in enumerate(rows):
        assert got[r.doc_id].fingerprint == f"{prints[k]:016x}" and got[r.doc_id].component_id == rows[want[k]].doc_id
    kept = simhash.keep_one(docs)
    assert sorted(r.doc_id for r in kept.collect()) == sorted({rows[w].doc_id for w in want})
    assert kept.columns == docs.columns


def test_simhash_odd_rows(spark):
    got = simhash.simhash_groups(odd(spark)).collect()
    assert len(got) == len(ODD_ROWS)
    assert {r.component_id for r in got if r.doc_id in (1, 2, 3)} == {1}
    assert simhash.simhash_groups(odd(spark).limit(0)).count() == 0
    kept = simhash.keep_one(odd(spark)).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in kept) == [(False, 1), (False, 4), (False, 6), (True, 0)]


def test_kept_rows_lose_no_unlike_text(spark):
    rng = random.Random(12)
    unlike = [" ".join(f"w{rng.randrange(10**6)}" for _ in range(80)) for _ in range(4)]
    rows = [(1, unlike[0], "a"), (1, unlike[1], "b"), (2, unlike[2], "c"), (3, unlike[0], "d"), (3, unlike[2].upper(), "e"), (1, unlike[0], "f"), (None, unlike[3], "g"), (None, unlike[3], "h")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, _name string").withColumn("_tie", F.lit(1))
    for keep in (simhash.keep_one, nearcopies.keep_one):
        kept = keep(docs)
        assert kept.columns == docs.columns
        got = sorted((r.doc_id or 0, r.text) for r in kept.collect())
        assert got == sorted([(1, unlike[0]), (1, unlike[1]), (2, unlike[2]), (0, unlike[3]), (0, unlike[3])])
        assert {r._name for r in kept.collect()} == {r._name for r in kept.collect()}


def test_heavy_keys_join_like_light_ones(spark):
    rows = spark.createDataFrame([(k, 7 if k % 3 else k) for k in range(300)], "x long, key long")
    per = rows.groupBy("key").agg(F.count("*").alias("n"), F.min("x").alias("low"))
    want = sorted(map(tuple, rows.join(per.drop("n"), "key").select("key", "x", "low").collect()))
    assert sorted(map(tuple, shared.join_heavy(rows, per, "key", "n", 300).select("key", "x", "low").collect())) == want


def jaccard(a, b):
    sets = []
    for text in (a, b):
        words = text.lower().split()
        sets.append({" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))})
    return len(sets[0] & sets[1]) / len(sets[0] | sets[1])


def test_pipeline_drops_near_copies_at_their_true_similarity(spark, smoke):
    rng = random.Random(9)
    texts = []
    for _ in range(12):
        words = [f"w{rng.randrange(10**6)}" for _ in range(rng.randrange(60, 400))]
        texts.append(" ".join(words))
        for cuts in (1, 2, 3, 4, 6, 9):
            other = list(words)
            for k in rng.sample(range(len(words)), cuts):
                other[k] = "changed"
            texts.append(" ".join(other))
    prints = [brute_print(t) for t in texts]
    pairs = [(i, j) for i in range(len(texts)) for j in range(i)]
    near = [(i, j) for i, j in pairs if jaccard(texts[i], texts[j]) >= 0.8]
    assert any((prints[i] ^ prints[j]).bit_count() > 4 for i, j in near)
    want = roots(len(texts), near + [(i, j) for i, j in pairs if (prints[i] ^ prints[j]).bit_count() <= 4])
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for held in (nearcopies.HELD, 1000):
        got = {r.doc_id: r.component_id for r in nearcopies.similar_groups(docs, held=held).collect()}
        assert [got[k] for k in range(len(texts))] == want
    kept = corpus_pipeline.drop_near_copies(spark, docs, smoke)
    assert sorted(r.doc_id for r in kept.collect()) == sorted(set(want))


def vectors(spark, rng, n=260):
    base = rng.normal(size=(12, 8))
    rows = []
    for k in range(n):
        v = base[rng.integers(12)] + rng.normal(size=8) * rng.choice([0, 0.02, 0.1, 0.2])
        rows.append((k, [float(np.float32(x)) for x in v], int(rng.integers(2))))
    rows += [(n, None, 1), (n + 1, [0.0] * 8, 1), (n + 2, [float("nan")] * 8, 0), (n + 3, rows[0][1], None), (n + 4, [None, *[1.0] * 7], 1), (n + 5, [1.0, 2.0], 1), (n + 6, [2.0, 4.0], 1), (n + 7, [], 1), (n + 8, [float("inf")] * 8, 1)]
    return rows


@pytest.mark.parametrize("anchors,cell_rows", [(2048, 4000), (4, 7), (30, 20)])
def test_cover_tree_links_equal_brute_force(spark, anchors, cell_rows):
    rows = vectors(spark, np.random.default_rng(cell_rows))
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").withColumn("weight", F.lit("x"))
    good = lambda v: v and all(x is not None and np.isfinite(x) for x in v) and any(v)
    links = []
    for i, (_, a, la) in enumerate(rows):
        for j, (_, b, lb) in enumerate(rows[:i]):
            if la is not None and la == lb and good(a) and good(b) and len(a) == len(b):
                x, y = np.float32(a).astype(float), np.float32(b).astype(float)
                if x @ y / np.sqrt((x @ x) * (y @ y)) >= 0.98:
                    links.append((i, j))
    want, n = roots(len(rows), links), [0] * len(rows)
    for i, j in links:
        n[i] += 1
        n[j] += 1
    got = {r.vec_id: r for r in covertree.link_vectors(df, anchors=anchors, cell_rows=cell_rows).collect()}
    assert len(got) == len(rows)
    assert [(got[k].n_links, got[k].component_id, got[k].kept) for k in range(len(rows))] == [(n[k], want[k], want[k] == k) for k in range(len(rows))]


def test_cover_tree_without_usable_rows(spark):
    df = spark.createDataFrame([(1, None, 1)], "vec_id long, embedding array<float>, label int")
    assert [tuple(r) for r in covertree.link_vectors(df).collect()] == [(1, 0, 1, True)]
    assert covertree.link_vectors(df.limit(0)).count() == 0


def plain_quotients(shares, seats):
    won = [0] * len(shares)
    for _ in range(seats):
        k = max(range(len(shares)), key=lambda i: (shares[i] / (2 * won[i] + 1), -i))
        won[k] += 1
    return won


def test_highest_quotients_equal_seat_by_seat(spark):
    rng = random.Random(4)
    for case in range(4):
        shares = [rng.choice([0, 1, 7, 53, 1000, 99999]) + rng.random() for _ in range(rng.randrange(1, 15))]
        seats = rng.randrange(0, 200)
        df = spark.createDataFrame([(k, s, seats) for k, s in enumerate(shares)], "k int, share double, seats long")
        got = mixing.highest_quotients(df, [], "share", "seats", [F.col("k")])
        assert [r.quota for r in got.orderBy("k").collect()] == plain_quotients(shares, seats)


def water_level(sizes, weights, percent=1.5, cap=2):
    target, free, pool = {}, dict(enumerate(sizes)), percent * sum(sizes)
    while free:
        total = sum(weights[k] for k in free)
        over = [k for k in free if weights[k] * pool / total >= cap * sizes[k]]
        if not over:
            return [target.get(k, weights[k] * pool / total if k in free else 0) for k in range(len(sizes))]
        for k in over:
            target[k] = cap * sizes[k]
        pool -= sum(target[k] for k in over)
        for k in over:
            del free[k]
    return [target[k] for k in range(len(sizes))]


def test_mix_meets_its_targets(spark, smoke):
    odd_docs = odd(spark)
    for docs in (shared.table(spark, smoke, "documents"), odd_docs):
        for block, shard_rows in ((1024, 4096), (16, 7)):
            got = mixing.mix(docs, block=block, shard_rows=shard_rows).toPandas()
            assert len(got) == docs.count() and (got.taken <= 2 * got["size"]).all()
            got["source"] = got.source.fillna("\U0010ffff")
            per = got.groupby("source").agg(target=("target", "first"), taken=("taken", "sum"), size=("size", "sum")).sort_index()
            want = water_level(per["size"].tolist(), [mixing.WEIGHTS[k % 3] for k in range(len(per))])
            assert np.allclose(per.target, want) and (abs(per.taken - per.target) <= 1).all()
    assert mixing.mix(odd_docs.limit(0)).count() == 0


def test_mixed_rows_spell_what_was_taken(spark, smoke):
    docs = shared.table(spark, smoke, "documents")
    taken = mixing.mix(docs).agg(F.sum("taken")).first()[0]
    rows = mixing.mixed_rows(docs)
    assert rows.columns == docs.columns
    assert rows.agg(F.sum(F.regexp_count("text", F.lit(mixing.WORD)))).first()[0] == taken
    assert rows.where("n_chars <> length(text)").count() == 0
    assert mixing.mixed_rows(odd(spark)).count() > 0


def test_pipeline_stages_keep_columns_and_take_effect(spark, smoke):
    docs = shared.table(spark, smoke, "documents")
    seen = [docs]
    for name, stage in corpus_pipeline.STAGES:
        seen.append(shared.stored(stage(spark, seen[-1], smoke)))
        if name != "packing":
            assert seen[-1].columns == docs.columns
    counts = [d.count() for d in seen]
    assert counts[0] >= counts[1] >= counts[2] == counts[3]
    prints = {brute_print(r.text) for r in seen[2].collect()}
    assert len(prints) == counts[2] and all((a ^ b).bit_count() > 4 for a in prints for b in prints if a != b)
    assert seen[3].where("text rlike 'token = \"[0-9a-f]{24}'").count() == 0
    ids = {r.doc_id for r in seen[4].select("doc_id").distinct().collect()}
    assert {r.doc_id for r in seen[5].select("doc_id").distinct().collect()} == ids


def test_pipeline_on_odd_rows(spark, smoke):
    docs = shared.stored(corpus_pipeline.drop_toxic(spark, odd(spark), smoke))
    assert docs.columns == odd(spark).columns
    near = shared.stored(corpus_pipeline.drop_near_copies(spark, odd(spark), smoke))
    kept = {r.doc_id: r.text for r in near.collect()}
    assert near.count() == 4 and kept == {1: None, 4: "same words here", None: "no id at all", 6: "long " * 9000}
    safe = shared.stored(corpus_pipeline.mask_secrets(spark, near, smoke))
    assert {r.doc_id: r.text for r in safe.collect()} == kept
    mixed = shared.stored(corpus_pipeline.mix_sources(spark, safe, smoke))
    assert mixed.columns == odd(spark).columns and {r.doc_id for r in mixed.select("doc_id").collect()} <= {4, None, 6}
    packed = corpus_pipeline.pack_sequences(spark, mixed, smoke).collect()
    assert len({(r.sequence_id, r.offset) for r in packed}) == len(packed) and all(len(r.ids) == 4 * r.length for r in packed)
    empty = odd(spark).limit(0)
    for _, stage in corpus_pipeline.STAGES:
        empty = shared.stored(stage(spark, empty, smoke))
    assert empty.count() == 0
