"""Near copies of texts: SimHash fingerprints within their radius, or five-word shingle sets of a Jaccard similarity.

Texts of equal sets form a class. Least hashes under seeded permutations, ``ROWS`` to a band, name
buckets; what shares a bucket, directly or through others, is one cluster of candidates. All pairs of
a cluster are candidates, and links are made only at a true similarity of ``SIMILARITY`` or more, so
no link is wrong; a pair of similarity s is missed with a chance of (1 - s^ROWS)^BANDS at most (5 in
100,000 at 0.8). The links of ``simhash`` are joined to these, so a group is what either reaches.

Defined cases: null and wordless texts have the empty set and are one class, linked like any other by its fingerprint; texts with fewer words
than a shingle have one shingle, the whole sequence; an empty table gives no rows; rows without an id
stay; of rows that repeat an id, unlike ones are in groups of their own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from setsync.llm.shared import bounded_batches, connected_components, cut, join_heavy
from setsync.llm.simhash import fingerprint, kept_rows, near_links, shingle_hashes, signed, with_smallest

WORDS = 5
SIMILARITY = 0.8
BANDS, ROWS = 25, 5
#: Shingles of one cluster that a task holds; larger clusters are dealt out as pairs of chunks.
HELD = 4 << 20

_DRAWS = np.random.Generator(np.random.PCG64(42)).integers(0, 1 << 63, (2, BANDS * ROWS), np.uint64)
FACTORS, TERMS = (_DRAWS[0] * np.uint64(2) + np.uint64(1))[:, None], _DRAWS[1][:, None]


def shingle_set(text: str | None) -> np.ndarray:
    """Distinct hashes of the shingles, sorted."""
    return np.unique(shingle_hashes(text, WORDS))


def buckets(own: np.ndarray) -> list[int]:
    """One bucket a band; none for the empty set, whose class has no near copies."""
    if not len(own):
        return []
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(own), 4096):
        np.minimum(least, (own[None, at : at + 4096] * FACTORS + TERMS).min(1), out=least)
    rows = least.reshape(BANDS, ROWS)
    return np.array([xxhash.xxh64_intdigest(rows[k].tobytes(), k) for k in range(BANDS)], np.uint64).view(np.int64).tolist()


def class_of(own: np.ndarray) -> int:
    return int(np.array(xxhash.xxh64_intdigest(own.tobytes(), 42), np.uint64).view(np.int64))


SKETCH = T.StructType([T.StructField("fp", T.LongType()), T.StructField("class", T.LongType()), T.StructField("shingles", T.LongType()), T.StructField("buckets", T.ArrayType(T.LongType()))])
SET = T.StructType([T.StructField("class", T.LongType()), T.StructField("own", T.BinaryType())])


@F.pandas_udf(SKETCH)
def sketch_column(text: pd.Series) -> pd.DataFrame:
    rows = []
    for t in text:
        own = shingle_set(t)
        rows.append((signed(fingerprint(t)), class_of(own), len(own), buckets(own)))
    return pd.DataFrame(rows, columns=SKETCH.names)


@F.pandas_udf(SET)
def set_column(text: pd.Series) -> pd.DataFrame:
    rows = []
    for t in text:
        own = shingle_set(t)
        rows.append((class_of(own), own.tobytes()))
    return pd.DataFrame(rows, columns=SET.names)


def cluster_links(sets: dict[int, np.ndarray], similarity: float = SIMILARITY) -> list[tuple[int, int]]:
    """Links that connect what all pairs of the wanted similarity connect: breadth first, at most one per member."""
    if len(sets) < 2:
        return []
    names, sizes = list(sets), np.array([len(s) for s in sets.values()])
    _, ids = np.unique(np.concatenate(list(sets.values())), return_inverse=True)
    starts = np.concatenate([[0], np.cumsum(sizes)])
    owner = np.repeat(np.arange(len(names)), sizes)
    flag = np.zeros(int(ids.max()) + 1, bool)
    waiting, live = np.ones(len(names), bool), np.arange(len(ids))
    out = []
    while waiting.any():
        first = int(np.flatnonzero(waiting)[0])
        queue, waiting[first] = [first], False
        while queue and waiting.any():
            x = queue.pop()
            if 2 * waiting[owner[live]].sum() < len(live):
                live = live[waiting[owner[live]]]
            own = ids[starts[x] : starts[x + 1]]
            flag[own] = True
            common = np.bincount(owner[live], flag[ids[live]], len(names))
            flag[own] = False
            near = np.flatnonzero(waiting & (common >= similarity * (sizes + sizes[x] - common) - 1e-9))
            out += [(names[x], names[y]) for y in near]
            queue += near.tolist()
            waiting[near] = False
    return out


def linking(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links of each cluster, or pair of its chunks, over rows sorted by it."""
    key, held = None, {}

    def flush():
        found = np.array(cluster_links(held), np.int64).reshape(-1, 2)
        return pa.record_batch([pa.array(found[:, 0]), pa.array(found[:, 1])], names=["a", "b"])

    for batch in batches:
        root, low, high, name, own = (batch.column(k).to_pylist() for k in range(5))
        for *at, c, s in zip(root, low, high, name, own):
            if at != key:
                if len(held) > 1:
                    yield flush()
                key, held = at, {}
            held[c] = np.frombuffer(s, np.uint64)
    if len(held) > 1:
        yield flush()


def similar_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", held: int = HELD) -> DataFrame:
    """``doc_id, tie, root, component_id``: every row that has an id, the hash of its text, its group and the smallest id that reaches."""
    bounded_batches(docs.sparkSession)
    docs = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).where("doc_id is not null")
    prints = cut(docs.select("doc_id", F.xxhash64("text").alias("tie"), sketch_column("text").alias("s")).select("doc_id", "tie", "s.*"))
    classes = cut(prints.groupBy("class").agg(F.min(F.struct("doc_id", "tie")).alias("rep"), F.max("shingles").alias("shingles"), F.first("buckets").alias("buckets"), F.count("*").alias("copies")))
    # Equal sets have equal buckets: one row a class is enough. Of a bucket all classes meet its least one.
    spots = classes.select("class", F.explode("buckets").alias("bucket"))
    least = spots.groupBy("bucket").agg(F.min("class").alias("first"), F.count("*").alias("n")).where("n > 1")
    star = join_heavy(spots, least, "bucket", "n", BANDS * classes.count()).where("class <> first")
    clusters = cut(connected_components(star.select("class", "first").distinct(), "class", "first").join(classes, F.col("node") == F.col("class")).select("class", "rep", "shingles", "root"))
    sizes = clusters.groupBy("root").agg(F.ceil(F.sum("shingles") / F.lit(held / 2)).cast("int").alias("chunks"), F.count("*").alias("n"))
    sizes = sizes.withColumn("chunks", F.when(F.col("chunks") <= 2, 1).otherwise(F.col("chunks")))
    placed = join_heavy(clusters, sizes, "root", "n", clusters.count())
    dealt = placed.select("class", "rep", "root", F.pmod(F.xxhash64("class"), F.col("chunks")).cast("int").alias("own_chunk"), F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("other"))
    dealt = dealt.select("class", "root", F.least("own_chunk", "other").alias("low"), F.greatest("own_chunk", "other").alias("high"))
    reps = clusters.select(F.col("rep.doc_id").alias("doc_id"), F.col("rep.tie").alias("tie")).distinct()
    texts = docs.withColumn("tie", F.xxhash64("text")).join(reps, ["doc_id", "tie"], "left_semi")
    sets = texts.select(set_column("text").alias("s")).select("s.*").dropDuplicates(["class"])
    pairs = sets.join(dealt, "class").select("root", "low", "high", "class", "own")
    pairs = pairs.repartition("root", "low", "high").sortWithinPartitions("root", "low", "high")
    # Texts of one set may repeat its shingles unlike often, and so differ in their fingerprints.
    both = cut(prints.select(F.col("fp").alias("a"), F.col("class").alias("b")).distinct())
    links = pairs.mapInArrow(linking, "a long, b long").unionByName(near_links(cut(both.select(F.col("a").alias("fp")).distinct()))).unionByName(both)
    roots = connected_components(links)
    named = cut(classes.join(roots, F.col("class") == F.col("node"), "left").select("class", "copies", "rep.doc_id", F.coalesce("root", "class").alias("root")))
    labels = with_smallest(named, "root", "doc_id").select("class", "root", "component_id", "copies")
    total = classes.agg(F.sum("copies")).first()[0] or 0
    return join_heavy(prints.select("doc_id", "tie", "class"), labels, "class", "copies", total).select("doc_id", "tie", "root", "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group, all columns kept: that of the smallest id; rows without an id stay."""
    return kept_rows(docs, similar_groups(docs, id_col, text_col), id_col, text_col)
