"""Context-triggered piecewise hashing: fingerprints of texts that survive local edits.

A rolling hash over seven bytes ends a chunk wherever it meets the block size; a chunk adds one letter
to the signature. The block size is the first of 3, 6, 12, ... that keeps a text near 64 chunks, and a
second signature is made at twice that size, so texts whose sizes differ by a factor of two still
compare. Likeness is the edit similarity (insertions and deletions) of two signatures at one block
size, and 0 where long signatures have no run of letters in common.

Defined cases: null is the empty text, whose signatures are empty; equal fingerprints are alike 1;
ties on the id are ordered by text; the document after the last is the first; a single document
follows itself; repeated rows are documents of their own; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from setsync.llm.shared import bounded_batches, table

WINDOW = 7
LEAST_BLOCK = 3
LETTERS = 64
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
#: Signatures from this length on must share a run of ``RUN`` letters.
LONG, RUN = 12, 4
#: Powers that a worker keeps; longer texts make their own.
KEPT_POWERS = 1 << 20
MULTIPLIER = 0x9E3779B97F4A7C15
FACTORS = np.array([pow(2_654_435_761, k, 1 << 32) | 1 for k in range(WINDOW)], np.uint32)


def powers(size: int) -> tuple[np.ndarray, np.ndarray]:
    """``made_powers``, kept for texts of usual length only."""
    return made_powers(size) if size <= KEPT_POWERS else made_powers.__wrapped__(size)


@lru_cache(maxsize=1)
def made_powers(size: int) -> tuple[np.ndarray, np.ndarray]:
    """The multiplier's powers and those of its inverse, modulo 2^64."""
    out = []
    for factor in (MULTIPLIER, pow(MULTIPLIER, -1, 1 << 64)):
        steps = np.full(size, factor, np.uint64)
        steps[0] = 1
        out.append(np.multiply.accumulate(steps))
    return tuple(out)


def rolling(raw: np.ndarray) -> np.ndarray:
    """A 32-bit mix of the seven bytes that end at each place (fewer at the start)."""
    out = np.zeros(len(raw), np.uint32)
    wide = raw.astype(np.uint32) + np.uint32(1)
    for k in range(min(WINDOW, len(raw))):
        out[k:] += FACTORS[k] * wide[: len(raw) - k]
    out ^= out >> np.uint32(15)
    out *= np.uint32(0x2C1B3C6D)
    out ^= out >> np.uint32(12)
    return out


def signature(prefix: np.ndarray, inverse: np.ndarray, ends: np.ndarray, most: int) -> str:
    """Letters of the chunks that end at ``ends``; the last of ``most`` takes all that is left."""
    total = len(prefix) - 1
    ends = ends[: most - 1]
    bounds = np.concatenate([[0], ends, [total]]) if not len(ends) or ends[-1] != total else np.concatenate([[0], ends])
    sums = (prefix[bounds[1:]] - prefix[bounds[:-1]]) * inverse[bounds[:-1]]
    sums ^= sums >> np.uint64(29)
    sums *= np.uint64(0xBF58476D1CE4E5B9)
    return "".join([ALPHABET[k] for k in (sums >> np.uint64(58)).tolist()])


def fingerprint(text: str | None) -> str:
    raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
    n = len(raw)
    if not n:
        return f"{LEAST_BLOCK}::"
    forward, inverse = powers(1 << max(16, n.bit_length()))
    prefix = np.zeros(n + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * forward[:n], out=prefix[1:])
    rolled = rolling(raw)
    block = LEAST_BLOCK
    while block * LETTERS < n:
        block *= 2
    while True:
        ends = np.flatnonzero(rolled % np.uint32(block) == block - 1) + 1
        if len(ends) >= LETTERS // 2 or block == LEAST_BLOCK:
            break
        block //= 2
    coarse = ends[rolled[ends - 1] % np.uint32(2 * block) == 2 * block - 1]
    return f"{block}:{signature(prefix, inverse, ends, LETTERS)}:{signature(prefix, inverse, coarse, LETTERS // 2)}"


def common_letters(a: str, b: str) -> int:
    """Length of the longest common subsequence, a row of bits at a time."""
    places: dict[str, int] = {}
    for k, c in enumerate(a):
        places[c] = places.get(c, 0) | 1 << k
    full = (1 << len(a)) - 1
    row = full
    for c in b:
        hit = row & places.get(c, 0)
        row = ((row + hit) | (row - hit)) & full
    return len(a) - row.bit_count()


def signature_likeness(a: str, b: str) -> float:
    if a == b:
        return 1.0
    if not a or not b:
        return 0.0
    if min(len(a), len(b)) >= LONG:
        grams = {a[k : k + RUN] for k in range(len(a) - RUN + 1)}
        if not any(b[k : k + RUN] in grams for k in range(len(b) - RUN + 1)):
            return 0.0
    return 2 * common_letters(a, b) / (len(a) + len(b))


def likeness(a: str | None, b: str | None) -> float:
    """0 to 1; fingerprints whose block sizes are not equal or a factor of two apart are alike 0."""
    if a is None or b is None:
        return 0.0
    if a == b:
        return 1.0
    (x, a1, a2), (y, b1, b2) = a.split(":"), b.split(":")
    x, y = int(x), int(y)
    if x == y:
        return max(signature_likeness(a1, b1), signature_likeness(a2, b2) if a2 and b2 and len(a2) >= LONG and len(b2) >= LONG else 0.0)
    if x == 2 * y:
        return signature_likeness(a1, b2)
    if y == 2 * x:
        return signature_likeness(a2, b1)
    return 0.0


@F.pandas_udf(T.StringType())
def fingerprint_column(text: pd.Series) -> pd.Series:
    return pd.Series([fingerprint(t) for t in text], dtype=object)


@F.pandas_udf(T.DoubleType())
def likeness_column(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([likeness(x, y) for x, y in zip(a, b)], dtype=float)


def edited(text: str, following: str) -> str:
    """The last half of the code points gives way to as many of the next text's first, or all it has."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def compare_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows ``bucket, follows, doc_id, text`` in order: each row of a bucket against the one after it."""
    held = None

    def row(doc, text, own, nxt, nxt_print):
        new = edited(text, nxt)
        changed = fingerprint(new)
        return (doc, len(text), hashlib.sha256(new.encode("utf-8", "surrogatepass")).hexdigest(), own, changed, likeness(own, changed), likeness(own, nxt_print))

    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
    for batch in batches:
        rows = []
        for bucket, follows, doc, text in zip(*(c.to_pylist() for c in batch.columns)):
            if follows and (held is None or held[0] != bucket):
                continue  # a second row that ties with the first one of the next bucket
            text = text or ""
            own = fingerprint(text)
            if held is not None:
                rows.append(row(*held[1:], text, own))
            held = None if follows else (bucket, doc, text, own)
        cols = list(zip(*rows)) or [()] * 7
        yield pa.record_batch([pa.array(c, k) for c, k in zip(cols, kinds)], names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])


def with_next(docs: DataFrame, id_col: str, text_col: str, buckets: int) -> DataFrame:
    """``bucket, follows, doc_id, text`` in order of the id within ranges, each range ended by the next one's first row.

    The driver sees the bounds and the first id of at most ``buckets`` ranges.
    """
    bounded_batches(docs.sparkSession)
    lowest = F.lit(-(1 << 63))
    key = F.coalesce(F.col(id_col).cast("long"), lowest)
    ids = docs.select(key.alias("key"))
    cuts = ids.select(F.percentile_approx("key", [k / buckets for k in range(1, buckets)] or [0.5], 20_000)).first()[0] or []
    bounds = np.unique(np.array(cuts if buckets > 1 else [], np.int64))

    @F.pandas_udf(T.LongType())
    def bucket_of(k: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(bounds, k.to_numpy(np.int64), side="left").astype(np.int64))

    firsts = {r.bucket: r.first_key for r in ids.select("key", bucket_of("key").alias("bucket")).groupBy("bucket").agg(F.min("key").alias("first_key")).collect()}
    order = sorted(firsts)
    before = {b: order[k - 1] for k, b in enumerate(order)}

    @F.pandas_udf(T.ArrayType(T.LongType()))
    def spots(k: pd.Series) -> pd.Series:
        keys = k.to_numpy(np.int64)
        own = np.searchsorted(bounds, keys, side="left").tolist()
        # b: the row itself; -1 - b: the row that ends bucket b.
        return pd.Series([[b, -1 - before[b]] if firsts.get(b) == x else [b] for b, x in zip(own, keys.tolist())], dtype=object)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), key.alias("key"))
    rows = rows.withColumn("spot", F.explode(spots("key")))
    follows = F.col("spot") < 0
    placed = rows.select(F.when(follows, -1 - F.col("spot")).otherwise(F.col("spot")).alias("bucket"), follows.alias("follows"), "doc_id", "text")
    return placed.repartition("bucket").sortWithinPartitions("bucket", "follows", "doc_id", "text")


def fingerprints_with_edit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", buckets: int | None = None) -> DataFrame:
    """Every document's fingerprint, its edited text's, and how near both and the next document's are."""
    if buckets is None:
        buckets = 4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return with_next(docs, id_col, text_col, buckets).mapInArrow(compare_task, OUT)


def op7_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints_with_edit(table(spark, sf_dir, "documents"))
