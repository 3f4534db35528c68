"""Toxicity: a convolutional text classifier trained in numpy.

Words hash into an embedding table; filters of several widths run over a text, the most each reaches
anywhere is its feature, and a logistic layer scores the features. Only the place of each maximum
learns. At scoring, a filter's product with every embedding is tabulated once, so a text costs one
look-up and one addition per word, filter and offset. All labelled rows teach: their words are hashed once,
shards, dealt by a value of the row, are fitted beside each other and meet after every epoch. Thresholds per language are calibrated on the fifth of the labelled
rows that was not fitted, by bins of their scores; they act on the flag alone, never on a score.

Defined cases: null and empty texts have one blank word and so a score; repeated rows score alike;
rows without a label teach nothing, of rows that repeat an id one does; without both classes among the labels all scores are the share
of toxic labels (0 if there are none); a language without labels uses the common threshold.
"""

from __future__ import annotations

import pickle
import struct
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import islice
from zlib import crc32

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from setsync.llm.shared import KEPT, bounded_batches, cut, table

BUCKETS = 1 << 15
SIZE = 16
WIDTHS = (1, 2, 3)
FILTERS = 8
#: Labelled rows for which one more shard is fitted beside the others, and the most shards (each then takes more rows).
SHARD_ROWS = 5000
SHARDS = 16
EPOCHS = 5
RATE = 0.08
HOLD = 5
#: Lengths of the beginnings of a word that are hashed beside it.
STEMS = (4, 5)
SEED = 20
STRIP = ".,;:!?\"'()[]{}|#*$%&<>-_=+/\\"
CACHE = 60_000
BLOCK_WORDS = 100_000
#: Labelled rows of each class from which a language has a threshold of its own.
LEAST_TOXIC = 10


def bucket(part: str) -> int:
    return 1 + crc32(part.encode("utf-8", "surrogatepass")) % (BUCKETS - 1)


class Stems(dict):
    """Buckets of beginnings of words, worked out when first asked for; few words have one of their own."""

    def __missing__(self, stem: str) -> int:
        if len(self) > CACHE:
            self.clear()
        self[stem] = found = bucket(f"{stem}*")
        return found


STEM_BUCKETS = Stems()


def buckets(word: str) -> tuple[int, ...]:
    """Buckets, 1 to ``BUCKETS - 1``, of a word and of its beginnings; bucket 0 is the blank."""
    bare = word.lower().strip(STRIP) or word
    return bucket(bare), *[STEM_BUCKETS[bare[:k]] if len(bare) >= k else 0 for k in STEMS]


#: A word's buckets as bytes; one that has none stands for the blank.
PACKED = struct.Struct(f"<{1 + len(STEMS)}H")


class PackedWords(dict):
    """``buckets`` of words as bytes, worked out when first asked for."""

    def __missing__(self, word: str) -> bytes:
        self[word] = packed = PACKED.pack(*buckets(word))
        return packed


def shorten(known: dict) -> None:
    """Lets go the later half of what was kept: frequent words come early, most later ones never again."""
    for word in list(islice(known, CACHE // 2, None)):
        del known[word]


def word_ids(text: str | None, known: PackedWords) -> bytes:
    """The buckets of each word of a text in turn; a blank for none. ``known`` is shortened when it has grown above ``CACHE``."""
    if len(known) > CACHE:
        shorten(known)
    return b"".join(map(known.__getitem__, (text or "").split())) or bytes(PACKED.size)


@dataclass
class Model:
    """``table``: embeddings; ``filters``: per width an array (offset, size, filters); then the logistic layer."""

    table: np.ndarray
    filters: list[np.ndarray]
    shift: np.ndarray
    weights: np.ndarray
    bias: float
    constant: float | None = None
    thresholds: dict = field(default_factory=dict)

    def kernel(self) -> np.ndarray:
        """All filters' offsets side by side, so one product with a word's vector serves them all."""
        return np.concatenate([f[k] for f in self.filters for k in range(len(f))], 1)


def padded(packed: bytes) -> np.ndarray:
    """A row of buckets for the words, one for each beginning; blanks at the end."""
    ids = np.frombuffer(packed, "<u2").reshape(-1, 1 + len(STEMS)).T
    out = np.zeros((len(ids), ids.shape[1] + max(WIDTHS) - 1), np.intp)
    out[:, : ids.shape[1]] = ids
    return out


def word_vectors(table_: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """The sum of the embeddings of each word's buckets; ``ids``: as ``padded`` gives them."""
    vectors = table_.take(ids[0], axis=0)
    for part in ids[1:]:
        vectors += table_.take(part, axis=0)
    return vectors


@dataclass
class Learner:
    """A model in the making: Adagrad on the logistic loss, one text a step, with the sums of squares it has seen."""

    model: Model
    seen_table: np.ndarray
    seen_filters: list[np.ndarray]
    seen_shift: np.ndarray
    seen_weights: np.ndarray
    seen_bias: float

    @classmethod
    def new(cls, seed: int = SEED) -> Learner:
        rng = np.random.default_rng(seed)
        model = Model(
            rng.normal(0, 0.3, (BUCKETS, SIZE)).astype(np.float32),
            [rng.normal(0, 0.3 / np.sqrt(w), (w, SIZE, FILTERS)).astype(np.float32) for w in WIDTHS],
            np.zeros(FILTERS * len(WIDTHS), np.float32),
            rng.normal(0, 0.1, FILTERS * len(WIDTHS)).astype(np.float32),
            0.0,
        )
        model.table[0] = 0
        full = lambda x: np.full_like(x, 1e-2)
        return cls(model, np.full(BUCKETS, 1e-2, np.float32), [full(f) for f in model.filters], full(model.shift), full(model.weights), 1e-2)

    def step(self, ids: np.ndarray, label: int, scale: float, rate: float = RATE) -> None:
        """``ids``: a text's padded buckets; ``scale``: the weight of its class."""
        model = self.model
        n = ids.shape[1] - max(WIDTHS) + 1
        vectors = word_vectors(model.table, ids)
        reach = model.kernel().T @ vectors.T
        places, tops, row = [], [], 0
        for width in WIDTHS:
            out = reach[row : row + FILTERS, :n]
            for k in range(1, width):
                out += reach[row + k * FILTERS : row + (k + 1) * FILTERS, k : k + n]
            row += width * FILTERS
            at = out.argmax(1)
            places.append(at)
            tops.append(out[np.arange(FILTERS), at])
        top = np.concatenate(tops) + model.shift
        hidden = np.maximum(top, 0)
        score = 1 / (1 + np.exp(-np.clip(hidden @ model.weights + model.bias, -30, 30)))
        error = np.float32((score - label) * scale)
        if abs(error) < 0.01:
            return
        back = error * model.weights * (top > 0)
        step = error * hidden + 1e-4 * model.weights
        self.seen_weights += step**2
        model.weights -= rate * step / np.sqrt(self.seen_weights)
        self.seen_bias += error**2
        model.bias -= rate * error / np.sqrt(self.seen_bias)
        self.seen_shift += back**2
        model.shift -= rate * back / np.sqrt(self.seen_shift)
        for w, (f, seen) in enumerate(zip(model.filters, self.seen_filters)):
            own = back[w * FILTERS : (w + 1) * FILTERS]
            if not own.any():
                continue
            for k in range(len(f)):
                at = places[w] + k
                slope = vectors[at].T * own
                pull = f[k].T * own[:, None]
                seen[k] += slope**2
                f[k] -= rate * slope / np.sqrt(seen[k])
                square, pull = (pull**2).mean(1), -rate * pull
                for part in ids[:, at]:
                    np.add.at(self.seen_table, part, square)
                    np.add.at(model.table, part, pull / np.sqrt(self.seen_table[part])[:, None])
        model.table[0] = 0

    def dense(self) -> list[np.ndarray]:
        """All but the table, as arrays that share the learner's memory where they can."""
        m = self.model
        return [*m.filters, m.shift, m.weights, np.array(m.bias), *self.seen_filters, self.seen_shift, self.seen_weights, np.array(self.seen_bias)]

    def moved(self, before: np.ndarray) -> tuple:
        """What a shard hands over: the table's rows that it changed, and the rest whole."""
        rows = np.flatnonzero(self.seen_table != before)
        return rows.astype(np.int32), self.model.table[rows], self.seen_table[rows], self.dense()

    def meet(self, parts: list[tuple]) -> None:
        """Means over the shards; a row of the table over those that changed it, so rare words keep their pace."""
        m = self.model
        table_, seen, times = np.zeros(m.table.shape), np.zeros(len(m.table)), np.zeros(len(m.table))
        for rows, own, own_seen, _ in parts:
            table_[rows] += own
            seen[rows] += own_seen
            times[rows] += 1
        hit = times > 0
        m.table[hit] = table_[hit] / times[hit, None]
        self.seen_table[hit] = seen[hit] / times[hit]
        mean = [np.mean([p[3][k] for p in parts], 0) for k in range(len(self.dense()))]
        for own, new in zip(self.dense(), mean):
            own[...] = new
        at = len(m.filters) + 2
        m.bias, self.seen_bias = float(mean[at]), float(mean[-1])


def class_scales(counts: dict[int, int]) -> dict[int, float]:
    """Weights of the classes, even in sum."""
    return {c: 0.5 * sum(counts.values()) / max(1, counts.get(c, 0)) for c in (0, 1)}


def back_to_shares(model: Model, counts: dict[int, int]) -> Model:
    """Back from even classes to those of the labels."""
    share = counts[1] / sum(counts.values())
    model.bias += float(np.log(max(1e-6, share) / max(1e-6, 1 - share)))
    return model


def constant(counts: dict[int, int]) -> Model:
    """Without both classes: the share of toxic labels."""
    model = Learner.new().model
    model.constant = counts.get(1, 0) / max(1, sum(counts.values()))
    return model


def fit(texts: list[str | None], labels: list[int], epochs: int = EPOCHS, seed: int = SEED, rate: float = RATE) -> Model:
    """One shard's fit over texts in memory; the class balance is that of ``labels``."""
    counts = {c: sum(int(y) == c for y in labels) for c in (0, 1)}
    if not counts[0] or not counts[1]:
        return constant(counts)
    learner, rng, scale, known = Learner.new(seed), np.random.default_rng(seed), class_scales(counts), PackedWords()
    rows = [padded(word_ids(t, known)) for t in texts]
    for _ in range(epochs):
        for r in rng.permutation(len(rows)):
            learner.step(rows[r], labels[r], scale[int(labels[r])], rate)
    return back_to_shares(learner.model, counts)


def shard_task(shared, scale: dict[int, float], epoch: int):
    """An epoch over one partition of ``ids, toxic``, batch by batch: nothing but a batch is held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        learner, steps = pickle.loads(shared.value), 0
        before = learner.seen_table.copy()
        rng = np.random.default_rng((SEED, epoch, TaskContext.get().partitionId()))
        for batch in batches:
            ids, labels = batch.column(0), batch.column(1).to_pylist()
            for r in rng.permutation(len(labels)).tolist():
                learner.step(padded(ids[r].as_py()), labels[r], scale[labels[r]])
            steps += len(labels)
        if steps:
            yield pa.record_batch([pa.array([pickle.dumps(learner.moved(before))], pa.binary())], names=["part"])

    return run


def fit_shards(rows: DataFrame, counts: dict[int, int], epochs: int = EPOCHS) -> Model:
    """Fits on every row of ``ids, toxic``: each partition goes on from the common model, and their outcomes meet after each epoch."""
    learner, scale, context = Learner.new(), class_scales(counts), rows.sparkSession.sparkContext
    for epoch in range(epochs):
        shared = context.broadcast(pickle.dumps(learner))
        learner.meet([pickle.loads(r.part) for r in rows.mapInArrow(shard_task(shared, scale, epoch), "part binary").collect()])
        shared.unpersist()
    return back_to_shares(learner.model, counts)


class Numbers(dict):
    """Words numbered from 1 as they come."""

    def __missing__(self, word: str) -> int:
        self[word] = number = len(self) + 1
        return number


class Scorer:
    """Scores texts in blocks; keeps each known word's product with every filter, ``CACHE`` words at most."""

    def __init__(self, model: Model):
        self.model = model
        self.kernel = model.kernel()
        self.known = Numbers()
        self.rows = np.zeros((self.kernel.shape[1], 1 << 12), np.float32)  # place 0: the blank


    def learn(self, words: list[str], first: int) -> None:
        """Words that are numbered from ``first`` on."""
        end = first + len(words)
        if end > self.rows.shape[1]:
            rows = np.zeros((len(self.rows), end + end // 2), np.float32)
            rows[:, :first] = self.rows[:, :first]
            self.rows = rows
        vectors = word_vectors(self.model.table, np.frombuffer(b"".join([PACKED.pack(*buckets(w)) for w in words]), "<u2").reshape(len(words), -1).T)
        self.rows[:, first:end] = (vectors @ self.kernel).T

    def block(self, texts: list[list[str]]) -> np.ndarray:
        if len(self.known) > CACHE:
            shorten(self.known)
            self.rows = self.rows[:, : 1 + len(self.known)].copy()
        first, number = len(self.known) + 1, self.known.__getitem__
        m, gap = self.model, max(WIDTHS) - 1
        sizes = np.array([max(1, len(x)) for x in texts])
        starts = np.concatenate([[0], np.cumsum(sizes + gap)[:-1]])
        n = int((sizes + gap).sum())
        flat = np.zeros(n, np.intp)
        for at, words in zip(starts.tolist(), texts):
            flat[at : at + len(words)] = list(map(number, words))
        if len(self.known) >= first:
            self.learn(list(islice(self.known, first - 1, None)), first)
        spans = np.stack([starts, starts + sizes], 1).ravel()
        tops, at = [], 0
        for width in WIDTHS:
            out = np.zeros((FILTERS, n), np.float32)
            for k in range(width):
                out[:, : n - k] += self.rows[at : at + FILTERS].take(flat[k:], axis=1)
                at += FILTERS
            tops.append(np.maximum.reduceat(out, spans, axis=1)[:, ::2])
        hidden = np.maximum(np.ascontiguousarray(np.concatenate(tops).T) + m.shift, 0)
        return 1 / (1 + np.exp(-np.clip(hidden.astype(np.float64) @ m.weights.astype(np.float64) + m.bias, -30, 30)))

    def scores(self, texts) -> np.ndarray:
        if self.model.constant is not None:
            return np.full(len(texts), self.model.constant)
        done, block, held = [], [], 0
        for text in texts:
            block.append((text or "").split())
            held += len(block[-1])
            if held >= BLOCK_WORDS:
                done.append(self.block(block))
                block, held = [], 0
        if block:
            done.append(self.block(block))
        return np.concatenate(done) if done else np.zeros(0)


def calibrate(bins: list) -> float:
    """The threshold of the best F1 over bins ``bin, n, toxic, low, high`` of all scores, in the middle of the gap below it; 0.5 with few labels of a class."""
    by_bin: dict[int, list] = {}
    for r in bins:
        n, toxic, low, high = by_bin.get(r.bin, (0, 0, 1.0, 0.0))
        by_bin[r.bin] = (n + r.n, toxic + r.toxic, min(low, r.low), max(high, r.high))
    falling = [by_bin[k] for k in sorted(by_bin, reverse=True)]
    n, hits = (np.cumsum([r[k] for r in falling]) for k in (0, 1))
    if not len(n) or min(hits[-1], n[-1] - hits[-1]) < LEAST_TOXIC:
        return 0.5
    k = int((2 * hits / (n + hits[-1])).argmax())
    return float((falling[k][2] + (falling[k + 1][3] if k + 1 < len(falling) else 0.0)) / 2)


def score_bins(scored: DataFrame) -> DataFrame:
    """``lang, bin, n, toxic, low, high``: all of ``lang, toxic, score`` in bins of 1/64 of a logit, at most 3,841 a language."""
    inner = F.least(F.greatest(F.col("score"), F.lit(1e-13)), F.lit(1 - 1e-13))
    logit = F.floor(F.log(inner / (1 - inner)) * 64).cast("int")
    return scored.groupBy("lang", logit.alias("bin")).agg(F.count("*").alias("n"), F.sum("toxic").alias("toxic"), F.min("score").alias("low"), F.max("score").alias("high"))


#: Bits of the number of a word of the bitmap that ``likely_labelled`` makes: 2^25 marks, 16 bytes for 64 of them.
MARK_BITS = 19


def likely_labelled(docs: DataFrame, usable: DataFrame) -> DataFrame:
    """``docs`` without most of the rows whose id is not in ``usable``; none that is there is lost.

    Ids are marked in a bitmap of bounded size, so that texts without a label need not move to be joined;
    the more labels there are, the more of those pass and meet the join.
    """
    if docs.schema["doc_id"].dataType != usable.schema["doc_id"].dataType:
        return docs
    place = F.xxhash64("doc_id", F.lit(SEED + 1))
    word, bit = F.shiftrightunsigned(place, 64 - MARK_BITS), place.bitwiseAND(F.lit(63)).cast("int")
    marks = usable.groupBy(word.alias("word")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), bit)).alias("marks"))
    marked = docs.withColumn("word", word).withColumn("bit", bit).join(F.broadcast(marks), "word")
    return marked.where("shiftright(marks, bit) & 1 = 1").drop("word", "bit", "marks")


def labelled_sample(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``doc_id, text, lang, toxic, turn`` of every labelled document but the held-out fifth; nothing is left out."""
    usable = labels.where("toxic in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    usable = usable.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % HOLD != 0).withColumn("turn", F.xxhash64("doc_id", F.lit(SEED)))
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit(None).cast("string")
    rows = likely_labelled(docs.select("doc_id", "text", lang.alias("lang")), usable).join(usable, "doc_id")
    # Of rows that repeat an id one teaches.
    own = F.min_by(F.struct("text", "lang"), F.xxhash64("text")).alias("own")
    return rows.groupBy("doc_id").agg(own, F.max("toxic").alias("toxic"), F.max("turn").alias("turn")).select("doc_id", "own.*", "toxic", "turn")


def worker_ids(texts: list) -> list[bytes | None]:
    known = SCORER.setdefault("words", PackedWords())
    return [word_ids(t, known) if isinstance(t, str) else None for t in texts]


@F.pandas_udf(T.BinaryType())
def ids_of(text: pd.Series) -> pd.Series:
    """``word_ids`` of texts; null for null."""
    return pd.Series(worker_ids(text.tolist()), dtype=object)


def dealt(sample: DataFrame, shards: int) -> DataFrame:
    """``lang, toxic, ids, text`` of a ``labelled_sample``, a partition for each shard: hashed words of the rows to fit, texts of those kept aside.

    A row's shard is a value of its id, so there are as many shards whatever the cluster deals rows into.
    """
    fifth = F.pmod("turn", F.lit(5)) == 0
    shard = F.pmod(F.hash("doc_id"), F.lit(shards))
    rows = sample.select(
        "doc_id", "lang", "toxic", "turn", shard.alias("shard"),
        ids_of(F.when(~fifth, F.coalesce("text", F.lit("")))).alias("ids"), F.when(fifth, F.coalesce("text", F.lit(""))).alias("text"),
    )
    return rows.repartitionById(shards, "shard").sortWithinPartitions("turn", "doc_id").select("lang", "toxic", "ids", "text")


def train(docs: DataFrame, labels: DataFrame) -> Model:
    """Fits on four fifths of all labelled rows and calibrates the flags' thresholds on all of the rest.

    The rows are dealt by id into shards, whose number follows from the labels, so a fit depends on the
    rows alone and not on the cluster; they are stored once and every epoch reads them from there.
    """
    bounded_batches(docs.sparkSession)
    shards = max(1, min(SHARDS, -(-labels.where("toxic is not null").count() // SHARD_ROWS)))
    rows = cut(dealt(labelled_sample(docs, labels), shards))
    kept, aside = rows.where("ids is not null"), rows.where("ids is null")
    counts = {r.toxic: r["count"] for r in kept.groupBy("toxic").count().collect()}
    model = fit_shards(kept.select("ids", "toxic"), counts) if len(counts) == 2 else constant(counts)
    bins = score_bins(aside.select("lang", "toxic", score_column(model, docs.sparkSession)(F.col("text")).alias("score"))).collect()
    model.thresholds = {None: calibrate(bins)}
    for lang in {r.lang for r in bins if r.lang is not None}:
        own = [r for r in bins if r.lang == lang]
        toxic = sum(r.toxic for r in own)
        if toxic >= LEAST_TOXIC and sum(r.n for r in own) - toxic >= LEAST_TOXIC:
            model.thresholds[lang] = calibrate(own)
    return model


SCORER = KEPT.setdefault("toxicity", {})


def score_column(model: Model, spark: SparkSession):
    """A column function from texts to scores; workers tabulate the broadcast model once."""
    bounded_batches(spark)
    shared = spark.sparkContext.broadcast(model)

    @F.pandas_udf(T.DoubleType())
    def score(text: pd.Series) -> pd.Series:
        return pd.Series(worker_scorer(shared).scores(text.tolist()), dtype=float)

    return score


def worker_scorer(shared) -> Scorer:
    if SCORER.get("key") != id(shared.value):
        SCORER.pop("words", None)
        SCORER.update(key=id(shared.value), model=shared.value, scorer=Scorer(shared.value))
    return SCORER["scorer"]


def flagged(score, lang, model: Model):
    """Whether a score reaches its language's threshold."""
    bound = F.lit(model.thresholds[None])
    for name, least in sorted((k, v) for k, v in model.thresholds.items() if k is not None):
        bound = F.when(lang == name, F.lit(least)).otherwise(bound)
    return score >= bound


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % HOLD == 0
    scored = docs.select("doc_id", "lang", held.alias("held_out"), score_column(model, spark)(F.col("text")).alias("score"))
    return scored.select("doc_id", "held_out", "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), flagged(F.col("score"), F.col("lang"), model).alias("flagged"))
