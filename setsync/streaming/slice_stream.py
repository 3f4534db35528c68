"""The continuous mode as a stream: slice files arrive, suspects shrink, a marker file says stop.

A slice counts only once all its words are there (they say how many it has, and may lie in any number of
files) and all slices before it have counted (the rule depends on the order): what comes early waits,
copies of words are dropped by their number, and slices after the stop are charged as overshoot.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsync.functions.hashing import DIALECTS
from setsync.operators.slices import SCOPE, build_slices, sized
from setsync.sources.messages import settled, shared_table

SLICE_SCHEMA = "run_id string, shard int, slice int, m long, word_no long, bits long, words long"


def write_slices(elements: DataFrame, path: str, first: int, last: int, phase: int = 1, dialect: str = "fast") -> None:
    """Slices as files partitioned by number; any reader of Parquet can follow them."""
    built = settled(build_slices(elements, first, last, phase, sized(elements), dialect), "built-slices")
    words = built.groupBy("slice").agg(F.count("*").alias("words"))
    built.join(F.broadcast(words), "slice").select(*SCOPE, "slice", "m", "word_no", "bits", "words", F.col("slice").alias("part")).write.mode("append").partitionBy("part").parquet(path)


@dataclass
class StreamState:
    """Next slice, stop, and trace rows (slice, new rejects, m); ``suspects`` is the current frame."""

    suspects: DataFrame
    next_slice: int = 0
    stop: int | None = None
    overshoot: int = 0
    trace: list[tuple[int, int, int]] = field(default_factory=list)


def fold_slice(state: StreamState, words: DataFrame, number: int, cost_bits: float, phase: int, dialect: str = "fast") -> None:
    m = words.agg(F.max("m")).first()[0]
    probes = state.suspects.withColumn("pos", DIALECTS[dialect].below(m, F.col("digest"), phase, number)).withColumn("word_no", F.floor(F.col("pos") / 64))
    met = probes.join(words.select(*SCOPE, "word_no", "bits"), [*SCOPE, "word_no"], "left")
    passes = F.expr("bits is not null and getbit(bits, cast(pmod(pos, 64) as int)) = 1")
    before = state.suspects.count()
    # Suspects go to the shared folder: the state survives its executors.
    state.suspects = met.where(passes).select(state.suspects.columns).checkpoint()
    new = before - state.suspects.count()
    state.trace.append((number, new, m))
    state.next_slice = number + 1
    if new * int(round(cost_bits * 10)) < m * 10:
        state.stop = number


def stream_slices(spark: SparkSession, path: str, suspects: DataFrame, cost_bits: float, phase: int = 1, checkpoint: str | None = None, dialect: str = "fast") -> StreamState:
    """Follows the slice files of one run at ``path`` until the stop rule holds or no file is left.

    Every micro-batch goes to the waiting table; slices that are whole and next in order are folded in. State
    transitions are idempotent by slice number, so a replayed batch changes nothing.
    """
    state = StreamState(suspects)
    waiting = shared_table(spark, "waiting-slices")
    arrived: set[int] = set()

    def kept() -> DataFrame:
        return spark.read.schema(SLICE_SCHEMA).parquet(waiting).where(F.col("slice") >= state.next_slice).dropDuplicates([*SCOPE, "slice", "word_no"])

    def take(batch: DataFrame, _: int) -> None:
        arrived.update(r.slice for r in batch.select("slice").distinct().collect())
        if state.stop is None:
            batch.where(F.col("slice") >= state.next_slice).write.mode("append").parquet(waiting)
            counts = kept().groupBy("slice").agg(F.count("*").alias("n"), F.max("words").alias("words"))
            whole = {r.slice for r in counts.where("words is null or n >= words").collect()}
            while state.stop is None and state.next_slice in whole:
                fold_slice(state, kept().where(F.col("slice") == state.next_slice), state.next_slice, cost_bits, phase, dialect)
        if state.stop is not None:
            state.overshoot = len([k for k in arrived if k > state.stop])

    files = spark.readStream.schema(SLICE_SCHEMA).option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(path)
    query = files.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint or shared_table(spark, "slice-stream")).trigger(availableNow=True).start()
    query.awaitTermination()
    return state
