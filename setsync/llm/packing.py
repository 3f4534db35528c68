"""Bounded-space online best-fit packing of token sequences.

A task keeps a fixed number of open bins. A piece goes to the fullest bin that still holds it, found
as the lowest set bit, from the piece's length on, of a bitset keyed by free space; where none fits
and all bins are in use, the fullest one closes. What is open at a task's end is packed once more,
bin by bin, over groups of tasks, so tasks don't each leave a row of part-filled sequences.

Defined cases: a null or empty text is its end token alone; ties and repeated rows are packed as
rows of their own; an empty table gives no rows; texts of any length are cut into full pieces.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsync.llm.shared import bounded_batches, lean_worker, stored, table
from setsync.llm.tokens import chunk_ids

ROOM = 4096
OPEN_BINS = 64
END_ID = 1
#: Tasks whose open bins meet in one task of the second pass.
FAN_IN = 64


class BestFit:
    """Places lengths of 1 to ``room``; ``place`` gives (bin, offset), and ``closed`` names bins that are final."""

    def __init__(self, room: int = ROOM, open_bins: int = OPEN_BINS):
        self.room, self.limit = room, open_bins
        self.bitset, self.by_free = 0, {}
        self.used = self.opened = 0
        self.closed: list[int] = []

    def place(self, length: int) -> tuple[int, int]:
        fits = self.bitset >> length
        if fits:
            free = length + (fits & -fits).bit_length() - 1
            number = self.take(free)
        else:
            if self.used >= self.limit:
                self.closed.append(self.take((self.bitset & -self.bitset).bit_length() - 1))
            free, number = self.room, self.opened
            self.opened += 1
        left = free - length
        if left:
            self.by_free.setdefault(left, []).append(number)
            self.bitset |= 1 << left
            self.used += 1
        else:
            self.closed.append(number)
        return number, self.room - free

    def take(self, free: int) -> int:
        bins = self.by_free[free]
        number = bins.pop()
        if not bins:
            del self.by_free[free]
            self.bitset &= ~(1 << free)
        self.used -= 1
        return number

    def open_now(self) -> dict[int, int]:
        """Free space of each open bin."""
        return {n: free for free, bins in self.by_free.items() for n in bins}


PIECES = "doc_id long, piece int, start long, length long, {ids}, bin long, offset long, open boolean"
#: What stands for a piece's ids: themselves, or their checksum alone, so that they need not be stored.
IDS = {"ids": ("ids binary", pa.binary(), bytes), "crc": ("ids_crc32 long", pa.int64(), zlib.crc32)}
#: Entries of the encoder's caches and bytes of a block of texts: smaller where ids are stored, as in a
#: pipeline, whose executors also hold what earlier stages left and the writers' blocks of ids.
CACHES = {"ids": (100_000, 2 << 20), "crc": (400_000, 4 << 20)}


def pack_task(path: str, room: int, open_bins: int, spell: str = "ids"):
    column, kind, spelled = IDS[spell]

    def made(rows: list[tuple], left_open: bool) -> pa.RecordBatch:
        cols = [*(list(zip(*rows)) or [()] * 7), (left_open,) * len(rows)]
        kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), kind, pa.int64(), pa.int64(), pa.bool_()]
        return pa.record_batch([pa.array(c, k) for c, k in zip(cols, kinds)], names=["doc_id", "piece", "start", "length", column.split()[0], "bin", "offset", "open"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker("packing")
        encoder, fit = chunk_ids(path, *CACHES[spell]), BestFit(room, open_bins)
        base = TaskContext.get().partitionId() << 36
        end = np.array([END_ID], "<u4").tobytes()
        held: dict[int, list[tuple]] = {}  # pieces of open bins: at most ``open_bins * room`` tokens
        for batch in batches:
            done: list[tuple] = []
            for doc, ids in zip(batch.column(0).to_pylist(), encoder.encode_column(batch.column(1))):
                ids += end
                n = len(ids) // 4
                for k, start in enumerate(range(0, n, room)):
                    part = ids[4 * start : 4 * (start + room)]
                    number, offset = fit.place(len(part) // 4)
                    held.setdefault(number, []).append((doc, k, start, len(part) // 4, spelled(part), base + number, offset))
                    while fit.closed:
                        done += held.pop(fit.closed.pop())
            yield made(done, False)
        yield made([row for rows in held.values() for row in rows], True)

    return run


def repack_task(room: int, open_bins: int):
    """Bins ``bin, fill`` placed as wholes: ``bin, into, shift``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fit, into = BestFit(room, open_bins), {}
        for batch in batches:
            bins, shifts, targets = batch.column(0).to_pylist(), [], []
            for number, fill in zip(bins, batch.column(1).to_pylist()):
                at, shift = fit.place(fill)
                targets.append(into.setdefault(at, number))  # a new sequence is named by its first bin
                shifts.append(shift)
            yield pa.record_batch([pa.array(bins, pa.int64()), pa.array(targets, pa.int64()), pa.array(shifts, pa.int64())], names=["bin", "into", "shift"])

    return run


def pack(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", room: int = ROOM, open_bins: int = OPEN_BINS, spell: str = "ids") -> DataFrame:
    """``doc_id, piece, start, length, ids, sequence_id, offset``: every piece with its ids and its place.

    ``spell="crc"`` gives ``ids_crc32`` for ``ids``, taken where the ids are made.

    The first pass is stored (its bins are named by task) and says of each piece whether its bin was still
    open at the task's end. Only those bins are packed again, as wholes, and only their pieces move.
    """
    bounded_batches(docs.sparkSession)
    placed = stored(docs.select(F.col(id_col).cast("long").alias("doc_id"), text_col).mapInArrow(pack_task(path, room, open_bins, spell), PIECES.format(ids=IDS[spell][0])))
    left = placed.where("open")
    fills = left.groupBy("bin").agg(F.sum("length").alias("fill"))
    tasks = left.select(F.countDistinct(F.shiftright("bin", 36))).first()[0]
    # Larger fills first: best-fit wastes least in falling order.
    dealt = fills.repartition(max(1, -(-tasks // FAN_IN)), F.xxhash64("bin")).sortWithinPartitions(F.desc("fill"), "bin")
    moved = dealt.mapInArrow(repack_task(room, open_bins * FAN_IN), "bin long, into long, shift long")
    again = left.join(moved.withColumnRenamed("bin", "from_bin"), F.col("bin") == F.col("from_bin"))
    columns = ["doc_id", "piece", "start", "length", IDS[spell][0].split()[0]]
    return placed.where("not open").select(*columns, F.col("bin").alias("sequence_id"), "offset").unionByName(
        again.select(*columns, F.col("into").alias("sequence_id"), (F.col("offset") + F.col("shift")).alias("offset"))
    )


def op5_bestfit_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), spell="crc")
