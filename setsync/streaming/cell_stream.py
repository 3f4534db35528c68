"""Cells kept up to date by a change feed, and windowed reconciliation of event streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsync.functions.hashing import Fast
from setsync.operators.cells import cell_positions, maintain_cells
from setsync.sources.messages import CELLS, shared_table

CHANGES = "run_id string, side int, shard int, digest long, change int"


def follow_changes(spark: SparkSession, path: str, start: DataFrame, high: int) -> DataFrame:
    """Folds a feed of inserts and deletes (files at ``path``) into a cell prefix, batch by batch.

    Versions of the prefix are tables in the shared folder named by their batch, so a batch that is
    replayed writes the same version again.
    """
    folder = shared_table(spark, "cell-versions")
    state = {"path": f"{folder}/start"}
    start.write.parquet(state["path"])

    def fold(batch: DataFrame, number: int) -> None:
        new = f"{folder}/batch-{number}"
        if state["path"] == new:
            return
        before = spark.read.schema(CELLS).parquet(state["path"])
        maintain_cells(before, batch, high).write.mode("overwrite").parquet(new)
        state["path"] = new

    feed = spark.readStream.schema(CHANGES).option("maxFilesPerTrigger", 1).parquet(path)
    feed.writeStream.foreachBatch(fold).option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(CELLS).parquet(state["path"])


def windowed_cells(events: DataFrame, cells: int, every: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Difference cells of each time window of a two-sided event stream: ``run_id, cell, id_xor, check_xor, cnt``.

    ``events``: ``ts, side, event_id``; works on streams (rows past the watermark are dropped) and
    tables alike. A window whose cells are all empty needs no reconciliation.
    """
    if events.isStreaming:
        events = events.withWatermark("ts", late)
    window = F.window("ts", every, slide) if slide else F.window("ts", every)
    rows = events.withColumn("digest", Fast.digest(F.col("event_id").cast("string"))).withColumn("cell", F.explode(cell_positions(F.col("digest"), cells)))
    sums = rows.groupBy(window, "cell").agg(F.bit_xor("digest").alias("id_xor"), F.bit_xor(Fast.check(F.col("digest"))).alias("check_xor"), F.sum(F.col("side").cast("long")).alias("cnt"))
    return sums.select(F.date_format("window.start", "yyyy-MM-dd'T'HH:mm").alias("run_id"), "cell", "id_xor", "check_xor", "cnt")


def session_sizes(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Elements and signed gap by user session: sessions whose gap is not 0 surely differ."""
    grouped = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"), F.sum(F.col("side").cast("long")).alias("gap"))
    return grouped.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "gap")


def latest_state(changes: DataFrame, key: str, at: str) -> DataFrame:
    """Each key's last row not after ``at``: the replica as of its last synchronisation."""
    from pyspark.sql import Window as W

    last = F.row_number().over(W.partitionBy(key).orderBy(F.desc("ts"), F.desc("event_id")))
    return changes.where(F.col("ts") <= F.lit(at).cast("timestamp")).withColumn("_r", last).where("_r = 1").drop("_r")
