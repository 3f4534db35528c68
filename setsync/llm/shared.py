"""What the corpus operators share: table access, lineage cuts in the shared folder, connected components."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


#: Rows that a worker gets at once: texts may be long, so a batch of them must stay small.
BATCH_ROWS = 1000


def bounded_batches(spark: SparkSession) -> None:
    """Keeps a Python worker's batch of whole texts small: a run-time setting, lowered for the session (see README)."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


#: What workers keep between tasks, by operator.
KEPT: dict[str, dict] = {}


def lean_worker(name: str) -> None:
    """Workers serve one stage after the other: lets go what other operators kept and gives free memory back to the system."""
    for other, kept in KEPT.items():
        if other != name:
            kept.clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; only where that is unset (tests) a local one."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        context = spark.sparkContext
        known = context._jsc.sc().getCheckpointDir()
        if known.isDefined():
            return known.get()
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="setsync-")
        context.setCheckpointDir(folder)
    return folder


def cut(df: DataFrame) -> DataFrame:
    """Narrow rows, written reliably to the shared folder; Spark's cleaner removes them with the frame."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """Wide rows, written as a Parquet table in the shared folder and read again."""
    path = f"{shared_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.option("parquet.block.size", 32 << 20).parquet(path)  # a writer holds a block in memory
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: A key is heavy with more than this share of all rows, so there are fewer than its inverse of them.
HEAVY_SHARE = 1 / 1000


def join_heavy(rows: DataFrame, per_key: DataFrame, key: str, weight: str, total: int) -> DataFrame:
    """``rows`` joined with ``per_key`` (unique ``key``; ``weight``: rows of the key), heavy keys by broadcast.

    At most ``1 / HEAVY_SHARE`` keys can be heavy, so what is broadcast is bounded whatever the data, and
    no task of the shuffled join gets more than that share for one key.
    """
    heavy = F.col(weight) > max(1, total * HEAVY_SHARE)
    hot = per_key.where(heavy)
    by_broadcast = rows.join(F.broadcast(hot.drop(weight)), key)
    rest = rows.join(F.broadcast(hot.select(key)), key, "left_anti").join(per_key.where(~heavy).drop(weight), key)
    return by_broadcast.unionByName(rest)


#: Edges that one task takes in whole, 16 bytes each.
SMALL_EDGES = 1 << 20


def rooted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``node, root`` of all edges ``u, v`` given: least labels spread along edges and are followed to their own."""
    parts = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
    if not parts:
        return
    u, v = (np.concatenate(x) for x in zip(*parts))
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    u, v = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[u], root[v])
        new = root.copy()
        for end in (root[u], root[v]):
            np.minimum.at(new, end, low)
        while (new[new] != new).any():
            new = new[new]
        if (new == root).all():
            break
        root = new
    yield pa.record_batch([pa.array(nodes), pa.array(nodes[root])], names=["node", "root"])


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """Smallest reachable node of every node that has an edge: ``node``, ``root``.

    Alternates two star contractions until the edge set stops changing (a logarithmic number of
    rounds); each round is two aggregations and two joins over at most the given edges, cut by a
    checkpoint. Only a count and a checksum reach the driver. Up to ``SMALL_EDGES`` edges are settled
    by one task instead. Rows with a null end are ignored, loops and repeated edges are harmless.
    """
    e = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"))
    e = cut(e.where("u is not null and v is not null and u <> v").distinct())
    seen = None
    if e.count() <= SMALL_EDGES:
        return cut(e.coalesce(1).mapInArrow(rooted, "node long, root long"))
    for _ in range(max_rounds):
        mark = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(mark) == seen or not mark[0]:
            break
        seen = tuple(mark)
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).withColumn("m", F.least("u", "m"))
        large = join_heavy(both, low, "u", "n", 2 * mark[0]).where("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = cut(large.distinct())
        low = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
        moved = join_heavy(large, low, "u", "n", 2 * mark[0]).where("v <> m").select(F.greatest("v", "m").alias("u"), F.least("v", "m").alias("v"))
        e = cut(moved.unionByName(low.select("u", F.col("m").alias("v"))).distinct())
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(
        e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    )


def spare_name(df: DataFrame, name: str) -> str:
    """``name``, lengthened until no column of ``df`` has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name
