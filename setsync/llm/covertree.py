"""Exact cosine near-duplicates of equally labelled vectors by dual traversal of cover trees.

On the unit sphere cosine >= c means a distance of at most sqrt(2 - 2c). A bounded sample gives the
upper levels: anchors, nested as the radii halve. Every vector descends to its nearest anchor (its
home), and also visits each other cell whose border may be within the link distance. A cell (or, of
a large one, a pair of its chunks) is one group: it builds the lower levels over what it holds and
walks pairs of nodes. Covering radii prune pairs that are too far, accept whole pairs that are near
enough without listing them, and leave the rest to leaves, where the cosine itself decides. A home
vector meets all its neighbours in its cell, so counts need no candidate pairs between tasks, and a
group returns only links that connect what it linked.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components, and rows
with a null label, link with nothing and stand alone; vectors of different lengths never link;
repeated vectors are searched once and count each other; ties keep the smallest id; an empty table
gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setsync.llm.shared import bounded_batches, connected_components, cut, stored, table

COSINE = 0.98
#: Distinct vectors that the upper levels are built from, over all labels, at most; a label of more than one cell sends four for each full cell.
ANCHORS = 4096
#: Distances to anchors that are held at once.
HELD = 1 << 20
#: Home vectors of a cell in one group.
CELL_ROWS = 4000
LEAF = 24
#: Children of a node at most; pairs of points that two nodes compare at once; pairs in one matrix.
FANOUT = 64
SMALL = 1 << 14
DENSE = 1 << 21
SLACK = 1e-9


def unit(rows: np.ndarray) -> np.ndarray:
    return rows / np.sqrt((rows * rows).sum(1))[:, None]


def upper_levels(points: np.ndarray, least: float) -> np.ndarray:
    """Indices of nested centres: at radii 2, 1, 1/2, ... down to ``least``, points not yet within one become centres."""
    centres: list[int] = []
    near = np.full(len(points), np.inf)
    radius = 2.0
    while len(points):
        while len(far := np.flatnonzero(near > radius)):
            centres.append(int(far[0]))
            near = np.minimum(near, np.sqrt(np.maximum(0, 2 - 2 * points @ points[far[0]])))
        if radius <= least:
            break
        radius /= 2
    return np.array(centres, int)


class Node:
    """Points with a centre and their measured covering radius; children halve it, made when first asked for."""

    __slots__ = ("points", "centre", "radius", "made")

    def __init__(self, vectors: np.ndarray, points: np.ndarray):
        self.points, self.centre, self.made = points, vectors[points[0]], None
        gaps = vectors[points] - self.centre
        self.radius = float(np.sqrt((gaps * gaps).sum(1).max()))

    def children(self, vectors: np.ndarray) -> list["Node"]:
        """Covers of half the radius; none for a leaf: few points, coinciding ones, or ones too spread for a cover of ``FANOUT``."""
        if self.made is None:
            self.made = []
            if len(self.points) > LEAF and self.radius > 1e-7:
                parts, left, scale = [], self.points, self.radius / 2
                while len(left) and len(parts) < FANOUT:
                    gaps = vectors[left] - vectors[left[0]]
                    inside = (gaps * gaps).sum(1) <= scale * scale
                    parts.append(left[inside])
                    left = left[~inside]
                if not len(left):
                    self.made = [Node(vectors, p) for p in parts]
        return self.made


def dual_links(vectors: np.ndarray, weights: np.ndarray, homes: np.ndarray, others: np.ndarray, cosine: float = COSINE) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """For each of ``homes`` the weight of ``others`` it links with (itself left out), and links that connect all those found.

    ``homes`` and ``others`` index the unit ``vectors``; they may overlap.
    """
    reach = np.sqrt(2 - 2 * cosine)
    counts = np.zeros(len(vectors), np.int64)
    parent = np.arange(len(vectors))

    def tie(members: np.ndarray) -> None:
        roots = parent[members]
        while len(up := np.flatnonzero(parent[roots] != roots)):
            roots[up] = parent[roots[up]]
        roots = np.unique(roots)
        parent[roots] = roots[0]

    def compare(a: np.ndarray, b: np.ndarray) -> None:
        for at in range(0, len(a), max(1, DENSE // len(b))):
            rows = a[at : at + max(1, DENSE // len(b))]
            near = (vectors[rows] @ vectors[b].T >= cosine) | (rows[:, None] == b[None, :])
            counts[rows] += near @ weights[b]
            for k in np.flatnonzero(near.sum(1) > (rows[:, None] == b[None, :]).any(1)):
                tie(np.append(b[near[k]], rows[k]))

    if len(homes) and len(others):
        work = [(Node(vectors, homes), Node(vectors, others))]
        while work:
            a, b = work.pop()
            gap = float(np.linalg.norm(a.centre - b.centre))
            spread = a.radius + b.radius
            if gap - spread > reach + SLACK:
                continue
            if gap + spread < reach - SLACK:
                counts[a.points] += weights[b.points].sum()
                tie(np.concatenate([a.points, b.points]))
            elif len(a.points) * len(b.points) <= SMALL:
                compare(a.points, b.points)
            elif a.radius >= b.radius and (below := a.children(vectors)):
                work += [(child, b) for child in below]
            elif below := b.children(vectors):
                work += [(a, child) for child in below]
            elif below := a.children(vectors):
                work += [(child, b) for child in below]
            else:
                compare(a.points, b.points)
    # A vector is among its own neighbours where the other side holds it.
    shared = np.intersect1d(homes, others)
    counts[shared] -= weights[shared]
    while (parent[parent] != parent).any():
        parent = parent[parent]
    linked = np.flatnonzero(parent != np.arange(len(vectors)))
    return counts[homes], list(zip(linked.tolist(), parent[linked].tolist()))


def spots_task(anchors: dict, chunks: dict | None, reach: float):
    """Classes ``label, dim, rep, weight, vec`` to the cells they are at home in or visit.

    ``anchors``: unit centres by (label, dim). Vector x visits cell h beside its home c only if the
    plane midway between the two is within ``reach`` of x, for beyond it no vector is at home in h.
    """

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, pd.DataFrame]]:
        for batch in batches:
            for (label, dim), own in batch.to_pandas().groupby(["label", "dim"], sort=False):
                step = max(1, HELD // len(anchors.get((label, dim), (0,))))
                for at in range(0, len(own), step):
                    yield label, dim, own[at : at + step]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for label, dim, own in blocks(batches):
            out = []
            centres = anchors.get((label, dim))
            if centres is None:  # a label of one cell, or one beyond the number of anchors
                home, visits = np.zeros(len(own), np.int64), np.ones((len(own), 1), bool)
            else:
                x = unit(np.stack([np.frombuffer(v, "<f8") for v in own.vec]))
                square = np.maximum(0, 2 - 2 * x @ centres.T)
                home = square.argmin(1)
            if chunks is None:
                cells, sizes = np.unique(home, return_counts=True)
                out.append((np.full(len(cells), label), np.full(len(cells), dim), cells, sizes))
            if chunks is not None and centres is not None:
                between = np.sqrt(np.maximum(1e-300, 2 - 2 * centres[home] @ centres.T))
                visits = (square - square[np.arange(len(x)), home][:, None]) / (2 * between) <= reach + SLACK
                visits[np.arange(len(x)), home] = True
            if chunks is not None:
                rep = own.rep.to_numpy(np.int64)
                rows, cells = np.nonzero(visits)
                many = np.array([chunks.get((label, dim, c), 1) for c in range(visits.shape[1])], np.int64)
                # Of a cell in n chunks, group (i, j) has the home vectors of chunk i and all vectors of chunk j.
                chunk = (rep[rows] * 2_654_435_761 % (1 << 31)) % many[cells]
                at_home = cells == home[rows]
                groups = np.repeat(np.arange(len(rows)), many[cells])
                turn = np.arange(len(groups)) - np.repeat(np.cumsum(many[cells]) - many[cells], many[cells])
                as_home = at_home[groups]
                spots = [(groups, turn, chunk[groups], as_home & (turn == chunk[groups]), np.ones(len(groups), bool))]
                extra = as_home & (turn != chunk[groups])
                spots.append((groups[extra], chunk[groups[extra]], turn[extra], np.ones(extra.sum(), bool), np.zeros(extra.sum(), bool)))
                for g, part, other, is_home, target in spots:
                    n = len(g)
                    out.append((np.full(n, label), np.full(n, dim), cells[g], part, other, is_home, target, rep[rows[g]], own.weight.to_numpy(np.int64)[rows[g]], own.vec.to_numpy()[rows[g]]))
            names = ["label", "dim", "cell", "n"] if chunks is None else ["label", "dim", "cell", "part", "other", "home", "target", "rep", "weight", "vec"]
            types = [pa.int64()] * 4 if chunks is None else [pa.int64()] * 5 + [pa.bool_()] * 2 + [pa.int64()] * 2 + [pa.binary()]
            for cols in out:
                yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, types)], names=names)

    return run


def group_task(cosine: float):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        vectors = unit(np.stack([np.frombuffer(v, "<f8") for v in pdf.vec]))
        homes, others = np.flatnonzero(pdf.home), np.flatnonzero(pdf.target)
        counts, links = dual_links(vectors, pdf.weight.to_numpy(np.int64), homes, others, cosine)
        reps = pdf.rep.to_numpy()
        return pd.DataFrame(
            {
                "a": np.concatenate([reps[homes], reps[[x for x, _ in links]]]).astype(np.int64),
                "b": pd.array([None] * len(homes) + reps[[r for _, r in links]].tolist(), "Int64"),
                "n": np.concatenate([counts, np.zeros(len(links), np.int64)]).astype(np.int64),
            }
        )

    return run


def link_vectors(vectors: DataFrame, cosine: float = COSINE, anchors: int = ANCHORS, cell_rows: int = CELL_ROWS) -> DataFrame:
    """``vec_id, n_links, component_id, kept``: one row for every row of ``vec_id, embedding, label``."""
    bounded_batches(vectors.sparkSession)
    reach = float(np.sqrt(2 - 2 * cosine))
    doubles = F.col("embedding").cast("array<double>")
    finite = F.forall(doubles, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    usable = F.col("label").isNotNull() & doubles.isNotNull() & finite & F.exists(doubles, lambda v: v != 0)
    rows = vectors.select("vec_id", F.col("label").cast("long").alias("label"), doubles.alias("embedding"), F.coalesce(usable, F.lit(False)).alias("usable"))
    rows = stored(rows)
    classes = rows.where("usable").groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight"))
    classes = classes.withColumn("dim", F.size("embedding"))
    # Doubles in native order, eight bytes each, as the kernels read them.
    packed = stored(classes.mapInArrow(pack_task, "label long, dim long, rep long, weight long, vec binary"))
    if not packed.limit(1).count():
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    # A label that fills no more than a cell needs no anchors; of the others the largest get them, so their number is bounded.
    large = packed.groupBy("label", "dim").agg(F.count("*").alias("_n")).where(F.col("_n") > cell_rows).orderBy(F.desc("_n"), "label", "dim").limit(anchors)
    large = cut(large)
    share = max(1, anchors // max(1, large.count()))
    most = W.partitionBy("label", "dim").orderBy(F.xxhash64("rep"), "rep")
    wanted = large.select("label", "dim", F.least(F.lit(share), F.ceil(F.col("_n") / F.lit(cell_rows / 4))).alias("_want"))
    chosen = packed.join(F.broadcast(wanted), ["label", "dim"]).withColumn("_turn", F.row_number().over(most)).where(f"_turn <= {share}").where("_turn <= _want").drop("_turn", "_want")
    centres: dict = {}
    for (label, dim), own in chosen.toPandas().groupby(["label", "dim"]):
        points = unit(np.stack([np.frombuffer(v, "<f8") for v in own.sort_values("rep").vec]))
        centres[(label, dim)] = points[upper_levels(points, reach)]
    spread = packed.mapInArrow(spots_task(centres, None, reach), "label long, dim long, cell long, n long")
    # A row for each cell above ``cell_rows``: at most ``anchors``, but for labels beyond that number.
    sizes = spread.groupBy("label", "dim", "cell").agg(F.sum("n").alias("rows")).where(F.col("rows") > cell_rows).collect()
    chunks = {(r.label, r.dim, r.cell): -(-r["rows"] // cell_rows) for r in sizes}
    spots = packed.mapInArrow(spots_task(centres, chunks, reach), "label long, dim long, cell long, part long, other long, home boolean, target boolean, rep long, weight long, vec binary")
    found = cut(spots.groupBy("label", "dim", "cell", "part", "other").applyInPandas(group_task(cosine), "a long, b long, n long"))
    counts = found.where("b is null").groupBy(F.col("a").alias("rep")).agg(F.sum("n").alias("links"))
    roots = connected_components(found.where("b is not null").select("a", "b"))
    named = counts.join(roots, counts.rep == roots.node, "left").select("rep", "links", F.coalesce("root", "rep").alias("component_id"))
    members = classes.join(named, "rep").select(F.col("label").alias("_l"), F.col("embedding").alias("_e"), (F.col("links") + F.col("weight") - 1).alias("links"), F.col("component_id").alias("component"))
    joined = rows.join(members, F.col("usable") & (F.col("label") == F.col("_l")) & (F.col("embedding") == F.col("_e")), "left")
    component = F.coalesce("component", "vec_id")
    return joined.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def pack_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        vec = [np.array(v, "<f8").tobytes() for v in batch.column("embedding").to_pylist()]
        cols = [batch.column(n).cast(pa.int64()) for n in ("label", "dim", "rep", "weight")]
        yield pa.record_batch([*cols, pa.array(vec, pa.binary())], names=["label", "dim", "rep", "weight", "vec"])


def op2_embedding_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_vectors(table(spark, sf_dir, "embeddings"))
