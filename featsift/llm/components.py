"""Connected components by local contraction and alternating large-star and small-star rounds on an edge table.

Edges are dealt evenly to tasks of a bounded number each, and a task replaces its own by stars around the smallest id of
each of their groups.  Where all edges fit one such task, that is the answer; else star rounds follow, until every group
is a star.  Minima are taken with partial aggregation.  The edges of a node then look its minimum up: nodes with a large
share of all edges are few and broadcast, so their edges stay where they are; the others join by key.  Rounds are written
to the shared folder, which ends their lineage.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import looked_up, parts_for, saved

#: Edges that one task contracts.
EDGES_AT_ONCE = 500_000


def stars_of(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges from every node to the smallest of its group, by hooking roots to smaller ones and jumping pointers."""
    ids, place = np.unique(np.concatenate((u, v)), return_inverse=True)
    a, b = place[: len(u)], place[len(u) :]
    label = np.arange(len(ids))
    while True:
        new = label.copy()
        least = np.minimum(label[a], label[b])
        np.minimum.at(new, label[a], least)
        np.minimum.at(new, label[b], least)
        while (jumped := new[new]).tobytes() != new.tobytes():
            new = jumped
        if (new == label).all():
            break
        label = new
    far = np.flatnonzero(label != np.arange(len(ids)))
    return ids[far], ids[label[far]]


def _contracted(edges: DataFrame, parts: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [(np.asarray(b.column(0)), np.asarray(b.column(1))) for b in batches if b.num_rows]
        if held:
            u, v = stars_of(*(np.concatenate(x) for x in zip(*held)))
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])

    return edges.select("u", "v").repartition(parts).mapInArrow(run, "u long, v long")


def _large_star(edges: DataFrame, n: int) -> DataFrame:
    both = edges.union(edges.select("v", "u"))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("n"))
    return looked_up(both.where("v > u"), least, ["u"], ["m"], "n", 2 * n).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame, n: int) -> DataFrame:
    least = edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
    moved = looked_up(edges, least, ["u"], ["m"], "n", n).where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def _settled(edges: DataFrame) -> bool:
    """Whether every node has one edge, to a node that has none: each group is a star around its smallest id."""
    often = edges.groupBy("u").agg(F.count("*").alias("n"))
    wrong = often.where("n > 1").select("u").union(often.join(edges.select(F.col("v").alias("u")).distinct(), "u", "left_semi").select("u"))
    return not wrong.limit(1).count()


def connected_components(edges: DataFrame, a: str = "u", b: str = "v") -> DataFrame:
    """(node, component): the smallest id reachable, for every node that some edge joins to another one.

    Edges may repeat and go either way; those with a null or equal ends are ignored.  No edges: no rows.
    """
    work = edges.where(f"{a} != {b}").select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    work = saved(work, "edges")
    while True:
        n = work.count()
        parts = parts_for(n, EDGES_AT_ONCE, 1)
        work = _contracted(work, parts)
        work = saved(work if parts == 1 else work.distinct(), "edges")
        if parts == 1 or _settled(work):
            break
        n = work.count()
        star = saved(_large_star(work, n), "edges")
        work = saved(_small_star(star, n), "edges")
    roots = work.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return work.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots)
