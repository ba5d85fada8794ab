"""Measures: AUC, times, speed-up, extrapolation, data set summaries, agreement and recovery of rankings."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.dataset import Dataset, SparseDataset
from ..plans.storage import saved


def timed(fn: Callable, *args, **kwargs) -> tuple[object, float]:
    began = time.perf_counter()
    return fn(*args, **kwargs), time.perf_counter() - began


def speedup(sequential: float, distributed: float) -> float:
    return sequential / distributed


def extrapolate_linear(points: Sequence[tuple[float, float]], x: float) -> float:
    """The straight line through two points (least squares through more), read at x."""
    n = len(points)
    mx, my = sum(p[0] for p in points) / n, sum(p[1] for p in points) / n
    slope = sum((a - mx) * (b - my) for a, b in points) / sum((a - mx) ** 2 for a, _ in points)
    return my + slope * (x - mx)


def auc(scored: DataFrame, score: str = "score", y: str = "y", weight: str | None = None) -> DataFrame:
    """One row, auc: area under the ROC curve by the rank sum with mid-ranks.  weight: how often a row counts.

    Rows are first counted per distinct score.  The running count needs an order over the scores, which is built in two
    levels, inside ranges and over the few ranges, so that no task sorts all of them.
    """
    one = F.col(weight) if weight else F.lit(1)
    by = scored.groupBy(F.col(score).alias("s")).agg(F.sum(F.when(F.col(y) == 1, one).otherwise(0)).alias("p"), F.sum(F.when(F.col(y) == 1, 0).otherwise(one)).alias("q"))
    ranged = saved(by.repartitionByRange("s").withColumn("part", F.spark_partition_id()), "ranges")  # two readers see the same ranges
    parts = ranged.groupBy("part").agg(F.sum("q").alias("q"), F.min("s").alias("least"))
    below = parts.select("part", F.coalesce(F.sum("q").over(Window.orderBy("least").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("below"))
    inside = F.coalesce(F.sum("q").over(Window.partitionBy("part").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    counted = ranged.withColumn("inside", inside).join(F.broadcast(below), "part")
    won = F.sum(F.col("p") * (F.col("below") + F.col("inside") + F.col("q") / 2))
    return counted.agg((won / (F.sum("p").cast("double") * F.sum("q"))).alias("auc"))


def dataset_summary(ds: Dataset | SparseDataset) -> DataFrame:
    """rows, features, classes, largest class share, density: one row."""
    if ds.sparse:
        per = ds.classes.groupBy("y").agg(F.count("*").alias("c")).agg(F.sum("c").alias("rows"), F.count("*").alias("classes"), (F.max("c") / F.sum("c")).alias("largest_share"))
        nnz = ds.postings.agg(F.count("*").alias("nnz"))
        size = ds.vocabulary.agg(F.count("*").alias("features"))
        one = per.crossJoin(F.broadcast(nnz)).crossJoin(F.broadcast(size))
        return one.select("rows", "features", "classes", "largest_share", (F.col("nnz") / (F.col("rows") * F.col("features"))).alias("density"))
    rows = ds.columns()
    filled = sum((F.when(F.col(f) != 0, 1).otherwise(0) for f in ds.features), F.lit(0))
    per = rows.groupBy("y").agg(F.count("*").alias("c"), F.sum(filled).alias("nnz"))
    n = len(ds.features)
    return per.agg(F.sum("c").alias("rows"), F.lit(n).cast("long").alias("features"), F.count("*").alias("classes"), (F.max("c") / F.sum("c")).alias("largest_share"), (F.sum("nnz") / (F.sum("c") * n)).alias("density"))


def model_size(k: int, n: int) -> float:
    """Share of the features that a model keeps."""
    return k / n


def overlap(a: Sequence[str], b: Sequence[str], k: int | None = None) -> float:
    """Share of the first k names that two rankings have in common."""
    k = k or min(len(a), len(b))
    return len(set(a[:k]) & set(b[:k])) / k


def kendall_distance(a: Sequence[str], b: Sequence[str]) -> int:
    """Pairs of common names that two rankings order differently."""
    place = {x: i for i, x in enumerate(b)}
    order = [place[x] for x in a if x in place]
    return sum(order[i] > order[j] for i in range(len(order)) for j in range(i + 1, len(order)))


def recovery(chosen: Sequence[str], planted: Sequence[str]) -> float:
    """Share of the planted features among the first ones chosen."""
    return len(set(chosen[: len(planted)]) & set(planted)) / len(planted)


def plan_costs(df: DataFrame) -> dict[str, int]:
    """Exchanges, broadcasts and Python steps in a frame's physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {"exchanges": text.count("Exchange hashpartitioning") + text.count("Exchange rangepartitioning") + text.count("Exchange SinglePartition"), "broadcasts": text.count("BroadcastExchange"), "python": text.count("MapInArrow") + text.count("ArrowEvalPython")}
