"""Contingency cells of all candidates at once: (feature, x, j, y, c).

Five ways that give the same cells for dense data:
packed   rows packed once into blocks, counted with NumPy; see there
explode  one row becomes (feature, code) pairs that carry the chosen code and the class of the same row; the partial hash
         aggregate of each task shrinks them before the only exchange
arrow    each task adds up dense arrays with NumPy and sends its non-empty cells once
gsets    one aggregation with a grouping set for each feature (few features)
blocks   feature-major blocks joined to the blocks of the chosen feature and the class
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.dataset import Dataset
from ..plans.layout import column, to_feature_blocks
from ..plans.storage import saved
from .packed import DenseEngine, column_sets

CELLS = "feature int, x int, j int, y int, c long"


def contingency(ds: Dataset, j: str | None = None, strategy: str = "explode", blocks: DataFrame | None = None) -> DataFrame:
    """feature (place in ds.features), x, j (null without a chosen feature), y, c."""
    match strategy:
        case "explode":
            return _explode(ds, j)
        case "arrow":
            return _arrow(ds, j)
        case "gsets":
            return _grouping_sets(ds, j)
        case "blocks":
            return _blocks(ds, j, blocks)
        case "packed":
            return DenseEngine(ds).cells(ds.features.index(j) if j else None)
    raise ValueError(f"unknown strategy {strategy!r}")


def _chosen(j: str | None):
    return F.col(j).cast("int") if j else F.lit(None).cast("int")


def _explode(ds: Dataset, j: str | None) -> DataFrame:
    rows = ds.columns()
    if j and j not in ds.features:
        rows = ds.only([*ds.features, j]).columns()
    long = rows.select(_chosen(j).alias("j"), "y", "_w", F.posexplode(F.array(*ds.features)).alias("feature", "x"))
    return long.groupBy("feature", "x", "j", "y").agg(F.sum("_w").alias("c"))


def _arrow(ds: Dataset, j: str | None) -> DataFrame:
    """Features in sets whose arrays keep within a budget; each set reads its own columns."""
    cards = ds.cards if not j or j in ds.features else ds.only([*ds.features, j]).cards
    rest = ((cards[j] if j else 1) + 1) * (cards[ds.label] + 1)
    partial = None
    for part in column_sets([(cards[f] + 1) * rest for f in ds.features]):
        one = _arrow_set(ds, j, [ds.features[i] for i in part], part[0], cards)
        partial = one if partial is None else partial.union(one)
    return partial.groupBy("feature", "x", "j", "y").agg(F.sum("c").alias("c"))


def _arrow_set(ds: Dataset, j: str | None, features: list[str], first: int, cards: dict[str, int]) -> DataFrame:
    names = list(dict.fromkeys([*features, *([j] if j else [])]))
    nj, ny = (cards[j] if j else 1) + 1, cards[ds.label] + 1
    sizes = [cards[f] + 1 for f in features]  # the last code of each stands for null

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = [np.zeros(s * nj * ny, np.int64) for s in sizes]

        def codes(c: pa.Array, size: int) -> np.ndarray:
            return np.asarray(c.fill_null(size - 1)).astype(np.int64)

        for batch in batches:
            y, w = codes(batch.column(len(names)), ny), np.asarray(batch.column(len(names) + 1))
            p = codes(batch.column(names.index(j)), nj) if j else np.zeros(batch.num_rows, np.int64)
            rest, plain = p * ny + y, (w == 1).all()
            for i in range(len(features)):
                at = codes(batch.column(i), sizes[i]) * (nj * ny) + rest
                total[i] += np.bincount(at, minlength=len(total[i])) if plain else np.bincount(at, w, len(total[i])).astype(np.int64)
        for i, t in enumerate(total):
            at = np.flatnonzero(t)
            x, p, y = at // (nj * ny), at // ny % nj, at % ny
            columns = [pa.array(np.full(len(at), first + i, np.int32))]
            for v, null in ((x, sizes[i] - 1), (p, nj - 1), (y, ny - 1)):
                columns.append(pa.array(v.astype(np.int32), mask=(v == null) if j or v is not p else np.ones(len(v), bool)))
            yield pa.RecordBatch.from_arrays([*columns, pa.array(t[at])], names=["feature", "x", "j", "y", "c"])

    return ds.only(names).columns().select(*names, "y", "_w").mapInArrow(count, CELLS)


def _grouping_sets(ds: Dataset, j: str | None) -> DataFrame:
    rows = ds.columns() if not j or j in ds.features else ds.only([*ds.features, j]).columns()
    rows = rows.withColumn("_j", _chosen(j))
    keys = [*ds.features, "_j", "y"]
    counted = rows.groupingSets([[f, "_j", "y"] for f in ds.features], *[F.col(k) for k in keys]).agg(F.sum("_w").alias("c"), *[F.grouping(f).alias(f"_g{i}") for i, f in enumerate(ds.features)])
    feature, x = F.lit(None).cast("int"), F.lit(None).cast("int")
    for i, f in enumerate(ds.features):
        feature = F.when(F.col(f"_g{i}") == 0, i).otherwise(feature)
        x = F.when(F.col(f"_g{i}") == 0, F.col(f)).otherwise(x)
    return counted.select(feature.alias("feature"), x.alias("x"), F.col("_j").alias("j"), "y", "c")


def _blocks(ds: Dataset, j: str | None, blocks: DataFrame | None) -> DataFrame:
    """The single columns join on the block; Spark broadcasts them only while they are small.

    Blocks are written first: candidates, chosen feature and class are read apart and must see the same rows in each block.
    """
    blocks = saved(to_feature_blocks(ds), "blocks") if blocks is None else blocks
    joined = blocks.where("feature >= 0").join(column(blocks, -1).withColumnRenamed("codes", "ys"), "block")
    if j:
        joined = joined.join(column(blocks, ds.features.index(j)).withColumnRenamed("codes", "js"), "block")
    else:
        joined = joined.withColumn("js", F.transform("codes", lambda _: F.lit(None).cast("int")))
    cells = joined.select("feature", F.explode(F.arrays_zip("codes", "js", "ys")).alias("e"))
    return cells.select("feature", F.col("e.codes").alias("x"), F.col("e.js").alias("j"), F.col("e.ys").alias("y")).groupBy("feature", "x", "j", "y").agg(F.count("*").alias("c"))


def class_totals(ds: Dataset) -> DataFrame:
    return ds.columns().groupBy("y").agg(F.sum("_w").alias("c"))
