"""What selection is compared with: one-core selection, other filters, random features and none at all."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.criteria import ArrayOps, Criterion, get_criterion
from ..functions.info import cube_information
from ..plans.dataset import Dataset, SparseDataset
from ..plans.storage import numbered
from .counts import contingency
from .relevance import named

#: Columns that the forest assembles into one vector at most.
MAX_FOREST = 5_000
#: Bytes of packed codes that the driver fetches at once.
PART_BYTES = 16 << 20
#: Rows that the one-core baseline takes into memory at most: 11 bytes each with ten features.
MAX_ROWS = 50_000_000


class Columns:
    """Codes in memory, in the smallest type that holds them, as pieces of rows: counting never widens more than a piece."""

    PIECE = 1 << 18

    def __init__(self, pieces: list[list[np.ndarray]], weights: list[np.ndarray] | None = None):
        """pieces: the columns of some rows, the class last; weights: how often each row counts."""
        self.pieces, self.weights = pieces, weights or [None] * len(pieces)
        tops = [[int(c.max(initial=0)) for c in piece] for piece in pieces]
        self.sizes = [max(t) + 1 for t in zip(*tops)]

    @staticmethod
    def small(codes: np.ndarray) -> np.ndarray:
        if codes.min(initial=0) < 0:
            raise ValueError("codes must be 0 or more")
        return codes.astype(np.min_scalar_type(int(codes.max(initial=0))))

    @classmethod
    def of(cls, columns: list[np.ndarray], weight: np.ndarray | None = None) -> Columns:
        columns = [cls.small(c) for c in columns]
        at = [slice(a, a + cls.PIECE) for a in range(0, max(len(columns[-1]), 1), cls.PIECE)]
        return cls([[c[s] for c in columns] for s in at], None if weight is None else [weight[s] for s in at])

    def pair(self, i: int, j: int | None) -> tuple[float, float]:
        """I(i; j) and I(i; j | class); without j, I(i; class)."""
        nj, ny = 1 if j is None else self.sizes[j], self.sizes[-1]
        total = np.zeros(self.sizes[i] * nj * ny, np.int64)
        for piece, w in zip(self.pieces, self.weights):
            at = piece[i].astype(np.intp)
            if j is not None:
                at = at * nj + piece[j]
            at = at * ny + piece[-1]
            total += np.bincount(at, minlength=len(total)) if w is None else np.rint(np.bincount(at, w, len(total))).astype(np.int64)
        cube = total.reshape(self.sizes[i], nj, ny)
        return cube_information(cube.transpose(0, 2, 1) if j is None else cube)


def one_core(columns: Columns, features: list[str], k: int, criterion: str | Criterion = "mrmr", **weights) -> list[dict]:
    """The same selection on one core over rows in memory: step, feature, name, score, rel."""
    crit = get_criterion(criterion, **weights)
    n = len(features)
    rel = np.array([columns.pair(i, None)[0] for i in range(n)])
    acc = {a: np.full(n, f.init) for a, f in crit.folds.items()}
    open_, out = np.ones(n, bool), []
    while len(out) < min(k, n):
        s = np.asarray(crit.score(ArrayOps, rel, acc, len(out)), np.float64)
        best = int(np.argmax(np.where(open_, np.round(s, 12), -np.inf)))
        out.append({"step": len(out) + 1, "feature": best, "name": features[best], "score": float(round(s[best], 12)), "rel": float(rel[best])})
        open_[best] = False
        if crit.folds and len(out) < min(k, n):
            for i in np.flatnonzero(open_):
                mi, cmi = columns.pair(i, best)
                for a, f in crit.folds.items():
                    acc[a][i] = f.combine(ArrayOps, acc[a][i], mi, cmi)
    return out


def sequential_select(pdf: pd.DataFrame, features: list[str], label: str, k: int, criterion: str | Criterion = "mrmr", **weights) -> list[dict]:
    """The selection on one core over the rows of a pandas frame."""
    return one_core(Columns.of([pdf[f].to_numpy(np.int64) for f in [*features, label]]), features, k, criterion, **weights)


def _blocks(ds: Dataset) -> DataFrame:
    """rows, bytes of the width of a code, codes: blocks of rows, column by column and the class last."""
    columns = [*ds.features, "y"]

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if any(c.null_count for c in batch.columns):
                raise ValueError("the one-core baseline has no code for null")
            codes = [Columns.small(np.asarray(c)) for c in batch.columns]
            kind = np.result_type(*codes)
            packed = b"".join(c.astype(kind).tobytes() for c in codes)
            yield pa.RecordBatch.from_arrays([pa.array([batch.num_rows]), pa.array([kind.str]), pa.array([packed], pa.binary())], names=["rows", "kind", "codes"])

    return ds.columns().select(*columns).mapInArrow(pack, "rows long, kind string, codes binary")


def sequential(ds: Dataset, k: int, criterion: str | Criterion = "mrmr", max_rows: int = MAX_ROWS, **weights) -> list[dict]:
    """One-core selection of a data set whose rows fit into the driver; more rows are refused, not cut.

    Tasks pack the codes to a byte each (more for large ones) and the driver takes one partition after the other, so a
    row of ten features costs it 11 bytes.
    """
    if ds.n > max_rows:
        raise MemoryError(f"{ds.n} rows don't fit the one-core baseline ({max_rows})")
    width, pieces = len(ds.features) + 1, []
    parts = max(1, ds.n * width // PART_BYTES)
    for r in _blocks(ds).repartition(parts).toLocalIterator():
        codes = np.frombuffer(r["codes"], r["kind"]).reshape(width, r["rows"])
        pieces.append(list(codes))
    if not pieces:
        pieces = [[np.zeros(0, np.uint8)] * width]
    return one_core(Columns(pieces), ds.features, k, criterion, **weights)


def all_features(ds: Dataset) -> list[str]:
    return list(ds.features)


def chi_square(ds: Dataset, k: int) -> DataFrame:
    """step, name, chi2 of the k features with the largest statistic of independence from the class."""
    cells = contingency(ds).select("feature", "x", "y", "c")
    fx = cells.groupBy("feature", "x").agg(F.sum("c").alias("cx"))
    fy = cells.groupBy("feature", "y").agg(F.sum("c").alias("cy"))
    n = cells.groupBy("feature").agg(F.sum("c").cast("double").alias("n"))
    # empty cells count too: sum (o - e)^2 / e = n (sum o^2 / (cx cy) - 1)
    joined = cells.join(fx, ["feature", "x"]).join(fy, ["feature", "y"]).join(n, "feature")
    term = F.col("c").cast("double") * F.col("c") / (F.col("cx").cast("double") * F.col("cy"))
    stat = joined.groupBy("feature").agg((F.first("n") * (F.sum(term) - 1)).alias("chi2"))
    best = named(ds, stat).withColumn("chi2", F.round("chi2", 6)).orderBy(F.desc("chi2"), "feature").limit(k)
    return numbered(best, [F.desc("chi2"), F.asc("feature")], "step", 1).select("step", "name", "chi2")


def forest_importance(ds: Dataset, k: int, trees: int = 20, depth: int = 5, seed: int = 7) -> DataFrame:
    """step, name, importance by a random forest: the embedded method among the baselines."""
    if len(ds.features) > MAX_FOREST:
        raise ValueError(f"{len(ds.features)} columns; at most {MAX_FOREST}")
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler

    rows = VectorAssembler(inputCols=ds.features, outputCol="v").transform(ds.columns().select(*ds.features, F.col("y").cast("double").alias("y")))
    model = RandomForestClassifier(featuresCol="v", labelCol="y", numTrees=trees, maxDepth=depth, maxBins=max(32, *ds.cards.values()), seed=seed).fit(rows)
    order = sorted(enumerate(model.featureImportances.toArray()), key=lambda x: (-x[1], x[0]))[:k]
    return ds.df.sparkSession.createDataFrame([(s + 1, ds.features[i], float(v)) for s, (i, v) in enumerate(order)], "step int, name string, importance double")


def random_features(features: list[str], k: int, seed: int = 7) -> list[str]:
    """k features in an order that only their place and the seed decide."""
    key = lambda i: ((i + 1) * 48_271 + seed * 69_621) * 16_807 % 2_147_483_647 % 1_000_003
    return [features[i] for i in sorted(range(len(features)), key=lambda i: (key(i), i))[:k]]


def random_names(ds: Dataset | SparseDataset, k: int, seed: int = 7) -> list[str]:
    """The same order on a vocabulary, which stays a table."""
    key = ((F.col("feature") + 1) * F.lit(48_271) + F.lit(seed * 69_621)) * F.lit(16_807) % F.lit(2_147_483_647) % F.lit(1_000_003)
    return [r["name"] for r in ds.vocabulary.orderBy(key, "feature").limit(k).collect()] if ds.sparse else random_features(list(ds.features), k, seed)
