"""Relevance of all features, redundancy of all features with one chosen, and all pairs of a few features."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import info
from ..plans.dataset import Dataset, SparseDataset
from ..plans.storage import numbered
from . import counts, sparse


def named(ds: Dataset | SparseDataset, df: DataFrame) -> DataFrame:
    """Adds the feature's name."""
    if ds.sparse:
        return df.join(ds.vocabulary.select("feature", "name"), "feature")
    return df.withColumn("name", F.element_at(F.array(*[F.lit(f) for f in ds.features]), F.col("feature") + 1))


def cells(ds: Dataset | SparseDataset, j: str | int | None = None, strategy: str | None = None, **more) -> DataFrame:
    return sparse.contingency(ds, j, **more) if ds.sparse else counts.contingency(ds, j, strategy or "explode", **more)


def relevance(ds: Dataset | SparseDataset, strategy: str | None = None, base: str = "2", **more) -> DataFrame:
    """feature, rel = I(feature; class)."""
    return info.mutual_info(cells(ds, None, strategy, **more), "x", "y", ["feature"], base=base).withColumnRenamed("mi", "rel")


def redundancy(ds: Dataset | SparseDataset, j: str | int, strategy: str | None = None, base: str = "2", **more) -> DataFrame:
    """feature, mi = I(feature; j), cmi = I(feature; j | class)."""
    return info.mi_and_cmi(cells(ds, j, strategy, **more), base=base)


#: Features of which all pairs may be counted in one pass: a row becomes that number squared, halved.
MAX_PAIRED = 200


def pair_cells(ds: Dataset) -> DataFrame:
    """i, k, x, j, y, c of all pairs of features i < k: for few features, in one pass over the rows."""
    if len(ds.features) > MAX_PAIRED:
        raise ValueError(f"all pairs of {len(ds.features)} features; at most {MAX_PAIRED} (count redundancy feature by feature instead)")
    rows = ds.columns()
    entry = F.array(*[F.struct(F.lit(i).alias("f"), F.col(f).alias("v")) for i, f in enumerate(ds.features)])
    pair = F.flatten(F.transform(entry, lambda a: F.transform(F.filter(entry, lambda b: b["f"] > a["f"]), lambda b: F.struct(a["f"].alias("i"), b["f"].alias("k"), a["v"].alias("x"), b["v"].alias("j")))))
    return rows.select(F.explode(pair).alias("p"), "y", "_w").groupBy("p.i", "p.k", "p.x", "p.j", "y").agg(F.sum("_w").alias("c"))


def pair_matrix(ds: Dataset, base: str = "2") -> DataFrame:
    """i, k, mi = I(i; k), cmi = I(i; k | class) for all pairs i < k."""
    keyed = pair_cells(ds).withColumn("feature", F.struct("i", "k"))
    return info.mi_and_cmi(keyed, base=base).select("feature.i", "feature.k", "mi", "cmi")


def rank(ds: Dataset | SparseDataset, strategy: str | None = None) -> DataFrame:
    """All features by relevance alone: step, feature, name, rel.  Ranges of the order are numbered each by a task of its own."""
    rel = named(ds, relevance(ds, strategy)).withColumn("rel", F.round("rel", 12))
    return numbered(rel, [F.desc("rel"), F.asc("feature")], "step", 1).select(F.col("step").cast("int").alias("step"), "feature", "name", "rel")
