"""Contingency cells of sparse data: only non-zero codes are counted, the cells with zeros follow from totals.

For a chosen feature p, rows in which p isn't 0 are all that need counting.  The other cells are differences:
c(x,0,y) = c(x,.,y) - sum_j c(x,j,y), c(0,j,y) = c(.,j,y) - sum_x c(x,j,y), and c(0,0,y) is what is left of c(y).  All
terms are signed rows of one union, added up by one aggregation; features that never meet p take part with their
totals alone.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.dataset import SparseDataset


def feature_totals(ds: SparseDataset) -> DataFrame:
    """feature, x (not 0), y, c."""
    return ds.postings.groupBy("feature", F.col("code").alias("x"), "y").agg(F.count("*").alias("c"))


def class_totals(ds: SparseDataset) -> DataFrame:
    return ds.classes.groupBy("y").agg(F.count("*").alias("c"))


def frequency_map(ds: SparseDataset, j: int) -> DataFrame:
    """j (not 0), y, c of one feature."""
    return ds.postings.where(F.col("feature") == j).groupBy(F.col("code").alias("j"), "y").agg(F.count("*").alias("c"))


def met_cells(ds: SparseDataset, j: int) -> DataFrame:
    """feature, x, j, y, c with x and j not 0: rows of the chosen feature meet the postings of the same rows.

    Spark broadcasts the chosen feature's rows while they are small and joins by row id beyond that.
    """
    chosen = ds.postings.where(F.col("feature") == j).select("row_id", F.col("code").alias("j"))
    return ds.postings.join(chosen, "row_id").groupBy("feature", F.col("code").alias("x"), "j", "y").agg(F.count("*").alias("c"))


def contingency(ds: SparseDataset, j: int | None = None, totals: DataFrame | None = None, met: DataFrame | None = None) -> DataFrame:
    """feature, x, j (null without a chosen feature), y, c of all features, cells with zeros included.

    ``met``: the cells of the chosen feature's rows, where blocks of whole rows have counted them already.
    """
    totals = feature_totals(ds) if totals is None else totals
    classes = class_totals(ds)
    features = ds.vocabulary.select("feature")
    null = F.lit(None).cast("int")
    if j is None:
        rows = totals.select("feature", "x", null.alias("j"), "y", "c")
        rows = rows.union(totals.select("feature", F.lit(0), null, "y", -F.col("c")))
        rows = rows.union(features.crossJoin(F.broadcast(classes)).select("feature", F.lit(0), null, "y", "c"))
    else:
        freq = frequency_map(ds, j) if met is None else met.where(F.col("feature") == j).select("j", "y", "c")
        met = met_cells(ds, j) if met is None else met
        zero = F.lit(0)
        rows = totals.select("feature", "x", zero.alias("j"), "y", "c")
        # a met cell counts for itself, and is taken off its row, its column and put back at (0, 0)
        parts = F.array(*[F.struct(x.alias("x"), y.alias("j"), F.lit(s).alias("s")) for x, y, s in ((F.col("x"), F.col("j"), 1), (F.col("x"), zero, -1), (zero, F.col("j"), -1), (zero, zero, 1))])
        met = met.select("feature", F.explode(parts).alias("p"), "y", "c")
        rows = rows.union(met.select("feature", "p.x", "p.j", "y", F.col("c") * F.col("p.s")))
        rows = rows.union(totals.select("feature", zero, zero, "y", -F.col("c")))
        # of every feature, the few cells of the class and of the chosen one
        few = freq.select("j", "y", "c").union(freq.select(zero, "y", -F.col("c"))).union(classes.select(zero, "y", "c"))
        few = few.groupBy("j", "y").agg(F.sum("c").alias("c"))
        rows = rows.union(features.crossJoin(F.broadcast(few)).select("feature", zero, "j", "y", "c"))
    return rows.groupBy("feature", "x", "j", "y").agg(F.sum("c").alias("c")).where("c > 0")


def never_met(ds: SparseDataset, j: int) -> DataFrame:
    """Features without a row in common with the chosen one."""
    rows = ds.postings.where(F.col("feature") == j).select("row_id")
    met = ds.postings.join(rows, "row_id", "left_semi").select("feature").distinct()
    return ds.vocabulary.join(met, "feature", "left_anti")
