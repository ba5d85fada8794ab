"""Functions for SQL users: information of small count tables, and selection within a partition.

The engine itself works with column expressions; these exist for ad-hoc queries.
"""

from __future__ import annotations

from array import array

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StringType, StructField, StructType
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult


def _information(counts, rows: int, cols: int) -> float:
    c = np.asarray(counts, np.float64).reshape(rows, cols)
    n = c.sum()
    return _g(c, n) - _g(c.sum(0), n) - _g(c.sum(1), n) if n else 0.0


def _g(c: np.ndarray, n: float) -> float:
    p = c[c > 0] / n
    return float((p * np.log2(p)).sum())


def mi_of_counts(counts: pd.Series, rows: pd.Series, cols: pd.Series) -> pd.Series:
    return pd.Series([max(_information(c, r, k), 0.0) for c, r, k in zip(counts, rows, cols)])


def cmi_of_counts(counts: pd.Series, rows: pd.Series, cols: pd.Series, layers: pd.Series) -> pd.Series:
    out = []
    for c, r, k, z in zip(counts, rows, cols, layers):
        cube = np.asarray(c, np.float64).reshape(z, r, k)
        n = cube.sum()
        out.append(max(sum(_information(m, r, k) * m.sum() for m in cube) / n, 0.0) if n else 0.0)
    return pd.Series(out)


def entropy_of(count: Column) -> Column:
    """Entropy in bits of a group's counts, as an aggregate expression."""
    c = count.cast("double")
    return F.log2(F.sum(c)) - F.sum(F.when(c > 0, c * F.log2(c)).otherwise(0.0)) / F.sum(c)


class SelectFeatures:
    """Table function: the ranking of one partition's integer columns.

    SELECT * FROM select_features(TABLE(t) PARTITION BY g, 'y', 3, 'mrmr'): the partition is held in one task, a column
    as an array of machine integers.  A fifth argument names a column that says how often each row counts, so that a table
    of many rows and few codes can be grouped first.  A column with nulls is no candidate.
    """

    @staticmethod
    def analyze(table: AnalyzeArgument, label: AnalyzeArgument, k: AnalyzeArgument, criterion: AnalyzeArgument, weight: AnalyzeArgument | None = None) -> AnalyzeResult:
        if not table.isTable:
            raise ValueError("the first argument must be a table")
        out = [StructField("step", IntegerType()), StructField("name", StringType()), StructField("score", DoubleType())]
        kinds = {f.name: f.dataType for f in table.dataType.fields}
        for column in (label, weight):
            if column is not None and column.value not in kinds:
                raise ValueError(f"no column {column.value!r}")
        return AnalyzeResult(StructType(out))

    def __init__(self):
        self.columns, self.label, self.k, self.criterion, self.weight = None, None, 0, "mrmr", None

    def eval(self, table, label, k, criterion, weight=None):
        if self.columns is None:
            self.columns = {name: array("q") for name in table.__fields__}
            self.label, self.k, self.criterion, self.weight = label, k, criterion, weight
        for name, value in zip(table.__fields__, table):
            held = self.columns.get(name)
            if held is not None:
                if isinstance(value, int) and not isinstance(value, bool):
                    held.append(value)
                else:
                    del self.columns[name]

    def terminate(self):
        if self.columns is None:
            return
        from ..operators.baselines import Columns, one_core

        codes = {name: np.frombuffer(held, np.int64) for name, held in self.columns.items()}
        for name in (self.label, self.weight):
            if name is not None and name not in codes:
                raise ValueError(f"{name!r} must hold integers without nulls")
        features = [c for c, v in codes.items() if c not in (self.label, self.weight) and v.min() != v.max()]
        columns = Columns.of([codes[c] for c in (*features, self.label)], codes.get(self.weight))
        for step in one_core(columns, features, self.k, self.criterion):
            yield step["step"], step["name"], step["score"]


def register_functions(spark: SparkSession) -> None:
    """mi_from_counts, cmi_from_counts and select_features for SQL."""
    spark.udf.register("mi_from_counts", F.pandas_udf(mi_of_counts, "double"))
    spark.udf.register("cmi_from_counts", F.pandas_udf(cmi_of_counts, "double"))
    spark.udtf.register("select_features", F.udtf(SelectFeatures))
