"""What a selection runs on: rows of codes with their class (dense), or postings of non-zero codes (sparse)."""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import cached_property

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import encode
from .storage import saved


#: Columns that a sparse data set may be spread into.
MAX_DENSE = 2_000


@dataclass
class Dataset:
    """Dense rows: one column of small codes for each feature, and the class.  The order of features decides ties."""

    df: DataFrame
    features: list[str]
    label: str = "y"
    weight: str | None = None
    name: str = "dense"
    max_bins: int = 256

    sparse = False

    @cached_property
    def cards(self) -> dict[str, int]:
        return encode.cardinalities(self.df, [*self.features, self.label])

    @cached_property
    def n(self) -> int:
        return self.df.count() if self.weight is None else int(self.df.agg(F.sum(self.weight)).first()[0] or 0)

    @property
    def names(self) -> list[str]:
        return self.features

    def columns(self) -> DataFrame:
        """Only what counting needs; Catalyst carries the selection down to the scan."""
        return self.df.select(*[F.col(f).cast("int").alias(f) for f in self.features], F.col(self.label).cast("int").alias("y"), (F.col(self.weight) if self.weight else F.lit(1)).cast("long").alias("_w"))

    def materialized(self) -> Dataset:
        """Codes are scanned once for each round, so they are kept in columnar memory, beyond it on disk."""
        kept = self.df.select(*[F.col(f).cast("short" if self.max_bins <= 32_000 else "int").alias(f) for f in self.features], F.col(self.label).cast("int").alias(self.label), *([self.weight] if self.weight else []))
        return replace(self, df=kept.persist(StorageLevel.MEMORY_AND_DISK))

    def release(self) -> None:
        self.df.unpersist()

    def only(self, features: list[str]) -> Dataset:
        return replace(self, features=list(features))

    def check(self) -> None:
        """Features beyond the bin limit would make count tables that no longer are small."""
        wide = {f: c for f, c in self.cards.items() if c > self.max_bins}
        if wide:
            raise ValueError(f"more than {self.max_bins} codes: {wide}; bin these features first")


@dataclass
class SparseDataset:
    """postings: feature (number), row_id, code (not 0), y; classes: row_id, y for all rows; vocabulary: feature, name."""

    postings: DataFrame
    classes: DataFrame
    vocabulary: DataFrame
    name: str = "sparse"
    _stored: bool = False

    sparse = True

    @cached_property
    def n(self) -> int:
        return self.classes.count()

    @cached_property
    def size(self) -> int:
        return self.vocabulary.count()

    def materialized(self) -> SparseDataset:
        """Written once, sorted by feature inside ranges of rows, so that a feature met in every row is no task's alone."""
        if self._stored:
            return self
        postings = self.postings.repartition("row_id").sortWithinPartitions("feature")
        return SparseDataset(saved(postings, "postings"), saved(self.classes, "classes"), saved(self.vocabulary, "vocabulary"), self.name, True)

    def release(self) -> None:
        """Tables in the shared folder go with it."""

    def restricted(self, features: DataFrame) -> SparseDataset:
        """Only the given features (a table of their numbers) as candidates."""
        keep = lambda df: df.join(features.select("feature"), "feature", "left_semi")
        return SparseDataset(keep(self.postings), self.classes, keep(self.vocabulary), self.name)

    def densified(self, features: list[int]) -> Dataset:
        """The given features as dense columns (tests and small vocabularies)."""
        if len(features) > MAX_DENSE:
            raise ValueError(f"{len(features)} columns; at most {MAX_DENSE}")
        wide = self.postings.where(F.col("feature").isin(features)).groupBy("row_id").pivot("feature", features).agg(F.max("code"))
        names = [f"f{i}" for i in features]
        full = self.classes.join(wide, "row_id", "left").select("y", *[F.coalesce(F.col(f"`{i}`"), F.lit(0)).cast("int").alias(n) for i, n in zip(features, names)])
        return Dataset(full, names)
