"""Layouts: feature-major blocks of dense data, and postings of sparse data.

The default path needs neither: Parquet and the cache are columnar already and the chosen feature and the class stand in
the same row as the candidates.  Blocks exist for data that come feature by feature, and to study the trade-off.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .dataset import Dataset, SparseDataset
from .storage import looked_up, numbered, saved

BLOCK_ROWS = 8192


def to_feature_blocks(ds: Dataset, nparts: int | None = None, mode: str = "range") -> DataFrame:
    """feature, block, codes: rows cut into blocks, each transposed; the class is feature -1.

    mode: 'range' sorts features into ``nparts`` partitions (at most two for a feature if nparts is at most their
    number), 'hash' deals them by feature, 'block' leaves blocks where they are.  A block's rows are those that its task
    met one after the other, which a second evaluation may order otherwise: whoever reads features apart stores it first.
    """
    columns = [*ds.features, "y"]

    def transpose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        block = TaskContext.get().partitionId() << 32
        for batch in batches:
            for at in range(0, batch.num_rows, BLOCK_ROWS):
                part = batch.slice(at, BLOCK_ROWS)
                ends = pa.array(range(0, len(columns) * part.num_rows + 1, part.num_rows), pa.int32())
                codes = pa.ListArray.from_arrays(ends, pa.concat_arrays([c.cast(pa.int32()) for c in part.columns]))
                yield pa.RecordBatch.from_arrays([pa.array([*range(len(columns) - 1), -1], pa.int32()), pa.array([block] * len(columns), pa.int64()), codes], names=["feature", "block", "codes"])
                block += 1

    rows = ds.columns().select(*columns)
    blocks = rows.mapInArrow(transpose, "feature int, block long, codes array<int>")
    n = nparts or feature_partitions(len(ds.features))
    if mode == "range":
        return blocks.repartitionByRange(n, "feature", "block").sortWithinPartitions("feature", "block")
    return blocks.repartition(n, "feature") if mode == "hash" else blocks


def feature_partitions(n: int, requested: int | None = None) -> int:
    """Partitions of feature blocks: as many as features unless asked otherwise, never more than twice that."""
    return max(1, min(requested or n, 2 * n))


def column(blocks: DataFrame, feature: int) -> DataFrame:
    """block, codes of one feature."""
    return blocks.where(F.col("feature") == feature).select("block", "codes")


def from_feature_blocks(blocks: DataFrame, features: list[str]) -> DataFrame:
    """Rows again, one column for each feature and y."""
    wide = blocks.groupBy("block").pivot("feature", [*range(len(features)), -1]).agg(F.first("codes"))
    zipped = wide.select(F.explode(F.arrays_zip(*[F.col(f"`{i}`").alias(n) for i, n in zip([*range(len(features)), -1], [*features, "y"])])).alias("r"))
    return zipped.select("r.*")


def partial_histograms(blocks: DataFrame) -> DataFrame:
    """feature, partitions: in how many partitions a feature has blocks, that is how many partial histograms it needs."""
    return blocks.select("feature", F.spark_partition_id().alias("p")).distinct().groupBy("feature").agg(F.count("*").alias("partitions"))


def to_postings(rows: DataFrame, tokens: Column | str, classes: DataFrame, row_id: str = "row_id", name: str = "sparse", min_df: int = 1) -> SparseDataset:
    """Postings of the tokens of each row: features numbered in the order of their names, with the class in each posting.

    Only rows with a class are read for tokens.  Frequent tokens find their number in a broadcast table, others by join.
    """
    classed = classes.select(row_id, "y")
    exploded = saved(rows.join(classed, row_id).select(row_id, "y", F.explode(F.array_distinct(tokens)).alias("name")).distinct(), "tokens")
    df = exploded.groupBy("name").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
    vocabulary = saved(numbered(df, ["name"], "feature"), "vocabulary")
    total = exploded.count()
    postings = looked_up(exploded, vocabulary, ["name"], ["feature"], "df", total).where("feature IS NOT NULL")
    postings = postings.select("feature", F.col(row_id).alias("row_id"), F.lit(1).alias("code"), "y")
    return SparseDataset(postings, classes.select(F.col(row_id).alias("row_id"), "y"), vocabulary.select("name", "feature"), name)


def hashed_postings(rows: DataFrame, tokens: Column | str, classes: DataFrame, buckets: int, row_id: str = "row_id", name: str = "hashed") -> SparseDataset:
    """Postings by feature hashing: no vocabulary has to be built or joined."""
    from ..functions.encode import hashed

    exploded = rows.join(classes.select(row_id, "y"), row_id).select(row_id, "y", F.explode(tokens).alias("t")).select(row_id, "y", hashed(F.col("t"), buckets).alias("feature")).distinct()
    postings = saved(exploded.select("feature", F.col(row_id).alias("row_id"), F.lit(1).alias("code"), "y"), "postings")
    vocabulary = postings.select("feature").distinct().select("feature", F.concat(F.lit("h"), F.col("feature").cast("string")).alias("name"))
    return SparseDataset(postings, classes.select(F.col(row_id).alias("row_id"), "y"), vocabulary, name)


def from_vectors(rows: DataFrame, vector: str, label: str, row_id: str = "row_id") -> SparseDataset:
    """Postings of a column of ML vectors, whose non-zero values must be small whole codes."""
    from pyspark.ml.functions import vector_to_array

    classes = rows.select(F.col(row_id).alias("row_id"), F.col(label).cast("int").alias("y"))
    exploded = rows.select(F.col(row_id).alias("row_id"), F.col(label).cast("int").alias("y"), F.posexplode(vector_to_array(vector)).alias("feature", "v"))
    postings = exploded.where("v != 0").select(F.col("feature").cast("long").alias("feature"), "row_id", F.col("v").cast("int").alias("code"), "y")
    vocabulary = postings.select("feature").distinct().select("feature", F.col("feature").cast("string").alias("name"))
    return SparseDataset(postings, classes, vocabulary)


def from_maps(rows: DataFrame, codes: str, label: str, row_id: str = "row_id") -> SparseDataset:
    """Postings of a column of maps from feature names to codes."""
    classes = rows.select(F.col(row_id).alias("row_id"), F.col(label).cast("int").alias("y"))
    exploded = rows.select(F.col(row_id).alias("row_id"), F.col(label).cast("int").alias("y"), F.explode(codes).alias("name", "code")).where("code != 0")
    exploded = saved(exploded, "maps")
    df = exploded.groupBy("name").agg(F.count("*").alias("df"))
    vocabulary = saved(numbered(df, ["name"], "feature"), "vocabulary")
    postings = looked_up(exploded, vocabulary, ["name"], ["feature"], "df", exploded.count())
    return SparseDataset(postings.select("feature", "row_id", F.col("code").cast("int").alias("code"), "y"), classes, vocabulary.select("name", "feature"))


def vectorized(postings: DataFrame, chunk_rows: int = 1 << 20) -> DataFrame:
    """feature, chunk, entries: a feature's postings as sorted (row_id, code) arrays, cut by row range so that a frequent feature never becomes one record."""
    entry = F.struct("row_id", "code")
    return postings.groupBy("feature", F.floor(F.col("row_id") / chunk_rows).alias("chunk")).agg(F.array_sort(F.collect_list(entry)).alias("entries"))


def sparsified(ds: Dataset) -> tuple[SparseDataset, dict[str, int]]:
    """Dense data as postings, each feature's most frequent code being the implicit one (its code 0; the old 0 takes its place)."""
    rows = ds.df.select(*ds.features, ds.label, *(["row_id"] if "row_id" in ds.df.columns else []))
    if "row_id" not in rows.columns:  # written, so that postings and classes see the same numbers
        rows = saved(rows.withColumn("row_id", F.monotonically_increasing_id()), "rows")
    modes = rows.agg(*[F.mode(f, True).alias(f) for f in ds.features]).first().asDict()
    code = lambda f: F.when(F.col(f) == modes[f], 0).when(F.col(f) == 0, modes[f]).otherwise(F.col(f)).cast("int")
    long = rows.select("row_id", F.col(ds.label).cast("int").alias("y"), F.posexplode(F.array(*[code(f) for f in ds.features])).alias("feature", "code"))
    postings = long.where("code != 0").select(F.col("feature").cast("long").alias("feature"), "row_id", "code", "y")
    vocabulary = ds.df.sparkSession.createDataFrame(list(enumerate(ds.features)), "feature long, name string")
    return SparseDataset(postings, rows.select("row_id", F.col(ds.label).cast("int").alias("y")), vocabulary, ds.name), modes
