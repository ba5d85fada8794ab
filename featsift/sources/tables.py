"""Readers and writers."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """Rows dealt anew where they come from fewer files than there are cores, which a small table's single file would leave idle."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if len(df.inputFiles()) < cores else df


def register_views(spark: SparkSession, sf_dir: str, names: Sequence[str] = TABLES) -> None:
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read(spark: SparkSession, fmt: str, path: str, schema: StructType | str | None = None, **options: str) -> DataFrame:
    """Any of Spark's file formats, with an explicit schema where the format has none of its own."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema: inferring one reads all data")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def libsvm(spark: SparkSession, path: str, num_features: int | None = None) -> DataFrame:
    """label, features (sparse vector).  Without the number of features Spark reads the data once to find it."""
    reader = spark.read.format("libsvm")
    return (reader.option("numFeatures", str(num_features)) if num_features else reader).load(path)


def write(df: DataFrame, path: str, mode: str = "overwrite", partition_by: Sequence[str] = (), compression: str = "zstd") -> None:
    writer = df.write.mode(mode).option("compression", compression)
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, by: Sequence[str], sort_by: Sequence[str] = (), path: str | None = None) -> DataFrame:
    """A bucketed table, in the warehouse or at ``path``: joins and aggregates on the bucket columns then need no exchange."""
    first, *rest = by
    writer = df.repartition(buckets, *by).write.mode("overwrite").bucketBy(buckets, first, *rest).sortBy(*(sort_by or by))
    (writer.option("path", path) if path else writer).saveAsTable(name)
    return df.sparkSession.table(name)


def vector_columns(df: DataFrame, column: str, size: int, prefix: str = "f") -> DataFrame:
    """A vector column as one column for each position."""
    from pyspark.ml.functions import vector_to_array

    return df.withColumn("_a", vector_to_array(column)).select("*", *[F.col("_a")[i].alias(f"{prefix}{i}") for i in range(size)]).drop("_a")


def to_vector(df: DataFrame, columns: Sequence[str], out: str = "features") -> DataFrame:
    from pyspark.ml.feature import VectorAssembler

    return VectorAssembler(inputCols=list(columns), outputCol=out).transform(df)
