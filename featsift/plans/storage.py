"""Tables between steps, in the folder that driver and executors share, and what is built on them."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_OWN: dict[str, str] = {}
#: Keys of more than 1 / (HOT_PARTS * partitions) of all rows are broadcast: there are at most HOT_PARTS * partitions.
HOT_PARTS = 8


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; one of our own only in local mode, where the session names none."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no folder that driver and executors share")
        base = _OWN.setdefault("dir", tempfile.mkdtemp(prefix="featsift-"))
        spark.sparkContext.setCheckpointDir(base)
    return base


def folder(spark: SparkSession) -> str:
    """Where this application's tables are."""
    return f"{shared_dir(spark)}/featsift/{spark.sparkContext.applicationId}"


def clear(spark: SparkSession) -> None:
    """Deletes all tables that this application has written between steps; results read from them must be stored first."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder(spark))
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def saved(df: DataFrame, name: str, partitions: int | None = None, by: str | None = None) -> DataFrame:
    """Writes a table and reads it back: plans stay small, and a lost executor costs no recomputation."""
    spark = df.sparkSession
    path = f"{folder(spark)}/{name}-{uuid.uuid4().hex}"
    if by:
        df = df.repartition(by) if partitions is None else df.repartition(partitions, by)
        df = df.sortWithinPartitions(by)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def numbered(df: DataFrame, order: Sequence[Column | str], out: str, first: int = 0) -> DataFrame:
    """``df`` with the place of each row in the order, counted from ``first``, as an integer of 64 bits.

    Rows are dealt to ranges of the order and written; every range is numbered by a task of its own, and starts at the
    number of rows before it.  What reaches the driver is one count for each range.  Rows that the order leaves equal
    are numbered as they come.
    """
    spark = df.sparkSession
    ranged = saved(df.repartitionByRange(*order).withColumn("_range", F.spark_partition_id()), "ranges")
    before, starts = first, []
    for r in sorted(ranged.groupBy("_range").agg(F.count("*").alias("n")).collect()):
        starts.append((r["_range"], before))
        before += r["n"]
    starts = F.broadcast(spark.createDataFrame(starts, "_range int, _start long"))
    place = F.row_number().over(Window.partitionBy("_range").orderBy(*order))
    return ranged.withColumn("_place", place).join(starts, "_range").withColumn(out, F.col("_start") + F.col("_place") - 1).drop("_range", "_place", "_start")


def looked_up(rows: DataFrame, found: DataFrame, keys: list[str], values: list[str], weight: str, total: int, nulls: bool = False) -> DataFrame:
    """``rows`` with the values that ``found`` has for their keys, null where it has none.  ``nulls``: null keys are equal.

    ``found`` has one row for each key and in ``weight`` the number of rows that have it.  Keys with a large share of the
    ``total`` are few whatever the size, so they are broadcast and their rows stay where they are; all others join by key.
    ``rows`` is read twice.
    """
    bound = max(1, int(total) // (HOT_PARTS * int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    named = found.select(*[F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)], *[F.col(v).alias(f"_v{i}") for i, v in enumerate(values)], F.col(weight).alias("_n"), F.lit(True).alias("_here"))
    match = F.lit(True)
    for i, k in enumerate(keys):
        match = match & (F.col(k).eqNullSafe(F.col(f"_k{i}")) if nulls else F.col(k) == F.col(f"_k{i}"))
    hot = rows.join(F.broadcast(named.where(F.col("_n") > bound)), match, "left")
    rest = hot.where("_here IS NULL").select(*rows.columns).join(named.where(F.col("_n") <= bound), match, "left")
    both = hot.where("_here").unionByName(rest)
    return both.select(*rows.columns, *[F.col(f"_v{i}").alias(v) for i, v in enumerate(values)])
