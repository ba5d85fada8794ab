"""Counts are sums, so relevance can be kept up to date as events arrive."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import info
from ..sources.workloads import EVENTS, event_codes

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str, max_files: int | None = None) -> DataFrame:
    """A stream of event files; event time is cast to a zoned timestamp, which watermarks need."""
    reader = spark.readStream.schema(SCHEMA)
    if max_files:
        reader = reader.option("maxFilesPerTrigger", max_files)
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def long_codes(stream: DataFrame) -> DataFrame:
    """ts, event_type and one row for each feature and code of an event."""
    return event_codes(stream).select("ts", "event_type", "event_id", F.posexplode(F.array(*EVENTS)).alias("feature", "x"))


def window_counts(stream: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """Contingency cells of each tumbling (or sliding) window: start, feature, x, event_type, c."""
    rows = long_codes(stream.withWatermark("ts", late))
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return rows.groupBy(window, "feature", "x", "event_type").agg(F.count("*").alias("c")).select(F.col("window.start").alias("start"), "feature", "x", "event_type", "c")


def session_counts(stream: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """Events of each user's sessions: user_id, start, event_type counts."""
    watched = stream.withWatermark("ts", late)
    return watched.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("c")).select("user_id", F.col("session_window.start").alias("start"), "c")


def deduplicated(stream: DataFrame, late: str = "2 hours") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_users(stream: DataFrame, users: DataFrame, key: str = "user_id") -> DataFrame:
    """Stream rows with a static table's columns."""
    return stream.join(users, key, "left")


def running_ranking(stream: DataFrame, table_path: str, checkpoint: str):
    """Keeps cumulative cells in a table, one folder for each batch, so a batch that is repeated replaces itself; starts the query over what is there."""

    def merge(batch: DataFrame, number: int) -> None:
        cells = long_codes(batch).groupBy("feature", "x", "event_type").agg(F.count("*").alias("c"))
        cells.write.mode("overwrite").parquet(f"{table_path}/batch={number}")

    return stream.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def ranking(spark: SparkSession, table_path: str) -> DataFrame:
    """feature, rel from the cells that the running ranking has kept so far."""
    cells = spark.read.parquet(table_path).groupBy("feature", "x", F.col("event_type").alias("y")).agg(F.sum("c").alias("c"))
    return info.mutual_info(cells, "x", "y", ["feature"]).withColumnRenamed("mi", "rel")


def relevance_drift(stream: DataFrame, table_path: str, checkpoint: str):
    """Relevance of each feature in every batch and in all batches before it; starts the query over what is there.

    Cells are added up before anything else happens, so a batch costs the driver nothing and the two tables (cells and
    drift, one folder for each batch) grow with the number of codes.  A batch that is repeated replaces itself.
    """

    def measure(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        cells = long_codes(batch).groupBy("feature", "x", F.col("event_type").alias("y")).agg(F.count("*").alias("c"))
        cells.write.mode("overwrite").parquet(f"{table_path}/cells/batch={number}")
        kept = spark.read.schema("feature int, x int, y string, c long, batch int").parquet(f"{table_path}/cells").where(F.col("batch") <= number)
        now = info.mutual_info(kept.where(F.col("batch") == number), "x", "y", ["feature"]).withColumnRenamed("mi", "rel")
        past = kept.where(F.col("batch") < number).groupBy("feature", "x", "y").agg(F.sum("c").alias("c"))
        past = info.mutual_info(past, "x", "y", ["feature"]).withColumnRenamed("mi", "before")
        found = now.join(past, "feature", "left").withColumn("change", F.col("rel") - F.col("before"))
        found.write.mode("overwrite").parquet(f"{table_path}/drift/batch={number}")

    return stream.writeStream.foreachBatch(measure).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _drift(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Mean value of a user bucket's events so far, and how far the mean of the latest batch is from that before it."""
    n, total = state.get if state.exists else (0, 0.0)
    m, more = 0, 0.0
    for pdf in batches:
        m += len(pdf)
        more += float(pdf["value"].fillna(0.0).sum())
    before, now = (total / n if n else 0.0), (more / m if m else 0.0)
    state.update((n + m, total + more))
    yield pd.DataFrame({"user_bucket": [key[0]], "n": [n + m], "mean": [(total + more) / max(n + m, 1)], "change": [now - before if n else 0.0]})


def drift(stream: DataFrame) -> DataFrame:
    """user_bucket, n, mean, change: a stateful detector of changes in the mean value of each user bucket."""
    rows = stream.select(F.pmod(F.col("user_id"), F.lit(16)).cast("int").alias("user_bucket"), "value")
    return rows.groupBy("user_bucket").applyInPandasWithState(_drift, "user_bucket int, n long, mean double, change double", "n long, total double", "update", GroupStateTimeout.NoTimeout)
