"""Oversampling, hold-out splits and ratio samples, by integer arithmetic on keys so that they repeat exactly."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRIME = 2_147_483_647


def bucket(key: Column, buckets: int = 100, multiplier: int = 48_271, shift: int = 11) -> Column:
    """A key's number from 0 to buckets - 1."""
    return F.pmod(F.pmod(key.cast("long") * F.lit(multiplier) + F.lit(shift), F.lit(PRIME)), F.lit(buckets))


def trains(key: Column, share: float = 0.8) -> Column:
    """Whether a key's rows are training rows."""
    return bucket(key) < round(share * 100)


def holdout(df: DataFrame, key: Column, share: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """Training and test rows; rows with equal keys stay together."""
    inside = trains(key, share)
    return df.where(inside), df.where(~inside)


def take_ratio(df: DataFrame, ratio: float, key: Column) -> DataFrame:
    """About this share of the rows, the same ones each time."""
    return df.where(bucket(key, 10_000, 16_807, 5) < round(ratio * 10_000))


def random_oversample(df: DataFrame, label: str, ratio: float = 1.0, key: Column | None = None, mode: str = "replicate") -> DataFrame:
    """Every class brought up to ``ratio`` times the largest one.

    Replicate: whole copies of each row, and one more of the rows that a hash of the key picks; class counts are exact
    in expectation, and nothing is dropped.  Weight: the copies as a column ``weight``.  Class counts are a few rows.
    """
    counts = df.groupBy(label).agg(F.count("*").alias("_c"))
    most = counts.agg(F.max("_c").alias("_m"))
    target = counts.crossJoin(F.broadcast(most)).select(F.col(label).alias("_l"), F.greatest(F.lit(1.0), F.col("_m") * F.lit(float(ratio)) / F.col("_c")).alias("_r"))
    rows = df.join(F.broadcast(target), df[label].eqNullSafe(F.col("_l")))
    pick = bucket(F.monotonically_increasing_id() if key is None else key, 1_000_000, 69_621, 7)
    copies = (F.floor("_r") + F.when(pick < F.floor((F.col("_r") - F.floor("_r")) * 1_000_000), 1).otherwise(0)).cast("int")
    if mode == "weight":
        return rows.withColumn("weight", copies).drop("_l", "_r")
    return rows.withColumn("_k", F.explode(F.array_repeat(F.lit(1), copies))).drop("_l", "_r", "_k")
