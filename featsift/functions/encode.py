"""Encoders from source columns to small non-negative codes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.ml.feature import Bucketizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.storage import numbered


def with_invalid(code: Column, value: Column, cardinality: int, handle: str = "keep") -> Column:
    """Nulls as a code of their own (keep), as null for a later filter (skip), or as an error."""
    match handle:
        case "keep":
            return F.when(value.isNull(), F.lit(cardinality)).otherwise(code).cast("int")
        case "skip":
            return code.cast("int")
        case "error":
            return F.when(value.isNull(), F.raise_error(F.lit("null in a feature"))).otherwise(code).cast("int")
    raise ValueError(f"handle_invalid: {handle!r}")


def equal_width(value: Column, lo: float, hi: float, bins: int) -> Column:
    """Bins of equal width; the upper end belongs to the last bin, a constant column to the first."""
    if hi <= lo:
        return F.when(value.isNotNull(), F.lit(0))
    at = F.floor((value - F.lit(float(lo))) / F.lit(float(hi) - float(lo)) * bins)
    return F.greatest(F.least(at, F.lit(bins - 1)), F.lit(0)).cast("int")


def width_bounds(df: DataFrame, columns: Sequence[str]) -> dict[str, tuple[float, float]]:
    """Least and greatest value of each column, all in one aggregate."""
    r = df.agg(*[f(c).cast("double").alias(f"{n}_{i}") for i, c in enumerate(columns) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    return {c: (r[f"lo_{i}"], r[f"hi_{i}"]) for i, c in enumerate(columns)}


def equal_frequency(df: DataFrame, columns: Sequence[str], bins: int, error: float = 0.001) -> DataFrame:
    """Adds <column>_bin with about equally many rows in each bin: quantiles of all columns in one aggregate."""
    cuts = df.stat.approxQuantile(list(columns), [i / bins for i in range(1, bins)], error)
    splits = [[float("-inf"), *sorted(set(c)), float("inf")] for c in cuts]
    outs = [f"{c}_bin" for c in columns]
    made = Bucketizer(splitsArray=splits, inputCols=list(columns), outputCols=outs, handleInvalid="keep").transform(df)
    return made.withColumns({o: F.col(o).cast("int") for o in outs})


def ntile_bins(df: DataFrame, column: str, bins: int, order: Sequence[str]) -> DataFrame:
    """Exact equal-frequency bins: adds <column>_bin.  Rows are placed by a distributed sort; the first bins take one more row."""
    placed = numbered(df, [column, *order], "_at")
    n = df.count()
    size, more = divmod(n, bins)
    head = more * (size + 1)
    bin_ = F.when(F.col("_at") < head, F.floor(F.col("_at") / (size + 1))).otherwise(more + F.floor((F.col("_at") - head) / max(size, 1)))
    return placed.withColumn(f"{column}_bin", bin_.cast("int")).drop("_at")


def bands(value: Column, splits: Sequence[float]) -> Column:
    """Number of boundaries that a value reaches."""
    code = F.lit(0)
    for s in splits:
        code = code + F.when(value >= F.lit(s), 1).otherwise(0)
    return F.when(value.isNotNull(), code).cast("int")


def dictionary(df: DataFrame, column: str) -> DataFrame:
    """value, code: ranks of the distinct values in order, numbered range by range."""
    values = df.select(F.col(column).alias("value")).where("value IS NOT NULL").distinct()
    return numbered(values, ["value"], "code").select("value", F.col("code").cast("int").alias("code"))


def with_dictionary(df: DataFrame, column: str, out: str) -> DataFrame:
    """Adds the code of a column's value.  The dictionary joins by its size: small ones are broadcast, large ones shuffled."""
    d = dictionary(df, column)
    return df.join(d, df[column] == d["value"], "left").drop("value").withColumnRenamed("code", out)


def rank_code(value: Column, values: Sequence[str]) -> Column:
    """Code of a value by its place in a known short list; null if it isn't there."""
    at = F.array_position(F.array(*[F.lit(v) for v in values]), value)
    return F.when(at > 0, at - 1).cast("int")


def tokens(text: Column, pattern: str = "[a-z]+") -> Column:
    """Distinct tokens of a text in lower case."""
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(pattern), F.lit(0)))


def ngrams(words: Column, n: int) -> Column:
    """All runs of n tokens, joined by a blank."""
    grams = words
    for k in range(1, n):
        short = F.slice(grams, F.lit(1), F.greatest(F.size(grams) - 1, F.lit(0)))
        grams = F.zip_with(short, F.slice(words, F.lit(k + 1), F.greatest(F.size(words) - k, F.lit(0))), lambda a, b: F.concat_ws(" ", a, b))
    return grams


def hashed(token: Column, buckets: int) -> Column:
    """Token as one of ``buckets`` feature numbers."""
    return F.pmod(F.xxhash64(token), F.lit(buckets))


def positions(df: DataFrame, array: str, size: int, prefix: str = "e") -> DataFrame:
    """An array column as one column for each position."""
    return df.select("*", *[F.col(array).getItem(i).cast("double").alias(f"{prefix}{i}") for i in range(size)])


def cardinalities(df: DataFrame, features: Sequence[str]) -> dict[str, int]:
    """Greatest code + 1 of each feature, in one aggregate."""
    r = df.agg(*[F.max(f).alias(f"m{i}") for i, f in enumerate(features)]).first()
    return {f: 0 if r[f"m{i}"] is None else int(r[f"m{i}"]) + 1 for i, f in enumerate(features)}


def drop_constant(df: DataFrame, features: Sequence[str]) -> list[str]:
    """Features that take more than one value."""
    r = df.agg(*[(F.min(f) != F.max(f)).alias(f"v{i}") for i, f in enumerate(features)]).first()
    return [f for i, f in enumerate(features) if r[f"v{i}"]]
