"""Shared pieces of the corpus operators: the shared folder, text access and packed exchanges."""

from __future__ import annotations

import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.storage import looked_up, shared_dir  # noqa: F401


def saved(df: DataFrame, name: str) -> DataFrame:
    """Writes a table into the shared folder and reads it back: lineage ends here and a lost executor costs nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/featsift/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_text(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The two columns an operator needs, under fixed names; null text counts as empty."""
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


def parts_for(n: int, each: int, least: int = 1) -> int:
    """So many partitions that each gets about ``each`` of ``n``."""
    return max(least, -(-int(n) // each))


def slices(batches, size: int):
    """Arrow batches cut into smaller ones of at most ``size`` rows."""
    for batch in batches:
        for at in range(0, batch.num_rows, size):
            yield batch.slice(at, size)


def record(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, t) for c, t in zip(columns, schema.types)], schema=schema)


#: Words of the membership bitmap: 2^20 of 64 bits, whatever the number of ids.
_WORD_BITS = 20


def _place(id_col: str):
    return F.pmod(F.xxhash64(F.expr(id_col)), F.lit(64 << _WORD_BITS))


def maybe_among(rows: DataFrame, ids: DataFrame, id_col: str = "doc_id", other_col: str | None = None) -> DataFrame:
    """Adds _maybe: false only if a row's id isn't among ``ids`` (there under ``other_col``).  Both must be 64-bit integers.

    The bitmap that is broadcast has at most 2^20 rows of two integers; as it fills up it lets more rows through, which
    the join that follows takes out.  It spares that join the texts of most rows.
    """
    other, own = f"cast({other_col or id_col} as long)", f"cast({id_col} as long)"
    bits = ids.select(F.shiftright(_place(other), 6).alias("_word"), F.expr(f"shiftleft(1L, cast(pmod(xxhash64({other}), 64) as int))").alias("_bit"))
    words = bits.groupBy("_word").agg(F.bit_or("_bit").alias("_bits"))
    placed = rows.withColumn("_word", F.shiftright(_place(own), 6))
    here = F.expr(f"coalesce(shiftrightunsigned(_bits, cast(pmod(xxhash64({own}), 64) as int)) & 1L, 0L) = 1L")
    return placed.join(F.broadcast(words), "_word", "left").withColumn("_maybe", here).drop("_word", "_bits")
