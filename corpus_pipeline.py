"""A corpus pipeline: each stage takes the documents that the one before it kept, the last one packs their ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from featsift.llm import exact_dedup, minhash_dedup, packing, quality, suffix_dedup
from featsift.llm.common import saved, table
from featsift.llm.queries import tokenizer_file


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose posterior quality is low go; decided by row, so null and repeated ids make no difference.  Null texts are judged as empty; no rows give none."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def exact_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the smallest id stays; decided by id and text.  Null texts are empty; rows without an id stay; no rows give none."""
    return exact_dedup.drop_exact_duplicates(docs)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays.  Rows that repeat an id are one document and share its fate; rows without an id or without words stay; no rows give none."""
    return minhash_dedup.drop_near_duplicates(docs)


def repeats_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 100 bytes and more that stand earlier in the corpus are cut out; all rows stay.  Null texts stay null, rows without an id are left as they are; no rows give none."""
    return suffix_dedup.without_repeats(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row's ids in sequences of 1024 at most, rows that repeat an id each on its own; null texts are empty; no rows give none."""
    return packing.pack(docs, tokenizer_file("byte_bpe_50k.json"))


STAGES = [
    ("quality classifier", quality_filter),
    ("exact dedup", exact_dedup_stage),
    ("MinHash near-dedup", near_dedup_stage),
    ("suffix-array dedup", repeats_stage),
    ("packing", packing_stage),
]

#: The classifier, MinHash components and tokenizer aren't SQL; tests compare every stage, and run(), with brute force on all documents of the smallest scale.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = saved(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
