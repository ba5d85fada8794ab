"""Exact duplicates through an extendible-hash index kept on shared files.

DataFrame operations only.

1. Every text is normalised and hashed; its entry (id, 64-bit key, digest) goes to the shared folder.
2. The directory starts with one bucket and doubles while a bucket holds more distinct keys than its capacity: that
   bucket is split by its next hash bit, all others stay.  Buckets are numbered in the order of their key ranges.
3. Entries are counted per bucket and key, with partial sums before the shuffle, and the index is written in ranges of
   buckets, one range for each owner task.  A key with one entry is settled.
4. A key with several entries is a chain.  Only their texts travel, each distinct one once per task; the owner of the
   bucket tells the texts of a chain apart by their bytes, so keys that collide by chance are different groups.
5. Rows look their key up in the index.  Chains so long that few can exist are broadcast, all others join by key; where a
   key has several texts, rows join by key and text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_text, looked_up, maybe_among, saved

#: Hash bits that one look at the keys can split by: at most 2^16 counts reach the driver at once for each overfull range.
LOOK_BITS = 16
#: Keys a bucket holds at least, and about how many buckets the directory has at most.
LEAST_CAPACITY, MOST_BUCKETS = 256, 4096


def normalised(text: Column) -> Column:
    """Each run of ASCII white space as one space."""
    return F.regexp_replace(text, r"[\x20\x09-\x0D]+", " ")


def key_of(norm: Column, bits: int = 64) -> Column:
    """The key of a normalised text; fewer bits (the upper ones) make keys collide, as tests do."""
    key = F.xxhash64(norm)
    return key if bits == 64 else F.shiftleft(F.shiftrightunsigned(key, 64 - bits), 64 - bits)


def prefix(key: Column, bits: int) -> Column:
    return F.shiftrightunsigned(key, 64 - bits) if bits else F.lit(0).cast("long")


def directory(keys: DataFrame, capacity: int) -> list[tuple[int, int]]:
    """(local depth, prefix) of each bucket in key order, none with more than ``capacity`` distinct keys unless all bits are used up.

    One look at the keys counts them by their next LOOK_BITS bits; the doublings within those bits follow from the
    counts.  A further look takes only the ranges that are still overfull.
    """
    buckets: list[tuple[int, int]] = []
    overfull: list[tuple[int, int]] = [(0, 0)]
    while overfull:
        depth = overfull[0][0]
        deep = min(64, depth + LOOK_BITS)
        part = keys if not depth else keys.where(prefix(F.col("key"), depth).isin([p for _, p in overfull]))
        counts: dict[int, dict[int, int]] = {depth: {}}
        for r in part.groupBy(prefix(F.col("key"), deep).alias("p")).agg(F.count("*").alias("n")).toLocalIterator():
            for d in range(depth, deep + 1):
                at = (r["p"] & (2**64 - 1)) >> (deep - d)
                level = counts.setdefault(d, {})
                level[at] = level.get(at, 0) + r["n"]
        left, overfull = overfull, []
        while left:  # doublings
            d, p = left.pop()
            if counts.get(d, {}).get(p, 0) <= capacity or d == 64:
                buckets.append((d, p))
            elif d == deep:
                overfull.append((d, p))
            else:
                left += [(d + 1, 2 * p), (d + 1, 2 * p + 1)]
        overfull.sort()
    return sorted(buckets, key=lambda b: b[1] << (64 - b[0]))


def with_bucket(rows: DataFrame, buckets: list[tuple[int, int]]) -> DataFrame:
    """Adds the number of the bucket that owns a row's key: the slot of its leading bits, then the bits it was split by."""
    first = min(LOOK_BITS, max(d for d, _ in buckets))
    slots: dict[int, list[tuple]] = {}
    for number, (d, p) in enumerate(buckets):
        if d <= first:
            for slot in range(p << (first - d), (p + 1) << (first - d)):
                slots[slot] = [(0, 0, number)]
        else:
            slots.setdefault(p >> (d - first), []).append((d, p if p < 2**63 else p - 2**64, number))
    table = rows.sparkSession.createDataFrame(list(slots.items()), "slot long, owners array<struct<depth:int,prefix:long,bucket:long>>")
    owner = "element_at(filter(owners, x -> x.depth = 0 OR shiftrightunsigned(key, 64 - x.depth) = x.prefix), 1).bucket"
    return rows.withColumn("slot", prefix(F.col("key"), first)).join(F.broadcast(table), "slot").withColumn("bucket", F.expr(owner)).drop("slot", "owners")


def _in_ranges(rows: DataFrame) -> DataFrame:
    """Dealt to owner tasks, each of which takes a range of buckets."""
    return rows.repartitionByRange(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), "bucket")


def exact_duplicates(docs: DataFrame, capacity: int | None = None, id_col: str = "doc_id", text_col: str = "text", key_bits: int = 64) -> DataFrame:
    """doc_id, keep_id (smallest id of the equal texts), group_size, kept and text_sha256 for every row.

    Null text counts as empty, and all empty texts are equal.  Rows that repeat an id count each; those that hold the
    smallest id of their group are all kept.  A row without an id is compared like any other, is kept only if no row
    of its group has an id, and then has a null keep_id.  An empty table gives no rows; other columns are ignored.
    """
    spark, texts = docs.sparkSession, id_text(docs, id_col, text_col)
    rows = texts.select("doc_id", normalised(F.col("text")).alias("norm"))
    entries = saved(rows.select("doc_id", key_of(F.col("norm"), key_bits).alias("key"), F.sha2(F.col("norm").cast("binary"), 256).alias("text_sha256")), "entries")
    keys = saved(entries.groupBy("key").agg(F.min("doc_id").alias("keep_id"), F.count("*").alias("group_size")), "keys")
    distinct, total = keys.agg(F.count("*"), F.coalesce(F.sum("group_size"), F.lit(0))).first()
    buckets = directory(keys.select("key"), capacity or max(LEAST_CAPACITY, distinct // MOST_BUCKETS))
    index = saved(_in_ranges(with_bucket(keys, buckets)).sortWithinPartitions("bucket", "key"), "index")

    # the texts of chains, each distinct one once per task, go to the owner of their bucket
    chained = index.where("group_size > 1").select("key")
    flagged = maybe_among(entries, chained, "key")
    suspects = maybe_among(texts, flagged.where("_maybe").select("doc_id"), "doc_id").where("_maybe")
    compared = suspects.select("doc_id", normalised(F.col("text")).alias("norm")).withColumn("key", key_of(F.col("norm"), key_bits))
    groups = compared.groupBy("key", "norm").agg(F.min("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    chain = F.collect_list(F.struct("keep_id", "group_size", "norm")).alias("chain")
    owned = _in_ranges(with_bucket(groups, buckets)).groupBy("bucket", "key").agg(chain).withColumn("texts", F.size("chain"))
    chains = owned.select("bucket", "key", "texts", F.explode("chain").alias("c")).select("bucket", "key", "texts", "c.keep_id", "c.group_size", F.when(F.col("texts") > 1, F.col("c.norm")).alias("norm"))
    chains = saved(chains.where("texts > 1 OR group_size > 1"), "chains")

    # look-up: by key where it has one text, by key and bytes where it has several
    by_key = chains.groupBy("key").agg(F.max("texts").alias("texts"), F.first("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"))
    several = chains.where("texts > 1")
    alone = flagged.where("NOT _maybe").select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), "text_sha256")
    looked = looked_up(flagged.where("_maybe").drop("_maybe"), by_key, ["key"], ["texts", "keep_id", "group_size"], "group_size", total).where("texts IS NULL OR texts = 1")
    looked = looked.select("doc_id", F.when(F.col("texts").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"), "text_sha256")
    by_bytes = compared.join(several.select("key", "norm", "keep_id", "group_size"), ["key", "norm"]).select("doc_id", "keep_id", "group_size", F.sha2(F.col("norm").cast("binary"), 256).alias("text_sha256"))
    found = alone.unionByName(looked).unionByName(by_bytes)
    return found.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def drop_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the rows that repeat an earlier row's text, all columns as they were.

    Decided by row: by id and text, so that an id with several texts loses only the copies.  Rows without an id all stay.
    Null texts are empty and equal to other empty ones.  An empty table stays empty.
    """
    gone = exact_duplicates(docs, id_col=id_col, text_col=text_col).where(~F.col("kept") & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("_gone"), F.col("text_sha256").alias("_sha"))
    gone = saved(gone, "gone")
    few = maybe_among(docs, gone, id_col, "_gone")
    sha = F.sha2(normalised(F.coalesce(F.col(text_col), F.lit(""))).cast("binary"), 256)
    here = few.where("_maybe").drop("_maybe")
    left = here.join(gone, (here[id_col] == gone["_gone"]) & (sha == gone["_sha"]), "left_anti")
    return few.where("NOT _maybe").drop("_maybe").unionByName(left)
