"""Chat formatting with cumulative snapshots collapsed.

A log that saves a conversation after each turn holds every prefix of it.  The turns of a conversation get a rolling
hash: running sums of two 64-bit hashes of each turn and its place, so a turn's digest covers all turns up to it.  A
conversation is a snapshot if its last digest is that of a proper prefix of a longer one, and a copy if an equal
conversation has a smaller id.  Digests are reduced to one row each before anti-joins drop both kinds; the turns
themselves join last, by conversation.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import saved

_TURN = ("turn", "role", "text")


def turn_rows(turns: DataFrame, id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """conv_id, turn, role and text; null text is empty, null role 'unknown'; turns of no conversation are left out."""
    rows = turns.select(F.col(id_col).cast("long").alias("conv_id"), F.col(turn_col).cast("long").alias("turn"), F.coalesce(F.col(role_col), F.lit("unknown")).alias("role"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return rows.where("conv_id IS NOT NULL")


def turn_table(rows: DataFrame) -> DataFrame:
    """conv_id, turns: the turns in order (ties by role and text), each a struct of turn, role and text."""
    return rows.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct(*_TURN))).alias("turns"))


def prefix_digests(rows: DataFrame) -> DataFrame:
    """conv_id, place, digest of each turn, and whether it is the last one of its conversation."""
    by_place = Window.partitionBy("conv_id").orderBy(*_TURN)
    placed = rows.withColumn("place", F.row_number().over(by_place)).withColumn("after", F.lead(F.lit(1)).over(by_place))
    hashes = placed.select("conv_id", "place", "after", *[F.xxhash64(F.lit(s), "place", "role", "text").cast("decimal(20,0)").alias(f"h{s}") for s in (1, 2)])
    running = Window.partitionBy("conv_id").orderBy("place").rowsBetween(Window.unboundedPreceding, 0)
    sums = [F.sum(f"h{s}").over(running).cast("string") for s in (1, 2)]
    return hashes.select("conv_id", "place", F.concat_ws(":", *sums).alias("digest"), F.col("after").isNull().alias("last"))


def maximal_conversations(turns: DataFrame, id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """conv_id, turns and n_turns of the conversations that are neither a proper prefix nor a later copy of another.

    Turns without a conversation id belong to none and are left out; null turn numbers sort first; repeated rows are
    repeated turns.  Texts of any length are hashed whole.  An empty table gives no rows; other columns are ignored.
    """
    rows = turn_rows(turns, id_col, turn_col, role_col, text_col)
    digests = saved(prefix_digests(rows), "digests")
    first = digests.where("last").groupBy("digest").agg(F.min("conv_id").alias("conv_id"), F.max("place").alias("n_turns"))
    longer = digests.where("NOT last").select("digest").distinct()
    kept = first.join(longer, "digest", "left_anti").select("conv_id", F.col("n_turns").cast("long").alias("n_turns"))
    return turn_table(rows).join(kept, "conv_id").select("conv_id", "turns", "n_turns")


def rendered(turns: Column) -> Column:
    """Turns under role headers, each closed by an end mark."""
    return F.concat_ws("", F.transform(turns, lambda t: F.concat(F.lit("<|"), t["role"], F.lit("|>\n"), t["text"], F.lit("<|end|>\n"))))


def format_chats(turns: DataFrame, **columns: str) -> DataFrame:
    """conv_id, n_turns and the rendered text of every maximal conversation."""
    return maximal_conversations(turns, **columns).select("conv_id", "n_turns", rendered(F.col("turns")).alias("chat"))
