"""Packing of token ids into fixed windows by minimum bin slack over the length histogram.

Every document is encoded once, cut into full windows and one shorter rest.  Only piece lengths matter
afterwards, and there are at most ``capacity`` of them, so the planner works on a histogram of bounded size
however large the corpus is: it takes the longest piece left, finds by subset-sum dynamic programming over a
bitset the multiset of remaining lengths that comes closest to the capacity, walks the bitsets back to get how
many pieces of each length that takes, and repeats the pattern as often as the counts allow.  Pieces find their
place by their rank among the pieces of equal length.
"""

from __future__ import annotations

import json
import re
import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import id_text, parts_for, saved

PIECES = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64())])
_PIECES_SQL = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"

#: The split pattern of the byte-level vocabulary (fixed value).
BYTE_LEVEL_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


class ByteLevelEncoder:
    """Ids of a byte-level BPE tokenizer file, as little-endian 32-bit integers.

    A blank before a non-blank always starts a new pre-token, so a text may be cut there and each distinct word
    be encoded once; words seen first (the frequent ones) stay in a table of at most ``cached`` entries.  Texts
    in which a blank is followed by more white space are encoded whole, texts with a special token's string by
    the tokenizers library itself.
    """

    def __init__(self, path: str, cached: int = 500_000):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.path, self.full = path, None
        self.special = [t["content"] for t in spec.get("added_tokens", [])]
        # printable stand-ins of the 256 bytes, as byte-level vocabularies write them
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        char = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in set(plain))}
        byte = {c: b for b, c in char.items()}
        ranks = {bytes(byte[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in self.special}
        core = tiktoken.Encoding("byte-level", pat_str=BYTE_LEVEL_PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.encode_ordinary = core.encode_ordinary
        self.odd = re.compile(r"\s (?:\s|$)")
        self.table = _Words(core.encode_ordinary, cached)

    def __call__(self, text: str) -> bytes:
        if any(s in text for s in self.special):
            if self.full is None:
                from tokenizers import Tokenizer

                self.full = Tokenizer.from_file(self.path)
            return _packed(self.full.encode(text, add_special_tokens=False).ids)
        if len(text) < 2 or self.odd.search(text):
            return _packed(self.encode_ordinary(text))
        first, *rest = text.split(" ")
        return _packed(self.encode_ordinary(first)) + b"".join(map(self.table.__getitem__, rest))


def _packed(ids: list[int]) -> bytes:
    return struct.pack(f"<{len(ids)}I", *ids)


class _Words(dict):
    def __init__(self, encode, most: int):
        self.encode, self.most = encode, most

    def __missing__(self, word: str) -> bytes:
        ids = self.encode(" " + word)
        packed = struct.pack(f"<{len(ids)}I", *ids)
        if len(self) < self.most:
            self[word] = packed
        return packed


_ENCODERS: dict[str, ByteLevelEncoder] = {}


def _encoder(path: str) -> ByteLevelEncoder:
    """One for each Python worker, kept between tasks."""
    if path not in _ENCODERS:
        _ENCODERS[path] = ByteLevelEncoder(path)
    return _ENCODERS[path]


def token_pieces(docs: DataFrame, tokenizer_path: str, capacity: int = 1024, separator: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece of a document: full windows of ``capacity`` ids, then the rest; the separator ends a document."""
    end = struct.pack("<I", separator)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _encoder(tokenizer_path)
        for batch in batches:
            rows = ([], [], [], [], [])
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = encode(text.as_py()) + end
                n = len(ids) // 4
                for at in range(0, n, capacity):
                    part = ids[4 * at : 4 * (at + capacity)]
                    for column, value in zip(rows, (doc, at, len(part) // 4, zlib.crc32(part), n)):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in rows], schema=PIECES)

    return id_text(docs, id_col, text_col).mapInArrow(cut, _PIECES_SQL)


def closest_multiset(counts: dict[int, int], target: int) -> dict[int, int]:
    """How many pieces of which lengths sum up closest to ``target`` from below: bitset subset sums, then walked back."""
    reached, steps = 1, []
    mask = (1 << (target + 1)) - 1
    for length in sorted((x for x, c in counts.items() if c and x <= target), reverse=True):
        steps.append((length, reached))
        left, k = min(counts[length], target // length), 1
        while left:
            k = min(k, left)
            reached |= (reached << (k * length)) & mask
            left -= k
            k *= 2
        if reached >> target & 1:
            break
    total, chosen = reached.bit_length() - 1, {}
    for length, before in reversed(steps):
        k = 0
        while not before >> total & 1:
            total -= length
            k += 1
        if k:
            chosen[length] = k
    return chosen


def plan_windows(histogram: dict[int, int], capacity: int) -> list[tuple[int, dict[int, int]]]:
    """Patterns (how often, {length: pieces}) that use up the histogram.  Each pattern runs until a length falls short of it, so their number depends on the capacity, not on the corpus."""
    left = {x: c for x, c in histogram.items() if c}
    plan = []
    while left:
        longest = max(left)
        left[longest] -= 1
        pattern = closest_multiset(left, capacity - longest)
        left[longest] += 1
        pattern[longest] = pattern.get(longest, 0) + 1
        often = min(left[x] // k for x, k in pattern.items())
        plan.append((often, pattern))
        for x, k in pattern.items():
            left[x] -= often * k
            if not left[x]:
                del left[x]
    return plan


def place_pieces(pieces: DataFrame, capacity: int = 1024, each: int = 200_000) -> DataFrame:
    """Adds sequence_id and offset to pieces (a saved table: it is read three times).

    Rank among equal lengths: hash buckets with counted offsets, so that no length is ordered in one task.  The plan
    that is broadcast has at most a few intervals for each of ``capacity`` lengths.
    """
    spark = pieces.sparkSession
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    buckets = parts_for(sum(histogram.values()), each, int(spark.conf.get("spark.sql.shuffle.partitions")))
    intervals: dict[int, list[tuple]] = {}
    used, sequence = dict.fromkeys(histogram, 0), 0
    for often, pattern in plan_windows(histogram, capacity):
        at = 0
        for length, k in sorted(pattern.items(), reverse=True):
            intervals.setdefault(length, []).append((used[length], sequence, k, at))
            used[length] += often * k
            at += length * k
        sequence += often
    plan = spark.createDataFrame(list(intervals.items()), "length long, runs array<struct<first:long,sequence:long,k:long,at:long>>")

    keyed = pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "start"), F.lit(buckets)))
    counted = keyed.groupBy("length", "bucket").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    counted = counted.select("length", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    inside = Window.partitionBy("length", "bucket").orderBy("doc_id", "start", "ids_crc32")
    ranked = (
        keyed.withColumn("rank", F.row_number().over(inside) - 1)
        .join(counted, ["length", "bucket"])
        .withColumn("rank", F.col("rank") + F.col("before"))
        .join(F.broadcast(plan), "length")
        .withColumn("run", F.element_at(F.filter("runs", lambda r: r["first"] <= F.col("rank")), -1))
        .withColumn("nth", F.col("rank") - F.col("run.first"))
    )
    return ranked.select(
        "doc_id", "start", "length", "ids_crc32", "doc_tokens",
        (F.col("run.sequence") + F.expr("nth div run.k")).alias("sequence_id"),
        (F.col("run.at") + F.expr("nth % run.k") * F.col("length")).alias("offset"),
    )


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = 1024, separator: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Packs all documents into sequences of at most ``capacity`` ids.

    Null or empty text: the separator alone.  Texts of any length are cut into as many pieces as they need.  Rows that
    repeat an id are packed each on its own; a null id is kept as null.  An empty table gives no rows.  Other columns
    of ``docs`` are ignored whatever their names.
    """
    return place_pieces(saved(token_pieces(docs, tokenizer_path, capacity, separator, id_col, text_col), "pieces"), capacity)
