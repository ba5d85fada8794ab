"""Sparse data of texts: tokens are counted with the class at once, and only those that a selection needs become blocks."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .dataset import SparseDataset
from .storage import saved

#: Classes with at most so many rows are broadcast to the texts; of more classes than MAX_CLASSES none are counted by column.
BROADCAST_ROWS, MAX_CLASSES = 1_000_000, 64
#: Entries of a block; distinct tokens whose counts a task holds at once.
BLOCK_ENTRIES, HELD = 1 << 19, 1 << 20
_WORDS = re.compile("[a-z]+")


def _split(ngram: int, buckets: int | None = None) -> Callable[[str], set]:
    """The distinct runs of ``ngram`` tokens of a text in lower case, or the buckets that ``encode.hashed`` puts them in."""
    find = _WORDS.findall

    def grams(text: str) -> set:
        words = find(text)
        return set(words if ngram == 1 else map(" ".join, zip(*(words[i:] for i in range(ngram)))))

    if not buckets:
        return grams
    digest = xxhash.xxh64_intdigest
    if not buckets & (buckets - 1):
        # the lowest bits are the same with and without a sign
        return lambda text: {digest(t, 42) & (buckets - 1) for t in grams(text)}
    return lambda text: {((digest(t, 42) ^ 1 << 63) - (1 << 63)) % buckets for t in grams(text)}


def _g(c: Column) -> Column:
    c = c.cast("double")
    return F.when(c > 0, c * F.log2(F.greatest(c, F.lit(1.0)))).otherwise(0.0)


class TokenSet(SparseDataset):
    """Rows with the tokens that they contain; ``inside`` picks the rows that count, all texts make the vocabulary.

    Postings and vocabulary are made (by ``make``) when they are asked for.  A selection whose scores relevance bounds
    needs neither: ``counted`` has the counts of all tokens, ``blocks`` the rows of a few.
    """

    def __init__(self, rows: DataFrame, classes: DataFrame, make: Callable[[], SparseDataset], name: str, ngram: int = 1, buckets: int | None = None, min_df: int = 1, inside: Column | None = None):
        """rows: row_id, text; classes: row_id, y; buckets: tokens are hashed to so many numbers, which then are the features."""
        self.rows, self.every, self.make, self.name, self.ngram, self.buckets, self.min_df = rows, classes, make, name, ngram, buckets, min_df
        self.inside = F.lit(True) if inside is None else inside
        self.spark = rows.sparkSession
        self._stored = False

    @cached_property
    def full(self) -> SparseDataset:
        whole = self.make()
        return SparseDataset(whole.postings.where(self.inside), whole.classes.where(self.inside), whole.vocabulary, whole.name)

    @property
    def postings(self) -> DataFrame:
        return self.full.postings

    @property
    def vocabulary(self) -> DataFrame:
        return self.full.vocabulary

    @property
    def classes(self) -> DataFrame:
        return self.every.where(self.inside)

    @cached_property
    def size(self) -> int:
        return self.counted.count() if self.plain else self.vocabulary.count()

    def within(self, inside: Column) -> TokenSet:
        """The same vocabulary on some of the rows."""
        return TokenSet(self.rows, self.every, self.make, self.name, self.ngram, self.buckets, self.min_df, inside)

    @cached_property
    def _classed(self) -> DataFrame:
        return saved(self.every.select("row_id", F.col("y").cast("int").alias("y"), self.inside.alias("inside")), "classes")

    @cached_property
    def _sizes(self) -> dict[tuple[int, bool], int]:
        return {(r["y"], r["inside"]): r["c"] for r in self._classed.groupBy("y", "inside").agg(F.count("*").alias("c")).collect()}

    @cached_property
    def class_codes(self) -> list[int]:
        return sorted({y for y, _ in self._sizes})

    @property
    def class_counts(self) -> np.ndarray:
        """Rows inside by class."""
        return np.array([self._sizes.get((y, True), 0) for y in self.class_codes], np.float64)

    @cached_property
    def plain(self) -> bool:
        """Whether every row has one text and one class: all that the short way counts."""
        if any(y is None or i is None for y, i in self._sizes) or len({y for y, _ in self._sizes}) > MAX_CLASSES:
            return False
        return self._met(self.rows.select("row_id")).groupBy("row_id").agg(F.count("*").alias("c")).where("c > 1").isEmpty()

    def _met(self, rows: DataFrame) -> DataFrame:
        small = sum(self._sizes.values()) <= BROADCAST_ROWS
        return rows.join(F.broadcast(self._classed) if small else self._classed, "row_id")

    @cached_property
    def counted(self) -> DataFrame:
        """key, df, and c0, c1, ..: the rows that have a token, and those inside by class."""
        place = F.array_position(F.array(*[F.lit(y) for y in self.class_codes]), F.col("y")).cast("int") - 1
        rows = self._met(self.rows).select(F.when(F.col("inside"), place).otherwise(-1).alias("slot"), F.lower("text"))
        split, slots, kind = _split(self.ngram, self.buckets), len(self.class_codes) + 1, pa.int64() if self.buckets else pa.string()

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = [Counter() for _ in range(slots)]

            def out():
                for slot, found in enumerate(held, -1):
                    keys = iter(found)
                    for at in range(0, len(found), 1 << 16):
                        some = [next(keys) for _ in range(min(1 << 16, len(found) - at))]
                        yield pa.RecordBatch.from_arrays([pa.array(some, kind), pa.array(np.full(len(some), slot, np.int32)), pa.array([found[k] for k in some], pa.int64())], names=["key", "slot", "n"])
                for found in held:
                    found.clear()

            for batch in batches:
                for slot, value in zip(batch.column(0).to_pylist(), batch.column(1)):
                    if (value := value.as_py()) is not None:
                        held[slot + 1].update(split(value))
                        if sum(map(len, held)) > HELD:
                            yield from out()
            yield from out()

        partial = rows.mapInArrow(count, f"key {'long' if self.buckets else 'string'}, slot int, n long").groupBy("key")
        found = partial.agg(F.sum("n").alias("df"), *[F.sum(F.when(F.col("slot") == i, F.col("n")).otherwise(0)).alias(f"c{i}") for i in range(slots - 1)])
        return saved(found.where(F.col("df") >= self.min_df), "counted")

    def pool(self, m: int) -> tuple[list, np.ndarray, float]:
        """The m most relevant tokens in their order, their rows inside by class, and the relevance of the best one left out."""
        sizes, columns = self.class_counts, [f"c{i}" for i in range(len(self.class_codes))]
        n = max(sizes.sum(), 1.0)
        own = sum((F.col(c) for c in columns), F.lit(0))
        s_xy = sum((_g(F.col(c)) + _g(F.lit(float(s)) - F.col(c)) for c, s in zip(columns, sizes)), F.lit(0.0))
        s_y = float(sum(s * np.log2(s) for s in sizes if s > 0))
        rel = F.lit(float(np.log2(n))) + (s_xy - _g(own) - _g(F.lit(float(sizes.sum())) - own) - F.lit(s_y)) / F.lit(float(n))
        top = self.counted.select("key", *columns, rel.alias("rel")).orderBy(F.desc(F.round("rel", 12)), "key").limit(m + 1).toArrow().sort_by([("rel", "descending"), ("key", "ascending")])
        bound = top.column("rel")[m].as_py() if top.num_rows > m else -np.inf
        top = top.slice(0, m).sort_by("key")
        return top.column("key").to_pylist(), np.array([top.column(c).to_numpy() for c in columns], np.int64).reshape(len(columns), -1).T, bound

    def blocks(self, keys: list) -> DataFrame:
        """n, inside, ptr, feature, y: whole rows with the places of those of the given tokens that they have, written once."""
        kind = np.uint16 if len(keys) <= 1 << 16 else np.int32
        place, split = dict(zip(keys, range(len(keys)))), _split(self.ngram, self.buckets)
        shared = self.spark.sparkContext.broadcast(place)

        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            place = shared.value
            held = {side: ([0], [], []) for side in (False, True)}

            def block(side):
                ptr, feature, y = held[side]
                parts = (np.array(ptr, np.int32), np.array(feature, kind), np.array(y, np.int32))
                held[side] = ([0], [], [])
                return pa.RecordBatch.from_arrays([pa.array([len(y)], pa.int64()), pa.array([side]), *(pa.array([p.tobytes()], pa.binary()) for p in parts)], names=["n", "inside", "ptr", "feature", "y"])

            for batch in batches:
                for side, y, value in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                    if (value := value.as_py()) is None:
                        continue
                    found = [place[t] for t in split(value) if t in place]
                    if found:
                        ptr, feature, classes = held[side]
                        feature += found
                        ptr.append(len(feature))
                        classes.append(y)
                        if len(feature) >= BLOCK_ENTRIES:
                            yield block(side)
            for side in (False, True):
                if held[side][2]:
                    yield block(side)

        rows = self._met(self.rows).select("inside", "y", F.lower("text"))
        return saved(rows.mapInArrow(pack, "n long, inside boolean, ptr binary, feature binary, y binary"), "blocks")

    def named(self, key) -> str:
        return f"h{key}" if self.buckets else key

    def numbers(self, keys: list) -> list[int]:
        """Feature numbers of tokens: how many of the vocabulary come before them; hashed ones are numbers already."""
        if not keys or self.buckets:
            return [int(k) for k in keys]
        r = self.counted.agg(*[F.sum(F.when(F.col("key") < k, 1).otherwise(0)).alias(f"k{i}") for i, k in enumerate(keys)]).first()
        return [int(r[f"k{i}"]) for i in range(len(keys))]

    def presence(self, blocks: DataFrame, places: list[int]) -> DataFrame:
        """inside, y, at (which of the places a row has, by their order), weight: equal rows once, those with none included."""
        order = np.full(max(places, default=0) + 1, -1, np.int32)
        order[places] = np.arange(len(places))

        def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for r in range(batch.num_rows):
                    n, inside = batch.column(0)[r].as_py(), batch.column(1)[r].as_py()
                    ptr, y = (np.frombuffer(batch.column(i)[r].as_buffer(), np.int32) for i in (2, 4))
                    raw = batch.column(3)[r].as_buffer()
                    feature = np.frombuffer(raw, np.uint16 if raw.size == 2 * ptr[-1] else np.int32)
                    here = np.flatnonzero(feature < len(order))
                    at = order[feature[here]]
                    here, at = here[at >= 0], at[at >= 0]
                    row = np.searchsorted(ptr, here, side="right") - 1
                    by = np.lexsort((at, row))
                    ends = np.searchsorted(row[by], np.arange(n + 1)).astype(np.int32)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(n, inside)), pa.array(y), pa.ListArray.from_arrays(pa.array(ends), pa.array(at[by].astype(np.int32)))], names=["inside", "y", "at"])

        found = blocks.mapInArrow(find, "inside boolean, y int, at array<int>").groupBy("inside", "y", "at").agg(F.count("*").alias("weight"))
        # rows without any of the tokens in the blocks are in none
        held = {(r["y"], r["inside"]): r["c"] for r in found.groupBy("inside", "y").agg(F.sum("weight").alias("c")).collect()}
        none = [(i, y, [], c - held.get((y, i), 0)) for (y, i), c in self._sizes.items() if c > held.get((y, i), 0)]
        return found.union(self.spark.createDataFrame(none, "inside boolean, y int, at array<int>, weight long"))
