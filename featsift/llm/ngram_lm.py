"""Language-model scores from a log-frequency Bloom filter of n-gram counts.

Counting.  Every task hashes its training tokens to 64 bits, counts words and word pairs with its own partial sums and
sends them in packed blocks to the owner of a hash range, which adds them up.  Counts of pairs are quantised to steps
of a logarithm and enter a Bloom filter once for each step up to their own, so that a count is read by probing step
after step until a probe fails.  Word counts stay exact.

Scoring.  p(w | v) = (1 - MIX) p(w) + MIX c(v, w) / c(v), with the filter's estimate of c(v, w), at most c(v) and c(w).
Words and filter are broadcast to the workers.  They grow with the corpus, so their size is checked: beyond the bound,
words are cut into hash segments and a pass handles the tokens whose own word and word before fall into one pair of
segments.  Each token belongs to one pass and scores add up, so the result is the same at the price of more passes.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_text, saved
from .minhash_dedup import WORDS, mix, words_of

#: Base of the quantisation, probes of each step and bits for each entry of the filter.
BASE, PROBES, BITS_PER_ENTRY = 1.6, 3, 10
#: Most bytes of words and filter in one broadcast.
SEGMENT_BYTES = 320 << 20
#: Word groups at least, and texts for each of the cells they make: what one task sorts.
LEAST_GROUPS, TEXTS_OF_A_CELL = 16, 10_000
#: Weight of the pair estimate.
MIX = 0.3
END = np.uint64(0xA5A5F00DCAFE1234)
_PAIR, _STEP = np.uint64(0xC2B2AE3D27D4EB4F), 0x165667B19E3779F9


def levels(count: np.ndarray) -> np.ndarray:
    """Step of a count: 1 + floor(log_BASE(count))."""
    return 1 + np.floor(np.log(count) / np.log(BASE) + 1e-9).astype(np.int64)


def estimate(level: np.ndarray) -> np.ndarray:
    """Count that stands for a step (0 for none): the middle of what it covers."""
    low = np.ceil(BASE ** (level - 1) - 1e-9)
    high = np.maximum(low, np.ceil(BASE**level - 1e-9) - 1)
    return np.where(level > 0, (low + high) / 2, 0.0)


def tokens(text: str) -> np.ndarray:
    """Hashes of a text's words in lower case, then the end token."""
    w = words_of(text)
    h = np.empty(len(w) + 1, np.uint64)
    h[:-1] = np.fromiter(map(WORDS.__getitem__, w), np.uint64, len(w))
    h[-1] = END
    return h


def _events(held: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """The word before each token (END at the start of a text) and the token, of texts one after the other."""
    h = np.concatenate(held)
    return np.concatenate(([END], h[:-1])), h  # a text ends with END, so the next one starts after it


def held_out_remainder(doc) -> int:
    return zlib.crc32(str(doc).encode()) % 10 if doc is not None else 0


def _chunks(batches: Iterator[pa.RecordBatch], keep, size: int):
    """(row, id) and token hashes of many texts at once."""
    docs, held, n = [], [], 0
    for batch in batches:
        for row, doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
            if keep(doc):
                h = tokens(text.as_py())
                docs.append((row, doc))
                held.append(h)
                n += len(h)
                if n >= size:
                    yield docs, held
                    docs, held, n = [], [], 0
    if docs:
        yield docs, held


def _pack(keys: np.ndarray, counts: np.ndarray) -> bytes:
    small = np.minimum(counts, 255).astype(np.uint8)
    return np.uint32(len(keys)).tobytes() + keys.tobytes() + small.tobytes() + counts[small == 255].astype(np.int64).tobytes()


def _unpack(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = int(np.frombuffer(blob, np.uint32, 1)[0])
    keys, counts = np.frombuffer(blob, np.uint64, n, 4), np.frombuffer(blob, np.uint8, n, 4 + 8 * n).astype(np.int64)
    large = counts == 255
    counts[large] = np.frombuffer(blob, np.int64, int(large.sum()), 4 + 9 * n)
    return keys, counts


def _summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    new = np.ones(len(keys), bool)
    new[1:] = keys[1:] != keys[:-1]
    at = np.flatnonzero(new)
    return keys[at], np.add.reduceat(counts, at) if len(at) else counts


def _group(word: np.ndarray, groups: int) -> np.ndarray:
    """Hash group of a word: contiguous ranges of the hash, so groups in order are sorted words."""
    return (((word >> np.uint64(32)) * np.uint64(groups)) >> np.uint64(32)).astype(np.int64)


def _cells(before: np.ndarray, word: np.ndarray, groups: int) -> np.ndarray:
    return _group(before, groups) * groups + _group(word, groups)


def count_ngrams(rows: DataFrame, groups: int) -> DataFrame:
    """kind (0 words, 1 pairs), cell, n, total, payload: counts over the training texts.  rows: doc_id, text.

    Words are dealt to groups * groups finer ranges of their hash, pairs by the groups of both words.
    """
    cells = groups * groups

    def blocks(kind: int, cell: np.ndarray, keys: np.ndarray, counts: np.ndarray, out) -> None:
        order = np.argsort(cell, kind="stable")
        ends = np.searchsorted(cell[order], np.arange(cells + 1))
        for x in range(cells):
            part = order[ends[x] : ends[x + 1]]
            if len(part):
                for column, value in zip(out, (kind, x, _pack(keys[part], counts[part]))):
                    column.append(value)

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, held in _chunks(batches, lambda d: held_out_remainder(d) != 0, 2_500_000):
            out = ([], [], [])
            before, h = _events(held)
            held.clear()
            words, counts = np.unique(h, return_counts=True)
            blocks(0, _group(words, cells), words, counts, out)
            pair = mix(before * _PAIR + h)
            keys, at, counts = np.unique(pair, return_index=True, return_counts=True)
            blocks(1, _cells(before[at], h[at], groups), keys, counts, out)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int32()), pa.array(out[1], pa.int32()), pa.array(out[2], pa.binary())], names=["kind", "cell", "payload"])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def close(key, blobs):
            keys, counts = _summed(*(np.concatenate(x) for x in zip(*map(_unpack, blobs))))
            steps = int(levels(counts).sum())
            return pa.RecordBatch.from_arrays([*(pa.array([k], pa.int32()) for k in key), pa.array([len(keys)], pa.int64()), pa.array([int(counts.sum())], pa.int64()), pa.array([steps], pa.int64()), pa.array([_pack(keys, counts)], pa.binary())], names=["kind", "cell", "n", "total", "steps", "payload"])

        now, blobs = None, []
        for batch in batches:
            for kind, cell, blob in zip(*(c.to_pylist() for c in batch.columns)):
                if (kind, cell) != now and blobs:
                    yield close(now, blobs)
                    blobs = []
                now = (kind, cell)
                blobs.append(blob)
        if blobs:
            yield close(now, blobs)

    dealt = rows.mapInArrow(local, "kind int, cell int, payload binary").repartition(2 * cells, "kind", "cell").sortWithinPartitions("kind", "cell")
    return saved(dealt.mapInArrow(merge, "kind int, cell int, n long, total long, steps long, payload binary"), "ngrams")


def _bits(key: np.ndarray, step: int, size, offset=0):
    """Positions in the filter of entries (key, step), one array for each probe."""
    x = mix(key ^ np.uint64(step * _STEP % 2**64))
    jump = (x >> np.uint64(33)) | np.uint64(1)
    for i in range(PROBES):
        yield (x + np.uint64(i) * jump) % size + offset


def filters(counts: DataFrame) -> DataFrame:
    """kind, cell, data: words as hashes and 32-bit counts, pairs as the cell's Bloom filter."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for kind, cell, payload in zip(*(c.to_pylist() for c in batch.columns)):
                keys, c = _unpack(payload)
                if kind == 0:
                    data = keys.tobytes() + np.minimum(c, 2**32 - 1).astype(np.uint32).tobytes()
                else:
                    level = levels(c)
                    size = -(-max(64, BITS_PER_ENTRY * int(level.sum())) // 8) * 8
                    bits = np.zeros(size, np.uint8)
                    for step in range(1, int(level.max()) + 1):
                        for probe in _bits(keys[level >= step], step, np.uint64(size), np.uint64(0)):
                            bits[probe.astype(np.int64)] = 1
                    data = np.packbits(bits, bitorder="little").tobytes()
                yield pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([cell], pa.int32()), pa.array([data], pa.binary())], names=["kind", "cell", "data"])

    return saved(counts.select("kind", "cell", "payload").mapInArrow(run, "kind int, cell int, data binary"), "filters")


class Model:
    """What one pass needs: the words of the groups of either side, and the filters of their cells."""

    def __init__(self, blocks: DataFrame, groups: int, left: range, right: range):
        self.groups, self.left, self.right = groups, left, right
        self.words = [self._words(blocks, side) for side in ((left,) if left == right else (left, right))]
        cells = [a * groups + b for a in left for b in right]
        found = blocks.where((F.col("kind") == 1) & F.col("cell").isin(cells)).select("cell", "data").toLocalIterator()
        self.size, self.offset = np.ones(groups * groups, np.uint64), np.zeros(groups * groups, np.uint64)
        parts, at = [np.zeros(1, np.uint8)], 8  # a cell without pairs points to an empty byte
        for r in found:
            self.size[r["cell"]], self.offset[r["cell"]] = 8 * len(r["data"]), at
            parts.append(np.frombuffer(r["data"], np.uint8))
            at += 8 * len(r["data"])
        self.filter = np.concatenate(parts)

    def _words(self, blocks: DataFrame, side: range) -> tuple[np.ndarray, np.ndarray]:
        low, high = side.start * self.groups, side.stop * self.groups
        found = blocks.where((F.col("kind") == 0) & (F.col("cell") >= low) & (F.col("cell") < high)).orderBy("cell").select("data").toLocalIterator()
        keys, counts = [np.empty(0, np.uint64)], [np.empty(0, np.uint32)]
        for r in found:
            n = len(r["data"]) // 12
            keys.append(np.frombuffer(r["data"], np.uint64, n))
            counts.append(np.frombuffer(r["data"], np.uint32, n, 8 * n))
        return np.concatenate(keys), np.concatenate(counts)

    def count(self, word: np.ndarray, side: int) -> np.ndarray:
        """Exact count in the training texts; 0 for others."""
        keys, counts = self.words[min(side, len(self.words) - 1)]
        if not len(keys):
            return np.zeros(len(word), np.int64)
        i = np.minimum(np.searchsorted(keys, word), len(keys) - 1)
        return np.where(keys[i] == word, counts[i], 0).astype(np.int64)

    def step(self, pair: np.ndarray, cell: np.ndarray) -> np.ndarray:
        """Step of each pair's count: probed upwards until one is missing."""
        found, at, step = np.zeros(len(pair), np.int64), np.arange(len(pair)), 0
        while len(at):
            step += 1
            size, offset = self.size[cell[at]], self.offset[cell[at]]
            here = np.ones(len(at), bool)
            for probe in _bits(pair[at], step, size, offset):
                here &= (self.filter[(probe >> np.uint64(3)).astype(np.int64)] >> (probe & np.uint64(7)).astype(np.uint8) & 1).astype(bool)
            at = at[here]
            found[at] = step
        return found


def score_pass(rows: DataFrame, model, total: int, distinct: int) -> DataFrame:
    """Sums over the tokens of one pass for each text: tokens, known ones, base score, score.  rows: row, doc_id, text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: Model = model.value
        for docs, held in _chunks(batches, lambda d: True, 400_000):
            size = np.array([len(h) for h in held], np.int64)
            before, h = _events(held)
            held.clear()
            doc = np.repeat(np.arange(len(docs)), size)
            mine = None
            if len(m.left) < m.groups or len(m.right) < m.groups:
                a, b = _group(before, m.groups), _group(h, m.groups)
                mine = (a >= m.left.start) & (a < m.left.stop) & (b >= m.right.start) & (b < m.right.stop)
                before, h, doc = before[mine], h[mine], doc[mine]
            # each distinct pair is looked up once
            order = np.lexsort((before, h))
            h, before, doc = h[order], before[order], doc[order]
            new = np.ones(len(h), bool)
            new[1:] = (h[1:] != h[:-1]) | (before[1:] != before[:-1])
            back = np.cumsum(new) - 1
            w, v = h[new], before[new]
            c, context = m.count(w, 1), m.count(v, 0)
            alone = (c + 0.1) / (total + 0.1 * (distinct + 1))
            both = np.minimum(estimate(m.step(mix(v * _PAIR + w), _cells(v, w, m.groups))), np.minimum(c, context))
            p = (1 - MIX) * alone + MIX * np.where(context > 0, both / np.maximum(context, 1), alone)
            sums = [np.bincount(doc, None if x is None else x[back], len(docs)) for x in (None, (c > 0).astype(float), np.log10(alone), np.log10(p))]
            row, ids = zip(*docs)
            yield pa.RecordBatch.from_arrays([pa.array(row, pa.int64()), pa.array(ids, pa.int64()), *(pa.array(np.rint(x).astype(np.int64)) for x in sums[:2]), pa.array(sums[2], pa.float64()), pa.array(sums[3], pa.float64())], names=["row", "doc_id", "n_tokens", "n_known", "base_score", "score"])

    return rows.mapInArrow(run, "row long, doc_id long, n_tokens long, n_known long, base_score double, score double")


def language_scores(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", segment_bytes: int = SEGMENT_BYTES, groups: int | None = None) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score (log10 probabilities) per row.

    Learns from the texts whose crc32(id as text) mod 10 is not 0.  Null or empty text: the end token alone.  Rows that
    repeat an id are scored each on its own and train each; a null id is held out.  With nothing to learn from, counts
    are 0 and the base score is defined by N = V = 0.  An empty table gives no rows; other columns are ignored.
    """
    spark = docs.sparkSession
    rows = id_text(docs, id_col, text_col).select(F.monotonically_increasing_id().alias("row"), "doc_id", "text")
    if groups is None:  # cells of a size that one task sorts, whatever the corpus
        groups = LEAST_GROUPS
        n = docs.count()
        while groups * groups * TEXTS_OF_A_CELL < n:
            groups *= 2
    counts = count_ngrams(rows, groups)
    kinds = {r["kind"]: r for r in counts.groupBy("kind").agg(F.sum("n").alias("n"), F.sum("total").alias("total"), F.sum("steps").alias("steps")).collect()}
    total, distinct = (kinds[0]["total"], kinds[0]["n"]) if 0 in kinds else (0, 0)
    pair_bytes = kinds[1]["steps"] * BITS_PER_ENTRY // 8 if 1 in kinds else 0
    blocks = filters(counts)
    segments = 1
    while segments < groups and 12 * distinct * (2 if segments > 1 else 1) / segments + pair_bytes / segments**2 > segment_bytes:
        segments *= 2
    sides = [range(i * groups // segments, (i + 1) * groups // segments) for i in range(segments)]
    if segments == 1:
        found = score_pass(rows, spark.sparkContext.broadcast(Model(blocks, groups, sides[0], sides[0])), total, distinct)
    else:  # one model at a time: a pass is written before the next one is broadcast
        found = None
        for a in sides:
            for b in sides:
                model = spark.sparkContext.broadcast(Model(blocks, groups, a, b))
                one = saved(score_pass(rows, model, total, distinct), "pass")
                model.destroy()
                found = one if found is None else found.union(one)
        found = found.groupBy("row", "doc_id").agg(*(F.sum(c).alias(c) for c in ("n_tokens", "n_known", "base_score", "score")))
    held_out = (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 10 == 0) | F.col("doc_id").isNull()
    return found.select("doc_id", held_out.alias("held_out"), "n_tokens", "n_known", F.lit(total).cast("long").alias("train_tokens"), "base_score", "score")
