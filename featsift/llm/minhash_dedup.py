"""Near-duplicates on word shingles: banded MinHash candidates, sequential Bayesian pruning, exact verification.

1. Every text becomes its set of distinct shingle hashes (64 bits); from it come the set's 128-bit class key and the
   band keys.  Equal sets need no comparison.
2. Rows that share a band key are candidates.  Each task links the rows of a key to one leader and sends on only the
   leader, so a key that a third of all rows share arrives once per task; connected candidates form neighbourhoods.
3. Distinct sets of a neighbourhood meet in blocks of bounded bytes.  Signatures are compared batch by batch; a pair
   leaves as soon as the posterior probability that its similarity reaches the threshold falls below the miss
   probability.  Survivors are verified on the full sets in order of their estimate, except those whose ends already
   belong together.
4. Where a neighbourhood has several blocks, one set of each group found so far meets the others', and then every set
   that isn't in the neighbourhood's largest group meets all blocks.  Pairs inside one group add nothing, so a group of
   near copies of any size costs about its own bytes, not their square; no other pair of the neighbourhood is left out.
5. Verified links give the components.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from fractions import Fraction
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_text, looked_up, maybe_among, saved
from .components import connected_components

BANDS, ROWS = 42, 6
#: Hashes compared before each look at the posterior.
BATCH = 36
MISS = 1e-7
#: Bytes of signatures and sets in one block.
BLOCK_BYTES = 2 << 20

_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


class _WordHashes(dict):
    """Hashes of the words seen by a Python worker, the first ``most`` of them kept."""

    def __init__(self, most: int = 200_000):
        self.most = most

    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh3_64_intdigest(word)
        if len(self) < self.most:
            self[word] = h
        return h


WORDS = _WordHashes()


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def words_of(text: str) -> list[bytes]:
    """Words of a text in lower case (A to Z only): runs of anything but ASCII white space."""
    return text.encode("utf-8", "surrogatepass").translate(_LOWER).split()


def shingles(text: str, width: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles; with fewer words, of the whole sequence as one."""
    words = words_of(text)
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(WORDS.__getitem__, words), np.uint64, len(words))
    n = min(width, len(words))
    s = np.full(len(words) - n + 1, n, np.uint64)
    for i in range(n):
        s = s * _MULTIPLIER + h[i : len(h) - n + 1 + i]
    return np.unique(mix(s))


@lru_cache
def _permutations(count: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20_240_607)
    return (rng.integers(0, 2**32, count, np.uint32)[:, None], (rng.integers(0, 2**31, count, np.uint32) * np.uint32(2) + np.uint32(1))[:, None])


def signature(s: np.ndarray, count: int = BANDS * ROWS) -> np.ndarray:
    """MinHash values of a non-empty set, 32 bits each."""
    salt, odd = _permutations(count)
    x = (s >> np.uint64(32)).astype(np.uint32)
    least = np.full(count, 2**32 - 1, np.uint32)
    for at in range(0, len(x), 1024):
        part = (x[None, at : at + 1024] ^ salt) * odd
        part ^= part >> np.uint32(15)
        part *= np.uint32(0x2C1B3C6D)
        np.minimum(least, part.min(axis=1), out=least)
    return least


def band_keys(sig: np.ndarray) -> np.ndarray:
    rows = sig.reshape(BANDS, ROWS).astype(np.uint64)
    key = np.arange(1, BANDS + 1, dtype=np.uint64)
    for i in range(ROWS):
        key = mix(key * _MULTIPLIER + rows[:, i])
    return key


@lru_cache
def least_matches(n: int, threshold: float, miss: float = MISS) -> int:
    """Fewest matches of ``n`` compared hashes at which a pair stays: with a uniform prior, P(similarity >= threshold | m of n) is P(Binomial(n + 1, threshold) <= m)."""
    below = 0.0
    for m in range(n + 1):
        below += math.comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
        if below >= miss:
            return m
    return n


def similar(a: np.ndarray, b: np.ndarray, threshold: Fraction) -> bool:
    """Whether the Jaccard similarity of two sorted sets reaches the threshold, in integers."""
    if min(len(a), len(b)) * threshold.denominator < max(len(a), len(b)) * threshold.numerator:
        return False
    both = np.concatenate((a, b))
    both.sort(kind="stable")
    common = int((both[1:] == both[:-1]).sum())
    return common * threshold.denominator >= (len(both) - common) * threshold.numerator


def link_block(sigs: np.ndarray, sets: list[np.ndarray], threshold: Fraction, split: int | None = None, groups: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links that connect a block as all its links would.  ``split``: only pairs across this position count.  ``groups``: what belongs together already."""
    n = len(sets)
    if n < 2:
        return []
    t, hashes = float(threshold), sigs.shape[1]
    low = np.ascontiguousarray(sigs.astype(np.uint16).T)
    sizes = np.array([len(s) for s in sets], np.int64)
    label, links = np.arange(n) if groups is None else np.unique(groups, return_inverse=True)[1], []
    members = {g: np.flatnonzero(label == g).tolist() for g in np.unique(label).tolist()}
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def join(i: int, j: int) -> None:
        links.append((i, j))
        a, b = sorted((int(label[i]), int(label[j])), key=lambda x: len(members[x]))
        label[members[a]] = b
        members[b] += members.pop(a)

    def settle() -> None:
        """Verifies what has survived, best estimate first."""
        if not found:
            return
        i, j, m = (np.concatenate(x) for x in zip(*found))
        found.clear()
        order = np.argsort(-m, kind="stable")
        i, j = i[order], j[order]
        at = 0
        while at < len(i):
            # look ahead in growing steps for pairs whose ends aren't joined yet
            part = slice(at, at + 4096)
            open_ = np.flatnonzero(label[i[part]] != label[j[part]])
            if not len(open_):
                at += 4096
                continue
            at += int(open_[0])
            if similar(sets[i[at]], sets[j[at]], threshold):
                join(int(i[at]), int(j[at]))
            at += 1

    waiting, step = 0, max(1, min(n, 4_000_000 // n))
    for start in range(0, n, step):
        rows = np.arange(start, min(start + step, n))
        if split is not None and rows[0] >= split:
            break
        left = start if split is None else split
        columns = np.arange(left, n)
        live = columns[None, :] > rows[:, None] if split is None else np.broadcast_to(rows[:, None] < split, (len(rows), n - left))
        live = live & (label[rows][:, None] != label[None, left:])
        live &= np.minimum(sizes[rows][:, None], sizes[None, left:]) * threshold.denominator >= np.maximum(sizes[rows][:, None], sizes[None, left:]) * threshold.numerator
        first = min(BATCH, hashes)
        count = np.zeros(live.shape, np.uint8)
        for k in range(first):
            count += low[k, rows][:, None] == low[k, left:][None, :]
        a, b = np.nonzero(live & (count >= least_matches(first, t)))
        m = count[a, b].astype(np.int32)
        a += start
        b += left
        for at in range(first, hashes, BATCH):
            to = min(at + BATCH, hashes)
            for k in range(at, to):
                m += low[k, a] == low[k, b]
            keep = m >= least_matches(to, t)
            a, b, m = a[keep], b[keep], m[keep]
        if len(a):
            found.append((a, b, m))
            waiting += len(a)
        if waiting > 2_000_000:
            settle()
            waiting = 0
    settle()
    return links


def shingle_rows(docs: DataFrame, width: int) -> DataFrame:
    """doc_id, n_shingles, the set's class key and its band keys, for every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, key, bands = [], [], []
            for text in batch.column(1):
                s = shingles(text.as_py(), width)
                n.append(len(s))
                key.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                bands.append(band_keys(signature(s)).tobytes() if len(s) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(key, pa.binary()), pa.array(bands, pa.binary())], names=["doc_id", "n_shingles", "key", "bands"])

    return id_text(docs).mapInArrow(run, "doc_id long, n_shingles long, key binary, bands binary")


def _stars(ids: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Edges from the rows of each key to its smallest id; the distinct keys and those ids."""
    order = np.lexsort((ids, keys))
    keys, ids = keys[order], ids[order]
    new = np.ones(len(keys), bool)
    new[1:] = keys[1:] != keys[:-1]
    leader = ids[np.flatnonzero(new)[np.cumsum(new) - 1]]
    edge = leader != ids
    u, v = ids[edge], leader[edge]
    order = np.lexsort((v, u))
    u, v = u[order], v[order]
    once = np.ones(len(u), bool)
    once[1:] = (u[1:] != u[:-1]) | (v[1:] != v[:-1])
    return u[once], v[once], keys[new], ids[new]


def candidate_edges(rows: DataFrame, buckets: int) -> DataFrame:
    """(u, v) that connect all rows with a band key in common, without naming all pairs."""
    packed = "bucket int, u long, v long, payload binary"

    def edges_batch(u, v):
        return pa.RecordBatch.from_arrays([pa.nulls(len(u), pa.int32()), pa.array(u, pa.int64()), pa.array(v, pa.int64()), pa.nulls(len(u), pa.binary())], names=["bucket", "u", "v", "payload"])

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, keys, held = [], [], 0

        def flush():
            k = np.frombuffer(b"".join(keys), np.uint64)
            u, v, k, leader = _stars(np.repeat(np.array(ids, np.int64), BANDS), k)
            yield edges_batch(u, v)
            to = (k % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(to, kind="stable")
            ends = np.searchsorted(to[order], np.arange(buckets + 1))
            k, leader = k[order], leader[order]
            full = [b for b in range(buckets) if ends[b] < ends[b + 1]]
            blobs = [k[ends[b] : ends[b + 1]].tobytes() + leader[ends[b] : ends[b + 1]].tobytes() for b in full]
            yield pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.nulls(len(full), pa.int64()), pa.nulls(len(full), pa.int64()), pa.array(blobs, pa.binary())], names=["bucket", "u", "v", "payload"])

        for batch in batches:
            for doc, bands in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids.append(doc)
                keys.append(bands)
            held += batch.num_rows
            if held >= 50_000:
                yield from flush()
                ids, keys, held = [], [], 0
        if held:
            yield from flush()

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, ids = [], []
        for batch in batches:
            for blob in batch.column(0).to_pylist():
                half = len(blob) // 2
                keys.append(np.frombuffer(blob, np.uint64, half // 8))
                ids.append(np.frombuffer(blob, np.int64, half // 8, half))
        if keys:
            u, v, _, _ = _stars(np.concatenate(ids), np.concatenate(keys))
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])

    first = saved(rows.where("bands IS NOT NULL AND doc_id IS NOT NULL").select("doc_id", "bands").mapInArrow(local, packed), "bands")
    across = first.where("payload IS NOT NULL").repartition(buckets, "bucket").select("payload").mapInArrow(merge, "u long, v long")
    return first.where("payload IS NULL").select("u", "v").union(across).distinct()


def _in_blocks(groups: DataFrame, size: str, block_bytes: int, out: str) -> DataFrame:
    """``groups`` of more than one row with the number of blocks of each component (``out``s) and the block of each row (``out``)."""
    blocks = groups.groupBy("component").agg(F.ceil(F.sum(size) / block_bytes).cast("int").alias(f"{out}s"), F.count("*").alias("n"))
    placed = looked_up(groups, saved(blocks, "blocks"), ["component"], [f"{out}s", "n"], "n", groups.count()).where("n > 1").drop("n")
    return placed.withColumn(out, F.pmod(F.xxhash64("doc_id"), F.col(f"{out}s")).cast("int"))


def _linked(dealt: DataFrame, keys: list[str], threshold: Fraction, parts: int) -> DataFrame:
    """(u, v) of the verified links inside each key, or across its two sides.  dealt: keys, side (0, 1 or null for none), label, doc_id, sig, members."""
    dealt = dealt.select(*keys, "side", "label", "doc_id", "sig", "members").repartition(parts, *keys).sortWithinPartitions(*keys, "side", "doc_id")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        u: list[int] = []
        v: list[int] = []

        def close():
            if len(held) > 1:
                side, label, ids, sigs, sets = zip(*held)
                split = None if side[0] is None else side.count(0)
                if split is None or 0 < split < len(held):
                    s = np.frombuffer(b"".join(sigs), np.uint32).reshape(len(ids), -1)
                    for i, j in link_block(s, [np.frombuffer(m, np.uint64) for m in sets], threshold, split, None if label[0] is None else np.array(label)):
                        u.append(ids[i])
                        v.append(ids[j])
            held.clear()

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if row[: len(keys)] != now:
                    close()
                    now = row[: len(keys)]
                held.append(row[len(keys) :])
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])
            u.clear()
            v.clear()
        close()
        yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])

    return dealt.mapInArrow(verify, "u long, v long")


def _labelled(rows: DataFrame, links: DataFrame) -> DataFrame:
    """``rows`` with the smallest id that each is linked to so far as label."""
    found = connected_components(links).select(F.col("node"), F.col("component").alias("label"))
    return rows.join(found, rows.doc_id == found.node, "left").drop("node").withColumn("label", F.coalesce("label", "doc_id"))


def verified_links(docs: DataFrame, groups: DataFrame, width: int, threshold: Fraction, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(u, v) of links that connect each group as all its links would.  groups: doc_id, component, n_shingles; one row per distinct set."""
    parts = 4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    sized = groups.select("doc_id", "component", (F.col("n_shingles") * 8 + 4 * BANDS * ROWS).alias("size"))
    placed = saved(_in_blocks(sized, "size", block_bytes, "block"), "placed")
    several = placed.where("blocks > 1")
    many = bool(several.limit(1).count())
    text = maybe_among(docs, placed).where("_maybe").join(placed, "doc_id")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                found = [shingles(t.as_py(), width) for t in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), *part.columns[2:], pa.array([signature(s).tobytes() for s in found], pa.binary()), pa.array([s.tobytes() for s in found], pa.binary())], names=["doc_id", "component", "block", "blocks", "sig", "members"])

    with_sets = text.select("doc_id", "text", "component", "block", "blocks").mapInArrow(sets, "doc_id long, component long, block int, blocks int, sig binary, members binary")
    if many:
        with_sets = saved(with_sets, "sets")
    none = [F.lit(None).cast("int").alias("side"), F.lit(None).cast("long").alias("label")]
    links = _linked(with_sets.select("*", *none), ["component", "block"], threshold, parts)
    if not many:
        return links
    sets_of = with_sets.select("doc_id", "sig", "members")

    # the smallest id of each group stands for it
    links = saved(links, "links")
    labelled = saved(_labelled(several.select("doc_id", "component", "size", "block", "blocks"), links), "labelled")
    heads = saved(_in_blocks(labelled.where("doc_id = label").select("doc_id", "component", "size"), "size", block_bytes, "part"), "heads")
    links = saved(links.union(_linked(heads.join(sets_of, "doc_id").select("*", *none), ["component", "part"], threshold, parts)), "links")

    # what isn't in the largest group of its component meets every block
    labelled = saved(_labelled(labelled.drop("label"), links), "labelled")
    often = labelled.groupBy("component", "label").agg(F.count("*").alias("n"))
    largest = often.groupBy("component").agg(F.max_by("label", F.struct("n", "label")).alias("main"), F.sum("n").alias("n"))
    largest = saved(largest, "largest")
    labelled = saved(looked_up(labelled, largest, ["component"], ["main"], "n", labelled.count()), "labelled")
    others = labelled.where("label != main")
    chunks = others.groupBy("component").agg(F.ceil(F.sum("size") / block_bytes).cast("int").alias("parts"))
    chunks = saved(chunks.join(largest.select("component", "n"), "component"), "chunks")
    labelled = saved(looked_up(labelled, chunks, ["component"], ["parts"], "n", labelled.count()).where("parts IS NOT NULL"), "labelled")
    others = labelled.where("label != main").withColumn("part", F.pmod(F.xxhash64("doc_id"), F.col("parts")).cast("int"))
    here = labelled.select("doc_id", "label", "component", "block", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("side"))
    there = others.select("doc_id", "label", "component", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), "part", F.lit(1).alias("side"))
    across = _linked(here.unionByName(there).join(sets_of, "doc_id"), ["component", "block", "part"], threshold, parts)
    return links.union(across)


def near_duplicates(docs: DataFrame, width: int = 5, threshold: Fraction = Fraction(3, 4), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id (smallest id reachable by links) and kept, one row per row of ``docs``.

    Texts that are null, empty or without words have no shingles, link with nothing and are kept.  Texts with fewer
    words than ``width`` are one shingle.  Rows that repeat an id are one node and share its fate; a null id links with
    nothing, keeps a null component_id and is kept.  An empty table gives no rows; other columns are ignored.
    """
    spark = docs.sparkSession
    rows = saved(shingle_rows(id_text(docs, id_col, text_col), width), "shingles")
    buckets = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    near = saved(connected_components(candidate_edges(rows, buckets)), "neighbours")
    members = saved(rows.join(near, rows.doc_id == near.node).select("doc_id", "n_shingles", "key", "component"), "members")
    # one row for each distinct set; its other rows link to it
    first = saved(members.groupBy("component", "key").agg(F.min("doc_id").alias("doc_id"), F.first("n_shingles").alias("n_shingles"), F.count("*").alias("n")), "first")
    total = members.count()
    equal = looked_up(members, first.withColumnRenamed("doc_id", "v"), ["component", "key"], ["v"], "n", total).where("doc_id != v").select(F.col("doc_id").alias("u"), "v")
    links = verified_links(id_text(docs, id_col, text_col), first.select("doc_id", "component", "n_shingles"), width, threshold)
    found = connected_components(links.union(equal)).withColumnRenamed("node", "doc_id")
    out = rows.select("doc_id", "n_shingles").join(found, "doc_id", "left").withColumn("component_id", F.coalesce("component", "doc_id"))
    return out.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def drop_near_duplicates(docs: DataFrame, width: int = 5, threshold: Fraction = Fraction(3, 4), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one document (the smallest id) of each component, all columns as they were."""
    gone = near_duplicates(docs, width, threshold, id_col, text_col).where(~F.col("kept")).select(F.col("doc_id").alias("_gone"))
    return docs.join(gone, docs[id_col] == gone["_gone"], "left_anti")
