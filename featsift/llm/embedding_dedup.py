"""Near-duplicate vectors: Euclidean p-stable hashing of normalised vectors, then exact cosines.

Equal vectors are one node first.  Each table hashes a vector to ``k`` quantised Gaussian projections; vectors that
agree in all of them share a bucket.  ``k`` follows from the number of vectors (so that buckets stay short) and the
number of tables from the chance of a pair at the threshold to meet, so recall is the same at every size.  Buckets
longer than a block are compared block by block.  What travels to the buckets is a sketch of each vector, the signs of
more projections; the vectors themselves follow only where a sketch is near another one's.  A pair is counted by the
first table in which it meets, so links can be counted without ever being listed; what leaves a task is a count per
vector and a star per local component.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import looked_up, saved
from .components import connected_components
from .minhash_dedup import mix

#: Width of a projection's cells, vectors in a block, chance of a pair at the threshold to be missed.
WIDTH, BLOCK, MISSED = 1.0, 1024, 0.002
#: Signs of a sketch, and the chance of a pair at the threshold to be taken for a distant one.
SKETCH, SKETCH_MISSED = 128, 1e-9


def meeting_chance(distance: float, width: float = WIDTH) -> float:
    """Chance of one projection to put two points at this distance into the same cell (Gaussian projections)."""
    r = width / distance
    return math.erf(r / math.sqrt(2)) - math.sqrt(2 / math.pi) / r * (1 - math.exp(-r * r / 2))


def tables_for(vectors: int, threshold: float) -> tuple[int, int]:
    """Projections in a key and number of tables.  Unrelated unit vectors are about sqrt(2) apart; about 512 of them may share a bucket."""
    near, far = meeting_chance(math.sqrt(2 - 2 * threshold)), meeting_chance(math.sqrt(2))
    k = max(2, math.ceil(math.log(max(vectors, 512) / 512) / -math.log(far)))
    return k, math.ceil(math.log(MISSED) / math.log(1 - near**k))


def projections(dim: int, k: int, tables: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(77_003)
    return rng.standard_normal((dim, k * tables)), rng.random(k * tables) * WIDTH


def bucket_keys(x: np.ndarray, k: int, tables: int) -> np.ndarray:
    """One 64-bit key for each vector and table."""
    a, shift = projections(x.shape[1], k, tables)
    cells = np.floor((x @ a + shift) / WIDTH).astype(np.int64).view(np.uint64).reshape(len(x), tables, k)
    key = np.broadcast_to(np.arange(1, tables + 1, dtype=np.uint64) + np.uint64(x.shape[1] << 32), (len(x), tables)).copy()
    for i in range(k):
        key = mix(key * np.uint64(0x9E3779B97F4A7C15) + cells[:, :, i])
    return key


def sketch_bound(threshold: float) -> int:
    """Signs in which two vectors may differ: pairs at the threshold differ in more with a chance below SKETCH_MISSED."""
    p, tail = math.acos(threshold) / math.pi, 1.0
    for h in range(SKETCH + 1):
        tail -= math.comb(SKETCH, h) * p**h * (1 - p) ** (SKETCH - h)
        if tail < SKETCH_MISSED:
            return h
    return SKETCH


def sketches(x: np.ndarray) -> np.ndarray:
    """Signs of SKETCH projections as 64-bit words, one row for each vector."""
    signs = x @ np.random.default_rng(40_961).standard_normal((x.shape[1], SKETCH)) > 0
    return np.packbits(signs, axis=1).view(np.int64)


def _usable(values) -> np.ndarray | None:
    """The vector in double precision, or None if it links with nothing."""
    if values is None or not values or any(v is None for v in values):
        return None
    x = np.array(values, np.float64)
    return x if np.isfinite(x).all() and x.any() else None


def unique_vectors(vectors: DataFrame, id_col: str, vector_col: str, kind: str) -> DataFrame:
    """vec_id and x: the vector as bytes of ``kind`` (f4 or f8), null if it links with nothing."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [_usable(v) for v in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([None if x is None else (x + 0.0).astype(kind).tobytes() for x in found], pa.binary())], names=["vec_id", "x"])

    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v"))
    return rows.mapInArrow(run, "vec_id long, x binary")


def _block_links(x: np.ndarray, key: np.ndarray, weight: np.ndarray, table: int, threshold: float, split: int | None) -> tuple[np.ndarray, np.ndarray]:
    """Weighted number of links of each vector of a block that this table is the first to see, and a local label."""
    n = len(x)
    norm = np.sqrt((x * x).sum(axis=1))
    cosine = (x @ x.T) / norm[:, None] / norm[None, :]
    link = cosine >= threshold
    np.fill_diagonal(link, False)
    if split is not None:
        link[:split, :split] = link[split:, split:] = False
    i, j = np.nonzero(link)
    if table:
        new = ~(key[i, :table] == key[j, :table]).any(axis=1)
        i, j = i[new], j[new]
    count = np.bincount(i, weight[j], n).astype(np.int64)
    label = np.arange(n)
    while len(i):
        least = label.copy()
        np.minimum.at(least, i, label[j])
        least = least[least]
        if (least == label).all():
            break
        label = least
    return count, label


def bucket_links(nodes: DataFrame, threshold: float, k: int, tables: int, kind: str) -> DataFrame:
    """node, links (count seen by one table and block) and v (a linked node, or null).  nodes: node, n, x."""

    def normalised(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        x = np.frombuffer(b"".join(blobs), kind).astype(np.float64).reshape(len(blobs), -1)
        return x, bucket_keys(x / np.sqrt((x * x).sum(axis=1))[:, None], k, tables)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            blobs = batch.column(1).to_pylist()
            for size in sorted({len(b) for b in blobs}):
                at = [i for i, b in enumerate(blobs) if len(b) == size]
                x, keys = normalised([blobs[i] for i in at])
                signs = sketches(x)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at)), pa.array(list(keys.view(np.int64)), pa.list_(pa.int64())), pa.array(signs[:, 0]), pa.array(signs[:, 1])], names=["node", "keys", "s0", "s1"])

    dealt = saved(nodes.select("node", "x").mapInArrow(hashed, "node long, keys array<long>, s0 long, s1 long"), "hashed")
    dealt = dealt.select("node", "s0", "s1", F.posexplode("keys").alias("t", "key"))
    sizes = dealt.groupBy("t", "key").agg(F.count("*").alias("size")).where("size > 1")
    placed = looked_up(dealt, saved(sizes, "sizes"), ["t", "key"], ["size"], "size", nodes.count() * tables).where("size IS NOT NULL").withColumn("blocks", F.ceil(F.col("size") / BLOCK).cast("int")).withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    pair = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda o: F.struct(F.least(o, F.col("block")).alias("i"), F.greatest(o, F.col("block")).alias("j")))
    placed = placed.select("node", "s0", "s1", "t", "key", "block", F.explode(pair).alias("p")).select("t", "key", "p.i", "p.j", "block", "node", "s0", "s1")
    parts, bound = 4 * int(nodes.sparkSession.conf.get("spark.sql.shuffle.partitions")), sketch_bound(threshold)

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows with another one of their blocks within the bound."""
        now, held = None, []

        def close():
            if len(held) < 2:
                return None
            block, node, s0, s1 = zip(*held)
            a, b = np.array(s0, np.int64).view(np.uint64), np.array(s1, np.int64).view(np.uint64)
            link = np.bitwise_count(a[:, None] ^ a) + np.bitwise_count(b[:, None] ^ b) <= bound
            np.fill_diagonal(link, False)
            if now[2] != now[3]:
                split = block.count(now[2])
                link[:split, :split] = link[split:, split:] = False
            found = np.flatnonzero(link.any(axis=1))
            columns = [pa.array([v] * len(found), k) for v, k in zip(now, (pa.int32(), pa.int64(), pa.int32(), pa.int32()))]
            return pa.RecordBatch.from_arrays([*columns, pa.array(np.array(block, np.int32)[found]), pa.array(np.array(node, np.int64)[found])], names=["t", "key", "i", "j", "block", "node"])

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if row[:4] != now:
                    if (out := close()) is not None:
                        yield out
                    now, held = row[:4], []
                held.append(row[4:])
        if (out := close()) is not None:
            yield out

    sifted = placed.repartition(parts, "t", "key", "i", "j").sortWithinPartitions("t", "key", "i", "j", "block", "node")
    full = sifted.mapInArrow(near, "t int, key long, i int, j int, block int, node long").join(nodes, "node")
    full = full.select("t", "key", "i", "j", "block", "node", "n", "x").repartition(parts, "t", "key", "i", "j").sortWithinPartitions("t", "key", "i", "j", "block", "node")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        now = None
        out: tuple[list, list, list] = ([], [], [])

        def close():
            if len(held) < 2:
                return
            t, _, a, b = now
            block, node, n, blobs = zip(*held)
            split = None if a == b else block.count(a)
            if len({len(b) for b in blobs}) > 1:
                return  # keys of different dimensions differ but for a collision of 64 bits
            x, keys = normalised(blobs)
            count, label = _block_links(x, keys, np.array(n, np.float64), t, threshold, split)
            for i in np.flatnonzero(count):
                out[0].append(node[i])
                out[1].append(int(count[i]))
                out[2].append(node[label[i]] if label[i] != i else None)

        def batch_out():
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], names=["node", "links", "v"])

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if row[:4] != now:
                    close()
                    held, now = [], row[:4]
                held.append(row[4:])
            yield batch_out()
            out = ([], [], [])
        close()
        yield batch_out()

    return full.mapInArrow(run, "node long, links long, v long")


def near_vectors(vectors: DataFrame, threshold: float = 0.95, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """vec_id, n_links (other rows linked directly), component_id (smallest id reachable) and kept, one row per row of ``vectors``.

    Vectors that are null, empty, zero or hold null or non-finite components link with nothing and are kept, as are
    vectors of another length than all others.  Equal vectors are always linked.  Rows that repeat an id count as rows
    but are one node; a null id has a null component and is kept.  An empty table gives no rows.
    """
    kind = "f4" if vectors.schema[vector_col].dataType.simpleString() == "array<float>" else "f8"
    rows = saved(unique_vectors(vectors, id_col, vector_col, kind), "vectors")
    nodes = saved(rows.where("x IS NOT NULL AND vec_id IS NOT NULL").groupBy("x").agg(F.min("vec_id").alias("node"), F.count("*").alias("n")), "nodes")
    k, tables = tables_for(nodes.count(), threshold)
    links = saved(bucket_links(nodes, threshold, k, tables, kind), "links")
    found = connected_components(links.where("v IS NOT NULL").select(F.col("node").alias("u"), "v"))
    counted = links.groupBy("node").agg(F.sum("links").alias("links"))
    named = nodes.join(counted, "node", "left").join(found, "node", "left")
    named = named.select("x", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "node").alias("component_id"))
    out = rows.withColumn("x", F.when(F.col("vec_id").isNotNull(), F.col("x"))).join(named, "x", "left")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
