"""Repeated substrings of a given length across all documents, by a difference cover of their suffixes.

Suffixes need to be told apart only up to ``LENGTH`` bytes.  The cover is a perfect difference set: of any two positions
there is a distance below the period at which both are sampled.  Two equal strings of ``LENGTH`` bytes thus have a sample
at the same distance, and the ``NAME`` bytes from it lie inside both.  Every document has a phase of its own, so that
copies aren't sampled at all the same places, which would only repeat the work.

1. Sampled tuples get names: tasks sort the hashes of the ``NAME`` bytes of their samples, owners of hash ranges merge
   them.  Names that occur once can't belong to a repeat; the others make a bitmap of checked size, or ranges of names
   are handled one after the other where it would exceed the bound.
2. Samples with such a name travel with the ``SIDE`` bytes on either side to the owner of the name.  A task sends each
   (name, context) once, by its earliest place.  The contexts are the second level of names, and the last one: beyond
   ``LENGTH`` bytes nothing has to be ordered.  Equal contexts make all later places repeats.
3. The remaining suffixes are merged in: for each distance to the sample, the prefixes of ``LENGTH`` bytes are sorted,
   neighbours are compared byte by byte, and all but the earliest of equal ones are repeats.
4. Repeats are merged into removed runs per document.

A name that very many samples share (a line of less than ``LENGTH`` bytes in a third of all documents) is split before
it travels: by ranges of distances, each with the bytes that all its strings have in common.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_text, maybe_among, saved

LENGTH = 100
#: A perfect difference set (fixed values): every distance modulo the period is the difference of one pair.
PERIOD, COVER = 57, (0, 1, 3, 13, 32, 36, 43, 52)
#: Bytes of a sampled tuple, of what is sent on either side of it, and of both.
NAME, SIDE = LENGTH - PERIOD + 1, PERIOD - 1
REACH = NAME + 2 * SIDE
PAD = b"\xff" * (LENGTH + 4)
#: Most bytes of a bitmap that is broadcast, and its bits for each name.
FILTER_BYTES, FILTER_BITS = 64 << 20, 16
#: A name is split by distances beyond so many samples, or beyond this share of all of them: so few names are.
HOT_LEAST, HOT_SHARE, DISTANCES = 4096, 1 << 23, 8
#: Samples that a task sorts at once, and contexts that it sends at once.
NAMES_AT_ONCE, CONTEXTS_AT_ONCE = 4_000_000, 250_000

_B = np.uint64(0xD6E8FEB86659FD93)
_C = np.uint64(0x9E3779B97F4A7C15)
_SAMPLED = np.isin(np.arange(PERIOD), COVER)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def phase(doc: np.ndarray) -> np.ndarray:
    """Where the cover starts in a document."""
    return (_mix((doc.astype(np.uint64) + np.uint64(1)) * _C) % np.uint64(PERIOD)).astype(np.int64)


class _Texts:
    """Gathers texts into padded buffers of about ``size`` bytes: ids, starts, lengths, bytes."""

    def __init__(self, batches: Iterator[pa.RecordBatch], size: int = 200_000):
        self.batches, self.size = batches, size

    def __iter__(self):
        docs, parts, starts, sizes, at = [], [PAD], [], [], len(PAD)
        for batch in self.batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                data = text.as_py().encode("utf-8", "surrogatepass")
                if len(data) < LENGTH:
                    continue
                docs.append(doc)
                starts.append(at)
                sizes.append(len(data))
                parts += (data, PAD)
                at += len(data) + len(PAD)
                if at > self.size:
                    yield np.array(docs, np.int64), np.array(starts, np.int64), np.array(sizes, np.int64), b"".join(parts)
                    docs, parts, starts, sizes, at = [], [PAD], [], [], len(PAD)
        if docs:
            yield np.array(docs, np.int64), np.array(starts, np.int64), np.array(sizes, np.int64), b"".join(parts)


def samples(docs: np.ndarray, starts: np.ndarray, sizes: np.ndarray, raw: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Sampled positions of padded texts, the document of each (its place in ``docs``), their names, and the bytes."""
    buf = np.frombuffer(raw, np.uint8)
    room = sizes - NAME + 1
    which = np.repeat(np.arange(len(docs)), room)
    inside = np.arange(len(which)) - np.repeat(np.cumsum(room) - room, room)
    taken = _SAMPLED[(inside + np.repeat(phase(docs), room)) % PERIOD]
    which, at = which[taken], inside[taken] + starts[which[taken]]
    # a polynomial hash of NAME bytes out of those of powers of two
    name, done = np.zeros(len(at), np.uint64), 0
    h, power, width = buf.astype(np.uint64) + np.uint64(1), _B, 1
    with np.errstate(over="ignore"):
        while True:
            if NAME & width:
                name = name * power + h[at + done]
                done += width
            if 2 * width > NAME:
                return at, which, _mix(name), buf
            h = h[:-width] * power + h[width:]
            power, width = power * power, 2 * width


def _short(name: np.ndarray) -> np.ndarray:
    """The 40 bits of a name that the first round counts; a false repeat only costs work."""
    return name >> np.uint64(24)


def _bucket_of(short: np.ndarray, buckets: int) -> np.ndarray:
    """Ranges of short names, so that sorted names are sorted by bucket."""
    return ((short * np.uint64(buckets)) >> np.uint64(40)).astype(np.int64)


def _planes(x: np.ndarray, width: int) -> bytes:
    """The low ``width`` bytes of integers, byte by byte: what compresses well where they are small."""
    return np.ascontiguousarray(x.astype(np.uint64).view(np.uint8).reshape(-1, 8).T[:width]).tobytes()


def _from_planes(data: bytes, n: int, width: int, at: int) -> np.ndarray:
    full = np.zeros((8, n), np.uint8)
    full[:width] = np.frombuffer(data, np.uint8, n * width, at).reshape(width, n)
    return np.ascontiguousarray(full.T).view(np.uint64).ravel()


def _pack_names(short: np.ndarray, count: np.ndarray) -> bytes:
    steps = np.diff(short, prepend=np.uint64(0))
    return struct.pack("<I", len(short)) + zstandard.compress(_planes(steps, 5) + _planes(count, 4), 1)


def _unpack_names(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    n, data = struct.unpack_from("<I", blob)[0], zstandard.decompress(blob[4:])
    return np.cumsum(_from_planes(data, n, 5, 0), dtype=np.uint64), _from_planes(data, n, 4, 5 * n)


def _grouped(batches: Iterator[pa.RecordBatch], close):
    """Calls ``close(bucket, rows)`` for the rows of each bucket; these come sorted by bucket, their first column."""
    now, held = None, []
    for batch in batches:
        for bucket, *row in zip(*(c.to_pylist() for c in batch.columns)):
            if bucket != now and held:
                yield close(now, held)
                held = []
            now = bucket
            held.append(row)
    if held:
        yield close(now, held)


_NAMES = "bucket int, n long, samples long, payload binary, often array<long>, times array<long>"


def _repeated_names(rows: DataFrame, buckets: int, least: int) -> DataFrame:
    """bucket, n, payload: the shortened names that occur twice or more, as 64-bit integers; those of more than ``least`` samples with their number."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def flush():
            short, count = np.unique(np.concatenate(held), return_counts=True)
            ends = np.searchsorted(_bucket_of(short, buckets), np.arange(buckets + 1))
            full = [b for b in range(buckets) if ends[b] < ends[b + 1]]
            blobs = [_pack_names(short[ends[b] : ends[b + 1]], count[ends[b] : ends[b + 1]]) for b in full]
            return pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "payload"])

        for texts in _Texts(batches):
            _, _, name, _ = samples(*texts)
            held.append(_short(name))
            n += len(name)
            if n > NAMES_AT_ONCE:
                yield flush()
                held, n = [], 0
        if held:
            yield flush()

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def close(bucket, rows):
            short, count = (np.concatenate(x) for x in zip(*(_unpack_names(r[0]) for r in rows)))
            order = np.argsort(short, kind="stable")
            short, count = short[order], count[order].astype(np.int64)
            at = np.flatnonzero(np.concatenate(([True], short[1:] != short[:-1])))
            short, count = short[at], np.add.reduceat(count, at)
            found, often = short[count > 1], count > least
            columns = ([bucket], [len(found)], [int(count.sum())], [found.tobytes()], [short[often].astype(np.int64)], [count[often]])
            types = (pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.int64()), pa.list_(pa.int64()))
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], names=["bucket", "n", "samples", "payload", "often", "times"])

        return _grouped(batches, close)

    dealt = rows.mapInArrow(local, "bucket int, payload binary").repartition(buckets, "bucket").sortWithinPartitions("bucket")
    return saved(dealt.mapInArrow(merge, _NAMES), "names")


def _bitmaps(names: DataFrame, bits: int) -> DataFrame:
    """The bitmap of each bucket, ``bits`` long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            maps = []
            for blob in batch.column(1).to_pylist():
                bitmap = np.zeros(bits, np.uint8)
                bitmap[(_mix(np.frombuffer(blob, np.uint64)) % np.uint64(bits)).astype(np.int64)] = 1
                maps.append(np.packbits(bitmap, bitorder="little").tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(maps, pa.binary())], names=["bucket", "bitmap"])

    return names.select("bucket", "payload").mapInArrow(run, "bucket int, bitmap binary")


def _span(start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return (start.astype(np.int64) << 32) | end.astype(np.int64)


def _merged(doc: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(doc, span) with the spans of a document that touch made one."""
    if not len(doc):
        return doc, _span(start, end)
    order = np.lexsort((start, doc))
    doc, start, end = doc[order], start[order], end[order]
    # the furthest end so far in the same document, by lifting documents apart
    group = np.cumsum(np.concatenate(([0], doc[1:] != doc[:-1])))
    far = np.maximum.accumulate(end + (group << 33)) - (group << 33)
    new = np.ones(len(doc), bool)
    new[1:] = (group[1:] != group[:-1]) | (start[1:] > far[:-1])
    last = np.append(np.flatnonzero(new)[1:] - 1, len(doc) - 1)
    return doc[new], _span(start[new], far[last])


_SENT = "bucket int, doc_id long, span long, n long, payload binary"


def _row_hash(rows: np.ndarray) -> np.ndarray:
    """64 bits for each row of a matrix of bytes."""
    width = -(-rows.shape[1] // 8) * 8
    full = np.zeros((len(rows), width), np.uint8)
    full[:, : rows.shape[1]] = rows
    h = np.full(len(rows), rows.shape[1], np.uint64)
    for word in np.ascontiguousarray(full.view(np.uint64).T):
        h = _mix((h ^ word) * _C)
    return h


def _sorted_equal(key: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order that puts equal rows of bytes side by side, and for each row in it the place of the first of its equals.

    Rows are sorted by a hash of theirs, and compared byte by byte with the first of their hash; if a hash stands for
    different bytes, the bytes themselves are sorted.  Equal rows keep their order.
    """

    def heads(first: np.ndarray) -> np.ndarray:
        return np.flatnonzero(first)[np.cumsum(first) - 1]

    order = np.argsort(key, kind="stable")
    sorted_key = key[order]
    first = np.concatenate((np.ones(min(1, len(key)), bool), sorted_key[1:] != sorted_key[:-1]))
    head = heads(first)
    rest = np.flatnonzero(~first)
    if (rows[order[rest]] != rows[order[head[rest]]]).any():
        order = np.argsort(np.ascontiguousarray(rows).view(f"S{rows.shape[1]}").ravel(), kind="stable")
        sorted_ = rows[order]
        head = heads(np.concatenate(([True], (sorted_[1:] != sorted_[:-1]).any(axis=1))))
    return order, head


def _room(context: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of the text to the left and right of each sampled tuple, at most SIDE."""
    return (context[:, :SIDE] != 255).sum(axis=1), (context[:, SIDE + NAME :] != 255).sum(axis=1)


def _first_contexts(name, doc, at, context):
    """The columns ordered by place; of equal contexts of a name the first; and the spans of the others."""
    order = np.lexsort((at, doc))
    name, doc, at, context = (x[order] for x in (name, doc, at, context))
    order, head = _sorted_equal(_row_hash(context), context)  # equal contexts have equal names
    lead = order[head]
    later = (doc[order] != doc[lead]) | (at[order] != at[lead])
    left, right = _room(context[order[later]])
    full = left + right >= SIDE
    gone = order[later][full]
    firsts = np.sort(order[head == np.arange(len(order))])
    return (name[firsts], doc[firsts], at[firsts], context[firsts]), (doc[gone], at[gone] - left[full], at[gone] + NAME + right[full])


def _split(name, doc, at, context):
    """Records of an often repeated name, one for each range of distances, keyed by the bytes that its strings share.

    What no string of the range has is blanked out, so the owner looks at these distances only.
    """
    left, right = _room(context)
    out = []
    for low in range(0, SIDE + 1, DISTANCES):
        high = min(low + DISTANCES - 1, SIDE)
        some = np.flatnonzero((left >= low) & (right >= SIDE - high))
        part = context[some]  # a copy
        part[:, : SIDE - high] = 255
        part[:, REACH - low :] = 255
        shared = _row_hash(part[:, SIDE - low : SIDE + NAME + SIDE - high])
        out.append((_mix((shared + np.uint64(low)) * _C), doc[some], at[some], part))
    return tuple(np.concatenate(x) for x in zip(*out))


def _spans_batch(doc: np.ndarray, span: np.ndarray, buckets: int) -> pa.RecordBatch:
    n = len(doc)
    return pa.RecordBatch.from_arrays([pa.array((phase(doc) + doc) % buckets, pa.int32()), pa.array(doc, pa.int64()), pa.array(span, pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.binary())], names=["bucket", "doc_id", "span", "n", "payload"])


def _send_contexts(rows: DataFrame, bitmaps, often, low: int, high: int, name_buckets: int, bits: int, buckets: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        maps, hot, squeeze = bitmaps.value, often.value, zstandard.ZstdCompressor(level=3).compress
        held, n = [], 0

        def flush():
            columns, gone = _first_contexts(*(np.concatenate(x) for x in zip(*held)))
            yield _spans_batch(*_merged(*gone), buckets)
            many = np.isin(_short(columns[0]), hot) if len(hot) else np.zeros(len(columns[0]), bool)
            if many.any():
                split, gone = _first_contexts(*_split(*(x[many] for x in columns)))
                yield _spans_batch(*_merged(*gone), buckets)
                columns = tuple(np.concatenate((x[~many], y)) for x, y in zip(columns, split))
            name, doc, at, context = columns
            to = (_mix(name) % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(to, kind="stable")
            ends = np.searchsorted(to[order], np.arange(buckets + 1))
            ids, counts, blobs = [], [], []
            for b in np.unique(to).tolist():
                i = order[ends[b] : ends[b + 1]]
                ids.append(b)
                counts.append(len(i))
                blobs.append(squeeze(b"".join((name[i].tobytes(), doc[i].tobytes(), at[i].tobytes(), context[i].tobytes()))))
            k = len(ids)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.array(counts, pa.int64()), pa.array(blobs, pa.binary())], names=["bucket", "doc_id", "span", "n", "payload"])

        reach = np.arange(-SIDE, NAME + SIDE)
        for docs, starts, sizes, raw in _Texts(batches):
            at, which, name, buf = samples(docs, starts, sizes, raw)
            short = _short(name)
            bucket = _bucket_of(short, name_buckets)
            bit = (_mix(short) % np.uint64(bits)).astype(np.int64)
            known = (bucket >= low) & (bucket < high)
            known[known] = maps[(bucket[known] - low) * (bits // 8) + (bit[known] >> 3)] >> (bit[known] & 7).astype(np.uint8) & 1
            at, which = at[known], which[known]
            if not len(at):
                continue
            held.append((name[known], docs[which], (at - starts[which]).astype(np.int32), buf[at[:, None] + reach]))
            n += len(at)
            if n > CONTEXTS_AT_ONCE:
                yield from flush()
                held, n = [], 0
        if held:
            yield from flush()

    return rows.mapInArrow(run, _SENT)


def _unpacked(n: int, blob: bytes):
    data, out, at = zstandard.decompress(blob), [], 0
    for kind, width in ((np.uint64, 1), (np.int64, 1), (np.int32, 1), (np.uint8, REACH)):
        out.append(np.frombuffer(data, kind, n * width, at))
        at += n * width * np.dtype(kind).itemsize
    return (*out[:3], out[3].reshape(n, REACH))


def repeats_of_bucket(name, doc, at, context) -> tuple[np.ndarray, np.ndarray]:
    """(doc, span) of all repeats among the samples of a bucket of names."""
    (name, doc, at, context), gone = _first_contexts(name, doc, at, context)
    found = [gone]
    # different contexts of a name; ordered by place, which the sorts below keep
    _, back, size = np.unique(name, return_inverse=True, return_counts=True)
    several = size[back] > 1
    doc, at, context = doc[several], at[several], context[several]
    if len(doc):
        n, (left, right) = len(doc), _room(context)
        repeat = np.zeros((SIDE + 3, n), bool)  # by distance of the start to the sample, with a false row at either end
        column = np.ascontiguousarray(context.T).astype(np.uint64) + np.uint64(1) if n < 20_000 else None
        byte = (lambda i: column[i]) if column is not None else (lambda i: context[:, i].astype(np.uint64) + np.uint64(1))
        h, top = np.zeros(n, np.uint64), np.uint64(1)
        for i in range(LENGTH):
            h += byte(SIDE + i) * top
            top = top * _B if i < LENGTH - 1 else top
        for distance in range(SIDE + 1):
            if distance:  # one byte more in front, one less at the end
                h = byte(SIDE - distance) + _B * (h - byte(SIDE - distance + LENGTH) * top)
            ok = np.flatnonzero((left >= distance) & (right >= SIDE - distance))
            if len(ok) < 2:
                continue
            order, head = _sorted_equal(h[ok], context[ok, SIDE - distance : SIDE - distance + LENGTH])
            lead, mine = ok[order[head]], ok[order]
            repeat[distance + 1, mine] = (doc[mine] != doc[lead]) | (at[mine] != at[lead])
        turn = np.diff(repeat.astype(np.int8), axis=0)
        row, begin = np.nonzero((turn == 1).T)
        _, end = np.nonzero((turn == -1).T)  # starts at the distances begin .. end - 1
        found.append((doc[row], at[row] - (end - 1), at[row] - begin + LENGTH))
    return _merged(*(np.concatenate(x) for x in zip(*found)))


def _owners(sent: DataFrame, buckets: int) -> DataFrame:
    """doc_id, span: the spans that tasks found by themselves, and those of each bucket of names."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def close(_, rows):
            told = [r[:2] for r in rows if r[3] is None]
            doc, span = (np.array(x, np.int64) for x in zip(*told)) if told else (np.empty(0, np.int64),) * 2
            blobs = [_unpacked(r[2], r[3]) for r in rows if r[3] is not None]
            if blobs:
                more = repeats_of_bucket(*(np.concatenate(x) for x in zip(*blobs)))
                doc, span = np.concatenate((doc, more[0])), np.concatenate((span, more[1]))
            return pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(span, pa.int64())], names=["doc_id", "span"])

        return _grouped(batches, close)

    return sent.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(run, "doc_id long, span long")


def removed_spans(rows: DataFrame) -> DataFrame:
    """doc_id, spans (start * 2^32 + end, in bytes, unordered) for documents that hold a repeat.  rows: doc_id, text."""
    spark = rows.sparkSession
    name_buckets = 2 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    names = _repeated_names(rows, name_buckets, HOT_LEAST)
    zero = F.lit(0)
    total, most, sampled = names.agg(F.coalesce(F.sum("n"), zero), F.coalesce(F.max("n"), zero), F.coalesce(F.sum("samples"), zero)).first()
    pair = names.select(F.explode(F.arrays_zip("often", "times")).alias("o")).where(F.col("o.times") > max(HOT_LEAST, sampled // HOT_SHARE))
    hot = np.array([r[0] for r in pair.select("o.often").toLocalIterator()], np.int64).astype(np.uint64)
    bits = max(64, 1 << (FILTER_BITS * int(most)).bit_length())
    each = max(1, FILTER_BYTES * 8 // bits)  # buckets in one bitmap
    buckets = max(16, int(total) // 20_000)
    often, found = spark.sparkContext.broadcast(hot), []
    for low in range(0, name_buckets if total else 0, each):
        high = min(low + each, name_buckets)
        bitmap = np.zeros((high - low) * (bits // 8), np.uint8)
        for r in _bitmaps(names.where((F.col("bucket") >= low) & (F.col("bucket") < high)), bits).toLocalIterator():
            bitmap[(r["bucket"] - low) * (bits // 8) :][: bits // 8] = np.frombuffer(r["bitmap"], np.uint8)
        shared = spark.sparkContext.broadcast(bitmap)
        found.append(saved(_owners(_send_contexts(rows, shared, often, low, high, name_buckets, bits, buckets), buckets), "spans"))
        shared.unpersist()
    if not found:
        return spark.createDataFrame([], "doc_id long, spans array<long>")
    spans = found[0]
    for more in found[1:]:
        spans = spans.union(more)
    return spans.groupBy("doc_id").agg(F.collect_list("span").alias("spans"))


def _with_spans(rows: DataFrame, spans: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Rows with their spans as a last column, null where they have none; only texts that may have some are shuffled."""
    spans = saved(spans.withColumnRenamed("doc_id", id_col), "spans")
    rows = maybe_among(rows, spans, id_col)
    none = rows.where("NOT _maybe").drop("_maybe").withColumn("spans", F.lit(None).cast("array<long>"))
    some = rows.where("_maybe").drop("_maybe").join(spans.withColumnRenamed(id_col, "_node"), F.col(id_col) == F.col("_node"), "left").drop("_node")
    return some.union(none)


def cut(data: bytes, spans: list[int]) -> tuple[bytes, int]:
    """What is left of a text without its spans, and the number of maximal removed runs."""
    kept, at, runs = [], 0, 0
    for s in sorted(spans):
        start, end = s >> 32, s & 0xFFFFFFFF
        if start > at or not runs:
            runs += 1
            kept.append(data[at:start])
        at = max(at, end)
    kept.append(data[at:])
    return b"".join(kept), runs


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept (bytes) per row: without every byte covered by a 100-byte string that also starts earlier.

    Earlier: in a document with a smaller id or further ahead in the same one, on the texts as given.  Null text is
    empty; texts under 100 bytes keep all.  Rows that repeat both id and text stand at the same place and don't remove
    each other; ids are meant to be unique otherwise.  Rows with a null id are left as they are and remove nothing.
    An empty table gives no rows; other columns are ignored.
    """
    rows = id_text(docs, id_col, text_col)
    spans = removed_spans(rows.where("doc_id IS NOT NULL"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                sizes, kept, runs = [], [], []
                for text, s in zip(part.column(1), part.column(2).to_pylist()):
                    data = text.as_py().encode("utf-8", "surrogatepass")
                    left, n = cut(data, s) if s else (data, 0)
                    sizes.append(len(data))
                    kept.append(left)
                    runs.append(n)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array([a - len(b) for a, b in zip(sizes, kept)], pa.int64()), pa.array(runs, pa.int64()), pa.array(kept, pa.binary())], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return _with_spans(rows, spans).mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")


def without_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size_col: str | None = "n_chars") -> DataFrame:
    """``docs`` with the repeated bytes cut out of the text and the size column set anew; all rows and other columns stay.

    A character of which only some bytes are left goes too.  Null texts stay null; emptied ones become empty.
    """
    ids = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    spans = removed_spans(ids.where("doc_id IS NOT NULL"))
    at, schema = docs.columns.index(text_col), docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, s in zip(batch.column(at), batch.column(batch.num_columns - 1).to_pylist()):
                data = text.as_py()
                texts.append(cut(data.encode(), s)[0].decode("utf-8", "ignore") if s else data)
            columns = list(batch.columns[:-1])
            columns[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays(columns, names=schema.names)

    plain = docs.select(*[F.col(c).alias(f"c{i}") for i, c in enumerate(docs.columns)], F.col(id_col).cast("long").alias("_id"))
    out = _with_spans(plain, spans, "_id").drop("_id").mapInArrow(run, schema)
    if size_col in docs.columns:
        out = out.withColumn(size_col, F.length(text_col).cast(schema[size_col].dataType))
    return out
