"""Counting on packed blocks: what a selection runs on while its state fits the driver.

Rows are packed once into blocks that stay in memory, beyond it on disk.  A round then is one job: every task adds up
the cells of its blocks with NumPy, the partial cells of all tasks meet in one exchange, and what reaches the driver are
two numbers for each feature.  Tasks are as many as cores ask for, not as many as blocks, so the exchange follows the
cluster and the number of features, never the rows.

Dense blocks hold the codes feature by feature, in columns of ``GROUP`` features: a round reads the columns it needs, and
counts features in sets whose cells keep within ``COUNT_BYTES`` in a task.  Sparse blocks hold whole rows, dealt by row,
so the postings that meet a chosen feature are found without a join, however many rows have it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.info import cube_information
from ..plans.dataset import Dataset, SparseDataset

BLOCK_ROWS, BLOCK_ENTRIES, GROUP = 1 << 15, 1 << 19, 64
#: Bytes of counts that a task holds at once, and of those that one task of the exchange adds up.
COUNT_BYTES, PART_BYTES = 64 << 20, 1 << 20
#: Most cells of one feature's three-way table.
MAX_CELLS = 1 << 24
#: Distinct cells that a task gathers before it adds them up.
GATHERED = 1 << 22


def _tasks(df: DataFrame) -> DataFrame:
    """As many tasks as keep all cores busy with a few turns each."""
    return df.coalesce(4 * df.sparkSession.sparkContext.defaultParallelism)


def column_sets(cells: list[int], budget: int = COUNT_BYTES) -> list[list[int]]:
    """Features in consecutive sets whose counts (8 bytes a cell) keep within the budget, one feature at least."""
    sets: list[list[int]] = []
    held = 0
    for i, c in enumerate(cells):
        if not sets or held + 8 * c > budget:
            sets.append([])
            held = 0
        sets[-1].append(i)
        held += 8 * c
    return sets


class DenseEngine:
    """Codes are stored one higher, so that 0 stands for null, a category of its own."""

    def __init__(self, ds: Dataset):
        self.ds, self.features = ds, list(ds.features)
        #: Whether all pairs are counted at once, and then what came of it.
        self.whole, self.known = False, None
        n = len(self.features)
        self.groups = [range(a, min(a + GROUP, n)) for a in range(0, n, GROUP)]
        kind, most = (np.int16, 32_000) if ds.max_bins <= 32_000 else (np.int32, 2**31 - 2)
        self.kind, groups = kind, self.groups

        def codes(column: pa.Array) -> np.ndarray:
            x = np.asarray(column.fill_null(-1)) + 1
            if len(x) and (x.max() > most or x.min() < 0):
                raise ValueError(f"codes must be 0 to {most - 1}; bin these features first")
            return x.astype(kind)

        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, rows = [], 0

            def flush():
                columns = [codes(pa.chunked_array([b.column(i) for b in held]).combine_chunks()) for i in range(n + 1)]
                w = np.concatenate([np.asarray(b.column(n + 1)) for b in held])
                out = [pa.array([rows], pa.int32()), pa.array([[int(c.max()) for c in columns]], pa.list_(pa.int32())), pa.array([columns[n].tobytes()], pa.binary()), pa.array([None if (w == 1).all() else w.astype(np.int64).tobytes()], pa.binary())]
                out += [pa.array([b"".join(columns[i].tobytes() for i in g)], pa.binary()) for g in groups]
                return pa.RecordBatch.from_arrays(out, names=["n", "top", "y", "w", *[f"g{k}" for k in range(len(groups))]])

            for batch in batches:
                for at in range(0, batch.num_rows, BLOCK_ROWS):
                    part = batch.slice(at, BLOCK_ROWS)
                    held.append(part)
                    rows += part.num_rows
                    if rows >= BLOCK_ROWS:
                        yield flush()
                        held, rows = [], 0
            if rows:
                yield flush()

        schema = "n int, top array<int>, y binary, w binary" + "".join(f", g{k} binary" for k in range(len(groups)))
        self.blocks = ds.columns().select(*self.features, "y", "_w").mapInArrow(pack, schema).persist(StorageLevel.MEMORY_AND_DISK)
        placed = self.blocks.select(F.spark_partition_id().alias("p"), F.posexplode("top"))
        found = placed.groupBy("pos").agg(F.max("col").alias("top"), F.count_distinct("p").alias("spread"), F.count("*").alias("blocks")).collect()
        tops = {r["pos"]: r["top"] for r in found}
        cores = ds.df.sparkSession.sparkContext.defaultParallelism
        if found and found[0]["spread"] < min(cores, found[0]["blocks"]):
            # rows that came in fewer partitions than there are cores: their blocks are dealt anew
            blocks, self.blocks = self.blocks, self.blocks.repartition(cores).persist(StorageLevel.MEMORY_AND_DISK)
            self.blocks.count()
            blocks.unpersist()
        #: Codes of each feature and of the class, null included.
        self.sizes, self.classes = [tops.get(i, 0) + 1 for i in range(n)], tops.get(n, 0) + 1
        bins = max(self.sizes, default=0)
        if bins * bins * self.classes > MAX_CELLS:
            self.release()
            raise ValueError("the three-way count table of a feature would be too large; use fewer bins")

    def release(self) -> None:
        self.blocks.unpersist()

    def _counted(self, pairs: list[tuple[int, int | None]], finish, schema: str) -> DataFrame:
        """``finish`` applied to each pair (feature, j) and its summed table (x, j, y)."""
        ny, kind, groups, sizes = self.classes, self.kind, self.groups, self.sizes
        nj = lambda j: 1 if j is None else sizes[j]
        found = None
        for place in column_sets([sizes[i] * nj(j) * ny for i, j in pairs]):
            some = [pairs[p] for p in place]
            bounds = np.concatenate(([0], np.cumsum([sizes[i] * nj(j) * ny for i, j in some])))
            mine: dict[int | None, list[tuple[int, int]]] = {}
            for p, (i, j) in enumerate(some):
                mine.setdefault(j, []).append((p, i))
            parts = int(max(1, min(len(some), 8 * bounds[-1] // PART_BYTES)))
            cuts = [len(some) * p // parts for p in range(parts + 1)]
            read = sorted({x // GROUP for pair in some for x in pair if x is not None})

            def count(batches, mine=mine, bounds=bounds, cuts=cuts, read=read):
                total = np.zeros(bounds[-1], np.int64)
                seen = False
                for batch in batches:
                    for r in range(batch.num_rows):
                        seen = True
                        n = batch.column(0)[r].as_py()
                        y = np.frombuffer(batch.column(1)[r].as_buffer(), kind).astype(np.intp)
                        w = batch.column(2)[r]
                        w = np.frombuffer(w.as_buffer(), np.int64) if w.is_valid else None
                        codes = {k: np.frombuffer(batch.column(3 + c)[r].as_buffer(), kind).reshape(-1, n) for c, k in enumerate(read)}
                        code = lambda i: codes[i // GROUP][i - groups[i // GROUP].start].astype(np.intp)  # noqa: B023, E731
                        for j, others in mine.items():
                            rest = y if j is None else code(j) * ny + y
                            for p, i in others:
                                at = code(i)
                                at *= nj(j) * ny
                                at += rest
                                size = bounds[p + 1] - bounds[p]
                                total[bounds[p] : bounds[p + 1]] += np.bincount(at, minlength=size) if w is None else np.rint(np.bincount(at, w, size)).astype(np.int64)
                if seen:
                    for p in range(len(cuts) - 1):
                        part = total[bounds[cuts[p]] : bounds[cuts[p + 1]]]
                        yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([part.tobytes()], pa.binary())], names=["part", "counts"])

            def merge(batches, some=some, bounds=bounds, cuts=cuts):
                sums: dict[int, np.ndarray] = {}
                for batch in batches:
                    for p, counts in zip(batch.column(0).to_pylist(), batch.column(1)):
                        counts = np.frombuffer(counts.as_buffer(), np.int64)
                        sums[p] = counts if p not in sums else sums[p] + counts
                for p, total in sums.items():
                    for place in range(cuts[p], cuts[p + 1]):
                        i, j = some[place]
                        yield finish(i, j, total[bounds[place] - bounds[cuts[p]] : bounds[place + 1] - bounds[cuts[p]]].reshape(sizes[i], nj(j), ny))

            partial = _tasks(self.blocks.select("n", "y", "w", *[f"g{k}" for k in read])).mapInArrow(count, "part int, counts binary")
            one = partial.repartition(parts, "part").mapInArrow(merge, schema)
            found = one if found is None else found.union(one)
        return found

    def cells(self, j: int | None = None) -> DataFrame:
        """feature, x, j, y, c of the cells that occur."""

        def finish(feature: int, j: int | None, cube: np.ndarray) -> pa.RecordBatch:
            x, p, y = np.nonzero(cube)
            columns = [pa.array(np.full(len(x), feature, np.int32))]
            for k, v in enumerate((x, p, y)):
                columns.append(pa.array(v.astype(np.int32) - 1, mask=(v == 0) if j is not None or k != 1 else np.ones(len(v), bool)))
            return pa.RecordBatch.from_arrays([*columns, pa.array(cube[x, p, y])], names=["feature", "x", "j", "y", "c"])

        return self._counted([(i, j) for i in range(len(self.features))], finish, "feature int, x int, j int, y int, c long")

    def information(self, pairs: list[tuple[int, int | None]]) -> pa.Table:
        """feature, j, mi = I(feature; j) and cmi = I(feature; j | class); without j, mi = I(feature; class)."""

        def finish(feature: int, j: int | None, cube: np.ndarray) -> pa.RecordBatch:
            mi, cmi = cube_information(cube.transpose(0, 2, 1) if j is None else cube)
            return pa.RecordBatch.from_arrays([pa.array([feature], pa.int64()), pa.array([j], pa.int64()), pa.array([mi]), pa.array([cmi])], names=["feature", "j", "mi", "cmi"])

        return self._counted(pairs, finish, "feature long, j long, mi double, cmi double").toArrow().sort_by([("j", "ascending"), ("feature", "ascending")])

    def expect(self, k: int) -> None:
        """The first k features will be chosen: if all pairs are no more than their rounds would count, one job counts them.

        With k - 1 rounds of n features that is so from about half of the features on.
        """
        n = len(self.features)
        cells = (sum(self.sizes) ** 2 - sum(s * s for s in self.sizes)) // 2 * self.classes
        self.whole = n - 1 <= 2 * (k - 1) and 8 * cells <= COUNT_BYTES

    def _known(self) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """By feature, what ``pair`` says of it, from one job over all pairs."""
        n = len(self.features)
        t = self.information([(i, j) for j in range(n) for i in range(j + 1, n)])
        a, b, mi, cmi = (t.column(c).to_numpy() for c in ("feature", "j", "mi", "cmi"))
        a, b, mi, cmi = np.concatenate((a, b)), np.concatenate((b, a)), np.tile(mi, 2), np.tile(cmi, 2)
        order = np.lexsort((a, b))
        ends = np.searchsorted(b[order], np.arange(n + 1))
        return {j: (a[at], mi[at], cmi[at]) for j, at in enumerate(np.split(order, ends[1:-1]))}

    def _of(self, j: int | None, some: list[int] | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        t = self.information([(i, j) for i in (range(len(self.features)) if some is None else sorted(some))])
        return tuple(t.column(c).to_numpy() for c in ("feature", "mi", "cmi"))

    def relevance(self) -> tuple[np.ndarray, list[str], np.ndarray]:
        ids, rel, _ = self._of(None, None) if self.features else (np.empty(0, np.int64),) * 3
        if len(ids) < len(self.features):  # no rows
            ids, rel = np.arange(len(self.features)), np.zeros(len(self.features))
        return ids, self.features, rel

    def pair(self, j: int, some: list[int] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Feature numbers in order, I(feature; j), I(feature; j | class)."""
        if some is not None or not self.whole:
            return self._of(j, some)
        if self.known is None:
            self.known = self._known()
        return self.known[j]


def _added(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys and the sums of their counts."""
    found, back = np.unique(keys, return_inverse=True)
    return found, np.bincount(back, counts, len(found)).astype(np.int64)


def _g(c: np.ndarray) -> np.ndarray:
    c = c.astype(np.float64)
    return c * np.log2(np.maximum(c, 1.0))


class SparseEngine:
    """Blocks of whole rows: pointers, feature numbers, codes and classes."""

    def __init__(self, ds: SparseDataset):
        self.ds = ds

        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, size = [], 0

            def block(row, feature, code, y):
                start = np.flatnonzero(np.concatenate(([True], row[1:] != row[:-1])))
                ptr = np.append(start, len(row)).astype(np.int32)
                small = feature.astype(np.int32) if feature.max() < 2**31 else feature
                return pa.RecordBatch.from_arrays([pa.array([v], pa.binary()) for v in (ptr.tobytes(), small.tobytes(), None if (code == 1).all() else code.astype(np.int32).tobytes(), y[start].astype(np.int32).tobytes())], names=["ptr", "feature", "code", "y"])

            for batch in batches:
                held.append([np.asarray(c) for c in batch.columns])
                size += batch.num_rows
                if size >= BLOCK_ENTRIES:
                    columns = [np.concatenate(c) for c in zip(*held)]
                    cut = int(np.searchsorted(columns[0], columns[0][-1]))  # the last row may go on
                    if cut:
                        yield block(*(c[:cut] for c in columns))
                    held, size = [[c[cut:] for c in columns]], size - cut
            if size:
                yield block(*(np.concatenate(c) for c in zip(*held)))

        rows = ds.postings.select(F.col("row_id").cast("long").alias("row_id"), F.col("feature").cast("long").alias("feature"), F.col("code").cast("int").alias("code"), F.col("y").cast("int").alias("y"))
        spark = ds.vocabulary.sparkSession
        parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
        dealt = rows.repartition(parts, "row_id").sortWithinPartitions("row_id")
        self.blocks = dealt.mapInArrow(pack, "ptr binary, feature binary, code binary, y binary").persist(StorageLevel.MEMORY_AND_DISK)
        self.class_counts = {int(r["y"]): r["c"] for r in ds.classes.groupBy("y").agg(F.count("*").alias("c")).collect()}

    def release(self) -> None:
        self.blocks.unpersist()

    def met(self, j: int | None = None) -> DataFrame:
        """feature, x, j, y, c of the codes other than 0 in the rows of feature j; without j in all rows, j then being 0."""

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: list[tuple] = []
            size = 0

            def added():
                f, x, p, y, c = (np.concatenate(v) for v in zip(*held))
                order = np.lexsort((y, p, x, f))
                f, x, p, y, c = (v[order] for v in (f, x, p, y, c))
                new = np.ones(len(f), bool)
                new[1:] = (f[1:] != f[:-1]) | (x[1:] != x[:-1]) | (p[1:] != p[:-1]) | (y[1:] != y[:-1])
                at = np.flatnonzero(new)
                return f[at], x[at], p[at], y[at], np.add.reduceat(c, at)

            for batch in batches:
                for r in range(batch.num_rows):
                    ptr, feature, code, y = (batch.column(i)[r] for i in range(4))
                    ptr, y = np.frombuffer(ptr.as_buffer(), np.int32), np.frombuffer(y.as_buffer(), np.int32)
                    entries = int(ptr[-1])
                    feature = np.frombuffer(feature.as_buffer(), np.int32 if len(feature.as_buffer()) == 4 * entries else np.int64)
                    code = np.frombuffer(code.as_buffer(), np.int32) if code.is_valid else np.ones(entries, np.int32)
                    if j is None:
                        rows, at, p = np.arange(len(y)), np.arange(entries), np.zeros(len(y), np.int32)
                    else:
                        here = np.flatnonzero(feature == j)
                        rows, p = np.searchsorted(ptr, here, side="right") - 1, code[here]
                        if not len(rows):
                            continue
                    length = (ptr[1:] - ptr[:-1])[rows]
                    if j is not None:
                        at = np.arange(length.sum()) + np.repeat(ptr[rows] - (np.cumsum(length) - length), length)
                    held.append((feature[at].astype(np.int64), code[at], np.repeat(p, length), np.repeat(y[rows], length), np.ones(len(at), np.int64)))
                    size += len(at)
                    if size > GATHERED:
                        held = [added()]
                        size = len(held[0][0])
                        if size > GATHERED // 2:  # mostly distinct: adding up waits for the exchange
                            yield out(held)
                            held, size = [], 0
            if held:
                held = [added()]
                yield out(held)

        def out(held: list[tuple]) -> pa.RecordBatch:
            f, x, p, y, c = held[0]
            return pa.RecordBatch.from_arrays([pa.array(f), pa.array(x, pa.int32()), pa.array(p, pa.int32()), pa.array(y, pa.int32()), pa.array(c, pa.int64())], names=["feature", "x", "j", "y", "c"])

        partial = _tasks(self.blocks).mapInArrow(count, "feature long, x int, j int, y int, c long")
        return partial.groupBy("feature", "x", "j", "y").agg(F.sum("c").alias("c"))

    def relevance(self) -> tuple[np.ndarray, list[str], np.ndarray]:
        """Feature numbers in order, names, I(feature; class).  Keeps the totals that the rounds need."""
        words = self.ds.vocabulary.select("feature", "name").toArrow()
        ids = words.column("feature").to_numpy()
        order = np.argsort(ids)
        self.ids = ids[order]
        names = words.column("name").take(pa.array(order)).to_pylist()
        ys = np.array(sorted(self.class_counts), np.int64)
        self.y_codes, self.class_sizes = ys, np.array([self.class_counts[y] for y in ys.tolist()], np.float64)
        t = self.met().toArrow()
        at = np.searchsorted(self.ids, t.column("feature").to_numpy())
        known = (at < len(self.ids)) & (self.ids[np.minimum(at, len(self.ids) - 1)] == t.column("feature").to_numpy()) if len(self.ids) else np.zeros(len(at), bool)
        x, y, c = (t.column(k).to_numpy()[known].astype(np.int64) for k in ("x", "y", "c"))
        self.totals = at[known], x, np.searchsorted(ys, y), c
        self.n = float(self.class_sizes.sum())
        self.s_xy, self.s_x = self._single(True), self._single(False)
        s_y = _g(self.class_sizes).sum()
        rel = np.log2(max(self.n, 1.0)) + (self.s_xy - self.s_x - s_y) / max(self.n, 1.0)
        return self.ids, names, _clamped(rel)

    def _single(self, with_y: bool) -> np.ndarray:
        """Sum of c log c over the codes of each feature (and class), 0 included."""
        f, x, y, c = self.totals
        sizes = self.class_sizes if with_y else np.array([self.n])
        y = y if with_y else np.zeros_like(y)
        width = int(x.max()) + 1 if len(x) else 1
        key, total = _added((f * width + x) * len(sizes) + y, c)
        left = sizes[None, :] - np.bincount(f * len(sizes) + y, c, len(self.ids) * len(sizes)).reshape(-1, len(sizes))
        return np.bincount(key // (width * len(sizes)), _g(total), len(self.ids)) + _g(left).sum(1)

    def _joint(self, met: tuple[np.ndarray, ...], freq: tuple[np.ndarray, ...], with_y: bool) -> np.ndarray:
        """Sum of c log c over the cells (x, j) or (x, j, y) of each feature: those met are counted, the others follow."""
        sizes = self.class_sizes if with_y else np.array([self.n])
        ny, n = len(sizes), len(self.ids)
        f, x, y, c = self.totals
        mf, mx, mj, my, mc = met
        fj, fy, fc = freq
        if not with_y:
            y, my, fy = np.zeros_like(y), np.zeros_like(my), np.zeros_like(fy)
        nx = int(max(x.max(initial=0), mx.max(initial=0))) + 1
        nj = int(max(mj.max(initial=0), fj.max(initial=0))) + 1
        key, cell = _added(((mf * nx + mx) * nj + mj) * ny + my, mc)
        out = np.bincount(key // (nx * nj * ny), _g(cell), n)
        # (x, 0): the feature's totals less what was met
        key, total = _added((f * nx + x) * ny + y, c)
        mkey, m = _added((mf * nx + mx) * ny + my, mc)
        left = total.copy()
        left[np.searchsorted(key, mkey)] -= m
        out += np.bincount(key // (nx * ny), _g(left), n)
        # (0, j): the chosen feature's counts less what was met
        fkey, often = _added(fj * ny + fy, fc)
        mkey, m = _added((mf * nj + mj) * ny + my, mc)
        before = often[np.searchsorted(fkey, mkey % (nj * ny))]
        out += _g(often).sum() + np.bincount(mkey // (nj * ny), _g(before - m) - _g(before), n)
        # (0, 0): what is left of the class
        own = np.bincount(f * ny + y, c, n * ny).reshape(n, ny)
        both = np.bincount(mf * ny + my, mc, n * ny).reshape(n, ny)
        return out + _g(sizes[None, :] - own - np.bincount(fy, fc, ny)[None, :] + both).sum(1)

    def pair(self, j: int, some: list[int] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Feature numbers in order, I(feature; j), I(feature; j | class), of all features (or some of them)."""
        t = self.met(j).toArrow()
        f = t.column("feature").to_numpy()
        x, p, y, c = (t.column(k).to_numpy().astype(np.int64) for k in ("x", "j", "y", "c"))
        y = np.searchsorted(self.y_codes, y)
        at = np.minimum(np.searchsorted(self.ids, f), max(len(self.ids) - 1, 0))
        own = f == j
        freq = p[own], y[own], c[own]
        known = self.ids[at] == f
        met = tuple(v[known] for v in (at, x, p, y, c))
        n, ny = self.n, len(self.class_sizes)
        fkey, often = _added(freq[0] * ny + freq[1], freq[2])
        jy = _g(often).sum() + _g(self.class_sizes - np.bincount(freq[1], freq[2], ny)).sum()
        _, by_j = _added(freq[0], freq[2])
        just_j = _g(by_j).sum() + _g(np.array([n - freq[2].sum()])).sum()
        mi = np.log2(n) + (self._joint(met, freq, False) - self.s_x - just_j) / n
        cmi = (self._joint(met, freq, True) + _g(self.class_sizes).sum() - self.s_xy - jy) / n
        mi, cmi = _clamped(mi), _clamped(cmi)
        if some is None:
            return self.ids, mi, cmi
        place = np.searchsorted(self.ids, np.array(sorted(some), np.int64))
        return self.ids[place], mi[place], cmi[place]


def _clamped(x: np.ndarray) -> np.ndarray:
    """Negative results that are rounding become 0."""
    return np.where((x < 0) & (x > -1e-9), 0.0, x)
