"""Counting for selections whose scores relevance bounds: only the most relevant tokens of a text set become blocks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel

from ..plans.tokens import TokenSet
from .packed import _clamped, _g

#: Tokens that take part at first; features whose cells one job counts besides the chosen one's; bytes of counts it returns.
POOL, AHEAD, RESULT_BYTES = 1 << 13, 15, 32 << 20


class PoolEngine:
    """Blocks of the rows inside, with the ``m`` most relevant tokens; ``bound`` is the relevance of the best token left out."""

    def __init__(self, ds: TokenSet, m: int):
        self.keys, counts, self.bound = ds.pool(m)
        self.ds, self.ys, self.class_sizes = ds, np.array(ds.class_codes, np.int64), ds.class_counts
        self.n, self.own = float(self.class_sizes.sum()), counts.astype(np.float64)
        self.stored = ds.blocks(self.keys)
        self.tasks = ds.spark.sparkContext.defaultParallelism
        self.blocks = self.stored.where("inside").select("n", "ptr", "feature", "y").coalesce(self.tasks).persist(StorageLevel.MEMORY_AND_DISK)
        self.known: dict[int, np.ndarray] = {}
        own, sizes = self.own, self.class_sizes
        self.s_xy = (_g(own) + _g(sizes[None, :] - own)).sum(1)
        self.s_x = _g(own.sum(1)) + _g(self.n - own.sum(1))

    def release(self) -> None:
        self.blocks.unpersist()

    def relevance(self) -> tuple[np.ndarray, list[str], np.ndarray]:
        n = max(self.n, 1.0)
        rel = np.log2(n) + (self.s_xy - self.s_x - _g(self.class_sizes).sum()) / n
        return np.arange(len(self.keys)), [self.ds.named(k) for k in self.keys], _clamped(rel)

    def met(self, some: list[int]) -> np.ndarray:
        """Rows that have one of the given tokens together with each token, by class, in one job."""
        m, ys = len(self.keys), self.ys

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros((len(some), m * len(ys)), np.int64)
            for batch in batches:
                for r in range(batch.num_rows):
                    ptr, y = (np.frombuffer(batch.column(i)[r].as_buffer(), np.int32) for i in (1, 3))
                    raw = batch.column(2)[r].as_buffer()
                    feature = np.frombuffer(raw, np.uint16 if raw.size == 2 * ptr[-1] else np.int32)
                    y = np.searchsorted(ys, y)
                    for p, j in enumerate(some):
                        rows = np.searchsorted(ptr, np.flatnonzero(feature == j), side="right") - 1
                        for c in range(len(ys)):
                            mine = rows[y[rows] == c]
                            if len(mine):
                                length = (ptr[1:] - ptr[:-1])[mine]
                                at = np.arange(length.sum()) + np.repeat(ptr[mine] - (np.cumsum(length) - length), length)
                                total[p, c::len(ys)] += np.bincount(feature[at], minlength=m)
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["counts"])

        found = np.zeros(len(some) * m * len(ys), np.int64)
        for r in self.blocks.mapInArrow(count, "counts binary").collect():
            found += np.frombuffer(r["counts"], np.int64)
        return found.reshape(len(some), m, len(ys))

    def ahead(self) -> int:
        return int(min(AHEAD, max(0, RESULT_BYTES // max(1, 8 * len(self.keys) * len(self.ys) * self.tasks) - 1)))

    def count(self, some: list[int]) -> None:
        """Counts what the next rounds may ask for."""
        some = [j for j in dict.fromkeys(some) if j not in self.known]
        if some:
            self.known |= dict(zip(some, self.met(some)))

    def pair(self, j: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Feature numbers, I(feature; j), I(feature; j | class)."""
        self.count([j])
        met, own, sizes = self.known.pop(j).astype(np.float64), self.own, self.class_sizes
        n = max(self.n, 1.0)

        def joint(met, own, sizes):
            return sum(_g(c).sum(1) for c in (met, own - met, own[j] - met, sizes - own - own[j] + met))

        both = [v.sum(1, keepdims=True) for v in (met, own)]
        just_j = _g(own[j].sum()) + _g(self.n - own[j].sum())
        jy = (_g(own[j]) + _g(sizes - own[j])).sum()
        mi = np.log2(n) + (joint(*both, np.array([self.n])) - self.s_x - just_j) / n
        cmi = (joint(met, own, sizes) + _g(sizes).sum() - self.s_xy - jy) / n
        return np.arange(len(self.keys)), _clamped(mi), _clamped(cmi)
