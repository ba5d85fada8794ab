"""Greedy forward selection.

Relevance is counted once; each round counts the cells of all candidates with the last chosen feature only, folds them
into the criterion's accumulators and takes the best candidate.  While the features are few enough, the accumulators live
on the driver and a round is one job on packed blocks that returns two numbers for each feature; else they are a table
that each round writes anew, of which only the best row is looked at.

Scores are compared after rounding to 12 decimals; the lowest feature number wins a tie.
"""

from __future__ import annotations

import hashlib
import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.criteria import ArrayOps, ColumnOps, Criterion, get_criterion
from ..plans import planner
from ..plans.dataset import Dataset, SparseDataset
from ..plans.layout import to_feature_blocks
from ..plans.storage import saved
from ..plans.tokens import TokenSet
from . import pooled, sparse
from . import relevance as rel_ops
from .packed import DenseEngine, SparseEngine

DIGITS = 12
RESULT = "step int, feature long, name string, score double, rel double"


@dataclass
class Selection:
    spark: SparkSession
    steps: list[dict]
    seconds: list[float] = field(default_factory=list)
    #: Candidates whose cells were counted in each round.
    counted: list[int] = field(default_factory=list)
    #: Of a text set: the blocks with the tokens that took part, and the places of the chosen ones there.
    blocks: DataFrame | None = None
    places: list[int] = field(default_factory=list)

    @property
    def names(self) -> list[str]:
        return [s["name"] for s in self.steps]

    def to_df(self) -> DataFrame:
        return self.spark.createDataFrame([(s["step"], s["feature"], s["name"], s["score"], s["rel"]) for s in self.steps], RESULT)


def select(
    ds: Dataset | SparseDataset,
    k: int,
    criterion: str | Criterion = "mrmr",
    *,
    beta: float | None = None,
    gamma: float | None = None,
    strategy: str = "auto",
    state: str = "auto",
    lazy: bool = False,
    min_score: float | None = None,
    resume: str | None = None,
    cache: bool = True,
) -> Selection:
    """The first k features (all, if there are fewer) by the criterion.

    strategy: packed, explode, arrow, gsets or blocks (sparse data: packed or sparse).  state: driver or frame.  lazy:
    skips candidates whose upper bound can't win (criteria whose score only falls).  min_score ends the selection before
    a score below it.  resume: a folder in which every round is logged; a second call with the same data continues after
    the last logged round, one with other data is refused.
    """
    crit = get_criterion(criterion, beta, gamma)
    if isinstance(ds, TokenSet) and crit.bounded and (strategy, state, lazy, resume) == ("auto", "auto", False, None) and ds.plain and ds.size:
        rounds = _PoolRounds(ds, k, crit, min_score)
        try:
            return rounds.run()
        except _PoolFull:
            pass
        finally:
            rounds.engine.release()
    plan = planner.choose(ds, state)
    how = plan.counting if strategy == "auto" else strategy
    spark = (ds.vocabulary if ds.sparse else ds.df).sparkSession
    log = Log(spark, resume, ds) if resume else None
    if plan.state == "driver" and how == "packed":
        engine = (SparseEngine if ds.sparse else DenseEngine)(ds)
    else:
        engine = TableEngine(ds, how, cache)
    try:
        if plan.state == "frame":
            return _in_table(engine, spark, k, crit, log, min_score)
        if isinstance(engine, DenseEngine) and not log and min_score is None and not (lazy and crit.falling):
            engine.expect(k)
        return _Rounds(engine, spark, k, crit, log, min_score, lazy and crit.falling).run()
    finally:
        engine.release()


def select_each(ds: Dataset | SparseDataset, k: int, names: Sequence[str]) -> dict[str, Selection]:
    """The first k features by each of several criteria: rows are packed once, and counts that several need are made once."""
    engine = (SparseEngine if ds.sparse else DenseEngine)(ds)
    engine.relevance, engine.pair = cache(engine.relevance), cache(engine.pair)
    spark = (ds.vocabulary if ds.sparse else ds.df).sparkSession
    try:
        return {c: _Rounds(engine, spark, k, get_criterion(c), None, None, False).run() for c in names}
    finally:
        engine.release()


class Log:
    """Rounds in a folder: relevance, and the redundancy of all features with each chosen one.

    The folder belongs to one data set: a digest of its features, class, weights and rows is written first and compared
    by every later call.
    """

    def __init__(self, spark: SparkSession, folder: str, ds: Dataset | SparseDataset):
        self.spark, self.folder = spark, folder
        mark, path = fingerprint(ds), f"{folder}/fingerprint"
        if not self.has(path):
            spark.createDataFrame([(mark,)], "mark string").coalesce(1).write.mode("overwrite").parquet(path)
        elif spark.read.parquet(path).first()["mark"] != mark:
            raise ValueError(f"{folder} is the log of another data set")

    def has(self, path: str) -> bool:
        at = self.spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
        return at.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(at)

    def table(self, name: str, make: Callable[[], DataFrame]) -> DataFrame:
        """A table of the log, made first if it isn't there."""
        path = f"{self.folder}/{name}"
        if not self.has(path):
            make().write.mode("overwrite").parquet(path)
        return self.spark.read.parquet(path)


def fingerprint(ds: Dataset | SparseDataset) -> str:
    """A digest of what a selection depends on, in one aggregate over the rows; their order doesn't matter."""
    total = lambda df, *c: tuple(df.agg(F.count("*"), F.sum(F.xxhash64(*c).cast("decimal(38,0)"))).first())
    if ds.sparse:
        parts = ("sparse", total(ds.postings, "feature", "row_id", "code", "y"), total(ds.classes, "row_id", "y"), total(ds.vocabulary, "feature", "name"))
    else:
        parts = ("dense", tuple(ds.features), ds.label, ds.weight, total(ds.columns(), *ds.features, "y", "_w"))
    return hashlib.sha256(repr(parts).encode()).hexdigest()


class TableEngine:
    """Counting by DataFrame operations: every strategy but the packed one."""

    def __init__(self, ds: Dataset | SparseDataset, how: str, cache: bool):
        self.ds = ds.materialized() if cache else ds
        self.cache, self.how, self.more, self.packed = cache, None if ds.sparse else how, {}, None
        if ds.sparse:
            self.more["totals"] = saved(sparse.feature_totals(self.ds), "totals")
            if how == "packed":
                self.packed = SparseEngine(self.ds)
        elif how == "blocks":
            self.more["blocks"] = saved(to_feature_blocks(self.ds), "blocks")

    def release(self) -> None:
        if self.cache:
            self.ds.release()
        if self.packed:
            self.packed.release()

    def relevance_table(self) -> DataFrame:
        return rel_ops.named(self.ds, rel_ops.relevance(self.ds, self.how, **self.more))

    def pair_table(self, feature: int) -> DataFrame:
        j = feature if self.ds.sparse else self.ds.features[feature]
        met = {"met": saved(self.packed.met(feature), "met")} if self.packed else {}
        return rel_ops.redundancy(self.ds, j, self.how, **self.more, **met)

    def relevance(self) -> tuple[np.ndarray, list[str], np.ndarray]:
        t = self.relevance_table().toArrow().sort_by("feature")
        return t.column("feature").to_numpy().astype(np.int64), t.column("name").to_pylist(), t.column("rel").to_numpy()

    def pair(self, j: int, some: list[int] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        found = self.pair_table(j)
        if some is not None:
            if self.ds.sparse:
                found = found.where(F.col("feature").isin(some))
            else:
                # the chosen feature comes along as the carried column
                found = rel_ops.redundancy(self.ds.only([self.ds.features[i] for i in sorted(some)]), self.ds.features[j], "explode")
        t = found.toArrow().sort_by("feature")
        feature = t.column("feature").to_numpy().astype(np.int64)
        if some is not None and not self.ds.sparse:
            feature = np.array(sorted(some), np.int64)[feature]
        return feature, t.column("mi").to_numpy(), t.column("cmi").to_numpy()


class _Taken:
    """The steps of a selection."""

    def __init__(self, spark: SparkSession, min_score: float | None):
        self.min_score, self.out = min_score, Selection(spark, [])

    def take(self, feature: int, name: str, score: float, rel: float, began: float, counted: int) -> bool:
        if self.min_score is not None and score < self.min_score:
            return False
        self.out.steps.append({"step": len(self.out.steps) + 1, "feature": int(feature), "name": name, "score": float(score), "rel": float(rel)})
        self.out.seconds.append(time.perf_counter() - began)
        self.out.counted.append(counted)
        return True


class _Rounds(_Taken):
    """Accumulators as arrays: one number per feature and accumulator."""

    def __init__(self, engine, spark: SparkSession, k: int, crit: Criterion, log: Log | None, min_score: float | None, lazy: bool):
        super().__init__(spark, min_score)
        self.engine, self.spark, self.k, self.crit, self.log, self.lazy = engine, spark, k, crit, log, lazy

    def relevance(self) -> tuple[np.ndarray, list[str], np.ndarray]:
        if not self.log:
            return self.engine.relevance()

        def make() -> DataFrame:
            ids, names, rel = self.engine.relevance()
            return self.spark.createDataFrame(pa.table({"feature": ids, "name": pa.array(names, pa.string()), "rel": rel}))

        t = self.log.table("relevance", make).toArrow().sort_by("feature")
        if isinstance(self.engine, SparseEngine):
            self.engine.relevance()  # the totals that the rounds need
        return t.column("feature").to_numpy(), t.column("name").to_pylist(), t.column("rel").to_numpy()

    def pair(self, j: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if not self.log:
            return self.engine.pair(j)
        make = lambda: self.spark.createDataFrame(pa.table(dict(zip(("feature", "mi", "cmi"), self.engine.pair(j)))))
        t = self.log.table(f"pair-{j}", make).toArrow().sort_by("feature")
        return tuple(t.column(c).to_numpy() for c in ("feature", "mi", "cmi"))

    def run(self) -> Selection:
        began = time.perf_counter()
        self.ids, self.names, self.rel = self.relevance()
        n = len(self.ids)
        self.acc = {a: np.full(n, f.init) for a, f in self.crit.folds.items()}
        self.open = np.ones(n, bool)
        self.folded = np.zeros(n, np.int64)  # chosen features already in a candidate's accumulators
        self.chosen: list[int] = []
        self.pairs = 0
        while len(self.chosen) < min(self.k, n):
            before = self.pairs
            best = self.best_lazy() if self.lazy else self.best()
            score = round(float(self.scores()[best]), DIGITS)
            if not self.take(self.ids[best], self.names[best], score, self.rel[best], began, self.pairs - before):
                break
            self.open[best] = False
            self.chosen.append(best)
            began = time.perf_counter()
            if self.crit.folds and not self.lazy and len(self.chosen) < min(self.k, n):
                self.fold_all(best)
        return self.out

    def scores(self) -> np.ndarray:
        with np.errstate(invalid="ignore"):
            s = np.asarray(self.crit.score(ArrayOps, self.rel, self.acc, len(self.chosen)), np.float64)
        return np.where(self.open, np.round(s, DIGITS), -np.inf)

    def best(self) -> int:
        return int(np.argmax(self.scores()))  # the first of equals

    def fold(self, at: np.ndarray, mi: np.ndarray, cmi: np.ndarray) -> None:
        for name, f in self.crit.folds.items():
            self.acc[name][at] = f.combine(ArrayOps, self.acc[name][at], mi, cmi)

    def fold_all(self, best: int) -> None:
        ids, mi, cmi = self.pair(int(self.ids[best]))
        self.fold(np.searchsorted(self.ids, ids), mi, cmi)
        self.pairs += int(self.open.sum())

    def best_lazy(self) -> int:
        """Folds what is missing only into candidates whose bound (their score without it) may still win."""
        s = len(self.chosen)
        while True:
            bound = self.scores()
            stale = self.open & (self.folded < s)
            best = int(np.argmax(bound))
            if not stale[best]:
                return best
            # a batch of the best bounds, each brought up to date with the feature it misses next
            order = np.argsort(-bound, kind="stable")
            batch = [i for i in order[: max(4, len(order) // 8)] if stale[i]]
            for missing in sorted({int(self.folded[i]) for i in batch}):
                these = np.array(sorted(i for i in batch if self.folded[i] == missing))
                _, mi, cmi = self.engine.pair(int(self.ids[self.chosen[missing]]), [int(x) for x in self.ids[these]])
                self.fold(these, mi, cmi)
                self.folded[these] += 1
                self.pairs += len(these)


class _PoolFull(Exception):
    """Too many tokens would have to take part."""


class _PoolRounds(_Rounds):
    """Rounds over the most relevant tokens; more take part as soon as one that is left out may win."""

    def __init__(self, ds: TokenSet, k: int, crit: Criterion, min_score: float | None):
        self.ds, self.m = ds, max(pooled.POOL, k + 1)
        super().__init__(pooled.PoolEngine(ds, self.m), ds.spark, k, crit, None, min_score, False)

    def run(self) -> Selection:
        out = super().run()
        for step, number in zip(out.steps, self.ds.numbers([self.engine.keys[i] for i in self.chosen])):
            step["feature"] = number
        out.blocks, out.places = self.engine.stored, self.chosen[: len(out.steps)]
        return out

    def best(self) -> int:
        while True:
            scores = self.scores()
            best = int(np.argmax(scores))
            if scores[best] > self.engine.bound + 3 * 10.0**-DIGITS:
                return best
            self.grow()

    def grow(self) -> None:
        """Four times as many tokens, all of them brought up to date with the chosen ones."""
        chosen, self.m = [self.engine.keys[i] for i in self.chosen], 4 * self.m
        if self.m > planner.DRIVER_STATE:
            raise _PoolFull
        self.engine.release()
        self.engine = pooled.PoolEngine(self.ds, self.m)
        self.ids, self.names, self.rel = self.engine.relevance()
        self.acc = {a: np.full(len(self.ids), f.init) for a, f in self.crit.folds.items()}
        place = {key: i for i, key in enumerate(self.engine.keys)}
        self.chosen = [place[key] for key in chosen]
        self.open = np.ones(len(self.ids), bool)
        self.open[self.chosen] = False
        if self.crit.folds:
            size = 1 + self.engine.ahead()
            for at, j in enumerate(self.chosen):
                if at % size == 0:
                    self.engine.count(self.chosen[at : at + size])
                self.fold(*self.engine.pair(j))

    def pair(self, j: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if j not in self.engine.known:
            # likely choices of the next rounds are counted with it
            likely = [int(i) for i in np.argsort(-self.scores(), kind="stable")[: self.k - len(self.chosen)] if self.open[i] and i not in self.engine.known]
            self.engine.count([j, *likely[: self.engine.ahead()]])
        return self.engine.pair(j)


def _in_table(engine: TableEngine, spark: SparkSession, k: int, crit: Criterion, log: Log | None, min_score: float | None) -> Selection:
    """Accumulators as a table in the shared folder: for more features than the driver should hold."""
    began, taken, folds = time.perf_counter(), _Taken(spark, min_score), crit.folds
    relevance = log.table("relevance", engine.relevance_table) if log else engine.relevance_table()
    state = saved(relevance.select(F.col("feature").cast("long").alias("feature"), "name", "rel", *[F.lit(f.init).alias(f"acc_{a}") for a, f in folds.items()]), "state")
    chosen: list[int] = []
    while len(chosen) < k:
        acc = {a: F.col(f"acc_{a}") for a in folds}
        score = F.round(crit.score(ColumnOps, F.col("rel"), acc, len(chosen)), DIGITS)
        left = state.where(~F.col("feature").isin(chosen)) if chosen else state
        top = left.select("feature", "name", "rel", score.alias("score")).orderBy(F.desc("score"), "feature").limit(1).collect()
        if not top or not taken.take(top[0]["feature"], top[0]["name"], top[0]["score"], top[0]["rel"], began, -1):
            break
        began = time.perf_counter()
        chosen.append(top[0]["feature"])
        if folds and len(chosen) < k:
            j = chosen[-1]
            pair = log.table(f"pair-{j}", lambda j=j: engine.pair_table(j)) if log else engine.pair_table(j)
            joined = state.join(pair.withColumn("feature", F.col("feature").cast("long")), "feature", "left")
            mi, cmi = F.coalesce("mi", F.lit(0.0)), F.coalesce("cmi", F.lit(0.0))
            state = saved(joined.select("feature", "name", "rel", *[f.combine(ColumnOps, F.col(f"acc_{a}"), mi, cmi).alias(f"acc_{a}") for a, f in folds.items()]), "state")
    return taken.out
