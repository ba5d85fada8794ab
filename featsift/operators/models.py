"""Classifiers for the evaluation of selections."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.encode import cardinalities

#: Bytes of packed rows that gradient descent fetches to the driver; more stay with the executors.
LOCAL_BYTES = 32 << 20
#: Widths of the hinge's rounded corner, from the first to the last; Newton steps at each.
CORNERS, NEWTON = tuple(4.0**-i for i in range(8)), 30


def _long(rows: DataFrame, features: list[str], *keep: str) -> DataFrame:
    return rows.select(*keep, F.posexplode(F.array(*[F.col(f).cast("int") for f in features])).alias("feature", "x"))


class CategoricalNB:
    """Naive Bayes over codes with additive smoothing, for two classes: one aggregate to fit, a projection to score.

    The fitted model is a weight for each feature and code, as many as the cardinalities add up to.
    """

    def __init__(self, features: list[str], smoothing: float = 1.0):
        self.features, self.smoothing = features, smoothing
        self.prior = 0.0
        self.weights: list[list[float]] = [[] for _ in features]

    def fit(self, rows: DataFrame, y: str = "y") -> CategoricalNB:
        a = self.smoothing
        one, zero = F.sum(F.when(F.col(y) == 1, 1).otherwise(0)), F.sum(F.when(F.col(y) == 1, 0).otherwise(1))
        cells = _long(rows, self.features, y).where("x IS NOT NULL").groupBy("feature", "x").agg(one.alias("c1"), zero.alias("c0")).collect()
        n = rows.agg(one.alias("n1"), zero.alias("n0")).first()
        n1, n0 = n["n1"] or 0, n["n0"] or 0
        self.prior = math.log((n1 + a) / (n0 + a))
        for i in range(len(self.features)):
            mine = {r["x"]: (r["c1"], r["c0"]) for r in cells if r["feature"] == i}
            v = len(mine)
            self.weights[i] = [math.log((c[0] + a) / (n1 + a * v)) - math.log((c[1] + a) / (n0 + a * v)) if (c := mine.get(x)) else 0.0 for x in range(max(mine, default=-1) + 1)]
        return self

    def score(self, rows: DataFrame, key: list[str], y: str = "y") -> DataFrame:
        """key, y, score (log odds to 10 digits).  A code that training didn't have says nothing."""
        odds = F.lit(self.prior)
        for f, w in zip(self.features, self.weights):
            if w:
                odds = odds + F.coalesce(F.get(F.array(*[F.lit(x) for x in w]), F.col(f).cast("int")), F.lit(0.0))
        return rows.select(*key, F.col(y).alias("y"), F.round(odds, 10).alias("score"))


class OneHot:
    """Codes as indicator vectors, which is what multinomial models understand.

    Fitted once, on the training rows: all vectors it makes have the same positions.  Codes that training didn't have,
    and nulls, share one position of their own for each feature.
    """

    def __init__(self, train: DataFrame, features: list[str], out: str = "v"):
        self.features, self.out = features, out
        self.cards = cardinalities(train, features)

    def __call__(self, rows: DataFrame) -> DataFrame:
        """v, y, and the weight of rows that have one."""
        from pyspark.ml.functions import array_to_vector

        def indicators(f: str):
            code = F.col(f).cast("int")
            place = F.when((code >= 0) & (code < self.cards[f]), code).otherwise(self.cards[f])
            return F.transform(F.sequence(F.lit(0), F.lit(self.cards[f])), lambda i: (i == place).cast("double"))

        return rows.select(array_to_vector(F.concat(*map(indicators, self.features))).alias(self.out), F.col("y").cast("double").alias("y"), *_weight(rows))


def _weight(rows: DataFrame) -> list[str]:
    return ["weight"] if "weight" in rows.columns else []


def grouped(rows: DataFrame, features: list[str]) -> DataFrame:
    """Rows with equal codes and class once, their number as the weight."""
    return rows.groupBy(*features, "y").agg(F.count("*").alias("weight"))


def presence_vectors(ds, features: list[int], out: str = "v") -> DataFrame:
    """row_id, v, y of a sparse data set: a position for each of the given features, its code where a row has it."""
    place = F.create_map(*[x for i, f in enumerate(features) for x in (F.lit(f).cast("long"), F.lit(i))])
    entry = F.struct(place[F.col("feature")].alias("i"), F.col("code").cast("double").alias("v"))
    found = ds.postings.where(F.col("feature").isin(features)).groupBy("row_id").agg(F.map_from_entries(F.collect_list(entry)).alias("m"))
    from pyspark.ml.functions import array_to_vector

    value = F.transform(F.sequence(F.lit(0), F.lit(len(features) - 1)), lambda i: F.coalesce(F.element_at(F.col("m"), i), F.lit(0.0)))
    return ds.classes.join(found, "row_id", "left").select("row_id", array_to_vector(value).alias(out), F.col("y").cast("double").alias("y"))


def restricted(presence: DataFrame, k: int) -> DataFrame:
    """``presence`` of the first k features: equal rows once."""
    return presence.groupBy("inside", "y", F.filter("at", lambda i: i < k).alias("at")).agg(F.sum("weight").alias("weight"))


def present(presence: DataFrame, k: int, out: str = "v") -> DataFrame:
    """v, y, and the weight of rows that have one: a position for each of the first k features, 1 where a row has it."""
    from pyspark.ml.functions import array_to_vector

    value = F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.array_contains("at", i).cast("double"))
    return presence.select(array_to_vector(value).alias(out), F.col("y").cast("double").alias("y"), *_weight(presence))


def naive_bayes(train: DataFrame, vector: str = "v", smoothing: float = 1.0):
    from pyspark.ml.classification import NaiveBayes

    weighted = {"weightCol": "weight"} if _weight(train) else {}
    return NaiveBayes(featuresCol=vector, labelCol="y", smoothing=smoothing, **weighted).fit(train)


@dataclass
class LinearModel:
    weights: np.ndarray
    intercept: float = 0.0


def packed(rows: DataFrame, vector: str = "v") -> DataFrame:
    """Vectors, classes and weights as blocks of the entries other than 0: n, size, ptr, at, value (null: all 1), y, w."""
    from pyspark.ml.functions import vector_to_array

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column(0).flatten().to_numpy().reshape(batch.num_rows, -1)
            y = batch.column(1).to_numpy()
            if not np.isin(y, (0.0, 1.0)).all():
                raise ValueError("classes must be 0 and 1")
            row, at = np.nonzero(x)
            value = x[row, at]
            ptr = np.searchsorted(row, np.arange(batch.num_rows + 1)).astype(np.int32)
            parts = (ptr, at.astype(np.int32), None if (value == 1).all() else value, y.astype(np.int8), batch.column(2).to_numpy().astype(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array([len(y)]), pa.array([x.shape[1]]), *(pa.array([None if v is None else v.tobytes()], pa.binary()) for v in parts)], names=["n", "size", "ptr", "at", "value", "y", "w"])

    weight = F.col("weight").cast("long") if _weight(rows) else F.lit(1).cast("long")
    return rows.select(vector_to_array(vector), "y", weight).mapInArrow(pack, "n long, size long, ptr binary, at binary, value binary, y binary, w binary")


def _slope(block, weights: np.ndarray) -> np.ndarray:
    """The sum of the hinge loss's subgradients over a block."""
    ptr, at = np.frombuffer(block["ptr"], np.int32), np.frombuffer(block["at"], np.int32)
    value = 1.0 if block["value"] is None else np.frombuffer(block["value"], np.float64)
    sign = 2.0 * np.frombuffer(block["y"], np.int8) - 1.0
    w = np.frombuffer(block["w"], np.int64)
    row = np.repeat(np.arange(len(sign)), np.diff(ptr))
    margin = np.bincount(row, weights[at] * value, len(sign))
    push = np.where(sign * margin < 1, -sign * w, 0.0)
    return np.bincount(at, push[row] * value, len(weights))


def sgd(blocks: DataFrame, step: float, reg: float, iters: int, tol: float = 0.001) -> LinearModel:
    """Gradient steps over all rows, as the library's stochastic gradient descent makes them when a batch is all rows.

    The step falls with the root of the round, weights shrink by the regularisation, and rounds end when the weights
    hardly move.  Few bytes of blocks are fetched once; else each round is a job that returns one vector for each task.
    """
    blocks = blocks.persist()
    try:
        total = blocks.agg(F.max("size").alias("size"), F.sum(F.length("ptr") + F.length("at") + F.coalesce(F.length("value"), F.lit(0)) + F.length("w")).alias("bytes")).first()
        if total["size"] is None:
            raise ValueError("no rows to fit")
        local = blocks.collect() if total["bytes"] <= LOCAL_BYTES else None
        spread = None if local is not None else blocks.coalesce(2 * blocks.sparkSession.sparkContext.defaultParallelism)
        n = float(sum(int(np.frombuffer(b["w"], np.int64).sum()) for b in local)) if local is not None else None
        if n is None:

            def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for batch in batches:
                    yield pa.RecordBatch.from_arrays([pa.array([int(np.frombuffer(b, np.int64).sum()) for b in batch.column("w").to_pylist()], pa.int64())], names=["n"])

            n = float(spread.mapInArrow(count, "n long").agg(F.sum("n")).first()[0])

        def slope(weights: np.ndarray) -> np.ndarray:
            if local is not None:
                return sum(_slope(b, weights) for b in local)

            def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                found = np.zeros(len(weights))
                for batch in batches:
                    for b in batch.to_pylist():
                        found += _slope(b, weights)
                yield pa.RecordBatch.from_arrays([pa.array([found.tobytes()], pa.binary())], names=["g"])

            return sum(np.frombuffer(r["g"], np.float64) for r in spread.mapInArrow(partial, "g binary").collect())

        weights = np.zeros(total["size"])
        for t in range(1, iters + 1):
            size = step / math.sqrt(t)
            before, weights = weights, weights * (1.0 - size * reg) - size * slope(weights) / n
            if t > 1 and np.linalg.norm(weights - before) < tol * max(np.linalg.norm(weights), 1.0):
                break
        return LinearModel(weights)
    finally:
        blocks.unpersist()


def _dense(block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows, signs and weights of a block."""
    ptr, at = np.frombuffer(block["ptr"], np.int32), np.frombuffer(block["at"], np.int32)
    x = np.zeros((block["n"], block["size"]))
    x[np.repeat(np.arange(block["n"]), np.diff(ptr)), at] = 1.0 if block["value"] is None else np.frombuffer(block["value"], np.float64)
    return x, 2.0 * np.frombuffer(block["y"], np.int8) - 1.0, np.frombuffer(block["w"], np.int64).astype(np.float64)


def _moments(block) -> np.ndarray:
    x, _, w = _dense(block)
    return np.concatenate(([w.sum()], w @ x, w @ (x * x)))


def _bend(block, scale: np.ndarray, at: np.ndarray, corner: float) -> np.ndarray:
    """Loss, slope and curvature over a block of the hinge with a rounded corner, at scaled weights and the intercept."""
    x, sign, w = _dense(block)
    x = np.hstack([x * scale, np.ones((len(x), 1))])
    short = 1.0 - sign * (x @ at)
    loss = np.where(short >= corner, short - corner / 2, np.maximum(short, 0.0) ** 2 / (2 * corner))
    push = np.clip(short / corner, 0.0, 1.0)
    bent = (short > 0) & (short < corner)
    return np.concatenate(([w @ loss], -(w * sign * push) @ x, ((x[bent] * (w[bent] / corner)[:, None]).T @ x[bent]).ravel()))


def hinge(blocks: DataFrame, reg: float) -> LinearModel:
    """The linear support vector machine with an intercept over blocks of weighted rows: what the library's batch optimiser minimises.

    Features count in units of their deviation, as there.  Newton steps go down a hinge with a rounded corner, which
    becomes sharper from stage to stage; the last one is off by less than half its width.  Few bytes of blocks are
    fetched once; else each step is a job that returns one vector for each task.
    """
    blocks = blocks.persist()
    try:
        total = blocks.agg(F.max("size").alias("size"), F.sum(F.length("ptr") + F.length("at") + F.coalesce(F.length("value"), F.lit(0)) + F.length("w")).alias("bytes")).first()
        if total["size"] is None:
            raise ValueError("no rows to fit")
        k = total["size"]
        local = blocks.collect() if total["bytes"] <= LOCAL_BYTES else None
        spread = None if local is not None else blocks.coalesce(2 * blocks.sparkSession.sparkContext.defaultParallelism)

        def added(part, *given) -> np.ndarray:
            if local is not None:
                return sum(part(b, *given) for b in local)

            def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                found = [part(b, *given) for batch in batches for b in batch.to_pylist()]
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array([sum(found).tobytes()], pa.binary())], names=["g"])

            return sum(np.frombuffer(r["g"], np.float64) for r in spread.mapInArrow(partial, "g binary").collect())

        moments = added(_moments)
        n, mean = moments[0], moments[1 : k + 1] / moments[0]
        deviation = np.sqrt(np.maximum(moments[k + 1 :] - n * mean * mean, 0.0) / max(n - 1, 1.0))
        scale = np.where(deviation > 0, 1.0 / np.where(deviation > 0, deviation, 1.0), 0.0)
        ridge = np.append(np.full(k, reg), 0.0)

        def bent(at: np.ndarray, corner: float) -> tuple[float, np.ndarray, np.ndarray]:
            found = added(_bend, scale, at, corner) / n
            return found[0] + ridge @ (at * at) / 2, found[1 : k + 2] + ridge * at, found[k + 2 :].reshape(k + 1, k + 1) + np.diag(ridge + 1e-6)

        at = np.zeros(k + 1)
        for corner in CORNERS:
            value, slope, curve = bent(at, corner)
            for _ in range(NEWTON):
                step, size = -np.linalg.solve(curve, slope), 1.0
                if -(slope @ step) < 1e-11:
                    break
                while (new := bent(at + size * step, corner))[0] > value + 1e-4 * size * (slope @ step) and size > 1e-9:
                    size /= 2
                if new[0] >= value:
                    break
                gain, at, (value, slope, curve) = value - new[0], at + size * step, new
                if gain < 1e-12:
                    break
        return LinearModel(at[:k] * scale, float(at[k]))
    finally:
        blocks.unpersist()


def svm(train: DataFrame, vector: str = "v", step: float = 1.0, reg: float = 1.0, iters: int = 100, batch: float = 1.0, impl: str = "owlqn"):
    """Linear support vector machine: by batch optimisation (packed rows: Newton steps), or by stochastic gradient descent (impl 'sgd')."""
    if impl == "sgd" and batch >= 1.0:
        return sgd(train if "ptr" in train.columns else packed(train, vector), step, reg, iters)
    if impl == "sgd":
        from pyspark.ml.functions import vector_to_array
        from pyspark.mllib.classification import SVMWithSGD
        from pyspark.mllib.regression import LabeledPoint

        points = train.select(vector_to_array(vector).alias("a"), "y").rdd.map(lambda r: LabeledPoint(r["y"], r["a"]))
        model = SVMWithSGD.train(points, iterations=iters, step=step, regParam=reg, miniBatchFraction=batch)
        model.clearThreshold()
        return model
    if "ptr" in train.columns:
        return hinge(train, reg)
    from pyspark.ml.classification import LinearSVC

    return LinearSVC(featuresCol=vector, labelCol="y", regParam=reg, maxIter=iters).fit(train)


def scored(model, test: DataFrame, vector: str = "v") -> DataFrame:
    """y, score of a fitted model, and the weight of rows that have one."""
    from pyspark.ml.functions import vector_to_array

    if hasattr(model, "transform"):
        margin = F.element_at(vector_to_array("rawPrediction"), 2)
        return model.transform(test).select("y", margin.alias("score"), *_weight(test))
    weights, bias = F.array(*[F.lit(float(w)) for w in model.weights]), float(model.intercept)
    product = F.aggregate(F.zip_with(vector_to_array(vector), weights, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return test.select("y", (product + bias).alias("score"), *_weight(test))
