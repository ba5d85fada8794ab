"""Selection as a stage of an ML pipeline."""

from __future__ import annotations

from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.feature import VectorSlicer
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.param.shared import HasFeaturesCol, HasLabelCol, HasOutputCol
from pyspark.ml.util import DefaultParamsReadable, DefaultParamsWritable
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.dataset import Dataset
from ..plans.layout import from_vectors
from .greedy import select


class _SelectorParams(HasFeaturesCol, HasLabelCol, HasOutputCol):
    k = Param(Params._dummy(), "k", "number of features to keep", TypeConverters.toInt)
    criterion = Param(Params._dummy(), "criterion", "selection criterion", TypeConverters.toString)
    beta = Param(Params._dummy(), "beta", "weight of redundancy", TypeConverters.toFloat)
    gamma = Param(Params._dummy(), "gamma", "weight of conditional redundancy", TypeConverters.toFloat)
    strategy = Param(Params._dummy(), "strategy", "counting strategy, or sparse", TypeConverters.toString)


class InfoSelector(Estimator, _SelectorParams, DefaultParamsReadable, DefaultParamsWritable):
    """Chooses k entries of a vector column whose values are small whole codes."""

    @keyword_only
    def __init__(self, *, k=10, criterion="mrmr", beta=None, gamma=None, strategy="auto", featuresCol="features", labelCol="label", outputCol="selected"):
        super().__init__()
        self._setDefault(k=10, criterion="mrmr", strategy="auto", featuresCol="features", labelCol="label", outputCol="selected")
        self._set(**{n: v for n, v in self._input_kwargs.items() if v is not None})

    def _fit(self, dataset: DataFrame) -> InfoSelectorModel:
        vector, label = self.getOrDefault("featuresCol"), self.getOrDefault("labelCol")
        weights = {n: self.getOrDefault(n) if self.isDefined(n) else None for n in ("beta", "gamma")}
        if self.getOrDefault("strategy") == "sparse":
            ds = from_vectors(dataset.withColumn("row_id", F.monotonically_increasing_id()), vector, label)
            how = "auto"
        else:
            from pyspark.ml.functions import vector_to_array

            size = dataset.select(F.size(vector_to_array(vector))).first()[0]
            names = [f"f{i}" for i in range(size)]
            rows = dataset.select(F.col(label).cast("int").alias("y"), vector_to_array(vector).alias("a"))
            ds = Dataset(rows.select("y", *[F.col("a")[i].cast("int").alias(n) for i, n in enumerate(names)]), names)
            how = self.getOrDefault("strategy")
        chosen = select(ds, self.getOrDefault("k"), self.getOrDefault("criterion"), strategy=how, **weights)
        indices = [s["feature"] for s in chosen.steps]
        model = InfoSelectorModel(indices=indices, scores=[s["score"] for s in chosen.steps], featuresCol=vector, outputCol=self.getOrDefault("outputCol"))
        return model


class InfoSelectorModel(Model, HasFeaturesCol, HasOutputCol, DefaultParamsReadable, DefaultParamsWritable):
    indices = Param(Params._dummy(), "indices", "chosen entries, best first", TypeConverters.toListInt)
    scores = Param(Params._dummy(), "scores", "their scores", TypeConverters.toListFloat)

    @keyword_only
    def __init__(self, *, indices=None, scores=None, featuresCol="features", outputCol="selected"):
        super().__init__()
        self._set(**{n: v for n, v in self._input_kwargs.items() if v is not None})

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return VectorSlicer(inputCol=self.getOrDefault("featuresCol"), outputCol=self.getOrDefault("outputCol"), indices=self.getOrDefault("indices")).transform(dataset)
