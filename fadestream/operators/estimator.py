"""The fading clusterer as a pipeline stage: fit on rows with a vector column and a batch number, transform adds the cluster."""

from __future__ import annotations

import numpy as np
from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.functions import vector_to_array
from pyspark.ml.linalg import VectorUDT
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.util import DefaultParamsReadable, DefaultParamsWritable
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadestream.operators.distance import assign
from fadestream.operators.engine import FadingClusterer


class _Shared(Params):
    featuresCol = Param(Params._dummy(), "featuresCol", "vector or array column", TypeConverters.toString)
    batchCol = Param(Params._dummy(), "batchCol", "batch number", TypeConverters.toString)
    predictionCol = Param(Params._dummy(), "predictionCol", "cluster of a row", TypeConverters.toString)

    def _points(self, df: DataFrame) -> DataFrame:
        col = self.getOrDefault(self.featuresCol)
        x = vector_to_array(F.col(col)) if isinstance(df.schema[col].dataType, VectorUDT) else F.col(col).cast("array<double>")
        return df.withColumn("x", x)


class FadingKMeans(Estimator, _Shared, DefaultParamsReadable, DefaultParamsWritable):
    k = Param(Params._dummy(), "k", "clusters", TypeConverters.toInt)
    rho = Param(Params._dummy(), "rho", "forget parameter", TypeConverters.toFloat)
    tMax = Param(Params._dummy(), "tMax", "batches retained", TypeConverters.toInt)
    start = Param(Params._dummy(), "start", "start policy", TypeConverters.toString)
    seed = Param(Params._dummy(), "seed", "seed", TypeConverters.toInt)

    @keyword_only
    def __init__(self, *, k: int = 5, rho: float = 0.457, tMax: int = 12, start: str = "pair", seed: int = 0, featuresCol: str = "features", batchCol: str = "batch_seq", predictionCol: str = "prediction") -> None:  # noqa: N803
        super().__init__()
        self._setDefault(k=5, rho=0.457, tMax=12, start="pair", seed=0, featuresCol="features", batchCol="batch_seq", predictionCol="prediction")
        self._set(**self._input_kwargs)

    def _fit(self, dataset: DataFrame) -> FadingKMeansModel:
        points = self._points(dataset).withColumn("__b", F.col(self.getOrDefault(self.batchCol)))
        t_max = self.getOrDefault(self.tMax)
        seqs = [r[0] for r in points.select("__b").distinct().orderBy("__b").collect()]
        f = FadingClusterer(self.getOrDefault(self.k), self.getOrDefault(self.rho), t_max, self.getOrDefault(self.start), seed=self.getOrDefault(self.seed))
        for s in seqs:
            f.step(points.where(F.col("__b") == s), int(s))
        return FadingKMeansModel().with_centroids(f.centroids)._set(**{p: self.getOrDefault(p) for p in ("featuresCol", "batchCol", "predictionCol")})


class FadingKMeansModel(Model, _Shared, DefaultParamsReadable, DefaultParamsWritable):
    flat = Param(Params._dummy(), "flat", "centroids, row by row", TypeConverters.toListFloat)
    size = Param(Params._dummy(), "size", "number of centroids", TypeConverters.toInt)

    def __init__(self) -> None:
        super().__init__()
        self._setDefault(featuresCol="features", batchCol="batch_seq", predictionCol="prediction")

    def with_centroids(self, c: np.ndarray) -> FadingKMeansModel:
        return self._set(flat=[float(v) for v in c.ravel()], size=len(c))

    @property
    def centroids(self) -> np.ndarray:
        return np.array(self.getOrDefault(self.flat)).reshape(self.getOrDefault(self.size), -1)

    def _transform(self, dataset: DataFrame) -> DataFrame:
        near = assign(self._points(dataset), self.centroids, "expr")
        return near.withColumnRenamed("k", self.getOrDefault(self.predictionCol)).drop("x", "d2")
