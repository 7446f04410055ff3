"""KCenter as an estimator and its model as a transformer."""

from __future__ import annotations

from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.operators.assign import assign, covering_radius
from farpoint.operators.blocked import blocked_farthest_first
from farpoint.operators.farthest_first import farthest_first
from farpoint.operators.sampling import pivot_sampling_kcenter


class _KCenterParams(Params):
    k = Param(Params._dummy(), "k", "number of centers", TypeConverters.toInt)
    algorithm = Param(Params._dummy(), "algorithm", "farthest_first, distributed, blocked or pivot_sampling", TypeConverters.toString)
    blocks = Param(Params._dummy(), "blocks", "blocks of the blocked scheme", TypeConverters.toInt)
    phi = Param(Params._dummy(), "phi", "pivot factor", TypeConverters.toFloat)
    measure = Param(Params._dummy(), "measure", "metric", TypeConverters.toString)
    idCol = Param(Params._dummy(), "idCol", "id column", TypeConverters.toString)
    featuresCol = Param(Params._dummy(), "featuresCol", "column of coordinates (array of doubles)", TypeConverters.toString)
    predictionCol = Param(Params._dummy(), "predictionCol", "column for the center's id", TypeConverters.toString)

    def _points(self, df: DataFrame) -> DataFrame:
        return df.select(F.col(self.getOrDefault("idCol")).cast("long").alias("id"), F.col(self.getOrDefault("featuresCol")).cast("array<double>").alias("coords"))


class KCenter(Estimator, _KCenterParams):
    @keyword_only
    def __init__(self, *, k=2, algorithm="blocked", blocks=8, phi=8.0, measure="euclidean", idCol="id", featuresCol="coords", predictionCol="center_id"):
        super().__init__()
        self._setDefault(k=2, algorithm="blocked", blocks=8, phi=8.0, measure="euclidean", idCol="id", featuresCol="coords", predictionCol="center_id")
        self._set(**self._input_kwargs)

    def _fit(self, dataset: DataFrame) -> KCenterModel:
        p, k, m = self._points(dataset), self.getOrDefault("k"), self.getOrDefault("measure")
        which = self.getOrDefault("algorithm")
        if which == "blocked":
            centers = blocked_farthest_first(p, k, self.getOrDefault("blocks"), measure=m).centers
        elif which == "pivot_sampling":
            centers = pivot_sampling_kcenter(p, k, measure=m, phi=self.getOrDefault("phi"))[0]
        elif which in ("farthest_first", "distributed"):
            centers = farthest_first(p, k, m, physical="distributed" if which == "distributed" else "single_task")
        else:
            raise ValueError(which)
        kept = dataset.sparkSession.createDataFrame(centers.collect(), centers.schema)  # k rows
        return self._copyValues(KCenterModel(kept))


class KCenterModel(Model, _KCenterParams):
    def __init__(self, centers: DataFrame | None = None):
        super().__init__()
        self.centers = centers

    def _transform(self, dataset: DataFrame) -> DataFrame:
        i, out = self.getOrDefault("idCol"), self.getOrDefault("predictionCol")
        served = assign(self._points(dataset), self.centers, self.getOrDefault("measure")).select(F.col("id").alias("__id"), F.col("center_id").alias(out))
        return dataset.join(served, dataset[i] == F.col("__id")).drop("__id")

    def radius(self, dataset: DataFrame) -> float:
        return covering_radius(self._points(dataset), self.centers, self.getOrDefault("measure")).first().radius
