"""Pipeline stage of the ML library around the clustering call."""

from __future__ import annotations

from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .api import cluster
from .functions.metrics import Euclidean, Metric
from .operators.assign import assign
from .schema import ClusterSpec
from .sources.tables import load_model, save_model


class _Common(Params):
    k = Param(Params._dummy(), "k", "number of centers", TypeConverters.toInt)
    eps = Param(Params._dummy(), "eps", "coreset precision", TypeConverters.toFloat)
    objective = Param(Params._dummy(), "objective", "median or means", TypeConverters.toString)
    featuresCol = Param(Params._dummy(), "featuresCol", "array<double> column", TypeConverters.toString)
    idCol = Param(Params._dummy(), "idCol", "unique long column", TypeConverters.toString)
    predictionCol = Param(Params._dummy(), "predictionCol", "center id column", TypeConverters.toString)

    def _points(self, df: DataFrame, *keep: str) -> DataFrame:
        return df.select(F.col(self.getOrDefault("idCol")).alias("id"), F.col(self.getOrDefault("featuresCol")).alias("pt"), *keep)


class CoresetClusteringModel(Model, _Common):
    def __init__(self, centers: DataFrame | None = None, metric: Metric | None = None):
        super().__init__()
        self.centers, self.metric = centers, metric or Euclidean()

    def _transform(self, df: DataFrame) -> DataFrame:
        """Every row of `df` with its center: rows travel as they are, so equal ids neither meet nor multiply."""
        rows = self._points(df.withColumn("_row", F.struct(*df.columns)), "_row")
        return assign(rows, self.centers, self.metric, keep=("_row",)).select("_row.*", F.col("center_id").alias(self.getOrDefault("predictionCol")))

    def save(self, path: str) -> None:
        save_model(self.centers, {p.name: self.getOrDefault(p) for p in self.params}, path)

    @classmethod
    def load(cls, spark, path: str) -> CoresetClusteringModel:
        centers, params = load_model(spark, path)
        model = cls(centers)
        for name, value in params.items():
            model._set(**{name: value})
        return model


class CoresetClustering(Estimator, _Common):
    """CoresetClustering(k=10).fit(df).transform(df)"""

    def __init__(self, k: int = 10, eps: float = 0.5, objective: str = "median", featuresCol: str = "features", idCol: str = "id", predictionCol: str = "prediction", metric: Metric | None = None):
        super().__init__()
        self.metric = metric or Euclidean()
        self._set(k=k, eps=eps, objective=objective, featuresCol=featuresCol, idCol=idCol, predictionCol=predictionCol)

    def _fit(self, df: DataFrame) -> CoresetClusteringModel:
        got = {p.name: self.getOrDefault(p) for p in self.params}
        result = cluster(self._points(df), ClusterSpec(got["k"], got["objective"], got["eps"], seeder="dsample"), self.metric, rounds=1)
        return CoresetClusteringModel(result.centers, self.metric)._set(**got)
