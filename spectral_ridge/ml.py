"""Estimator and model, so that sketched ridge works in pipelines and cross-validation."""

from __future__ import annotations

from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.param.shared import HasFeaturesCol, HasLabelCol, HasPredictionCol
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators.design import RidgeSpec, feature_column
from .operators.fit import fit_sketch
from .operators.predict import dot
from .operators.solve import solve


class _SketchParams(HasFeaturesCol, HasLabelCol, HasPredictionCol):
    method = Param(Params._dummy(), "method", "sketch method id", TypeConverters.toString)
    ell = Param(Params._dummy(), "ell", "sketch rows", TypeConverters.toInt)
    gamma = Param(Params._dummy(), "gamma", "penalty", TypeConverters.toFloat)


class SketchRidgeRegression(Estimator, _SketchParams):
    """Ridge regression from a sketch; ``featuresCol`` is an array or a vector column."""

    @keyword_only
    def __init__(self, *, featuresCol: str = "features", labelCol: str = "label", predictionCol: str = "prediction", method: str = "robust_fd_ridge", ell: int = 64, gamma: float = 1.0):
        super().__init__()
        self._setDefault(featuresCol="features", labelCol="label", predictionCol="prediction", method="robust_fd_ridge", ell=64, gamma=1.0)
        self._set(**self._input_kwargs)

    def _fit(self, dataset: DataFrame) -> SketchRidgeModel:
        spec = RidgeSpec(self.getFeaturesCol(), self.getLabelCol())
        sketch = fit_sketch(dataset, spec, self.getOrDefault(self.method), self.getOrDefault(self.ell))
        row = solve(sketch, self.getOrDefault(self.gamma)).first()
        return self._copyValues(SketchRidgeModel(list(row["coefficients"]), row["certificate"]))


class SketchRidgeModel(Model, _SketchParams):
    def __init__(self, coefficients: list[float] | None = None, certificate: float | None = None):
        super().__init__()
        self.coefficients, self.certificate = coefficients or [], certificate

    def _transform(self, dataset: DataFrame) -> DataFrame:
        features = feature_column(dataset, RidgeSpec(self.getFeaturesCol(), self.getLabelCol()))
        return dataset.withColumn(self.getPredictionCol(), dot(features, F.array(*[F.lit(float(c)) for c in self.coefficients])))
