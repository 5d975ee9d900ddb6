"""``pyspark.ml`` estimator and model around the two-phase fit, on a vector or array column."""

from __future__ import annotations

import numpy as np
from pyspark.ml import Estimator, Model
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.param.shared import HasFeaturesCol, HasLabelCol, HasPredictionCol
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from featgreedy.operators import layout
from featgreedy.operators.model import SRGConfig, fit


class _Shared(HasFeaturesCol, HasLabelCol, HasPredictionCol):
    blockWidth = Param(Params._dummy(), "blockWidth", "columns per block", TypeConverters.toInt)
    radius = Param(Params._dummy(), "radius", "nuclear radius", TypeConverters.toFloat)
    threshold = Param(Params._dummy(), "threshold", "plateau threshold; not positive: the default", TypeConverters.toFloat)
    cap = Param(Params._dummy(), "cap", "most steps of phase one", TypeConverters.toInt)

    def __init__(self):
        super().__init__()
        self._setDefault(featuresCol="features", labelCol="label", predictionCol="prediction", blockWidth=1, radius=500.0, threshold=0.0, cap=200)

    def _values(self, column: str, df: DataFrame):
        kind = df.schema[column].dataType.simpleString()
        return vector_to_array(F.col(column)) if kind == "vector" else F.col(column).cast("array<double>") if kind.startswith("array") else F.array(F.col(column).cast("double"))


class TwoPhaseRegression(Estimator, _Shared):
    """Scalar or vector label; features are cut into blocks of ``blockWidth`` columns."""

    def __init__(self, **params):
        super().__init__()
        self._set(**params)

    def _fit(self, df: DataFrame) -> TwoPhaseRegressionModel:
        rows = df.select(self._values(self.getFeaturesCol(), df).alias("f"), self._values(self.getLabelCol(), df).alias("y")).withColumn("t", F.monotonically_increasing_id())
        rows = layout.numbered(rows, "t")
        width = len(rows.select("f").first()["f"])
        w = self.getOrDefault(self.blockWidth)
        widths = [min(w, width - i) for i in range(0, width, w)]
        t = self.getOrDefault(self.threshold)
        config = SRGConfig(radius=self.getOrDefault(self.radius), threshold=t if t > 0 else "default", cap=self.getOrDefault(self.cap), center=True)
        m = fit(layout.to_blocks(rows, widths), layout.to_segments(rows), config)
        beta = np.zeros((width, len(m.intercept)))
        for j, b in m.coef.items():
            a = layout.manifest(widths)[j][0]
            beta[a : a + len(b)] = b
        return self._copyValues(TwoPhaseRegressionModel(beta, m.intercept, m))


class TwoPhaseRegressionModel(Model, _Shared):
    def __init__(self, beta: np.ndarray, intercept: np.ndarray, fitted=None):
        super().__init__()
        self.beta, self.intercept, self.fitted = beta, intercept, fitted

    def _transform(self, df: DataFrame) -> DataFrame:
        """Dot products with the nonzero coefficients, as plain expressions."""
        f = self._values(self.getFeaturesCol(), df)
        outs = []
        for k in range(self.beta.shape[1]):
            s = F.lit(float(self.intercept[k]))
            for i in np.flatnonzero(self.beta[:, k]):
                s = s + F.get(f, F.lit(int(i))) * F.lit(float(self.beta[i, k]))
            outs.append(s)
        return df.withColumn(self.getPredictionCol(), outs[0] if len(outs) == 1 else array_to_vector(F.array(*outs)))
