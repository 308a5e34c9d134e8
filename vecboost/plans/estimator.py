"""Estimator and model for pipelines, and SQL functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark import keyword_only
from pyspark.ml import Estimator
from pyspark.ml import Model as MlModel
from pyspark.ml.param.shared import HasFeaturesCol, HasLabelCol, HasPredictionCol, HasProbabilityCol
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import BoostConfig
from ..functions.losses import loss_of
from ..operators.binning import array_edges, binned
from .boost import fit
from .model import Model


class _Cols(HasFeaturesCol, HasLabelCol, HasPredictionCol, HasProbabilityCol):
    pass


class VectorBoost(Estimator, _Cols):
    """Fits on an array<double> features column; labels 0..outputs-1 (or arrays for real and multi-label losses)."""

    @keyword_only
    def __init__(self, *, config: BoostConfig | None = None, featuresCol="x", labelCol="y", predictionCol="prediction", probabilityCol="probability"):
        super().__init__()
        self.config = config or BoostConfig()
        self._set(featuresCol=featuresCol, labelCol=labelCol, predictionCol=predictionCol, probabilityCol=probabilityCol)

    def _fit(self, df: DataFrame) -> VectorBoostModel:
        x = self.getFeaturesCol()
        width = df.select(F.max(F.size(x))).first()[0] or 0
        cuts = array_edges(df, x, width, self.config.bins)
        base = binned(df.withColumn("y", F.col(self.getLabelCol())), x, cuts, ["y"]).persist()
        try:
            return self._copyValues(VectorBoostModel(fit(base, self.config, cuts)))
        finally:
            base.unpersist()


class VectorBoostModel(MlModel, _Cols):
    def __init__(self, booster: Model):
        super().__init__()
        self.booster = booster

    def _transform(self, df: DataFrame) -> DataFrame:
        predict = probability_udf(self.booster)
        p = predict(F.col(self.getFeaturesCol()).cast("array<double>"))
        best = F.array_position(F.col(self.getProbabilityCol()), F.array_max(self.getProbabilityCol())) - 1
        if self.booster.config.loss == "logistic":
            best = (F.element_at(self.getProbabilityCol(), 1) >= 0.5).cast("int")
        return df.withColumn(self.getProbabilityCol(), p).withColumn(self.getPredictionCol(), best.cast("int"))

    def save_to(self, spark: SparkSession, path: str) -> None:
        self.booster.save(spark, path)

    @staticmethod
    def load_from(spark: SparkSession, path: str, stamp: int) -> VectorBoostModel:
        return VectorBoostModel(Model.load(spark, path, stamp))


def probability_udf(model: Model):
    """A vectorised function of an array of raw features: what the loss says of the scores."""
    folded, loss = model.fold(), loss_of(model.config.loss, model.config.outputs, model.config.label_encoding)
    cuts = [np.asarray(e) for e in model.edges]

    @F.pandas_udf("array<double>")
    def run(x: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype=object)
        m = np.stack(x.to_numpy()).astype(float)
        b = np.stack([np.where(np.isnan(m[:, f]), 0, np.searchsorted(cuts[f], m[:, f]) + 1) for f in range(len(cuts))], axis=1).astype(np.uint8)
        return pd.Series(list(loss.predict(folded.scores(b))))

    return run


def register(spark: SparkSession, model: Model, name: str = "boost_score") -> None:
    """SELECT boost_score(array(...)) and SELECT * FROM boost_nodes()."""
    from pyspark.sql.functions import udtf

    spark.udf.register(name, probability_udf(model))
    rows = [(k, j, cond, [float(v) for v in w]) for k, j, cond, w in model.rules()]

    @udtf(returnType="tree int, node int, rule string, weights array<double>")
    class Nodes:
        def eval(self):
            yield from rows

    spark.udtf.register("boost_nodes", Nodes)
