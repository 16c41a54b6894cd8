"""Use of fitted models: scoring, folds, grids and many models in one pass, and the library's estimator interface."""

from __future__ import annotations

import numpy as np
from pyspark.ml import Estimator, Model
from pyspark.ml.functions import vector_to_array
from pyspark.ml.param.shared import HasFeaturesCol, HasLabelCol, HasPredictionCol, Param, Params, TypeConverters
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .instances import Instances, Problem
from .losses import LeastSquares, Logistic, sigmoid
from .optim import minimize


def score(data: Instances, w: np.ndarray, threshold: float = 0.5) -> DataFrame:
    """(y, z, prob, predicted)."""
    out = Problem(data, Logistic()).margins(w, np.zeros_like(w)).select("y", "z")
    return out.withColumn("prob", sigmoid(F.col("z"))).withColumn("predicted", (F.col("prob") >= threshold).cast("int"))


def folds(df: DataFrame, key: str, k: int, seed: int = 0) -> DataFrame:
    return df.withColumn("fold", F.pmod(F.xxhash64(key, F.lit(seed)), F.lit(k)).cast("int"))


def path(data: Instances, lams: list[float], **options) -> list[tuple[float, np.ndarray, float]]:
    """Fits from the strongest penalty to the weakest, each from the one before."""
    w, out = None, []
    for lam in sorted(lams, reverse=True):
        fit = minimize(Problem(data, Logistic(), lam), w0=w, **options)
        w = fit.w
        out.append((lam, w, fit.trace[-1]["loss"]))
    return out


def batched_coefficients(data: Instances, rays: list[tuple], degree: int) -> np.ndarray:
    """Coefficients of many (label column, w, p) in one pass over narrow rows: rays x (degree + 1)."""
    loss, p0 = Logistic(), Problem(data, Logistic())
    cols = []
    for y, w, p in rays:
        cols += loss.taylor_terms(p0._columns(w), p0._columns(p), y, degree)
    row = data.df.agg(F.count("*"), *(F.sum(c) for c in cols)).first()
    return np.array(row[1:], float).reshape(len(rays), degree + 1) / row[0]


def group_coefficients(df: DataFrame, group: str, loss, degree: int) -> DataFrame:
    """Mean coefficients of (group, y, z, q) rows for every group in one pass."""
    terms = loss.taylor_terms(F.col("z"), F.col("q"), F.col("y"), degree)
    return df.groupBy(group).agg(F.count("*").alias("n"), *(F.avg(t).alias(f"c{k}") for k, t in enumerate(terms)))


class _Shared(HasFeaturesCol, HasLabelCol, HasPredictionCol):
    regParam = Param(Params._dummy(), "regParam", "L2 weight", TypeConverters.toFloat)
    degree = Param(Params._dummy(), "degree", "degree of the Taylor model", TypeConverters.toInt)
    tol = Param(Params._dummy(), "tol", "relative error at which a model is trusted", TypeConverters.toFloat)
    maxIter = Param(Params._dummy(), "maxIter", "outer iterations", TypeConverters.toInt)
    method = Param(Params._dummy(), "method", "gd, ncg or lbfgs", TypeConverters.toString)
    search = Param(Params._dummy(), "search", "taylor or wolfe", TypeConverters.toString)
    family = Param(Params._dummy(), "family", "logistic or least_squares", TypeConverters.toString)

    def _instances(self, df: DataFrame, label=True) -> DataFrame:
        kind = dict(df.dtypes)[self.getFeaturesCol()]
        x = F.col(self.getFeaturesCol())
        x = (vector_to_array(x) if kind == "vector" else x.cast("array<double>"))
        return df.withColumn("_x", F.array_append(x, F.lit(1.0)))


class RayRegression(Estimator, _Shared):
    """Logistic regression or least squares on a vector or array column, with the constant feature added."""

    def __init__(self, **params):
        super().__init__()
        self._setDefault(regParam=1e-6, degree=5, tol=1e-4, maxIter=50, method="lbfgs", search="taylor", family="logistic")
        self._set(**params)

    def _fit(self, dataset: DataFrame) -> RayModel:
        get = lambda n: self.getOrDefault(getattr(self, n))
        df = self._instances(dataset).select(F.col("_x").alias("x"), F.col(self.getLabelCol()).cast("double").alias("y"))
        data = Instances(df, len(df.select("x").first()[0]), kind="dense").persist()
        loss = Logistic() if get("family") == "logistic" else LeastSquares()
        fit = minimize(Problem(data, loss, get("regParam")), get("method"), get("search"), max_iter=get("maxIter"), degree=get("degree"), theta=get("tol"))
        data.unpersist()
        out = RayModel(fit.w, fit)
        return self._copyValues(out)


class RayModel(Model, _Shared):
    def __init__(self, w: np.ndarray, fit=None):
        super().__init__()
        self._setDefault(family="logistic")
        self.w, self.fit_ = w, fit

    def _transform(self, dataset: DataFrame) -> DataFrame:
        w = F.array(*(F.lit(float(x)) for x in self.w))
        z = F.aggregate(F.zip_with("_x", w, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
        out = self._instances(dataset).withColumn("margin", z).drop("_x")
        if self.getOrDefault(self.family) != "logistic":
            return out.withColumn(self.getPredictionCol(), F.col("margin"))
        return out.withColumn("probability", sigmoid(F.col("margin"))).withColumn(self.getPredictionCol(), (F.col("probability") >= 0.5).cast("double"))


def cross_validate(df: DataFrame, key: str, lams: list[float], k: int = 3, m: int | None = None, kind: str = "dense", **options) -> DataFrame:
    """(lam, fold, n, log_loss, accuracy) of models fitted without the fold, on it; penalties from the strongest, each warm."""
    spark, held = df.sparkSession, folds(df, key, k).persist()
    m = m or len(held.select("x").first()[0])
    rows = []
    for fold in range(k):
        rest, own = (Instances(held.filter(c), m, kind=kind) for c in (F.col("fold") != fold, F.col("fold") == fold))
        for lam, w, _ in path(rest, lams, **options):
            p = F.least(F.greatest("prob", F.lit(1e-15)), F.lit(1 - 1e-15))
            r = score(own, w).agg(F.count("*"), F.avg(F.when(F.col("y") != 0, -F.log(p)).otherwise(-F.log(1 - p))), F.avg((F.col("predicted") == (F.col("y") != 0).cast("int")).cast("double"))).first()
            rows.append((float(lam), fold, r[0], r[1], r[2]))
    held.unpersist()
    return spark.createDataFrame(rows, "lam double, fold int, n long, log_loss double, accuracy double")
