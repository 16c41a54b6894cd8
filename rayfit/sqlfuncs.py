"""The functions of the learners for SQL users: temporary SQL functions, which the optimiser inlines, and a table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from .ship import ship

FUNCTIONS = {
    "softplus_neg(z DOUBLE) RETURNS DOUBLE": "log1p(exp(-abs(z))) + greatest(-z, 0D)",
    "sigmoid(z DOUBLE) RETURNS DOUBLE": "1D / (1D + exp(-z))",
    "horner(c ARRAY<DOUBLE>, t DOUBLE) RETURNS DOUBLE": "aggregate(reverse(c), 0D, (a, x) -> a * t + x)",
    "horner_d1(c ARRAY<DOUBLE>, t DOUBLE) RETURNS DOUBLE": "aggregate(reverse(slice(transform(c, (x, i) -> x * i), 2, 1000)), 0D, (a, x) -> a * t + x)",
    "horner_d2(c ARRAY<DOUBLE>, t DOUBLE) RETURNS DOUBLE": "aggregate(reverse(slice(transform(c, (x, i) -> x * i * (i - 1)), 3, 1000)), 0D, (a, x) -> a * t + x)",
    "dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "sparse_dot(idx ARRAY<INT>, val ARRAY<DOUBLE>, w ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(idx, val, (i, x) -> x * w[i]), 0D, (s, x) -> s + x)",
    "ls_terms(z DOUBLE, q DOUBLE, y DOUBLE) RETURNS ARRAY<DOUBLE>": "array((z - y) * (z - y) / 2, (z - y) * q, q * q / 2)",
    "mf_terms(a0 DOUBLE, a1 DOUBLE, a2 DOUBLE) RETURNS ARRAY<DOUBLE>": "array(a0 * a0 / 2, a0 * a1, a0 * a2 + a1 * a1 / 2, a1 * a2, a2 * a2 / 2)",
    "logit_terms(z DOUBLE, q DOUBLE, y DOUBLE) RETURNS ARRAY<DOUBLE>": "transform(array(1D / (1D + exp(-z))), s -> array(log1p(exp(-abs(z))) + greatest(-z, 0D) + if(y = 0, z, 0D), q * (s - if(y = 0, 0D, 1D)), q * q * s * (1 - s) / 2, pow(q, 3) * s * (1 - s) * (1 - 2 * s) / 6, pow(q, 4) * s * (1 - s) * (1 - 6 * s * (1 - s)) / 24, pow(q, 5) * s * (1 - s) * (1 - 2 * s) * (1 - 12 * s * (1 - s)) / 120))[0]",
    "wolfe_ok(phi DOUBLE, phi0 DOUBLE, dphi DOUBLE, dphi0 DOUBLE, a DOUBLE) RETURNS BOOLEAN": "phi <= phi0 + 1e-4D * a * dphi0 AND abs(dphi) <= 0.9D * abs(dphi0)",
}


@udtf(returnType="alpha double, coeffs array<double>, t double, value double, estimate double, status string")
class LineSearchStep:
    """One row for the minimum of a model given by its coefficients at alpha."""

    def eval(self, coeffs, alpha: float):
        from rayfit.taylor import TaylorModel

        model = TaylorModel(coeffs, alpha)
        best = model.argmin()
        yield alpha, list(coeffs), best.t, model.value(best.t), model.error_estimate(best.t), best.status


@udtf(returnType="i int, w double")
class FitLogistic:
    """Weights of a logistic model of a small table with columns x (array) and y, constant last: SELECT * FROM
    fit_logistic(TABLE(t) WITH SINGLE PARTITION, lam => 1e-3). The table is held by one worker; large ones go to RayRegression."""

    def __init__(self):
        self.x, self.y, self.lam = [], [], 0.0

    def eval(self, row, lam: float = 0.0):
        self.x.append([*row["x"], 1.0])
        self.y.append(float(row["y"]))
        self.lam = float(lam)

    def terminate(self):
        import numpy as np

        from rayfit import losses, optim

        if self.x:
            fit = optim.minimize(optim.ArrayProblem(np.array(self.x, float), np.array(self.y), losses.Logistic(), self.lam), max_iter=60)
            yield from ((i, float(v)) for i, v in enumerate(fit.w))


def register(spark: SparkSession) -> list[str]:
    """Defines all of them in the session; their names."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    ship(spark)
    spark.udtf.register("line_search_step", LineSearchStep)
    spark.udtf.register("fit_logistic", FitLogistic)
    return [h.split("(")[0] for h in FUNCTIONS] + ["line_search_step", "fit_logistic"]


def horner_columns(coeffs, t):
    """Value and first two derivatives of a polynomial held as an array column."""
    scaled = lambda k: F.slice(F.transform(coeffs, lambda x, i: x * (i if k == 1 else i * (i - 1))), k + 1, 1000)
    run = lambda c: F.aggregate(F.reverse(c), F.lit(0.0), lambda a, x: a * t + x)
    return run(coeffs), run(scaled(1)), run(scaled(2))
