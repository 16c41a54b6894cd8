"""Low-rank factorization of ratings (i, j, value): half the mean squared residual of u_i . v_j, plus a penalty.

Factors are tables (i, vec, dir) and (j, vec, dir). Along a ray the residual is quadratic in the step, so a model of degree
four is exact and one pass solves the line search."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tables import forget, staged
from .taylor import Step, TaylorModel


def _dot(a, b):
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def joined(ratings: DataFrame, u: DataFrame, v: DataFrame) -> DataFrame:
    """Ratings with a0 + a1 t + a2 t^2, the residual along the ray, and both factors."""
    both = ratings.join(u.select("i", F.col("vec").alias("u"), F.col("dir").alias("p")), "i").join(v.select("j", F.col("vec").alias("v"), F.col("dir").alias("q")), "j")
    return both.select("i", "j", "u", "v", (_dot("u", "v") - F.col("value")).alias("a0"), (_dot("u", "q") + _dot("p", "v")).alias("a1"), _dot("p", "q").alias("a2"))


def terms(a0, a1, a2):
    """The five coefficients in t of half the square of the residual."""
    return [a0 * a0 / 2, a0 * a1, a0 * a2 + a1 * a1 / 2, a1 * a2, a2 * a2 / 2]


def _penalty(u: DataFrame, v: DataFrame, lam: float) -> np.ndarray:
    out = np.zeros(5)
    for t in (u, v):
        row = t.agg(F.sum(_dot("vec", "vec")), F.sum(_dot("vec", "dir")), F.sum(_dot("dir", "dir"))).first()
        out[:3] += np.array([lam / 2 * (row[0] or 0), lam * (row[1] or 0), lam / 2 * (row[2] or 0)])
    return out


def expand(ratings: DataFrame, u: DataFrame, v: DataFrame, lam: float = 0.0) -> TaylorModel:
    held = joined(ratings, u, v)
    row = held.agg(F.count("*"), *(F.sum(t) for t in terms(F.col("a0"), F.col("a1"), F.col("a2")))).first()
    return TaylorModel(np.array([x or 0.0 for x in row[1:]]) / max(1, row[0]) + _penalty(u, v, lam), 0.0, exact=True)


def gradient(ratings: DataFrame, u: DataFrame, v: DataFrame, lam: float = 0.0, n: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(i, g) and (j, g): two grouped sums of residual times partner; nothing on the driver but the count, if it isn't given."""
    n = n or max(1, ratings.count())
    held = joined(ratings, u, v)
    rank = len((u.select("vec").first() or [[]])[0])

    def side(key, partner, own):
        sums = held.groupBy(key).agg(F.array(*(F.sum(F.col("a0") * F.col(partner)[k]) for k in range(rank))).alias("s"))
        zero = F.array(*[F.lit(0.0)] * rank)
        return own.join(sums, key, "left").select(key, F.zip_with(F.coalesce("s", zero), "vec", lambda s, w: s / n + lam * w).alias("g"))

    return side("i", "v", u), side("j", "u", v)


def exact_step(model: TaylorModel) -> float:
    """The step ahead at which the quartic is least."""
    best = model.argmin("roots")
    return best.t if math.isfinite(best.t) and best.t > 0 else 0.0


def started(ratings: DataFrame, rank: int) -> tuple[DataFrame, DataFrame]:
    """Factors from a formula of key and component, the same in every engine."""
    def side(key, shift):
        vec = F.array(*(F.cos(F.col(key).cast("double") * (k + 1) + shift + k) / rank for k in range(rank)))
        return ratings.select(key).distinct().select(key, vec.alias("vec"), F.array(*[F.lit(0.0)] * rank).alias("dir"))

    return side("i", 0.0), side("j", 0.5)


def _aimed(factors: DataFrame, g: DataFrame, key: str, beta: float) -> DataFrame:
    return factors.join(g, key).select(key, "vec", F.zip_with("g", "dir", lambda x, d: -x + F.lit(float(beta)) * d).alias("dir"))


def _moved(factors: DataFrame, t: float) -> DataFrame:
    return factors.withColumn("vec", F.zip_with("vec", "dir", lambda w, d: w + F.lit(float(t)) * d))


def fit(ratings: DataFrame, rank: int = 4, lam: float = 1e-3, max_iter: int = 10) -> tuple[DataFrame, DataFrame, list[dict]]:
    """Polak-Ribiere conjugate gradients with exact steps.

    Factors, directions and gradients are written to the shared folder in each iteration and read again, so that the plan
    of an iteration is as long as that of the first one; those of earlier iterations are deleted. Without ratings the trace is empty."""
    ratings = staged(ratings)
    n = ratings.count()
    u, v = (staged(t) for t in started(ratings, rank))
    trace, gu0, gv0, gg0 = [], None, None, 0.0
    for k in range(max_iter if n else 0):
        gu, gv = (staged(g) for g in gradient(ratings, u, v, lam, n))
        gg = sum(g.agg(F.sum(_dot("g", "g"))).first()[0] or 0.0 for g in (gu, gv))
        beta = 0.0
        if gu0 is not None:
            mixed = sum(a.join(b.withColumnRenamed("g", "h"), key).agg(F.sum(_dot("g", "h"))).first()[0] or 0.0 for a, b, key in ((gu, gu0, "i"), (gv, gv0, "j")))
            beta = max(0.0, (gg - mixed) / gg0) if abs(mixed) < 0.2 * gg else 0.0
            forget(gu0, gv0)
        aimed = staged(_aimed(u, gu, "i", beta)), staged(_aimed(v, gv, "j", beta))
        forget(u, v)
        u, v = aimed
        model = expand(ratings, u, v, lam)
        t = exact_step(model)
        trace.append({"k": k, "loss": model.c[0], "grad_norm": math.sqrt(gg), "alpha": t, "model_loss": model.value(t)})
        if t == 0.0:
            break
        moved = staged(_moved(u, t)), staged(_moved(v, t))
        forget(u, v)
        u, v = moved
        gu0, gv0, gg0 = gu, gv, gg
    return u, v, trace


def search(ratings: DataFrame, u: DataFrame, v: DataFrame, lam: float = 0.0) -> Step:
    model = expand(ratings, u, v, lam)
    t = exact_step(model)
    return Step(t, 1, [(0.0, model.c, t, 0.0, "roots")])
