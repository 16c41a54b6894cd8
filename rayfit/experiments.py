"""The experiments on whole fits: convergence traces, speedups, timings by method, cost by number of parameters, ablations.

Each takes the workload's own features, penalty and tolerance. Features are built and persisted once for all methods, and counted
before any clock starts."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import features as X
from . import measures
from . import workloads as W
from .instances import Problem, kept
from .losses import Logistic
from .optim import OPS, TRACE, minimize

#: Workloads with more parameters than rows, whose fits end where exp(-loss) no longer gains ACC_GAIN over five iterations.
LARGE, ACC_GAIN, MOST = ("w3", "w4", "w5"), 1e-3, 25


@contextmanager
def prepared(spark: SparkSession, sf_dir: str, name: str, **options):
    work = getattr(W, name)(spark, sf_dir, **options)
    work.data.persist().count()
    try:
        yield work
    finally:
        work.data.unpersist()


def fitted(work, name: str, method: str, search: str, max_iter: int = MOST, **options):
    own = {"theta": work.theta, "acc_gain": ACC_GAIN if name in LARGE else 0.0} | options
    return minimize(Problem(work.data, work.loss, work.lam), method, search, max_iter=max_iter, **own)


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def traces(spark: SparkSession, sf_dir: str, name: str, methods, max_iter: int = MOST) -> DataFrame:
    """Every iterate of every method with both searches, and its gap to the least loss that any of them met."""
    with prepared(spark, sf_dir, name) as work, ThreadPoolExecutor(2 if name in LARGE else 2 * len(methods)) as pool:
        # no clock counts here, so fits share the machine; vectors of two large ones fit into the driver
        runs = [(m, s, pool.submit(fitted, work, name, m, s, max_iter)) for m in methods for s in ("taylor", "wolfe")]
        out = [fit.result().trace_frame(spark, f"{name}_{m}_{s}", name) for m, s, fit in runs]
    return measures.gap(union(out)).drop("best", "seconds", "cum_seconds")


def speedup(spark: SparkSession, sf_dir: str, name: str, width: float = 0.02, max_iter: int = MOST) -> DataFrame:
    """Ratios of iterations and of seconds, Wolfe to Taylor, at equal exp(-loss), in windows of it; L-BFGS."""
    with prepared(spark, sf_dir, name) as work:
        own = {s: fitted(work, name, "lbfgs", s, max_iter).trace_frame(spark, s, name) for s in ("wolfe", "taylor")}
    return measures.windowed(measures.speedup(own["wolfe"], own["taylor"]), width).withColumn("acc", F.col("bin") * width).orderBy("acc")


def timing(spark: SparkSession, sf_dir: str, names, methods=("lbfgs", "ncg"), iterations: int = 6) -> DataFrame:
    """tau_tot, tau_fg, tau_ls with deviations and n_e, by workload, method and search, and what passes alone would take.

    Of a fit only the rows of its trace and passes stay, so that the vectors of one lie on the driver at a time; they are summed up
    together, in one plan."""
    runs, trace, ops = [], [], []
    for name in names:
        with prepared(spark, sf_dir, name) as work:
            for m in methods:
                for s in ("wolfe", "taylor"):
                    fit, run = fitted(work, name, m, s, iterations, acc_gain=0.0), f"{name} {m} {s}"
                    trace += fit.trace_rows(run, name)
                    ops += fit.ops_rows(run)
                    runs.append((len(runs), run, name, m, s, work.data.n, work.data.m))
                    del fit
    own = measures.timing(spark.createDataFrame(trace, TRACE), spark.createDataFrame(ops, OPS))
    out = spark.createDataFrame(runs, "place int, run string, dataset string, method string, search string, n int, m int").join(own, "run").orderBy("place")
    return measures.pass_model(out.drop("run", "place"))


def cost_by_m(spark: SparkSession, sf_dir: str, name: str = "w3", powers=(10, 12, 14, 16, 18, 20), passes: int = 4) -> DataFrame:
    """Median seconds of a gradient and of a coefficient pass, and their ratio, as the number of parameters grows.

    Words are hashed once; powers of two divide each other, so the fewer buckets are the remainders of the most."""
    rows, most = [], 1 << max(powers)
    held = kept(W.slots(spark, sf_dir, name, most))
    for power in powers:
        with prepared(spark, sf_dir, name, m=1 << power, held=X.folded(held, 1 << power) if 1 << power < most else held) as work:
            problem, m = Problem(work.data, work.loss, work.lam), work.data.m
            g = np.random.default_rng(power)
            took = {"fg": [], "ls": []}
            for _ in range(passes + 1):
                w, p = g.normal(size=m) / m, g.normal(size=m) / m
                for kind, run in (("fg", lambda: problem.gradient(w)), ("ls", lambda: problem.coefficients(w, p, 0.0, 5))):  # noqa: B023
                    began = time.perf_counter()
                    run()
                    took[kind].append(time.perf_counter() - began)
            fg, ls = (float(np.median(took[k][1:])) for k in ("fg", "ls"))  # the first pass starts workers
            rows.append((m, fg, ls, ls / fg))
    held.unpersist()
    return spark.createDataFrame(rows, "m int, tau_fg double, tau_ls double, ratio double")


#: Varied one at a time, on the planted rows: degree, tolerance, history, restart threshold, unit directions, minimiser, shrinking of a bracket.
ABLATIONS = [("degree", "lbfgs", "taylor", [{"degree": d} for d in (1 + k for k in range(1, 7))]), ("theta", "lbfgs", "taylor", [{"theta": t} for t in (1e-2, 1e-4, 1e-6, 1e-8, 1e-10)]), ("history", "lbfgs", "taylor", [{"history": h} for h in (1, 3, 5, 9)]), ("restart", "ncg", "taylor", [{"restart": r} for r in (0.1, 0.2, 0.5, 1.0)]), ("normalize", "ncg", "taylor", [{"normalize": n} for n in (True, False)]), ("argmin", "lbfgs", "taylor", [{"argmin": a} for a in ("newton", "bisect", "backtrack", "roots")]), ("shrink", "ncg", "wolfe", [{"shrink": a} for a in ("bisect", "secant", "dual")]), ("safeguard", "lbfgs", "taylor", [{"safeguard": g} for g in (True, False)])]


def ablations(spark: SparkSession, sf_dir: str, name: str = "w9", gap: float = 1e-6, max_iter: int = 8) -> DataFrame:
    """Iterations to a gap and evaluations for each search, by what is varied."""
    rows = []
    with prepared(spark, sf_dir, name) as work:
        best = fitted(work, name, "lbfgs", "taylor", max_iter, theta=1e-10).trace[-1]["loss"]
        for what, method, search, values in ABLATIONS:
            for options in values:
                fit = fitted(work, name, method, search, max_iter, **options)
                k = next((t["k"] for t in fit.trace if t["loss"] - best <= gap), -1)
                rows.append((what, str(next(iter(options.values()))), method, search, k, sum(t["n_eval"] for t in fit.trace) / max(1, len(fit.trace) - 1), fit.trace[-1]["loss"] - best))
    return spark.createDataFrame(rows, "varied string, value string, method string, search string, iterations int, n_e double, final_gap double")


def reductions(spark: SparkSession, sf_dir: str, name: str = "w3") -> DataFrame:
    """The gradient at weights 0.01 sin(f), summed at once and by trees of 1, 2 and 4 levels: loss and norm of each."""
    rows = []
    with prepared(spark, sf_dir, name, stable=True) as work:
        w = 0.01 * np.sin(np.arange(work.data.m))
        for how, levels in (("flat", None), ("tree", 1), ("tree", 2), ("tree", 4)):
            loss, g = Problem(work.data, work.loss, 0.0, reduce=how, levels=levels).value_and_gradient(w)
            rows.append((f"{how}{levels or ''}", float(loss), float(np.linalg.norm(g))))
    return spark.createDataFrame(rows, "reduce string, loss double, grad_norm double")


def library(spark: SparkSession, sf_dir: str, name: str = "w2", max_iter: int = 30) -> DataFrame:
    """Iterations, seconds and last loss of the library's L-BFGS and of ours with both searches, on one objective."""
    from .optim import mllib_reference

    with prepared(spark, sf_dir, name) as work:
        work.data.df.persist().count()  # the library reads rows, not packed ones
        began = time.perf_counter()
        _, history = mllib_reference(work.data, work.lam, max_iter)
        rows = [("library", len(history) - 1, time.perf_counter() - began, float(history[-1]))]
        for s in ("wolfe", "taylor"):
            fit = fitted(work, name, "lbfgs", s, max_iter)
            rows.append((s, fit.trace[-1]["k"], fit.trace[-1]["cum_seconds"], fit.trace[-1]["loss"]))
    return spark.createDataFrame(rows, "search string, iterations int, seconds double, loss double")


def cost_report(fit, data) -> dict:
    """Of a finished fit: passes by kind, their seconds, doubles reduced and sent, and the physical plan of its rows."""
    by = {}
    for o in fit.ops:
        n, s, r, b = by.get(o.op, (0, 0.0, 0, 0))
        by[o.op] = (n + 1, s + o.seconds, r + o.reduced * data.lanes(), b + o.broadcast)
    return {"passes": by, "iterations": len(fit.trace) - 1, "plan": data.df._jdf.queryExecution().executedPlan().toString()}


def preconditioned(spark: SparkSession, sf_dir: str, name: str = "w9", max_iter: int = 25) -> DataFrame:
    """Conjugate gradients with and without a diagonal from the second derivative at 0."""
    from .optim import diagonal

    rows = []
    with prepared(spark, sf_dir, name) as work:
        scale = diagonal(Problem(work.data, Logistic(), work.lam), np.zeros(work.data.m))
        for label, p in (("plain", None), ("diagonal", scale)):
            fit = fitted(work, name, "ncg", "taylor", max_iter, precondition=p)
            rows.append((label, fit.trace[-1]["k"], fit.trace[-1]["loss"]))
    return spark.createDataFrame(rows, "kind string, iterations int, loss double")
