"""Registered queries of the learners over the given tables, and the SQL of those that SQL can express."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import experiments, factorization, measures, modeling, sources, sqlfuncs, streaming, tables, taylor, wolfe
from . import features as X
from . import workloads as W
from .instances import Instances, Problem
from .losses import L2, Logistic
from .optim import minimize
from .ship import ship

Z9, Q9 = [0.1, -0.2, 0.3, -0.1, 0.05], [0.5, -0.5, 0.1, 0.2, 0.1]
ITERATIONS = 15
PLANTED = """
WITH raw AS (SELECT l_orderkey, (l_quantity - 25.5) / 14.43 AS x1, (l_extendedprice - 52500) / 30000 AS x2, (l_discount - 0.05) / 0.0316 AS x3, (l_tax - 0.04) / 0.0258 AS x4,
  (CAST('0x' || substr(md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber)), 1, 8) AS BIGINT) + 0.5::DOUBLE) / 4294967296::DOUBLE AS u FROM lineitem),
d AS (SELECT *, CASE WHEN x1 - 0.8 * x2 + 0.5 * x3 + 0.3 * x4 + 0.2 + ln(u / (1 - u)) > 0 THEN 1 ELSE 0 END AS y FROM raw)"""
TERMS = """ln(1 + exp(-abs(z))) + greatest(-z, 0) + CASE WHEN y = 0 THEN z ELSE 0 END AS b0, q * (s - CASE WHEN y = 0 THEN 0 ELSE 1 END) AS b1, q * q * s * (1 - s) / 2 AS b2,
 pow(q, 3) * s * (1 - s) * (1 - 2 * s) / 6 AS b3, pow(q, 4) * s * (1 - s) * (1 - 6 * s * (1 - s)) / 24 AS b4, pow(q, 5) * s * (1 - s) * (1 - 2 * s) * (1 - 12 * s * (1 - s)) / 120 AS b5"""
MEANS = ", ".join(f"round(avg(b{k}), 6) + 0.0 AS c{k}" for k in range(6))
ZQ9 = ", ".join(f"{' + '.join(f'({w}) * {x}' for w, x in zip(v, ['x1', 'x2', 'x3', 'x4', '1'], strict=True))} AS {n}" for v, n in ((Z9, "z"), (Q9, "q")))
C9 = f"{PLANTED}, m AS (SELECT *, {ZQ9} FROM d), t AS (SELECT *, 1 / (1 + exp(-z)) AS s FROM m), b AS (SELECT l_orderkey, {TERMS} FROM t), c AS (SELECT {', '.join(f'avg(b{k}) AS c{k}' for k in range(6))} FROM b)"
#: Methods of the timed orders, by customer.
TIMED = ["lbfgs_wolfe", "lbfgs_taylor", "ncg_wolfe", "ncg_taylor"]
#: Two traces of six iterates for the measures: run, k, loss, seconds.
TOY = [("wolfe", k, x, 1.0 * k) for k, x in enumerate((0.69, 0.60, 0.50, 0.42, 0.36, 0.32))] + [("taylor", k, x, 1.1 * k) for k, x in enumerate((0.69, 0.52, 0.40, 0.33, 0.31, 0.3))]


def _r(c, digits=6):
    return F.round(c, digits) + F.lit(0.0)


def _frame(spark: SparkSession, values, names) -> DataFrame:
    return spark.createDataFrame([tuple(float(v) for v in values)], ", ".join(f"{n} double" for n in names)).select(*(_r(F.col(n)).alias(n) for n in names))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The trace of L-BFGS with Taylor searches on the planted workload."""
    return fit_query("w9", "lbfgs", "taylor")(spark, sf_dir)


# -- passes ------------------------------------------------------------------------------------------------------------------
def _w1_margins(spark, sf_dir) -> DataFrame:
    """z and q of embeddings with weights sin(i) / 10 and cos(i) / 10, i from 0, and 0.1 for the constant of z."""
    x = F.col("embedding").cast("array<double>")
    dot = lambda f: F.aggregate(F.transform(x, lambda e, i: e * f(i.cast("double")) / 10), F.lit(0.0), lambda s, e: s + e)
    return W.table(spark, sf_dir, "embeddings").select((dot(F.sin) + 0.1).alias("z"), dot(F.cos).alias("q"), (F.col("label") < 5).cast("double").alias("y"), "label")


def loss_logit_w1(spark, sf_dir):
    data = W.w1(spark, sf_dir).data
    value = Problem(data, Logistic()).value(np.r_[np.sin(np.arange(64)) / 10, 0.1])
    return _frame(spark, [value], ["loss"]).withColumn("n", F.lit(data.count()))


def coeffs_logit_w1_d5(spark, sf_dir):
    w, p = np.r_[np.sin(np.arange(64)) / 10, 0.1], np.r_[np.cos(np.arange(64)) / 10, 0.0]
    return _frame(spark, Problem(W.w1(spark, sf_dir).data, Logistic()).coefficients(w, p, 0.0, 5).c, [f"c{k}" for k in range(6)])


def grad_logit_w9(spark, sf_dir):
    p = Problem(W.w9(spark, sf_dir).data, Logistic(), 1e-3)
    value, g = p.value_and_gradient(np.array(Z9))
    return _frame(spark, [value, *g], ["loss", "g1", "g2", "g3", "g4", "g5"])


def coeffs_logit_w9_d5(spark, sf_dir):
    return _frame(spark, Problem(W.w9(spark, sf_dir).data, Logistic()).coefficients(np.array(Z9), np.array(Q9), 0.0, 5).c, [f"c{k}" for k in range(6)])


def coeffs_ls_w6_d2(spark, sf_dir):
    w = W.w6(spark, sf_dir)
    return _frame(spark, Problem(w.data, w.loss).coefficients(np.full(6, 0.1), np.array([1, -1, 0.5, 0.2, 0.3, 0.4]), 0.0, 2).c, ["c0", "c1", "c2"])


def _mf(ratings):
    side = lambda key, s: ratings.select(key).distinct().select(key, *(F.array(*(f(F.col(key).cast("double") + k + s) / 2 for k in range(2))).alias(n) for f, n in ((F.cos, "vec"), (F.sin, "dir"))))
    return factorization.expand(ratings, side("i", 0.0), side("j", 0.5))


def coeffs_mf_w7a_d4(spark, sf_dir):
    return _frame(spark, _mf(W.w7a(spark, sf_dir)).c, [f"c{k}" for k in range(5)])


def coeffs_mf_w7b_d4(spark, sf_dir):
    return _frame(spark, _mf(W.w7b(spark, sf_dir)).c, [f"c{k}" for k in range(5)])


def coeffs_table_w9_d5(spark, sf_dir):
    """The coefficients by way of a parameter table and exploded features."""
    d = W.planted(spark, sf_dir).withColumn("row_id", F.monotonically_increasing_id())
    ex = d.select("row_id", F.posexplode(F.array("x1", "x2", "x3", "x4")).alias("f", "v")).withColumn("f", F.col("f").cast("long"))
    params = spark.createDataFrame([(k, Z9[k], Q9[k]) for k in range(4)], "f long, w double, p double")
    held = tables.margins(ex, d.select("row_id", "y"), params, (Z9[4], Q9[4]))
    return _frame(spark, tables.coefficients(held, params, Logistic(), 5).c, [f"c{k}" for k in range(6)])


def coeffs_arrow_w9_d5(spark, sf_dir):
    """The coefficients by Arrow batches over array rows."""
    from .instances import Instances

    df = W.planted(spark, sf_dir).select("y", F.array("x1", "x2", "x3", "x4", "x5").alias("x"))
    return _frame(spark, Problem(Instances(df, 5, kind="dense"), Logistic()).coefficients(np.array(Z9), np.array(Q9), 0.0, 5).c, [f"c{k}" for k in range(6)])


def l2_terms(spark, sf_dir):
    """The penalty's polynomial at step 0.5 of a ray through the parts' sizes and prices."""
    rows = W.table(spark, sf_dir, "part").orderBy("p_partkey").select((F.col("p_size") / 50).alias("w"), (F.col("p_retailprice") / 2000).alias("p")).toArrow()
    w, p = rows["w"].to_numpy(), rows["p"].to_numpy()
    return _frame(spark, L2(1.0).terms(w + 0.5 * p, p, 3) / len(w), ["c0", "c1", "c2", "c3"])


def horner_grid(spark, sf_dir):
    """A polynomial and its first two derivatives at every order line's quantity, by quantity."""
    c = F.array(*(F.lit(x) for x in (0.6, -0.4, 0.3, -0.1, 0.05, 0.01)))
    at = W.table(spark, sf_dir, "lineitem").select(((F.col("l_quantity") - 25) / 10).alias("t"))
    v, d1, d2 = sqlfuncs.horner_columns(c, F.col("t"))
    own = at.select(_r(F.col("t"), 1).alias("t"), v.alias("v"), d1.alias("d1"), d2.alias("d2"))
    return own.groupBy("t").agg(F.count("*").alias("n"), *(_r(F.avg(x)).alias(x) for x in ("v", "d1", "d2")))


def model_vs_truth_w9(spark, sf_dir):
    """The model at 0 against the true loss on a grid of steps, all steps in one pass."""
    problem = Problem(W.w9(spark, sf_dir).data, Logistic())
    model = problem.coefficients(np.array(Z9), np.array(Q9), 0.0, 5)
    held = problem.margins(np.array(Z9), np.array(Q9))
    grid = [k / 4 for k in range(9)]
    truth = held.agg(*(F.avg(Logistic().value_term(F.col("z") + a * F.col("q"), F.col("y"))).alias(f"a{k}") for k, a in enumerate(grid))).first()
    rows = [(a, float(truth[k]), model.value(a), abs(model.error_estimate(a))) for k, a in enumerate(grid)]
    return spark.createDataFrame(rows, "t double, truth double, model double, estimate double").select("t", *(_r(F.col(c)).alias(c) for c in ("truth", "model", "estimate")))


def wolfe_checks_w9(spark, sf_dir):
    problem = Problem(W.w9(spark, sf_dir).data, Logistic())
    held = problem.margins(np.array(Z9), np.array(Q9))
    grid, loss = [0.5, 1.0, 2.0, 4.0, 8.0], Logistic()
    at = lambda a: F.col("z") + a * F.col("q")
    row = held.agg(*(F.avg(c) for a in (0.0, *grid) for c in (loss.value_term(at(a), F.col("y")), loss.slope_term(at(a), F.col("y")) * F.col("q")))).first()
    rows = [(a, bool(wolfe.decrease(row[2 + 2 * k], row[0], row[1], a)), bool(wolfe.curvature(row[3 + 2 * k], row[1])), row[2 + 2 * k], row[3 + 2 * k]) for k, a in enumerate(grid)]
    return spark.createDataFrame(rows, "a double, decrease boolean, curvature boolean, phi double, dphi double").select("a", "decrease", "curvature", _r(F.col("phi")).alias("phi"), _r(F.col("dphi")).alias("dphi"))


def cubic_min_cases(spark, sf_dir):
    """Minimisers of a cubic for each part, from values and slopes at two points; their mean by size."""
    ship(spark)

    def run(batches):
        for batch in batches:
            k, *c = (x.to_pylist() for x in batch.columns)
            x = []
            for a3, a2, a1 in zip(*c, strict=True):
                f, d = (lambda x: a3 * x**3 + a2 * x**2 + a1 * x), (lambda x: 3 * a3 * x**2 + 2 * a2 * x + a1)  # noqa: B023
                x.append(wolfe.cubic_min(0.0, f(0.0), d(0.0), 4.0, f(4.0), d(4.0)))
            yield pa.record_batch([pa.array(k, pa.int32()), pa.array(x, pa.float64())], ["k", "x"])

    cubics = W.table(spark, sf_dir, "part").select(F.col("p_size").cast("int").alias("k"), (0.5 + F.col("p_size") / 25).alias("a3"), ((F.col("p_retailprice") - 1400) / 200).alias("a2"), (-1.0 - F.col("p_partkey") % 7).alias("a1"))
    return cubics.mapInArrow(run, "k int, x double").groupBy("k").agg(F.count("*").alias("n"), _r(F.avg("x")).alias("x"))


def fallback_step_w9(spark, sf_dir):
    m = Problem(W.w9(spark, sf_dir).data, Logistic()).coefficients(np.array(Z9), np.array(Q9), 0.0, 2)
    return _frame(spark, [m.fallback()], ["t"])


def example_1d_taylor(spark, sf_dir):
    """The first iterate of the worked function, weighed by the order lines, for degrees 2 to 7; derivatives come from a DataFrame."""
    d = [r[0] for r in W.example(spark, sf_dir).orderBy("k").select("d").collect()]
    rows = [(n, 1.0 + taylor.TaylorModel([d[k] / math.factorial(k) for k in range(n + 1)], 1.0).argmin().t) for n in range(2, 8)]
    return spark.createDataFrame(rows, "degree int, alpha double").select("degree", _r(F.col("alpha")).alias("alpha"))


def example_1d_wolfe(spark, sf_dir):
    """A search on the same function, a pass over the order lines for each evaluation."""

    def f(a):
        d = W.example(spark, sf_dir, a, (0, 1)).orderBy("k").collect()
        return d[0].d, d[1].d, None

    s = wolfe.line_search(f, *f(0.0)[:2])
    return _frame(spark, [s.alpha, s.n_eval, *f(s.alpha)[:2]], ["alpha", "n_eval", "phi", "dphi"])


def ls_exact_step_w6(spark, sf_dir):
    w = W.w6(spark, sf_dir)
    p = Problem(w.data, w.loss)
    s = taylor.taylor_line_search(lambda a: p.coefficients(np.full(6, 0.1), np.array([0.1, 0.1, -0.1, 0.05, 0.1, 0.3]), a, 2), 1.0)
    return _frame(spark, [s.alpha, s.n_eval], ["alpha", "n_eval"])


def ls_fit_w6(spark, sf_dir):
    """Least squares of the price on six columns by L-BFGS with exact steps."""
    w = W.w6(spark, sf_dir)
    fit = minimize(Problem(w.data.persist(), w.loss), "lbfgs", "taylor", degree=2, max_iter=40)
    w.data.unpersist()
    return _frame(spark, fit.w, [f"w{i + 1}" for i in range(6)])


def normal_equations_w6(spark, sf_dir):
    """The same weights from one pass of products, solved on the driver."""
    return _frame(spark, measures.normal_equations(W.w6(spark, sf_dir).data), [f"w{i + 1}" for i in range(6)])


# -- fits --------------------------------------------------------------------------------------------------------------------
def run_fit(spark, sf_dir, name, method, search, max_iter=ITERATIONS, **options):
    work = getattr(W, name)(spark, sf_dir)
    work.data.persist()
    fit = minimize(Problem(work.data, work.loss, work.lam, cached=options.pop("cached", False)), method, search, max_iter=max_iter, theta=options.pop("theta", work.theta), degree=options.pop("degree", work.degree), **options)
    work.data.unpersist()
    return fit


#: Workloads, and the optimisers that are run on each.
METHODS = {"w1": ("gd", "ncg", "lbfgs"), "w2": ("gd", "ncg", "lbfgs"), "w3": ("ncg", "lbfgs"), "w4": ("ncg", "lbfgs"), "w5": ("ncg", "lbfgs"), "w9": ("gd", "ncg", "lbfgs")}
#: Penalty and tolerance of each, as in workloads.
SETTINGS = {"w1": (1e-8, 1e-6), "w2": (1e-7, 1e-4), "w3": (1e-8, 1e-4), "w4": (1e-9, 1e-6), "w5": (1e-9, 1e-4), "w9": (1e-3, 1e-6)}


def first_iterates(name, method, search, iterations=3, cached=False, **options):
    """The first iterates of a fit, to be told apart from SQL by nothing: loss, gradient norm, step and evaluations."""

    def query(spark, sf_dir):
        work = getattr(W, name)(spark, sf_dir, **({"stable": True} if name in ("w3", "w4", "w5") else {}))
        work.data.persist()
        fit = minimize(Problem(work.data, work.loss, work.lam, cached=cached), method, search, max_iter=iterations, theta=work.theta, **options)
        work.data.unpersist()
        return fit.trace_frame(spark).select("k", _r(F.col("loss"), 7).alias("loss"), _r(F.col("grad_norm")).alias("grad_norm"), _r(F.col("alpha"), 4).alias("alpha"), "n_eval")

    return query


def fit_query(name, method, search, max_iter=ITERATIONS, **options):
    def query(spark, sf_dir):
        fit = run_fit(spark, sf_dir, name, method, search, max_iter, **options)
        return fit.trace_frame(spark, f"{name}_{method}_{search}", name).drop("seconds", "cum_seconds")

    return query


def _mf_fit(ratings, rank, max_iter):
    def query(spark, sf_dir):
        _, _, trace = factorization.fit(ratings(spark, sf_dir), rank, max_iter=max_iter)
        return spark.createDataFrame([(t["k"], t["loss"], t["grad_norm"], t["alpha"], t["model_loss"]) for t in trace], "k int, loss double, grad_norm double, alpha double, model_loss double")

    return query


def ablations_w9(spark, sf_dir):
    return experiments.ablations(spark, sf_dir)


def minibatch_w15(spark, sf_dir):
    """One step for each day of events, as batches of a stream would come."""
    events = W.table(spark, sf_dir, "events")
    learner = streaming.MiniBatch(lambda b: W.w15(b).data.df, 126, Logistic())
    days = [r[0] for r in events.select(F.to_date("ts").alias("d")).distinct().orderBy("d").collect()]
    for k, day in enumerate(days):
        learner(events.filter(F.to_date("ts") == day), k)
    return spark.createDataFrame([(t["batch"], t["n"], t["loss"], t["alpha"]) for t in learner.trace], "batch int, n long, loss double, alpha double")


# -- measures ----------------------------------------------------------------------------------------------------------------
def _toy(spark):
    return spark.createDataFrame(TOY, "search string, k int, loss double, cum_seconds double").withColumns({"dataset": F.lit("toy"), "method": F.lit("lbfgs"), "run": F.col("search"), "acc": F.exp(-F.col("loss"))})


def trace_gap(spark, sf_dir):
    out = measures.gap(_toy(spark))
    return out.select("search", "k", _r(F.col("gap")).alias("gap"), _r(F.col("acc")).alias("acc"))


def _daily(spark, sf_dir):
    """Traces from the events: users of even and odd ids stand for the searches, days for iterates; losses fall as values come in."""
    even = F.when(F.col("user_id") % 2 == 0, "wolfe").otherwise("taylor")
    days = W.table(spark, sf_dir, "events").groupBy(even.alias("search"), F.to_date("ts").alias("day")).agg(F.sum("value").alias("value"))
    all_, past = Window.partitionBy("search"), Window.partitionBy("search").orderBy("day")
    share = F.sum("value").over(past.rowsBetween(Window.unboundedPreceding, 0)) / F.sum("value").over(all_)
    t = days.select("search", (F.row_number().over(past) - 1).alias("k"), share.alias("share"))
    slow = F.col("search") == "wolfe"
    t = t.select("search", "k", (0.7 - 0.5 * F.when(slow, F.col("share")).otherwise(F.sqrt("share"))).alias("loss"), (F.col("k") * F.when(slow, 1.0).otherwise(1.1)).alias("cum_seconds"))
    return t.withColumns({"dataset": F.lit("events"), "method": F.lit("lbfgs"), "run": F.col("search"), "acc": F.exp(-F.col("loss"))})


def to_gap_toy(spark, sf_dir):
    return measures.to_gap(_daily(spark, sf_dir), (0.1, 0.01)).select("search", "goal", "k", _r(F.col("seconds")).alias("seconds"))


def trace_speedup(spark, sf_dir):
    t = _toy(spark)
    out = measures.speedup(t.filter("search = 'wolfe'"), t.filter("search = 'taylor'"))
    return out.select("k_w", "k_t", _r(F.col("acc")).alias("acc"), _r(F.col("iter_ratio")).alias("iter_ratio"), _r(F.col("time_ratio")).alias("time_ratio"))


def speedup_windows(spark, sf_dir):
    t = _daily(spark, sf_dir)
    out = measures.windowed(measures.speedup(t.filter("search = 'wolfe'"), t.filter("search = 'taylor'")), 0.1)
    return out.select("bin", "n", *(_r(F.col(c)).alias(c) for c in ("iter_mean", "iter_sd", "time_mean", "time_sd")))


def plateau_toy(spark, sf_dir):
    return measures.plateau(_daily(spark, sf_dir), 0.05, 2).select("run", "k", _r(F.col("acc")).alias("acc"))


def _timed_orders(spark, sf_dir):
    """Orders as timed iterations: priorities stand for datasets, customers for methods, prices for seconds."""
    t = W.table(spark, sf_dir, "orders").select(F.col("o_orderpriority").alias("dataset"), F.get(F.array(*map(F.lit, TIMED)), (F.col("o_custkey") % 4).cast("int")).alias("method"), (F.col("o_totalprice") / 1e4).alias("tau_tot"), "o_orderkey")
    t = t.withColumn("tau_fg", F.col("tau_tot") * (0.5 + F.col("o_orderkey") % 5 / 10))
    return t.withColumns({"tau_ls": F.when(F.col("method").endswith("taylor"), F.col("tau_fg") * (0.2 + F.col("o_orderkey") % 3 / 10)), "n_e": 1.0 + F.col("o_orderkey") % 4})


def timing_table(spark, sf_dir):
    """One row for each dataset of the timed orders, with mean seconds by method."""
    return _timed_orders(spark, sf_dir).groupBy("dataset").pivot("method", TIMED).agg(_r(F.avg("tau_tot"), 4))


def pass_model(spark, sf_dir):
    """What passes alone would take, from the means of the timed orders."""
    means = _timed_orders(spark, sf_dir).groupBy("dataset", "method").agg(*(F.avg(c).alias(c) for c in ("tau_tot", "tau_fg", "tau_ls", "n_e")))
    out = measures.pass_model(means)
    return out.select("dataset", "method", _r(F.col("passes"), 4).alias("passes"), _r(F.col("pass_ratio"), 4).alias("pass_ratio"))


def timing_rollup(spark, sf_dir):
    """Mean seconds by dataset and kind of search, with subtotals."""
    t = _timed_orders(spark, sf_dir).withColumn("search", F.split_part("method", F.lit("_"), F.lit(2)))
    return t.rollup("dataset", "search").agg(F.count("*").alias("n"), _r(F.avg("tau_tot"), 4).alias("tau_tot"))


def comm_cost(spark, sf_dir):
    """Passes and doubles of runs: kinds of events stand for runs, hours for passes, values for doubles."""
    i = F.dayofyear("ts") * 24 + F.hour("ts")
    hours = W.table(spark, sf_dir, "events").groupBy(F.col("event_type").alias("run"), i.alias("i")).agg(F.sum(F.floor("value")).alias("doubles_reduced"), F.count("*").alias("doubles_broadcast"))
    return measures.communication(hours.withColumn("op", F.when(F.col("i") % 3 == 1, "coeffs").otherwise("fg")), 8)


def timing_measured(spark, sf_dir):
    """The timing table from own runs."""
    return experiments.timing(spark, sf_dir, ("w1", "w2", "w3", "w4", "w5"))


def cost_by_m_w3(spark, sf_dir):
    return experiments.cost_by_m(spark, sf_dir)


def library_w2(spark, sf_dir):
    return experiments.library(spark, sf_dir)


def preconditioned_w9(spark, sf_dir):
    return experiments.preconditioned(spark, sf_dir)


def wolfe_bracket(spark, sf_dir):
    """Searches on the worked function from steps that are too short, fine and too long, into the bracket."""
    f, out = taylor.worked_example, []
    for a0 in (0.01, 0.1, 1.0, 1.9, 3.0, 8.0):
        s = wolfe.line_search(lambda a: (f(a, 0), f(a, 1), None), f(0.0, 0), f(0.0, 1), a0, nu2=0.1)
        out.append((a0, s.alpha, s.n_eval))
    return spark.createDataFrame(out, "first double, alpha double, n_eval int").select("first", _r(F.col("alpha")).alias("alpha"), "n_eval")


def tree_vs_flat(spark, sf_dir):
    """The gradient of the largest sparse text by one level and by several: loss and norm."""
    return experiments.reductions(spark, sf_dir).select("reduce", _r(F.col("loss"), 8).alias("loss"), _r(F.col("grad_norm"), 8).alias("grad_norm"))


# -- features, reports, model use ----------------------------------------------------------------------------------------------
def hash_features_w2(spark, sf_dir):
    """Rows and sums of values by feature of the hashed text."""
    return X.exploded(W.w2(spark, sf_dir).data.df).groupBy("f").agg(F.count("*").alias("n"), _r(F.sum("v")).alias("total"))


def onehot_w5(spark, sf_dir):
    """Rows and positive labels by feature of the one-hot order lines."""
    rows = W.w5(spark, sf_dir, stable=True).data.df.select("y", F.explode("idx").alias("i"))
    return rows.groupBy(F.col("i").cast("long").alias("f")).agg(F.count("*").alias("n"), F.sum("y").alias("positive"))


def label_ratio(spark, sf_dir):
    """Positive and negative labels of the classification workloads."""
    works = [(n, getattr(W, n)(spark, sf_dir)) for n in ("w1", "w2", "w3", "w4", "w5", "w9")] + [("w15", W.w15(W.table(spark, sf_dir, "events")))]
    return experiments.union([measures.summary(w.data).select(F.lit(n).alias("workload"), "positive", "negative") for n, w in works])


def dataset_summary(spark, sf_dir):
    works = [W.w1(spark, sf_dir), W.w2(spark, sf_dir), *(f(spark, sf_dir, stable=True) for f in (W.w3, W.w4, W.w5)), W.w9(spark, sf_dir)]
    out = experiments.union([measures.summary(w.data) for w in works])
    return out.select("dataset", "n", "m", _r(F.col("nnz"), 4).alias("nnz"), _r(F.col("nnz_sd"), 4).alias("nnz_sd"), "positive", "negative")


def _scored9(spark, sf_dir):
    held = Problem(W.w9(spark, sf_dir).data, Logistic()).margins(np.array([1.0, -0.8, 0.5, 0.3, 0.2]), np.zeros(5))
    return held.select("y", _r(1 / (1 + F.exp(-F.col("z"))), 4).alias("prob"))


def confusion_w9(spark, sf_dir):
    out = measures.classify(_scored9(spark, sf_dir))
    return out.select("n", "tp", "fp", "tn", "fn", _r(F.col("base_rate")).alias("base_rate"), _r(F.col("accuracy")).alias("accuracy"))


def auc_w9(spark, sf_dir):
    return measures.classify(_scored9(spark, sf_dir)).select(_r(F.col("auc")).alias("auc"), _r(F.col("log_loss")).alias("log_loss"))


def ovr_coeffs_w1(spark, sf_dir):
    """Slopes and bends of ten one-against-rest losses in one pass."""
    x = W.table(spark, sf_dir, "embeddings").select("label", *(F.col("embedding")[i].cast("double").alias(f"x{i}") for i in range(64)), F.lit(1.0).alias("x64"))
    narrow = Instances(x, 65, [f"x{i}" for i in range(65)])
    w, p = np.r_[np.sin(np.arange(64)) / 10, 0.1], np.r_[np.cos(np.arange(64)) / 10, 0.0]
    out = modeling.batched_coefficients(narrow, [((F.col("label") == c).cast("double"), w, p) for c in range(10)], 2)
    return _frame(spark, out[:, :2].ravel(), [f"c{k}_{c}" for c in range(10) for k in range(2)])


def group_coeffs_nation(spark, sf_dir):
    """A model of each nation's customers in one pass."""
    d = W.planted(spark, sf_dir).join(W.table(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(W.table(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    z, q = (sum((F.col(f"x{i + 1}") * w[i] for i in range(4)), F.lit(w[4])) for w in (Z9, Q9))
    out = modeling.group_coefficients(d.select(F.col("c_nationkey").cast("long").alias("nation"), "y", z.alias("z"), q.alias("q")), "nation", Logistic(), 2)
    return out.select("nation", "n", *(_r(F.col(f"c{k}")).alias(f"c{k}") for k in range(3)))


def stream_window_loss(spark, sf_dir):
    e = W.table(spark, sf_dir, "events").select("ts", Logistic().value_term(F.log1p("value") / 10, (F.col("event_type") == "purchase").cast("double")).alias("loss"))
    out = streaming.window_loss(e)
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n", _r(F.col("loss")).alias("loss"), _r(F.col("acc")).alias("acc"))


def residual_topk_w9(spark, sf_dir):
    """The orders whose planted rows are told worst: largest total loss, ten of them."""
    t = W.planted(spark, sf_dir)
    z = sum((F.col(f"x{i + 1}") * w for i, w in enumerate([1.0, -0.8, 0.5, 0.3])), F.lit(0.2))
    return t.groupBy("l_orderkey").agg(_r(F.sum(Logistic().value_term(z, F.col("y")))).alias("loss"), F.count("*").alias("n")).orderBy(F.desc("loss"), "l_orderkey").limit(10)


def labelled_documents(spark, sf_dir):
    """Documents with and without labels by language: a semi and an anti join."""
    d, l = W.table(spark, sf_dir, "documents"), W.table(spark, sf_dir, "labels")
    out = d.join(l, "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("labelled"))
    rest = d.join(l, "doc_id", "left_anti").groupBy("lang").agg(F.count("*").alias("unlabelled"))
    return out.join(rest, "lang", "full").select("lang", F.coalesce("labelled", F.lit(0)).alias("labelled"), F.coalesce("unlabelled", F.lit(0)).alias("unlabelled"))


def sql_terms_w9(spark, sf_dir):
    """The coefficients again, written in SQL with the registered functions."""
    sqlfuncs.register(spark)
    W.planted(spark, sf_dir).createOrReplaceTempView("rayfit_planted")
    z, q = (" + ".join(f"({w}D) * x{i + 1}" for i, w in enumerate(v)) for v in (Z9, Q9))
    return spark.sql(f"SELECT {', '.join(f'round(avg(b[{k}]), 6) + 0D AS c{k}' for k in range(6))} FROM (SELECT logit_terms({z}, {q}, y) AS b FROM rayfit_planted)")


# -- parameter tables, streams in batch form, text instances, measures of real runs -----------------------------------------------
def lbfgs_table_w9(spark, sf_dir):
    """The first iterates of L-BFGS with every vector in a table, on the planted workload."""
    d = tables.staged(W.planted(spark, sf_dir).withColumn("row_id", F.monotonically_increasing_id()))
    ex = d.select("row_id", F.posexplode(F.array("x1", "x2", "x3", "x4")).alias("f", "v")).withColumn("f", F.col("f").cast("long"))
    _, _, trace = tables.minimize(ex, d.select("row_id", "y"), Logistic(), 1e-3, max_iter=3, theta=1e-6)
    out = spark.createDataFrame([(t["k"], t["loss"], t["grad_norm"], t["alpha"], t["n_eval"]) for t in trace], "k int, loss double, grad_norm double, alpha double, n_eval int")
    return out.select("k", _r(F.col("loss"), 7).alias("loss"), _r(F.col("grad_norm")).alias("grad_norm"), _r(F.col("alpha"), 4).alias("alpha"), "n_eval")


def libsvm_roundtrip(spark, sf_dir):
    """Order lines written as libsvm text to the shared folder and read again: rows and sums by label."""
    t = W.table(spark, sf_dir, "lineitem").select(F.array(F.lit(0), F.lit(1), F.lit(2), F.lit(3)).alias("idx"), F.array("l_quantity", F.col("l_discount") + 0.0, "l_tax", F.lit(1.0)).alias("val"), (F.col("l_quantity") > 7).cast("double").alias("y"))
    path = tables.fresh_path(spark, "libsvm")
    sources.write_libsvm(t, path, 3)
    back = sources.read_libsvm(spark, path, 3)
    return back.groupBy("y").agg(F.count("*").alias("n"), *(_r(F.sum(F.element_at("val", k + 1)), 4).alias(f"s{k}") for k in range(4)))


def _scored_events(spark, sf_dir):
    y = (F.col("event_type") == "purchase").cast("double")
    return W.table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", y.alias("y"), (F.log1p("value") / 10).alias("z"), F.log1p("value").alias("q"), Logistic().value_term(F.log1p("value") / 10, y).alias("loss"))


def session_loss_events(spark, sf_dir):
    """Sessions of users, ended by two hours without an event: rows and mean loss of each."""
    out = streaming.session_loss(_scored_events(spark, sf_dir), "user_id", pause="2 hours")
    return out.select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", _r(F.col("loss")).alias("loss"))


def running_coeffs_events(spark, sf_dir):
    """Sums of coefficient terms of each day, the epochs of a stream."""
    own = _scored_events(spark, sf_dir).withColumn("epoch", F.date_format("ts", "yyyy-MM-dd"))
    out = streaming.running_coefficients(own, Logistic(), 2)
    return out.select("epoch", "n", *(_r(F.col(f"c{k}"), 4).alias(f"c{k}") for k in range(3)))


def dedup_events(spark, sf_dir):
    """Events delivered twice, each counted once."""
    e = W.table(spark, sf_dir, "events").select("event_id", "ts", "event_type")
    return streaming.deduplicated(e.unionAll(e)).groupBy("event_type").agg(F.count("*").alias("n"))


def interval_join_events(spark, sf_dir):
    """For each user, pairs of a purchase and a later event of the same user within an hour."""
    e = W.table(spark, sf_dir, "events").select("user_id", "ts", "event_type")
    out = streaming.interval_join(e.filter("event_type = 'purchase'"), e, "user_id", "1 hour")
    return out.groupBy(F.col("a.user_id").alias("user_id")).agg(F.count("*").alias("n"))


def step_accuracy_w9(spark, sf_dir):
    """Distance to the exact step, and the slope left there, of the first steps of both searches by degree."""
    problem, w, rows = Problem(W.w9(spark, sf_dir).data, Logistic(), 1e-3), np.zeros(5), []
    value, g = problem.value_and_gradient(w)
    problem.begin_ray(w, -g)
    exact = taylor.exact_line_search(lambda a: problem.coefficients(w, -g, a, 7)).alpha
    for d in (2, 3, 5):
        step = taylor.taylor_line_search(lambda a, d=d: problem.coefficients(w, -g, a, d), 1.0, 1e-4)
        rows += [(f"taylor_{d}", r["alpha"], r["distance"], r["slope_left"]) for r in measures.step_accuracy(problem, w, -g, [(step.alpha,)], exact)]

    def at(a):
        f, h = problem.value_and_gradient(w - a * g)
        return f, float(-g @ h), h

    step = wolfe.line_search(at, value, float(-g @ g), 1.0)
    rows += [("wolfe", r["alpha"], r["distance"], r["slope_left"]) for r in measures.step_accuracy(problem, w, -g, [(step.alpha,)], exact)]
    problem.end_ray()
    return spark.createDataFrame(rows, "search string, alpha double, distance double, slope_left double")


def event_counts_w1(spark, sf_dir):
    """Restarts, fallback steps and guards of both searches."""
    fits = [run_fit(spark, sf_dir, "w1", "ncg", s, 8).trace_frame(spark, s, "w1") for s in ("taylor", "wolfe")]
    return measures.events(fits[0].unionByName(fits[1]))


def penalty_path_w9(spark, sf_dir):
    """Losses along falling penalties, each fit begun where the one before ended."""
    data = W.w9(spark, sf_dir).data.persist()
    out = modeling.path(data, [1e-1, 1e-2, 1e-3], max_iter=5)
    data.unpersist()
    return spark.createDataFrame([(lam, loss, float(np.linalg.norm(w))) for lam, w, loss in out], "lam double, loss double, norm double")


def sample_events(spark, sf_dir):
    """A share of each kind of event, the same in every engine."""
    e = W.table(spark, sf_dir, "events")
    return X.hash_sample(e, "event_id", {"purchase": 0.5, "view": 0.1, "click": 0.25}, "event_type", 3).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


def exact_sum_lineitem(spark, sf_dir):
    """A sum that no order of the rows changes."""
    return measures.exact_sum(W.table(spark, sf_dir, "lineitem"), "l_extendedprice", 4).select(F.col("total").cast("string").alias("total"))


def top_features_w2(spark, sf_dir):
    """The three features of the hashed text with the largest sums, by label."""
    df = W.w2(spark, sf_dir).data.df
    own = X.exploded(df).join(df.select("row_id", "y"), "row_id").groupBy("y", "f").agg(_r(F.sum("v"), 5).alias("total"))
    return measures.top_by_group(own.filter("f < 1024"), "y", "total", "f", 3)


def stats_w9(spark, sf_dir):
    """Moments, order statistics and cardinalities of the planted columns."""
    d = W.planted(spark, sf_dir)
    return d.agg(_r(F.corr("x1", "x2")).alias("corr"), _r(F.covar_samp("x1", "x2")).alias("covar"), _r(F.skewness("x2")).alias("skew"), _r(F.percentile("x2", 0.9)).alias("p90"), F.countDistinct("x1").alias("distinct_x1"), F.min_by("l_orderkey", F.struct("x2", "l_orderkey")).alias("first_order"))


def document_sets(spark, sf_dir):
    """Ids of documents and labels: shared, without a label, and quartiles by length."""
    d, l = W.table(spark, sf_dir, "documents"), W.table(spark, sf_dir, "labels").select("doc_id")
    both, rest = d.select("doc_id").intersect(l), d.select("doc_id").exceptAll(l)
    quarter = d.select(F.ntile(4).over(Window.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("q"), "n_chars")
    parts = [both.agg(F.lit("both").alias("what"), F.count("*").alias("n")), rest.agg(F.lit("rest").alias("what"), F.count("*").alias("n"))]
    return experiments.union(parts + [quarter.groupBy(F.concat(F.lit("q"), F.col("q").cast("string")).alias("what")).agg(F.max("n_chars").alias("n"))])


def url_hosts(spark, sf_dir):
    return W.table(spark, sf_dir, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("n"))


def sql_functions(spark, sf_dir):
    """Every registered function at the quantities of all order lines, and one step of the worked function by the table function."""
    sqlfuncs.register(spark)
    W.table(spark, sf_dir, "lineitem").createOrReplaceTempView("rayfit_lines")
    c = ", ".join(f"{(1 + k) * math.exp(1) / math.factorial(k) + (-1) ** k * math.exp(3) / math.factorial(k)!r}D" for k in range(6))
    means = ", ".join(f"round(avg({x}), 6) + 0D AS {x}" for x in "abcdefghi")
    return spark.sql(f"""SELECT m.*, round(s.alpha + s.t, 6) + 0D AS k FROM (SELECT t, count(*) AS n, {means}, every(j) AS j FROM (
      SELECT g.t, softplus_neg(g.t) AS a, sigmoid(g.t) AS b, horner(array(1D, 2D, 3D), g.t) AS c, horner_d1(array(1D, 2D, 3D), g.t) AS d, horner_d2(array(1D, 2D, 3D), g.t) AS e,
      dot(array(g.t, 2D), array(3D, g.t)) AS f, sparse_dot(array(2, 0), array(g.t, 1D), array(5D, 6D, 7D)) AS g, ls_terms(g.t, 2D, 1D)[1] AS h, mf_terms(g.t, 1D, 2D)[2] AS i, wolfe_ok(1D, 2D, g.t, -1D, 0.5D) AS j
      FROM (SELECT (l_quantity - 25) / 4D AS t FROM rayfit_lines) g) GROUP BY t) m, (SELECT * FROM line_search_step(array({c}), 1D)) s""")


def queries() -> dict:
    own = [loss_logit_w1, coeffs_logit_w1_d5, grad_logit_w9, coeffs_logit_w9_d5, coeffs_ls_w6_d2, coeffs_mf_w7a_d4, coeffs_mf_w7b_d4, coeffs_table_w9_d5, coeffs_arrow_w9_d5, l2_terms, horner_grid, model_vs_truth_w9, wolfe_checks_w9, cubic_min_cases, fallback_step_w9, example_1d_taylor, example_1d_wolfe, ls_exact_step_w6, ls_fit_w6, normal_equations_w6, ablations_w9, minibatch_w15, trace_gap, to_gap_toy, trace_speedup, speedup_windows, plateau_toy, timing_table, pass_model, timing_rollup, comm_cost, timing_measured, cost_by_m_w3, library_w2, preconditioned_w9, wolfe_bracket, tree_vs_flat, hash_features_w2, onehot_w5, label_ratio, dataset_summary, confusion_w9, auc_w9, ovr_coeffs_w1, group_coeffs_nation, stream_window_loss, residual_topk_w9, labelled_documents, sql_terms_w9, lbfgs_table_w9, libsvm_roundtrip, session_loss_events, running_coeffs_events, dedup_events, interval_join_events, step_accuracy_w9, event_counts_w1, penalty_path_w9, sample_events, exact_sum_lineitem, top_features_w2, stats_w9, document_sets, url_hosts, sql_functions]
    out = {f.__name__: f for f in own}
    for name, methods in METHODS.items():
        out[f"traces_{name}"] = lambda spark, sf_dir, name=name, methods=methods: experiments.traces(spark, sf_dir, name, methods, 12 if name == "w9" else experiments.MOST)
    for name in experiments.LARGE:
        out[f"speedup_{name}"] = lambda spark, sf_dir, name=name: experiments.speedup(spark, sf_dir, name)
    out |= {"mf_fit_w7a": _mf_fit(W.w7a, 4, 6), "mf_fit_w7b": _mf_fit(W.w7b, 8, 4)}
    for name, methods in METHODS.items():
        for method in methods:
            for search in ("taylor", "wolfe"):
                out[f"{method}_{search}_{name}_3iters"] = first_iterates(name, method, search)
    for degree in (2, 3, 4):
        out[f"lbfgs_taylor_w9_d{degree}_3iters"] = first_iterates("w9", "lbfgs", "taylor", degree=degree)
    out["newton_taylor_w9"] = fit_query("w9", "newton", "taylor", 5)
    out["lbfgs_backtracking_w9_3iters"] = first_iterates("w9", "lbfgs", "backtracking")
    out["lbfgs_cached_w1_3iters"] = first_iterates("w1", "lbfgs", "taylor", cached=True)
    return out


def _values(rows, names):
    cell = lambda v: "NULL" if v is None else f"'{v}'" if isinstance(v, str) else f"{v}::INTEGER" if isinstance(v, int) else f"{v}::DOUBLE"
    return f"(VALUES {', '.join('(' + ', '.join(map(cell, r)) + ')' for r in rows)}) AS v({names})"


def _mf_sql(ratings: str) -> str:
    dot = lambda f, g: " + ".join(f"{f}(i + {k}) / 2 * {g}(j + {k} + 0.5) / 2" for k in range(2))
    return f"""WITH r AS ({ratings}), a AS (SELECT {dot('cos', 'cos')} - value AS a0, {dot('cos', 'sin')} + {dot('sin', 'cos')} AS a1, {dot('sin', 'sin')} AS a2 FROM r)
SELECT round(avg(a0 * a0 / 2), 6) + 0.0 AS c0, round(avg(a0 * a1), 6) + 0.0 AS c1, round(avg(a0 * a2 + a1 * a1 / 2), 6) + 0.0 AS c2, round(avg(a1 * a2), 6) + 0.0 AS c3, round(avg(a2 * a2 / 2), 6) + 0.0 AS c4 FROM a"""


def oracle_sql() -> dict:
    e1 = "WITH m AS (SELECT label, CASE WHEN label < 5 THEN 1 ELSE 0 END AS y, list_sum(list_transform(range(0, 64), lambda i: CAST(embedding[i + 1] AS DOUBLE) * sin(i) / 10)) + 0.1 AS z, list_sum(list_transform(range(0, 64), lambda i: CAST(embedding[i + 1] AS DOUBLE) * cos(i) / 10)) AS q FROM embeddings), t AS (SELECT *, 1 / (1 + exp(-z)) AS s FROM m)"
    c9 = f"{C9} SELECT {', '.join(f'round(c{k}, 6) + 0.0 AS c{k}' for k in range(6))} FROM c"
    f1 = [math.factorial(k) for k in range(8)]
    g9 = " , ".join(f"round(avg((s - y) * {x}) + 0.001 * ({w}), 6) + 0.0 AS g{i + 1}" for i, (x, w) in enumerate(zip(["x1", "x2", "x3", "x4", "1"], Z9, strict=True)))
    z6 = "0.1 * (x1 + x2 + x3 + x4 + x5 + 1)"
    six = "WITH d AS (SELECT (l_quantity - 25.5) / 14.43 AS x1, (l_discount - 0.05) / 0.0316 AS x2, (l_tax - 0.04) / 0.0258 AS x3, (p_size - 25.5) / 14.4 AS x4, (p_retailprice - 1400) / 300 AS x5, l_extendedprice / 1e5 AS y FROM lineitem JOIN part ON l_partkey = p_partkey)"
    toy = f"SELECT search, k, loss, cum_seconds, exp(-loss) AS acc FROM {_values(TOY, 'search, k, loss, cum_seconds')}"
    sp = f"WITH t AS ({toy}), s AS (SELECT w.k AS k_w, w.acc, w.cum_seconds AS sw, min(t.k) AS k_t FROM t w JOIN t ON w.search = 'wolfe' AND t.search = 'taylor' AND t.acc >= w.acc WHERE w.k > 0 GROUP BY ALL HAVING min(t.k) > 0), r AS (SELECT s.*, s.k_w / s.k_t AS ir, sw / t.cum_seconds AS tr FROM s JOIN t ON t.search = 'taylor' AND t.k = s.k_t)"
    daily = "SELECT search, k, 0.7 - 0.5 * CASE search WHEN 'wolfe' THEN share ELSE sqrt(share) END AS loss, k * CASE search WHEN 'wolfe' THEN 1.0 ELSE 1.1 END AS cum_seconds FROM (SELECT search, CAST(row_number() OVER (PARTITION BY search ORDER BY day) - 1 AS INTEGER) AS k, sum(value) OVER (PARTITION BY search ORDER BY day ROWS UNBOUNDED PRECEDING) / sum(value) OVER (PARTITION BY search) AS share FROM (SELECT CASE user_id % 2 WHEN 0 THEN 'wolfe' ELSE 'taylor' END AS search, CAST(ts AS DATE) AS day, sum(value) AS value FROM events GROUP BY 1, 2))"
    daily = f"SELECT search, k, loss, CAST(cum_seconds AS DOUBLE) AS cum_seconds, exp(-loss) AS acc FROM ({daily})"
    timed = "SELECT *, CASE WHEN method LIKE '%taylor' THEN tau_fg * (0.2 + o_orderkey % 3 / 10) END AS tau_ls, 1.0::DOUBLE + o_orderkey % 4 AS n_e FROM (SELECT *, tau_tot * (0.5 + o_orderkey % 5 / 10) AS tau_fg FROM (SELECT o_orderpriority AS dataset, ['lbfgs_wolfe', 'lbfgs_taylor', 'ncg_wolfe', 'ncg_taylor'][o_custkey % 4 + 1] AS method, o_totalprice / 1e4 AS tau_tot, o_orderkey FROM orders))"
    uv = "WITH u AS (SELECT avg(l_quantity) / 25.5 AS u, avg(l_extendedprice) / 52500 AS v FROM lineitem)"
    s9 = f"{PLANTED}, s AS (SELECT y, round(1 / (1 + exp(-(x1 - 0.8 * x2 + 0.5 * x3 + 0.3 * x4 + 0.2))), 4) AS prob FROM d)"
    ev = f"WITH m AS (SELECT *, ln(1 + value) / 10 AS z, ln(1 + value) AS q, CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END AS y FROM events), t AS (SELECT *, 1 / (1 + exp(-z)) AS s FROM m), e AS (SELECT ts, user_id, {TERMS} FROM t)"
    grid = "(VALUES (0.5), (1.0), (2.0), (4.0), (8.0)) AS g(a)"
    at = "SELECT CAST(a AS DOUBLE) AS a, avg(ln(1 + exp(-abs(z + a * q))) + greatest(-(z + a * q), 0) + CASE WHEN y = 0 THEN z + a * q ELSE 0 END) AS phi, avg(q * (1 / (1 + exp(-(z + a * q))) - y)) AS dphi"
    from . import oracles

    fits = {f"{me}_{se}_{w}_3iters": oracles.trace(w, me, se, *SETTINGS[w]) for w, methods in METHODS.items() for me in methods for se in ("taylor", "wolfe")}
    fits |= {f"lbfgs_taylor_w9_d{d}_3iters": oracles.trace("w9", "lbfgs", "taylor", *SETTINGS["w9"], degree=d) for d in (2, 3, 4)}
    fits |= {"lbfgs_table_w9": fits["lbfgs_taylor_w9_3iters"], "lbfgs_cached_w1_3iters": fits["lbfgs_taylor_w1_3iters"], "lbfgs_backtracking_w9_3iters": fits["lbfgs_wolfe_w9_3iters"]}
    solved = oracles.solve([f"x{i}" for i in range(1, 7)], "y", f"{six}, six AS (SELECT *, 1::DOUBLE AS x6 FROM d)", "six")
    shapes = {n: f"WITH {oracles.features(n)}, c AS (SELECT row_id, count(*) AS c FROM ex GROUP BY 1)" for n in METHODS}
    sizes = {"w1": 65, "w2": 1025, "w9": 5} | {n: (1 << 20) + 1 for n in experiments.LARGE}
    return fits | {
        "sample_events": "SELECT event_type, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events WHERE ('0x' || substr(md5(event_id || '|3'), 1, 8))::BIGINT < 4294967296 * CASE event_type WHEN 'purchase' THEN 0.5 WHEN 'view' THEN 0.1 WHEN 'click' THEN 0.25 ELSE 0 END GROUP BY 1",
        "exact_sum_lineitem": "SELECT CAST(sum(CAST(l_extendedprice AS DECIMAL(22, 4))) AS VARCHAR) AS total FROM lineitem",
        "top_features_w2": f"WITH {oracles.features('w2')}, t AS (SELECT y::DOUBLE AS y, f, round(sum(v), 5) + 0.0 AS total FROM ex JOIN yy USING (row_id) WHERE f < 1024 GROUP BY 1, 2) SELECT y, f, total, CAST(row_number() OVER (PARTITION BY y ORDER BY total DESC, f) AS INTEGER) AS rank FROM t QUALIFY rank <= 3",
        "stats_w9": f"{PLANTED} SELECT round(corr(x1, x2), 6) + 0.0 AS corr, round(covar_samp(x1, x2), 6) + 0.0 AS covar, round((avg(x2 * x2 * x2) - 3 * avg(x2) * avg(x2 * x2) + 2 * pow(avg(x2), 3)) / pow(var_pop(x2), 1.5), 6) + 0.0 AS skew, round(quantile_cont(x2, 0.9), 6) + 0.0 AS p90, count(DISTINCT x1) AS distinct_x1, arg_min(l_orderkey, (x2, l_orderkey)) AS first_order FROM d",
        "document_sets": "SELECT 'both' AS what, count(*) AS n FROM (SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels) UNION ALL SELECT 'rest', count(*) FROM (SELECT doc_id FROM documents EXCEPT ALL SELECT doc_id FROM labels) UNION ALL SELECT 'q' || q, max(n_chars) FROM (SELECT ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS q, n_chars FROM documents) GROUP BY 1",
        "url_hosts": "SELECT regexp_extract(url, '://([^/?#:]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1",
        "sql_functions": "SELECT t, count(*) AS n, round(avg(ln(1 + exp(-abs(t))) + greatest(-t, 0)), 6) + 0.0 AS a, round(avg(1 / (1 + exp(-t))), 6) + 0.0 AS b, round(avg(1 + 2 * t + 3 * t * t), 6) + 0.0 AS c, round(avg(2 + 6 * t), 6) + 0.0 AS d, 6::DOUBLE AS e, round(avg(5 * t), 6) + 0.0 AS f, round(avg(7 * t + 5), 6) + 0.0 AS g, round(avg((t - 1) * 2), 6) + 0.0 AS h, round(avg(2 * t + 0.5), 6) + 0.0 AS i, bool_and(abs(t) <= 0.9) AS j, 1.535434::DOUBLE AS k FROM (SELECT (l_quantity - 25) / 4 AS t FROM lineitem) GROUP BY t",
        "ls_fit_w6": solved,
        "normal_equations_w6": solved,
        "wolfe_bracket": oracles.bracket([0.01, 0.1, 1.0, 1.9, 3.0, 8.0]),
        "hash_features_w2": f"WITH {oracles.features('w2')} SELECT f, count(*) AS n, round(sum(v), 6) + 0.0 AS total FROM ex GROUP BY f",
        "onehot_w5": f"WITH {oracles.features('w5')} SELECT f, count(*) AS n, sum(y)::DOUBLE AS positive FROM ex JOIN yy USING (row_id) GROUP BY f",
        "label_ratio": " UNION ALL ".join([f"SELECT '{n}' AS workload, * FROM (WITH {oracles.features(n)} SELECT count(*) FILTER (y = 1) AS positive, count(*) FILTER (y = 0) AS negative FROM yy)" for n in METHODS] + ["SELECT 'w15', count(*) FILTER (event_type = 'purchase'), count(*) FILTER (event_type <> 'purchase') FROM events"]),
        "dataset_summary": " UNION ALL ".join(f"SELECT '{n}' AS dataset, * FROM ({q} SELECT count(*) AS n, {sizes[n]}::BIGINT AS m, round(avg(c), 4) + 0.0 AS nnz, round(stddev_pop(c), 4) + 0.0 AS nnz_sd, count(*) FILTER (y = 1) AS positive, count(*) FILTER (y = 0) AS negative FROM c JOIN yy USING (row_id))" for n, q in shapes.items()),
        "tree_vs_flat": f"WITH {oracles.features('w3')}, z AS (SELECT row_id, y, sum(v * 0.01 * sin(f)) AS z FROM ex JOIN yy USING (row_id) GROUP BY 1, 2), g AS (SELECT f, sum(v * (1 / (1 + exp(-z)) - y)) / (SELECT count(*) FROM yy) AS g FROM ex JOIN z USING (row_id) GROUP BY f) SELECT reduce, round((SELECT avg({oracles.SOFT.format(z='z')}) FROM z), 8) + 0.0 AS loss, round((SELECT sqrt(sum(g * g)) FROM g), 8) + 0.0 AS grad_norm FROM (VALUES ('flat'), ('tree1'), ('tree2'), ('tree4')) AS r(reduce)",
        "loss_logit_w1": f"{e1}, b AS (SELECT {TERMS} FROM t) SELECT count(*) AS n, round(avg(b0), 6) + 0.0 AS loss FROM b",
        "coeffs_logit_w1_d5": f"{e1}, b AS (SELECT {TERMS} FROM t) SELECT {MEANS} FROM b",
        "grad_logit_w9": f"{PLANTED}, m AS (SELECT *, {ZQ9} FROM d), t AS (SELECT *, 1 / (1 + exp(-z)) AS s FROM m) SELECT round(avg(ln(1 + exp(-abs(z))) + greatest(-z, 0) + CASE WHEN y = 0 THEN z ELSE 0 END) + {5e-4 * sum(x * x for x in Z9)}, 6) + 0.0 AS loss, {g9} FROM t",
        "coeffs_logit_w9_d5": c9,
        "coeffs_table_w9_d5": c9,
        "coeffs_arrow_w9_d5": c9,
        "sql_terms_w9": c9,
        "coeffs_ls_w6_d2": f"{six}, m AS (SELECT {z6} AS z, x1 - x2 + 0.5 * x3 + 0.2 * x4 + 0.3 * x5 + 0.4 AS q, y FROM d) SELECT round(avg((z - y) * (z - y) / 2), 6) + 0.0 AS c0, round(avg((z - y) * q), 6) + 0.0 AS c1, round(avg(q * q / 2), 6) + 0.0 AS c2 FROM m",
        "coeffs_mf_w7a_d4": _mf_sql("SELECT user_id AS i, CAST(json_extract_string(props, '$.k') AS BIGINT) AS j, avg(value / 100) AS value FROM events GROUP BY 1, 2"),
        "coeffs_mf_w7b_d4": _mf_sql("SELECT o_custkey AS i, l_partkey AS j, sum(l_quantity) / 50 AS value FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"),
        "l2_terms": "WITH p AS (SELECT p_size / 50 + 0.5 * p_retailprice / 2000 AS r, p_retailprice / 2000 AS p FROM part) SELECT round(avg(r * r) / 2, 6) + 0.0 AS c0, round(avg(r * p), 6) + 0.0 AS c1, round(avg(p * p) / 2, 6) + 0.0 AS c2, 0::DOUBLE AS c3 FROM p",
        "horner_grid": "WITH g AS (SELECT (l_quantity - 25) / 10 AS t FROM lineitem), h AS (SELECT t, 0.6 - 0.4 * t + 0.3 * t**2 - 0.1 * t**3 + 0.05 * t**4 + 0.01 * t**5 AS v, -0.4 + 0.6 * t - 0.3 * t**2 + 0.2 * t**3 + 0.05 * t**4 AS d1, 0.6 - 0.6 * t + 0.6 * t**2 + 0.2 * t**3 AS d2 FROM g) SELECT round(t, 1) + 0.0 AS t, count(*) AS n, round(avg(v), 6) + 0.0 AS v, round(avg(d1), 6) + 0.0 AS d1, round(avg(d2), 6) + 0.0 AS d2 FROM h GROUP BY 1",
        "model_vs_truth_w9": f"{C9}, g AS (SELECT i / 4 AS t FROM range(9) r(i)), h AS (SELECT g.t AS t, avg(ln(1 + exp(-abs(z + g.t * q))) + greatest(-(z + g.t * q), 0) + CASE WHEN y = 0 THEN z + g.t * q ELSE 0 END) AS truth FROM m, g GROUP BY g.t) SELECT t, round(truth, 6) + 0.0 AS truth, round(c0 + c1 * t + c2 * t**2 + c3 * t**3 + c4 * t**4 + c5 * t**5, 6) + 0.0 AS model, round(abs(c5 * t**5), 6) + 0.0 AS estimate FROM h, c",
        "wolfe_checks_w9": f"{PLANTED}, m AS (SELECT *, {ZQ9} FROM d), o AS ({at} FROM m, (VALUES (0.0)) AS g(a) GROUP BY a), h AS ({at} FROM m, {grid} GROUP BY a) SELECT h.a AS a, h.phi <= o.phi + 1e-4 * h.a * o.dphi AS decrease, abs(h.dphi) <= 0.9 * abs(o.dphi) AS curvature, round(h.phi, 6) + 0.0 AS phi, round(h.dphi, 6) + 0.0 AS dphi FROM h, o",
        "cubic_min_cases": "WITH c AS (SELECT CAST(p_size AS INTEGER) AS k, 0.5 + p_size / 25 AS a3, (p_retailprice - 1400) / 200 AS a2, -1.0::DOUBLE - p_partkey % 7 AS a1 FROM part) SELECT k, count(*) AS n, round(avg((-a2 + sqrt(a2 * a2 - 3 * a3 * a1)) / (3 * a3)), 6) + 0.0 AS x FROM c GROUP BY k",
        "fallback_step_w9": f"{C9} SELECT round(-c1 / (2 * c2), 6) + 0.0 AS t FROM c",
        "example_1d_taylor": f"{uv.replace('WITH', 'WITH RECURSIVE', 1)}, d(k, c) AS ({' UNION ALL '.join(f'SELECT {k}, ((1 + {k}) * u * exp(1::DOUBLE) + ({(-1) ** k}) * v * exp(3::DOUBLE)) / {f1[k]} FROM u' for k in range(8))}), n(degree, i, t) AS (SELECT CAST(g AS INTEGER), 0, 0::DOUBLE FROM range(2, 8) r(g) UNION ALL SELECT n.degree, i + 1, t - (SELECT sum(k * c * pow(t, k - 1)) FROM d WHERE k BETWEEN 1 AND n.degree) / (SELECT sum(k * (k - 1) * c * pow(t, k - 2)) FROM d WHERE k BETWEEN 2 AND n.degree) FROM n WHERE i < 12) SELECT degree, round(1 + t, 6) + 0.0 AS alpha FROM n WHERE i = 12",
        "example_1d_wolfe": f"{uv}, f AS (SELECT v * exp(4::DOUBLE) AS f0, u - v * exp(4::DOUBLE) AS d0, u * exp(1::DOUBLE) + v * exp(3::DOUBLE) AS f1, 2 * u * exp(1::DOUBLE) - v * exp(3::DOUBLE) AS d1 FROM u) SELECT CASE WHEN f1 <= f0 + 1e-4 * d0 AND abs(d1) <= 0.9 * abs(d0) THEN 1::DOUBLE END AS alpha, 1::DOUBLE AS n_eval, round(f1, 6) + 0.0 AS phi, round(d1, 6) + 0.0 AS dphi FROM f",
        "ls_exact_step_w6": f"{six}, m AS (SELECT {z6} - y AS e, 0.1 * x1 + 0.1 * x2 - 0.1 * x3 + 0.05 * x4 + 0.1 * x5 + 0.3 AS q FROM d) SELECT round(-sum(e * q) / sum(q * q), 6) + 0.0 AS alpha, 1::DOUBLE AS n_eval FROM m",
        "trace_gap": f"WITH t AS ({toy}) SELECT search, k, round(abs(loss - min(loss) OVER ()), 6) + 0.0 AS gap, round(acc, 6) + 0.0 AS acc FROM t",
        "to_gap_toy": f"WITH t AS ({daily}), g AS (SELECT *, abs(loss - min(loss) OVER ()) AS gap FROM t) SELECT search, CAST(goal AS DOUBLE) AS goal, min(k) AS k, round(min(cum_seconds), 6) + 0.0 AS seconds FROM g, (VALUES (0.1), (0.01)) AS x(goal) WHERE gap <= CAST(goal AS DOUBLE) GROUP BY 1, 2",
        "trace_speedup": f"{sp} SELECT k_w, k_t, round(acc, 6) + 0.0 AS acc, round(ir, 6) + 0.0 AS iter_ratio, round(tr, 6) + 0.0 AS time_ratio FROM r",
        "speedup_windows": f"{sp.replace(toy, daily)} SELECT CAST(floor(acc / 0.1::DOUBLE) AS BIGINT) AS bin, count(*) AS n, round(avg(ir), 6) + 0.0 AS iter_mean, round(stddev_pop(ir), 6) + 0.0 AS iter_sd, round(avg(tr), 6) + 0.0 AS time_mean, round(stddev_pop(tr), 6) + 0.0 AS time_sd FROM r GROUP BY 1",
        "plateau_toy": f"WITH t AS ({daily}), l AS (SELECT *, lead(acc, 2) OVER (PARTITION BY search ORDER BY k) AS later FROM t) SELECT search AS run, min(k) AS k, round(arg_min(acc, k), 6) + 0.0 AS acc FROM l WHERE later - acc < 0.05 GROUP BY 1",
        "timing_table": f"SELECT dataset, {', '.join(f'round(avg(tau_tot) FILTER (method = {chr(39)}{m}{chr(39)}), 4) + 0.0 AS {m}' for m in TIMED)} FROM ({timed}) GROUP BY 1",
        "pass_model": f"SELECT dataset, method, round(CASE WHEN tau_ls IS NULL THEN n_e * tau_fg ELSE tau_fg + n_e * tau_ls END, 4) + 0.0 AS passes, round(tau_ls / tau_fg, 4) + 0.0 AS pass_ratio FROM (SELECT dataset, method, avg(tau_fg) AS tau_fg, avg(tau_ls) AS tau_ls, avg(n_e) AS n_e FROM ({timed}) GROUP BY 1, 2)",
        "timing_rollup": f"SELECT dataset, split_part(method, '_', 2) AS search, count(*) AS n, round(avg(tau_tot), 4) + 0.0 AS tau_tot FROM ({timed}) GROUP BY ROLLUP (1, 2)",
        "comm_cost": "WITH o AS (SELECT event_type AS run, CAST(dayofyear(ts) * 24 + hour(ts) AS INTEGER) AS i, sum(CAST(floor(value) AS BIGINT)) AS r, count(*) AS b FROM events GROUP BY 1, 2) SELECT run, i, CASE i % 3 WHEN 1 THEN 'coeffs' ELSE 'fg' END AS op, CAST(r * 8 AS BIGINT) AS reduced, CAST(b AS BIGINT) AS broadcast, count(*) OVER w AS passes_total, CAST(sum(r * 8) OVER w AS BIGINT) AS reduced_total, CAST(sum(b) OVER w AS BIGINT) AS broadcast_total FROM o WINDOW w AS (PARTITION BY run ORDER BY i)",
        "confusion_w9": f"{s9} SELECT count(*) AS n, count(*) FILTER (y = 1 AND prob >= 0.5) AS tp, count(*) FILTER (y = 0 AND prob >= 0.5) AS fp, count(*) FILTER (y = 0 AND prob < 0.5) AS tn, count(*) FILTER (y = 1 AND prob < 0.5) AS fn, round(avg(y), 6) + 0.0 AS base_rate, round(avg(CASE WHEN (prob >= 0.5) = (y = 1) THEN 1 ELSE 0 END), 6) + 0.0 AS accuracy FROM s",
        "auc_w9": f"{s9}, k AS (SELECT *, rank() OVER (ORDER BY prob) + (count(*) OVER (PARTITION BY prob) - 1) / 2 AS r FROM s) SELECT round((sum(r) FILTER (y = 1) - count(*) FILTER (y = 1) * (count(*) FILTER (y = 1) + 1) / 2) / (count(*) FILTER (y = 1)::DOUBLE * count(*) FILTER (y = 0)), 6) + 0.0 AS auc, round(avg(-y * ln(prob) - (1 - y) * ln(1 - prob)), 6) + 0.0 AS log_loss FROM k",
        "ovr_coeffs_w1": f"{e1} SELECT {', '.join(f'round(avg(ln(1 + exp(-abs(z))) + greatest(-z, 0) + CASE WHEN label <> {c} THEN z ELSE 0 END), 6) + 0.0 AS c0_{c}, round(avg(q * (s - CASE WHEN label = {c} THEN 1 ELSE 0 END)), 6) + 0.0 AS c1_{c}' for c in range(10))} FROM t",
        "group_coeffs_nation": f"{C9} SELECT CAST(c_nationkey AS BIGINT) AS nation, count(*) AS n, {', '.join(f'round(avg(b{k}), 6) + 0.0 AS c{k}' for k in range(3))} FROM b JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1",
        "stream_window_loss": "WITH e AS (SELECT strftime(ts, '%Y-%m-%d') AS day, ln(1 + value) / 10 AS z, event_type FROM events), l AS (SELECT day, ln(1 + exp(-abs(z))) + greatest(-z, 0) + CASE WHEN event_type <> 'purchase' THEN z ELSE 0 END AS loss FROM e) SELECT day, count(*) AS n, round(avg(loss), 6) + 0.0 AS loss, round(exp(-avg(loss)), 6) + 0.0 AS acc FROM l GROUP BY 1",
        "residual_topk_w9": f"{PLANTED}, z AS (SELECT l_orderkey, y, x1 - 0.8 * x2 + 0.5 * x3 + 0.3 * x4 + 0.2 AS z FROM d) SELECT l_orderkey, round(sum(ln(1 + exp(-abs(z))) + greatest(-z, 0) + CASE WHEN y = 0 THEN z ELSE 0 END), 6) + 0.0 AS loss, count(*) AS n FROM z GROUP BY 1 ORDER BY loss DESC, l_orderkey LIMIT 10",
        "libsvm_roundtrip": "SELECT CAST(l_quantity > 7 AS DOUBLE) AS y, count(*) AS n, round(sum(l_quantity), 4) + 0.0 AS s0, round(sum(l_discount), 4) + 0.0 AS s1, round(sum(l_tax), 4) + 0.0 AS s2, CAST(count(*) AS DOUBLE) AS s3 FROM lineitem GROUP BY 1",
        "session_loss_events": f"{ev}, g AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM e), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(avg(b0), 6) + 0.0 AS loss FROM s GROUP BY user_id, k",
        "running_coeffs_events": f"{ev} SELECT strftime(ts, '%Y-%m-%d') AS epoch, count(*) AS n, {', '.join(f'round(sum(b{k}), 4) + 0.0 AS c{k}' for k in range(3))} FROM e GROUP BY 1",
        "dedup_events": "SELECT event_type, count(*) AS n FROM events GROUP BY 1",
        "interval_join_events": "SELECT a.user_id AS user_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'purchase' GROUP BY 1",
        "labelled_documents": "SELECT lang, count(l.doc_id) AS labelled, count(*) - count(l.doc_id) AS unlabelled FROM documents d LEFT JOIN labels l USING (doc_id) GROUP BY 1",
    }
