"""Measures of cost and accuracy on traces and operation logs, as DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

RUN = ["dataset", "method", "search"]


def reference_loss(traces: DataFrame) -> DataFrame:
    """The least loss that any run on a dataset met."""
    return traces.groupBy("dataset").agg(F.min("loss").alias("best"))


def gap(traces: DataFrame) -> DataFrame:
    """Traces with gap = loss - best, its logarithm, and exp(-loss)."""
    out = traces.join(F.broadcast(reference_loss(traces)), "dataset")
    out = out.withColumn("gap", F.abs(F.col("loss") - F.col("best")))
    return out.withColumn("log_gap", F.when(F.col("gap") > 0, F.log10("gap"))).withColumn("acc", F.exp(-F.col("loss")))


def to_gap(traces: DataFrame, gaps=(1e-3, 1e-6, 1e-10)) -> DataFrame:
    """The first iteration, and its seconds, at which a run is within each gap."""
    out = gap(traces).withColumn("goal", F.explode(F.array(*map(F.lit, gaps)))).filter("gap <= goal")
    return out.groupBy(*RUN, "goal").agg(F.min("k").alias("k"), F.min("cum_seconds").alias("seconds"))


def timing(trace: DataFrame, ops: DataFrame) -> DataFrame:
    """Mean and deviation of seconds by iteration and by kind of pass, and evaluations for each search, by run.

    Passes marked warm (the first of their kind) and the iteration that holds them are left out where others follow."""
    later = F.when(F.max("k").over(Window.partitionBy("run")) > 1, F.col("k") > 1).otherwise(F.col("k") > 0)
    own = trace.withColumn("counts", later).groupBy("run").agg(F.avg(F.when(F.col("counts"), F.col("seconds"))).alias("tau_tot"), F.stddev_samp(F.when(F.col("counts"), F.col("seconds"))).alias("tau_tot_sd"), (F.sum("n_eval") / F.count_if(F.col("k") > 0)).alias("n_e"))
    kind = F.when(F.col("op") == "coeffs", "ls").otherwise("fg")
    w = Window.partitionBy("run", kind)
    ops = ops.withColumns({"kind": kind, "few": F.count_if(~F.col("warm")).over(w) == 0}).filter("few or not warm")
    fg, ls = F.col("kind") == "fg", F.col("kind") == "ls"
    by = ops.groupBy("run").agg(*(f(F.when(c, F.col("seconds"))).alias(n) for c, n0 in ((fg, "tau_fg"), (ls, "tau_ls")) for f, n in ((F.avg, n0), (F.stddev_samp, n0 + "_sd"))))
    return own.join(by, "run", "left")


def pass_model(timing: DataFrame) -> DataFrame:
    """Seconds of an iteration if passes were all: a gradient and n_e coefficient passes, or n_e fused ones; and tau_ls / tau_fg."""
    taylor = F.col("tau_ls").isNotNull()
    passes = F.when(taylor, F.col("tau_fg") + F.col("n_e") * F.col("tau_ls")).otherwise(F.col("n_e") * F.col("tau_fg"))
    return timing.withColumn("passes", passes).withColumn("pass_ratio", F.col("tau_ls") / F.col("tau_fg"))


def communication(ops: DataFrame, partitions: int = 1) -> DataFrame:
    """Passes, doubles reduced (each from every partition) and broadcast, by run, and their running totals."""
    w = Window.partitionBy("run").orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    return ops.select("run", "i", "op", (F.col("doubles_reduced") * partitions).alias("reduced"), F.col("doubles_broadcast").alias("broadcast")).withColumns({"passes_total": F.count("*").over(w), "reduced_total": F.sum("reduced").over(w), "broadcast_total": F.sum("broadcast").over(w)})


def speedup(base: DataFrame, other: DataFrame) -> DataFrame:
    """For each iterate of base, the first of other that is at least as accurate: ratios of iterations and of seconds.

    Both are (dataset, k, acc, cum_seconds). The running best of other is ordered by accuracy, so one window and no
    pairing of all iterates finds it."""
    best = other.withColumn("top", F.max("acc").over(Window.partitionBy("dataset").orderBy("k")))
    best = best.withColumn("before", F.lag("top").over(Window.partitionBy("dataset").orderBy("k"))).filter("before is null or top > before")
    marks = best.select("dataset", F.col("top").alias("acc"), F.struct(F.col("k").alias("k_o"), F.col("cum_seconds").alias("s_o")).alias("o"), F.lit(None).cast("int").alias("k"), F.lit(None).cast("double").alias("s"), F.lit(1).alias("side"))
    asked = base.select("dataset", "acc", F.lit(None).cast(marks.schema["o"].dataType).alias("o"), "k", F.col("cum_seconds").alias("s"), F.lit(0).alias("side"))
    w = Window.partitionBy("dataset").orderBy(F.desc("acc"), F.desc("side")).rowsBetween(Window.unboundedPreceding, 0)
    out = marks.unionByName(asked).withColumn("o", F.last("o", ignorenulls=True).over(w)).filter("side = 0 and o is not null")
    return out.filter("k > 0 and o.k_o > 0").select("dataset", "acc", F.col("k").alias("k_w"), F.col("o.k_o").alias("k_t"), (F.col("k") / F.col("o.k_o")).alias("iter_ratio"), (F.col("s") / F.col("o.s_o")).alias("time_ratio"))


def windowed(speedups: DataFrame, width: float = 0.02) -> DataFrame:
    """Mean and deviation of the ratios in windows of accuracy."""
    bin_ = F.floor(F.col("acc") / width).cast("long")
    return speedups.groupBy("dataset", bin_.alias("bin")).agg(F.avg("iter_ratio").alias("iter_mean"), F.stddev_pop("iter_ratio").alias("iter_sd"), F.avg("time_ratio").alias("time_mean"), F.stddev_pop("time_ratio").alias("time_sd"), F.count("*").alias("n"))


def plateau(trace: DataFrame, eps: float = 1e-3, span: int = 5) -> DataFrame:
    """The first iterate of each run from which accuracy gains less than eps over the next span iterates."""
    w = Window.partitionBy("run").orderBy("k")
    out = trace.withColumn("later", F.lead("acc", span).over(w)).filter(F.col("later") - F.col("acc") < eps)
    return out.groupBy("run").agg(F.min_by("acc", "k").alias("acc"), F.min("k").alias("k"))


def events(trace: DataFrame) -> DataFrame:
    return trace.groupBy("run").agg(F.sum("restarts").alias("restarts"), F.sum("fallbacks").alias("fallbacks"), F.sum("guards").alias("guards"), F.max("k").alias("iterations"))


def step_accuracy(problem, w, p, history: list, reference: float, degree: int = 1) -> list[dict]:
    """Distance of each visited step to the reference, and the share of the slope that is left there."""
    start = abs(problem.coefficients(w, p, 0.0, 1).c[1])
    return [{"alpha": h[0], "distance": abs(h[0] - reference), "slope_left": abs(problem.coefficients(w, p, h[0], 1).c[1]) / start} for h in history]


def model_error(problem, w, p, model, steps) -> list[dict]:
    """True loss against the model at alpha + t, and the estimate of the difference."""
    return [{"t": t, "truth": (f := problem.value_and_gradient(w + (model.alpha + t) * p)[0]), "model": model.value(t), "error": f - model.value(t), "estimate": model.error_estimate(t)} for t in steps]


def classify(scored: DataFrame, threshold: float = 0.5) -> DataFrame:
    """One row: n, base rate, accuracy, confusion counts, log loss and AUC of (y, prob); ties in prob share their rank.

    Ranks come from counts by distinct score, summed by a window over score bands, so no single task sorts all rows."""
    y = F.when(F.col("y") != 0, 1.0).otherwise(0.0)
    p = F.least(F.greatest("prob", F.lit(1e-15)), F.lit(1 - 1e-15))
    basic = scored.agg(F.count("*").alias("n"), F.avg(y).alias("base_rate"), F.avg(((F.col("prob") >= threshold).cast("double") == y).cast("double")).alias("accuracy"), *(F.count_if((y == a) & ((F.col("prob") >= threshold) == bool(b))).alias(f"{'t' if a == b else 'f'}{'p' if b else 'n'}") for a in (0, 1) for b in (0, 1)), F.avg(-y * F.log(p) - (1 - y) * F.log(1 - p)).alias("log_loss"))
    counts = scored.groupBy("prob").agg(F.sum(y).alias("pos"), F.sum(1 - y).alias("neg")).withColumn("band", F.floor(F.col("prob") * 1024).cast("int"))
    bands = counts.groupBy("band").agg(F.sum("neg").alias("neg")).withColumn("below", F.coalesce(F.sum("neg").over(Window.orderBy("band").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))  # 1,025 rows
    inner = F.coalesce(F.sum("neg").over(Window.partitionBy("band").orderBy("prob").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    auc = counts.withColumn("inner", inner).join(F.broadcast(bands.select("band", "below")), "band").agg((F.sum(F.col("pos") * (F.col("below") + F.col("inner") + F.col("neg") / 2)) / F.nullif(F.sum("pos") * F.sum("neg"), F.lit(0.0))).alias("auc"))
    return basic.crossJoin(auc)


def summary(data) -> DataFrame:
    """Rows, parameters, nonzeros by row, positive and negative labels."""
    size = {"narrow": F.lit(data.m), "dense": F.size("x") if data.kind == "dense" else None, "sparse": F.size("idx") if data.kind == "sparse" else None}[data.kind]
    return data.df.agg(F.lit(data.name).alias("dataset"), F.count("*").alias("n"), F.lit(data.m).cast("long").alias("m"), F.avg(size).alias("nnz"), F.stddev_pop(size).alias("nnz_sd"), F.count_if(F.col("y") != 0).alias("positive"), F.count_if(F.col("y") == 0).alias("negative"))


def normal_equations(data) -> "np.ndarray":
    """Least squares weights of narrow rows from one pass of m (m + 3) / 2 sums."""
    import numpy as np

    x = data.features
    pairs = [(i, j) for i in range(len(x)) for j in range(i, len(x))]
    row = data.df.agg(*(F.sum(F.col(x[i]) * F.col(x[j])) for i, j in pairs), *(F.sum(F.col(c) * F.col("y")) for c in x)).first()
    a = np.zeros((len(x), len(x)))
    for (i, j), v in zip(pairs, row, strict=False):
        a[i, j] = a[j, i] = v or 0.0
    return np.linalg.lstsq(a, np.array([v or 0.0 for v in row[len(pairs) :]]), rcond=None)[0]


def exact_sum(df: DataFrame, column: str, digits: int = 6) -> DataFrame:
    """The sum of a column in decimals of so many digits, which no order of the rows changes."""
    return df.agg(F.sum(F.col(column).cast(f"decimal({min(38, 18 + digits)},{digits})")).alias("total"))


def top_by_group(df: DataFrame, group: str, order: str, tie: str, k: int) -> DataFrame:
    """The k rows of each group with the largest values, ties to the smaller tie column; partial tops come before the shuffle."""
    w = Window.partitionBy(group).orderBy(F.desc(order), tie)
    return df.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
