"""Learning with parameters as a table (f, w, p), for models too large for the driver.

Margins are an equi-join of exploded features with the parameters and a sum by row; the constant feature never explodes
but comes as a number. Vectors never leave the cluster: norms, dot products and penalties are aggregates."""

from __future__ import annotations

import os
import tempfile
import uuid

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .losses import Loss
from .taylor import TaylorModel, taylor_line_search


def margins(exploded: DataFrame, labels: DataFrame, params: DataFrame, bias: tuple[float, float] = (0.0, 0.0)) -> DataFrame:
    """(row_id, y, z, q); rows without any feature have the bias alone."""
    own = exploded.join(params.select("f", "w", "p"), "f").groupBy("row_id").agg(F.sum(F.col("v") * F.col("w")).alias("z"), F.sum(F.col("v") * F.col("p")).alias("q"))
    return labels.join(own, "row_id", "left").select("row_id", "y", (F.coalesce("z", F.lit(0.0)) + bias[0]).alias("z"), (F.coalesce("q", F.lit(0.0)) + bias[1]).alias("q"))


def coefficients(held: DataFrame, params: DataFrame, loss: Loss, degree: int, alpha: float = 0.0, lam: float = 0.0, bias: tuple[float, float] = (0.0, 0.0)) -> TaylorModel:
    """The model at alpha of the ray from (y, z, q) rows and the parameter table's penalty."""
    z = F.col("z") + F.lit(float(alpha)) * F.col("q")
    row = held.select("y", z.alias("z"), "q").agg(F.count("*"), *(F.sum(t) for t in loss.taylor_terms(F.col("z"), F.col("q"), F.col("y"), degree))).first()
    r = F.col("w") + F.lit(float(alpha)) * F.col("p")
    pen = params.agg(F.sum(r * r), F.sum(r * F.col("p")), F.sum(F.col("p") * F.col("p"))).first()
    b = bias[0] + alpha * bias[1]
    pen = [(pen[0] or 0.0) + b * b, (pen[1] or 0.0) + b * bias[1], (pen[2] or 0.0) + bias[1] ** 2]
    c = np.array([x or 0.0 for x in row[1:]]) / max(1, row[0])
    c += np.array(([lam / 2 * pen[0], lam * pen[1], lam / 2 * pen[2]] + [0.0] * degree)[: degree + 1])
    return TaylorModel(c, alpha, loss.exact_degree is not None and degree >= max(2, loss.exact_degree))


def gradient(exploded: DataFrame, held: DataFrame, params: DataFrame, loss: Loss, n: int, lam: float = 0.0) -> DataFrame:
    """(f, g) for every parameter of the table; features that no row has get the penalty's part."""
    slope = held.select("row_id", (loss.slope_term(F.col("z"), F.col("y")) / n).alias("s"))
    own = exploded.join(slope, "row_id").groupBy("f").agg(F.sum(F.col("v") * F.col("s")).alias("s"))
    return params.join(own, "f", "left").select("f", (F.coalesce("s", F.lit(0.0)) + lam * F.col("w")).alias("g"))


def moved(params: DataFrame, alpha: float) -> DataFrame:
    return params.withColumn("w", F.col("w") + F.lit(float(alpha)) * F.col("p"))


def dots(basis: DataFrame, columns: list[str]) -> np.ndarray:
    """All dot products of the columns of a table of vectors, in one aggregate."""
    k = len(columns)
    row = basis.agg(*(F.sum(F.col(columns[i]) * F.col(columns[j])) for i in range(k) for j in range(i, k))).first()
    out, at = np.zeros((k, k)), 0
    for i in range(k):
        for j in range(i, k):
            out[i, j] = out[j, i] = row[at] or 0.0
            at += 1
    return out


def two_loop(basis: DataFrame, pairs: int) -> DataFrame:
    """(f, p): the limited-memory direction from a table f, s1.., y1.., g, without a vector on the driver."""
    from .optim import two_loop_dots

    names = [f"s{i + 1}" for i in range(pairs)] + [f"y{i + 1}" for i in range(pairs)] + ["g"]
    d = two_loop_dots(dots(basis, names), pairs)
    p = F.lit(0.0)
    for x, c in zip(d, names, strict=True):
        p = p + F.lit(float(x)) * F.col(c)
    return basis.select("f", p.alias("p"))


def fresh_path(spark, name: str) -> str:
    """A new path in the session's shared checkpoint folder; in a folder of this process only where none is set (tests in one JVM)."""
    at = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not at and not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    at = at or f"file://{tempfile.gettempdir()}/rayfit-{os.getpid()}"
    return f"{at.rstrip('/')}/rayfit/{name}-{uuid.uuid4().hex}"


def staged(df: DataFrame) -> DataFrame:
    """df written to the shared folder and read again, so that iterations do not lengthen the plan and a lost executor costs
    no earlier iteration."""
    spark, path = df.sparkSession, fresh_path(df.sparkSession, "state")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def forget(*held: DataFrame) -> None:
    """Deletes the files of staged tables that no later plan reads."""
    for df in held:
        spark = df.sparkSession
        jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
            if "/rayfit/state-" in folder:
                path = jvm.org.apache.hadoop.fs.Path(folder)
                path.getFileSystem(conf).delete(path, True)


def minimize(exploded: DataFrame, labels: DataFrame, loss: Loss, lam: float = 0.0, max_iter: int = 20, degree: int = 5, theta: float = 1e-4, history: int = 5, grad_tol: float = 1e-10) -> tuple[DataFrame, float, list[dict]]:
    """L-BFGS with Taylor searches where weights, gradient and history are columns of one table (f, w, g, s1.., y1..).

    exploded is (row_id, f, v) without the constant feature, labels (row_id, y). Returns (f, w), the weight of the constant
    and a trace. The driver holds the dot products of 2 * history + 1 vectors and the numbers of the constant feature. An
    iteration joins rows and parameters twice (margins of weights and direction, gradient); expansions of a search only
    sum the kept margins. Features that no row has keep weight 0. Without rows the trace is empty."""
    n = labels.count()
    state = exploded.select("f").distinct().withColumn("w", F.lit(0.0))
    if not n:
        return state, 0.0, []
    bias, pairs, trace = {"w": 0.0}, 0, []
    held = labels.select("row_id", "y", F.lit(0.0).alias("z"))

    def graded(state: DataFrame, held: DataFrame) -> tuple[DataFrame, float, float]:
        """The table with its gradient as column h, the constant's gradient, and the mean loss without the penalty."""
        value, slope = held.agg(F.avg(loss.value_term(F.col("z"), F.col("y"))), F.avg(loss.slope_term(F.col("z"), F.col("y")))).first()
        out = state.join(gradient(exploded, held, state, loss, n, lam).withColumnRenamed("g", "h"), "f")
        return out, slope + lam * bias["w"], value

    state, bias["g"], value = graded(state, held)
    state = staged(state.withColumnRenamed("h", "g"))
    for k in range(max_iter + 1):
        names = [f"s{i + 1}" for i in range(pairs)] + [f"y{i + 1}" for i in range(pairs)] + ["g", "w"]
        own = np.array([bias[c] for c in names])
        gram = dots(state, names) + np.outer(own, own)
        grad_norm = float(np.sqrt(gram[-2, -2]))
        trace.append({"k": k, "loss": float(value + lam / 2 * gram[-1, -1]), "grad_norm": grad_norm, "alpha": float(step.alpha) if k else 0.0, "n_eval": step.n_eval if k else 0})
        if k == max_iter or grad_norm <= grad_tol:
            break
        good = [i for i in range(pairs) if gram[i, pairs + i] > 1e-16 * gram[pairs + i, pairs + i]]
        at = good + [pairs + i for i in good] + [2 * pairs]
        weights = _direction(gram[np.ix_(at, at)], len(good))
        basis = [names[i] for i in at]
        p = F.lit(0.0)
        for x, c in zip(weights, basis, strict=True):
            p = p + F.lit(float(x)) * F.col(c)
        bias["p"] = float(sum(x * bias[c] for x, c in zip(weights, basis, strict=True)))
        before, state = state, staged(state.withColumn("p", p))
        forget(before)
        rays = staged(margins(exploded, labels, state, (bias["w"], bias["p"])))
        step = taylor_line_search(lambda a: coefficients(rays, state, loss, degree, a, lam, (bias["w"], bias["p"])), 1.0, theta)  # noqa: B023
        # the pair of this step comes last; of the earlier ones the newest good history - 1 stay, in order
        kept = good[len(good) - min(len(good), history - 1) :]
        old, bias["w"] = dict(bias), bias["w"] + step.alpha * bias["p"]
        after, slope, value = graded(moved(state, step.alpha), rays.select("row_id", "y", (F.col("z") + F.lit(step.alpha) * F.col("q")).alias("z")))
        cols, bias, pairs = ["f", "w", F.col("h").alias("g")], {"w": bias["w"], "g": slope}, len(kept) + 1
        for j, i in enumerate(kept, 1):
            for c in "sy":
                cols.append(F.col(f"{c}{i + 1}").alias(f"{c}{j}"))
                bias[f"{c}{j}"] = old[f"{c}{i + 1}"]
        cols += [(F.lit(step.alpha) * F.col("p")).alias(f"s{pairs}"), (F.col("h") - F.col("g")).alias(f"y{pairs}")]
        bias |= {f"s{pairs}": step.alpha * old["p"], f"y{pairs}": slope - old["g"]}
        before, state = state, staged(after.select(*cols))
        forget(before, rays)
    return state.select("f", "w"), bias["w"], trace


def _direction(gram: np.ndarray, pairs: int) -> np.ndarray:
    """Coefficients of the direction; steepest descent where the two loops do not lead downhill."""
    from .optim import two_loop_dots

    d = two_loop_dots(gram, pairs)
    return d if gram[-1] @ d < 0 else np.r_[np.zeros(2 * pairs), -1.0]
