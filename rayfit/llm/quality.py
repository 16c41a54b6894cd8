"""Quality scores by random Fourier features, ridge regression and isotonic calibration.

Each text is reduced to the statistics of stats.py, standardised by the labelled rows. Cosines of random projections
approximate a Gaussian kernel on them; every partition sums its share of the normal equations for each fold of the rows, tasks
add these, and the driver solves them with a ridge (their size is fixed). Values of the labelled rows, each from the
equations of the other folds, are counted in fine bins with their labels and made monotone by pooling adjacent violators;
the resulting curve turns a value into a probability."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import stats
from .common import ship, slices, staged, vector_sum
from .textkit import Words

WIDTH = 192
RIDGE = 1e-3
BINS = 2000
SEED = 5
#: Parts of the labelled rows, by a hash of the key, for the curve.
FOLDS = 4
#: Weight of the kernel's distances: 1 / (GAMMA * statistics) is the squared bandwidth.
SPREAD = 0.35


def statistics(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, x array of statistics) for every row; zeros for null and empty texts."""
    ship(docs.sparkSession)

    def run(batches):
        for batch in batches:
            for low, high in slices(batch.column(1)):
                x = stats.of(Words(batch.column(1), low, high)).astype(np.float32)
                flat = pa.array(x.ravel())
                yield pa.record_batch([batch.column(0).slice(low, high - low), pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), flat)], ["key", "x"])

    out = docs.select(F.col(key).alias("key"), F.coalesce(F.col(text), F.lit("")).alias("text")).mapInArrow(run, f"key {dict(docs.dtypes)[key]}, x array<float>")
    return out.withColumnRenamed("key", key)


def matrix(column) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1).astype(float)


class Kernel:
    """Standardisation and random Fourier features."""

    def __init__(self, mean, scale, width=WIDTH, seed=SEED):
        g = np.random.default_rng(seed)
        self.mean, self.scale = mean, np.where(scale > 1e-9, scale, 1.0)
        self.w = g.normal(0, SPREAD, (len(mean), width))
        self.b = g.uniform(0, 2 * np.pi, width)

    def __call__(self, x):
        z = np.clip((x - self.mean) / self.scale, -6, 6)
        return np.concatenate([np.ones((len(x), 1)), z, np.sqrt(2 / len(self.b)) * np.cos(z @ self.w + self.b)], 1)


def pool(value: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """The nondecreasing sequence nearest to value in weighted least squares."""
    blocks: list[list[float]] = []
    for v, w in zip(value, weight, strict=True):
        blocks.append([v, w, 1])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            v2, w2, n2 = blocks.pop()
            v1, w1, n1 = blocks.pop()
            blocks.append([(v1 * w1 + v2 * w2) / (w1 + w2), w1 + w2, n1 + n2])
    return np.repeat([b[0] for b in blocks], [int(b[2]) for b in blocks])


class Model:
    def __init__(self, kernel, beta, at, height):
        self.kernel, self.beta, self.at, self.height = kernel, beta, at, height

    def raw(self, x):
        return self.kernel(x) @ self.beta

    def score(self, x):
        return np.interp(self.raw(x), self.at, self.height)


def _sums(labelled: DataFrame, kernel: Kernel) -> np.ndarray:
    """Of each fold, the products of all features and the label with one another."""
    size = 2 + len(kernel.mean) + len(kernel.b)

    def partial(batches):
        total = np.zeros((FOLDS, size, size))
        for batch in batches:
            if batch.num_rows:
                f, y, fold = kernel(matrix(batch.column(0))), batch.column(1).to_numpy().astype(float), batch.column(2).to_numpy()
                both = np.concatenate([f, y[:, None]], 1)
                for k in set(fold.tolist()):
                    total[k] += both[fold == k].T @ both[fold == k]
        return total.ravel()

    return vector_sum(labelled.select("x", "y", "fold"), partial, FOLDS * size * size).reshape(FOLDS, size, size)


def solved(sums: np.ndarray) -> np.ndarray:
    """Ridge coefficients from the products; zeros without rows."""
    a, b = sums[:-1, :-1], sums[:-1, -1]
    return np.linalg.solve(a + RIDGE * a[0, 0] * np.eye(len(a)), b) if a[0, 0] else np.zeros(len(b))


def fit(labelled: DataFrame) -> Model:
    """From (x, y, fold) rows, y 0 or 1. With no rows, every score is 0.5.

    The curve is fitted on values of rows that had no part in the coefficients that gave them: those of the other folds."""
    n = len(stats.NAMES)
    agg = labelled.select(F.posexplode("x").alias("i", "v")).groupBy("i").agg(F.avg("v").alias("m"), F.stddev_pop("v").alias("s")).collect()
    mean, scale = np.zeros(n), np.ones(n)
    for i, m, s in agg:
        mean[i], scale[i] = m, s
    kernel = Kernel(mean, scale)
    if not agg:
        return Model(kernel, np.zeros(1 + n + WIDTH), np.array([0.0]), np.array([0.5]))
    sums = _sums(labelled, kernel)
    beta, others = solved(sums.sum(0)), np.stack([solved(sums.sum(0) - own) for own in sums])

    def values(batches):
        for batch in batches:
            if batch.num_rows:
                value = (kernel(matrix(batch.column(0))) * others[batch.column(2).to_numpy()]).sum(1)
                at = np.clip(np.floor((value + 0.5) * BINS / 2), 0, BINS - 1).astype(np.int64)
                yield pa.record_batch([pa.array(at), batch.column(1)], ["at", "y"])

    bins = labelled.select("x", F.col("y").cast("double").alias("y"), "fold").mapInArrow(values, "at long, y double").groupBy("at").agg(F.avg("y").alias("y"), F.count("*").alias("n")).toArrow().to_pandas().sort_values("at")
    height = pool(bins["y"].to_numpy(), bins["n"].to_numpy(float))
    return Model(kernel, beta, (bins["at"].to_numpy() + 0.5) * 2 / BINS - 0.5, height)


def scored(features: DataFrame, model: Model, key: str = "doc_id") -> DataFrame:
    """(key, score) for every row of (key, x)."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                yield pa.record_batch([batch.column(0), pa.array(np.clip(model.score(matrix(batch.column(1))), 0, 1))], ["key", "score"])

    return features.select(F.col(key).alias("key"), "x").mapInArrow(run, f"key {dict(features.dtypes)[key]}, score double").withColumnRenamed("key", key)


def classify(docs: DataFrame, labels: DataFrame, train, key: str = "doc_id", text: str = "text", target: str = "quality") -> DataFrame:
    """(key, score, predicted) for every row of docs; labels (key, target) count where train, a column of key, holds.

    A null label is no label; of several for one key, the largest holds."""
    x = staged(statistics(docs, key, text), "statistics")
    known = labels.filter(F.col(target).isNotNull() & train).groupBy(key).agg(F.max(target).alias("y"))
    fold = F.pmod(F.xxhash64(key, F.lit(7)), F.lit(FOLDS)).cast("int")
    labelled = staged(x.join(known, key).select("x", F.col("y").cast("double").alias("y"), fold.alias("fold")), "labelled")
    out = scored(x, fit(labelled), key)
    return out.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))
