"""Instance tables and the passes over them: loss, gradient and Taylor coefficients.

Plans: narrow columns with weights as literals, all in generated code (N); arrays or sparse pairs with broadcast vectors in
Arrow batches (V); parameters as a table, joined to exploded features (T, in tables.py)."""

from __future__ import annotations

import threading
import time
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .losses import L2, Loss
from .ship import ship
from .taylor import TaylorModel

#: Doubles of a gradient that travel and are summed as one value.
BLOCK = 1 << 16
#: Above so many doubles of all partitions together a gradient is not gathered as whole vectors of all partitions.
FLAT_LIMIT = 1 << 22
#: Values of a packed row, and partitions whose vectors are summed by one level of a tree.
PACK, ONE_LEVEL = 1 << 19, 64
#: Lets Spark cut the partitions of a persisted plan to its size; otherwise they are as many as a shuffle has.
ADAPTS = "spark.sql.optimizer.canChangeCachedPlanOutputPartitioning"


#: Packed rows, of up to 4 MB each, that are sent to a worker at once; Spark's own number would hold a task's whole input in one batch.
SENT, _RECORDS = "2", "spark.sql.execution.arrow.maxRecordsPerBatch"
_small = {"lock": threading.Lock(), "inside": 0, "before": None}


@contextmanager
def small_batches(spark, packed: bool):
    """For passes over packed rows, also for some at once: the first one in sets, the last one out sets back."""
    if not packed:
        yield
        return
    with _small["lock"]:
        if not _small["inside"]:
            _small["before"] = spark.conf.get(_RECORDS)
            spark.conf.set(_RECORDS, SENT)
        _small["inside"] += 1
    try:
        yield
    finally:
        with _small["lock"]:
            _small["inside"] -= 1
            if not _small["inside"]:
                spark.conf.set(_RECORDS, _small["before"])


def kept(df: DataFrame) -> DataFrame:
    """Persisted in partitions of its own size."""
    conf = df.sparkSession.conf
    before = conf.get(ADAPTS)
    conf.set(ADAPTS, "true")
    try:
        return df.persist(StorageLevel.MEMORY_AND_DISK)
    finally:
        conf.set(ADAPTS, before)


@dataclass
class Instances:
    """df with label column y and features: names of columns (narrow), 'x' (dense) or 'idx' and 'val' (sparse, m given)."""

    df: DataFrame
    m: int
    features: list[str] | None = None
    kind: str = "narrow"
    name: str = ""
    n: int | None = None
    parts: int = 1
    packed: DataFrame | None = None
    #: Every value of val is 1, as in one-hot rows, so that packing need not read them.
    ones: bool = False

    def count(self) -> int:
        """Rows, and along with them the partitions that hold some; with persisted rows this fills the cache."""
        if self.n is None:
            held, rows = (self.df, F.count("*")) if self.packed is None else (self.packed, F.coalesce(F.sum("n"), F.lit(0)))
            row = held.withColumn("part", F.spark_partition_id()).agg(rows, F.max("part")).first()
            self.n, self.parts = row[0], (row[1] or 0) + 1
        return self.n

    def lanes(self) -> int:
        """Tasks of a pass, and so vectors of a gradient."""
        return self.parts if self.packed is None else min(self.parts, self.df.sparkSession.sparkContext.defaultParallelism)

    def persist(self) -> Instances:
        """Keeps narrow rows as they are; of arrays, many rows as one row of bytes, which passes read without a copy of each value."""
        if self.kind == "narrow":
            self.df = kept(self.df)
        else:
            ship(self.df.sparkSession)
            self.packed = kept((self.df.select("y", "idx") if self.ones else self.arrays()).mapInArrow(_packer(self.kind), PACKED))
        return self

    def unpersist(self) -> None:
        if self.packed is not None:
            self.packed.unpersist()
            self.packed = None
        self.df.unpersist()

    def arrays(self) -> DataFrame:
        return self.df.select("y", *(["x"] if self.kind == "dense" else ["idx", "val"]))

    def minibatch(self, fraction: float, seed: int, key: str) -> Instances:
        """The rows whose hash of key falls into the seed's share; a table partitioned by that hash reads only its files."""
        buckets = max(1, round(1 / fraction))
        return Instances(self.df.filter(F.pmod(F.xxhash64(key), F.lit(buckets)) == seed % buckets), self.m, self.features, self.kind, self.name)

    def validate(self) -> dict:
        """Counts of rows that no learner should see: nulls, non-finite numbers, indices out of range or order."""
        bad_number = lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))
        checks = {"y": bad_number(F.col("y"))}
        if self.kind == "narrow":
            checks |= {c: bad_number(F.col(c)) for c in self.features}
        elif self.kind == "dense":
            checks["x"] = F.col("x").isNull() | (F.size("x") != self.m) | F.exists("x", bad_number)
        else:
            rising = F.size(F.array_distinct("idx")) == F.size("idx")
            checks["idx"] = F.col("idx").isNull() | (F.size("idx") != F.size("val")) | F.exists("idx", lambda i: i.isNull() | (i < 0) | (i >= self.m)) | ~rising | (F.array_sort("idx") != F.col("idx"))
            checks["val"] = F.col("val").isNull() | F.exists("val", bad_number)
        return self.df.agg(*(F.count_if(F.coalesce(c, F.lit(True))).alias(k) for k, c in checks.items())).first().asDict()


@dataclass
class Op:
    op: str
    seconds: float
    reduced: int
    broadcast: int
    #: The first pass of its kind, which starts workers and compiles code.
    warm: bool = False


def _rows(batch, kind: str):
    """Arrays of a batch (y first): dense matrix, or (values of each row, idx, val); without val, they are ones."""
    y = batch.column(0).to_numpy(zero_copy_only=False).astype(float)
    if kind == "dense":
        return y, batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(y), -1)
    idx = batch.column(1)
    size = np.diff(idx.offsets.to_numpy())
    return y, (size, idx.flatten().to_numpy(zero_copy_only=False), batch.column(2).flatten().to_numpy(zero_copy_only=False) if batch.num_columns > 2 else None)


PACKED = "n int, y binary, size binary, idx binary, val binary"


def _packer(kind: str):
    """Rows to rows of bytes: labels, and the values of up to PACK of them (one row's at least) with their places.

    Labels 0 and 1 take a byte, equal sizes are written once, and values of sparse rows that are all 1 not at all."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            y, x = _rows(batch, kind)
            if kind == "dense":
                size, idx, val = np.full(len(y), x.shape[1]), np.empty(0, np.int32), x.astype(float).ravel()
            else:
                size, idx, val = x[0], x[1].astype(np.int32), np.empty(0) if x[2] is None or (x[2] == 1).all() else x[2].astype(float)
            ones = kind == "sparse" and not len(val)
            if ((y == 0) | (y == 1)).all():
                y = y.astype(np.uint8)
            ends = np.cumsum(size)
            cuts = np.r_[0, np.flatnonzero(np.diff((ends - 1) // PACK)) + 1, len(y)]
            for a, b in zip(cuts[:-1], cuts[1:]):
                low, high = ends[a] - size[a], ends[b - 1]
                sizes = size[a : a + 1] if (size[a:b] == size[a]).all() else size[a:b]
                blobs = (y[a:b], sizes.astype(np.int32), idx[low:high], val if ones else val[low:high])
                yield pa.record_batch([pa.array([b - a], pa.int32()), *(pa.array([v.tobytes()], pa.binary()) for v in blobs)], ["n", "y", "size", "idx", "val"])

    return run


def _batches(batches, kind: str, packed: bool):
    """(labels, features) of batches of rows, or of rows of bytes; no values of sparse rows stand for ones."""
    for batch in batches:
        if batch.num_rows and not packed:
            yield _rows(batch, kind)
        elif batch.num_rows:
            for k in range(batch.num_rows):
                n, blobs = batch.column("n")[k].as_py(), {c: batch.column(c)[k].as_buffer() for c in ("y", "size", "idx", "val")}
                y = np.frombuffer(blobs["y"], np.uint8 if len(blobs["y"]) == n else float).astype(float)
                size, idx, val = (np.frombuffer(blobs[c], t) for c, t in (("size", np.int32), ("idx", np.int32), ("val", float)))
                size = np.full(n, size[0]) if len(size) < n else size
                yield y, val.reshape(len(y), -1) if kind == "dense" else (size, idx.astype(np.intp), val if len(val) else None)


def _dot(x, w: np.ndarray) -> np.ndarray:
    if isinstance(x, np.ndarray):
        return x @ w
    size, idx, val = x
    inside = len(idx) and idx.min() >= 0 and idx.max() < len(w)
    terms = w.take(idx, mode="clip") if inside else w[idx]  # the quicker one does not check places
    if val is not None:
        terms *= val
    if size.all():
        return np.add.reduceat(terms, np.cumsum(size, dtype=np.int64) - size)
    return np.bincount(np.repeat(np.arange(len(size)), size), weights=terms, minlength=len(size))


def _add_weighted(total: np.ndarray, x, s: np.ndarray) -> None:
    """Adds the rows times s to total; a few values into a long vector one by one, without another vector as long."""
    if isinstance(x, np.ndarray):
        total += s @ x
        return
    size, idx, val = x
    terms = np.repeat(s, size)
    if val is not None:
        terms *= val
    if len(total) <= 2 * len(idx):
        total += np.bincount(idx, weights=terms, minlength=len(total))
    else:
        np.add.at(total, idx, terms)


def _add_blocks(table: pa.Table) -> pa.Table:
    total = sum(np.frombuffer(b) for b in table["part"].to_pylist())
    return pa.table({"block": table["block"].slice(0, 1), "lane": table["lane"].slice(0, 1), "part": pa.array([total.tobytes()], pa.binary())})


def tree_sum(blocks: DataFrame, levels: int, parts: int) -> DataFrame:
    """(block, part) sums of (block, lane, part) rows in so many levels; each cuts the lanes to about parts^(1 - l/levels)."""
    for level in range(1, levels + 1):
        lanes = max(1, round(parts ** (1 - level / levels)))
        blocks = blocks.withColumn("lane", (F.col("lane") % lanes).cast("int")).groupBy("block", "lane").applyInArrow(_add_blocks, "block int, lane int, part binary")
    return blocks


@dataclass
class Problem:
    """Mean loss over instances plus a penalty, with every pass timed and counted in ops."""

    data: Instances
    loss: Loss
    lam: float = 0.0
    regularize_bias: bool = True
    reduce: str = "auto"
    levels: int | None = None
    cached: bool = False
    ops: list = field(default_factory=list)

    def __post_init__(self):
        self.penalty = L2(self.lam, self.regularize_bias)
        self._margins = self._sent = None

    @property
    def m(self) -> int:
        return self.data.m

    def _timed(self, op, began, reduced, broadcast):
        self.ops.append(Op(op, time.perf_counter() - began, reduced, broadcast, all((o.op == "coeffs") != (op == "coeffs") for o in self.ops)))

    def _columns(self, w):
        z = F.lit(0.0)
        for c, x in zip(self.data.features, w, strict=True):
            z = z + F.col(c) * F.lit(float(x))
        return z

    # -- loss and gradient -------------------------------------------------------------------------------------------------
    def value_and_gradient(self, w: np.ndarray, with_value: bool = True) -> tuple[float, np.ndarray]:
        n, began = self.data.count(), time.perf_counter()
        if self.data.kind == "narrow":
            marked = self.data.df.select(*self.data.features, "y", self._columns(w).alias("z"))
            s = self.loss.slope_term(F.col("z"), F.col("y"))
            sums = marked.select(self.loss.value_term(F.col("z"), F.col("y")).alias("v"), s.alias("s"), *self.data.features)
            row = sums.agg(F.sum("v"), *(F.sum(F.col("s") * F.col(c)) for c in self.data.features)).first()
            value, grad = (row[0] or 0.0) / n, np.array([x or 0.0 for x in row[1:]]) / n
        else:
            value, grad = self._arrow_gradient(w)
        self._timed("fg" if with_value else "g", began, self.m + 1, self.m)
        return value + self.penalty.value(w), grad + self.penalty.gradient(w)

    def gradient(self, w):
        return self.value_and_gradient(w, with_value=False)[1]

    def value(self, w) -> float:
        return self.coefficients(w, np.zeros_like(w), 0.0, 0).c[0]

    def _held(self) -> tuple[DataFrame, bool]:
        """Rows for a pass, and whether they are packed. Packed ones are read by as many tasks as run at once, since each task costs
        its start and, in a gradient, a vector to send; a task reads its partitions one after another."""
        return (self.data.arrays(), False) if self.data.packed is None else (self.data.packed.coalesce(self.data.lanes()), True)

    def curvature_product(self, w: np.ndarray, d: np.ndarray) -> np.ndarray:
        """The second derivative at w times d, in one pass; what truncated Newton directions are made of."""
        n, began = self.data.count(), time.perf_counter()
        if self.data.kind == "narrow":
            marked = self.data.df.select(*self.data.features, "y", self._columns(w).alias("z"), self._columns(d).alias("q"))
            bend = 2 * self.loss.taylor_terms(F.col("z"), F.lit(1.0), F.col("y"), 2)[2] * F.col("q")
            row = marked.select(bend.alias("s"), *self.data.features).agg(*(F.sum(F.col("s") * F.col(c)) for c in self.data.features)).first()
            out = np.array([x or 0.0 for x in row]) / n
        else:
            out = self._arrow_gradient(w, d)[1]
        self._timed("hv", began, self.m, 2 * self.m)
        return out + self.penalty.gradient(d)

    def _arrow_gradient(self, w, d=None):
        """Mean loss and gradient; with d, the second derivative times d in place of the gradient."""
        spark, kind, m, loss = self.data.df.sparkSession, self.data.kind, self.m, self.loss
        ship(spark)
        rows, packed = self._held()
        sent = spark.sparkContext.broadcast((w, d))

        def run(batches):
            from pyspark import TaskContext

            total, value = np.zeros(m), 0.0
            for y, x in _batches(batches, kind, packed):
                at, along = sent.value
                b = loss.kernel(_dot(x, at), np.ones(len(y)), y, 1 if along is None else 2)
                value += b[0].sum()
                _add_weighted(total, x, b[1] if along is None else 2 * b[2] * _dot(x, along))
            lane = TaskContext.get().partitionId()
            held = [(-1, np.array([value]))] + [(k, total[k * BLOCK : (k + 1) * BLOCK]) for k in range(-(-m // BLOCK))]
            held = [h for h in held if h[1].any()]  # blocks that no row touched stay at home
            yield pa.record_batch([pa.array([h[0] for h in held], pa.int32()), pa.array([lane] * len(held), pa.int32()), pa.array([h[1].tobytes() for h in held], pa.binary())], ["block", "lane", "part"])

        blocks = rows.mapInArrow(run, "block int, lane int, part binary")
        n, lanes = self.data.count(), self.data.lanes()
        small = m * lanes <= FLAT_LIMIT
        how = self.reduce if self.reduce != "auto" else "flat" if small else "tree"
        if how == "tree":
            blocks = tree_sum(blocks, self.levels or (1 if lanes <= ONE_LEVEL else 2), lanes)
        grad, value = np.zeros(m), 0.0
        # in parallel; after a tree, one row for each block; many whole vectors come one partition at a time
        with small_batches(spark, packed):
            for k, _, part in blocks.collect() if small or how == "tree" else blocks.toLocalIterator():
                x = np.frombuffer(part)
                if k < 0:
                    value += float(x[0])
                else:
                    grad[k * BLOCK : k * BLOCK + len(x)] += x
        sent.destroy()
        return value / n, grad / n

    # -- Taylor coefficients -----------------------------------------------------------------------------------------------
    def margins(self, w, p) -> DataFrame:
        """(y, z, q) of every row for parameters w and direction p."""
        if self.data.kind == "narrow":
            return self.data.df.select("y", self._columns(w).alias("z"), self._columns(p).alias("q"))
        spark, kind = self.data.df.sparkSession, self.data.kind
        ship(spark)
        rows, packed = self.data.arrays() if self.data.packed is None else self.data.packed, self.data.packed is not None
        sent = self._sent = spark.sparkContext.broadcast((w, p))

        def run(batches):
            for y, x in _batches(batches, kind, packed):
                yield pa.record_batch([pa.array(y), pa.array(_dot(x, sent.value[0])), pa.array(_dot(x, sent.value[1]))], ["y", "z", "q"])

        return rows.mapInArrow(run, "y double, z double, q double")

    def begin_ray(self, w, p) -> None:
        """With cached margins, every expansion on the ray reads 24 bytes a row and broadcasts nothing."""
        self.end_ray()
        if self.cached:
            self._margins = self.margins(w, p).persist(StorageLevel.MEMORY_AND_DISK)

    def end_ray(self) -> None:
        if self._margins is not None:
            self._margins.unpersist()
            self._margins = None
            if self._sent is not None:
                self._sent.destroy()
                self._sent = None

    def coefficients(self, w, p, alpha: float, degree: int) -> TaylorModel:
        """The model of the loss at w + (alpha + t) p."""
        n, began, r = self.data.count(), time.perf_counter(), w + alpha * p
        if self._margins is not None:
            held, sent = self._margins.select("y", (F.col("z") + F.col("q") * F.lit(float(alpha))).alias("z"), "q"), 0
        elif self.data.kind == "narrow":
            held, sent = self.margins(r, p), 2 * self.m
        else:
            held, sent = None, 2 * self.m
        if held is not None:
            terms = self.loss.taylor_terms(F.col("z"), F.col("q"), F.col("y"), degree)
            c = np.array([x or 0.0 for x in held.agg(*(F.sum(t).alias(f"c{k}") for k, t in enumerate(terms))).first()])
        else:
            c = self._arrow_coefficients(r, p, degree)
        self._timed("coeffs", began, degree + 1, sent)
        exact = self.loss.exact_degree is not None and degree >= max(2, self.loss.exact_degree)
        return TaylorModel(c / n + self.penalty.terms(r, p, degree), alpha, exact)

    def _arrow_coefficients(self, r, p, degree):
        spark, kind, loss = self.data.df.sparkSession, self.data.kind, self.loss
        ship(spark)
        rows, packed = self._held()
        sent = spark.sparkContext.broadcast((r, p))
        names = [f"c{k}" for k in range(degree + 1)]

        def run(batches):
            total = np.zeros(degree + 1)
            for y, x in _batches(batches, kind, packed):
                total += loss.kernel(_dot(x, sent.value[0]), _dot(x, sent.value[1]), y, degree).sum(1)
            yield pa.record_batch([pa.array([t]) for t in total], names)

        with small_batches(spark, packed):
            sums = rows.mapInArrow(run, ", ".join(f"{c} double" for c in names)).collect()  # one row a task, so no stage to add them
        sent.destroy()
        return np.array(sums, float).reshape(-1, degree + 1).sum(0)
