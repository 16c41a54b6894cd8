"""Mini-batch learning and running sums on streams."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .instances import Instances, Problem
from .taylor import taylor_line_search


class MiniBatch:
    """One gradient direction and one Taylor search for each micro-batch; weights stay on the driver.

    Batches repeated after a restart are skipped by number. features: events -> sparse instance columns (idx, val, y)."""

    def __init__(self, features, m: int, loss, lam: float = 1e-4, theta: float = 1e-4, degree: int = 3, damping: float = 0.5):
        self.features, self.m, self.loss, self.lam, self.theta, self.degree, self.damping = features, m, loss, lam, theta, degree, damping
        self.w, self.seen, self.trace = np.zeros(m), -1, []

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number <= self.seen:
            return
        data = Instances(self.features(batch), self.m, kind="sparse").persist()
        if data.count():
            problem = Problem(data, self.loss, self.lam)
            value, g = problem.value_and_gradient(self.w)
            size = np.linalg.norm(g)
            if size > 0:
                p = -g / size
                step = taylor_line_search(lambda a: problem.coefficients(self.w, p, a, self.degree), 1.0, self.theta)
                self.w = self.w + self.damping * step.alpha * p
                self.trace.append({"batch": number, "n": data.count(), "loss": value, "alpha": step.alpha})
        data.unpersist()
        self.seen = number


def start(events: DataFrame, learner: MiniBatch, checkpoint: str, trigger: dict | None = None):
    return events.writeStream.foreachBatch(learner).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def window_loss(scored: DataFrame, ts: str = "ts", width: str = "1 day", slide: str | None = None, late: str | None = None) -> DataFrame:
    """Rows, mean loss and exp(-mean loss) in windows of event time, of (ts, loss) rows; a batch or a stream."""
    own = scored.withColumn(ts, F.col(ts).cast("timestamp"))
    own = own.withWatermark(ts, late) if late else own
    win = F.window(ts, width, slide) if slide else F.window(ts, width)
    return own.groupBy(win.alias("win")).agg(F.count("*").alias("n"), F.avg("loss").alias("loss")).select(F.col("win.start").alias("start"), "n", "loss", F.exp(-F.col("loss")).alias("acc"))


def session_loss(scored: DataFrame, key: str, ts: str = "ts", pause: str = "1 hour") -> DataFrame:
    own = scored.withColumn(ts, F.col(ts).cast("timestamp"))
    return own.groupBy(key, F.session_window(ts, pause).alias("win")).agg(F.count("*").alias("n"), F.avg("loss").alias("loss")).select(key, F.col("win.start").alias("start"), "n", "loss")


def running_coefficients(rows: DataFrame, loss, degree: int, epoch: str = "epoch") -> DataFrame:
    """Sums of coefficient terms by epoch of (epoch, y, z, q) rows: additive, so a stream in complete or update mode keeps
    them in state. Sums only add up for one ray, hence a new epoch with each change of weights."""
    terms = loss.taylor_terms(F.col("z"), F.col("q"), F.col("y"), degree)
    return rows.groupBy(epoch).agg(F.count("*").alias("n"), *(F.sum(t).alias(f"c{k}") for k, t in enumerate(terms)))


def deduplicated(events: DataFrame, key: str = "event_id", ts: str = "ts", late: str = "1 day") -> DataFrame:
    own = events.withColumn(ts, F.col(ts).cast("timestamp"))
    return own.withWatermark(ts, late).dropDuplicatesWithinWatermark([key]) if events.isStreaming else own.dropDuplicates([key])


def interval_join(left: DataFrame, right: DataFrame, key: str, width: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Rows of right that follow a row of left with the same key within width."""
    a = left.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).alias("a")
    b = right.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).alias("b")
    return a.join(b, F.expr(f"a.{key} = b.{key} AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL {width}"))
