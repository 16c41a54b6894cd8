"""Readers and writers around the learners: libsvm text, instances, traces, models, checkpoints of a fit."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .instances import Instances


def read_libsvm(spark: SparkSession, path: str, m: int) -> DataFrame:
    """(idx, val, y) of libsvm text with 1-based indices, with the constant feature m at the end; bad tokens give nulls."""
    line = F.split(F.trim(F.regexp_replace("value", r"#.*", "")), r"\s+")
    pairs = F.filter(F.slice(line, F.lit(2), F.size(line)), lambda t: t != "")
    idx = F.transform(pairs, lambda t: (F.split(t, ":")[0].try_cast("int") - 1))
    val = F.transform(pairs, lambda t: F.split(t, ":")[1].try_cast("double"))
    text = spark.read.text(path).filter(F.trim("value") != "")
    return text.select(F.concat(idx, F.array(F.lit(m))).alias("idx"), F.concat(val, F.array(F.lit(1.0))).alias("val"), line[0].try_cast("double").alias("y"))


def write_libsvm(df: DataFrame, path: str, m: int) -> None:
    """Sparse rows as text, without the constant feature m."""
    kept = F.filter(F.arrays_zip("idx", "val"), lambda e: e["idx"] < m)
    words = F.transform(kept, lambda e: F.concat((e["idx"] + 1).cast("string"), F.lit(":"), e["val"].cast("string")))
    df.select(F.concat_ws(" ", F.col("y").cast("string"), words).alias("value")).write.mode("overwrite").text(path)


def write_instances(data: Instances, path: str, partition_by: str | None = None) -> None:
    """Only what the passes read; a fold or mini-batch column as partition lets a batch read its own files."""
    writer = data.df.write.mode("overwrite")
    (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)


def read_table(spark: SparkSession, path: str, form: str = "parquet", schema=None, **options) -> DataFrame:
    reader = spark.read.format(form).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_table(df: DataFrame, path: str, form: str = "parquet", mode: str = "append", **options) -> None:
    df.write.format(form).mode(mode).options(**options).save(path)


def model_json(w: np.ndarray, **about) -> str:
    return json.dumps(about | {"w": [float(x) for x in w]})


def save_state(spark: SparkSession, path: str, k: int, fit) -> None:
    """Weights and history pairs after iteration k, so that a fit outlives its driver."""
    rule = fit.state["rule"]
    rows = [("w", 0, fit.w.tolist())] + [(n, i, v.tolist()) for i, pair in enumerate(getattr(rule, "pairs", [])) for n, v in zip("sy", pair, strict=True)]
    spark.createDataFrame([(k, *r) for r in rows], "k int, name string, i int, v array<double>").coalesce(1).write.mode("append").parquet(path)


def load_state(spark: SparkSession, path: str, history: int = 5) -> dict:
    """The latest saved state, for minimize(state=...)."""
    from .optim import Lbfgs

    rows = spark.read.parquet(path)
    rows = rows.filter(F.col("k") == rows.agg(F.max("k")).first()[0]).collect()
    rule = Lbfgs(history)
    s, y = ({r.i: np.array(r.v) for r in rows if r.name == n} for n in "sy")
    rule.pairs = [(s[i], y[i]) for i in sorted(s)]
    return {"w": np.array(next(r.v for r in rows if r.name == "w")), "rule": rule, "k": rows[0].k}


class LibsvmSource(DataSource):
    """format("rayfit_libsvm").option("m", ...).load(path): read_libsvm's rows, a task for each file; bad tokens end the read.

    Files are opened by the workers, so that path is one that they can open; read_libsvm also splits large files."""

    @classmethod
    def name(cls):
        return "rayfit_libsvm"

    def schema(self):
        return "idx array<int>, val array<double>, y double"

    def reader(self, schema):
        return LibsvmReader(self.options["path"], int(self.options["m"]))


class LibsvmReader(DataSourceReader):
    def __init__(self, path: str, m: int):
        self.path, self.m = path.removeprefix("file://").removeprefix("file:"), m

    def partitions(self):
        import glob
        import os

        files = sorted(f for f in glob.glob(os.path.join(self.path, "*")) if os.path.basename(f)[0] not in "._") if os.path.isdir(self.path) else [self.path]
        return [InputPartition(f) for f in files]

    def read(self, partition):
        with open(partition.value) as lines:
            for line in lines:
                y, *pairs = line.split("#")[0].split() or [None]
                if y is not None:
                    both = [p.split(":") for p in pairs]
                    yield [int(i) - 1 for i, _ in both] + [self.m], [float(v) for _, v in both] + [1.0], float(y)
