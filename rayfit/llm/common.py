"""Shared folder, staged tables and Arrow helpers of the text operators."""

from __future__ import annotations

import os
import tempfile
import uuid
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one vectorised step looks at; a longer document is a step of its own.
STEP_BYTES = 500_000
#: Bytes of an Arrow batch while a table is staged; a longer row is a batch of its own.
BATCH_BYTES = 8_000_000


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir of the session; only where it is unset
    (tests in one JVM) a folder of this process."""
    at = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not at and not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not at:
        at = f"file://{os.path.join(tempfile.gettempdir(), f'rayfit-{os.getpid()}')}"
    return at.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/rayfit/{name}-{uuid.uuid4().hex}"


@contextmanager
def small_batches(spark: SparkSession, most: int = BATCH_BYTES):
    """Within it, Arrow batches end at so many bytes: one with wide binary columns is held several times over, by the JVM
    and by Python. The session's own setting comes back afterwards."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key, None)
    spark.conf.set(key, str(most))
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


def staged(df: DataFrame, name: str) -> DataFrame:
    """df written to the shared folder and read again: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    with small_batches(spark):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def forget(df: DataFrame) -> None:
    """Deletes the files of a staged table that no later plan reads."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        if "/rayfit/" in folder:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(conf).delete(path, True)


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


#: Partial sums that one task adds at most, of the partitions that share a lane: partitions / LANES at the first level.
LANES = (256, 16)


def vector_sum(rows: DataFrame, partial, size: int):
    """The sum of partial(batches), a vector of so many doubles, over all partitions of rows.

    Partitions work in parallel and their vectors are added in tasks, by lanes, in two levels; the driver adds LANES[-1] of them."""
    import numpy as np

    def run(batches):
        from pyspark import TaskContext

        yield pa.record_batch([pa.array([TaskContext.get().partitionId()], pa.int32()), pa.array([np.asarray(partial(batches), float).tobytes()], pa.binary())], ["lane", "part"])

    def add(table):
        whole = sum(np.frombuffer(x.as_buffer()) for x in table["part"])
        return pa.table({"lane": table["lane"].slice(0, 1), "part": pa.array([whole.tobytes()], pa.binary())})

    out = rows.mapInArrow(run, "lane int, part binary")
    for lanes in LANES:
        out = out.withColumn("lane", (F.col("lane") % lanes).cast("int")).groupBy("lane").applyInArrow(add, "lane int, part binary")
    return sum((np.frombuffer(r.part) for r in out.collect()), np.zeros(size))


def split_mark(column: str, modulus: int, held: int):
    """crc32(id as text) mod modulus = held, as a column."""
    return F.pmod(F.crc32(F.col(column).cast("string")), F.lit(modulus)) == held


def flat(column) -> pa.Array:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column


def slices(text: pa.Array, step: int = STEP_BYTES):
    """Row ranges of an Arrow string array, each of about step bytes or of one row."""
    import numpy as np

    n = len(text)
    if not n:
        return
    kind = np.int64 if pa.types.is_large_string(text.type) else np.int32
    ends = np.frombuffer(text.buffers()[1], kind, n + 1, text.offset * np.dtype(kind).itemsize).astype(np.int64)
    low = 0
    while low < n:
        high = max(low + 1, int(np.searchsorted(ends, ends[low] + step, "right")) - 1)
        yield low, min(high, n)
        low = min(high, n)


_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Sends this package to the executors once a session, as their Python need not have it."""
    import zipfile
    from pathlib import Path

    sc = spark.sparkContext
    if sc.applicationId in _SHIPPED:
        return
    top = Path(__file__).resolve().parents[2]
    to = os.path.join(tempfile.mkdtemp(prefix="rayfit-"), "rayfit_shipped.zip")
    with zipfile.ZipFile(to, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted((top / "rayfit").rglob("*.py")):
            z.write(p, p.relative_to(top))
    sc.addPyFile(to)
    _SHIPPED.add(sc.applicationId)
