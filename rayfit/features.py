"""Feature builders, all in DataFrame operations: dense, hashed text, one-hot, scaled."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def bucket(token: Column, m: int) -> Column:
    """The first eight hexadecimal digits of md5 modulo m; any SQL engine can redo it."""
    return (F.conv(F.substring(F.md5(token.cast("binary")), 1, 8), 16, 10).cast("long") % m).cast("int")


def quick_bucket(m: int, *cols) -> Column:
    return F.pmod(F.xxhash64(*cols), F.lit(m)).cast("int")


def tokens(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def bigrams(words: Column) -> Column:
    return F.transform(F.sequence(F.lit(0), F.size(words) - 2), lambda i: F.concat_ws(" ", F.get(words, i), F.get(words, i + 1)))


def slots(df: DataFrame, key: str, words: Column, m: int, label: Column, stable: bool = False, dealt: bool = False) -> DataFrame:
    """(row_id, y, s): the bucket of each word, sorted, so that equal ones are neighbours. The key names one row of df.

    Rows are dealt out by key as they are read, unless they are dealt already; words never leave their row."""
    own = (lambda t: bucket(t, m)) if stable else (lambda t: quick_bucket(m, t))
    held = (df if dealt else df.repartition(key)).select(F.col(key).alias("row_id"), label.cast("double").alias("y"), F.filter(F.coalesce(words, F.array().cast("array<string>")), lambda t: t.isNotNull()).alias("t"))
    return held.select("row_id", "y", F.sort_array(F.transform("t", lambda t: F.coalesce(own(t), F.lit(0)))).alias("s"))


def folded(rows: DataFrame, m: int) -> DataFrame:
    """Slots of m buckets from slots of a multiple of m."""
    return rows.withColumn("s", F.sort_array(F.transform("s", lambda x: (x % m).cast("int"))))


def weighed(rows: DataFrame, m: int) -> DataFrame:
    """(row_id, idx, val, y) of slots: 1 + log of counts by bucket, of length 1 in all, and the constant feature m at the end.

    A row without words keeps the constant alone."""
    first = F.filter(F.transform("s", lambda x, i: F.when((i == 0) | (x != F.get("s", i - 1)), i)), lambda i: i.isNotNull())
    at = rows.select("row_id", "y", "s", first.alias("at"))
    held = at.select("row_id", "y", F.transform("at", lambda i: F.get("s", i)).alias("i"), F.transform("at", lambda i, k: 1 + F.log(F.coalesce(F.get("at", k + 1), F.size("s")) - i)).alias("v"))
    norm = F.array(F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, e: a + e * e)))
    # the norm is a lambda's variable, as an expression inside the inner lambda would be computed again for each value
    scaled = F.get(F.transform(norm, lambda n: F.transform("v", lambda e: e / n)), F.lit(0))
    return held.select("row_id", F.concat("i", F.array(F.lit(m))).alias("idx"), F.concat(scaled, F.array(F.lit(1.0))).alias("val"), "y")


def hashed(df: DataFrame, key: str, words: Column, m: int, label: Column, stable: bool = False) -> DataFrame:
    return weighed(slots(df, key, words, m, label, stable), m)


def one_hot(df: DataFrame, parts: list[tuple[str, list]], m: int, label: Column, keep: list[str] = (), stable: bool = False) -> DataFrame:
    """(idx, val, y): a bucket for each named combination of columns, each once, and the constant feature m.

    stable: buckets by md5 of name and values joined by |, which any SQL engine can redo; otherwise by a quicker hash."""
    text = lambda c: (F.col(c) if isinstance(c, str) else c).cast("string")
    slot = (lambda name, cols: bucket(F.concat_ws("|", F.lit(name), *map(text, cols)), m)) if stable else (lambda name, cols: quick_bucket(m, F.lit(name), *cols))
    own = F.sort_array(F.array_distinct(F.array(*(slot(name, cols) for name, cols in parts))))
    return df.select(*keep, F.concat(own, F.array(F.lit(m))).alias("idx"), label.cast("double").alias("y")).withColumn("val", F.transform("idx", lambda _: F.lit(1.0)))


def dense(df: DataFrame, column: str, label: Column) -> DataFrame:
    return df.select(F.array_append(F.col(column).cast("array<double>"), F.lit(1.0)).alias("x"), label.cast("double").alias("y"))


def standardized(df: DataFrame, columns: list[str]) -> DataFrame:
    """Columns shifted and scaled to mean 0 and deviation 1; one small aggregate, joined back as one row."""
    stats = df.agg(*(F.avg(c).alias(f"{c}_m") for c in columns), *(F.stddev_pop(c).alias(f"{c}_s") for c in columns))
    out = df.crossJoin(F.broadcast(stats))
    return out.withColumns({c: (F.col(c) - F.col(f"{c}_m")) / F.when(F.col(f"{c}_s") > 0, F.col(f"{c}_s")).otherwise(1.0) for c in columns}).drop(*(f"{c}_{k}" for c in columns for k in "ms"))


def to_vector(df: DataFrame, m: int) -> DataFrame:
    """Sparse pairs as the library's vectors, in libsvm's layout (label, features)."""
    from pyspark.ml.functions import array_to_vector

    full = F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: F.coalesce(F.get("val", (F.array_position("idx", i) - 1).cast("int")), F.lit(0.0)))
    return df.select(F.col("y").alias("label"), array_to_vector(full).alias("features"))


def exploded(df: DataFrame) -> DataFrame:
    """(row_id, f, v) of sparse rows."""
    return df.select("row_id", F.explode(F.arrays_zip("idx", "val")).alias("e")).select("row_id", F.col("e.idx").cast("long").alias("f"), F.col("e.val").alias("v"))


def hash_sample(df: DataFrame, key: str, fractions, by: str | None = None, seed: int = 0) -> DataFrame:
    """Rows whose md5 of key and seed falls into a share: one for all, or one for each value of column by (others: none).

    The same rows in every run and engine, unlike sample and sampleBy."""
    share = F.lit(float(fractions)) if by is None else F.coalesce(F.element_at(F.create_map(*[F.lit(x) for kv in fractions.items() for x in kv]), F.col(by)), F.lit(0.0))
    return df.filter(F.conv(F.substring(F.md5(F.concat_ws("|", F.col(key).cast("string"), F.lit(str(seed))).cast("binary")), 1, 8), 16, 10).cast("double") < share * 4294967296.0)


def idf(df: DataFrame) -> DataFrame:
    """Sparse rows with each value times ln((1 + n) / (1 + rows with the feature)) + 1, and of length 1 again; the last feature,
    the constant, stays. Frequencies are one grouped count, joined by feature."""
    n = df.count()
    pairs = exploded(df)
    last = pairs.groupBy("row_id").agg(F.max("f").alias("last"))
    weight = pairs.groupBy("f").agg((F.log((1 + n) / (1 + F.count("*"))) + 1).alias("idf"))
    own = pairs.join(weight, "f").join(last, "row_id")
    rows = own.groupBy("row_id").agg(F.array_sort(F.collect_list(F.struct("f", F.when(F.col("f") < F.col("last"), F.col("v") * F.col("idf")).alias("v")))).alias("x"))
    norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, e: a + F.coalesce(e["v"] * e["v"], F.lit(0.0))))
    scaled = rows.select("row_id", F.transform("x.f", lambda f: f.cast("int")).alias("idx"), F.transform("x", lambda e: F.coalesce(e["v"] / F.when(norm > 0, norm).otherwise(1.0), F.lit(1.0))).alias("val"))
    return scaled.join(df.select("row_id", "y"), "row_id").select("row_id", "idx", "val", "y")


def to_sparse(df: DataFrame, column: str = "x") -> DataFrame:
    """Dense rows as pairs of those entries that are not 0, in place of the column."""
    at = F.filter(F.sequence(F.lit(0), F.size(column) - 1), lambda i: F.get(column, i) != 0)
    return df.withColumn("idx", at).withColumn("val", F.transform("idx", lambda i: F.get(column, i))).drop(column)
