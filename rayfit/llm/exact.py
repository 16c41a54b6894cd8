"""Exact duplicates through an extendible-hash index on shared files, in DataFrame operations only.

The directory starts as one bucket. Whatever bucket holds more than CAPACITY distinct hashes is split by their next bit, and the
directory doubles; only what lies in overfull buckets is counted again. There is no bound on the depth: hashes that
agree in all bits are one entry of the directory, and their texts are a chain.

Rows with their texts then go to the owner of their range of hashes. An owner compares the bytes of the texts that share a
hash, chains those that differ, and writes its part of the index: one row for each text with the key that stays and
the number of copies. Rows look their entry up by the directory's slot, hash and digest; that equi-join can be split by Spark
where a text is hot. Copies of a hash that more than HOT rows have are combined within their tasks before they go to the owner."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import partitions, staged

#: Distinct hashes that a bucket holds before it is split.
CAPACITY = 65_536
#: Bits by which counts are finer than the splits that they serve.
STRIDE = 8
#: Rows of one hash from which copies are combined before they are sent.
HOT = 32
#: Most rows of a table that may be broadcast (two or three longs each).
BROADCAST_ROWS = 100_000


def keyed(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, body, hash); a null text counts as the empty one."""
    body = F.coalesce(F.col(text), F.lit(""))
    return docs.select(F.col(key).alias("key"), body.alias("body"), F.xxhash64(body).alias("hash"))


def _digest(body):
    return F.coalesce(F.sha2(body, 256), F.lit(""))


def _prefix(column, bits: int, of: int = 64):
    """The upper bits of a number of `of` bits. In two steps, as a shift by 64 is none."""
    return column if bits == of else F.shiftrightunsigned(F.shiftrightunsigned(column, 1), of - bits - 1)


def _small(df: DataFrame) -> DataFrame:
    """df, to be broadcast only behind a check of its rows."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df.hint("merge")


def directory(hashes: DataFrame, capacity: int = CAPACITY) -> tuple[DataFrame, int]:
    """(slot, bucket, local) and the global depth, from a table of distinct hashes.

    A bucket is its prefix of local bits. It is split while it holds more than capacity hashes; the directory has a slot for
    each prefix of as many bits as the deepest bucket has, and several slots share a bucket that is less deep."""
    done, depth, rest = [], 0, hashes.select("hash")
    while True:
        top = min(64, depth + STRIDE)
        fine = staged(rest.groupBy(_prefix(F.col("hash"), top).alias("p")).agg(F.count("*").alias("n")), "counts")
        for local in range(depth + (depth > 0), top + 1):
            held = staged(fine.groupBy(_prefix(F.col("p"), local, top).alias("bucket")).agg(F.sum("n").alias("held")).withColumn("local", F.lit(local)), "buckets")
            done.append(held.filter(F.col("held") <= capacity).select("bucket", "local"))
            over = held.filter(F.col("held") > capacity).select("bucket")
            if over.isEmpty():
                found = reduce(DataFrame.unionAll, done)
                last = found.agg(F.max("local")).first()[0] or 0
                wide = F.lit(last) - F.col("local")
                slots = F.sequence(F.expr(f"shiftleft(bucket, {last} - local)"), F.expr(f"shiftleft(bucket + 1, {last} - local) - 1"))
                return staged(found.withColumn("slot", F.explode(F.when(wide == 0, F.array("bucket")).otherwise(slots))).select("slot", "bucket", "local"), "directory"), last
            fine = fine.join(_small(over.withColumnRenamed("bucket", "_over")), _prefix(F.col("p"), local, top) == F.col("_over"), "left_semi")
        rest, depth = hashes.select("hash").join(_small(over.withColumnRenamed("bucket", "_over")), _prefix(F.col("hash"), top) == F.col("_over"), "left_semi"), top


def index(docs: DataFrame, key: str = "doc_id", text: str = "text", capacity: int = CAPACITY, hot: int = HOT) -> tuple[DataFrame, DataFrame, int]:
    """The index, written to the shared folder, its directory and the directory's depth.

    The index is (bucket, local, slot, hash, chain, digest, keep, size), one row per text."""
    rows, parts = keyed(docs, key, text), partitions(docs.sparkSession)
    hashes = staged(rows.groupBy("hash").agg(F.count("*").alias("n")), "hashes")
    slots, depth = directory(hashes, capacity)
    crowded = hashes.filter(F.col("n") > hot).select("hash")
    held = rows.select("hash", "body", F.col("key").alias("keep"), F.lit(1).cast("long").alias("size"))
    if not crowded.isEmpty():
        known = _small(crowded)
        copies = held.join(known, "hash", "left_semi").groupBy("hash", "body").agg(F.max("keep").alias("keep"), F.sum("size").alias("size"))
        held = held.join(known, "hash", "left_anti").unionByName(copies)
    # ranges of the unsigned hash, which are ranges of slots too
    owner = F.shiftright(F.shiftrightunsigned("hash", 33) * parts, 31).cast("int")
    routed = held.withColumn("owner", owner).repartitionById(parts, F.col("owner"))
    # owner is among the keys, so that these run where the rows are
    texts = routed.groupBy("owner", "hash", "body").agg(F.max("keep").alias("keep"), F.sum("size").alias("size"))
    texts = texts.select("owner", "hash", _digest(F.col("body")).alias("digest"), "keep", "size")
    chained = texts.withColumn("chain", F.row_number().over(Window.partitionBy("owner", "hash").orderBy("digest")))
    entries = chained.withColumn("slot", _prefix(F.col("hash"), depth)).join(_small(slots), "slot")
    return staged(entries.select("bucket", "local", "slot", "hash", "chain", "digest", "keep", "size"), "index"), slots, depth


def _found(docs: DataFrame, key: str, text: str, **options) -> DataFrame:
    """(key, hash, digest, keep, size) of every row, through the directory and the index."""
    at, slots, depth = index(docs, key, text, **options)
    own = keyed(docs, key, text).select("key", "hash", _digest(F.col("body")).alias("digest")).withColumn("slot", _prefix(F.col("hash"), depth))
    led = own.join(_small(slots.select("slot", "bucket")), "slot")
    return led.join(at.select("bucket", "hash", "digest", "keep", "size"), ["bucket", "hash", "digest"]).select("key", "hash", "digest", "keep", "size")


def groups(docs: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """(key, keep_id, group_size, kept, text_sha256) for every row; of equal texts the largest key stays.

    Null and empty texts are one group. A repeated row (same key and text) is kept if its key is the largest. A null key is
    smaller than all others: its rows stay only where a text has no other key."""
    out = _found(docs, key, text, **options)
    return out.select(F.col("key").alias(key), F.col("keep").alias("keep_id"), F.col("size").alias("group_size"), F.col("key").eqNullSafe(F.col("keep")).alias("kept"), F.col("digest").alias("text_sha256"))


def keep_last(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with the row of the largest key of each text, found in the index as by groups; see there."""
    at, _, _ = index(docs, key, text)
    body = F.coalesce(F.col(text), F.lit(""))
    kept = at.select(F.col("hash").alias("_hash"), F.col("digest").alias("_digest"), F.col("keep").alias("_keep"))
    same = docs[key].eqNullSafe(F.col("_keep")) & (F.xxhash64(body) == F.col("_hash")) & (_digest(body) == F.col("_digest"))
    return docs.join(kept, same, "left_semi")
