"""Exact top-k inner products by a bit-sliced index.

Vectors become integers floor(scale * x). A block of rows holds, for every attribute, bitmaps of its upper bits (one bit of all
rows in each), and their complements for negative weights. A query's score is then a sum of bitmaps with weights that
are powers of two, which carry-save adders reduce, plane by plane, to one bitmap for each bit of the sum. From the most
significant plane downward these select the best rows; all rows that the bits left out could lift to the last of them form
the boundary, and are scored exactly from the integers."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import partitions, ship, staged

ROWS = 16_384
QUERIES = 256
#: Upper bits of an attribute that are sliced.
KEPT = 5


LONG = 2**63 - 1


class Block:
    def __init__(self, ids: np.ndarray, values: np.ndarray, kept: int = KEPT):
        self.ids, self.values = ids, values
        self.widest = max(int(values.max()), -int(values.min()), 1)
        if self.widest > 2**40:
            return  # no planes: every score is made of Python's integers
        n, d = values.shape
        self.low = values.min(0)
        spread = values - self.low
        bits = max(1, int(spread.max()).bit_length())
        self.cut = max(0, bits - kept)
        high = spread >> self.cut
        self.bits = bits - self.cut
        self.words = -(-n // 64)
        planes = np.zeros((d, self.bits, self.words * 64), np.uint8)
        for b in range(self.bits):
            planes[:, b, :n] = ((high >> b) & 1).T
        self.planes = np.packbits(planes, axis=-1, bitorder="little").view(np.uint64)
        self.all = np.packbits(np.r_[np.ones(n, np.uint8), np.zeros(self.words * 64 - n, np.uint8)], bitorder="little").view(np.uint64)
        self.other = ~self.planes & self.all

    def sums(self, weights: np.ndarray) -> list[np.ndarray]:
        """Bit planes of sum over attributes of |w| * (upper bits, or their complement where w < 0)."""
        size = np.abs(weights)
        side = np.where((weights < 0)[:, None, None], self.other, self.planes)
        heap: dict[int, list[np.ndarray]] = {}
        for c in range(int(size.max()).bit_length()):
            used = np.flatnonzero((size >> c) & 1)
            for b in range(self.bits):
                if len(used):
                    heap.setdefault(b + c, []).append(side[used, b])
        out, p = [], 0
        while p <= max(heap, default=-1):
            rows = np.concatenate(heap.pop(p)) if p in heap else np.zeros((0, self.words), np.uint64)
            while len(rows) > 2:
                k = len(rows) // 3
                a, b, c = rows[:k], rows[k : 2 * k], rows[2 * k : 3 * k]
                x = a ^ b
                heap.setdefault(p + 1, []).append((a & b) | (x & c))
                rows = np.concatenate([x ^ c, rows[3 * k :]])
            if len(rows) == 2:
                heap.setdefault(p + 1, []).append((rows[0] & rows[1])[None])
                rows = (rows[0] ^ rows[1])[None]
            out.append(rows[0] if len(rows) else np.zeros(self.words, np.uint64))
            p += 1
        return out

    def _rows(self, bitmap: np.ndarray) -> np.ndarray:
        return np.flatnonzero(np.unpackbits(bitmap.view(np.uint8), bitorder="little"))

    def top(self, own: int, weights: np.ndarray, k: int) -> list[tuple[int, int]]:
        """The k best (id, score) of the rows other than own, ties to the smaller id."""
        n = len(self.ids)
        if self.widest > 2**40 or self.widest * sum(abs(int(w)) for w in weights) > LONG:
            own_out = np.flatnonzero(self.ids != own)
            score = (self.values[own_out].astype(object) @ weights.astype(object)).tolist()
            best = sorted(zip((-max(-LONG - 1, min(LONG, x)) for x in score), self.ids[own_out].tolist(), strict=True))[:k]
            return [(i, -x) for x, i in best]
        if n > 4 * (k + 1) and weights.any():
            planes = self.sums(weights)
            sure, tied, wanted, last = np.zeros(self.words, np.uint64), self.all.copy(), k + 1, 0
            for p in range(len(planes) - 1, -1, -1):  # the value of the wanted-th best row, bit by bit
                with_bit = tied & planes[p]
                if int(np.bitwise_count(sure | with_bit).sum()) >= wanted:
                    tied, last = with_bit, last | (1 << p)
                else:
                    sure, tied = sure | with_bit, tied & ~planes[p]
            slack = int(np.abs(weights).sum()) * ((1 << self.cut) - 1) >> self.cut
            least = max(0, last - slack - 1)
            more, equal = np.zeros(self.words, np.uint64), self.all.copy()
            for p in range(len(planes) - 1, -1, -1):  # rows of at least that value
                if (least >> p) & 1:
                    equal = equal & planes[p]
                else:
                    more |= equal & planes[p]
                    equal = equal & ~planes[p]
            rows = self._rows(more | equal)
        else:
            rows = np.arange(n)
        rows = rows[self.ids[rows] != own]
        score = self.values[rows].astype(np.int64) @ weights.astype(np.int64)
        best = np.lexsort((self.ids[rows], -score))[:k]
        return [(int(self.ids[rows[i]]), int(score[i])) for i in best]


def _pack(rows: DataFrame, most: int) -> DataFrame:
    """Blocks (dim, n, ids, cells) of at most so many (id, v array<int>) rows of one dimension, made where the rows lie."""

    def run(batches):
        held: dict[int, list] = {}

        def block(dim):
            ids, values = zip(*held.pop(dim), strict=True)
            return pa.record_batch([pa.array([dim], pa.int32()), pa.array([len(ids)], pa.int32()), pa.array([np.array(ids, np.int64).tobytes()], pa.binary()), pa.array([np.array(values, np.int64).tobytes()], pa.binary())], ["dim", "n", "ids", "cells"])

        for batch in batches:
            for i, v in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                x = v.values.to_numpy(zero_copy_only=False)
                own = held.setdefault(len(x), [])
                own.append((i, x))
                if len(own) == most:
                    yield block(len(x))
        for dim in list(held):
            yield block(dim)

    return rows.mapInArrow(run, "dim int, n int, ids binary, cells binary")


def search(vectors: DataFrame, queries, k: int = 5, key: str = "vec_id", vector: str = "embedding", scale: int = 256) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best of all rows but its own for every row where queries, a column, holds.

    Vectors that are null or hold nulls or non-finite components take no part; vectors meet those of their own length.
    Components beyond a long after scaling count as its ends; scores are exact, and one beyond a long counts as its end.
    Every block of queries is sent to every block of rows, which is read once; only the k best of each leave it."""
    spark = vectors.sparkSession
    ship(spark)
    x = F.col(vector)
    sound = x.isNotNull() & ~F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    rows = vectors.filter(sound & (F.size(x) > 0)).select(F.col(key).cast("long").alias("id"), F.transform(x, lambda c: F.floor(c.cast("double") * scale).cast("long")).alias("v"), queries.alias("asks"))
    blocks = staged(_pack(rows.select("id", "v"), ROWS).withColumn("at", F.monotonically_increasing_id()), "blocks")
    asked = staged(_pack(rows.filter("asks").select("id", "v"), QUERIES), "queries")
    at = sorted((r[0], r[1]) for r in blocks.select("at", "dim").collect())  # two numbers for each ROWS rows
    if not at:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    number = spark.createDataFrame([(a, d, i) for i, (a, d) in enumerate(at)], "at long, dim int, block int")
    held = blocks.join(number.select("at", "block"), "at").select("block", F.lit(0).alias("kind"), "dim", "ids", "cells")
    sent = asked.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(len(at) - 1)))).select("block", F.lit(1).alias("kind"), "dim", "ids", "cells")
    parts = min(len(at), partitions(spark))
    both = held.unionAll(sent).repartitionById(parts, F.col("block") % parts).sortWithinPartitions("block", "kind")

    def run(batches):
        last, dim, block = None, None, None
        for batch in batches:
            for where, kind, size, ids, cells in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if not kind:
                    last, dim, block = where, size, Block(np.frombuffer(ids, np.int64), np.frombuffer(cells, np.int64).reshape(-1, size))
                elif where == last and size == dim:
                    out = [(q, *best) for q, w in zip(np.frombuffer(ids, np.int64), np.frombuffer(cells, np.int64).reshape(-1, size), strict=True) for best in block.top(int(q), w, k)]
                    if out:
                        a = np.array(out, np.int64)
                        yield pa.record_batch([pa.array(a[:, i]) for i in range(3)], ["query_id", "vec_id", "score"])

    best = staged(both.mapInArrow(run, "query_id long, vec_id long, score long"), "best")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
