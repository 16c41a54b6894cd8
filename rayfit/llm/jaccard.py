"""Exact n-gram Jaccard join by partition-enumeration signatures, and the components of its links.

A document is the set of its distinct w-word shingles. Sizes lie in bands; the family of a band has its upper bound r, and each
document takes part in the family of its own size and, if a partner may be larger than that, in the next one. In a family the
feature domain is cut by a hash into parts on two levels: n1 first parts, each of SECOND second parts. Two sets of a family with
similarity t or more differ in at most k <= (1-t)/(1+t) (a+b) elements. As n1 > k / (SPARE + 1), there is a first part in which
they differ in SPARE elements at most, so that SECOND - SPARE of its second parts hold the same elements in both. The signatures of a
set are the contents of every subset of SECOND - SPARE second parts of every first part; linked sets share at least one.

At most spoilt(k, n1) of all signatures can differ between linked sets. So a set needs to emit but one more than that, the last ones in an
order that depends on a signature's contents alone (count of uncommon elements, count of elements, hash): the last of those that
agree is then among them on both sides. What is left out are subsets that hold nothing or common shingles only, which would
bring together sets that have nothing else in common.

Sets that are equal are one class. Only classes take part; a bucket of equal signatures yields one star of pairs, checked
exactly; what a bucket holds beyond one component is then compared in blocks of BLOCK, after a histogram bound. So no
true link between two components is lost, and components cost no square of the size of a group of near copies.

The join itself has all links. They lie within components, so that the classes of each component are compared exactly, all
with all, in blocks of LINKED: this does cost the square of a component, in counts of shared elements."""

from __future__ import annotations

from functools import lru_cache
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, partitions, ship, slices, staged
from .components import connected
from .textkit import Words, mix

BLOCK = 256
#: Second parts of a first part, and how many of them a subset leaves out.
SECOND, SPARE = 3, 1
#: Elements whose signatures a task of the buckets gets, about; more partitions are made for more.
DEALT = 1_000_000
#: Classes of one component in a block, and distinct elements that one product takes.
LINKED, TAKEN = 128, 4096
#: Hashes that a task gathers before it passes them on.
HELD = 1_000_000
#: Buckets of a document that its rows name when pairs are told.
FIRST = 16
#: A set's histogram has a cell or two for each element, between these numbers; counts stop at 3.
FEWEST, MOST = 16, 32768
#: Most bytes of class ids that may be broadcast; beyond, they are joined by a shuffle.
BROADCAST_IDS = 2_000_000


class Rule:
    """Similarity of num/den or more; sizes in bands of ratio 2."""

    def __init__(self, num: int = 3, den: int = 4):
        self.num, self.den = num, den

    def links(self, inter, a, b):
        return inter * self.den >= self.num * (a + b - inter)

    def most(self, a, b):
        """Of elements by which linked sets of these sizes differ."""
        return ((self.den - self.num) * (a + b)) // (self.den + self.num)

    def families(self, n: int) -> list[int]:
        """Upper bounds r of the families that a set of n elements takes part in."""
        own = 4
        while own < n:
            own *= 2
        return [own] if n * self.den <= own * self.num else [own, own * 2]

    def first_parts(self, r: int) -> int:
        """First parts of a family: enough for one that differs in SPARE elements at most, and some to choose from."""
        return max(r // 5, self.most(r, r) // (SPARE + 1) + 1)

    def emits(self, n: int, r: int) -> int:
        """Signatures that a set of n elements emits in a family: one more than can differ from a linked set's."""
        n1 = self.first_parts(r)
        return min(n1 * comb(SECOND, SPARE), spoilt(self.most(n, min(r, n * self.den // self.num)), n1) + 1)


def spoilt(k: int, n1: int) -> int:
    """Most signatures that k differing elements can change: the d-th one in a first part adds less than the one before, so
    that they change most where they are spread evenly."""
    out = 0
    for d in range(SPARE + 1):
        here = min(k, n1)
        out += here * (comb(SECOND - d, SPARE - d) - (comb(SECOND - d - 1, SPARE - d - 1) if d < SPARE else 0))
        k -= here
    return out


@lru_cache(100_000)
def _plan(rule_num: int, rule_den: int, n: int) -> tuple[tuple[int, int, int], ...]:
    """(family, first parts, signatures to emit) for a set of n elements."""
    rule = Rule(rule_num, rule_den)
    return tuple((r, rule.first_parts(r), rule.emits(n, r)) for r in rule.families(n))


def signatures(sets: np.ndarray, offsets: np.ndarray, ids: np.ndarray, rule: Rule, common: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Signatures of each set, and the ids of their sets."""
    rare = np.ones(len(sets), np.int64)
    if len(common):
        rare[common[np.minimum(np.searchsorted(common, sets), len(common) - 1)] == sets] = 0
    sizes = np.diff(offsets)
    plans = [(i, *p) for i, n in enumerate(sizes.tolist()) if n for p in _plan(rule.num, rule.den, n)]
    if not plans:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    who, family, n1, most = (np.array(x, np.int64) for x in zip(*plans, strict=True))
    # every set once for each of its families: its elements, and where its first parts begin
    n = sizes[who]
    begins = np.cumsum(np.r_[0, n])
    at = np.arange(begins[-1]) - np.repeat(begins[:-1] - offsets[who], n)
    x = sets[at]
    salted = x * np.uint64(0x9FB21C651E98DF25) ^ np.repeat(family.astype(np.uint64), n)
    salted ^= salted >> np.uint64(29)
    top = np.cumsum(np.r_[0, n1])
    first = ((salted >> np.uint64(11)) % np.repeat(n1.astype(np.uint64), n)).astype(np.int64) + np.repeat(top[:-1], n)
    cell = first * SECOND + ((salted * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(40)).astype(np.int64) % SECOND
    cells = int(top[-1]) * SECOND
    low, high = (np.bincount(cell, (x >> np.uint64(s) & np.uint64(0xFFFFFFFF)).astype(float), cells).astype(np.uint64) for s in (0, 32))
    held = (low + (high << np.uint64(32))).reshape(-1, SECOND)  # sums of the elements of each second part, modulo 2^64
    count, weight = (np.bincount(cell, w, cells).reshape(-1, SECOND) for w in (None, rare[at].astype(float)))
    number = np.arange(int(top[-1])) - np.repeat(top[:-1], n1)
    tag = mix(number.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93) + np.repeat(family.astype(np.uint64), n1))
    subsets = list(combinations(range(SECOND), SECOND - SPARE))
    sigs, ranks = np.empty((len(held), len(subsets)), np.uint64), np.empty((len(held), len(subsets)), np.uint64)
    for j, subset in enumerate(subsets):
        own = list(subset)
        sigs[:, j] = mix(held[:, own].sum(1, dtype=np.uint64) + tag + np.uint64(j + 1))
        some, much = (np.minimum(v[:, own].sum(1), 4095).astype(np.uint64) for v in (weight, count))
        ranks[:, j] = (some << np.uint64(52)) | (much << np.uint64(40)) | (sigs[:, j] >> np.uint64(24))
    sigs, ranks, edges = sigs.ravel(), ranks.ravel(), (top * len(subsets)).tolist()
    out = []
    for a, b, k in zip(edges, edges[1:], most.tolist(), strict=False):
        out.append(sigs[a:b] if k >= b - a else sigs[a + np.argpartition(ranks[a:b], b - a - k)[b - a - k :]])
    return np.concatenate(out), np.repeat(ids[who], [len(o) for o in out])


def _read(docs: DataFrame, key: str, text: str) -> DataFrame:
    return docs.filter(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), F.coalesce(F.col(text), F.lit("")).alias("text"))


def _only(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """docs semi- or anti-joined with a table of ids, which is broadcast only behind a check of its size."""
    small = ids.count() * 8 <= BROADCAST_IDS
    return docs.join(F.broadcast(ids) if small else ids.hint("merge"), "id", how)


def packed(x: np.ndarray) -> bytes:
    """Histogram of a set's hashes, four cells to a byte."""
    c = FEWEST
    while c < len(x) and c < MOST:
        c *= 2
    v = np.minimum(np.bincount(((x >> np.uint64(40)) & np.uint64(c - 1)).astype(np.int64), minlength=c), 3).astype(np.uint8)
    return (v[0::4] | (v[1::4] << 2) | (v[2::4] << 4) | (v[3::4] << 6)).tobytes()


def unpacked(held: list[bytes], to: int) -> np.ndarray:
    """Histograms of one length as rows, folded to a shorter one; sums of stopped counts still bound differences."""
    b = np.frombuffer(b"".join(held), np.uint8).reshape(len(held), -1)
    v = np.empty((len(held), 4 * b.shape[1]), np.int8)
    for k in range(4):
        v[:, k::4] = (b >> (2 * k)) & 3
    v = v.astype(np.int16) if v.shape[1] > to else v
    while v.shape[1] > to:
        half = v.shape[1] // 2
        v = v[:, :half] + v[:, half:]
    return v


def differ(a: list[bytes], b: list[bytes]) -> np.ndarray:
    """For pairs of packed histograms, a number of elements by which their sets differ at least."""
    sizes = np.array([(len(x), len(y)) for x, y in zip(a, b, strict=True)])
    out = np.zeros(len(a), np.int64)
    for la, lb in {tuple(x) for x in sizes.tolist()}:
        own, to = np.flatnonzero((sizes == (la, lb)).all(1)), 4 * min(la, lb)
        step = max(1, (1 << 22) // to)
        for low in range(0, len(own), step):
            at = own[low : low + step]
            out[at] = np.abs(unpacked([a[i] for i in at], to) - unpacked([b[i] for i in at], to)).sum(1, dtype=np.int64)
    return out


def _survey(width: int):
    """Of each document: size, fingerprint of the set, histogram; and shingles that are common within a batch."""

    def run(batches):
        kinds = pa.schema([("kind", pa.int8()), ("id", pa.int64()), ("n", pa.int64()), ("f1", pa.int64()), ("f2", pa.int64()), ("cells", pa.binary())])

        def common(kept, rows):
            value, count = np.unique(np.concatenate(kept), return_counts=True)
            often = count >= max(3, rows // 400)
            m = int(often.sum())
            return pa.record_batch([pa.array(np.ones(m, np.int8)), pa.nulls(m, pa.int64()), pa.array(count[often].astype(np.int64)), pa.array(value[often].view(np.int64)), pa.nulls(m, pa.int64()), pa.nulls(m, pa.binary())], schema=kinds)

        for batch in batches:
            ids, text, kept, rows = batch.column(0), batch.column(1), [], 0
            for low, high in slices(text):
                x, at = Words(text, low, high).shingles(width)
                kept.append(x)
                rows += high - low
                if sum(map(len, kept)) >= HELD:
                    yield common(kept, rows)
                    kept, rows = [], 0
                n = np.diff(at)
                more = mix(x ^ np.uint64(0x6A09E667F3BCC909))
                sums = [np.r_[np.uint64(0), np.cumsum(v, dtype=np.uint64)] for v in (mix(x), more)]
                f1, f2 = ((s[at[1:]] - s[at[:-1]]).view(np.int64) for s in sums)
                cells = [packed(x[at[i] : at[i + 1]]) for i in range(high - low)]
                yield pa.record_batch([pa.array(np.zeros(high - low, np.int8)), ids.slice(low, high - low), pa.array(n), pa.array(f1), pa.array(f2), pa.array(cells, pa.binary())], schema=kinds)
            if kept:
                yield common(kept, rows)

    return run


def _sign(width: int, rule: Rule, common: np.ndarray, parts: int):
    """Signatures and their owners, packed, by target part."""

    def run(batches):

        def dealt(sigs, owners):
            s, o = np.concatenate(sigs), np.concatenate(owners)
            to = (s % np.uint64(parts)).astype(np.int64)
            order = np.argsort(to, kind="stable")
            s, o, edge = s[order], o[order], np.searchsorted(to[order], np.arange(parts + 1))
            full = np.flatnonzero(np.diff(edge))
            return pa.record_batch([pa.array(full.astype(np.int32)), pa.array([s[edge[p] : edge[p + 1]].tobytes() for p in full], pa.binary()), pa.array([o[edge[p] : edge[p + 1]].tobytes() for p in full], pa.binary())], ["part", "sigs", "owners"])

        for batch in batches:
            ids, text, sigs, owners = batch.column(0).to_numpy(), batch.column(1), [], []
            for low, high in slices(text):
                x, at = Words(text, low, high).shingles(width)
                s, o = signatures(x, at, ids[low:high], rule, common)
                sigs.append(s)
                owners.append(o)
                if sum(map(len, sigs)) >= HELD:
                    yield dealt(sigs, owners)
                    sigs, owners = [], []
            if sigs:
                yield dealt(sigs, owners)

    return run


def _buckets(batches):
    """kind 0: pairs that are a whole bucket of this task, each once; kind 1: members of larger buckets, of equal ones one;
    kind 2: in how many buckets of this task, of two or more, a document is."""
    s, o = [], []
    for batch in batches:
        s += [np.frombuffer(x, np.uint64) for x in batch.column(1).to_pylist()]
        o += [np.frombuffer(x, np.int64) for x in batch.column(2).to_pylist()]
    schema = pa.schema([("kind", pa.int8()), ("bucket", pa.int64()), ("a", pa.int64()), ("b", pa.int64())])
    if not s:
        return

    def rows(kind, bucket, a, b):
        for low in range(0, len(b), 50_000):
            n = len(b[low : low + 50_000])
            yield pa.record_batch([pa.array(np.full(n, kind, np.int8)), *(pa.nulls(n, pa.int64()) if x is None else pa.array(x[low : low + 50_000]) for x in (bucket, a, b))], schema=schema)

    s, o = np.concatenate(s), np.concatenate(o)
    order = np.lexsort((o, s))
    s, o = s[order], o[order]
    new = np.r_[True, (s[1:] != s[:-1]) | (o[1:] != o[:-1])]  # a repeated row counts once
    s, o = s[new], o[new]
    cut = np.flatnonzero(np.r_[True, s[1:] != s[:-1]])
    size = np.diff(np.r_[cut, len(s)])
    two = cut[size == 2]
    pairs = np.unique(np.stack([o[two], o[two + 1]], 1), axis=0)
    yield from rows(0, None, pairs[:, 0], pairs[:, 1])
    sums = np.add.reduceat(mix(o.view(np.uint64)), cut)
    _, first = np.unique(np.where(size > 2, sums, 0), return_index=True)
    take = np.zeros(len(cut), bool)
    take[first] = True
    take &= size > 2
    held = np.flatnonzero(np.repeat(take, size))
    yield from rows(1, np.repeat(sums, size)[held].view(np.int64), None, o[held])
    who, times = np.unique(o[np.repeat(size > 2, size)], return_counts=True)
    yield from rows(2, None, who, times.astype(np.int64))


def _bound(rule: Rule):
    """Of pairs with both histograms: the least number of elements by which the sets differ, and if they may link."""

    def run(batches):
        for batch in batches:
            a, b, na, nb = (batch.column(i).to_numpy() for i in range(4))
            if not len(a):
                continue
            least = differ(batch.column(4).to_pylist(), batch.column(5).to_pylist())
            yield pa.record_batch([pa.array(a), pa.array(b), pa.array(na), pa.array(nb), pa.array(least), pa.array(least <= rule.most(na, nb))], ["a", "b", "na", "nb", "least", "may"])

    return run


def _exact(batches):
    for batch in batches:
        sets = [[np.frombuffer(x, np.uint64) for x in batch.column(i).to_pylist()] for i in (2, 3)]
        inter = [len(np.intersect1d(x, y, assume_unique=True)) for x, y in zip(*sets, strict=True)]
        yield pa.record_batch([batch.column(0), batch.column(1), pa.array(inter, pa.int64())], ["a", "b", "inter"])


def _sets(width: int):
    def run(batches):
        for batch in batches:
            for low, high in slices(batch.column(1)):
                x, at = Words(batch.column(1), low, high).shingles(width)
                yield pa.record_batch([batch.column(0).slice(low, high - low), pa.array([x[at[i] : at[i + 1]].tobytes() for i in range(high - low)], pa.binary())], ["id", "held"])

    return run


def _across(rule: Rule):
    """Pairs within sorted blocks (bucket, bi, bj): different components, and neither the sizes, the distances to the
    bucket's head nor the histograms rule a link out."""
    reach = (rule.den - rule.num) / rule.den + 1e-9

    def of(bucket, rows):
        blk, bi, bj, d, comp, n, low, high, cells, least = rows
        members = [set(x) for x in least]
        first, second = np.flatnonzero(blk == bi), np.flatnonzero(blk == bj)
        size = np.array([4 * len(c) for c in cells])
        level, rough = {}, {}
        for c in set(size.tolist()):
            grid = np.zeros((len(cells), c), np.int16)
            for s in {s for s in size.tolist() if s >= c}:
                at = np.flatnonzero(size == s)
                grid[at] = unpacked([cells[i] for i in at], c)
            level[c], rough[c] = grid, grid.reshape(len(cells), 4, -1).sum(1, dtype=np.int16)
        out = []
        for i in first:
            js = second[second > i] if bi == bj else second
            js = js[(comp[js] != comp[i]) & (n[js] * rule.den >= n[i] * rule.num) & (n[i] * rule.den >= n[js] * rule.num) & (low[js] - high[i] <= reach) & (low[i] - high[js] <= reach)]
            shared = np.minimum(size[js], size[i])
            for c in set(shared.tolist()):
                at = js[shared == c]
                for grid in (rough[c], level[c]):
                    at = at[np.abs(grid[at] - grid[i]).sum(1, dtype=np.int64) <= rule.most(n[at], n[i])]
                for j in at:  # of the buckets that both lists name, only the first one tells of the pair
                    if d[i] != d[j] and min(members[i] & members[j], default=bucket) == bucket:
                        out.append((d[i], d[j], n[i], n[j]) if d[i] < d[j] else (d[j], d[i], n[j], n[i]))
        return out

    def run(batches):
        held, seen = None, set()
        for batch in [*batches, None]:
            if batch is not None and not batch.num_rows:
                continue
            if batch is not None:
                cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(9)] + [np.array([*batch.column(9).to_pylist(), None], object)[:-1], np.array([*map(tuple, batch.column(10).to_pylist()), None], object)[:-1]]
                held = cols if held is None else [np.concatenate([x, y]) for x, y in zip(held, cols, strict=True)]
            if held is None:
                return
            bucket, bi, bj = held[:3]
            cut = np.flatnonzero(np.r_[True, (bucket[1:] != bucket[:-1]) | (bi[1:] != bi[:-1]) | (bj[1:] != bj[:-1])])
            ends = np.r_[cut[1:], len(bucket)]
            whole = len(cut) if batch is None else len(cut) - 1
            found = []
            for a, b in zip(cut[:whole], ends[:whole], strict=True):
                if b - a > 1:
                    got = of(bucket[a], [held[3][a:b], bi[a], bj[a], *(x[a:b] for x in held[4:])])
                    found += [p for p in got if p not in seen]
                    if len(seen) < 1_000_000:
                        seen.update(found)
            if found:
                p = np.array(found, np.int64)
                yield pa.record_batch([pa.array(p[:, k]) for k in range(4)], ["a", "b", "na", "nb"])
            held = [x[cut[whole] :] for x in held] if whole < len(cut) else None

    return run


def _within(rule: Rule, told: bool):
    """Links within sorted blocks (component, bi, bj): pairs if told, otherwise the rows that each class links with."""

    def of(bi, bj, blk, ids, rows, sets):
        first, second = np.flatnonzero(blk == bi), np.flatnonzero(blk == bj)
        n = np.array([len(x) for x in sets])
        owner = np.repeat(np.arange(len(sets)), n)
        _, code, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        keep = np.flatnonzero(count[code] > 1)
        keep = keep[np.argsort(code[keep], kind="stable")]
        owner, code = owner[keep], code[keep]
        code = np.cumsum(np.r_[False, code[1:] != code[:-1]][: len(code)])
        inter = np.zeros((len(first), len(second)), np.int64)
        for low in range(0, int(code[-1]) + 1 if len(code) else 0, TAKEN):
            a, b = np.searchsorted(code, [low, low + TAKEN])
            x = np.zeros((len(sets), int(code[b - 1]) - low + 1), np.float32)
            x[owner[a:b], code[a:b] - low] = 1
            inter += (x[first] @ x[second].T).astype(np.int64)
        ok = rule.links(inter, n[first][:, None], n[second][None])
        i, j = np.nonzero(np.triu(ok, 1) if bi == bj else ok)
        a, b = first[i], second[j]
        if told:
            turn = ids[a] > ids[b]
            a, b, inter = np.where(turn, b, a), np.where(turn, a, b), inter[i, j]
            return [ids[a], ids[b], inter, n[a], n[b]]
        sums = np.bincount(a, rows[b], len(ids)) + np.bincount(b, rows[a], len(ids))
        some = np.flatnonzero(sums)
        return [ids[some], sums[some].astype(np.int64)]

    def run(batches):
        held = None
        for batch in _ended(batches):
            if batch is not None:
                cols = [batch.column(i).to_numpy() for i in range(6)] + [np.array([*(np.frombuffer(x, np.uint64) for x in batch.column(6).to_pylist()), None], object)[:-1]]
                held = cols if held is None else [np.concatenate([x, y]) for x, y in zip(held, cols, strict=True)]
            if held is None:
                return
            comp, bi, bj = held[:3]
            cut = np.flatnonzero(np.r_[True, (comp[1:] != comp[:-1]) | (bi[1:] != bi[:-1]) | (bj[1:] != bj[:-1])])
            ends = np.r_[cut[1:], len(comp)]
            whole = len(cut) if batch is None else len(cut) - 1
            found = [of(bi[a], bj[a], *(x[a:b] for x in held[3:6]), held[6][a:b].tolist()) for a, b in zip(cut[:whole], ends[:whole], strict=True) if b - a > 1]
            if found:
                yield pa.record_batch([pa.array(np.concatenate(x).astype(np.int64)) for x in zip(*found, strict=True)], ["a", "b", "inter", "na", "nb"] if told else ["id", "links"])
            held = [x[cut[whole] :] for x in held] if whole < len(cut) else None

    return run


def _ended(batches):
    """Batches that hold rows, and None after the last."""
    for batch in batches:
        if batch.num_rows:
            yield batch
    yield None


def _linked(read: DataFrame, member: DataFrame, comps: DataFrame, width: int, rule: Rule, told: bool) -> DataFrame:
    """All links between the classes of each component, see _within."""
    sized = member.groupBy(F.col("rep").alias("id")).agg(F.count("*").alias("rows"))
    own = staged(comps.join(sized, "id").select("component", "id", "rows"), "linked")
    kinds = "a long, b long, inter long, na long, nb long" if told else "id long, links long"
    if own.isEmpty():
        return read.sparkSession.createDataFrame([], kinds)
    held = staged(_only(read, own.select("id"), "left_semi").mapInArrow(_sets(width), "id long, held binary").dropDuplicates(["id"]), "sets")
    count = F.ceil(F.col("m") / LINKED).cast("int")
    side = own.join(own.groupBy("component").agg(F.count("*").alias("m")), "component")
    side = side.withColumn("blk", F.pmod(F.xxhash64("id"), count).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), count - 1)))
    side = side.select("component", F.least("blk", "other").alias("bi"), F.greatest("blk", "other").alias("bj"), "blk", "id", "rows").join(held, "id").select("component", "bi", "bj", "blk", "id", "rows", "held")
    side = side.repartition(partitions(read.sparkSession), "component", "bi", "bj").sortWithinPartitions("component", "bi", "bj")
    out = staged(side.mapInArrow(_within(rule, told), kinds), "links")
    forget(held)
    return out


def _with_unnamed(out: DataFrame, docs: DataFrame, key: str) -> DataFrame:
    """out and, with nulls, the rows of docs whose key is null: they can be no one's link."""
    return out.unionByName(docs.filter(F.col(key).isNull()).select(F.lit(None).cast("long").alias(key)), allowMissingColumns=True)


def join(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = 5, rule: Rule | None = None) -> DataFrame:
    """(key, n_shingles, class_id, component_id, n_links) for every row, see classes; n_links: the other rows that it links
    with, those of an equal set included."""
    read, member, comps = _grouped(docs, key, text, width, rule or Rule())
    links = _linked(read, member, comps, width, rule or Rule(), False).groupBy("id").agg(F.sum("links").alias("links"))
    sized = member.groupBy(F.col("rep").alias("id")).agg(F.count("*").alias("rows"))
    known = sized.join(comps, "id", "left").join(links, "id", "left").select(F.col("id").alias("rep"), "component", (F.col("rows") - 1 + F.coalesce("links", F.lit(0))).alias("links"))
    out = member.join(known, "rep")
    return _with_unnamed(out.select(F.col("id").alias(key), F.col("n").alias("n_shingles"), F.col("rep").alias("class_id"), F.coalesce("component", "rep").alias("component_id"), F.when(F.col("n") > 0, F.col("links")).otherwise(0).alias("n_links")), docs, key)


def pairs(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = 5, rule: Rule | None = None) -> DataFrame:
    """(a, b, inter, na, nb) for every two linked classes, a < b: their class_id, and the elements shared and held."""
    return _linked(*_grouped(docs, key, text, width, rule or Rule()), width, rule or Rule(), True)


def classes(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = 5, rule: Rule | None = None) -> DataFrame:
    """(key, n_shingles, class_id, component_id) for every row, without the links within components.

    class_id: the smallest key with the same set; component_id: the smallest key reachable by links. Null and empty
    texts have no shingles and link with nothing; repeated rows are equal sets; keys are taken to be unique integers. A row with a null key has nulls in all columns.
    Links between classes are exact for 64-bit shingle hashes. Extra columns of docs are not read."""
    _, member, comps = _grouped(docs, key, text, width, rule or Rule())
    out = member.join(comps.withColumnRenamed("id", "rep"), "rep", "left")
    return _with_unnamed(out.select(F.col("id").alias(key), F.col("n").alias("n_shingles"), F.col("rep").alias("class_id"), F.coalesce("component", "rep").alias("component_id")), docs, key)


def _grouped(docs: DataFrame, key: str, text: str, width: int, rule: Rule) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(id, text) and (id, n, rep) of every row, and (id, component) of every class with a link."""
    spark = docs.sparkSession
    ship(spark)
    read = _read(docs, key, text)
    survey = staged(read.mapInArrow(_survey(width), "kind byte, id long, n long, f1 long, f2 long, cells binary"), "survey")
    rows = survey.filter("kind = 0")
    total = rows.count()
    # at most mean set size / 0.0025 shingles can be this common; the order they give changes no result
    common = survey.filter("kind = 1").groupBy("f1").agg(F.sum("n").alias("n")).filter(F.col("n") * 400 >= total).orderBy(F.desc("n"), "f1").limit(100_000).select("f1").toArrow()
    common = np.sort(common["f1"].to_numpy().view(np.uint64)) if common.num_rows else np.zeros(0, np.uint64)
    groups = rows.filter("n > 0").groupBy("f1", "f2", "n").agg(F.min("id").alias("rep"))
    member = staged(rows.select("id", "f1", "f2", "n").join(groups, ["f1", "f2", "n"], "left").select("id", "n", F.coalesce("rep", "id").alias("rep")), "member")

    parts = max(partitions(spark), -(-(rows.agg(F.sum("n")).first()[0] or 0) // DEALT))
    # empty sets and all but one of each class have nothing to sign
    quiet = member.filter("id <> rep").select("id").distinct()
    signed = _only(read, quiet, "left_anti").mapInArrow(_sign(width, rule, common, parts), "part int, sigs binary, owners binary")
    found = staged(signed.repartition(parts, "part").mapInArrow(_buckets, "kind byte, bucket long, a long, b long"), "buckets")
    if found.isEmpty():  # no two classes share a signature
        return read, member, found.select(F.col("a").alias("id"), F.col("b").alias("component")).limit(0)
    sketch = rows.select("id", "n", "cells")

    def both(pairs: DataFrame, table: DataFrame, names: list[str]) -> DataFrame:
        for end in ("a", "b"):
            pairs = pairs.join(table.select(F.col("id").alias(end), *(F.col(c).alias(f"{end}_{c}") for c in names)), end)
        return pairs

    def checked(pairs: DataFrame) -> DataFrame:
        """(a, b, inter, na, nb) of pairs that the sizes and histograms let pass."""
        texts = _only(read, staged(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), "ids"), "left_semi")
        held = staged(texts.mapInArrow(_sets(width), "id long, held binary").dropDuplicates(["id"]), "sets")
        out = staged(both(pairs.select("a", "b"), held, ["held"]).select("a", "b", "a_held", "b_held").mapInArrow(_exact, "a long, b long, inter long").join(pairs.select("a", "b", "na", "nb"), ["a", "b"]), "checked")
        forget(held)
        return out

    # the head of a bucket is the member found in most buckets: the original of a group of altered copies, if it is there
    sets = found.filter("kind = 1").select("bucket", "b").distinct()
    degree = found.filter("kind = 2").groupBy(F.col("a").alias("b")).agg(F.sum("b").alias("degree"))
    sets = staged(sets.join(degree, "b").select("bucket", "b", "degree"), "sets")
    heads = sets.groupBy("bucket").agg(F.max(F.struct("degree", (-F.col("b")).alias("minus"))).alias("h")).select("bucket", (-F.col("h.minus")).alias("head"))
    stars = staged(sets.join(heads, "bucket").select("bucket", "head", "b", F.least("head", "b").alias("x"), F.greatest("head", "b").alias("y")), "stars")
    pairs = found.filter("kind = 0").select("a", "b").union(stars.filter("x < y").select("x", "y")).distinct()
    one = sketch.dropDuplicates(["id"])
    sized = both(pairs, one, ["n", "cells"]).filter(F.least("a_n", "b_n") * rule.den >= F.greatest("a_n", "b_n") * rule.num)
    bounded = staged(sized.select("a", "b", "a_n", "b_n", "a_cells", "b_cells").mapInArrow(_bound(rule), "a long, b long, na long, nb long, least long, may boolean"), "bounded")
    star = checked(bounded.filter("may").select("a", "b", "na", "nb"))
    link = F.expr(f"inter * {rule.den} >= {rule.num} * (na + nb - inter)")
    links = star.filter(link).select("a", "b")
    comps = staged(connected(links), "components")

    # what a bucket holds beyond one component
    placed = stars.join(comps.withColumnRenamed("id", "b"), "b", "left").select("bucket", F.col("x").alias("a"), F.col("y").alias("c"), "b", F.coalesce("component", "b").alias("comp"))
    mixed = placed.groupBy("bucket").agg(F.count("*").alias("m"), F.min("comp").alias("c0"), F.max("comp").alias("c1")).filter("c0 < c1").select("bucket", "m")
    # distance to the head: exact where checked; else at least what the histogram says; sizes alone where they rule it out
    known = bounded.select("a", "b", "na", "nb", "least").join(star.select("a", "b", "inter"), ["a", "b"], "left")
    far = lambda inter: 1 - F.greatest(inter, F.lit(0.0)) / (F.col("na") + F.col("nb") - F.greatest(inter, F.lit(0.0)))
    known = known.select("a", F.col("b").alias("c"), far(F.coalesce(F.col("inter").cast("double"), (F.col("na") + F.col("nb") - F.col("least")) / 2)).alias("low"), F.when(F.col("inter").isNotNull(), far(F.col("inter").cast("double"))).otherwise(1.0).alias("high"))
    # each document's first buckets, so that a pair of many shared buckets is told once; a document has no more buckets than signatures
    inside = staged(placed.join(mixed, "bucket"), "mixed")
    if inside.isEmpty():
        return read, member, comps
    first = inside.groupBy("b").agg(F.slice(F.array_sort(F.collect_set("bucket")), 1, FIRST).alias("least"))
    side = inside.join(first, "b").join(known, ["a", "c"], "left").join(one.withColumnRenamed("id", "b"), "b")
    side = side.select("bucket", "m", "b", "comp", "n", F.when(F.col("a") == F.col("c"), 0.0).otherwise(F.coalesce("low", F.lit(0.0))).alias("low"), F.when(F.col("a") == F.col("c"), 0.0).otherwise(F.coalesce("high", F.lit(1.0))).alias("high"), "cells", "least")
    count = F.ceil(F.col("m") / BLOCK).cast("int")
    blk = F.pmod(F.xxhash64("b"), count).cast("int")
    side = side.withColumn("blk", blk).withColumn("other", F.explode(F.sequence(F.lit(0), count - 1)))
    side = side.select("bucket", F.least("blk", "other").alias("bi"), F.greatest("blk", "other").alias("bj"), "blk", "b", "comp", "n", "low", "high", "cells", "least")
    side = side.repartition(parts, "bucket", "bi", "bj").sortWithinPartitions("bucket", "bi", "bj")
    across = side.mapInArrow(_across(rule), "a long, b long, na long, nb long").distinct()
    more = staged(across.join(star.select("a", "b"), ["a", "b"], "left_anti"), "across")
    if not more.isEmpty():
        extra = checked(more).filter(link).select("a", "b")
        if not extra.isEmpty():
            comps = staged(connected(links.union(extra)), "components")
    return read, member, comps


def keep_first(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs without the rows whose component holds a smaller key."""
    drop = classes(docs, key, text).filter(F.col("component_id") < F.col(key)).select(F.col(key).alias("id")).distinct()
    small = drop.count() * 8 <= BROADCAST_IDS
    return docs.join(F.broadcast(drop) if small else drop.hint("merge"), docs[key] == drop["id"], "left_anti")
