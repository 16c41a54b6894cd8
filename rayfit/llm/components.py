"""Connected components of a table of links, by contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import staged


def _roots(edges: DataFrame) -> DataFrame:
    """(id, p) for every id in edges (a, b): the root of its tree, where each id hangs on its smallest neighbour.

    Such pointers have cycles of two ids only, of which the smaller becomes the root. Parents are replaced by their own
    parents until none moves: as many steps as the logarithm of the deepest tree, and one that finds nothing."""
    a, b = F.col("a"), F.col("b")
    near = staged(edges.unionByName(edges.select(b.alias("a"), a.alias("b"))).groupBy(a.alias("id")).agg(F.min("b").alias("q")), "nearest")
    back = near.select(F.col("id").alias("q"), F.col("q").alias("back"))
    to = near.join(back, "q").select("id", F.when((F.col("back") == F.col("id")) & (F.col("id") < F.col("q")), F.col("id")).otherwise(F.col("q")).alias("p"))
    to = staged(to, "parents")
    while True:
        above = to.select(F.col("id").alias("p"), F.col("p").alias("above"))
        to = staged(to.join(above, "p").select("id", F.col("above").alias("p"), (F.col("p") != F.col("above")).alias("moved")), "parents")
        if to.filter("moved").isEmpty():
            return to.select("id", "p")
        to = to.select("id", "p")


def connected(links: DataFrame) -> DataFrame:
    """(id, component) for every id in links (a, b): component is the smallest id it can reach.

    Each round hangs every id on its smallest neighbour and replaces both ends of each link by the roots of their trees;
    links within one tree go. Every tree has two ids or more, so a round at least halves the ids that still have links,
    whatever their order: rounds are as many as the logarithm of the largest component at most, and one for a star, a
    clique or a rising chain. The rounds' maps are then applied from last to first, and the smallest id of each root is
    told. Each round is written to the shared folder. Minima are combined before the shuffle, and hubs meet only in joins
    that can be split. Nulls and self-links carry nothing. An empty table gives an empty one."""
    a, b = F.col("a"), F.col("b")
    edges = staged(links.select(a.cast("long"), b.cast("long")).filter("a <> b").select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b")).distinct(), "edges")
    maps = []
    while not edges.isEmpty():
        to = _roots(edges)
        maps.append(to)
        moved = edges.join(to.select(F.col("id").alias("a"), F.col("p").alias("pa")), "a").join(to.select(F.col("id").alias("b"), F.col("p").alias("pb")), "b")
        edges = staged(moved.filter("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(), "edges")
    if not maps:
        return links.select(a.cast("long").alias("id"), a.cast("long").alias("component")).limit(0)
    out = maps[-1].select("id", F.col("p").alias("root"))
    for to in reversed(maps[:-1]):
        below = out.select(F.col("id").alias("p"), F.col("root").alias("deeper"))
        out = to.join(below, "p", "left").select("id", F.coalesce("deeper", "p").alias("root"))
    least = out.groupBy("root").agg(F.min("id").alias("component"))
    return out.join(least, "root").select("id", "component")
