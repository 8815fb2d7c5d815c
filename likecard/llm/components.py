"""Connected components of a graph given as an edge table: distributed
union-find by contraction, in DataFrame operations only."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut

_HALF = 0xFFFFFFFF


def _scramble(x: Column) -> Column:
    """A bijection of 64-bit integers (three Feistel rounds), so that 'smallest'
    means a random order and chains of consecutive ids contract fast."""
    left, right = F.shiftrightunsigned(x, 32).bitwiseAND(F.lit(_HALF)), x.bitwiseAND(F.lit(_HALF))
    for salt in (11, 23, 37):
        left, right = right, left.bitwiseXOR(F.xxhash64(right, F.lit(salt)).bitwiseAND(F.lit(_HALF)))
    return F.shiftleft(left, 32).bitwiseOR(right)


def _unscrambled(y: Column) -> Column:
    left, right = F.shiftrightunsigned(y, 32).bitwiseAND(F.lit(_HALF)), y.bitwiseAND(F.lit(_HALF))
    for salt in (37, 23, 11):
        left, right = right.bitwiseXOR(F.xxhash64(left, F.lit(salt)).bitwiseAND(F.lit(_HALF))), left
    return F.shiftleft(left, 32).bitwiseOR(right)


def components(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """(node, component) for every node that has an edge to another; component is the
    smallest node id reachable.

    Each round every node points to the least (in scrambled order) of itself and
    its neighbours, edges are redrawn between pointers, and loops and repeats
    go: nodes shrink by a constant factor a round. Minima are pre-aggregated
    before each shuffle, and both sides of each join are written tables, so a
    hot node is split by adaptive execution. Null ends and self loops are
    dropped; an empty edge table gives an empty result.
    """
    a, b = _scramble(F.col(src).cast("long")), _scramble(F.col(dst).cast("long"))
    live = edges.filter(F.col(src).isNotNull() & F.col(dst).isNotNull() & (F.col(src) != F.col(dst)))
    live = cut(live.select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b")).distinct())
    names = live.select(F.explode(F.array("a", "b")).alias("at")).distinct().withColumn("node", _unscrambled(F.col("at")))
    while not live.isEmpty():
        ends = live.select(F.explode(F.array(F.struct(F.col("a").alias("x"), F.col("b").alias("y")), F.struct(F.col("b").alias("x"), F.col("a").alias("y")))).alias("e")).select("e.*")
        to = cut(ends.groupBy("x").agg(F.least(F.col("x"), F.min("y")).alias("p")))
        names = names.join(to.withColumnRenamed("x", "at"), "at", "left").select("node", F.coalesce("p", "at").alias("at"))
        pa, pb = to.select(F.col("x").alias("a"), F.col("p").alias("pa")), to.select(F.col("x").alias("b"), F.col("p").alias("pb"))
        live = live.join(pa, "a").join(pb, "b").filter("pa != pb")
        live = cut(live.select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct())
    names = cut(names)
    least = cut(names.groupBy("at").agg(F.min("node").alias("component")))
    return names.join(least, "at").select("node", "component")


def forest(pairs_a, pairs_b):
    """A spanning forest (numpy arrays of edges) of the pairs given as numpy
    arrays: as many links as nodes at most, whatever the number of pairs."""
    import numpy as np

    nodes, flat = np.unique(np.concatenate([pairs_a, pairs_b]), return_inverse=True)
    a, b = flat[: len(pairs_a)], flat[len(pairs_a) :]
    root = np.arange(len(nodes))
    while len(a):
        low, high = np.minimum(root[a], root[b]), np.maximum(root[a], root[b])
        keep = low != high
        a, b = a[keep], b[keep]
        np.minimum.at(root, high[keep], low[keep])
        while True:
            up = root[root]
            if (up == root).all():
                break
            root = up
    linked = root != np.arange(len(nodes))
    return nodes[linked], nodes[root[linked]]


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
