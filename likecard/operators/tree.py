"""The upper tree: keys of the tiers over a threshold, in one contiguous array."""

from __future__ import annotations

import struct
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .ranking import running_sum

MAX_NODES = 4_000_000


def nodes(catalog: DataFrame, threshold: int) -> DataFrame:
    """(node_id, parent_id, key, ch, tier, first_child, is_last), numbered by
    length, then key: children of a node are consecutive. Every prefix of a key
    over the threshold is over it too, so the keys are the nodes. Numbers count
    within ranges of keys and add up over ranges."""
    top = catalog.filter(F.col("tier") > threshold).select("key", "len", "tier")
    own = running_sum(top, ["len", "key"], F.lit(1), "node_id")
    own = own.select("key", "len", "tier", F.col("node_id").cast("int").alias("node_id"), F.expr("left(key, len - 1)").alias("up"))
    ids = own.select(F.col("key").alias("up"), F.col("node_id").alias("parent_id"))
    kids = own.groupBy(F.col("up").alias("key")).agg(F.min("node_id").alias("first_child"))
    last = F.lead("node_id").over(Window.partitionBy("up").orderBy("node_id")).isNull()
    out = own.withColumn("is_last", last).join(ids, "up", "left").join(kids, "key", "left")
    return out.select("node_id", "parent_id", "key", F.expr("right(key, 1)").alias("ch"), "tier", "first_child", "is_last")


def lookup(patterns: DataFrame, tree: DataFrame) -> DataFrame:
    """patterns (key, ...) with tree_tier, null where the tree has no such key."""
    return patterns.join(tree.select("key", F.col("tier").alias("tree_tier")), "key", "left")


@dataclass(frozen=True)
class PackedTree:
    """Nodes as bytes: per node a code point (4), the first child (4, 0 if none)
    and tier and last flag (2). The published widths (4 bits, 2 bytes, 1 bit)
    hold 16 tiers and 65,536 nodes; model_bits counts those where they suffice."""

    data: bytes = field(repr=False)

    def __len__(self) -> int:
        return len(self.data) // 10

    @property
    def model_bits(self) -> int:
        n = len(self)
        return n * (8 + 4 + (16 if n < 65_536 else 32) + 1)

    def tier(self, key: str) -> int | None:
        at, found = 0, None
        for i, ch in enumerate(key):
            if i and at == 0 or not self.data:
                return None
            while True:
                code, child, flags = struct.unpack_from("<IIH", self.data, at * 10)
                if code == ord(ch):
                    found, at = flags >> 1, child
                    break
                if flags & 1:
                    return None
                at += 1
        return found


def pack(tree: DataFrame) -> PackedTree:
    """The tree on the driver; its size follows the keys of high counts only,
    and is refused over MAX_NODES."""
    if tree.count() > MAX_NODES:
        raise ValueError("upper tree too large; raise its threshold")
    import numpy as np

    node = tree.select("node_id", F.expr("cast(conv(hex(encode(ch, 'UTF-32')), 16, 10) as long)").alias("ch"), F.coalesce("first_child", F.lit(0)).alias("child"), (F.col("tier") * 2 + F.col("is_last").cast("int")).alias("flags"))
    rows = node.toArrow()
    out = np.zeros(len(rows), np.dtype([("ch", "<u4"), ("child", "<u4"), ("flags", "<u2")]))
    at = rows["node_id"].to_numpy()
    for name in out.dtype.names:
        out[name][at] = rows[name].to_numpy()
    return PackedTree(out.tobytes())
