"""Tiers of patterns by ascending probes, and the prefix walks."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import cut
from . import bloom, layers
from .layers import TableModel, TierFilter
from .tree import PackedTree


@dataclass(frozen=True)
class KindModel:
    """The structures of one kind: filters by tier, perhaps a tree above them.
    Filters of any size may be a TableModel, for batches only."""

    kind: str
    filters: dict[int, TierFilter] | TableModel = field(repr=False)
    tree: PackedTree | None = None
    frontier: bool = True
    #: (key, tier) of the tree as a table; the packed tree is all that the driver holds.
    tree_table: DataFrame | None = field(default=None, repr=False, compare=False)

    @property
    def tree_keys(self) -> dict[str, int]:
        """The keys of the tree on this process, for local probes."""
        if self.tree_table is None:
            return {}
        rows = self.tree_table.select("key", "tier").toArrow()  # pack() has checked their number
        return dict(zip(rows["key"].to_pylist(), rows["tier"].to_pylist()))

    def high(self, spark: SparkSession) -> DataFrame:
        """(key, tree_tier) of the keys of the tree."""
        if self.tree_table is None:
            return spark.createDataFrame([], "key string, tree_tier int")
        return self.tree_table.select("key", F.col("tier").alias("tree_tier"))

    @property
    def inline(self) -> bool:
        """Whether all filters together may be one expression in a plan."""
        words = sum(len(b.words) for f in self.filters.values() for b in f.blooms)
        return words <= bloom.MAX_INLINE and all(f.inline for f in self.filters.values())

    def tier(self, key: str) -> int:
        if self.tree is not None and (found := self.tree.tier(key)) is not None:
            return found
        return next((t for t in sorted(self.filters) if self.filters[t].accepts(key)), 1)

    def walk(self, key: str, rule: str = "monotone") -> int:
        """The walk from short to long prefixes: tier 1 settles it at once."""
        last = None
        for i in range(1, len(key) + 1):
            t = self.tier(key[:i])
            if t == 1 or rule == "monotone" and last is not None and last < t:
                return 1
            last = min(last, t) if rule == "min" and last is not None else t
        return last or 1


def direct_col(key: Column, model: KindModel) -> Column:
    """First tier whose filter accepts, in ascending order; none: tier 1. Each
    branch is evaluated only if those before it refused."""
    out = F.lit(1)
    for t in sorted(model.filters, reverse=True):
        out = F.when(model.filters[t].accepts_col(key), t).otherwise(out)
    return out.cast("int")


def _by_arrays(patterns: DataFrame, model: KindModel) -> DataFrame:
    """patterns with tier by filters that are too large for a plan: tasks hold
    their words as arrays and ask tiers in ascending order, and a join with the
    last layers decides where no Bloom layer has."""
    spark = patterns.sparkSession
    shared = spark.sparkContext.broadcast([(t, f.blooms) for t, f in sorted(model.filters.items())])
    names = patterns.columns

    def run(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            keys = batch.column("key").to_pylist()
            sure, asked = np.zeros(len(keys), np.int32), [[] for _ in keys]
            live = np.array([i for i, k in enumerate(keys) if k is not None], np.int64)
            ready = bloom.prepared(keys, [f for _, blooms in shared.value for f in blooms])
            for t, blooms in shared.value:
                left = live
                for j, f in enumerate(blooms, 1):
                    ok = bloom.hits(f, ready[left])
                    if j % 2 == 0:
                        sure[left[~ok]] = t
                    left = left[ok]
                for i in left:
                    asked[i].append(t)
                live = live[sure[live] == 0]
            more = [pa.array(sure), pa.array(asked, pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *more], names=[*names, "_sure", "_asked"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in patterns.schema)
    out = bloom.dealt(patterns).mapInArrow(run, f"{kinds}, _sure int, _asked array<int>")
    last = layers.listed(spark, model.filters).groupBy("key").agg(F.collect_list("tier").alias("_in"))
    none = F.array().cast("array<int>")
    odd = F.array(*[F.lit(t) for t, f in model.filters.items() if f.layers % 2]).cast("array<int>")
    held = F.coalesce("_in", none)
    yes = F.filter("_asked", lambda t: F.array_contains(held, t) == F.array_contains(odd, t))
    tier = F.coalesce(F.get(yes, F.lit(0)), F.when(F.col("_sure") > 0, F.col("_sure")), F.lit(1))
    return out.join(last, "key", "left").select(*names, tier.cast("int").alias("tier"))


def direct(patterns: DataFrame, model: KindModel) -> DataFrame:
    """patterns (key, ...) with tier. The tree, where there is one, is asked first."""
    if isinstance(model.filters, TableModel):
        found = model.filters.tiers(patterns.select("key").distinct()).withColumnRenamed("tier", "_tier")
        out = patterns.join(found, "key").withColumnRenamed("_tier", "tier").withColumn("tier", F.col("tier").cast("int"))
        if model.tree is None:
            return out.select(*patterns.columns, "tier")
        return out.join(model.high(patterns.sparkSession), "key", "left").select(*patterns.columns, F.coalesce("tree_tier", "tier").alias("tier"))
    if not model.inline:
        out = _by_arrays(patterns, model)
        if model.tree is None:
            return out
        met = out.join(model.high(patterns.sparkSession), "key", "left")
        return met.select(*patterns.columns, F.coalesce("tree_tier", "tier").alias("tier"))
    if model.tree is None:
        return patterns.withColumn("tier", direct_col(F.col("key"), model))
    met = patterns.join(model.high(patterns.sparkSession), "key", "left")
    return met.withColumn("tier", F.coalesce("tree_tier", direct_col(F.col("key"), model))).drop("tree_tier")


def trace(patterns: DataFrame, model: KindModel) -> DataFrame:
    """patterns with tier and trace: for each tier asked, the layer that decided
    and whether it accepted."""
    steps = [F.struct(F.lit(t).alias("tier"), f.decided(F.col("key")).alias("layer"), f.accepts_col(F.col("key")).alias("accepted")) for t, f in sorted(model.filters.items())]
    out = direct(patterns, model)
    seen = F.filter(F.array(*steps), lambda s: (F.col("tier") == 1) | (s.tier <= F.col("tier")))
    return out.withColumn("trace", seen if steps else F.array())


def _chain(patterns: DataFrame) -> DataFrame:
    """(pid, at, key) of the prefixes of patterns (pid, key, ...)."""
    return patterns.select("pid", F.posexplode(F.transform(F.sequence(F.lit(1), F.length("key")), lambda i: F.substring(F.col("key"), 1, i))).alias("at", "key"))


def prefix_tiers(patterns: DataFrame, model: KindModel) -> DataFrame:
    """(key, tier) of all different prefixes, written: what walks under several
    rules over the same patterns start from."""
    return cut(direct(_chain(patterns).select("key").distinct(), model))


def walk(patterns: DataFrame, model: KindModel, rule: str = "monotone", known: DataFrame | None = None) -> DataFrame:
    """patterns (pid, key, ...) with the tier that all prefixes of the key agree on.

    rule 'min': tier 1 if any prefix is in it, else the least tier seen. rule
    'monotone': tier 1 also if a shorter prefix is in a lower tier than a longer
    one, which no pattern with matches can show; else the key's own tier. Each
    different prefix is classified once, however many patterns share it. known
    has their tiers, where prefix_tiers has found them before.
    """
    chain = _chain(patterns)
    if known is None:
        known = prefix_tiers(patterns, model) if rule == "monotone" else direct(chain.select("key").distinct(), model)
    if rule == "monotone":
        up = known.select(F.col("key").alias("_up"), F.col("tier").alias("_above"))
        known = known.join(up, F.expr("left(key, length(key) - 1)") == F.col("_up"), "left")
        known = known.select("key", "tier", ((F.col("tier") == 1) | (F.coalesce("_above", "tier") < F.col("tier"))).alias("settled"))
        found = F.when(F.max("settled"), 1).otherwise(F.max_by("tier", "at"))
    else:
        found = F.min("tier")
    own = chain.join(known, "key").groupBy("pid").agg(found.alias("tier"))
    return patterns.join(own, "pid", "left").withColumn("tier", F.coalesce("tier", F.lit(1)))
