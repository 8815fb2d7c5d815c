"""Layered tier filters: Bloom layers over members and over what they let pass,
in turn, the last layer exact."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property, reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import salt_of
from ..sources.scratch import cut
from . import bloom
from .bloom import Filter

#: Keys of a last layer that are gathered where no table may stay; more are
#: refused. Gathered keys up to which an expression lists them, and keys
#: of a table that may come to one process for local probes.
MAX_LISTED, MAX_INLINE, MAX_LOCAL = 50_000, 1_000, 2_000_000


def apart(n: int) -> bool:
    """Whether a last layer of that many keys stays a table where tables may: as
    soon as no expression lists it, for a plan of parallelized rows would be
    held by the driver and sent with every query."""
    return n > min(MAX_LISTED, MAX_INLINE)


@dataclass(frozen=True)
class TierPlan:
    """layers counts the exact one; fprs has one rate a Bloom layer."""

    layers: int = 3
    fprs: tuple[float, ...] = (0.05, 0.05)

    @staticmethod
    def uniform(layers: int, fpr: float) -> TierPlan:
        return TierPlan(layers, (fpr,) * (layers - 1))


@dataclass(frozen=True)
class TableModel:
    """The filters of all tiers as tables that nobody gathers: words (tier, layer,
    word_idx, word), the keys of the last layers (tier, key), and per tier the
    sizes of the Bloom layers and the number of layers."""

    blooms: dict[int, tuple[Filter, ...]]
    layers: dict[int, int]
    words: DataFrame = field(repr=False)
    listed: DataFrame = field(repr=False)

    def tiers(self, keys: DataFrame) -> DataFrame:
        """keys (key), each once, with tier: the first that accepts, else 1. All
        tiers are asked together, a join with the words a layer; keys that a
        layer settles go no further."""
        spark = keys.sparkSession
        if not self.layers:
            return keys.withColumn("tier", F.lit(1))
        live = keys.select(F.explode(F.array(*map(F.lit, sorted(self.layers)))).alias("tier"), "key")
        yes = spark.createDataFrame([], "tier int, key string")
        for j in range(1, max(self.layers.values())):
            now = {t: b[j - 1] for t, b in self.blooms.items() if len(b) >= j}
            asked = live.filter(F.col("tier").isin(*now))
            passed = cut(bloom.probe_by_join(asked, self.words.filter(F.col("layer") == j).drop("layer"), now))
            missed = asked.join(passed, ["tier", "key"], "left_anti")
            done = live.filter(~F.col("tier").isin(*now))
            yes = yes.unionByName(missed) if j % 2 == 0 else yes
            live = cut(passed.unionByName(done))
        odd = F.col("tier").isin(*[t for t, m in self.layers.items() if m % 2])
        hit = live.join(self.listed.withColumn("_in", F.lit(True)), ["tier", "key"], "left")
        yes = yes.unionByName(hit.filter(F.coalesce("_in", F.lit(False)) == odd).select("tier", "key"))
        first = yes.groupBy("key").agg(F.min("tier").alias("tier"))
        return keys.join(first, "key", "left").withColumn("tier", F.coalesce("tier", F.lit(1)))


@dataclass(frozen=True)
class TierFilter:
    tier: int
    layers: int
    blooms: tuple[Filter, ...]
    residual: frozenset[str] = field(default=frozenset(), repr=False)
    survivors: tuple[int, ...] = ()
    #: The last layer as (tier, key), where it is too long for residual.
    table: DataFrame | None = field(default=None, repr=False, compare=False)

    @cached_property
    def keys(self) -> frozenset[str]:
        """The keys of the last layer, on this process."""
        if self.table is None:
            return self.residual
        if self.survivors[-1] > MAX_LOCAL:
            raise ValueError(f"tier {self.tier} lists {self.survivors[-1]} keys; take more layers or lower rates")
        return frozenset(self.table.select("key").toArrow()["key"].to_pylist())

    @property
    def listed_bytes(self) -> int:
        if self.table is None:
            return sum(len(k.encode()) for k in self.residual)
        return self.table.agg(F.sum(F.octet_length("key"))).first()[0]

    @property
    def inline(self) -> bool:
        """Whether it may be an expression in a plan."""
        return self.table is None and len(self.residual) <= MAX_INLINE

    def accepts(self, key: str) -> bool:
        for j, f in enumerate(self.blooms, 1):
            if not f.has(key):
                return j % 2 == 0
        return (key in self.keys) == (self.layers % 2 == 1)

    def decided(self, key: Column) -> Column:
        """The layer that decides a key: the first whose filter lacks it, or the last."""
        out = F.lit(self.layers)
        for j, f in reversed(list(enumerate(self.blooms, 1))):
            out = F.when(~f.has_col(key), j).otherwise(out)
        return out

    def accepts_col(self, key: Column) -> Column:
        listed = key.isin(*sorted(self.keys)) if self.keys else F.lit(False)
        out = listed if self.layers % 2 else ~listed
        for j, f in reversed(list(enumerate(self.blooms, 1))):
            out = F.when(~f.has_col(key), F.lit(j % 2 == 0)).otherwise(out)
        return out

    @property
    def bits(self) -> int:
        return sum(f.n_bits for f in self.blooms)


def listed(spark: SparkSession, filters: dict[int, TierFilter]) -> DataFrame:
    """(tier, key) of the last layers of all filters."""
    rows = [(t, k) for t, f in filters.items() if f.table is None for k in sorted(f.residual)]
    own = spark.createDataFrame(rows, "tier int, key string")
    return reduce(DataFrame.unionByName, [f.table for f in filters.values() if f.table is not None], own)


def negatives(catalog: DataFrame, top: int) -> DataFrame:
    """(tier, key): for each filtered tier i from 2 to top the keys of tier 1 and
    of higher tiers; lower tiers have answered before i is asked."""
    asked = F.when(F.col("tier") == 1, F.sequence(F.lit(2), F.lit(top))).when(F.col("tier") > 2, F.sequence(F.lit(2), F.least(F.col("tier") - 1, F.lit(top))))
    return catalog.select(F.explode(asked).alias("tier"), "key") if top >= 2 else catalog.select("tier", "key").limit(0)


def _by_tier(rows: DataFrame, tiers: list[int]) -> dict[int, list[str]]:
    """The keys of (tier, key) on this process, by tier."""
    got, out = rows.filter(F.col("tier").isin(*tiers)).select("tier", "key").toArrow(), {t: [] for t in tiers}
    for t, k in zip(got["tier"].to_pylist(), got["key"].to_pylist()):
        out[t].append(k)
    return out


def _as_table(spark: SparkSession, tier: int, keys: list[str]) -> DataFrame:
    return spark.createDataFrame([(tier, k) for k in keys], "tier int, key string")


def _rest(sides: list[list[str]], j: int, plan: TierPlan, salts, tier: int, family: str, blooms: list[Filter], survivors: list[int]) -> list[str]:
    """The layers of one tier from the j-th on, of members and others that fit on
    this process: the same filters and survivors as by jobs. Returns the keys of
    the last layer."""
    import numpy as np

    while j < plan.layers and sides[(j + 1) % 2]:
        keys, fpr = sides[(j + 1) % 2], plan.fprs[j - 1]
        f = Filter(salts(j), len(keys), *bloom.sized(len(keys), fpr), fpr, family)
        f = bloom.filled(f, bloom.prepared(keys, [f]))
        ok = bloom.hits(f, bloom.prepared(sides[j % 2], [f]))
        sides[j % 2] = [sides[j % 2][i] for i in np.flatnonzero(ok)]
        blooms.append(f)
        survivors.append(len(sides[j % 2]))
        j += 1
    return sides[len(blooms) % 2]


def build(catalog: DataFrame, kind: str, plans: dict[int, TierPlan] | TierPlan, top: int, family: str = "portable", skip_first: bool = True, seed: str = "", by_join: bool = False, only: list[int] | None = None, long_lists: bool = False) -> dict[int, TierFilter] | TableModel:
    """Filters of tiers 2 to top over catalog (key, tier): all tiers advance
    together, one job or two a layer, whatever their number.

    Layer 1 holds a tier's members; layer 2 the others that layer 1 lets pass;
    layer 3 the members that layer 2 holds, and so on; the last layer lists what
    is left. A tier stops early when nothing is left. Once members and others of
    all tiers are MAX_LISTED rows at most, the layers that remain are built here. skip_first=False also
    filters tier 1, the naive form, for comparison. by_join gathers nothing: word
    tables are probed by joins, and the outcome is a TableModel. only builds
    the filters of some tiers, as after changes that made those stale. long_lists
    keeps last layers over MAX_LISTED as tables, else they are refused.
    """
    low = 2 if skip_first else 1
    plan_of = (lambda t: plans) if isinstance(plans, TierPlan) else (lambda t: plans.get(t, TierPlan()))
    members = catalog.filter((F.col("tier") >= low) & (F.col("tier") <= top)).select("tier", "key")
    dealt = bloom.dealt(catalog)
    others = negatives(dealt, top)
    if not skip_first:
        others = others.unionByName(dealt.filter("tier > 1").select(F.lit(1).alias("tier"), "key"))
    if only is not None:
        members, others = (x.filter(F.col("tier").isin(*only)) for x in (members, others))
    sides = [cut(members), others]
    size = {r.tier: r["count"] for r in sides[0].groupBy("tier").count().collect()}
    tiers, blooms, survivors = sorted(size), {t: [] for t in size}, {t: [size[t]] for t in size}
    depth, tables = max((plan_of(t).layers for t in tiers), default=1), []
    ended = {}
    for j in range(1, depth):
        own, against = (j + 1) % 2, j % 2
        live = [t for t in tiers if len(blooms[t]) == j - 1 and size.get(t)]
        if j > 1 and not by_join and sum(survivors[t][-1] + survivors[t][-2] for t in live) <= MAX_LISTED:
            here = [_by_tier(side, live) for side in sides]
            for t in live:
                salts = lambda k, t=t: salt_of(kind, t, k, seed)
                ended[t] = _rest([here[0][t], here[1][t]], j, plan_of(t), salts, t, family, blooms[t], survivors[t])
            break
        now = {}
        for t in tiers:
            if j < plan_of(t).layers and size.get(t):
                fpr = plan_of(t).fprs[j - 1]
                bits, hashes = bloom.sized(size[t], fpr)
                now[t] = Filter(salt_of(kind, t, j, seed), size[t], bits, hashes, fpr, family)
        if not now:
            break
        table = bloom.word_table(sides[own], now)
        if by_join:
            table, ready = cut(table), now
            tables.append(table.withColumn("layer", F.lit(j)))
        else:
            ready = bloom.gather(table, now)
        rest = sides[against].filter(F.col("tier").isin(*now))
        if by_join:
            passed = bloom.probe_by_join(rest, table, now)
        else:
            passed = bloom.passing(rest, ready)
        sides[against] = cut(passed)
        size = {r.tier: r["count"] for r in sides[against].groupBy("tier").count().collect()}
        for t in now:
            blooms[t].append(ready[t])
            survivors[t].append(size.get(t, 0))
    out = {}
    if by_join:
        words = reduce(DataFrame.unionByName, tables) if tables else catalog.sparkSession.createDataFrame([], "tier int, word_idx int, word long, layer int")
        odd = F.col("tier").isin(*[t for t in tiers if len(blooms[t]) % 2 == 0])
        listed = sides[0].filter(odd).unionByName(sides[1].filter(F.col("tier").isin(*tiers) & ~odd))
        return TableModel({t: tuple(blooms[t]) for t in tiers}, {t: len(blooms[t]) + 1 for t in tiers}, words, cut(listed))
    for t in tiers:
        m = len(blooms[t]) + 1
        left = ended[t] if t in ended else sides[(m + 1) % 2].filter(F.col("tier") == t)
        if survivors[t][-1] > MAX_LISTED and not long_lists:
            raise ValueError(f"tier {t} leaves {survivors[t][-1]} keys for its last layer; take more layers or lower rates")
        out[t] = (m, left)
    if not out:
        return {}
    long = {t: cut((_as_table(catalog.sparkSession, t, left) if t in ended else left).select("tier", "key")) for t, (m, left) in out.items() if long_lists and apart(survivors[t][-1])}
    few: dict[int, list] = {t: ended[t] if t in ended and t not in long else [] for t in tiers}
    frames = [left.select("tier", "key") for t, (m, left) in out.items() if survivors[t][-1] and t not in long and t not in ended]
    if frames:
        rows = reduce(DataFrame.unionByName, frames).toArrow()  # MAX_LISTED a tier at most
        for t, k in zip(rows["tier"].to_pylist(), rows["key"].to_pylist()):
            few[t].append(k)
    return {t: TierFilter(t, out[t][0], tuple(blooms[t]), frozenset(few[t]), tuple(survivors[t]), long.get(t)) for t in tiers}
