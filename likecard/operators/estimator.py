"""The estimator of one string set: fit, estimate, save and load."""

from __future__ import annotations

import json
import time
from array import array
from dataclasses import asdict, dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.patterns import canonical_key, parse_like
from ..functions.tiers import TierScheme
from ..functions.tiers import build as build_tiers
from ..plans.tuning import EstimatorPlan, optimise
from ..sources.scratch import cut
from . import classify, frontier, layers, markov, tree
from .bloom import Filter
from .catalog import enumerate_keys, max_count, with_tiers
from .classify import KindModel
from .layers import TierFilter, TierPlan


@dataclass(frozen=True)
class EstimatorConfig:
    """The two user parameters, bound and empty_conf, and how to meet them.
    plan fixes layers and rates instead of tuning them. by_join keeps filters of
    any size as tables; such models answer batches and are not saved or served."""

    bound: str = "1.5"
    max_len: int = 10
    kinds: tuple[str, ...] = ("P", "S", "C")
    rep: str = "geomean"
    frontier: bool = True
    tree: bool = True
    empty_conf: float | None = None
    strategy: str = "walk"
    rule: str = "monotone"
    per_tier: bool = False
    clamp: bool = False
    family: str = "fast"
    plan: TierPlan | None = None
    by_join: bool = False


@dataclass
class Estimator:
    config: EstimatorConfig
    n_records: int
    schemes: dict[str, TierScheme]
    models: dict[str, KindModel]
    plans: dict[str, EstimatorPlan] = field(default_factory=dict)
    seconds: dict[str, float] = field(default_factory=dict)
    catalogs: dict[str, DataFrame] = field(default_factory=dict, repr=False)

    def tiers(self, patterns: DataFrame, kind: str, strategy: str | None = None, rule: str | None = None) -> DataFrame:
        """patterns (pid, key) of one kind, canonical and short, with tier."""
        model = self.models[kind]
        if (strategy or self.config.strategy) == "direct":
            return classify.direct(patterns, model)
        return classify.walk(patterns, model, rule or self.config.rule)

    def short(self, patterns: DataFrame, kind: str, **how) -> DataFrame:
        scheme = self.schemes[kind]
        return self.tiers(patterns, kind, **how).withColumn("est", scheme.rep_col(F.col("tier")))

    def estimate_keys(self, patterns: DataFrame, kind: str, clamp: bool | None = None) -> DataFrame:
        """patterns (pid, key) of one kind with est, long ones by the Markov chain."""
        size = self.config.max_len
        brief = self.short(patterns.filter(F.length("key") <= size), kind).drop("tier")
        if "C" not in self.models:
            return brief
        long = patterns.filter(F.length("key") > size)
        if long.isEmpty():
            return brief
        clamp = self.config.clamp if clamp is None else clamp
        far = markov.estimate(long, kind, size, lambda p: self.short(p, kind), lambda p: self.short(p, "C"), clamp, self.schemes[kind].value(1))
        return brief.unionByName(far.select(brief.columns))

    def estimate(self, patterns: DataFrame) -> DataFrame:
        """patterns (pid, kind, lit) with est. The bare '%' (an empty literal)
        gets the number of records; kinds without a model get null. Each kind is
        answered by a plan of its own, for one of all kinds fills the driver."""
        out = None
        for kind in self.models:
            own = patterns.filter((F.col("kind") == kind) & (F.col("lit") != "")).select("pid", "lit", canonical_key(kind, F.col("lit")).alias("key"))
            part = cut(self.estimate_keys(own.select("pid", "key"), kind).select("pid", "est"))
            out = part if out is None else out.unionByName(part)
        every = patterns.join(out, "pid", "left") if out is not None else patterns.withColumn("est", F.lit(None).cast("double"))
        return every.withColumn("est", F.when(F.col("lit") == "", float(self.n_records)).otherwise(F.col("est")))

    def estimate_like(self, patterns: DataFrame, escape: str = "\\") -> DataFrame:
        """patterns (pid, pattern) with kind, lit and est."""
        return self.estimate(patterns.withColumn("_p", parse_like(F.col("pattern"), escape)).select("*", "_p.kind", "_p.lit").drop("_p"))

    def sizes(self) -> DataFrame:
        """(kind, tier, layers, bloom_bits, listed, listed_bytes) and tree rows (tier 0)."""
        spark = SparkSession.getActiveSession()
        rows = []
        for kind, m in self.models.items():
            for t, f in m.filters.items():
                rows.append((kind, t, f.layers, f.bits, f.survivors[-1], f.listed_bytes))
            if m.tree is not None:
                rows.append((kind, 0, 0, 0, len(m.tree), -(-m.tree.model_bits // 8)))
        return spark.createDataFrame(rows, "kind string, tier int, layers int, bloom_bits long, listed long, listed_bytes long")

    def model_bytes(self) -> int:
        total = 0
        for m in self.models.values():
            total += sum(-(-f.bits // 8) + f.listed_bytes for f in m.filters.values())
            total += -(-m.tree.model_bits // 8) if m.tree is not None else 0
        return total

    def save(self, spark: SparkSession, path: str) -> None:
        """Words, listed keys and trees as Parquet by kind and tier, and a manifest."""
        words, trees, manifest = [], [], []
        high = spark.createDataFrame([], "kind string, key string, tier int")
        listed = spark.createDataFrame([], "kind string, tier int, key string")
        for kind, m in self.models.items():
            entry = {"kind": kind, "frontier": m.frontier, "scheme": asdict(self.schemes[kind]), "filters": []}
            for t, f in m.filters.items():
                entry["filters"].append({"tier": t, "layers": f.layers, "survivors": f.survivors, "blooms": [{k: v for k, v in asdict(b).items() if k != "words"} for b in f.blooms]})
                words += [(kind, t, j, bytearray(b.words.tobytes())) for j, b in enumerate(f.blooms, 1)]
            listed = listed.unionByName(layers.listed(spark, m.filters).withColumn("kind", F.lit(kind)))
            if m.tree is not None:
                trees.append((kind, bytearray(m.tree.data)))
                high = high.unionByName(m.high(spark).select(F.lit(kind).alias("kind"), "key", F.col("tree_tier").alias("tier")))
            manifest.append(entry)
        spark.createDataFrame(words, "kind string, tier int, layer int, words binary").write.mode("overwrite").partitionBy("kind", "tier").parquet(f"{path}/words")
        listed.write.mode("overwrite").parquet(f"{path}/listed")
        spark.createDataFrame(trees, "kind string, data binary").write.mode("overwrite").parquet(f"{path}/trees")
        high.write.mode("overwrite").parquet(f"{path}/high")
        text = json.dumps({"config": asdict(self.config), "n_records": self.n_records, "kinds": manifest})
        spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Estimator:
        spec = json.loads(spark.read.text(f"{path}/manifest", wholetext=True).first()[0])
        config = spec["config"] | {"kinds": tuple(spec["config"]["kinds"])}
        if config["plan"]:
            config["plan"] = TierPlan(config["plan"]["layers"], tuple(config["plan"]["fprs"]))
        words = {(r.kind, r.tier, r.layer): r.words for r in spark.read.parquet(f"{path}/words").collect()}
        rows, listed, long = spark.read.parquet(f"{path}/listed"), {}, {}
        sizes = {(e["kind"], f["tier"]): f["survivors"][-1] for e in spec["kinds"] for f in e["filters"]}
        for (kind, t), n in sizes.items():
            if layers.apart(n):
                long[kind, t] = rows.filter((F.col("kind") == kind) & (F.col("tier") == t)).select("tier", "key")
        few = [x for x, n in sizes.items() if n and not layers.apart(n)]
        for r in rows.filter(F.concat("kind", "tier").isin(*[f"{k}{t}" for k, t in few])).collect() if few else ():
            listed.setdefault((r.kind, r.tier), set()).add(r.key)
        trees = {r.kind: r for r in spark.read.parquet(f"{path}/trees").collect()}
        schemes, models = {}, {}
        for e in spec["kinds"]:
            kind, filters = e["kind"], {}
            for f in e["filters"]:
                blooms = []
                for j, b in enumerate(f["blooms"], 1):
                    b["words"] = array("q", bytes(words[kind, f["tier"], j]))
                    blooms.append(Filter(**b))
                filters[f["tier"]] = TierFilter(f["tier"], f["layers"], tuple(blooms), frozenset(listed.get((kind, f["tier"]), ())), tuple(f["survivors"]), long.get((kind, f["tier"])))
            packed = tree.PackedTree(bytes(trees[kind].data)) if kind in trees else None
            high = spark.read.parquet(f"{path}/high").filter(F.col("kind") == kind).select("key", "tier") if packed else None
            models[kind] = KindModel(kind, filters, packed, e["frontier"], high)
            schemes[kind] = TierScheme(**e["scheme"])
        return Estimator(EstimatorConfig(**config), spec["n_records"], schemes, models)


def fit_catalog(catalog: DataFrame, kind: str, config: EstimatorConfig = EstimatorConfig()) -> tuple[TierScheme, KindModel, EstimatorPlan]:
    """Scheme, structures and plan of one kind from its catalog (key, len, n)."""
    scheme = build_tiers(config.bound, max_count(catalog), config.rep)
    tiered = with_tiers(catalog, scheme)
    kept = cut(frontier.reduce(tiered) if config.frontier else tiered)
    sizes = {r.tier: r["count"] for r in kept.groupBy("tier").count().collect()}
    if config.plan is not None:
        plan = EstimatorPlan({t: config.plan for t in sizes if t > 1}, None)
        if config.tree and scheme.n > 6:
            plan = replace(plan, threshold=6)
    else:
        plan = optimise(sizes, config.max_len, empty_conf=config.empty_conf, strategy=config.strategy, tree=config.tree, per_tier=config.per_tier)
    top = plan.top(max(sizes, default=1))
    packed, table = None, None
    if plan.threshold is not None:
        table = cut(tree.nodes(tiered, top))
        packed = tree.pack(table)
    filters = layers.build(kept.filter(F.col("tier") <= top), kind, plan.tiers or TierPlan(), top, config.family, by_join=config.by_join, long_lists=True)
    return scheme, KindModel(kind, filters, packed, config.frontier, table), plan


def fit(strings: DataFrame, config: EstimatorConfig = EstimatorConfig(), catalogs: dict[str, DataFrame] | None = None) -> Estimator:
    """The estimator of a string set (sid, s). seconds has the wall time of each
    kind: enumeration, tuning and build; catalogs enumerated before are taken as
    they are, and their time is not in it."""
    out = Estimator(config, strings.filter("s is not null").count(), {}, {})
    for kind in config.kinds:
        began = time.perf_counter()
        out.catalogs[kind] = catalogs[kind] if catalogs else cut(enumerate_keys(strings, kind, config.max_len))
        out.schemes[kind], out.models[kind], out.plans[kind] = fit_catalog(out.catalogs[kind], kind, config)
        out.seconds[kind] = time.perf_counter() - began
    return out
