"""The comparison of all methods on one string set: estimates of test and empty
patterns, preparation seconds, seconds a pattern, and bytes."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass
from functools import partial, reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import metrics
from ..functions.patterns import canonical_key
from ..operators.baselines import dbms, learned, ngram, sample, suffix_tree, text_index
from ..operators.estimator import Estimator, EstimatorConfig, fit
from ..operators.serve import LocalModel
from ..sources.scratch import cut
from . import workloads

#: Test, empty and training patterns of a kind: one to two, as published, where
#: the caps are 250,000 and 500,000.
TEST, TRAIN = 10_000, 20_000


@dataclass
class Rival:
    """A fitted method: patterns (pid, kind, lit, ...) of its kinds to est."""

    name: str
    kinds: tuple[str, ...]
    estimate: Callable[[DataFrame], DataFrame]
    seconds: float
    bytes: float
    #: Our own method's estimator, for its local path.
    fitted: Estimator | None = None


def patterns(catalogs: dict[str, DataFrame], strings: DataFrame, max_len: int = 10, test: int = TEST, train: int = TRAIN) -> DataFrame:
    """(pid, kind, lit, true_n, split) of the workload: 'test' and 'train' keys of
    the catalogs, and 'empty' patterns grown from test keys."""
    chars, parts = workloads.vocabulary(strings), []
    for kind, keys in catalogs.items():
        own = workloads.split(keys, test, train).select("key", F.col("n").alias("true_n"), "split")
        none = workloads.empty_patterns(keys, chars, max_len).orderBy(F.xxhash64("key"), "key").limit(test)
        parts.append(own.unionByName(none.select("key", F.lit(0).cast("long").alias("true_n"), F.lit("empty").alias("split"))).withColumn("kind", F.lit(kind)))
    every = reduce(DataFrame.unionByName, parts)
    lit = F.when(F.col("kind") == "S", canonical_key("S", F.col("key"))).otherwise(F.col("key"))
    return cut(every.select(F.xxhash64("kind", "key", "split").alias("pid"), "kind", lit.alias("lit"), "true_n", "split"))


def _timed(build: Callable):
    began = time.perf_counter()
    out = build()
    return out, time.perf_counter() - began


def _by_kind(estimate: Callable[[DataFrame, str], DataFrame], kinds: str = "PSC") -> Callable:
    return lambda p: reduce(DataFrame.unionByName, [estimate(p.filter(F.col("kind") == k), k) for k in kinds])


def _utf8(rows) -> int:
    return sum(len((r or "").encode()) for r in rows)


def classical(strings: DataFrame, catalogs: dict[str, DataFrame], enumeration: dict[str, float]) -> list[Callable[[], Rival]]:
    """Makers of our method under both strategies, and of the methods without
    training. The catalogs are enumerated once; methods that need one have its
    seconds in theirs."""
    n = strings.count()

    def ours(name: str, config: EstimatorConfig) -> Rival:
        e, took = _timed(lambda: fit(strings, config, catalogs))
        return Rival(name, ("P", "S", "C"), e.estimate, took + sum(enumeration.values()), e.model_bytes(), e)

    def heuristic() -> Rival:
        d, took = _timed(lambda: dbms.fit(strings))
        return Rival("dbms_heuristic", ("P", "S", "C"), _by_kind(d.estimate), took, _utf8([s for s, _ in d.values]) + 8 * len(d.values) + _utf8(d.bounds))

    def sampled() -> Rival:
        s, took = _timed(lambda: cut(sample.fit(strings)))
        return Rival("uniform_sample", ("P", "S", "C"), lambda p: sample.estimate(p.select("pid", "kind", "lit"), s).join(p.drop("kind", "lit"), "pid"), took, s.agg(F.coalesce(F.sum(F.octet_length("s")), F.lit(0))).first()[0])

    def pruned(name: str, parse: str) -> Rival:
        t, took = _timed(lambda: suffix_tree.fit(catalogs["C"], n, parse=parse))
        return Rival(name, ("C",), t.estimate, took + enumeration["C"], t.bytes)

    def grams() -> Rival:
        g, took = _timed(lambda: cut(ngram.fit(strings)))
        return Rival("ngram_signature", ("C",), lambda p: ngram.estimate(p, g), took, g.agg(F.sum(F.octet_length("gram") + 8 + 64 * 8)).first()[0] or 0)

    def indexed() -> Rival:
        x, took = _timed(lambda: text_index.fit(strings))
        return Rival("compact_text_index", ("C",), x.estimate, took, 8 * len(x.knots))

    own = [partial(ours, "tier_filters", EstimatorConfig()), partial(ours, "tier_filters_plain", EstimatorConfig(frontier=False, strategy="direct"))]
    return [*own, heuristic, sampled, partial(pruned, "pruned_suffix_tree", "overlap"), partial(pruned, "suffix_tree_independent", "independent"), grams, indexed]


def trained(strings: DataFrame, train: DataFrame, catalogs: dict[str, DataFrame]) -> list[Callable[[], Rival]]:
    """Makers of the learned families: one model of all kinds where that is
    published, one a kind for the others."""
    short = reduce(DataFrame.unionByName, [k.filter("len <= 2").select(F.lit(kind).alias("kind"), canonical_key(kind, F.col("key")).alias("lit"), "n") for kind, k in catalogs.items()])
    short, train = cut(short), cut(train.select("kind", "lit", "true_n"))

    def learnt(name: str, make: Callable) -> Rival:
        if name in learned.JOINT:
            m, took = _timed(make)
            return Rival(name, ("P", "S", "C"), m.estimate, took, m.bytes)
        fits = {kind: _timed(lambda kind=kind: make(kind)) for kind in catalogs}
        by = {kind: m for kind, (m, _) in fits.items()}
        return Rival(name, tuple(by), _by_kind(lambda p, k: by[k].estimate(p), "".join(by)), sum(took for _, took in fits.values()), sum(m.bytes for m in by.values()))

    return [partial(learnt, name, make) for name, make in learned.families(train, strings, short).items()]


def estimates(rivals: list[Rival], asked: DataFrame) -> tuple[DataFrame, list[tuple]]:
    """((method, pid, kind, lit, true_n, split, est) of all methods on patterns of
    their kinds, [(method, preparation_s, ms a pattern in batches, bytes)])."""
    parts, costs = [], []
    for r in rivals:
        own = asked.filter(F.col("kind").isin(*r.kinds))
        done, took = _timed(lambda r=r, own=own: cut(r.estimate(own).select(F.lit(r.name).alias("method"), "pid", "kind", "lit", "true_n", "split", F.col("est").cast("double").alias("est"))))
        parts.append(done)
        costs.append((r.name, r.seconds, took * 1000 / max(1, done.count()), float(r.bytes)))
    return reduce(DataFrame.unionByName, parts), costs


def with_error(est: DataFrame) -> DataFrame:
    return est.filter("split = 'test'").withColumn("ratio_error", metrics.ratio_error(F.col("est"), F.col("true_n")))


def local_ms(model: LocalModel, asked: list[tuple[str, str]]) -> float:
    """Milliseconds a pattern (kind, lit) of the path without Spark jobs."""
    began = time.perf_counter()
    for kind, lit in asked:
        model.estimate_key(kind, lit)
    return (time.perf_counter() - began) * 1000 / max(1, len(asked))
