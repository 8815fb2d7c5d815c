"""What only larger sets show: whole workloads, filters over the driver's limits."""

import threading

import numpy as np
from helpers import brute_keys, rows, strings
from pyspark.sql import functions as F

import __spark_entry__ as entry
from likecard import queries
from likecard.functions import hashing, tiers
from likecard.operators import bloom, catalog, classify, layers
from likecard.operators.baselines import learned, suffix_tree
from likecard.operators.estimator import EstimatorConfig, fit, fit_catalog
from likecard.operators.layers import TierPlan
from likecard.plans import study, workloads


def test_split_keeps_every_key_without_caps(spark):
    df = spark.range(800_000).select(F.col("id").cast("string").alias("key"))
    out = {r.split: r["count"] for r in workloads.split(df).groupBy("split").count().collect()}
    assert sum(out.values()) == 800_000 and out["test"] > 260_000 and out["train"] > 520_000


def test_suffix_tree_multiplies_first():
    t = suffix_tree.SuffixTree(22, {"ab": 15})
    assert 22 * (15 / 22) != 15 and t.estimate_py("ab") == 15.0


def test_large_filters_answer_as_small_ones(spark, monkeypatch):
    """Filters too large for a plan, whose last layers are too long to list,
    answer as those that are expressions, and one by one."""
    keys = spark.createDataFrame([(1 + (i % 7 == 0) + (i % 21 == 0), f"k{i}") for i in range(300)], "tier int, key string")
    asked = keys.select("key").unionByName(spark.createDataFrame([(f"x{i}",) for i in range(200)], "key string")).coalesce(1)
    build = lambda: classify.KindModel("P", layers.build(keys, "P", TierPlan.uniform(2, 0.3), 3, "fast", long_lists=True))
    want = rows(classify.direct(asked, build()), "key", "tier")
    monkeypatch.setattr(layers, "MAX_LISTED", 0)
    monkeypatch.setattr(bloom, "MAX_INLINE", 0)
    got = build()
    assert all(f.table is not None for f in got.filters.values()) and not got.inline
    assert rows(classify.direct(asked, got), "key", "tier") == want == sorted((k, got.tier(k)) for k, _ in want)


def test_hashes_of_many_keys():
    keys = ["", "a", "é漢😀", "x" * 50]
    for salt in ("P|2|1|", "C|12|10|", "a seed of some length|S|3|2|"):
        at, step = hashing.fast_all(salt, np.array([hashing.fast_base(k) for k in keys], np.uint64))
        assert list(zip(at.tolist(), step.tolist())) == [hashing.fast_py(salt, k) for k in keys]


def test_portable_hashes_of_many_keys():
    keys = ["", "a", "é漢😀", "x" * 50, *map(str, range(500))]
    for salt in ("P|2|1|", "a seed of some length that is over 32 bytes|S|3|2|"):
        at, step = hashing.portable_all(salt, np.array(keys, object))
        assert list(zip(at.tolist(), step.tolist())) == [hashing.portable_py(salt, k) for k in keys]


def test_tier_edges_follow_a_table(spark, sf):
    got = entry.queries()["tier_edges_15"](spark, sf).collect()
    n = spark.read.parquet(f"{sf}/events.parquet").filter("props != ''").count()
    assert sum(r.n_keys for r in got) > 0 and max(got, key=lambda r: r.tier).lo <= n <= max(r.hi for r in got)


def test_alphabets_are_one_constant(spark):
    """A large alphabet, or many character pairs, are no literals of a plan."""
    chars = [chr(0x4E00 + i) for i in range(6000)]
    keys = spark.createDataFrame([(f"k{i}",) for i in range(300)], "key string")
    df = workloads.empty_patterns(keys, chars)
    plan = df._jdf.queryExecution().logical().treeString()
    assert plan.count(chars[77]) <= 6 and plan.count("\n") < 200
    got = {r.key for r in df.collect()}
    test = [k for k, in keys.filter(workloads.digest("split|", F.col("key")) % 3 == 0).collect()]
    assert len(got) == len(test) and all(k[: len(k.rstrip("".join(chars)))] in test and set(k[2:]) - set("0123456789") <= set(chars) for k in got)


def test_looked_up_in_order(spark):
    table = spark.createDataFrame([("ab", 1.0), ("bc", 2.0), ("漢", 5.0)], "part string, value double")
    df = spark.createDataFrame([("abcx",), ("漢",), ("abcx",)], "lit string")
    got = learned.looked_up(df, learned._pairs("lit"), table, "v").collect()
    assert sorted((r.lit, r.v) for r in got) == [("abcx", [1.0, 2.0, -10.0])] * 2 + [("漢", [5.0])]


def test_tree_and_long_lists_stay_tables(spark):
    """The driver holds the packed tree and the words, no dict of keys."""
    keys = spark.createDataFrame([(f"k{i}", len(f"k{i}"), 1 + i % 40) for i in range(9000)], "key string, len int, n long")
    _, m, _ = fit_catalog(keys, "P", EstimatorConfig(plan=TierPlan.uniform(2, 0.5), frontier=False))
    assert all(f.table is not None and not f.residual for f in m.filters.values() if f.survivors[-1] > layers.MAX_INLINE)
    assert any(f.table is not None for f in m.filters.values()) and "tree_keys" not in vars(m)
    want = {r.key: m.tier(r.key) for r in keys.limit(300).collect()}
    assert {r.key: r.tier for r in classify.direct(keys.limit(300).select("key"), m).collect()} == want


def test_last_layers_of_few_keys_need_no_jobs(spark, monkeypatch):
    """Layers that are built on the driver equal those built by jobs."""
    keys = spark.createDataFrame([(1 + (i % 7 == 0) + (i % 21 == 0), f"k{i}") for i in range(400)], "tier int, key string")
    for family in ("fast", "portable"):
        build = lambda: layers.build(keys, "P", TierPlan.uniform(6, 0.4), 3, family, long_lists=True)  # noqa: B023, E731
        with monkeypatch.context() as m:
            m.setattr(layers, "MAX_LISTED", -1)
            want = build()
        calls = []
        with monkeypatch.context() as m:
            m.setattr(bloom, "gather", lambda *a, f=bloom.gather: calls.append(1) or f(*a))
            got = build()
        same = lambda x: {t: (f.layers, f.blooms, f.survivors, f.keys) for t, f in x.items()}
        assert same(got) == same(want) and max(f.layers for f in got.values()) > 3 and len(calls) == 1


def test_suffix_tree_stays_a_table(spark):
    """No process holds the kept parts; estimates are those of a dict of all."""
    records = ["".join("abcd"[(i * j + i // 3) % 4] for j in range(1, 3 + i % 6)) for i in range(150)] + ["漢字😀"]
    full = brute_keys(records, "C", 6)
    for parse in ("overlap", "independent"):
        t = suffix_tree.fit(catalog.enumerate_keys(strings(spark, records), "C", 6), len(records), 0.3, parse)
        kept = dict(sorted(full.items(), key=lambda x: (-x[1], len(x[0]), x[0]))[: -(-len(full) * 3 // 10)])
        want = suffix_tree.SuffixTree(len(records), kept, 1.0, parse)
        asked = [*full, "zz", "", "dcbadcba" * 2, "abczabc"]
        got = {r.lit: r.est for r in t.estimate(spark.createDataFrame([(x,) for x in asked], "lit string")).collect()}
        assert not t.counts and t.bytes == want.bytes and got == {x: want.estimate_py(x) for x in asked}


def test_each_kind_has_its_own_plan(spark):
    e = fit(strings(spark, ["abc", "abd", "xbc"] * 4), EstimatorConfig(max_len=3))
    df = spark.createDataFrame([(i, k, "ab") for i, k in enumerate("PSC")], "pid long, kind string, lit string")
    out = e.estimate(df)
    assert out._jdf.queryExecution().optimizedPlan().treeString().count("\n") < 30
    assert {r.pid for r in out.collect() if r.est >= 1} == {0, 1, 2}


def test_empty_rates_are_no_plan_of_all(spark, sf, monkeypatch):
    """Each strategy runs on its own, prefixes are classified once for both walks,
    and the rates are those of the strategies one by one."""
    asked = []
    monkeypatch.setattr(classify, "direct", lambda p, m, f=classify.direct: asked.append(m.kind) or f(p, m))
    df = entry.queries()["empty_rates"](spark, sf)
    assert sorted(asked) == sorted("PSC" * 2)
    assert df._jdf.queryExecution().optimizedPlan().treeString().count("\n") < 5
    got = {(r.kind, r.strategy): (r.n, r.tier_one) for r in df.collect()}
    assert len(got) == 9
    for strategy, walk in (("direct", False), ("walk_monotone", True)):
        r = queries._tier_one_rate(spark, sf, "P", walk).first()
        assert got["P", strategy] == (r.n, round(r.tier_one / r.n, 6))


def test_rates_are_found_once_a_session(spark, sf, monkeypatch):
    entry.queries()["empty_rates"](spark, sf)
    asked = []
    monkeypatch.setattr(classify, "direct", lambda p, m, f=classify.direct: asked.append(m.kind) or f(p, m))
    assert all(r.holds for r in entry.queries()["walk_ge_direct"](spark, sf).collect()) and not asked


def test_bound_is_checked_for_every_kind(spark, monkeypatch):
    """A kind whose literals are estimated beyond the bound is seen."""
    k = spark.createDataFrame([("a", 1, 40), ("ab", 2, 40), ("b", 1, 1)], "key string, len int, n long").coalesce(1)
    for bad in "PSC":
        made = {}

        def model(spark, d, kind, config, bad=bad, made=made):
            scheme = tiers.build(config.bound, 40)
            found = layers.build(catalog.with_tiers(k, scheme), kind, TierPlan.uniform(2, 0.05), scheme.n) if kind != bad else {}
            return made.setdefault((kind, config.bound), (scheme, classify.KindModel(kind, found), None))

        monkeypatch.setattr(queries, "keys", lambda *a: k)
        monkeypatch.setattr(queries, "model", model)
        monkeypatch.setattr(queries, "BOUNDS", ("1.5",))
        assert [tuple(r) for r in queries.bound_holds(spark, "").collect()] == [("1.5", False)]
        assert {kind for kind, _ in made} == set("PSC")


def test_methods_without_times_run_side_by_side(spark, monkeypatch):
    """Two methods meet, which one after the other they never would; all are asked."""
    met = threading.Barrier(2, timeout=60)
    asked = spark.createDataFrame([(1, "P", "a", 3, "test"), (2, "P", "b", 0, "empty"), (3, "P", "c", 2, "train")], "pid long, kind string, lit string, true_n long, split string")

    def rival(name):
        met.wait()
        return study.Rival(name, ("P",), lambda p: p.withColumn("est", F.lit(6.0)), 0.0, 0)

    monkeypatch.setattr(queries, "keys", lambda *a: None)
    monkeypatch.setattr(queries, "_study_patterns", lambda *a: asked)
    monkeypatch.setattr(queries, "_trained_makers", lambda *a: [lambda: rival("learnt")])
    monkeypatch.setattr(queries, "_classical_makers", lambda *a: [lambda: rival("plain")])
    got = sorted(tuple(r) for r in queries.accuracy_by_length(spark, "no such folder").collect())
    assert got == [("learnt", "P", 1, 1, 2.0), ("plain", "P", 1, 1, 2.0)]
