import random

import pytest
from helpers import brute_keys, rows, strings
from pyspark.sql import functions as F

from likecard.functions import hashing, tiers
from likecard.operators import bloom, catalog, classify, exact, frontier, layers, markov, tree
from likecard.operators.estimator import Estimator, EstimatorConfig, fit
from likecard.operators.layers import TierPlan
from likecard.operators.serve import LocalModel


def random_set(seed, n=150, alphabet="abc", most=7):
    rng = random.Random(seed)
    return ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, most))) for _ in range(n)]


WORKED = ["AA", "AB", "AB", "AB", "AC", "AC", "AC", "AD", "BC", "CD", "DA"]


def test_worked_example(spark):
    keys = catalog.with_tiers(catalog.enumerate_keys(strings(spark, WORKED), "P", 2), tiers.build("1.5", 8))
    by = {}
    for r in keys.collect():
        by.setdefault(r.tier, set()).add(r.key)
    assert by == {3: {"A"}, 2: {"AB", "AC"}, 1: {"B", "C", "D", "AA", "AD", "BC", "CD", "DA"}}
    assert {r.key for r in frontier.reduce(keys).filter("tier = 1").collect()} == {"B", "C", "D", "AA", "AD"}
    e = fit(strings(spark, WORKED), EstimatorConfig(kinds=("P",), max_len=2, plan=TierPlan.uniform(3, 0.05), tree=False))
    assert LocalModel(e).tier("P", "BC") == 1
    assert {k: LocalModel(e).tier("P", k) for k in ("A", "AB", "AC", "AD")} == {"A": 3, "AB": 2, "AC": 2, "AD": 1}


def test_forced_layers_of_the_worked_example():
    """Layer 1 passes A and AD, layer 2 holds them and passes AB, which is listed."""

    class Stub:
        def __init__(self, keys):
            self.keys = keys

        def has(self, key):
            return key in self.keys

    f = layers.TierFilter(2, 3, (Stub({"AB", "AC", "A", "AD"}), Stub({"A", "AD", "AB"})), frozenset({"AB"}))
    assert {k: f.accepts(k) for k in ("AB", "AC", "A", "AD", "B")} == {"AB": True, "AC": True, "A": False, "AD": False, "B": False}


@pytest.mark.parametrize("m", [2, 3, 4, 5])
@pytest.mark.parametrize("kind", "PSC")
def test_members_are_never_misclassified(spark, m, kind):
    records = random_set(m)
    keys = catalog.enumerate_keys(strings(spark, records), kind, 4)
    scheme = tiers.build("1.3", catalog.max_count(keys))
    tiered = catalog.with_tiers(keys, scheme)
    top = max(r.tier for r in tiered.select("tier").distinct().collect())
    full = classify.KindModel(kind, layers.build(tiered, kind, TierPlan.uniform(m, 0.3), top), frontier=False)
    pruned = classify.KindModel(kind, layers.build(frontier.reduce(tiered), kind, TierPlan.uniform(m, 0.3), top))
    want = {k: scheme.tier(n) for k, n in brute_keys(records, kind, 4).items()}
    probe = keys.select(F.xxhash64("key").alias("pid"), "key")
    assert {r.key: r.tier for r in classify.direct(probe, full).collect()} == want
    for rule in ("min", "monotone"):
        assert {r.key: r.tier for r in classify.walk(probe, pruned, rule).collect()} == want
        assert all(pruned.walk(k, rule) == t for k, t in want.items())


@pytest.mark.parametrize("records", [[], [""], [None], ["a"], ["same"] * 50, ["漢字", "é" * 5, "😀a"]])
def test_degenerate_sets(spark, records):
    e = fit(strings(spark, records), EstimatorConfig(max_len=3))
    local = LocalModel(e)
    for kind in "PSC":
        for key, n in brute_keys(records, kind, 3).items():
            v = local.estimate_key(kind, key[::-1] if kind == "S" else key)
            assert max(v / n, n / v) <= 1.5 + 1e-12
    assert local.estimate("%") == sum(r is not None for r in records)
    assert local.estimate("%zz%") >= 1 or not records


def test_batch_equals_local_and_survives_saving(spark, tmp_path):
    e = fit(strings(spark, random_set(3)), EstimatorConfig(max_len=4))
    rows_ = [(i, k, lit) for i, (k, lit) in enumerate((k, lit) for k in "PSC" for lit in ("a", "ab", "abca", "abcabc", "zz", "", "cab" * 3))]
    got = {r.pid: r.est for r in e.estimate(spark.createDataFrame(rows_, "pid long, kind string, lit string")).collect()}
    local = LocalModel(e)
    assert all(abs(got[i] - local.estimate_key(k, lit)) < 1e-9 * got[i] for i, k, lit in rows_)
    e.save(spark, f"file://{tmp_path}/m")
    again = Estimator.load(spark, f"file://{tmp_path}/m")
    assert all(LocalModel(again).estimate_key(k, lit) == local.estimate_key(k, lit) for _, k, lit in rows_)


def test_like_texts(spark):
    e = fit(strings(spark, ["50% off", "50_x", "a"]), EstimatorConfig(max_len=4))
    df = spark.createDataFrame([(1, "50\\%%"), (2, "%"), (3, "a_b")], "pid long, pattern string")
    got = {r.pid: r.est for r in e.estimate_like(df).collect()}
    assert abs(got[1] - 2**0.5) < 1e-9 and got[2] is None and got[3] is None


@pytest.mark.parametrize("family", ["portable", "fast"])
def test_hashes_agree_with_plain_python(spark, family):
    keys = ["", "a", "é漢😀", "x" * 50]
    a, b = hashing.FAMILIES[family]("P|2|1|", F.col("key"))
    got = {r.key: (r.a, r.b) for r in spark.createDataFrame([(k,) for k in keys], "key string").select("key", a.alias("a"), b.alias("b")).collect()}
    assert got == {k: hashing.LOCAL[family]("P|2|1|", k) for k in keys}


@pytest.mark.parametrize("m", [2, 3, 4])
def test_filters_as_tables_equal_gathered_ones(spark, monkeypatch, m):
    """A fit by_join gathers nothing and answers as the gathered filters do,
    patterns without matches included."""
    config = dict(kinds=("P", "C"), max_len=4, plan=TierPlan.uniform(m, 0.3), tree=False)
    records = random_set(20 + m, 200)
    want = fit(strings(spark, records), EstimatorConfig(**config))
    probe = [(i, k, lit) for i, (k, lit) in enumerate((k, lit) for k in "PC" for lit in ("a", "ab", "cab", "bbbb", "zz", "abcz", "abcabc", ""))]
    df = spark.createDataFrame(probe, "pid long, kind string, lit string")
    expected = rows(want.estimate(df), "pid", "est")
    monkeypatch.setattr(bloom, "gather", None)
    got = fit(strings(spark, records), EstimatorConfig(**config, by_join=True))
    assert rows(got.estimate(df), "pid", "est") == expected


@pytest.mark.parametrize("rule", ["min", "monotone"])
def test_local_probes_walk_as_the_model_does(spark, rule):
    e = fit(strings(spark, random_set(9, 400)), EstimatorConfig(max_len=5, rule=rule))
    local, rng = LocalModel(e), random.Random(2)
    for _ in range(300):
        key = "".join(rng.choice("abcz") for _ in range(rng.randint(1, 5)))
        assert all(local.probes[k].walk(key, rule) == e.models[k].walk(key, rule) for k in "PSC")


def test_probe_by_join_equals_expression(spark):
    keys = spark.createDataFrame([(2, f"k{i}") for i in range(300)], "tier int, key string")
    bits, hashes = bloom.sized(300, 0.2)
    f = {2: bloom.Filter("s|", 300, bits, hashes, 0.2)}
    table = bloom.word_table(keys, f)
    ready = bloom.gather(table, f)[2]
    others = spark.createDataFrame([(2, f"x{i}") for i in range(500)], "tier int, key string")
    by_join = rows(bloom.probe_by_join(others, table, f), "key")
    assert by_join == rows(others.filter(ready.has_col(F.col("key"))), "key") == sorted((f"x{i}",) for i in range(500) if ready.has(f"x{i}"))
    assert keys.filter(~ready.has_col(F.col("key"))).count() == 0
    assert 0.1 < len(by_join) / 500 < 0.3


def test_tree_packs_and_answers(spark):
    records = random_set(11, 300)
    keys = catalog.with_tiers(catalog.enumerate_keys(strings(spark, records), "C", 4), tiers.build("1.5", 300))
    packed = tree.pack(tree.nodes(keys, 2))
    want = {r.key: r.tier for r in keys.collect()}
    assert all(packed.tier(k) == (t if t > 2 else None) for k, t in want.items())
    assert packed.tier("zzz") is None and tree.pack(tree.nodes(keys, 99)).tier("a") is None


def test_exact_counts_of_any_length(spark):
    records = random_set(13) + [None, "", "abcabcabcabc"]
    pats = [(i, k, lit) for i, (k, lit) in enumerate((k, lit) for k in "PSC" for lit in ("a", "bc", "abcabca", "abcabcabcab", "zz", ""))]
    got = {r.pid: r.true_n for r in exact.count_patterns(strings(spark, records), spark.createDataFrame(pats, "pid long, kind string, lit string")).collect()}
    fits = {"P": str.startswith, "S": str.endswith, "C": str.__contains__}
    assert got == {i: sum(fits[k](s, lit) for s in records if s is not None) for i, k, lit in pats}


def test_long_pattern_by_hand(spark):
    est = {"ab": 4.0, "bc": 2.0, "cd": 1.0, "b": 5.0, "c": 3.0}
    look = lambda p: p.join(spark.createDataFrame(list(est.items()), "key string, est double"), "key")
    p = spark.createDataFrame([(1, "abcd")], "pid long, key string")
    assert abs(markov.estimate(p, "C", 2, look, look).first().est - 4.0 * 2 / 5 * 1 / 3) < 1e-12
    assert markov.estimate(p, "C", 2, look, look, clamp=True, floor=1.2).first().est == 1.2


def test_residual_limit_is_refused(spark, monkeypatch):
    monkeypatch.setattr(layers, "MAX_LISTED", 1)
    keys = spark.createDataFrame([(1, f"a{i}") for i in range(50)] + [(2, f"b{i}") for i in range(50)], "tier int, key string")
    with pytest.raises(ValueError):
        layers.build(keys, "P", TierPlan.uniform(2, 0.9), 2)
