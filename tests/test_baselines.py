import random

from helpers import brute_keys, strings
from pyspark.sql import functions as F

from likecard.operators import catalog
from likecard.operators.baselines import dbms, learned, ngram, suffix_tree, text_index


def some(seed=2, n=200):
    rng = random.Random(seed)
    return ["".join(rng.choice("abcd") for _ in range(rng.randint(1, 8))) for _ in range(n)]


def test_dbms(spark):
    records = ["x"] * 50 + some()
    m = dbms.fit(strings(spark, records), 5, 20)
    assert m.values[0][0] == "x" and len(m.bounds) == 20 and m.bounds == sorted(m.bounds)
    got = {r.lit: r.est for r in m.estimate(spark.createDataFrame([("x",), ("q",), ("a",)], "lit string"), "P").collect()}
    assert got["x"] >= 50 and got["q"] >= 1 and 20 < got["a"] < 120


def test_suffix_tree(spark):
    records = some()
    keys = catalog.enumerate_keys(strings(spark, records), "C", 6)
    full = brute_keys(records, "C", 6)
    kept = {r.key: r.n for r in suffix_tree.kept_nodes(keys, 0.05).collect()}
    k = -(-len(full) * 5 // 100)
    assert kept == dict(sorted(full.items(), key=lambda x: (-x[1], len(x[0]), x[0]))[:k])
    t = suffix_tree.SuffixTree(100, {"a": 50, "b": 40, "c": 20, "ab": 30, "bc": 10})
    assert t.estimate_py("ab") == 30 and abs(t.estimate_py("abc") - 30 * 10 / 40) < 1e-9
    assert t.estimate_py("zz") == 1.0


def test_ngram(spark):
    records = some()
    table = ngram.fit(strings(spark, records))
    pats = spark.createDataFrame([(1, "abc"), (2, "ab"), (3, "zzz"), (4, "abcd")], "pid long, lit string")
    got = {r.pid: r.est for r in ngram.estimate(pats, table).collect()}
    full = brute_keys(records, "C", 4)
    assert got[1] == full["abc"] and got[2] == full["ab"] and got[3] == 1.0 and got[4] >= 1.0


def test_text_index(spark):
    records = some(n=400)
    idx = text_index.fit(strings(spark, records))
    full = brute_keys(records, "C", 2)
    pats = spark.createDataFrame([(k,) for k in full], "lit string")
    errs = [max(r.est / full[r.lit], full[r.lit] / r.est) for r in idx.estimate(pats).collect()]
    assert sum(errs) / len(errs) < 1.5


def test_learned_families_run(spark):
    records = some()
    keys = catalog.enumerate_keys(strings(spark, records), "C", 4)
    rows = keys.select(F.lit("C").alias("kind"), F.col("key").alias("lit"), F.col("n").alias("true_n"))
    short = keys.filter("len <= 2").select(F.lit("C").alias("kind"), F.col("key").alias("lit"), "n")
    for name, trainer in learned.families(rows, strings(spark, records), short, 50).items():
        if name in ("sample_bitmap_net", "hybrid_frequent_gram", "flat_regression"):
            est = trainer().estimate(rows).select(F.avg(F.greatest(F.col("est") / F.col("true_n"), F.col("true_n") / F.col("est"))).alias("e"), F.min("est").alias("least")).first()
            assert est.e < 6 and est.least >= 1, name
