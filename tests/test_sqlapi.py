from helpers import strings

from likecard.functions import patterns
from likecard.operators import sqlapi
from likecard.operators.baselines import catalyst
from likecard.operators.estimator import EstimatorConfig, fit
from likecard.operators.serve import LocalModel
from likecard.plans import workloads
from likecard.sources import io


def test_sql_surface(spark):
    e = fit(strings(spark, ["abc", "abd", "xbc", "50%"]), EstimatorConfig(max_len=3))
    sqlapi.register(spark, e)
    texts = ["ab%", "%bc", "%b%", "%", "a_c", "abc", "50\\%%", "NATION\\_1%", "%\\_%", "a\\%", "x\\", "a%b", ""]
    spark.createDataFrame([(t,) for t in texts], "p string").createOrReplaceTempView("pats")
    got = {r.p: r for r in spark.sql("select p, like_estimate(p) as est, like_kind(p) as kind from pats").collect()}
    local = LocalModel(e)
    assert {t: got[t].est for t in texts} == {t: local.estimate(t) for t in texts}
    assert {t: got[t].kind for t in texts} == {t: patterns.parse_like_py(t)[0] for t in texts}
    keys = sorted(r.key for r in spark.sql("select key, len from like_enumerate('aba', 2)").collect())
    assert keys == ["a", "ab", "b", "ba"]
    assert spark.table("like_tiers").filter("kind = 'P'").count() == e.schemes["P"].n
    assert spark.table("like_catalog_c").count() == e.catalogs["C"].count()


def test_files_in(spark, tmp_path):
    (tmp_path / "p.txt").write_text("ab%\n%cd\n")
    (tmp_path / "p.csv").write_text("value\nab%\n%cd\n")
    (tmp_path / "p.json").write_text('{"value": "ab%"}\n{"value": "%cd"}\n')
    for name, fmt, options in (("p.txt", "text", {}), ("p.csv", "csv", {"header": "true"}), ("p.json", "json", {})):
        df = io.read_patterns(spark, f"file://{tmp_path}/{name}", fmt, **options)
        assert sorted(r.pattern for r in df.collect()) == ["%cd", "ab%"]


def test_catalyst_keeps_the_whole_table(spark):
    s = strings(spark, ["abc"] * 10)
    assert catalyst.estimate(s, "ab%", 10) == 10.0


def test_split_respects_caps(spark):
    df = spark.range(5000).selectExpr("cast(id as string) as key", "1L as n")
    out = {r.split: r["count"] for r in workloads.split(df, 500, 700).groupBy("split").count().collect()}
    assert 350 < out["test"] < 650 and 550 < out["train"] < 850


def test_top_keys_are_limited_before_the_shuffle(spark):
    from likecard.plans import profile

    df = spark.createDataFrame([("P", i % 3, f"k{i:03}", i % 7) for i in range(200)], "kind string, tier int, key string, n long")
    top = profile.top_per_tier(df, 2)
    assert "WindowGroupLimit" in top._jdf.queryExecution().executedPlan().toString()
    assert sorted((r.tier, r.rank, r.key) for r in top.collect())[:2] == [(0, 1, "k006"), (0, 2, "k027")]
