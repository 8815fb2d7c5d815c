from pyspark.sql import functions as F

from likecard.functions import patterns

CASES = {
    "Cust%": ("P", "Cust"), "%99": ("S", "99"), "%00%": ("C", "00"), "NATION\\_1%": ("P", "NATION_1"), "100\\%%": ("P", "100%"),
    "%": ("O", None), "": ("O", None), "a%b": ("O", None), "a_b": ("O", None), "abc": ("O", None), "%%": ("O", None), "%é漢%": ("C", "é漢"), "a\nb%": ("P", "a\nb"),
}


def test_parse(spark):
    df = spark.createDataFrame([(p,) for p in CASES] + [(None,)], "p string").select("p", patterns.parse_like(F.col("p")).alias("x"))
    for r in df.collect():
        want = CASES.get(r.p, ("O", None))
        assert (r.x.kind, r.x.lit) == want == patterns.parse_like_py(r.p), r.p


def test_round_trip():
    for kind in "PSC":
        for lit in ("a", "10%", "a_b", "x\\y", "漢"):
            assert patterns.parse_like_py(patterns.to_like(kind, lit)) == (kind, lit)
