"""Queries that once made their data up: they read given tables and equal their SQL."""

import pytest
from pyspark.sql import functions as F
from test_entry import test_oracle as equals_sql

import __spark_entry__ as entry
from likecard.functions import patterns
from likecard.sources import stringsets


@pytest.mark.parametrize("name", ["parse_escape", "pattern_kinds", "theory_hit_prob", "theory_walk_prob"])
def test_equal_to_sql(spark, sf, name):
    equals_sql(spark, sf, name)


@pytest.mark.parametrize("name", ["parse_escape", "pattern_kinds", "theory_hit_prob", "theory_walk_prob"])
def test_reads_documents(spark, tmp_path, name):
    """Without the table there is no result."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        entry.queries()[name](spark, str(tmp_path)).collect()


def test_every_string_is_a_pattern(spark, sf):
    got = {r.kind: r.n for r in entry.queries()["pattern_kinds"](spark, sf).collect()}
    assert sum(got.values()) == stringsets.load(spark, sf, "doc_openers").count() and set(got) == set("PSCO")


def test_line_ends_and_long_literals(spark):
    long = "x" * 30_000
    cases = {"a%\n": "O", "a%\r": "O", "a\n": "O", "%" + long: "S", long + "\\%%": "P"}
    df = spark.createDataFrame([(p,) for p in cases], "p string").select("p", patterns.parse_like(F.col("p")).alias("x"))
    assert {r.p: r.x.kind for r in df.collect()} == cases == {p: patterns.parse_like_py(p)[0] for p in cases}
