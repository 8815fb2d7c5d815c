import pytest

from likecard.functions import tiers

GOLDEN = {
    "1.3": [(1, 1), (2, 3), (4, 6), (7, 11), (12, 20), (21, 35), (36, 60), (61, 103)],
    "1.5": [(1, 2), (3, 6), (7, 15), (16, 36), (37, 83), (84, 189)],
    "1.7": [(1, 2), (3, 8), (9, 26), (27, 78), (79, 228)],
    "2.0": [(1, 4), (5, 20), (21, 84), (85, 340)],
    "2.5": [(1, 6), (7, 43), (44, 275)],
}


@pytest.mark.parametrize("bound", GOLDEN)
def test_edges(bound):
    assert list(tiers.build(bound, GOLDEN[bound][-1][1]).edges) == GOLDEN[bound]


@pytest.mark.parametrize("rep", ["geomean", "lower_times_bound"])
@pytest.mark.parametrize("bound", GOLDEN)
def test_value_is_within_bound(bound, rep):
    s = tiers.build(bound, 5000, rep)
    for n in range(1, 5001):
        v = s.value(s.tier(n))
        assert max(v / n, n / v) <= float(bound) + 1e-12


def test_number_of_tiers_at_450000_records():
    assert [tiers.build(b, 450_000).n for b in ("1.3", "1.5", "2.5")] == [24, 16, 8]


def test_tier_expression(spark):
    s = tiers.build("1.5", 1000)
    from pyspark.sql import functions as F

    got = spark.range(1, 1001).select("id", s.tier_col(F.col("id")).alias("t")).collect()
    assert all(r.t == s.tier(r.id) for r in got)


def test_bound_must_exceed_one():
    with pytest.raises(ValueError):
        tiers.build("1.0", 5)
