import random

import pytest
from helpers import brute_keys, rows, strings

from likecard.functions import tiers
from likecard.operators import catalog, frontier

RECORDS = ["abab", "aba", "aba", "b", "", None, "é漢字é", "abababababab", "\n x"]


@pytest.mark.parametrize("kind", "PSC")
@pytest.mark.parametrize("dedupe", [True, False])
def test_enumeration(spark, kind, dedupe):
    got = {r.key: (r.len, r.n) for r in catalog.enumerate_keys(strings(spark, RECORDS), kind, 4, dedupe).collect()}
    assert got == {k: (len(k), n) for k, n in brute_keys(RECORDS, kind, 4).items()}


def test_rollup(spark):
    s = strings(spark, RECORDS)
    assert rows(catalog.enumerate_prefix_rollup(s, 5), "key", "len", "n") == rows(catalog.enumerate_keys(s, "P", 5), "key", "len", "n")


@pytest.mark.parametrize("kind", "PSC")
def test_levelwise_has_rich_keys_and_frontier(spark, kind):
    rng = random.Random(5)
    records = ["".join(rng.choice("abc") for _ in range(rng.randint(0, 6))) for _ in range(60)]
    full = brute_keys(records, kind, 4)
    want = sorted((k, n) for k, n in full.items() if len(k) == 1 or full[k[:-1]] > 2)
    assert rows(catalog.enumerate_levelwise(strings(spark, records), kind, 2, 4), "key", "n") == want


def test_frontier_by_parent_is_the_full_definition(spark):
    rng = random.Random(7)
    records = ["".join(rng.choice("ab") for _ in range(rng.randint(0, 7))) for _ in range(80)]
    keys = catalog.enumerate_keys(strings(spark, records), "C", 5)
    scheme = tiers.build("1.5", catalog.max_count(keys))
    tiered = catalog.with_tiers(keys, scheme)
    ones = {k for k, n in brute_keys(records, "C", 5).items() if n <= 2}
    want = sorted((k,) for k in ones if not any(k[:i] in ones for i in range(1, len(k))))
    assert rows(frontier.reduce(tiered).filter("tier = 1"), "key") == want


def test_empty_set(spark):
    assert catalog.enumerate_keys(strings(spark, ["", None]), "C", 3).count() == 0
    assert catalog.enumerate_keys(strings(spark, []), "P", 3).count() == 0


def test_long_records_are_cut_into_pieces(spark, monkeypatch):
    rng = random.Random(6)
    records = ["".join(rng.choice("abc") for _ in range(n)) for n in (3, 7, 8, 9, 40, 41, 63)] * 2
    monkeypatch.setattr(catalog, "PIECE", 8)
    for first in (True, False):
        got = {r.key: r.n for r in catalog.enumerate_keys(strings(spark, records), "C", 4, first).collect()}
        assert got == dict(brute_keys(records, "C", 4))
