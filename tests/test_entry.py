import duckdb
import pytest

import __spark_entry__ as entry
from likecard.plans import planner

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = [
    "keys_prefix_rollup", "keys_levelwise", "tier_edges_15", "estimate_P", "classify_walk_S", "error_summary", "tree_nodes", "long_estimate_C", "bloom_probe", "empty_patterns_S", "parse_escape", "plan_query_14", "event_windows_session",
    "classify_by_join_build", "layer_survivors", "residual_table", "classify_trace", "residual_exact", "empty_rate_direct", "empty_rate_walk",
    "suffix_tree_estimate", "ngram_signature_estimate", "hybrid_exact_part", "stream_refresh", "event_versions",
]


@pytest.mark.parametrize("name", CHECKED)
def test_oracle(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = entry.queries()[name](spark, sf)
    cols = sorted(df.columns)
    want = con.execute(f"select {', '.join(cols)} from ({entry.oracle_sql()[name]})").fetchall()
    got = [tuple(r) for r in df.select(*cols).collect()]
    key = lambda r: tuple(map(str, r))
    assert sorted(map(key, map(norm_row, got))) == sorted(map(key, map(norm_row, want)))


def norm_row(r):
    return tuple(round(float(v), 6) if isinstance(v, float) else v for v in r)


def test_entry(spark):
    assert entry.entry(spark).limit(1).count() == 1


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_linked_order():
    """The smallest table first, then the smallest that a condition links."""
    of = {"o_k = l_k": {"o", "l"}, "c_k = o_c": {"c", "o"}, "p_k = l_p": {"p", "l"}}
    assert planner.linked_order(["c", "p", "o", "l"], list(of), of.get) == ["c", "o", "l", "p"]
    assert planner.linked_order(["x", "y"], [], of.get) == ["x", "y"]


def test_joins_in_another_order(spark, sf):
    from likecard.plans import workloads

    spec = workloads.JOINS[0]
    named, conditions = workloads.join_parts(spec)
    assert named == {"lineitem": "lineitem", "orders": "orders", "customer": "customer"} and len(conditions) == 2
    assert workloads.join_sql(spec, "", ["customer", "orders", "lineitem"]).count(" join ") == 0
    self_join = next(s for s in workloads.JOINS if s[0] == "j7")
    assert workloads.join_parts(self_join)[0] == {"a": "conversations", "b": "conversations"}


def test_advice():
    order, hint = planner.advise([planner.Side("a", 10, 10), planner.Side("b", 1e9, 10)], 1000)
    assert order == ["a", "b"] and hint == "/*+ broadcast(a) */"
    assert planner.advise([planner.Side("a", 1e8, 10), planner.Side("b", 1e9, 10)], 1000)[1] == "/*+ shuffle_hash(a) */"
