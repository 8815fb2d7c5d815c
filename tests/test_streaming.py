import random

import pytest
from pyspark.sql import functions as F

from helpers import rows, strings
from likecard.functions import tiers
from likecard.operators import catalog, classify, layers
from likecard.operators.layers import TierPlan
from likecard.streaming import maintenance as M


def test_stream_equals_batch(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    src = f"{tmp_path}/src"
    events.repartition(4, F.to_date("ts")).write.parquet(f"file://{src}")
    stream = M.read_events(spark, f"file://{src}", 2)
    M.maintain(stream, f"file://{tmp_path}/cat", f"file://{tmp_path}/ck").awaitTermination(120)
    path, want = f"file://{tmp_path}/cat", rows(M.key_counts(events), "key", "n")
    part = rows(M.catalog_of(spark, path, 0), "key", "n")
    assert rows(M.catalog_of(spark, path), "key", "n") == want and part != want
    last = M.compact(spark, path)
    assert last >= 1 and M.compact(spark, path) == last and rows(M.catalog_of(spark, path), "key", "n") == want
    with pytest.raises(ValueError):
        M.catalog_of(spark, path, 0)


def test_windows_stream(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.write.parquet(f"file://{tmp_path}/src")
    q = M.windowed(M.deduplicated(M.read_events(spark, f"file://{tmp_path}/src", 100)), "tumbling", late=None).writeStream.format("memory").queryName("w").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    batch = {r.start: r.n for r in M.windowed(events, "tumbling", late=None).collect()}
    got = {r.start: r.n for r in spark.table("w").collect()}
    assert got and all(batch[k] == n for k, n in got.items())


def test_crossings(spark):
    s = tiers.build("1.5", 100)
    a = spark.createDataFrame([("x", 2), ("y", 5), ("z", 1)], "key string, n long")
    b = spark.createDataFrame([("x", 3), ("y", 6), ("w", 40)], "key string, n long")
    got = M.crossings(a, b, s)
    assert rows(got, "key", "old_tier", "new_tier") == [("w", 0, 5), ("x", 1, 2), ("z", 1, 0)]
    assert M.stale_tiers(got) == [2, 5] and M.needs_rebuild(got, 10) and not M.needs_rebuild(got, 1000)


def test_late_rows_are_counted(spark, sf, tmp_path):
    """Files in order of time, one a batch, then an old one again: its rows are late."""
    events = spark.read.parquet(f"{sf}/events.parquet")
    days = [r[0] for r in events.select(F.to_date("ts")).distinct().orderBy(F.to_date("ts")).collect()]
    import os

    for i, day in enumerate([days[0], days[-1], days[0]]):
        events.filter(F.to_date("ts") == F.lit(day)).coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/src")
        new = max((os.path.join(f"{tmp_path}/src", x) for x in os.listdir(f"{tmp_path}/src") if x.endswith(".parquet")), key=os.path.getmtime)
        os.utime(new, (1_000_000 + 100 * i, 1_000_000 + 100 * i))
    q = M.windowed(M.read_events(spark, f"file://{tmp_path}/src", 1), "tumbling").writeStream.format("noop").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert M.late_rows(q) > 0


def test_refreshed_filters_decide_all_keys(spark):
    rng = random.Random(4)
    words = ["".join(rng.choice("abcd") for _ in range(rng.randint(1, 4))) for _ in range(400)]
    plan, s = TierPlan.uniform(3, 0.2), tiers.build("1.5", 10_000)
    old = catalog.enumerate_keys(strings(spark, words[:250]), "P", 4)
    new = catalog.enumerate_keys(strings(spark, words), "P", 4)
    first = catalog.with_tiers(old, s).select("key", "tier")
    m = classify.KindModel("P", layers.build(first, "P", plan, first.agg(F.max("tier")).first()[0]))
    crossed = M.crossings(old, new, s)
    tiered = catalog.with_tiers(new, s).select("key", "tier")
    again = M.refreshed(m, tiered, crossed, plan)
    assert M.stale_filters(m, crossed) and not M.stale_filters(again, crossed)
    assert rows(classify.direct(new.select("key"), again), "key", "tier") == rows(tiered, "key", "tier")


def test_as_of(spark):
    e = spark.sql("select * from values (1L, timestamp'2024-01-01 10:00:00', 1L), (1L, timestamp'2024-01-02 10:00:00', 2L) t(user_id, ts, event_id)")
    v = spark.sql("select * from values (timestamp'2024-01-01 00:00:00', 1), (timestamp'2024-01-02 00:00:00', 2) t(ts, version)")
    assert rows(M.as_of(e, v), "event_id", "version") == [(1, 1), (2, 2)]
