"""Append-only upkeep of catalogs, and pattern counts over time, by Structured Streaming."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import schemas
from ..operators import classify, layers
from ..operators.catalog import literals
from ..operators.classify import KindModel
from ..operators.ranking import running_last


def read_events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """events as a stream of Parquet files with a fixed schema."""
    return spark.readStream.schema(schemas.EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def key_counts(events: DataFrame, kind: str = "P", max_len: int = 10, column: str = "props") -> DataFrame:
    """Running (key, n) of a column's literals; output mode update or complete."""
    flat = events.filter(F.col(column).isNotNull() & (F.col(column) != "")).select(F.explode(literals(F.col(column), kind, max_len)).alias("key"))
    return flat.groupBy("key").agg(F.count("*").alias("n"))


def windowed(events: DataFrame, how: str, pattern: str = "%9}", late: str | None = "2 hours") -> DataFrame:
    """Matches of a pattern by tumbling hours, sliding hours (every 15 minutes)
    or sessions per user (30 minutes of rest). late sets the watermark on streams."""
    rows = events.withWatermark("ts", late) if late else events
    hit = F.count_if(F.col("props").like(pattern)).alias("matches")
    if how == "session":
        w = F.session_window("ts", "30 minutes")
        return rows.groupBy("user_id", w.alias("w")).agg(F.count("*").alias("n"), hit).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "matches")
    w = F.window("ts", "1 hour", "15 minutes") if how == "sliding" else F.window("ts", "1 hour")
    return rows.groupBy(w.alias("w")).agg(F.count("*").alias("n"), hit).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "matches")


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def merged(catalog: DataFrame, delta: DataFrame) -> DataFrame:
    """The catalog (key, n) after a batch of new counts."""
    return catalog.select("key", "n").unionByName(delta.select("key", "n")).groupBy("key").agg(F.sum("n").alias("n"))


def crossings(old: DataFrame, new: DataFrame, scheme) -> DataFrame:
    """Keys whose tier differs between two catalogs: (key, old_tier, new_tier),
    tier 0 for absent. Filters of both tiers are stale for such a key."""
    a = old.select("key", scheme.tier_col(F.col("n")).alias("old_tier"))
    b = new.select("key", scheme.tier_col(F.col("n")).alias("new_tier"))
    both = a.join(b, "key", "full").select("key", F.coalesce("old_tier", F.lit(0)).alias("old_tier"), F.coalesce("new_tier", F.lit(0)).alias("new_tier"))
    return both.filter("old_tier != new_tier")


def stale_tiers(crossed: DataFrame) -> list[int]:
    rows = crossed.select(F.explode(F.array("old_tier", "new_tier")).alias("tier")).filter("tier > 1").distinct().collect()
    return sorted(r.tier for r in rows)


def stale_filters(model: KindModel, crossed: DataFrame) -> list[int]:
    """Tiers whose filters are known to decide a key wrongly: those that take a key
    that has moved, or should. crossed: (key, new_tier, ...), new keys included."""
    wrong = classify.direct(crossed.filter("new_tier > 0"), model).filter("tier != new_tier")
    return sorted(r.t for r in wrong.select(F.explode(F.array("tier", "new_tier")).alias("t")).filter("t > 1").distinct().collect())


def refreshed(model: KindModel, tiered: DataFrame, crossed: DataFrame, plans) -> KindModel:
    """model with its stale filters built anew from the catalog (key, tier), until
    every key that has moved is in its tier. Other filters still decide all keys:
    nothing else has changed for them. A round a tier at most."""
    top = tiered.agg(F.max("tier")).first()[0]
    family = next((b.family for f in model.filters.values() for b in f.blooms), "fast")
    while stale := stale_filters(model, crossed):
        fresh = layers.build(tiered, model.kind, plans, top, family, only=stale, long_lists=True)
        kept = {t: f for t, f in model.filters.items() if t not in stale}
        model = replace(model, filters=dict(sorted({**kept, **fresh}.items())))
    return model


def late_rows(query) -> int:
    """Rows that a running or ended query dropped as too late, of its kept progress."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p.get("stateOperators", []))


def needs_rebuild(crossed: DataFrame, n_keys: int, share: float = 0.01) -> bool:
    """Bloom filters cannot forget, so tiers with movers are rebuilt once the
    movers are more than a share of all keys."""
    return crossed.count() > share * n_keys


def maintain(stream: DataFrame, path: str, checkpoint: str, kind: str = "P", max_len: int = 10):
    """Starts a query that writes each batch's key counts under path/delta. A
    batch that is run again after a failure writes the same delta again."""

    def add(batch: DataFrame, version: int) -> None:
        key_counts(batch, kind, max_len).withColumn("kind", F.lit(kind)).write.mode("overwrite").parquet(f"{path}/delta/batch={version}")

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


DELTAS = "key string, n long, kind string, batch int"


def _base(spark: SparkSession, path: str) -> tuple[DataFrame, int]:
    """The latest compacted catalog and the last batch in it, (nothing, -1) if none."""
    jvm = spark.sparkContext._jvm
    root = jvm.org.apache.hadoop.fs.Path(f"{path}/base")
    fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    done = [int(s.getPath().getName()) for s in fs.listStatus(root) if fs.exists(jvm.org.apache.hadoop.fs.Path(s.getPath(), "_SUCCESS"))] if fs.exists(root) else []
    if not done:
        return spark.createDataFrame([], "key string, n long"), -1
    return spark.read.parquet(f"{path}/base/{max(done)}").select("key", "n"), max(done)


def catalog_of(spark: SparkSession, path: str, upto: int | None = None) -> DataFrame:
    """(key, n) after all batches, or after batch `upto`: the compacted catalog and
    the deltas since."""
    base, last = _base(spark, path)
    if upto is not None and upto < last:
        raise ValueError(f"batches up to {last} are compacted")
    rows = spark.read.schema(DELTAS).parquet(f"{path}/delta").filter(F.col("batch") > last)
    return merged(base, rows if upto is None else rows.filter(F.col("batch") <= upto))


def compact(spark: SparkSession, path: str) -> int | None:
    """Merges the deltas into a new base; the number of its last batch. Older
    deltas and bases may then go; readers prefer the newest finished base."""
    last = spark.read.schema(DELTAS).parquet(f"{path}/delta").agg(F.max("batch")).first()[0]
    if last is not None and last > _base(spark, path)[1]:
        catalog_of(spark, path, last).write.mode("overwrite").parquet(f"{path}/base/{last}")
    return last


def as_of(events: DataFrame, versions: DataFrame) -> DataFrame:
    """Each event (user_id, ts, event_id) with the catalog version in force at its
    time: versions (ts, version) and events are put in one order of time, in
    ranges, and the last version is carried over from range to range."""
    both = events.select("user_id", "ts", "event_id", F.lit(None).cast("int").alias("version"))
    both = both.unionByName(versions.select(F.lit(None).cast("long").alias("user_id"), "ts", F.lit(None).cast("long").alias("event_id"), "version"))
    both = both.withColumn("late", F.col("event_id").isNotNull())
    return running_last(both, ["ts", "late", "event_id", "version"], "version").filter("late").drop("late")
