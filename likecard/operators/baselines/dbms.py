"""dbms_heuristic: most common values, an equi-depth histogram, and fixed odds per character."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...functions.patterns import matches
from ..ranking import running_sum


@dataclass(frozen=True)
class DbmsModel:
    rows: int
    values: list[tuple[str, float]] = field(repr=False)
    bounds: list[str] = field(repr=False)
    floor_fraction: float = 1e-4
    per_char: float = 0.2
    per_wildcard: float = 5.0

    def estimate(self, patterns: DataFrame, kind: str) -> DataFrame:
        """patterns (lit, ...) with est."""
        lit = F.col("lit")
        pick = F.array(*[F.struct(F.lit(v).alias("v"), F.lit(s).alias("s")) for v, s in self.values]) if self.values else F.array().cast("array<struct<v:string,s:double>>")
        known = F.aggregate(F.filter(pick, lambda x: matches(kind, x.v, lit)), F.lit(0.0), lambda acc, x: acc + x.s)
        inner = self.bounds[1:-1]
        hits = F.size(F.filter(F.array(*map(F.lit, inner)), lambda b: matches(kind, b, lit))) if inner else F.lit(0)
        odds = F.least(F.lit(1.0), F.pow(F.lit(self.per_char), F.length(lit)) * (self.per_wildcard if kind in "SC" else 1.0))
        rest = F.when(hits > 0, hits / max(1, len(inner))).otherwise(odds)
        share = known + (1 - sum(s for _, s in self.values)) * rest
        return patterns.withColumn("est", F.greatest(F.lit(1.0), self.rows * F.greatest(F.lit(self.floor_fraction), share)))


def fit(strings: DataFrame, n_mcv: int = 100, n_hist: int = 100, floor_fraction: float = 1e-4) -> DbmsModel:
    """Counts of values are exact. Histogram ranks add up over ranges of values,
    so no task sorts all records."""
    counts = strings.groupBy("s").agg(F.count("*").alias("w"))
    rows = counts.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    top = mcv(counts, n_mcv).collect()
    rest = counts.join(F.broadcast(strings.sparkSession.createDataFrame([(r.s,) for r in top], "s string")), "s", "left_anti")
    left = rest.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    ranked = running_sum(rest, ["s"], F.col("w"), "before").withColumn("cum", F.col("before") + F.col("w"))
    first, last = F.ceil((F.col("cum") - F.col("w")) * n_hist / max(1, left)), F.ceil(F.col("cum") * n_hist / max(1, left)) - 1
    edges = ranked.select("s", F.explode(F.when(last >= first, F.sequence(first, last))).alias("j")).filter((F.col("j") >= 0) & (F.col("j") <= n_hist)).orderBy("j").collect()
    return DbmsModel(rows, [(r.s, r.w / rows) for r in top], [r.s for r in edges], floor_fraction)


def mcv(counts: DataFrame, n: int = 100) -> DataFrame:
    return counts.orderBy(F.desc("w"), "s").limit(n)
