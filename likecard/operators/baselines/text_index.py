"""compact_text_index: suffix order approximated by a piecewise-linear rank function."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BYTES = 7


def code(s: Column, fill: str = "00") -> Column:
    """The first seven bytes as a number; shorter strings are filled up."""
    return F.conv(F.rpad(F.substring(F.hex(F.encode(s, "utf-8")), 1, 2 * BYTES), 2 * BYTES, fill), 16, 10).cast("bigint")


@dataclass(frozen=True)
class TextIndex:
    suffixes: int
    knots: list[int] = field(repr=False)
    per_occurrence: float = 1.0

    def rank(self, x: Column) -> Column:
        """Suffixes below x, linear between knots of equal depth. A run of equal
        knots is a jump that belongs to the numbers from it on."""
        k, n = F.split(F.lit(",".join(map(str, self.knots))), ",").cast("array<bigint>"), len(self.knots)
        below = F.size(F.filter(k, lambda v: v < x))
        low, high = F.element_at(k, F.greatest(below, F.lit(1))), F.element_at(k, F.least(below + 1, F.lit(n)))
        part = F.when(high > low, (x - low) / (high - low).cast("double")).otherwise(0.0)
        return F.when(below == 0, 0.0).when(below >= n, float(self.suffixes)).otherwise((below - 1 + part) * self.suffixes / (n - 1))

    def estimate(self, patterns: DataFrame) -> DataFrame:
        """patterns (lit, ...) with est, 1 at least."""
        width = self.rank(code(F.col("lit"), "FF") + 1) - self.rank(code(F.col("lit")))
        return patterns.withColumn("est", F.greatest(F.lit(1.0), width * self.per_occurrence))


def fit(strings: DataFrame, knots: int = 512) -> TextIndex:
    rows = strings.filter("s != ''")
    suffixes = rows.select(F.explode(F.transform(F.sequence(F.lit(1), F.length("s")), lambda i: F.substring(F.col("s"), i, BYTES))).alias("x"))
    got = suffixes.agg(F.percentile_approx(code(F.col("x")), [i / (knots - 1) for i in range(knots)], 100_000).alias("k"), F.count("*").alias("n")).first()
    pairs = F.transform(F.sequence(F.lit(1), F.length("s") - 1), lambda i: F.substring(F.col("s"), i, 2))
    two = rows.filter(F.length("s") > 1).agg((F.sum(F.size(F.array_distinct(pairs))) / F.sum(F.size(pairs))).alias("r")).first()
    return TextIndex(got.n, list(got.k or [0]), float(two.r or 1.0))
