"""Tiers of counts: ranges so narrow that one value estimates all their members."""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction
from functools import cached_property
from math import sqrt

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class TierScheme:
    """Tier i holds counts lo to hi, hi <= lo * bound**2, greedily from 1 up to
    max_n; its value is sqrt(lo * hi) ('geomean') or lo * bound, so that value
    and count differ by a factor of bound at most."""

    bound: str
    max_n: int
    rep: str = "geomean"

    @cached_property
    def edges(self) -> tuple[tuple[int, int], ...]:
        step, lo, out = Fraction(self.bound) ** 2, 1, []
        while True:
            hi = lo * step.numerator // step.denominator
            out.append((lo, hi))
            if hi >= self.max_n:
                return tuple(out)
            lo = hi + 1

    @property
    def n(self) -> int:
        return len(self.edges)

    def value(self, tier: int) -> float:
        lo, hi = self.edges[tier - 1]
        return sqrt(lo * hi) if self.rep == "geomean" else lo * float(Fraction(self.bound))

    def tier(self, count: int) -> int:
        return next((i for i, (_, hi) in enumerate(self.edges, 1) if count <= hi), self.n)

    def tier_col(self, n: Column) -> Column:
        out = F.lit(self.n)
        for i in range(self.n - 1, 0, -1):
            out = F.when(n <= self.edges[i - 1][1], i).otherwise(out)
        return out.cast("int")

    def rep_col(self, tier: Column) -> Column:
        return F.element_at(F.array(*[F.lit(self.value(i)) for i in range(1, self.n + 1)]), tier)

    def tier_sql(self, n: str) -> str:
        return "case " + " ".join(f"when {n} <= {hi} then {i}" for i, (_, hi) in enumerate(self.edges, 1)) + f" else {self.n} end"

    def rep_sql(self, tier: str) -> str:
        return f"list_extract([{', '.join(repr(self.value(i)) for i in range(1, self.n + 1))}]::double[], {tier})"


def build(bound: str | float, max_n: int, rep: str = "geomean") -> TierScheme:
    bound = str(bound)
    if not Fraction(bound) > 1:
        raise ValueError("the bound must be over 1")
    if rep not in ("geomean", "lower_times_bound"):
        raise ValueError(rep)
    return TierScheme(bound, max(1, int(max_n)), rep)
