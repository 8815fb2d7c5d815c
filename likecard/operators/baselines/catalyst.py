"""catalyst_default: the optimiser's own row estimate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...plans.planner import catalyst_rows


def estimate(strings: DataFrame, pattern: str, n_records: int, escape: str = "\\") -> float:
    """Rows that Catalyst expects; without statistics it has only the size, and
    a filter leaves that whole, so the number of records is returned."""
    rows = catalyst_rows(strings.filter(F.col("s").like(pattern)))
    return float(n_records) if rows is None else rows
