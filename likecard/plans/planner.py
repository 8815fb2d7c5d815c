"""Plan guidance: broadcast decisions and join order from LIKE estimates."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..operators.serve import LocalModel


@dataclass(frozen=True)
class Side:
    """One filtered input of a join: an estimate of its rows, and the bytes of a row."""

    name: str
    rows: float
    row_bytes: float

    @property
    def bytes(self) -> float:
        return self.rows * self.row_bytes


def estimated_rows(local: dict[tuple[str, str], LocalModel], table: str, column: str, pattern: str, table_rows: int) -> float:
    """Rows of table that a pattern leaves; all of them where no model knows."""
    model = local.get((table, column))
    est = model.estimate(pattern) if model else None
    return float(table_rows) if est is None else min(est, float(table_rows))


def advise(sides: list[Side], limit: float) -> tuple[list[str], str]:
    """(names by rising estimated size, SQL hint): sides under the limit are
    broadcast, smallest first; the rest are merged, and one that others dwarf is
    hashed."""
    order = sorted(sides, key=lambda s: s.bytes)
    small = [s.name for s in order if s.bytes <= limit][:-1] if all(s.bytes <= limit for s in order) else [s.name for s in order if s.bytes <= limit]
    hints = [f"broadcast({', '.join(small)})"] if small else []
    rest = [s for s in order if s.name not in small]
    if not small and len(rest) > 1:
        hints.append(f"{'shuffle_hash' if rest[0].bytes * 3 < rest[1].bytes else 'merge'}({rest[0].name})")
    return [s.name for s in order], f"/*+ {', '.join(hints)} */" if hints else ""


def linked_order(names: list[str], conditions: list[str], of_column) -> list[str]:
    """names (by rising size) reordered so that each table after the first shares a
    condition with one before it; of_column names the tables of a condition."""
    edges, left, out = [of_column(c) for c in conditions], list(names), []
    while left:
        joined = [n for n in left if any(n in e and set(e) & set(out) for e in edges)]
        out.append((joined or left)[0])
        left.remove(out[-1])
    return out


def table_bytes(df: DataFrame) -> float:
    """Catalyst's size of a table, from its files."""
    return float(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def catalyst_rows(df: DataFrame) -> float | None:
    """Catalyst's own row estimate of a frame, if statistics give one."""
    count = df._jdf.queryExecution().optimizedPlan().stats().rowCount()
    return float(str(count.get())) if count.isDefined() else None


def chosen_joins(spark: SparkSession, sql: str) -> list[str]:
    """Names of the physical joins of a query, outermost first."""
    import re

    text = spark.sql(sql)._jdf.queryExecution().executedPlan().toString()
    return re.findall(r"(BroadcastHashJoin|SortMergeJoin|ShuffledHashJoin|BroadcastNestedLoopJoin)", text)
