"""LIKE texts to (kind, literal): P 'x%', S '%x', C '%x%', all else O."""

from __future__ import annotations

import re

from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = ("P", "S", "C")


def _shape(escape: str) -> str:
    e = re.escape(escape)
    return rf"(?s)^(%?)((?:[^%_{e}]++|{e}[%_{e}])+)(%?)(?!.)"


def parse_like(pattern: Column, escape: str = "\\") -> Column:
    """struct(kind, lit). One-sided and two-sided patterns have one literal, in
    which escaped characters stand for themselves. Equality ('abc'), the bare
    '%', inner wildcards and '_' are kind O with a null literal."""
    shape, e = _shape(escape), re.escape(escape)
    head, body, tail = (F.regexp_extract(pattern, shape, i) for i in (1, 2, 3))
    kind = F.when((head == "") & (tail == "%"), "P").when((head == "%") & (tail == ""), "S").when((head == "%") & (tail == "%"), "C").otherwise("O")
    kind = F.when(F.coalesce(pattern.rlike(shape), F.lit(False)), kind).otherwise("O")
    lit = F.regexp_replace(body, f"{e}([%_{e}])", "$1")
    return F.struct(kind.alias("kind"), F.when(kind != "O", lit).alias("lit"))


def parse_like_py(pattern: str | None, escape: str = "\\") -> tuple[str, str | None]:
    m = re.match(_shape(escape), pattern) if pattern is not None else None
    kind = {("", "%"): "P", ("%", ""): "S", ("%", "%"): "C"}.get((m[1], m[3]), "O") if m else "O"
    return kind, re.sub(f"{re.escape(escape)}([%_{re.escape(escape)}])", r"\1", m[2]) if kind != "O" else None


def to_like(kind: str, lit: str, escape: str = "\\") -> str:
    body = re.sub(f"([%_{re.escape(escape)}])", lambda m: escape + m[1], lit)
    return ("%" if kind in "SC" else "") + body + ("%" if kind in "PC" else "")


def canonical_key(kind: str, lit: Column) -> Column:
    """Literals of suffix patterns are read backwards, so that prefixes of keys
    are shorter patterns of the same kind."""
    return F.reverse(lit) if kind == "S" else lit


def matches(kind: str, s: Column, lit: Column) -> Column:
    return {"P": s.startswith, "S": s.endswith, "C": s.contains}[kind](lit)
