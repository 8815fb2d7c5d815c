"""Estimates without a Spark job, for optimisers and single patterns."""

from __future__ import annotations

from array import array
from dataclasses import dataclass, field

from xxhash import xxh64_intdigest

from ..functions.hashing import COVER, portable_py
from ..functions.patterns import parse_like_py
from .classify import KindModel
from .estimator import Estimator


class Probe:
    """One kind's structures laid out for probes in plain Python: each prefix is
    hashed once for all filters (fast family), words are one array a filter, and
    keys of the upper tree are looked up whole."""

    def __init__(self, model: KindModel):
        self.high, self.tiers = model.tree_keys, []
        for t, f in sorted(model.filters.items()):
            blooms = [(b.salt.encode(), b.salt, b.n_bits, b.n_hashes, array("q", b.words), b.family) for b in f.blooms]
            self.tiers.append((t, blooms, f.keys, f.layers % 2 == 1))

    def tier(self, key: str, most: int = 1 << 30) -> int | None:
        """The first tier up to `most` that accepts a key, else 1."""
        if (found := self.high.get(key)) is not None:
            return found
        base = xxh64_intdigest(key.encode("utf-8", "surrogatepass"), 42)  # what all fast hashes of a key begin with
        for t, blooms, residual, odd in self.tiers:
            if t > most:
                break
            accepted = None
            for j, (salt, text, bits, hashes, words, family) in enumerate(blooms):
                if family == "fast":
                    h = xxh64_intdigest(salt, base)
                    p, step = (h & COVER) % bits, (h >> 24 | 1) % bits
                else:
                    a, b = portable_py(text, key)
                    p, step = a % bits, b % bits
                for _ in range(hashes):
                    if not words[p >> 6] >> (p & 63) & 1:
                        accepted = j % 2 == 1
                        break
                    p = (p + step) % bits
                if accepted is not None:
                    break
            if accepted is None:
                accepted = (key in residual) == odd
            if accepted:
                return t
        return 1

    def walk(self, key: str, rule: str = "monotone") -> int:
        """As KindModel.walk. Under the monotone rule a longer prefix in a higher
        tier settles tier 1 just as one in none, so no tier above the last one
        is asked."""
        last = None
        for i in range(1, len(key) + 1):
            t = self.tier(key[:i], last if rule == "monotone" and last is not None else 1 << 30)
            if t == 1 or rule == "monotone" and last is not None and last < t:
                return 1
            last = min(last, t) if rule == "min" and last is not None else t
        return last or 1


@dataclass(frozen=True)
class LocalModel:
    """Probes the gathered structures in plain Python, without a Spark job."""

    estimator: Estimator
    probes: dict[str, Probe] = field(default_factory=dict, repr=False)

    def __post_init__(self):
        self.probes.update({k: Probe(m) for k, m in self.estimator.models.items()})

    def tier(self, kind: str, lit: str) -> int:
        key = lit[::-1] if kind == "S" else lit
        if self.estimator.config.strategy == "direct":
            return self.probes[kind].tier(key)
        return self.probes[kind].walk(key, self.estimator.config.rule)

    def estimate_key(self, kind: str, lit: str, clamp: bool | None = None) -> float:
        """The estimate of a literal of any length."""
        e, size = self.estimator, self.estimator.config.max_len
        if not lit:
            return float(e.n_records)
        if len(lit) <= size:
            return e.schemes[kind].value(self.tier(kind, lit))
        clamp = e.config.clamp if clamp is None else clamp
        key = lit[::-1] if kind == "S" else lit
        turn = (lambda s: s[::-1]) if kind == "S" else (lambda s: s)
        inner = lambda s: e.schemes["C"].value(self.tier("C", turn(s)))
        out = e.schemes[kind].value(self.tier(kind, turn(key[:size])))
        least = float("inf")
        for i in range(1, len(key) - size + 1):
            win, ctx = inner(key[i : i + size]), inner(key[i : i + size - 1])
            out *= min(1.0, win / ctx) if clamp else win / ctx
            least = min(least, win)
        return max(e.schemes[kind].value(1), min(out, least)) if clamp else out

    def estimate(self, pattern: str, escape: str = "\\") -> float | None:
        """The estimate of a LIKE text; None for kinds it has no model for."""
        if pattern == "%":
            return float(self.estimator.n_records)
        kind, lit = parse_like_py(pattern, escape)
        return self.estimate_key(kind, lit) if kind in self.estimator.models else None
