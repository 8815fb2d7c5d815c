"""Closed forms: chances of empty patterns, error ceilings, storage."""

from __future__ import annotations

from fractions import Fraction
from math import comb, exp, log, prod


def filter_rate(n_keys: int, bits: int, hashes: int) -> float:
    """Chance that a Bloom filter of that size holds a key it was not given."""
    return (1 - exp(-hashes * n_keys / bits)) ** hashes


def hit_prob(fprs: tuple[float, ...], layers: int) -> float:
    """Chance that a key in no layer's set is accepted by a tier: it is passed by
    an odd number of layers and missed by the next, or passed by all Bloom
    layers when the last, exact one lists negatives."""
    out = sum(prod(fprs[: 2 * k - 1]) * (1 - fprs[2 * k - 1]) for k in range(1, (layers - 1) // 2 + 1))
    return out + (prod(fprs[: layers - 1]) if layers % 2 == 0 else 0.0)


def hit_prob_uniform(f: float, layers: int) -> float:
    return (f - f**layers) / (1 + f) if layers % 2 else (f + f**layers) / (1 + f)


def fallthrough_prob(hits: list[float]) -> float:
    return prod(1 - p for p in hits)


def walk_prob(q: float, t: int, n: int) -> float:
    """Chance that the walk over t independent prefixes ends in tier 1, where
    each is in tier 1 with chance q and else in any of the n - 1 others."""
    return 1.0 if n < 2 else 1 - (1 - q) ** t * comb(n + t - 2, t) / (n - 1) ** t


def least_q(target: float, n: int, t: int = 2) -> float:
    """The q from which walk_prob(q, t, n) reaches the target."""
    return max(0.0, 1 - (n - 1) * ((1 - target) / comb(n + t - 2, t)) ** (1 / t)) if n > 1 else 0.0


def long_bound(bound: str, length: int, max_len: int) -> float:
    """Ceiling of the ratio error of a pattern longer than max_len, for strings
    that follow the Markov assumption."""
    return float(Fraction(bound) ** (1 + 2 * max(0, length - max_len)))


def storage_bits(members: int, others: int, max_len: int, fprs: tuple[float, ...], layers: int) -> float:
    """Bits of one tier: each Bloom layer holds what its predecessors on the
    other side let pass, the last layer lists what is left at 8 bits a character."""
    side, out = [float(members), float(others)], 0.0
    for j in range(1, layers):
        own, against = (j + 1) % 2, j % 2
        f = fprs[j - 1]
        out += -log(f) / log(2) ** 2 * side[own]
        side[against] *= f
    return out + side[(layers + 1) % 2] * 8 * max_len


def s_odd(k: int, f: float, members: int, others: int, max_len: int) -> float:
    """storage_bits for 2k + 1 layers of one rate, summed in closed form."""
    return -log(f) / log(2) ** 2 * (members + others * f) / (1 - f) * (1 - f**k) + 8 * max_len * members * f**k


def s_even(k: int, f: float, members: int, others: int, max_len: int) -> float:
    """storage_bits for 2k layers of one rate, summed in closed form."""
    return -log(f) / log(2) ** 2 / (1 - f) * (members * (1 - f**k) + others * f * (1 - f ** (k - 1))) + 8 * max_len * others * f**k


def uniform_bits(members: int, others: int, max_len: int, f: float, layers: int) -> float:
    return (s_odd if layers % 2 else s_even)(layers // 2, f, members, others, max_len)


def others_of(sizes: dict[int, int], tier: int, ones: int, top: int) -> int:
    """Keys that tier's filter must refuse: tier 1 as kept, and tiers above it
    that a filter, not the tree, answers for."""
    return ones + sum(n for t, n in sizes.items() if tier < t <= top)


def total_bits(sizes: dict[int, int], ones: int, max_len: int, f: float, layers: int, top: int | None = None) -> float:
    top = top or max(sizes, default=1)
    return sum(uniform_bits(n, others_of(sizes, t, ones, top), max_len, f, layers) for t, n in sizes.items() if 2 <= t <= top and n)
