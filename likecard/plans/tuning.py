"""Layers, rates and tree threshold from tier sizes: numbers only, no data."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from ..operators.layers import TierPlan
from .theory import hit_prob_uniform, least_q, others_of, total_bits, uniform_bits

LOW, HIGH = 1e-6, 0.999


def divide_rectangles(f: Callable[[float], float], low: float, high: float, evaluations: int = 200) -> tuple[float, float]:
    """(x, f(x)) of the least value found on [low, high] by dividing intervals:
    in each round every interval that some slope makes the most promising (the
    lower convex hull of half-width against centre value) is cut in three."""
    mid = (low + high) / 2
    cells = [((high - low) / 2, f(mid), mid)]
    used = 1
    while used < evaluations:
        best_of: dict[float, tuple] = {}
        for c in cells:
            w = round(c[0], 15)
            if w not in best_of or c[1] < best_of[w][1]:
                best_of[w] = c
        hull: list[tuple] = []
        for c in sorted(best_of.values(), reverse=True):
            while len(hull) > 1 and (hull[-1][1] - hull[-2][1]) * (c[0] - hull[-2][0]) >= (c[1] - hull[-2][1]) * (hull[-1][0] - hull[-2][0]):
                hull.pop()
            if not hull or c[1] < hull[-1][1]:
                hull.append(c)
        if all(w < 1e-9 * (high - low) for w, _, _ in hull):
            break
        for c in hull:
            w, _, x = c
            cells.remove(c)
            third = w * 2 / 3
            cells += [(w / 3, c[1], x), (w / 3, f(x - third), x - third), (w / 3, f(x + third), x + third)]
            used += 2
    _, value, x = min(cells, key=lambda c: c[1])
    return x, value


def feasible(layers: int, most: float, low: float = LOW, high: float = HIGH, steps: int = 4000) -> list[tuple[float, float]]:
    """Intervals of f on which a tier accepts an empty pattern with chance
    `most` at most. For odd layers there may be two: near 1 the exact last layer
    decides almost alone. Edges are bisected."""

    def ok(f: float) -> bool:
        return hit_prob_uniform(f, layers) <= most

    def edge(a: float, b: float) -> float:
        side = ok(a)
        for _ in range(60):
            m = (a + b) / 2
            a, b = (m, b) if ok(m) == side else (a, m)
        return a if side else b

    grid = [low * (high / low) ** (i / steps) for i in range(steps + 1)]
    out, start = [], grid[0] if ok(grid[0]) else None
    for a, b in zip(grid, grid[1:]):
        if ok(a) and not ok(b):
            out.append((start, edge(a, b)))
            start = None
        elif not ok(a) and ok(b):
            start = edge(a, b)
    return out + ([(start, grid[-1])] if start is not None else [])


@dataclass(frozen=True)
class EstimatorPlan:
    """Plans of the filtered tiers (2 to top); tiers over `threshold` are in the
    tree, None for no tree. bits is the model's total."""

    tiers: dict[int, TierPlan] = field(default_factory=dict)
    threshold: int | None = None
    bits: float = 0.0

    def top(self, n: int) -> int:
        return self.threshold if self.threshold is not None else n


def _best(cost: Callable[[float, int], float], layers: int, most: float | None) -> tuple[float, float] | None:
    ranges = [(LOW, HIGH)] if most is None else feasible(layers, most)
    found = [divide_rectangles(lambda f: cost(f, layers), a, b) for a, b in ranges if b > a]
    return min(found, key=lambda x: x[1]) if found else None


def optimise(sizes: dict[int, int], max_len: int, ones: int | None = None, max_layers: int = 8, empty_conf: float | None = None, strategy: str = "walk", walk_min_prefixes: int = 2, tree: bool = False, per_tier: bool = False) -> EstimatorPlan:
    """The plan of least storage for tier sizes {tier: keys}.

    ones: tier-1 keys that filters must refuse (the frontier, where it is used).
    empty_conf bounds from below the chance that an empty pattern ends in tier
    1: through the walk over walk_min_prefixes prefixes, or directly. tree tries
    every threshold, each tree node at 8 + 4 + 16 + 1 bits. per_tier chooses
    layers and rate for each tier on its own instead of one pair for all.
    """
    ones = sizes.get(1, 0) if ones is None else ones
    n = max(sizes, default=1)
    best: EstimatorPlan | None = None
    for threshold in range(n, 0, -1) if tree else [n]:
        high = sum(k for t, k in sizes.items() if t > threshold)
        bits = high * (8 + 4 + (16 if high < 65_536 else 32) + 1)
        most = None
        if empty_conf is not None and threshold > 1:
            q = empty_conf if strategy == "direct" else least_q(empty_conf, threshold, walk_min_prefixes)
            most = 1 - q ** (1 / (threshold - 1))
        filtered = {t: k for t, k in sizes.items() if 2 <= t <= threshold and k}
        plans: dict[int, TierPlan] = {}
        if per_tier:
            for t, k in filtered.items():
                rest = others_of(sizes, t, ones, threshold)
                tries = [(m, _best(lambda f, m, k=k, rest=rest: uniform_bits(k, rest, max_len, f, m), m, most)) for m in range(2, max_layers + 1)]
                m, (f, cost) = min(((m, x) for m, x in tries if x), key=lambda y: y[1][1])
                plans[t], bits = TierPlan.uniform(m, f), bits + cost
        elif filtered:
            tries = [(m, _best(lambda f, m: total_bits(sizes, ones, max_len, f, m, threshold), m, most)) for m in range(2, max_layers + 1)]
            m, (f, cost) = min(((m, x) for m, x in tries if x), key=lambda y: y[1][1])
            plans, bits = dict.fromkeys(filtered, TierPlan.uniform(m, f)), bits + cost
        plan = EstimatorPlan(plans, threshold if tree and threshold < n else None, bits)
        if best is None or plan.bits < best.bits:
            best = plan
    return best or EstimatorPlan()
