from itertools import product

import pytest

from likecard.plans import theory, tuning


@pytest.mark.parametrize("m", [2, 3, 4, 5, 6, 7])
@pytest.mark.parametrize("f", [0.01, 0.1, 0.4, 0.8])
def test_closed_forms_agree_with_sums(f, m):
    assert abs(theory.hit_prob((f,) * (m - 1), m) - theory.hit_prob_uniform(f, m)) < 1e-12
    assert abs(theory.storage_bits(100, 900, 10, (f,) * (m - 1), m) - theory.uniform_bits(100, 900, 10, f, m)) < 1e-6


def test_walk_prob_by_enumeration():
    n, t, q = 4, 3, 0.7
    total = 0.0
    for seq in product(range(1, n + 1), repeat=t):
        p = 1.0
        for b in seq:
            p *= q if b == 1 else (1 - q) / (n - 1)
        if 1 in seq or any(y < x for x, y in zip(seq, seq[1:])):
            total += p
    assert abs(theory.walk_prob(q, t, n) - total) < 1e-12


def test_walk_is_at_least_direct():
    assert all(theory.walk_prob(q, t, n) >= q - 1e-12 for q in (0.1, 0.5, 0.9) for t in (1, 2, 5) for n in (2, 5, 16))


def test_least_q():
    assert [round(theory.least_q(0.999, 16, t), 4) for t in (2, 3, 5)] == [0.9567, 0.8294, 0.4206]
    assert abs(theory.walk_prob(theory.least_q(0.99, 9), 2, 9) - 0.99) < 1e-12


@pytest.mark.parametrize("m", range(2, 9))
def test_dividing_intervals_beats_a_dense_grid(m):
    cost = lambda f: theory.uniform_bits(3000, 36_000, 10, f, m)
    _, got = tuning.divide_rectangles(cost, tuning.LOW, tuning.HIGH)
    assert got <= min(cost(i / 2000) for i in range(1, 1998)) * 1.001


def test_feasible_set_of_odd_layers_has_two_parts():
    parts = tuning.feasible(3, 0.1)
    assert len(parts) == 2 and parts[1][1] > 0.99
    assert all(theory.hit_prob_uniform(x, 3) <= 0.1 + 1e-9 for a, b in parts for x in (a, (a + b) / 2, b))


SIZES = {1: 35_863, 2: 2987, 3: 725, 4: 276, 5: 114, 6: 46, 7: 15, 8: 6, 9: 4}


def test_published_storage_totals():
    """Totals of one rate over all tiers, rates on a 0.001 grid."""
    best = lambda ones, m: min(theory.total_bits(SIZES, ones, 10, i / 1000, m) for i in range(1, 1000)) / 8000
    assert [round(best(35_863, m), 2) for m in (2, 3, 4, 5)] == pytest.approx([10.39, 7.74, 7.66, 7.64], rel=0.03)
    assert [round(best(5795, m), 2) for m in (2, 3, 4, 5)] == pytest.approx([7.71, 5.97, 5.51, 5.32], rel=0.03)


def test_directions():
    plain = tuning.optimise(SIZES, 10)
    assert tuning.optimise(SIZES, 10, ones=5795).bits < plain.bits
    assert tuning.optimise(SIZES, 10, tree=True).bits <= plain.bits
    assert tuning.optimise(SIZES, 10, per_tier=True).bits <= plain.bits
    bits = [tuning.optimise(SIZES, 10, empty_conf=c).bits for c in (0.999, 0.9999, 0.99999)]
    assert plain.bits <= bits[0] <= bits[1] <= bits[2]


def test_constraint_is_met():
    p = tuning.optimise(SIZES, 10, empty_conf=0.999)
    plan = p.tiers[2]
    hit = theory.hit_prob(plan.fprs, plan.layers)
    assert theory.walk_prob((1 - hit) ** 8, 2, 9) >= 0.999 - 1e-9
    direct = tuning.optimise(SIZES, 10, empty_conf=0.99, strategy="direct").tiers[2]
    assert (1 - theory.hit_prob(direct.fprs, direct.layers)) ** 8 >= 0.99 - 1e-9


def test_long_bound():
    assert theory.long_bound("1.5", 12, 10) == 1.5**5


@pytest.mark.parametrize("conf", [None, 0.999])
def test_tuner_against_a_grid(conf):
    """No pair of layers and rate on a fine grid needs less than the tuned plan,
    by sums written out layer by layer."""
    from math import comb, log, sqrt

    sizes, top = {1: 40_000, 2: 3000, 3: 700, 4: 250, 5: 90, 6: 60}, 6

    def bits(m, f):
        out = 0.0
        for t in range(2, top + 1):
            own, rest = sizes[t], sizes[1] + sum(n for u, n in sizes.items() if u > t)
            for j in range(1, m):
                out += -log(f) / log(2) ** 2 * (own if j % 2 else rest)
                own, rest = (own, rest * f) if j % 2 else (own * f, rest)
            out += (own if m % 2 else rest) * 80
        return out

    def allowed(m, f):
        if conf is None:
            return True
        hit = sum(f ** (2 * k - 1) * (1 - f) for k in range(1, (m - 1) // 2 + 1)) + (f ** (m - 1) if m % 2 == 0 else 0)
        q = (1 - hit) ** (top - 1)
        return 1 - (1 - q) ** 2 * comb(top, 2) / (top - 1) ** 2 >= conf

    grid = min(bits(m, f) for m in range(2, 9) for i in range(1, 4000) for f in (10 ** (-6 + 6 * i / 4000),) if allowed(m, f))
    tuned = tuning.optimise(sizes, 10, empty_conf=conf)
    plan = tuned.tiers[2]
    assert tuned.bits <= grid * 1.001 and allowed(plan.layers, plan.fprs[0] * (1 - 1e-9))
    assert tuned.bits == pytest.approx(bits(plan.layers, plan.fprs[0]), rel=1e-6)
