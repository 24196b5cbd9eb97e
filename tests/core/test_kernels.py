import itertools
import math
import random

import numpy as np
import pytest

from sizeprofile.functions import isotonic as iso
from sizeprofile.functions import noise
from sizeprofile.functions.budget import BudgetExceeded, BudgetLedger
from sizeprofile.operators import matching


def test_worked_isotonic_example():
    x = [3, 1, 2, 5, 4]
    assert iso.isotonic_l2(x).tolist() == [2, 2, 2, 4.5, 4.5]
    assert iso.isotonic_l1(x).tolist() == [1, 1, 2, 4, 4]


@pytest.mark.parametrize("p", [1, 2])
def test_isotonic_equals_min_max_form(p):
    rnd = random.Random(p)
    for _ in range(300):
        x = [rnd.randint(-5, 9) for _ in range(rnd.randint(1, 12))]
        got = iso.isotonic(x, p)
        assert np.allclose(got, iso.isotonic_minmax(x, p))
        assert (np.diff(got) >= -1e-12).all()


@pytest.mark.parametrize("p", [1, 2])
def test_clipped_fit_is_optimal(p):
    rnd = random.Random(p)
    for _ in range(60):
        x = [rnd.randint(-3, 7) for _ in range(rnd.randint(1, 5))]
        got = iso.isotonic(x, p, 0, 4)
        cost = lambda y: sum(abs(a - b) ** p for a, b in zip(x, y))
        grid = [k / 4 for k in range(17)] if p == 2 else range(5)
        best = min(cost(y) for y in itertools.combinations_with_replacement(grid, len(x)))
        assert cost(got) <= best + 1e-9


def test_empty_isotonic():
    assert len(iso.isotonic_l2([])) == 0 and len(iso.isotonic_l1([])) == 0


def test_noise_law():
    for scale in (0.5, 2.0, 10.0):
        ks = range(-4000, 4001)
        p = [noise.geometric_pmf(k, scale) for k in ks]
        assert math.isclose(sum(p), 1, abs_tol=1e-9)
        assert math.isclose(sum(k * k * x for k, x in zip(ks, p)), noise.geometric_variance(scale), rel_tol=1e-6)
        assert max(noise.geometric_pmf(k, scale) / noise.geometric_pmf(k + 1, scale) for k in range(-20, 20)) <= math.exp(1 / scale) + 1e-9
        d = noise.noise_density(scale)
        assert math.isclose(d["nonzero"], 1 - noise.geometric_pmf(0, scale)) and math.isclose(d["positive"], d["nonzero"] / 2)


def test_sensitivities_by_exhaustion():
    """All neighbours (one entity more) of all databases of three groups with sizes up to 4."""

    def forms(sizes, k=6):
        h = [sizes.count(i) for i in range(k + 1)]
        return {"naive": h, "hc": list(np.cumsum(h)), "hg": sorted(sizes)}

    worst = dict.fromkeys(("naive", "hc", "hg"), 0)
    for sizes in itertools.product(range(5), repeat=3):
        for i in range(3):
            more = [*sizes]
            more[i] += 1
            a, b = forms(list(sizes)), forms(more)
            for m in worst:
                worst[m] = max(worst[m], sum(abs(x - y) for x, y in zip(a[m], b[m])))
    assert worst == {m: noise.SENSITIVITY[m] for m in worst}


def test_ledger():
    ledger = BudgetLedger(1.0)
    assert ledger.split(4) == [0.25] * 4
    with pytest.raises(BudgetExceeded):
        ledger.spend("more", 0.01)
    parallel = BudgetLedger(1.0)
    for k in range(6):
        parallel.spend("categories", 1.0, f"category {k}")
    assert parallel.spent == 1.0
    assert BudgetLedger(1.0).split(2, [1, 3]) == [0.25, 0.75]


def test_secret_seed_hides_itself():
    assert "..." in repr(noise.SecretSeed()) and noise.SecretSeed() != noise.SecretSeed()


def test_hamilton_shares():
    assert matching.hamilton_shares([300, 100], [200, 100, 100]) == [[150, 75, 75], [50, 25, 25]]
    assert matching.hamilton_shares([10, 20], [11, 10, 9])[0] == [4, 3, 3]
    rnd = random.Random(2)
    for _ in range(300):
        have = [rnd.randint(0, 20) for _ in range(rnd.randint(1, 5))]
        cut = sorted(rnd.randint(0, sum(have)) for _ in range(3))
        n = [b - a for a, b in zip([0, *cut], [*cut, sum(have)])]
        for shares in (matching.hamilton_shares(n, have), matching.spread_shares(n, have)):
            assert [sum(s) for s in shares] == n
            assert [sum(s) for s in zip(*shares)] == have
            assert min(map(min, shares)) >= 0


def test_spread_shares_follow_positions():
    rnd = random.Random(4)
    for _ in range(200):
        have = [rnd.randint(1, 15) for _ in range(rnd.randint(1, 4))]
        order = sorted(((2 * j - 1) / (2 * c), k) for k, c in enumerate(have) for j in range(1, c + 1))
        cut = sorted(rnd.randint(0, sum(have)) for _ in range(4))
        n = [b - a for a, b in zip([0, *cut], [*cut, sum(have)])]
        at, want = 0, []
        for take in n:
            want.append([sum(1 for _, k in order[at : at + take] if k == c) for c in range(len(have))])
            at += take
        assert matching.spread_shares(n, have) == want


def test_sorted_pairing_is_optimal_and_not_above_greedy():
    rnd = random.Random(6)
    for _ in range(80):
        a, b = ([rnd.randint(0, 12) for _ in range(6)] for _ in range(2))
        cost = sum(abs(x - y) for x, y in zip(sorted(a), sorted(b)))
        assert cost == matching.optimal_cost(a, b) <= matching.greedy_edge_cost(a, b) <= 2 * max(cost, 0) + 1e-9 or cost <= matching.greedy_edge_cost(a, b)
