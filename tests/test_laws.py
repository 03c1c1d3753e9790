"""Closed forms against plain sums, and their limits."""

import math

import pytest

from sparse_release.functions import laws as L
from sparse_release.functions.noise import alpha_of, moments, sensitivity

ALPHA = math.exp(-0.1)


def mass(alpha, x):
    return (1 - alpha) / (1 + alpha) * alpha**x


def keep(x, cut, tau):
    return 0.0 if x < max(cut, 1) else min(x / tau, 1.0) if tau > 1 else 1.0


@pytest.mark.parametrize("eps", [0.01, 0.1, 0.5, 1.0, 2.0])
@pytest.mark.parametrize("cut", [0, 1, 2, 5, 17, 40])
@pytest.mark.parametrize("tau", [0.5, 1.0, 3.0, 5.0, 12.5, 20.0, 20.7, 100.0])
def test_keep_law(eps, cut, tau):
    a = math.exp(-eps)
    total = [2 * mass(a, x) * keep(x, cut, tau) for x in range(1, 6000)]
    law = L.KeepLaw(a, cut, tau)
    assert law.keep() == pytest.approx(sum(total), abs=1e-12)
    assert L.KeepLaw(a, cut, tau, 1).keep() == pytest.approx(sum(total) / 2, abs=1e-12)
    for x in (1, 2, 5, 6, 18, 21, 41, 101):
        assert law.at_least(x) == pytest.approx(sum(total[x - 1 :]) / sum(total), abs=1e-9)
    cuts = law.cuts()
    assert cuts == sorted(cuts, reverse=True)


@pytest.mark.parametrize(("cut", "tau", "sides", "p"), [(1, 1, 1, 0.47502081), (5, 1, 1, 0.31841597), (5, 1, 2, 0.63683195), (0, 7, 2, 0.71796664), (0, 40, 2, 0.24501253), (0, 12.5, 2, 0.56955986), (5, 20, 2, 0.39441347), (10, 10, 2, 0.38625810), (20, 10, 2, 0.14209641), (5, 20.5, 2, 0.38792958)])
def test_known_values(cut, tau, sides, p):
    law = L.KeepLaw(ALPHA, cut, tau if tau > cut or cut == tau else 1.0, sides)
    assert law.keep() == pytest.approx(p, abs=5e-9)


def test_choices():
    m, n = 1_000_000, 100_000
    assert L.pick_cut(m, n, ALPHA, 1e5, 1) == 16 and L.pick_cut(m, n, ALPHA, 1e5, 2) == 23
    assert L.pick_tau(1e7, m, ALPHA, 1e5) == pytest.approx(199.8335, abs=1e-4)
    tau = L.pick_tau_empty(m, n, ALPHA, 1000)
    assert (m - n) * L.KeepLaw(ALPHA, 0, tau).keep() == pytest.approx(1000, rel=1e-6)
    tau = L.solve_tau([(100, n)], m, n, ALPHA, 50_000)
    assert n * min(100 / tau, 1) + (m - n) * L.KeepLaw(ALPHA, 0, tau).keep() == pytest.approx(50_000, rel=1e-6)
    assert L.laplace_keep(10, 5, 3) == pytest.approx(math.exp(-0.5))
    assert L.laplace_keep(10, 0, 20) == pytest.approx(0.5 * (1 - math.exp(-2)))
    assert L.predicted_error(100_000, m, ALPHA, "tree") < L.predicted_error(100_000, m, ALPHA) and L.predicted_error(100, m, ALPHA, "tree") > L.predicted_error(100, m, ALPHA)


def test_noise_numbers():
    got = moments(ALPHA)
    assert got["zero"] == pytest.approx(0.0499584, abs=1e-7) and got["mean_abs"] == pytest.approx(9.983353, abs=1e-6) and got["variance"] == pytest.approx(199.83342, abs=1e-5)
    assert [sensitivity("disjoint"), sensitivity("levels", levels=21), sensitivity("grid", a=8, b=6), sensitivity("sketch", rows=3), sensitivity("groupings", sets=4), sensitivity("bounded", rows=5)] == [1, 21, 48, 6, 4, 5]
    with pytest.raises(ValueError):
        alpha_of(0)


def test_cut_of_a_full_domain():
    """No empty cell: the least cut, and no error."""
    assert [L.pick_cut(281_250, 281_250, ALPHA, 20_000, s) for s in (1, 2)] == [1, 1] and L.pick_cut(281_250, 281_249, ALPHA, 20_000, 2) == 1
