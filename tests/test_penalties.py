"""Penalty curves: stated numbers, shapes, and the forms without sorting."""

from __future__ import annotations

import math

import numpy as np
import pytest

from collanom.functions import penalties as pen

PSI = 2 * math.log(10_000)


def test_stated_values():
    assert pen.flat_penalty(500, PSI)[0] == pytest.approx(728.782398, abs=1e-6)
    assert pen.linear_penalty(500, PSI)[0] == pytest.approx(49.270578, abs=1e-6)
    curve = pen.curve_penalty(500, PSI)
    assert curve[0] == pytest.approx(94.199851, abs=1e-6)
    assert curve[-1] == pytest.approx(771.240345, abs=1e-6)


@pytest.mark.parametrize(("p", "psi", "sparse", "dense"), [(500, PSI, 18, 253), (100, 2 * math.log(5000), 14, 40), (64, 2 * math.log(500), 12, 22)])
def test_which_curve_binds(p, psi, sparse, dense):
    flat, linear, curve = pen.flat_penalty(p, psi), pen.linear_penalty(p, psi), pen.curve_penalty(p, psi)
    low = pen.composite_penalty(p, psi)
    for k in range(1, p + 1):
        name = "linear" if k <= sparse else "flat" if k >= dense else "curve"
        assert low[k - 1] == {"flat": flat, "linear": linear, "curve": curve}[name][k - 1]


def test_curve_never_binds_for_few_components():
    psi = 2 * math.log(5000)
    assert pen.composite_penalty(10, psi) == pen.two_regime_penalty(10, psi)
    assert pen.composite_penalty(5, 2 * math.log(720)) == pen.linear_penalty(5, 2 * math.log(720))


@pytest.mark.parametrize("p", [5, 64, 300])
def test_increasing_and_concave(p):
    for curve in (pen.curve_penalty(p, 20.0), pen.composite_penalty(p, 20.0)):
        steps = np.diff(curve)
        assert (steps >= -1e-9).all()
        assert (np.diff(steps) <= 1e-6).all()


def test_increments_round_trip():
    curve = pen.composite_penalty(40, 15.0)
    assert pen.from_increments(*pen.to_increments(curve)) == pytest.approx(curve)


def test_lines_bound_the_statistic():
    rng = np.random.default_rng(3)
    curve = np.array(pen.composite_penalty(64, 12.0))
    few, all_ = pen.chords(curve), pen.chords(curve, 400)
    for _ in range(200):
        s = rng.chisquare(1, 64) * rng.uniform(0.5, 6)
        exact = (np.cumsum(-np.sort(-s)) - curve).max()
        bound = max(np.maximum(s - g, 0).sum() - c for g, c in few)
        every = max(np.maximum(s - g, 0).sum() - c for g, c in all_)
        assert bound >= exact - 1e-9 or exact < 0
        if exact > 0:
            assert every == pytest.approx(exact, abs=1e-6)


def test_lag_penalties():
    assert pen.lag_linear_penalty(10, 5.0, 0, 0.0) == pytest.approx(pen.linear_penalty(10, 5.0))
    assert pen.lag_charge(0) == 0
    assert pen.lag_linear_penalty(10, 5.0, 20)[0] > pen.lag_linear_penalty(10, 5.0, 10)[0]


def test_presets_and_bound():
    assert pen.psi_for("power", 100, 50) == pytest.approx(2 * math.log(100) + 2 * math.log(math.log(50)))
    assert pen.false_positive_bound(1000, 30.0, 50) < pen.false_positive_bound(1000, 30.0)


@pytest.mark.parametrize("cost", ["mean", "poisson", "meanvar", "var"])
def test_empirical_curve(cost):
    curve = np.array(pen.empirical_penalty(cost, 30, 8.0, 4, 40))
    assert (np.diff(curve) >= -1e-9).all() and (np.diff(curve, 2) < 1e-9).all()
    assert (np.array(pen.empirical_penalty(cost, 30, 8.0, 4, 40, 5)) > curve).all()
    if cost == "mean":
        # prices of the simulated law lie near those that are derived for it
        known = np.array(pen.composite_penalty(30, 8.0))
        assert (curve > 0.75 * known).all() and (curve < 1.8 * known).all()


@pytest.mark.parametrize("cost", ["poisson", "meanvar", "var"])
def test_empirical_curve_holds_its_level(cost):
    """Of windows of noise, fewer than exp(-psi) are above the curve."""
    rng, p, psi = np.random.default_rng(3), 6, 4.0
    curve = np.array(pen.empirical_penalty(cost, p, psi, 5, 40))
    for size in (5, 12, 40):
        draws = rng.choice(pen.null_savings(cost, float(size)), (40_000, p))
        top = np.cumsum(-np.sort(-draws, axis=1), axis=1)
        assert (top > curve).any(axis=1).mean() < math.exp(-psi)
