"""Baselines, and the directions in which methods differ."""

from __future__ import annotations

import math

import numpy as np
import pytest

from collanom import workloads
from collanom.comparators import changepoints, higher_criticism
from collanom.config import DetectorConfig
from collanom.operators import detect, evaluate, simulate


@pytest.fixture(scope="module")
def series(spark):
    truth = simulate.truth_frame(spark, [("0", 1, 100, 130, c, 0, 0, 3.0) for c in (1, 2)])
    return simulate.inject(simulate.noise(spark, 300, 6, 2, 6), truth).persist(), truth


def test_normal_tail():
    z = np.array([0.0, 1.0, 1.96, 3.0, 8.0])
    want = [0.5 * math.erfc(v / math.sqrt(2)) for v in z]
    assert higher_criticism.normal_upper(z) == pytest.approx(want, rel=1e-3)
    assert higher_criticism.normal_upper(z[:4]) == pytest.approx(want[:4], abs=1e-7)


def test_higher_criticism_by_definition():
    z = np.array([[3.0, 0.2, -1.0, 0.5]])
    p = np.sort([math.erfc(abs(v) / math.sqrt(2)) for v in z[0]])
    want = max(2 * (i / 4 - p[i - 1]) / math.sqrt(p[i - 1] * (1 - p[i - 1])) for i in (1, 2))
    assert higher_criticism.higher_criticism(z, 1)[0] == pytest.approx(want, rel=1e-3)


def test_comparators_find_a_strong_window(series):
    long, truth = series
    hc = higher_criticism.higher_criticism_scan(long, DetectorConfig(m=40), 2, 25.0)
    assert evaluate.match_windows(hc, truth).count() == 1
    for found in (changepoints.sparse_projection_changepoints(long), changepoints.classical_changepoints(long), changepoints.classical_changepoints(long, "wild"), changepoints.classical_changepoints(long, "partition"), changepoints.double_cusum(long)):
        rows = found.where("series_id = '0'").collect()
        assert any(abs(r["cp"] - 100) <= 3 for r in rows) and any(abs(r["cp"] - 130) <= 3 for r in rows)
        assert found.where("series_id = '1'").count() <= 1
    single = higher_criticism.per_component_scan(long, DetectorConfig(m=40))
    assert {r["component"] for r in single.where("series_id = '0'").collect()} == {1, 2}
    post = {r["t"]: r["p_anomalous"] for r in higher_criticism.hmm_two_state(long).where("series_id = '0'").collect()}
    assert post[115] > 0.9 > 0.5 > post[30]


def test_partition_is_optimal():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(26, 2))
    x[9:17] += 2

    def cost(a, b):
        return ((x[a:b] - x[a:b].mean(axis=0)) ** 2).sum()

    best = [0.0] + [math.inf] * 26
    for e in range(2, 27):
        for s in range(0, e - 1):
            best[e] = min(best[e], best[s] + cost(s, e) + 5.0) if s == 0 or s >= 2 else best[e]
    cps = [0, *(c for c, _ in changepoints._mean_cost_partition(x, 5.0, 2)), 26]
    assert sum(cost(a, b) + 5.0 for a, b in zip(cps, cps[1:], strict=False)) == pytest.approx(best[26])


def test_right_lag_is_best_and_points_matter_little(spark):
    """With lags in the data the right lag locates best; points change hardly anything."""
    base, truth, _ = workloads.simulated(spark, 4, 10, False, 6, 1500, rate=0.004, seed=3)
    spiked, _, _ = workloads.simulated(spark, 4, 10, True, 6, 1500, rate=0.004, seed=3)
    found = {}
    for name, long in (("plain", base), ("spiked", spiked)):
        for w in (0, 10):
            cfg = workloads.detector(w, 1500).with_(m=60)
            found[name, w] = evaluate.match_windows(detect.detect(long, cfg).windows, truth)
    errors = {r["method"]: r["mad"] for r in evaluate.location_error({"w=0": found["plain", 0], "w=10": found["plain", 10]}).collect()}
    assert errors["w=10"] < errors["w=0"]
    for w in (0, 10):
        assert abs(found["plain", w].count() - found["spiked", w].count()) <= 2


def test_detector_locates_better_than_higher_criticism(spark):
    rows = {r["method"]: r["mad"] for r in workloads.location_study(spark, 1, 10, False, replicates=6, n=1500).collect()}
    assert rows["detector w=0"] <= rows["higher criticism"]


def test_false_positives_and_power(spark, sf):
    for r in workloads.false_positive_study(spark, sf, 4).collect():
        assert r["p_window"] <= 0.25
    power = {(r["xi"], r["r"], r["regime"]): r["power"] for r in workloads.power_study(spark, replicates=4).collect()}
    assert power[0.85, 3.0, "composite"] >= power[0.85, 0.5, "composite"]
    assert power[0.3, 0.05, "composite"] >= power[0.3, 0.3, "composite"]
    assert all(power[x, r, "composite"] >= power[x, r, "two"] for x, r, _ in power)


def test_consistency(spark):
    rows = workloads.consistency_study(spark).collect()
    assert all(r["k_equal"] >= 0.75 and r["within_bound"] >= 0.75 for r in rows)


def test_toy(spark):
    plain = {(r["s"], r["e"]) for r in workloads.toy(spark).collect()}
    assert len(plain) == 2
    assert all(min(abs(s - a) + abs(e - b) for a, b in ((150, 200), (350, 400))) <= 4 for s, e in plain)
    assert len({(r["s"], r["e"]) for r in workloads.toy(spark, True).collect()}) == 2
