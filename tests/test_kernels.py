"""Array kernels against brute force: scores, programmes, lags, points, pruning."""

from __future__ import annotations

import itertools
import dataclasses
import math

import numpy as np
import pytest

from collanom.config import DetectorConfig
from collanom.functions import penalties as pen
from collanom.functions.costs import FAMILIES, residual_saving
from collanom.operators.blocks import Chain, Kernel, best_chain, dense_optimum, greedy_chain, pruned_optimum, undominated


def kernel(n, p, **changes):
    cfg = DetectorConfig(**({"l": 2, "m": n, "psi": 1.5, "regime": "composite"} | changes))
    return Kernel(cfg.l, cfg.m, cfg.curve(n, p), cfg.cost, cfg.w, cfg.gamma, cfg.point_price(n, p), cfg.points)


def brute_windows(x, k):
    """Every window's penalised saving by its definition, with lags."""
    n, p = x.shape
    out = {}
    for s in range(n):
        for e in range(s + k.l, min(n, s + k.m) + 1):
            savings = []
            for c in range(p):
                best = -math.inf
                for d in range(k.w + 1):
                    for f in range(k.w + 1):
                        a, b = s + d, e - f
                        if b - a >= k.l:
                            v = residual_saving(x[a:b, c : c + 1])[0] - (k.gamma if d or f else 0.0)
                            best = max(best, v)
                savings.append(best)
            top = np.cumsum(sorted(savings, reverse=True)) - k.price
            out[s, e] = float(top.max())
    return out


@pytest.mark.parametrize("w", [0, 1, 3])
@pytest.mark.parametrize("gamma", [0.0, 1.5])
@pytest.mark.parametrize("regime", ["linear", "composite"])
def test_scores(w, gamma, regime):
    rng = np.random.default_rng(w)
    x = rng.normal(size=(24, 3))
    x[8:15, :2] += 2.5
    if w and not gamma:
        regime = "lag"
    k = kernel(24, 3, m=10, w=w, gamma=gamma, regime=regime)
    truth = {key: v for key, v in brute_windows(x, k).items() if v > 1e-9}
    f = k.scores(x, 0)
    found = {(int(s), int(e)): v for s, e, v in zip(f["s"], f["e"], f["score"], strict=True)}
    assert found.keys() == truth.keys()
    for key, v in truth.items():
        assert found[key] == pytest.approx(v, abs=1e-8)


def all_chains(items):
    """Every set of intervals that don't overlap, by enumeration."""
    best = 0.0
    for r in range(len(items) + 1):
        for some in itertools.combinations(items, r):
            ordered = sorted(some)
            if all(a[1] <= b[0] for a, b in zip(ordered, ordered[1:], strict=False)):
                best = max(best, sum(i[2] for i in some))
    return best


def test_optimum_by_enumeration():
    rng = np.random.default_rng(4)
    for _ in range(15):
        x = rng.normal(size=(9, 2))
        x[2:5] += rng.normal(0, 2.5, 2)
        x[7, 0] += 4
        k = kernel(9, 2, m=5, psi=0.7)
        windows = [(s, e, v, "window") for (s, e), v in brute_windows(x, k).items() if v > 0]
        points = [(i, i + 1, float(v), "point") for i, v in enumerate(k.point_savings(x)) if v > 0]
        items = sorted(windows + points, key=lambda i: -i[2])[:14]
        full = all_chains(items) if len(windows) + len(points) <= 14 else None
        value, parts, _ = dense_optimum(x, k)
        chain, _ = best_chain(windows + points)
        assert value == pytest.approx(chain, abs=1e-9)
        if full is not None:
            assert value == pytest.approx(full, abs=1e-9)
        assert sum(i[2] for i in parts) == pytest.approx(value)


@pytest.mark.parametrize("w", [0, 1, 3])
def test_pruned_equals_dense(w):
    rng = np.random.default_rng(10 + w)
    for _ in range(6):
        n = 60
        x = rng.normal(size=(n, 3))
        for s in rng.integers(0, n - 12, 3):
            x[s : s + 10, rng.integers(0, 3)] += rng.normal(0, 3)
        k = kernel(n, 3, psi=2.0, w=w, regime="lag" if w else "composite")
        dense, _, _ = dense_optimum(x, k)
        pruned, parts, profile = pruned_optimum(x, k)
        assert pruned == pytest.approx(dense, abs=1e-8)
        assert sum(a for _, a in profile) <= n * n
        f = k.scores(x, 0)
        spans = [(int(s), int(e), float(v), "window") for s, e, v in zip(f["s"], f["e"], f["score"], strict=True)]
        spans += [(i, i + 1, float(v), "point") for i, v in enumerate(k.point_savings(x)) if v > 0]
        few = [spans[i] for i in np.flatnonzero(undominated(*(np.array([x[j] for x in spans]) for j in range(3))))]
        assert best_chain(few)[0] == pytest.approx(dense, abs=1e-8)
        assert sum(spans[i][2] for i in greedy_chain(spans)) <= dense + 1e-9


def test_min_gap_keeps_windows_apart():
    spans = [(0, 5, 3.0, "window"), (5, 9, 3.0, "window"), (6, 9, 2.0, "window")]
    assert best_chain(spans)[0] == 6.0
    assert best_chain(spans, 1)[0] == 5.0


def test_ties_prefer_nothing_points_and_later_starts():
    assert best_chain([(0, 3, 0.0, "window")])[1] == []
    assert best_chain([(1, 4, 2.0, "window"), (2, 4, 2.0, "window")])[1] == [1]
    assert best_chain([(3, 4, 2.0, "window"), (3, 4, 2.0, "point")])[1] == [1]


def test_block_edges_do_not_matter():
    rng = np.random.default_rng(8)
    x = rng.normal(size=(80, 4))
    x[30:45] += 1.2
    k = kernel(80, 4, m=20, psi=2.0)
    whole = k.scores(x, 0)
    want = sorted(zip(whole["s"].tolist(), whole["e"].tolist(), np.round(whole["score"], 9).tolist(), strict=True))
    for cut in (21, 37, 50):
        a, b = k.scores(x[:cut], 0), k.scores(x[cut - 20 :], 20)
        got = list(zip(a["s"].tolist(), a["e"].tolist(), np.round(a["score"], 9).tolist(), strict=True))
        got += [(s + cut - 20, e + cut - 20, v) for s, e, v in zip(b["s"].tolist(), b["e"].tolist(), np.round(b["score"], 9).tolist(), strict=True)]
        assert [g[:2] for g in sorted(got)] == [g[:2] for g in want]


def test_invariances():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(50, 4))
    x[20:32, :3] += 2
    k = kernel(50, 4, m=20)
    value = dense_optimum(x, k)[0]
    assert dense_optimum(x[:, ::-1], k)[0] == pytest.approx(value)
    assert dense_optimum(x * np.array([1, -1, 1, -1]), k)[0] == pytest.approx(value)
    assert dense_optimum(x[::-1], k)[0] == pytest.approx(value)
    assert dense_optimum(x, kernel(50, 4, m=20, scale=1e6))[0] == 0
    assert dense_optimum(x, kernel(50, 4, m=20, w=4, gamma=1e9, regime="composite"))[0] == pytest.approx(value)


def test_savings_of_families():
    rng = np.random.default_rng(1)
    counts = rng.poisson(4.0, 12).astype(float)
    total = counts.sum()

    def likelihood(rate):
        return 2 * (counts * np.log(rate) - rate).sum()

    assert FAMILIES["poisson"].saving(np.array(total), None, 12, 3.0) == pytest.approx(likelihood(counts.mean()) - likelihood(3.0))
    z = rng.normal(1, 2, 15)
    gauss = lambda m, v: -(np.log(v) + (z - m) ** 2 / v).sum()
    assert FAMILIES["meanvar"].saving(z.sum(), (z**2).sum(), 15) == pytest.approx(gauss(z.mean(), z.var()) - gauss(0, 1))
    assert FAMILIES["var"].saving(z.sum(), (z**2).sum(), 15) == pytest.approx(gauss(0, (z**2).mean()) - gauss(0, 1))
    assert FAMILIES["mean"].saving(z.sum(), None, 15) == pytest.approx(residual_saving(z[:, None])[0])


def test_splitting_never_lowers_the_saving():
    rng = np.random.default_rng(6)
    for _ in range(50):
        x = rng.normal(size=(20, 1))
        cut = int(rng.integers(2, 18))
        parts = residual_saving(x[:cut])[0] + residual_saving(x[cut:])[0]
        gap = cut * (20 - cut) / 20 * (x[:cut].mean() - x[cut:].mean()) ** 2
        assert parts == pytest.approx(residual_saving(x)[0] + gap)


def test_config_checks():
    with pytest.raises(ValueError, match="l <= m"):
        DetectorConfig(l=5, m=3)
    assert DetectorConfig(w=3).priced_by == "lag" and DetectorConfig(w=3).with_(w=0).priced_by == "composite"
    assert DetectorConfig(w=3, gamma=2.0).priced_by == "linear" and DetectorConfig(cost="poisson").priced_by == "empirical"
    with pytest.raises(ValueError, match="no price for lags"):
        DetectorConfig(w=4, regime="flat")
    with pytest.raises(ValueError, match="no price for lags"):
        DetectorConfig(regime="composite").with_(w=4)
    with pytest.raises(ValueError, match="unknown regime"):
        DetectorConfig(regime="other")
    assert len(pen.curve_for("max", 4, 2.0)) == 4


def test_lagged_ties_go_to_the_widest_window():
    """A window that gains nothing by its first row, because lags trim it, ties with the one without it."""
    x = np.zeros((30, 3))
    x[12:20, 0], x[12:19, 1], x[13:20, 2] = 5.0, 5.0, 5.0
    k = dataclasses.replace(kernel(30, 3, m=12, w=2, regime="lag", points=False), widest=True)
    found = k.scores(x, 0)
    top = found["score"].max()
    tied = sorted((e, s) for s, e, v in zip(found["s"].tolist(), found["e"].tolist(), found["score"].tolist(), strict=True) if v >= top - 1e-9)
    assert len(tied) > 1
    want = tied[0][1], tied[0][0]
    assert [p[:2] for p in dense_optimum(x, k)[1]] == [want]
    assert [p[:2] for p in pruned_optimum(x, k)[1]] == [want]
    chain = Chain(0, True)
    kept = undominated(found["s"], found["e"], found["score"], 1e-12)
    for e, s, v in sorted(zip(found["e"][kept].tolist(), (-found["s"][kept]).tolist(), found["score"][kept].tolist(), strict=True)):
        chain.offer(-s, e, v, "window", (-s, e))
    assert chain.picked() == [want]


@pytest.mark.parametrize("w", [0, 6])
def test_scales_share_the_savings(monkeypatch, w):
    """The candidates of several scales are those of each, from savings that are made once."""
    from collanom.config import DetectorConfig
    from collanom.operators import detect

    x = np.random.default_rng(5).normal(size=(300, 5))
    x[100:115, :3] += 2
    made = []
    inner = Kernel.lagged if w else Kernel.window_savings
    monkeypatch.setattr(Kernel, "lagged" if w else "window_savings", lambda self, *a: made.append(1) or inner(self, *a))
    for regime in ("lag", "composite") if not w else ("lag",):
        cfg = DetectorConfig(m=20, w=w, psi=4.0, regime=regime if w or regime == "composite" else "linear")
        block = detect.Block("0", 300, 5, x, 0, 0, None)
        want = [detect.scored(block, cfg.with_(scale=c), few=True) for c in (0.5, 1.0, 1.5)]
        times = len(made)
        got = detect.scored_at(block, cfg, [0.5, 1.0, 1.5], few=True)
        assert (len(made) - times) * 3 == times and len(want[0]["s"])
        made.clear()
        assert all((a[c] == b[c]).all() for a, b in zip(want, got, strict=True) for c in a)
