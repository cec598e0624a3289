"""Penalty curves P(1..p) for the number of affected components, and their parts.

All curves are plain lists of p numbers made on the driver; they are broadcast with the kernels.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from functools import lru_cache
from statistics import NormalDist

import numpy as np
from pyspark.sql import DataFrame, SparkSession

_NORMAL = NormalDist()
REGIMES = ("flat", "linear", "curve", "composite", "two", "max", "lag", "consistency", "empirical")
#: Draws of a null law, and the share of the largest that its tail is fitted to.
DRAWS, TAIL = 200_000, 0.005


def chi2_quantile(upper: float) -> float:
    """The value that a chi-square variable of one degree exceeds with this probability."""
    return _NORMAL.inv_cdf(1 - upper / 2) ** 2 if upper < 1 else 0.0


def chi2_weight(upper: float) -> float:
    """Quantile times density there: z times the normal density of z."""
    if upper >= 1:
        return 0.0
    z = _NORMAL.inv_cdf(1 - upper / 2)
    return z * _NORMAL.pdf(z)


def flat_penalty(p: int, psi: float) -> list[float]:
    """One price however many components are affected."""
    return [p + 2 * math.sqrt(p * psi) + 2 * psi] * p


def linear_penalty(p: int, psi: float, eps: float = 0.0) -> list[float]:
    """A price per window and one per affected component."""
    return [2 * (1 + eps) * psi + 2 * k * math.log(p) for k in range(1, p + 1)]


def curve_penalty(p: int, psi: float) -> list[float]:
    """Between the two: from the upper quantiles of the chi-square law."""
    q = psi + math.log(p)
    rises = [k + 2 * p * chi2_weight(k / p) for k in range(1, p + 1)]
    return [2 * q + v + 2 * math.sqrt(v * q) for v in rises]


def pointwise_min(*curves: Sequence[float]) -> list[float]:
    return [min(x) for x in zip(*curves, strict=True)]


def composite_penalty(p: int, psi: float, eps: float = 0.0) -> list[float]:
    return pointwise_min(flat_penalty(p, psi), linear_penalty(p, psi, eps), curve_penalty(p, psi))


def two_regime_penalty(p: int, psi: float, eps: float = 0.0) -> list[float]:
    """Without the curve, as an ablation."""
    return pointwise_min(flat_penalty(p, psi), linear_penalty(p, psi, eps))


def max_penalty(p: int, psi: float, eps: float = 0.0) -> list[float]:
    """Only the strongest component counts: further ones are priced out."""
    first = linear_penalty(p, psi, eps)[0]
    return [first] + [1e12 * k for k in range(1, p)]


def sparse_threshold(p: int, psi: float) -> float:
    """Number of components that parts sparse from dense changes."""
    return math.sqrt(p) * psi / math.log(p) if p > 1 else math.inf


def consistency_penalty(p: int, psi: float, c: float) -> list[float]:
    bound = sparse_threshold(p, psi)
    return [c * psi + c * k * math.log(p) if k <= bound else p + c * psi + c * math.sqrt(p * psi) for k in range(1, p + 1)]


def lag_linear_penalty(p: int, psi: float, w: int, eps: float = 0.05) -> list[float]:
    """The linear curve that also pays for the choice of lags up to w."""
    return [2 * (1 + eps) * psi + 2 * k * (1 + eps) * (math.log(p) + math.log(w + 1)) for k in range(1, p + 1)]


def lag_charge(w: int, eps: float = 0.05) -> float:
    """What a trimmed component pays where the curve is the one without lags."""
    return 2 * (1 + eps) * math.log(w + 1)


def lag_indicator_penalty(p: int, psi: float, w: int, eps: float = 0.05) -> tuple[list[float], float]:
    return linear_penalty(p, psi), lag_charge(w, eps)


def point_penalty(p: int, psi: float) -> float:
    return 2 * math.log(p) + 2 * psi


def sparse_penalty(p: int, psi: float, w: int = 0) -> list[float]:
    """For long series of few components."""
    return lag_linear_penalty(p, psi, w) if w else linear_penalty(p, psi)


@lru_cache(maxsize=128)
def null_savings(cost: str, size: float, seed: int = 1) -> np.ndarray:
    """Simulated savings of one typical component, ascending: of windows of `size` observations, for counts of that expected total."""
    from .costs import FAMILIES

    rng, family = np.random.default_rng(np.random.SeedSequence([seed, int(size * 1000)])), FAMILIES[cost]
    if cost == "poisson":
        return np.sort(family.saving(rng.poisson(size, DRAWS).astype(float), None, 1.0, size))
    total = rng.normal(0.0, math.sqrt(size), DRAWS)
    squares = total**2 / size + (rng.chisquare(size - 1, DRAWS) if size > 1 else 0.0)
    return np.sort(family.saving(total, squares, size))


class _Law:
    """A null law: the draws, and an exponential tail beyond their largest share, fitted or, for counts, the known bound 2 exp(-x / 2)."""

    def __init__(self, savings: np.ndarray, counts: bool = False) -> None:
        cut = int(len(savings) * (1 - TAIL))
        self.body, self.start = savings[:cut], float(savings[cut])
        # 5 % above the fitted mean excess: the tail is not taken for lighter than it may be
        self.rate = 0.5 if counts else 1.0 / (1.05 * max(float((savings[cut:] - self.start).mean()), 1e-6))
        self.share = 2 * math.exp(-self.start / 2) if counts else TAIL

    def excess(self, a: float, theta: float) -> float:
        """E exp(theta (S - a)+) - 1."""
        beyond = theta / (self.rate - theta)
        if a >= self.start:
            return self.share * math.exp(-self.rate * (a - self.start)) * beyond
        grown = math.exp(theta * (self.start - a))
        return (1 - TAIL) * float(np.expm1(theta * np.maximum(self.body - a, 0.0)).mean()) + TAIL * (grown - 1) + self.share * grown * beyond


@lru_cache(maxsize=256)
def empirical_lines(cost: str, p: int, psi: float, l: int, m: int, w: int = 0) -> tuple[tuple[float, float], ...]:  # noqa: E741
    """Lines (slope a, height c) of prices c + a k for savings of any law.

    The k largest savings sum to at most k a plus all that exceeds a; that excess is above c with chance
    exp(-theta c) E[exp(theta (S - a)+)]^p at most, for any theta. c makes this exp(-psi) over the number
    of lines, at the best theta, for the worst of several window lengths. A maximum over lags is at most
    the sum over them.
    """
    from .costs import FAMILIES

    least = max(l, FAMILIES[cost].least)
    sizes = (0.3, 1.0, 3.0, 10.0, 100.0) if cost == "poisson" else sorted({min(least * 2**i, max(m, least)) for i in range(8)})
    laws = [_Law(null_savings(cost, float(s)), cost == "poisson") for s in sizes]
    many = (w + 1) ** 2
    low, rate = max(x.start for x in laws), min(x.rate for x in laws)
    high = low + max(0.0, math.log(TAIL * p * many * 100)) / rate
    slopes = sorted({0.0, *(float(np.quantile(laws[0].body, q)) for q in (0.5, 0.8, 0.95)), *np.linspace(low, high, 4).tolist()})
    goal = psi + math.log(len(slopes))
    lines = []
    for a in slopes:
        heights = []
        for law in laws:
            thetas = law.rate * np.array([0.02, 0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.88, 0.94, 0.97])
            heights.append(min((goal + p * math.log1p(many * law.excess(a, float(t)))) / float(t) for t in thetas))
        lines.append((a, max(heights)))
    return tuple(lines)


def empirical_penalty(cost: str, p: int, psi: float, l: int, m: int, w: int = 0) -> list[float]:  # noqa: E741
    """The curve for savings without a formula: at every k the lowest of the lines."""
    lines = empirical_lines(cost, p, psi, l, m, w)
    return [min(c + a * k for a, c in lines) for k in range(1, p + 1)]


def psi_for(setting: str, n: int, p: int) -> float:
    """Presets: panels of many components, long streams, both, and the one of the power result."""
    presets = {
        "panel": lambda: math.log(p),
        "stream": lambda: math.log(n),
        "both": lambda: math.log(n) + math.log(p),
        "twice": lambda: 2 * math.log(n),
        "power": lambda: 2 * math.log(n) + 2 * math.log(math.log(p)),
    }
    return presets[setting]()


def false_positive_bound(n: int, psi: float, m: int | None = None, a: float = 1.0) -> float:
    """The order of the bound on the chance of any false window: n^2 or n*M times e^-psi."""
    return min(1.0, a * n * (m or n) * math.exp(-psi))


def to_increments(curve: Sequence[float]) -> tuple[float, list[float]]:
    """The price of a window and of each further component; only the curve matters for the statistic."""
    beta = [0.0, *np.diff(np.asarray(curve, float)).tolist()]
    return float(curve[0]), beta


def from_increments(alpha: float, beta: Sequence[float]) -> list[float]:
    return (alpha + np.cumsum(np.asarray(beta, float))).tolist()


def is_linear(curve: Sequence[float]) -> bool:
    """Whether equal steps allow the form without sorting."""
    steps = np.diff(np.asarray(curve, float))
    return len(steps) < 2 or float(np.ptp(steps)) < 1e-9 * max(1.0, float(np.abs(curve).max()))


def scaled(curve: Sequence[float], c: float) -> list[float]:
    return [c * x for x in curve]


def chords(curve: Sequence[float], nodes: int = 9) -> list[tuple[float, float]]:
    """Lines (slope g, height c) whose minimum lies on or below a concave curve, touching it at the nodes.

    The sum of (saving - g)+ minus c, at its largest over the lines, is then never below the penalised
    saving; it equals it if the curve is a line, or with a node at every k.
    """
    p = len(curve)
    if p == 1:
        return [(0.0, float(curve[0]))]
    if is_linear(curve):
        g = float(curve[1] - curve[0])
        return [(g, float(curve[0]) - g)]
    at = sorted({1, p, *(int(round(p ** (i / (nodes - 1)))) for i in range(nodes))})
    lines = []
    for a, b in zip(at, at[1:], strict=False):
        g = (curve[b - 1] - curve[a - 1]) / (b - a)
        lines.append((float(g), float(curve[a - 1] - g * a)))
    # a price for further components that is out of reach (max) is no concave curve: keep its first step
    return lines


def curve_for(regime: str, p: int, psi: float, w: int = 0, eps: float = 0.0, c: float = 1.0) -> list[float]:
    """The curve of a named regime."""
    made = {
        "flat": lambda: flat_penalty(p, psi),
        "linear": lambda: linear_penalty(p, psi, eps),
        "curve": lambda: curve_penalty(p, psi),
        "composite": lambda: composite_penalty(p, psi, eps),
        "two": lambda: two_regime_penalty(p, psi, eps),
        "max": lambda: max_penalty(p, psi, eps),
        "lag": lambda: lag_linear_penalty(p, psi, w, eps or 0.05),
        "consistency": lambda: consistency_penalty(p, psi, c),
    }
    return made[regime]()


def penalty_table(spark: SparkSession, p: int, psi: float) -> DataFrame:
    """(k, flat, linear, curve, composite, binding): which curve is the lowest at each k."""
    rows = []
    for k, values in enumerate(zip(flat_penalty(p, psi), linear_penalty(p, psi), curve_penalty(p, psi), strict=True), 1):
        low = min(values)
        rows.append((k, *map(float, values), float(low), ("flat", "linear", "curve")[values.index(low)]))
    return spark.createDataFrame(rows, "k int, flat double, linear double, curve double, composite double, binding string")
