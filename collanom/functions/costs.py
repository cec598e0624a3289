"""Savings of refitting a window's parameter, from sums over the window.

Each family turns (sum, sum of squares, length, typical parameter) of windows into savings: twice the
gain in log-likelihood. Arrays broadcast; components are the last axis. `point` is the saving of a single
observation, whose price is `price`.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class MeanCost:
    """Change in mean of standardised values; also the quadratic loss."""

    squares: bool = False
    least: int = 1

    def saving(self, total, squares, length, rate=None):
        return total * total / length

    def point(self, x, price, rate=None):
        return x * x


@dataclass(frozen=True)
class PoissonCost:
    """Change in rate of counts; `rate` is the typical rate of each component."""

    squares: bool = False
    least: int = 1

    def saving(self, total, squares, length, rate=1.0):
        typical = np.maximum(length * np.asarray(rate, float), 1e-12)
        with np.errstate(divide="ignore", invalid="ignore"):
            log = np.where(total > 0, total * np.log(np.where(total > 0, total, 1.0) / typical), 0.0)
        return 2.0 * (log - (total - typical))

    def point(self, x, price, rate=1.0):
        return self.saving(x, None, 1.0, rate)


def _own_variance(x, price):
    """One observation by its own variance about the typical mean; the floor keeps values near that mean below the price."""
    return x * x - 1.0 - np.log(np.exp(-price) + x * x)


@dataclass(frozen=True)
class MeanVarCost:
    """Change in mean and variance of standardised values."""

    squares: bool = True
    least: int = 2

    def saving(self, total, squares, length, rate=None):
        spread = np.maximum(squares / length - (total / length) ** 2, 1e-8)
        return squares - length * (1.0 + np.log(spread))

    def point(self, x, price, rate=None):
        return _own_variance(x, price)


@dataclass(frozen=True)
class VarCost:
    """Change in variance about the typical mean."""

    squares: bool = True
    least: int = 1

    def saving(self, total, squares, length, rate=None):
        ratio = np.maximum(squares / length, 1e-8)
        return squares - length - length * np.log(ratio)

    def point(self, x, price, rate=None):
        return _own_variance(x, price)


FAMILIES = {"mean": MeanCost(), "poisson": PoissonCost(), "meanvar": MeanVarCost(), "var": VarCost()}


def residual_saving(x: np.ndarray) -> np.ndarray:
    """The mean change by its definition: squares about zero minus squares about the mean."""
    return (x**2).sum(axis=0) - ((x - x.mean(axis=0)) ** 2).sum(axis=0)
