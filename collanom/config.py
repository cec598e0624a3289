"""Parameters of a detection run."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from .functions import penalties as pen


@dataclass(frozen=True)
class DetectorConfig:
    """`l` and `m` bound the length of windows, `w` the lags; `scale` multiplies every penalty, `c` is the constant of the consistency curve.

    `regime` names the penalty curve. `auto` takes the composite curve, the one for lags if w > 0 (the linear
    one if trimmed components pay `gamma` instead), and prices from the law of the savings for other costs
    than the mean's. It is resolved when prices are made, so a changed w, gamma or cost changes it too.
    """

    l: int = 2  # noqa: E741
    m: int = 100
    w: int = 0
    psi: float | None = None
    eps: float = 0.0
    gamma: float = 0.0
    regime: str = "auto"
    cost: str = "mean"
    points: bool = True
    #: Of tied windows, which lags that trim them make, the widest instead of the one that starts last.
    widest: bool = False
    beta_point: float | None = None
    min_gap: int = 0
    scale: float = 1.0
    c: float = 3.0
    how: str = "iqr"

    def __post_init__(self) -> None:
        if self.l < 1 or self.m < self.l:
            raise ValueError("windows need 1 <= l <= m")
        if self.regime != "auto" and self.regime not in pen.REGIMES:
            raise ValueError(f"unknown regime {self.regime}")
        if self.w and not self.gamma and self.regime not in ("auto", "lag", "empirical"):
            raise ValueError(f"the {self.regime} regime has no price for lags: take lag, empirical or auto, or let trimmed components pay gamma")

    @property
    def priced_by(self) -> str:
        """The regime that `auto` stands for."""
        if self.regime != "auto":
            return self.regime
        if self.cost != "mean":
            return "empirical"
        return "composite" if not self.w else "linear" if self.gamma else "lag"

    def resolved_psi(self, n: int) -> float:
        return self.psi if self.psi is not None else 2 * math.log(max(n, 2))

    def curve(self, n: int, p: int) -> list[float]:
        regime, psi, p = self.priced_by, self.resolved_psi(n), max(p, 1)
        if regime == "empirical":
            made = pen.empirical_penalty(self.cost, p, psi, self.l, self.m, 0 if self.gamma else self.w)
        else:
            made = pen.curve_for(regime, p, psi, self.w, self.eps, self.c)
        return pen.scaled(made, self.scale)

    def point_price(self, n: int, p: int) -> float:
        return self.scale * (self.beta_point if self.beta_point is not None else pen.point_penalty(max(p, 1), self.resolved_psi(n)))

    def with_(self, **changes) -> DetectorConfig:
        return replace(self, **changes)
