"""The plan for a run, from the sizes of the series: which statistic, which programme, which chunk."""

from __future__ import annotations

import math
from dataclasses import dataclass

from ..config import DetectorConfig
from ..functions import penalties as pen

#: Observations from which a run without a cap on lengths takes the pruned recursion.
LONG = 1000
#: Components from which sums over tiles of them are taken.
WIDE = 20_000


@dataclass(frozen=True)
class Plan:
    """Decisions, and what they cost."""

    statistic: str
    programme: str
    chunk: int
    lines: int
    pairs: int
    work: float
    shuffle_bytes: int
    reasons: tuple[str, ...]


def choose(cfg: DetectorConfig, n: int, p: int, series: int = 1) -> Plan:
    """The plan that `detect` takes for series of at most n times and p components.

    Islands where lengths are capped, one pruned recursion per long series where they aren't, tiles of
    components for very wide panels; the sum form where the curve is a line, else a screen of lines with
    exact scores for what passes it.
    """
    from ..operators.detect import chunk_rows

    curve = cfg.curve(n, p)
    linear = pen.is_linear(curve)
    lines = len(pen.chords(curve))
    tiles = p > WIDE and not cfg.w and cfg.priced_by not in ("max", "consistency")
    programme = "pruned" if cfg.m >= n > LONG else "tiles" if tiles else "islands"
    chunk = 2 * cfg.m if tiles else chunk_rows(cfg, p)
    longest = min(cfg.m, n)
    pairs = series * max(0, (longest - cfg.l + 1) * (2 * n - longest - cfg.l + 2) // 2)
    work = float(pairs) * p * (1 + lines) + (pairs * p * 2 * math.ceil(math.log2(cfg.w + 1)) if cfg.w else 0)
    reasons = (
        "the curve is a line: one sum per window, nothing is sorted" if linear else f"{lines} lines screen the windows; only survivors are sorted",
        {"pruned": "no cap on lengths: one pruned recursion per series", "tiles": "more components than a task should hold: sums over tiles of them", "islands": "positive candidates fall into islands that are solved apart"}[programme],
        "lags by two sliding maxima" if cfg.w else "no lags",
    )
    return Plan("sum" if linear else "screened", programme, chunk, lines, pairs, work, int(8 * n * p * series * (1 + cfg.m / chunk)), reasons)


def explain_plan(cfg: DetectorConfig, n: int, p: int, series: int = 1) -> str:
    """The decision in words and numbers."""
    plan = choose(cfg, n, p, series)
    head = f"statistic {plan.statistic}, programme {plan.programme}, chunks of {plan.chunk} rows"
    cost = f"{plan.pairs:,} windows, {plan.work:,.0f} cell updates, {plan.shuffle_bytes:,} bytes shuffled"
    return "\n".join([head, *plan.reasons, cost])
