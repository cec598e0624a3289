"""Array kernels: scores of all windows that end in a block, dynamic programmes, greedy selection.

A block is an n x p array of standardised values (or counts) with `halo` rows before its own rows.
Windows are half open, (s, e]; places count from the series' first row, which is 1.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np

from ..functions import penalties as pen
from ..functions.costs import FAMILIES

#: Bytes of one array of savings; wider blocks are cut over components or ends.
TILE_BYTES = 48 << 20


def sliding_max(a: np.ndarray, w: int, shift: tuple[int, int]) -> np.ndarray:
    """Maximum over j = 0..w of `a` shifted j times by `shift` (steps along axes 0 and 1), by doubling."""
    out, have = a, 0
    while have < w:
        step = min(have + 1, w - have)
        d0, d1 = step * shift[0], step * shift[1]
        if d0 < out.shape[0] and d1 < out.shape[1]:
            moved = out.copy()
            np.maximum(out[d0:, d1:], out[: out.shape[0] - d0, : out.shape[1] - d1], out=moved[d0:, d1:])
            out = moved
        have += step
    return out


@dataclass
class Kernel:
    """Everything that scoring needs; made on the driver and shipped with the tasks."""

    l: int  # noqa: E741
    m: int
    curve: Sequence[float]
    cost: str = "mean"
    w: int = 0
    gamma: float = 0.0
    beta_point: float = 0.0
    points: bool = True
    rates: Sequence[float] | None = None
    lines: list[tuple[float, float]] = field(default_factory=list)
    widest: bool = False

    def __post_init__(self) -> None:
        self.price = np.asarray(self.curve, float)
        self.exact = pen.is_linear(self.curve)
        self.lines = self.lines or pen.chords(self.curve)
        self.family = FAMILIES[self.cost]
        self.l = max(self.l, self.family.least)

    def sums(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
        zero = np.zeros((1, x.shape[1]))
        return np.concatenate([zero, np.cumsum(x, axis=0)]), np.concatenate([zero, np.cumsum(x * x, axis=0)]) if self.family.squares else None

    def window_savings(self, sums, length: int, ends: np.ndarray) -> np.ndarray:
        """Savings (ends x components) of the windows of one length."""
        p1, p2 = sums
        total = p1[ends] - p1[ends - length]
        return self.family.saving(total, p2[ends] - p2[ends - length] if p2 is not None else None, length, self.rates)

    def statistic(self, savings: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Penalised saving and number of affected components of each row: the sorted form."""
        top = np.cumsum(-np.sort(-savings, axis=-1), axis=-1) - self.price
        k = np.argmax(top, axis=-1)
        return np.take_along_axis(top, k[..., None], axis=-1)[..., 0], k + 1

    def bound(self, savings: np.ndarray) -> np.ndarray:
        """Never below the penalised saving; a plain sum for each line, nothing to sort."""
        best = None
        for g, c in self.lines:
            value = np.maximum(savings - g, 0.0).sum(axis=-1) - c
            best = value if best is None else np.maximum(best, value)
        return best

    def scores(self, x: np.ndarray, first: int, floor: float = 0.0) -> dict[str, np.ndarray]:
        """Windows with a penalised saving above `floor` that end in rows first.. of the block (0-based rows), as block places s, e."""
        return self.scores_of([self], x, first, floor)[0]

    def scores_of(self, priced: Sequence[Kernel], x: np.ndarray, first: int, floor: float = 0.0) -> list[dict[str, np.ndarray]]:
        """The scores of several kernels that differ from this one in their prices only: savings are made once for all of them."""
        n = len(x)
        sums = self.sums(x)
        if self.w:
            return self._lagged_scores(priced, x, sums, first, floor)
        found: list[list] = [[] for _ in priced]
        pairs = 0
        for length in range(self.l, min(self.m, n) + 1):
            ends = np.arange(max(first + 1, length), n + 1)
            if not len(ends):
                continue
            pairs += len(ends)
            savings = self.window_savings(sums, length, ends)
            for kernel, own in zip(priced, found, strict=True):
                maybe = kernel.bound(savings) > floor
                if maybe.any():
                    kernel._keep(own, savings[maybe], ends[maybe], length, floor)
        return [self._table(own, pairs) for own in found]

    def _keep(self, found, savings, ends, length, floor) -> None:
        score, k = self.statistic(savings)
        good = score > floor
        if good.any():
            found.append((ends[good] - length, ends[good], score[good], k[good]))

    def _table(self, found, pairs) -> dict[str, np.ndarray]:
        parts = list(zip(*found, strict=True)) if found else [[np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0)], [np.empty(0, np.int64)]]
        return dict(zip(("s", "e", "score", "k"), (np.concatenate(p) for p in parts), strict=True)) | {"pairs": np.int64(pairs)}

    def lagged(self, sums, n: int, columns: slice, low: int, high: int) -> np.ndarray:
        """Savings with lags of the windows of all lengths up to m that end in low+1..high, for some components: (m + 1) x ends x components.

        Inner windows are those of the same sums; a start shift keeps the end and shortens, an end shift
        keeps the start and shortens both.
        """
        p1, p2 = sums
        own = Kernel(self.l, self.m, self.curve, self.cost, rates=None if self.rates is None else np.asarray(self.rates)[columns], lines=self.lines)
        base = max(0, low - self.w)
        ends = np.arange(base + 1, high + 1)
        u = np.full((self.m + 1, len(ends), p1[:, columns].shape[1]), -np.inf)
        cut = (p1[:, columns], p2[:, columns] if p2 is not None else None)
        for length in range(self.l, self.m + 1):
            good = ends >= length
            if good.any():
                u[length, good] = own.window_savings(cut, length, ends[good])
        best = sliding_max(sliding_max(u, self.w, (1, 0)), self.w, (1, 1))
        out = np.maximum(u, best - self.gamma)[:, low - base :]
        return out

    def _lagged_scores(self, priced, x, sums, first, floor) -> list[dict[str, np.ndarray]]:
        n, p = x.shape
        found: list[list] = [[] for _ in priced]
        pairs = 0
        exact = all(kernel.exact for kernel in priced)
        wide = p if not exact else max(1, min(p, TILE_BYTES // (8 * (self.m + 1) * (self.w + 64))))
        rows = max(32, TILE_BYTES // (8 * (self.m + 1) * wide) - self.w)
        lengths = np.arange(self.m + 1)[:, None]
        for low in range(first, n, rows):
            high = min(n, low + rows)
            ends = np.arange(low + 1, high + 1)
            allowed = (lengths >= self.l) & (lengths <= ends)
            pairs += int(allowed.sum())
            if exact:
                total, k = np.zeros((len(priced), *allowed.shape)), np.zeros((len(priced), *allowed.shape), np.int64)
                top = np.full(allowed.shape, -np.inf)
                for a in range(0, p, wide):
                    s = self.lagged(sums, n, slice(a, min(p, a + wide)), low, high)
                    top = np.maximum(top, s.max(axis=-1))
                    for i, kernel in enumerate(priced):
                        over = s - kernel.lines[0][0]
                        k[i] += np.count_nonzero(over > 0, axis=-1)
                        total[i] += np.maximum(over, 0.0, out=over).sum(axis=-1)
                for i, kernel in enumerate(priced):
                    g, c = kernel.lines[0]
                    score = np.where(k[i] > 0, total[i], top - g) - c
                    good = allowed & (score > floor)
                    at, j = np.nonzero(good)
                    if len(at):
                        found[i].append((ends[j] - at, ends[j], score[good], np.maximum(k[i][good], 1)))
            else:
                s = self.lagged(sums, n, slice(0, p), low, high)
                for kernel, own in zip(priced, found, strict=True):
                    at, j = np.nonzero(allowed & (kernel.bound(s) > floor))
                    if len(at):
                        score, k = kernel.statistic(s[at, j])
                        good = score > floor
                        own.append(((ends[j] - at)[good], ends[j][good], score[good], k[good]))
        return [self._table(own, pairs) for own in found]

    def point_matrix(self, x: np.ndarray) -> np.ndarray:
        """Savings of single observations, rows x components."""
        return self.family.point(x, self.beta_point, self.rates)

    def point_savings(self, x: np.ndarray) -> np.ndarray:
        """Summed savings of single observations above the price of a point, per row."""
        return np.maximum(self.point_matrix(x) - self.beta_point, 0.0).sum(axis=1)

    def affected(self, x: np.ndarray, sums, s: int, e: int) -> int:
        """Number of components at which the window (s, e] has its penalised saving."""
        return int(self.statistic(_from_starts(self, *sums, np.array([s]), e))[1][0])


Interval = tuple[int, int, float, str]


def _order(interval: Interval) -> tuple:
    s, e, _, kind = interval
    return e, kind != "point", -s


def tied(total: float) -> float:
    """How far apart two equal totals may be by rounding."""
    return 1e-12 * max(1.0, abs(total))


class Chain:
    """The best set of intervals that don't overlap, offered by their ends: at one end points first, then later starts first.

    One interval is kept per end, so memory grows with the time covered and not with the intervals. Windows
    keep `min_gap` between them and whatever comes before. Equal totals: nothing before what is offered
    first; with `widest`, the earliest start instead, whose total may fall short by rounding.
    """

    def __init__(self, min_gap: int = 0, widest: bool = False) -> None:
        self.min_gap, self.widest = min_gap, widest
        self.starts: list[int] = [0]
        self.ends: list[int] = []
        self.value, self.choice, self.back = [0.0], [None], [0]

    def offer(self, s: int, e: int, score: float, kind: str, what) -> None:
        if not self.ends or self.ends[-1] != e:
            self.ends.append(e)
            self.value.append(self.value[-1])
            self.choice.append(None)
            self.back.append(len(self.value) - 2)
            self.starts.append(e)
        j = bisect_right(self.ends, s - (self.min_gap if kind == "window" else 0))
        total = self.value[j] + score
        slack = tied(total)
        earlier = self.widest and self.choice[-1] is not None and s < self.starts[-1] and total >= self.value[-1] - slack
        if earlier or total > self.value[-1] + (slack if self.widest else 1e-12):
            self.value[-1], self.choice[-1], self.back[-1], self.starts[-1] = total, what, j, s

    def picked(self) -> list:
        out, i = [], len(self.value) - 1
        while i > 0:
            if self.choice[i] is not None:
                out.append(self.choice[i])
            i = self.back[i]
        return out[::-1]


def best_chain(intervals: list[Interval], min_gap: int = 0) -> tuple[float, list[int]]:
    """The set of intervals (s, e, score, kind) of greatest total score whose members don't overlap: its score and their places."""
    chain = Chain(min_gap)
    for i in sorted(range(len(intervals)), key=lambda i: _order(intervals[i])):
        chain.offer(*intervals[i], i)
    return chain.value[-1], chain.picked()


def undominated(s: np.ndarray, e: np.ndarray, score: np.ndarray, slack: float = 0.0) -> np.ndarray:
    """Which candidates hold no other of a greater score (by more than `slack` of it), which could always replace them: a mask.

    By growing length: the best score inside (e - length, e] is that of its two parts that are shorter by one.
    """
    keep = np.ones(len(s), bool)
    if not len(s):
        return keep
    base, length = int(s.min()), e - s
    order = np.argsort(length, kind="stable")
    cuts = np.searchsorted(length[order], np.arange(int(length.max()) + 2))
    best = np.full(int(e.max()) - base + 1, -np.inf)
    for size in range(1, len(cuts) - 1):
        best[1:] = np.maximum(best[1:], best[:-1])
        here = order[cuts[size] : cuts[size + 1]]
        if len(here):
            at = e[here] - base
            keep[here] = best[at] <= score[here] * (1 + slack)
            np.maximum.at(best, at, score[here])
    return keep


def greedy_chain(intervals: list[Interval], min_gap: int = 0) -> list[int]:
    """Again and again the best interval that does not overlap those taken; windows keep `min_gap` after what comes before."""
    order = sorted(range(len(intervals)), key=lambda i: (-intervals[i][2], intervals[i][3] != "point", -intervals[i][0]))
    gap = lambda i: min_gap if intervals[i][3] == "window" else 0
    starts: list[int] = []
    taken: list[int] = []  # by start
    for i in order:
        s, e, score, _ = intervals[i]
        at = bisect_right(starts, s)
        before, after = taken[at - 1 : at], taken[at : at + 1]
        if score > 0 and all(intervals[j][1] + gap(i) <= s for j in before) and all(e + gap(j) <= intervals[j][0] for j in after):
            starts.insert(at, s)
            taken.insert(at, i)
    return taken


def dense_optimum(x: np.ndarray, kernel: Kernel) -> tuple[float, list[Interval], dict[str, int]]:
    """The reference recursion over a whole series, every window in reach."""
    n = len(x)
    sums = kernel.sums(x)
    value, back = np.zeros(n + 1), [None] * (n + 1)
    point = kernel.point_savings(x) if kernel.points else np.zeros(n)
    lag = kernel.lagged(sums, n, slice(0, x.shape[1]), 0, n) if kernel.w else None
    scored = 0
    for e in range(1, n + 1):
        best, how = value[e - 1], None
        if kernel.points and point[e - 1] > 0 and value[e - 1] + point[e - 1] > best:
            best, how = value[e - 1] + point[e - 1], (e - 1, e, point[e - 1], "point")
        lengths = np.arange(kernel.l, min(kernel.m, e) + 1)
        if len(lengths):
            savings = lag[lengths, e - 1] if lag is not None else np.stack([kernel.window_savings(sums, int(L), np.array([e]))[0] for L in lengths])
            score, _ = kernel.statistic(savings)
            scored += len(lengths)
            total = value[e - lengths] + score
            i = int(np.argmax(total))
            if kernel.widest:  # windows that only differ in what is trimmed: the widest
                i = int(np.flatnonzero(total >= total[i] - tied(total[i]))[-1])
            if total[i] > best + (tied(best) if kernel.widest else 1e-12):
                best, how = total[i], (e - int(lengths[i]), e, float(score[i]), "window")
        value[e], back[e] = best, how
    return value[n], _trace(back, n), {"scored": scored}


def _trace(back, n) -> list[Interval]:
    out, e = [], n
    while e > 0:
        if back[e] is None:
            e -= 1
        else:
            out.append(back[e])
            e = back[e][0]
    return out[::-1]


def pruned_optimum(x: np.ndarray, kernel: Kernel) -> tuple[float, list[Interval], list[tuple[int, int]]]:
    """The recursion without a cap on lengths, dropping starts that can never win again.

    A start t goes once, with l (and the lags) more steps passed, the value so far exceeds what t offers
    by the whole penalty. Returns the optimum, its parts, and (step, starts alive).
    """
    n, p = x.shape
    sums = kernel.sums(x)
    p1, p2 = sums
    whole = float(kernel.price[-1])
    value, back = np.zeros(n + 1), [None] * (n + 1)
    point = kernel.point_savings(x) if kernel.points else np.zeros(n)
    alive = np.zeros(0, np.int64)
    doomed = np.zeros(0, np.int64)  # the step after which a start is gone
    profile = []
    never = 1 << 60
    reach = kernel.l + kernel.w
    for e in range(1, n + 1):
        if e >= kernel.l:
            alive, doomed = np.append(alive, e - kernel.l), np.append(doomed, never)
        live = doomed > e
        alive, doomed = alive[live], doomed[live]
        best, how = value[e - 1], None
        if kernel.points and point[e - 1] > 0:
            best, how = value[e - 1] + point[e - 1], (e - 1, e, float(point[e - 1]), "point")
        near = alive[e - alive <= kernel.m] if kernel.m < n else alive
        if len(near):
            savings = _from_starts(kernel, p1, p2, near, e)
            score, _ = kernel.statistic(savings)
            total = value[near] + score
            i = len(total) - 1 - int(np.argmax(total[::-1]))
            if kernel.widest:  # windows that only differ in what is trimmed: the widest
                i = int(np.flatnonzero(total >= total[i] - tied(total[i]))[0])
            if total[i] > best + (tied(best) if kernel.widest else 1e-12):
                best, how = float(total[i]), (int(near[i]), e, float(score[i]), "window")
            value[e] = best
            lost = near[(value[e] - whole > total) & (near <= e - reach)]
            if len(lost):
                at = np.searchsorted(alive, lost)
                doomed[at] = np.minimum(doomed[at], e + reach)
        value[e], back[e] = best, how
        profile.append((e, len(near)))
    return float(value[n]), _trace(back, n), profile


def _from_starts(kernel: Kernel, p1, p2, starts: np.ndarray, e: int) -> np.ndarray:
    """Savings (starts x components) of windows (s, e] for given starts, with lags if any."""

    def plain(s, end):
        length = (end - s)[:, None].astype(float)
        bad = length[:, 0] < kernel.l
        length[bad] = 1.0
        out = kernel.family.saving(p1[end] - p1[s], p2[end] - p2[s] if p2 is not None else None, length, kernel.rates)
        out[bad] = -np.inf
        return out

    ends = np.full(len(starts), e)
    own = plain(starts, ends)
    if not kernel.w:
        return own
    best = own.copy()
    for f in range(kernel.w + 1):
        for d in range(kernel.w + 1):
            if d or f:
                s, t = starts + d, ends - f
                good = t - s >= kernel.l
                if good.any():
                    inner = plain(s[good], t[good])
                    best[good] = np.maximum(best[good], inner)
    return np.maximum(own, best - kernel.gamma)
