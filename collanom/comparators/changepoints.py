"""Comparator S (sparse projection of the cumulative-sum matrix) and classical changepoint searches.

Every series is one task: these searches look at all of a series at every step. An anomalous window is
two changepoints to them.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

_FOUND = "series_id string, cp bigint, score double, level double"


def cusum_matrix(long: DataFrame) -> DataFrame:
    """(series_id, component, t, cusum): weighted difference of the means before and after each time, by a running sum."""
    w = Window.partitionBy("series_id", "component")
    running = F.sum("x").over(w.orderBy("t").rowsBetween(Window.unboundedPreceding, 0))
    n, total = F.count("*").over(w), F.sum("x").over(w)
    rows = long.select("series_id", "component", "t", running.alias("r"), n.alias("n"), total.alias("total")).where("t < n")
    value = F.sqrt(F.col("n") / (F.col("t") * (F.col("n") - F.col("t")))) * (F.col("t") / F.col("n") * F.col("total") - F.col("r"))
    return rows.select("series_id", "component", "t", value.alias("cusum"))


def _cusum(x: np.ndarray) -> np.ndarray:
    n = len(x)
    t = np.arange(1, n)[:, None]
    return np.sqrt(n / (t * (n - t))) * (t / n * x.sum(axis=0) - np.cumsum(x, axis=0)[:-1])


def sparse_direction(c: np.ndarray, lam: float, rounds: int = 50) -> np.ndarray:
    """Leading direction of the soft-thresholded matrix, by power iteration on the p x p Gram matrix."""
    m = np.sign(c) * np.maximum(np.abs(c) - lam, 0.0)
    if not m.any():
        v = np.zeros(c.shape[1])
        v[np.argmax(np.abs(c).max(axis=0))] = 1.0
        return v
    gram = m.T @ m
    v = gram[:, np.argmax(np.diag(gram))].copy()
    v /= np.linalg.norm(v)
    for _ in range(rounds):
        new = gram @ v
        new /= np.linalg.norm(new)
        if np.abs(new - v).max() < 1e-10:
            break
        v = new
    return v


def _projection(x: np.ndarray, least: int, lam: float) -> tuple[int, float]:
    c = _cusum(x)
    along = np.abs(c @ sparse_direction(c, lam))
    inner = along[least - 1 : len(along) - least + 1]
    i = int(np.argmax(inner)) + least - 1
    return i + 1, float(along[i])


def _binary(x: np.ndarray, best, threshold: float, least: int, seed: int = 0, intervals: int = 0) -> list[tuple[int, float, float]]:
    """Recursive splitting: (place, score, level); with `intervals` the best of that many random parts decides (wild search).

    The level is the least score on the way to a change: a run at a higher threshold finds those whose level
    exceeds it, so one run answers for all thresholds above its own.
    """
    rng, out, todo = np.random.default_rng(seed), [], [(0, len(x), math.inf)]
    parts = [tuple(sorted(rng.integers(0, len(x) + 1, 2).tolist())) for _ in range(intervals)]
    known: dict[tuple[int, int], tuple[int, float]] = {}
    while todo:
        a, b, above = todo.pop()
        found = []
        for i, j in [(a, b), *(p for p in parts if a <= p[0] and p[1] <= b)]:
            if j - i >= 2 * least:
                if (i, j) not in known:
                    known[i, j] = best(x[i:j])
                found.append((*known[i, j], i))
        if not found:
            continue
        at, score, begin = max(found, key=lambda f: f[1])
        if score > threshold:
            cp, level = begin + at, min(above, score)
            out.append((cp, score, level))
            todo += [(a, cp, level), (cp, b, level)]
    return sorted(out)


def _mean_cost_partition(x: np.ndarray, penalty: float, least: int) -> list[tuple[int, float, float]]:
    """Exact partition with pruning for changes in the mean vector."""
    n = len(x)
    s1 = np.concatenate([np.zeros((1, x.shape[1])), np.cumsum(x, axis=0)])
    s2 = np.concatenate([[0.0], np.cumsum((x**2).sum(axis=1))])
    f, last, alive = np.full(n + 1, np.inf), np.zeros(n + 1, int), [0]
    f[0] = -penalty
    for e in range(least, n + 1):
        a = np.array([i for i in alive if e - i >= least])
        d = s1[e] - s1[a]
        cost = f[a] + s2[e] - s2[a] - (d**2).sum(axis=1) / (e - a) + penalty
        i = int(np.argmin(cost))
        f[e], last[e] = cost[i], a[i]
        gone = set(a[cost - penalty > f[e]].tolist())
        alive = [i for i in alive if i not in gone] + [e]
    out, e = [], n
    while e > 0:
        e = last[e]
        if e > 0:
            out.append((int(e), float(penalty), float(penalty)))
    return sorted(out)


def _searched(long: DataFrame, search) -> DataFrame:
    wide = long.groupBy("series_id", "t").agg(F.transform(F.array_sort(F.collect_list(F.struct("component", "x"))), lambda c: c["x"]).alias("xs"))

    def run(pdf):
        x = np.array(pdf.sort_values("t")["xs"].tolist(), float)
        found = search(x)
        return pd.DataFrame({"series_id": pdf["series_id"].iloc[0], "cp": [f[0] for f in found], "score": [f[1] for f in found], "level": [f[2] for f in found]}, columns=["series_id", "cp", "score", "level"])

    tasks = int(long.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return wide.repartition(tasks, "series_id").groupBy("series_id").applyInPandas(run, _FOUND)  # small series are not joined in one task: their searches take long


def sparse_projection_changepoints(long: DataFrame, threshold: float | None = None, lam: float | None = None, least: int = 2, intervals: int = 50) -> DataFrame:
    """(series_id, cp, score, level): changes along sparse projections, searched over random parts and recursively."""

    def search(x):
        n, p = x.shape
        cut = lam if lam is not None else math.sqrt(math.log(max(p, 2) * math.log(max(n, 3))) / 2)
        limit = threshold if threshold is not None else 1.2 * math.sqrt(2 * math.log(n * max(p, 2))) + 1.0
        return _binary(x, lambda part: _projection(part, least, cut), limit, least, intervals=intervals)

    return _searched(long, search)


def classical_changepoints(long: DataFrame, how: str = "binary", threshold: float | None = None, least: int = 2) -> DataFrame:
    """(series_id, cp, score): `binary` or `wild` segmentation on the largest summed square, or the exact pruned `partition`."""

    def pooled(part):
        c = (_cusum(part) ** 2).sum(axis=1)
        inner = c[least - 1 : len(c) - least + 1]
        i = int(np.argmax(inner)) + least - 1
        return i + 1, float(c[i])

    def search(x):
        n, p = x.shape
        limit = threshold if threshold is not None else p + 2 * math.sqrt(2 * p * math.log(n)) + 4 * math.log(n)
        if how == "partition":
            return _mean_cost_partition(x, limit, least)
        return _binary(x, pooled, limit, least, intervals=100 if how == "wild" else 0)

    return _searched(long, search)


def double_cusum(long: DataFrame, threshold: float | None = None, least: int = 2) -> DataFrame:
    """(series_id, cp, score): binary segmentation on the gap between the m largest and the other components, at its best m."""

    def gap(part):
        c = -np.sort(-np.abs(_cusum(part)), axis=1)
        p = c.shape[1]
        m = np.arange(1, p + 1)
        top = np.cumsum(c, axis=1)
        rest = top[:, -1:] - top
        value = np.sqrt(m * (2 * p - m) / (2 * p)) * (top / m - rest / np.maximum(2 * p - m, 1))
        best = value.max(axis=1)
        inner = best[least - 1 : len(best) - least + 1]
        i = int(np.argmax(inner)) + least - 1
        return i + 1, float(best[i])

    def search(x):
        n, p = x.shape
        limit = threshold if threshold is not None else 1.6 * math.sqrt(math.log(n * p)) * math.sqrt(p) ** 0.5
        return _binary(x, gap, limit, least)

    return _searched(long, search)
