"""Calibration of the one constant that scales every penalty, and sweeps over it."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import DetectorConfig
from .detect import _kinds, candidates, chunk_rows, known_sizes, read_block, scored_at, series_sizes, solve, with_halo


def critical_scale(null: DataFrame, cfg: DetectorConfig, chunk: int | None = None, rates: DataFrame | None = None) -> DataFrame:
    """(series_id, scale): the largest constant at which a null series still shows anything.

    One pass: a series fires at c if some window's k largest savings exceed c times the curve, or some
    point exceeds c times its price; so the maximum of the ratios decides. Per chunk, then per series.
    """
    base = cfg.with_(scale=1.0)
    sizes = known_sizes(null)
    size = chunk or chunk_rows(cfg, sizes.p)

    def most(key, group):
        block = read_block(key, group, base, size)
        kernel, x, first = block.kernel(base), block.x, block.first
        sums, top = kernel.sums(x), 0.0
        if kernel.w:
            for low in range(first, len(x), 64):
                s = kernel.lagged(sums, len(x), slice(0, block.p), low, min(len(x), low + 64))
                ends = np.arange(low + 1, min(len(x), low + 64) + 1)
                lengths = np.arange(kernel.m + 1)[:, None]
                good = (lengths >= kernel.l) & (lengths <= ends)
                if good.any():
                    top = max(top, float((np.cumsum(-np.sort(-s[good], axis=-1), axis=-1) / kernel.price).max()))
        else:
            for length in range(kernel.l, min(kernel.m, len(x)) + 1):
                ends = np.arange(max(first + 1, length), len(x) + 1)
                if len(ends):
                    s = kernel.window_savings(sums, length, ends)
                    top = max(top, float((np.cumsum(-np.sort(-s, axis=-1), axis=-1) / kernel.price).max()))
        if kernel.points:
            top = max(top, float(kernel.point_matrix(x[first:]).max() / kernel.beta_point))
        return pa.table({"series_id": pa.array([block.series], pa.string()), "scale": pa.array([top], pa.float64())})

    rows = with_halo(null, sizes, base, size, rates)
    return rows.groupBy("series_id", "chunk").applyInArrow(most, "series_id string, scale double").groupBy("series_id").agg(F.max("scale").alias("scale"))


def calibrate_scale(null: DataFrame, cfg: DetectorConfig, rate: float = 0.05) -> float:
    """The smallest constant with at most this share of null series showing anything; the only number fetched."""
    return float(critical_scale(null, cfg).agg(F.percentile("scale", 1 - rate).alias("c")).first()["c"])


def sweep(long: DataFrame, cfg: DetectorConfig, scales: list[float], rates: DataFrame | None = None) -> DataFrame:
    """Chosen candidates at every scale: (series_id, scale, s, e, score, kind).

    The rows are read and dealt once; a worker makes the savings of its chunk once and scores them at each
    scale. The candidates are kept until the session's cache is cleared, and are made here, before the
    branches that read them run side by side: each would make them again.
    """
    sizes = known_sizes(long)
    size = chunk_rows(cfg, sizes.p)
    if min(scales) <= 0:
        raise ValueError("scales must be positive")

    def score(key, group):
        block = read_block(key, group, cfg, size)
        out = []
        for c, f in zip(sorted(scales), scored_at(block, cfg, sorted(scales), few=True), strict=True):
            out.append((np.full(len(f["s"]), c), f["s"], f["e"], f["score"], f["is_point"]))
        scale, s, e, v, is_point = (np.concatenate(z) for z in zip(*out, strict=True))
        return pa.table({"series_id": pa.array([block.series] * len(s), pa.string()), "scale": scale, "s": s, "e": e, "score": v, "kind": _kinds(is_point)})

    rows = with_halo(long, sizes, cfg, size, rates)
    found = rows.groupBy("series_id", "chunk").applyInArrow(score, "series_id string, scale double, s bigint, e bigint, score double, kind string").persist()
    found.count()
    return solve(found, cfg.min_gap, by=("series_id", "scale"), longest=cfg.m, widest=cfg.widest)


def tune_to_share(long: DataFrame, cfg: DetectorConfig, share: float = 0.04, scales: list[float] | None = None) -> float:
    """The scale whose windows flag a share of the positions closest to the wanted one: a grid in one pass, refined once."""

    def closest(grid: list[float]) -> float:
        n = series_sizes(long).agg(F.sum("n").alias("n")).first()["n"]
        chosen = sweep(long, cfg.with_(points=False), grid).where("kind = 'window'").groupBy("scale").agg((F.sum(F.col("e") - F.col("s")) / n).alias("share")).collect()
        known = {r["scale"]: r["share"] for r in chosen}
        return min(grid, key=lambda c: abs(known.get(c, 0.0) - share))

    grid = scales or [0.25, 0.5, 0.75, 1.0, 1.5, 2.0, 3.0, 4.0]
    best = closest(grid)
    return closest([best * f for f in (0.75, 0.85, 0.93, 1.0, 1.08, 1.18, 1.3)])


__all__ = ["calibrate_scale", "candidates", "critical_scale", "sweep", "tune_to_share"]
