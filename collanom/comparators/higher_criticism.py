"""Comparator H: window p-values of the components, higher criticism, greedy selection of windows."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import DetectorConfig
from ..operators.detect import candidates, chunk_rows, known_sizes, read_block, solve, with_halo

_SCORED = "series_id string, s bigint, e bigint, k int, score double, kind string"


def normal_upper(z: np.ndarray) -> np.ndarray:
    """P(N > z) for z >= 0: a rational approximation up to 6 (absolute error below 1e-7, which is 0.2 % of the value at 5), the tail's series beyond."""
    t = 1.0 / (1.0 + 0.2316419 * z)
    poly = t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    near = np.exp(-0.5 * z * z) / np.sqrt(2 * np.pi) * poly
    with np.errstate(divide="ignore", invalid="ignore"):
        far = np.exp(-0.5 * z * z) / np.sqrt(2 * np.pi) / z * (1 - 1 / z**2 + 3 / z**4 - 15 / z**6)
    return np.where(z > 6, far, near)


def higher_criticism(z: np.ndarray, alpha0: int) -> np.ndarray:
    """Largest standardised gap between the i-th smallest p-value and i / p, over i >= alpha0; rows are windows."""
    p = z.shape[-1]
    values = np.sort(np.clip(2 * normal_upper(np.abs(z)), 1e-300, 1 - 1e-12), axis=-1)
    i = np.arange(1, p + 1)
    hc = np.sqrt(p) * (i / p - values) / np.sqrt(values * (1 - values))
    return hc[..., alpha0 - 1 : max(alpha0, p // 2)].max(axis=-1)


def hc_windows(long: DataFrame, cfg: DetectorConfig, alpha0: int = 1, threshold: float = 20.0) -> DataFrame:
    """Windows of lengths 1..m whose statistic exceeds the threshold: (series_id, s, e, k, score, kind)."""
    sizes = known_sizes(long)
    size = chunk_rows(cfg, sizes.p)
    m = cfg.m

    def score(key, group):
        block = read_block(key, group, cfg, size)
        x, first, base = block.x, block.first, block.base
        sums = np.concatenate([np.zeros((1, x.shape[1])), np.cumsum(x, axis=0)])
        out = []
        for length in range(1, min(m, len(x)) + 1):
            ends = np.arange(max(first + 1, length), len(x) + 1)
            if len(ends):
                hc = higher_criticism((sums[ends] - sums[ends - length]) / np.sqrt(length), alpha0)
                good = hc > threshold
                out.append((ends[good] - length + base, ends[good] + base, hc[good] - threshold))
        s, e, v = (np.concatenate(z) for z in zip(*out, strict=True)) if out else (np.empty(0, int), np.empty(0, int), np.empty(0))
        kinds = np.where(e - s == 1, "point", "window").tolist()
        return pa.table({"series_id": pa.array([block.series] * len(s), pa.string()), "s": s.astype(np.int64), "e": e.astype(np.int64), "k": pa.array([0] * len(s), pa.int32()), "score": v, "kind": pa.array(kinds, pa.string())})

    return with_halo(long, sizes, cfg, size).groupBy("series_id", "chunk").applyInArrow(score, _SCORED)


def higher_criticism_scan(long: DataFrame, cfg: DetectorConfig, alpha0: int = 1, threshold: float = 20.0) -> DataFrame:
    """Greedy selection (circular binary segmentation); hits of length one count as points."""
    return solve(hc_windows(long, cfg, alpha0, threshold).persist(), greedy=True)


def per_component_scan(long: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Each component by itself, hits pooled: (series_id, component, s, e, score)."""
    alone = long.select(F.concat_ws("#", "series_id", F.col("component").cast("string")).alias("series_id"), "t", F.lit(1).alias("component"), "x")
    hits = solve(candidates(alone, cfg.with_(points=False), few=True).persist(), greedy=True)
    at = F.split("series_id", "#")
    return hits.select(at[0].alias("series_id"), at[1].cast("int").alias("component"), "s", "e", "score")


def hmm_two_state(long: DataFrame, shift: float = 3.0, stay: float = 0.99) -> DataFrame:
    """(series_id, t, p_anomalous): a hidden typical/anomalous chain on the summed squares, by forward-backward passes."""
    energy = long.groupBy("series_id", "t").agg(F.sum(F.col("x") * F.col("x")).alias("q"), F.count("*").alias("p"))

    def smooth(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("t")
        q, p = pdf["q"].to_numpy(float), float(pdf["p"].iloc[0])
        scale = np.array([1.0, 1.0 + shift / np.sqrt(p)])
        log = -0.5 * q[:, None] / scale - 0.5 * p * np.log(scale)
        like = np.exp(log - log.max(axis=1, keepdims=True))
        move = np.array([[stay, 1 - stay], [1 - stay, stay]])
        n = len(q)
        a, b = np.empty((n, 2)), np.ones((n, 2))
        now = np.array([0.99, 0.01]) * like[0]
        for i in range(n):
            if i:
                now = (a[i - 1] @ move) * like[i]
            a[i] = now / now.sum()
        for i in range(n - 2, -1, -1):
            b[i] = move @ (like[i + 1] * b[i + 1])
            b[i] /= b[i].sum()
        post = a * b
        pdf["p_anomalous"] = post[:, 1] / post.sum(axis=1)
        return pdf[["series_id", "t", "p_anomalous"]]

    smooth.__annotations__ = {}
    return energy.groupBy("series_id").applyInPandas(smooth, "series_id string, t bigint, p_anomalous double")
