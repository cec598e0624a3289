"""Candidates of very wide panels: sums over tiles of components, so that no task holds a time's whole vector.

With a concave penalty curve the statistic is never above the greatest, over a few lines (g, c), of the
sum over components of (saving - g)+ minus c; these sums add up over tiles. Where the curve is a line
they are the statistic itself; elsewhere the windows whose bound is positive are scored exactly, from
ranked savings in the relational form.
"""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import DetectorConfig
from .blocks import Kernel
from .detect import _CANDIDATES, Sizes, _in_order, _with_rates, known_sizes, kernel_for, rows_in_windows
from .relational import saving_column

#: Components of a tile.
TILE = 2048
_PARTS = "series_id string, chunk bigint, length int, n bigint, p int, low bigint, sums array<double>"


def tiled_candidates(long: DataFrame, cfg: DetectorConfig, tile: int = TILE, chunk: int | None = None, sizes: Sizes | None = None, rates: DataFrame | None = None) -> DataFrame:
    """The candidates of `detect.candidates`, by tiles of components; without lags, for concave curves."""
    if cfg.w or cfg.priced_by in ("max", "consistency"):
        raise ValueError("tiles need a concave curve and no lags")
    sizes = sizes or known_sizes(long)
    size, counted = chunk or 2 * cfg.m, rates is not None
    place = F.col("t") - F.col("first")
    own = F.floor(place / size).cast("long")
    twice = F.when(place >= (own + 1) * size - cfg.m, F.array(own, own + 1)).otherwise(F.array(own))
    cells = _with_rates(long, rates).join(sizes.frame, "series_id").withColumn("tile", F.floor((F.col("component") - 1) / tile).cast("int"))
    head = ("series_id", "n", "p", "first", "last", "tile")
    dealt = cells.select(*head, "t", "component", "x", "rate", F.explode(twice).alias("chunk")).where(F.col("chunk") * size < F.col("n")).repartition("series_id", "chunk", "tile")
    rows = dealt.groupBy(*head, "chunk", "t").agg(_in_order("x").alias("xs"), _in_order("rate").alias("rates"))

    def partial(key, group):
        series, chunk_no, tile_no = (k.as_py() for k in key)
        n, p, start, last = (group.column(c)[0].as_py() for c in ("n", "p", "first", "last"))
        width = min(p - tile_no * tile, tile)
        group = group.combine_chunks().sort_by("t")
        t, lists = group.column("t").to_numpy(), group.column("xs").to_pylist()
        low, high = start + max(0, chunk_no * size - cfg.m), min(last, start + (chunk_no + 1) * size - 1)
        if len(t) != high - low + 1 or t[0] != low or t[-1] != high or any(len(v) != width or None in v for v in lists):
            raise ValueError(f"series {series} has gaps, missing values or times without all components; fill its grid first")
        x = np.array(lists, float)
        own_rates = group.column("rates")[0].as_py()
        kernel = replace(kernel_for(cfg, n, p), rates=np.array(own_rates, float) if counted else None)
        first, sums = int(start + chunk_no * size - t[0]), kernel.sums(x)
        lengths, out = [], []
        for length in range(kernel.l, min(cfg.m, len(x)) + 1):
            ends = np.arange(max(first + 1, length), len(x) + 1)
            if len(ends):
                lengths.append((length, int(ends[0]) + int(t[0]) - 1))
                out.append(_line_sums(kernel, kernel.window_savings(sums, length, ends)))
        if kernel.points:
            over = kernel.point_matrix(x[first:]) - kernel.beta_point
            lengths.append((0, first + int(t[0])))
            out.append(np.concatenate([np.maximum(over, 0.0).sum(axis=1), (over > 0).sum(axis=1)]))
        m = len(out)
        return pa.table({"series_id": pa.array([series] * m, pa.string()), "chunk": pa.array([chunk_no] * m, pa.int64()), "length": pa.array([a for a, _ in lengths], pa.int32()), "n": pa.array([n] * m, pa.int64()), "p": pa.array([p] * m, pa.int32()), "low": pa.array([b for _, b in lengths], pa.int64()), "sums": pa.array(out, pa.list_(pa.float64()))})

    def total(key, group):
        series, length = key[0].as_py(), key[2].as_py()
        n, p, low = (group.column(c)[0].as_py() for c in ("n", "p", "low"))
        group = group.combine_chunks()
        lists = group.column("sums").combine_chunks()
        lists = lists if isinstance(lists, pa.ListArray) else pa.concat_arrays(lists.chunks)
        sums = lists.flatten().to_numpy().reshape(len(lists), -1).sum(axis=0)
        kernel = kernel_for(cfg, n, p)
        if length == 0:
            score, k = np.split(sums, 2)
        else:
            parts = sums.reshape(len(kernel.lines) + 1, -1)
            score, k = (parts[:-1] - np.array([c for _, c in kernel.lines])[:, None]).max(axis=0), parts[-1]
        at = np.flatnonzero(score > 0)
        e = at + low
        return pa.table({"series_id": pa.array([series] * len(at), pa.string()), "s": e - max(length, 1), "e": e, "k": np.maximum(k[at], 1).astype(np.int32), "score": score[at], "kind": pa.array(["window" if length else "point"] * len(at), pa.string())})

    parts = rows.groupBy("series_id", "chunk", "tile").applyInArrow(partial, _PARTS)
    found = parts.groupBy("series_id", "chunk", "length").applyInArrow(total, _CANDIDATES)
    if cfg.priced_by in ("linear", "flat"):
        return found
    found = found.persist()
    return found.where("kind = 'point'").unionByName(_exact(long, found.where("kind = 'window'"), cfg, sizes, rates))


def _line_sums(kernel: Kernel, savings: np.ndarray) -> np.ndarray:
    """For each line the sums of what exceeds its slope, then the number of components above the first line's."""
    sums = [np.maximum(savings - g, 0.0).sum(axis=1) for g, _ in kernel.lines]
    return np.concatenate([*sums, (savings > kernel.lines[0][0]).sum(axis=1)])


def _exact(long: DataFrame, windows: DataFrame, cfg: DetectorConfig, sizes: Sizes, rates: DataFrame | None) -> DataFrame:
    """Windows with their penalised saving, where it is positive."""
    key = ["series_id", "s", "e"]
    per = rows_in_windows(long, windows.select(*key)).groupBy(*key, "component").agg(F.sum("x").alias("total"), F.sum(F.col("x") * F.col("x")).alias("squares"))
    savings = _with_rates(per, rates).select(*key, "component", saving_column(cfg.cost, F.col("rate")).alias("saving"))
    order = Window.partitionBy(*key).orderBy(F.desc("saving"), "component")
    ranked = savings.withColumn("k", F.row_number().over(order)).withColumn("t_k", F.sum("saving").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    curves: dict[tuple, np.ndarray] = {}

    def priced(batches):
        for batch in batches:
            pdf = batch.to_pandas()
            sizes_ = list(zip(pdf["n"], pdf["p"], strict=True))
            for n, p in set(sizes_):
                if (n, p) not in curves:
                    curves[n, p] = np.array(cfg.curve(int(n), int(p)))
            pdf["v"] = pdf["t_k"] - [curves[z][k - 1] for z, k in zip(sizes_, pdf["k"], strict=True)]
            yield pa.RecordBatch.from_pandas(pdf[[*key, "k", "v"]], preserve_index=False)

    valued = ranked.join(sizes.frame.select("series_id", "n", "p"), "series_id").select(*key, "k", "t_k", "n", "p").mapInArrow(priced, "series_id string, s bigint, e bigint, k int, v double")
    best = valued.groupBy(*key).agg(F.max_by("k", F.struct("v", -F.col("k"))).alias("k"), F.max("v").alias("score"))
    return best.where("score > 0").select(*key, "k", "score", F.lit("window").alias("kind"))
