"""Functions for SQL users: Arrow scalar and aggregate functions, a table function, and their registration."""

from __future__ import annotations

from statistics import NormalDist

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from . import penalties as pen


def _normal_sf(z):
    from ..comparators.higher_criticism import normal_upper

    v = z.to_numpy(float)
    upper = normal_upper(np.abs(v))
    return pd.Series(np.where(v >= 0, upper, 1 - upper))


def _chi2_quantile(upper):
    inv = NormalDist().inv_cdf
    return pd.Series([inv(1 - u / 2) ** 2 if 0 < u < 1 else 0.0 for u in upper])


normal_sf = F.pandas_udf(_normal_sf, DoubleType(), F.PandasUDFType.SCALAR)
chi2_quantile = F.pandas_udf(_chi2_quantile, DoubleType(), F.PandasUDFType.SCALAR)


def penalised_saving_udaf(curve: list[float]):
    """A grouped aggregate: the penalised saving of the savings in a group."""
    price = np.asarray(curve, float)

    def best(v):
        top = np.cumsum(-np.sort(-v.to_numpy(float)))
        return float((top - price[: len(top)]).max())

    return F.pandas_udf(best, DoubleType(), F.PandasUDFType.GROUPED_AGG)


class DetectWindows:
    """Table function over one series at a time: rows (series_id, t, xs) in, chosen windows and points out."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, list[float]]] = []
        self.series = None

    def eval(self, row):
        self.series = row["series_id"]
        self.rows.append((row["t"], row["xs"]))

    def terminate(self):
        from ..config import DetectorConfig
        from ..operators.blocks import Kernel, best_chain

        if not self.rows:
            return
        x = np.array([v for _, v in sorted(self.rows)], float)
        n, p = x.shape
        cfg = DetectorConfig(m=min(60, n))
        kernel = Kernel(cfg.l, cfg.m, cfg.curve(n, p), beta_point=cfg.point_price(n, p))
        f = kernel.scores(x, 0)
        spans = [(int(s), int(e), float(v), "window") for s, e, v in zip(f["s"], f["e"], f["score"], strict=True)]
        spans += [(i, i + 1, float(v), "point") for i, v in enumerate(kernel.point_savings(x)) if v > 0]
        for i in best_chain(spans)[1]:
            yield (self.series, *spans[i])


detect_windows = F.udtf(DetectWindows, returnType="series_id string, s bigint, e bigint, score double, kind string")


def register(spark: SparkSession) -> None:
    """Makes the functions known to SQL."""
    spark.udf.register("normal_sf", normal_sf)
    spark.udf.register("chi2_upper_quantile", chi2_quantile)
    spark.udtf.register("detect_windows", detect_windows)


__all__ = ["chi2_quantile", "detect_windows", "normal_sf", "pen", "penalised_saving_udaf", "register"]
