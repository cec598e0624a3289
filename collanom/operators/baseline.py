"""Typical behaviour of each component, and scaling by it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed: makes the interquartile range and the median deviation estimate a normal standard deviation.
IQR_SCALE, MAD_SCALE = 1.349, 1.4826
#: Observations of a component up to which quantiles are exact; beyond, an exact one would hold all different values in a task.
EXACT_ROWS = 4_000_000
KEY = ["series_id", "component"]


def fit_typical(long: DataFrame, how: str = "iqr", approximate: bool = False, accuracy: int = 10_000) -> DataFrame:
    """(series_id, component, mu, sigma, n_obs): robust by quartiles (iqr) or median deviation (mad), or moments, or rate."""
    groups = long.groupBy(*KEY)
    n = F.count("x").alias("n_obs")
    if how == "moments":
        return groups.agg(F.avg("x").alias("mu"), F.stddev_samp("x").alias("sigma"), n)
    if how == "rate":
        return groups.agg(F.avg("x").alias("mu"), F.sqrt(F.avg("x")).alias("sigma"), n)
    if how == "iqr":
        quartiles = F.percentile_approx("x", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), F.lit(accuracy)) if approximate else F.percentile("x", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)))
        q = groups.agg(quartiles.alias("q"), n)
        return q.select(*KEY, F.col("q")[1].cast("double").alias("mu"), ((F.col("q")[2] - F.col("q")[0]) / IQR_SCALE).alias("sigma"), "n_obs")
    if how == "mad":
        median = (lambda c: F.percentile_approx(c, 0.5, F.lit(accuracy)).cast("double")) if approximate else F.median
        centre = groups.agg(median("x").alias("mu"), n)
        return long.join(centre, KEY).groupBy(*KEY, "mu", "n_obs").agg((median(F.abs(F.col("x") - F.col("mu"))) * MAD_SCALE).alias("sigma")).select(*KEY, "mu", "sigma", "n_obs")
    raise ValueError(f"unknown estimator {how}")


def guard_scale(params: DataFrame, floor: float = 1e-9, fallback: float = 1.0) -> DataFrame:
    """Components whose scale is zero (or missing) get a fallback scale and are marked degenerate."""
    bad = F.col("sigma").isNull() | F.isnan("sigma") | (F.col("sigma") <= floor)
    return params.withColumn("degenerate", bad).withColumn("sigma", F.when(bad, fallback).otherwise(F.col("sigma")))


def standardise(long: DataFrame, params: DataFrame, drop_degenerate: bool = True, own: bool = False) -> DataFrame:
    """(x - mu) / sigma; missing cells and, if asked, degenerate components become typical (zero).

    The parameters are one row per component and series. They are broadcast by Spark's own check of
    their size; beyond it the join shuffles on the key. With `own` parameters, those of the rows themselves,
    every row has some; so an outer join gives the same, in which the rows are never what is broadcast
    (Spark takes rows that grow out of a small table for a small table).
    """
    params = params.select(*KEY, "mu", "sigma", "degenerate")
    joined = long.dropna(subset=KEY).join(params, KEY, "left") if own else long.join(params, KEY)
    z = F.coalesce((F.col("x") - F.col("mu")) / F.col("sigma"), F.lit(0.0))
    return joined.select("series_id", "t", "component", (F.when(F.col("degenerate"), 0.0).otherwise(z) if drop_degenerate else z).alias("x"))


def too_long(long: DataFrame) -> bool:
    """Whether any component has more than `EXACT_ROWS` observations, so that its quantiles are taken by sketches."""
    most = long.groupBy(*KEY).agg(F.count("*").alias("n")).agg(F.max("n").alias("n")).first()["n"]
    return (most or 0) > EXACT_ROWS


def scaled(long: DataFrame, how: str = "iqr", approximate: bool | None = False) -> DataFrame:
    """Standardised by its own typical behaviour; `approximate=None` counts first and decides by `EXACT_ROWS`."""
    return standardise(long, guard_scale(fit_typical(long, how, too_long(long) if approximate is None else approximate)), own=True)
