"""Seeded noise, truths and injection: the same numbers on any partitioning, and in SQL.

Every draw is the md5 of a text (seed, purpose, series, indices); its first 32 bits make a uniform
number, two of them a normal one.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def uniform(*parts) -> Column:
    """A uniform number in (0, 1) from the texts of the parts."""
    text = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") + 0.5) / 4294967296.0


def normal(*parts) -> Column:
    """A standard normal number by the polar form of two uniforms."""
    return F.sqrt(-2 * F.log(uniform(*parts, "a"))) * F.cos(2 * math.pi * uniform(*parts, "b"))


def noise(spark: SparkSession, n: int, p: int, replicates: int = 1, seed: int = 1) -> DataFrame:
    """Long rows of independent standard normal noise, one series per replicate."""
    cells = spark.range(0, n * p * replicates)
    i = F.col("id")
    r, t, c = F.floor(i / (n * p)), F.floor(i / p) % n + 1, (i % p + 1)
    rows = cells.select(r.cast("string").alias("series_id"), t.cast("long").alias("t"), c.cast("int").alias("component"))
    return rows.withColumn("x", normal(seed, "noise", F.col("series_id"), F.col("t"), F.col("component")))


#: Settings of the simulation study: affected components by p, spread of the means, lags.
def setting(number: int, p: int, doubled: bool = False) -> dict:
    few = 2 if p <= 10 else max(2, round(6 * p / 100))
    sigma = {1: 2 * math.log(p), 2: p**-0.25, 3: math.log(p), 4: math.log(p)}[number]
    return {"k": {1: 1, 2: p, 3: few, 4: few}[number], "sigma": sigma * (2 if doubled and number == 2 else 1), "w": 10 if number == 4 else 0, "alpha0": min({1: 1, 2: p, 3: few, 4: few}[number], 5)}


def poisson_table(mean: float) -> list[float]:
    """Cumulative chances of a Poisson number, up to where they no longer matter."""
    total, out = 0.0, []
    for j in range(int(4 * mean) + 20):
        total += math.exp(-mean + j * math.log(mean) - math.lgamma(j + 1))
        out.append(total)
    return out


def _apart(starts: DataFrame) -> DataFrame:
    """(series_id, s, e) of windows that begin at or after the end of the last one taken, by their starts.

    A window that begins after all ends before it is always taken, so the walk is made in short runs.
    """
    order = Window.partitionBy("series_id").orderBy("s")
    reach = F.max("e").over(order.rowsBetween(Window.unboundedPreceding, -1))
    runs = starts.withColumn("new", F.when(reach.isNull() | (F.col("s") >= reach), F.col("s"))).withColumn("run", F.last("new", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    spans = runs.groupBy("series_id", "run").agg(F.array_sort(F.collect_list(F.struct("s", "e"))).alias("spans"))
    none = F.array().cast("array<struct<s:bigint,e:bigint>>")
    taken = F.aggregate("spans", none, lambda acc, v: F.when((F.size(acc) == 0) | (v["s"] >= F.element_at(acc, -1)["e"]), F.concat(acc, F.array(v))).otherwise(acc))
    return spans.select("series_id", F.explode(taken).alias("v")).select("series_id", "v.s", "v.e")


def truths(spark: SparkSession, n: int, p: int, k: int, sigma: float, w: int = 0, replicates: int = 1, seed: int = 1, rate: float = 0.001, mean_length: float = 20.0, every: int = 0) -> DataFrame:
    """True windows, exploded to components: (series_id, k, s, e, component, d, f, mu).

    Starts come at the rate per time (or every so many times), lengths are Poisson (2 at least, 4 with
    lags), windows that begin inside an earlier one or end after n are left out. Affected components are
    those with the smallest draws; lags are one of the pairs up to w whose sum is below the length, each as
    likely as the others.
    """
    cells = spark.range(0, n * replicates).select(F.floor(F.col("id") / n).cast("string").alias("series_id"), (F.col("id") % n).alias("s"))
    at = (F.col("series_id"), F.col("s"))
    starts = cells.where((F.col("s") % every == every // 2) if every else (uniform(seed, "start", *at) < rate))
    table = F.array(*[F.lit(c) for c in poisson_table(mean_length)])
    drawn = F.size(F.filter(table, lambda c: c < uniform(seed, "length", *at)))
    spans = starts.select(*at, (F.col("s") + F.greatest(F.lit(4 if w else 2), drawn)).cast("long").alias("e")).where(F.col("e") <= n)
    numbered = _apart(spans).withColumn("k", F.row_number().over(Window.partitionBy("series_id").orderBy("s")))
    part = (*at, F.col("component"))
    cells = numbered.withColumn("component", F.explode(F.sequence(F.lit(1), F.lit(p))))
    order = Window.partitionBy(*at).orderBy(uniform(seed, "affected", *part), "component")
    hit = cells.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    mu = (normal(seed, "mean", *part) * sigma).alias("mu")
    none = F.lit(0)
    if not w:
        return hit.select("series_id", "k", "s", "e", "component", none.alias("d"), none.alias("f"), mu)
    pairs = F.array(*[F.struct(F.lit(d).alias("d"), F.lit(f).alias("f")) for d in range(w + 1) for f in range(w + 1)])
    fit = hit.withColumn("fit", F.filter(pairs, lambda v: v["d"] + v["f"] < F.col("e") - F.col("s")))
    one = F.element_at("fit", (F.floor(uniform(seed, "lags", *part) * F.size("fit")) + 1).cast("int"))
    return fit.withColumn("one", one).select("series_id", "k", "s", "e", "component", "one.d", "one.f", mu)


def add_points(spark: SparkSession, n: int, p: int, replicates: int = 1, seed: int = 1, points: int = 5) -> DataFrame:
    """(series_id, t, component, delta): single deviations of variance 8 log p."""
    rows = spark.range(0, replicates * points).select(F.floor(F.col("id") / points).cast("string").alias("series_id"), (F.col("id") % points).alias("j"))
    key = (seed, "point", F.col("series_id"), F.col("j"))
    return rows.select("series_id", (F.floor(uniform(*key, "t") * n) + 1).cast("long").alias("t"), (F.floor(uniform(*key, "c") * p) + 1).cast("int").alias("component"), (normal(*key, "v") * math.sqrt(8 * math.log(p))).alias("delta"))


def inject(long: DataFrame, truth: DataFrame, points: DataFrame | None = None, bucket: int = 128) -> DataFrame:
    """Long rows with the truths' means added for s + d < t <= e - f, and the points' deltas."""
    spread = truth.select("series_id", "component", (F.col("s") + F.col("d")).alias("lo"), (F.col("e") - F.col("f")).alias("hi"), "mu").where("hi > lo")
    cells = spread.select("series_id", "component", F.explode(F.sequence(F.col("lo") + 1, F.col("hi"))).alias("t"), F.col("mu").alias("add"))
    if points is not None:
        cells = cells.unionByName(points.select("series_id", "component", "t", F.col("delta").alias("add")))
    total = cells.groupBy("series_id", "component", "t").agg(F.sum("add").alias("add"))
    return long.join(total, ["series_id", "component", "t"], "left").select("series_id", "t", "component", (F.col("x") + F.coalesce("add", F.lit(0.0))).alias("x"))


def truth_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """Truths written out: (series_id, k, s, e, component, d, f, mu)."""
    return spark.createDataFrame(rows, "series_id string, k int, s bigint, e bigint, component int, d int, f int, mu double")


def sparse_mixture(spark: SparkSession, p: int, xi: float, r: float, length: int, n: int, start: int, replicates: int, seed: int = 1) -> DataFrame:
    """Truths of one window in which each component is affected with chance p^-xi, at strength r."""
    squared = (2 * r * math.log(p) if xi > 0.5 else p ** (-2 * r)) / length
    cells = spark.range(0, replicates * p).select(F.floor(F.col("id") / p).cast("string").alias("series_id"), (F.col("id") % p + 1).cast("int").alias("component"))
    hit = cells.where(uniform(seed, "mixture", F.col("series_id"), F.col("component")) < p**-xi)
    return hit.select("series_id", F.lit(1).alias("k"), F.lit(start).cast("long").alias("s"), F.lit(start + length).cast("long").alias("e"), "component", F.lit(0).alias("d"), F.lit(0).alias("f"), F.lit(math.sqrt(squared)).alias("mu"))
