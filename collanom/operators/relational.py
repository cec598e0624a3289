"""The relational forms: prefix sums, window savings by an offset equi-join, penalised savings by plain aggregates."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def prefix_sums(long: DataFrame) -> DataFrame:
    """(series_id, component, t, x, s1, s2): running sums and sums of squares, one row before the first."""
    w = Window.partitionBy("series_id", "component").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return long.select("series_id", "component", "t", "x", F.sum("x").over(w).alias("s1"), F.sum(F.col("x") * F.col("x")).over(w).alias("s2"))


def window_sums(long: DataFrame, l: int, m: int, ordered: bool = False) -> DataFrame:  # noqa: E741
    """(series_id, s, e, component, total, squares) of every window of length l..m: an equi-join on (series, component, e - length).

    `ordered`: the starts are taken from the ordered rows instead, which need no second shuffle and no join; a
    component of a series is then one task's, so this is for short series.
    """
    sums = prefix_sums(long).select("series_id", "component", "t", "s1", "s2")
    if ordered:
        start = F.struct(F.col("t").alias("s"), F.col("s1").alias("a1"), F.col("s2").alias("a2"))
        none = F.struct(F.lit(0).cast("long").alias("s"), F.lit(0.0).alias("a1"), F.lit(0.0).alias("a2"))
        before = Window.partitionBy("series_id", "component").orderBy("t").rangeBetween(-m, -l)
        zero = F.when(F.col("t").between(l, m), F.array(none)).otherwise(F.slice(F.array(none), 1, 0))
        spread = sums.withColumn("starts", F.collect_list(start).over(before)).withColumn("from", F.explode(F.concat(zero, "starts"))).where("from.s >= 0")
        return spread.select("series_id", F.col("from.s").alias("s"), F.col("t").alias("e"), "component", (F.col("s1") - F.col("from.a1")).alias("total"), (F.col("s2") - F.col("from.a2")).alias("squares"))
    zero = sums.select("series_id", "component").distinct().select("series_id", "component", F.lit(0).cast("long").alias("t"), F.lit(0.0).alias("s1"), F.lit(0.0).alias("s2"))
    starts = sums.unionByName(zero).select("series_id", "component", F.col("t").alias("s"), F.col("s1").alias("a1"), F.col("s2").alias("a2"))
    lengths = F.when(F.col("t") >= l, F.sequence(F.lit(l), F.least(F.lit(m), F.col("t").cast("int")))).otherwise(F.array().cast("array<int>"))
    ends = sums.select("series_id", "component", F.col("t").alias("e"), "s1", "s2", F.explode(lengths).alias("len"))
    joined = ends.withColumn("s", F.col("e") - F.col("len")).join(starts, ["series_id", "component", "s"])
    return joined.select("series_id", "s", "e", "component", (F.col("s1") - F.col("a1")).alias("total"), (F.col("s2") - F.col("a2")).alias("squares"))


def _log0(x: Column, y: Column) -> Column:
    return F.when(x > 0, x * F.log(x / y)).otherwise(0.0)


def saving_column(family: str, rate: Column | None = None) -> Column:
    """The saving of a window from `total`, `squares`, `s`, `e` (and the typical rate of counts)."""
    size, total, squares = (F.col("e") - F.col("s")).cast("double"), F.col("total"), F.col("squares")
    if family == "mean":
        return total * total / size
    if family == "poisson":
        typical = F.greatest(size * rate, F.lit(1e-12))
        return 2 * (_log0(total, typical) - (total - typical))
    if family == "meanvar":
        return squares - size * (1 + F.log(F.greatest(squares / size - F.pow(total / size, F.lit(2.0)), F.lit(1e-8))))
    if family == "var":
        ratio = F.greatest(squares / size, F.lit(1e-8))
        return squares - size - size * F.log(ratio)
    raise ValueError(f"unknown family {family}")


def window_savings_long(long: DataFrame, l: int, m: int, family: str = "mean", rates: DataFrame | None = None) -> DataFrame:  # noqa: E741
    """(series_id, s, e, component, saving)."""
    sums = window_sums(long, l, m)
    if rates is not None:
        sums = sums.join(rates.select("series_id", "component", F.col("mu").alias("rate")), ["series_id", "component"])
    return sums.select("series_id", "s", "e", "component", saving_column(family, F.col("rate") if rates is not None else None).alias("saving"))


KEY = ["series_id", "s", "e"]


def penalised_saving_flat(savings: DataFrame, alpha: float) -> DataFrame:
    """All components affected: one sum and one price."""
    return savings.groupBy(*KEY).agg((F.sum("saving") - alpha).alias("score"))


def penalised_saving_linear(savings: DataFrame, alpha: float, beta: float) -> DataFrame:
    """Equal steps: what exceeds the step, summed; partial sums combine before the shuffle."""
    return savings.groupBy(*KEY).agg((F.sum(F.greatest(F.col("saving") - beta, F.lit(0.0))) - alpha).alias("score"))


def penalised_saving(savings: DataFrame, curve: Sequence[float]) -> DataFrame:
    """Any curve: ranked savings, running sums, the best k: (series_id, s, e, score, k)."""
    spark = savings.sparkSession
    prices = F.broadcast(spark.createDataFrame([(k, float(v)) for k, v in enumerate(curve, 1)], "k int, price double"))
    order = Window.partitionBy(*KEY).orderBy(F.desc("saving"), "component")
    ranked = savings.withColumn("k", F.row_number().over(order)).withColumn("t_k", F.sum("saving").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    scored = ranked.join(prices, "k").withColumn("v", F.col("t_k") - F.col("price"))
    return scored.groupBy(*KEY).agg(F.max("v").alias("score"), F.max_by(F.col("k"), F.struct("v", -F.col("k"))).alias("k"))


def penalised_saving_lines(savings: DataFrame, lines: list[tuple[float, float]]) -> DataFrame:
    """A concave curve as a minimum of lines: one sum per line in one aggregate, then the greatest."""
    sums = [F.sum(F.greatest(F.col("saving") - g, F.lit(0.0))) - c for g, c in lines]
    return savings.groupBy(*KEY).agg((F.greatest(*sums) if len(sums) > 1 else sums[0]).alias("score"))


def penalised_saving_array(wide: DataFrame, curve: Sequence[float]) -> DataFrame:
    """The same from one row per window with an array `savings`: sort, running sum and maximum with array functions."""
    prices = F.array(*[F.lit(float(v)) for v in curve])
    down = F.reverse(F.array_sort("savings"))
    last = lambda acc: F.when(F.size(acc) > 0, F.get(acc, F.size(acc) - 1)).otherwise(0.0)
    running = F.aggregate(down, F.array().cast("array<double>"), lambda acc, v: F.concat(acc, F.array(last(acc) + v)))
    return wide.select(*KEY, F.array_max(F.zip_with(running, prices, lambda t, c: t - c)).alias("score"))


def saving_by_residuals(long: DataFrame, windows: DataFrame) -> DataFrame:
    """The mean change by its definition, for given windows: squares about zero minus squares about the mean."""
    from .detect import rows_in_windows

    rows = rows_in_windows(long, windows)
    means = rows.groupBy(*KEY, "component").agg(F.avg("x").alias("m"))
    return rows.join(means, [*KEY, "component"]).groupBy(*KEY, "component").agg((F.sum(F.col("x") * F.col("x")) - F.sum(F.pow(F.col("x") - F.col("m"), F.lit(2.0)))).alias("saving"))


def score_given_subset(savings: DataFrame, components: Sequence[int], curve: Sequence[float]) -> DataFrame:
    """The statistic of a stated set of components."""
    return savings.where(F.col("component").isin(*components)).groupBy(*KEY).agg((F.sum("saving") - float(curve[len(components) - 1])).alias("score"))


def lagged_savings(long: DataFrame, l: int, m: int, w: int, gamma: float = 0.0) -> DataFrame:  # noqa: E741
    """(series_id, s, e, component, saving, d, f): outer windows joined to their trimmed inner ones, the best of them."""
    inner = window_savings_long(long, l, m)
    trims = F.explode(F.sequence(F.lit(0), F.lit(w)))
    outer = inner.select("series_id", "s", "e", "component").withColumn("d", trims).withColumn("f", F.explode(F.sequence(F.lit(0), F.lit(w)))).where(F.col("e") - F.col("s") - F.col("d") - F.col("f") >= l)
    keyed = outer.withColumn("is_", F.col("s") + F.col("d")).withColumn("ie", F.col("e") - F.col("f"))
    found = keyed.join(inner.select("series_id", "component", F.col("s").alias("is_"), F.col("e").alias("ie"), "saving"), ["series_id", "component", "is_", "ie"])
    net = F.col("saving") - F.when((F.col("d") > 0) | (F.col("f") > 0), gamma).otherwise(0.0)
    best = F.max(F.struct(net.alias("v"), (-F.col("d")).alias("d"), (-F.col("f")).alias("f"))).alias("b")
    return found.groupBy(*KEY, "component").agg(best).select(*KEY, "component", F.col("b.v").alias("saving"), (-F.col("b.d")).alias("d"), (-F.col("b.f")).alias("f"))


def point_savings(long: DataFrame, beta: float) -> DataFrame:
    """(series_id, t, score): squares above the price, summed over the components."""
    return long.groupBy("series_id", "t").agg(F.sum(F.greatest(F.col("x") * F.col("x") - beta, F.lit(0.0))).alias("score"))


def segment_cost(long: DataFrame) -> DataFrame:
    """(series_id, component, n, cost): twice the negative log-likelihood of a whole series under its typical law."""
    return long.groupBy("series_id", "component").agg(F.count("*").alias("n"), F.sum(F.col("x") * F.col("x") + F.log(F.lit(2 * 3.141592653589793))).alias("cost"))
