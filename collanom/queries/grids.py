"""Queries on grids, typical behaviour, sums, savings and penalties."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import penalties as pen
from ..operators import baseline, relational
from ..sources import densify, load, series_from_table, to_wide
from . import data
from .data import HOURLY, HOURLY_STD, VECTORS
from .registry import query

#: Counts on a scale give sums that lie exactly between two roundings; this moves them off.
_OFF = 3e-9


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    """Floating outputs to six decimals; the sign of zero does not matter."""
    return df.withColumns({c: F.round(F.col(c) + _OFF, 6) + 0.0 for c in columns})


@query(f"WITH {HOURLY} SELECT series_id, t, component, x FROM hourly")
def grid_hourly_counts(spark: SparkSession, sf: str) -> DataFrame:
    return data.hourly(spark, sf)


@query("""
WITH cells AS (SELECT date_trunc('day', l_shipdate) AS tick, l_suppkey::VARCHAR AS label, sum(l_extendedprice) AS x FROM lineitem GROUP BY 1, 2),
bounds AS (SELECT min(tick) AS lo, max(tick) AS hi FROM cells),
labels AS (SELECT label, (row_number() OVER (ORDER BY label))::INTEGER AS component FROM (SELECT DISTINCT label FROM cells)),
grid AS (SELECT lo, unnest(range(0, date_diff('day', lo, hi) + 1)) AS i FROM bounds)
SELECT 'all' AS series_id, (g.i + 1)::BIGINT AS t, l.component, round(coalesce(c.x, 0), 2) AS x
FROM grid g CROSS JOIN labels l LEFT JOIN cells c ON c.label = l.label AND c.tick = g.lo + g.i * INTERVAL 1 DAY""")
def grid_daily_supplier_revenue(spark: SparkSession, sf: str) -> DataFrame:
    cells = series_from_table(load(spark, sf, "lineitem"), "l_shipdate", F.col("l_suppkey"), F.col("l_extendedprice"), "sum", "day")
    return densify(cells, "day").withColumn("x", F.round("x", 2))


@query("""
WITH cells AS (
  SELECT date_trunc('week', o.o_orderdate) AS tick, n.n_name AS label, count(*)::DOUBLE AS x
  FROM orders o JOIN customer c ON o.o_custkey = c.c_custkey JOIN nation n ON c.c_nationkey = n.n_nationkey JOIN region r ON n.n_regionkey = r.r_regionkey GROUP BY 1, 2),
bounds AS (SELECT min(tick) AS lo, max(tick) AS hi FROM cells),
labels AS (SELECT label, (row_number() OVER (ORDER BY label))::INTEGER AS component FROM (SELECT DISTINCT label FROM cells)),
grid AS (SELECT lo, unnest(range(0, date_diff('week', lo, hi) + 1)) AS i FROM bounds)
SELECT 'all' AS series_id, (g.i + 1)::BIGINT AS t, l.component, coalesce(c.x, 0)::DOUBLE AS x
FROM grid g CROSS JOIN labels l LEFT JOIN cells c ON c.label = l.label AND c.tick = g.lo + g.i * INTERVAL 7 DAY""")
def grid_orders_nation_weekly(spark: SparkSession, sf: str) -> DataFrame:
    orders, customer = load(spark, sf, "orders"), load(spark, sf, "customer")
    joined = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(load(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(load(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return densify(series_from_table(joined, "o_orderdate", F.col("n_name"), unit="week"), "week")


def _typical(how: str):
    def made(spark: SparkSession, sf: str) -> DataFrame:
        return rounded(baseline.guard_scale(baseline.fit_typical(data.hourly(spark, sf), how)), "mu", "sigma")

    return made


_GUARD = "sigma IS NULL OR sigma <= 1e-9"
_TYPICAL = "SELECT series_id, component, round(mu + 3e-9, 6) AS mu, round(CASE WHEN {g} THEN 1.0 ELSE sigma END + 3e-9, 6) AS sigma, n_obs, coalesce({g}, true) AS degenerate FROM p".format(g=_GUARD)
query(f"WITH {HOURLY}, p AS (SELECT series_id, component, quantile_cont(x, 0.5) AS mu, (quantile_cont(x, 0.75) - quantile_cont(x, 0.25)) / 1.349 AS sigma, count(*) AS n_obs FROM hourly GROUP BY ALL) {_TYPICAL}", "typical_iqr")(_typical("iqr"))
query(f"WITH {HOURLY}, m AS (SELECT series_id, component, median(x) AS mu FROM hourly GROUP BY ALL), p AS (SELECT h.series_id, h.component, m.mu, median(abs(h.x - m.mu)) * 1.4826 AS sigma, count(*) AS n_obs FROM hourly h JOIN m USING (series_id, component) GROUP BY ALL) {_TYPICAL}", "typical_mad")(_typical("mad"))
query(f"WITH {HOURLY}, p AS (SELECT series_id, component, avg(x) AS mu, stddev_samp(x) AS sigma, count(*) AS n_obs FROM hourly GROUP BY ALL) {_TYPICAL}", "typical_moments")(_typical("moments"))
query(f"WITH {HOURLY}, p AS (SELECT series_id, component, avg(x) AS mu, sqrt(avg(x)) AS sigma, count(*) AS n_obs FROM hourly GROUP BY ALL) {_TYPICAL}", "typical_rate")(_typical("rate"))


@query()
def typical_approx(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(baseline.guard_scale(baseline.fit_typical(data.hourly(spark, sf), "iqr", approximate=True)), "mu", "sigma")


@query(f"WITH {HOURLY_STD} SELECT series_id, t, component, round(x + 3e-9, 6) AS x FROM std")
def standardised_series(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(data.hourly_std(spark, sf), "x")


@query(f"WITH {HOURLY_STD} SELECT series_id, component, count(*) AS n, round(sum(x * x + ln(2 * 3.141592653589793)), 5) AS cost FROM std GROUP BY ALL")
def segment_cost(spark: SparkSession, sf: str) -> DataFrame:
    return relational.segment_cost(data.hourly_std(spark, sf)).withColumn("cost", F.round("cost", 5))


@query(f"WITH {HOURLY_STD} SELECT series_id, component, t, round(sum(x) OVER w + 3e-9, 6) AS s1, round(sum(x * x) OVER w + 3e-9, 6) AS s2 FROM std WINDOW w AS (PARTITION BY series_id, component ORDER BY t)")
def prefix_sums(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(relational.prefix_sums(data.hourly_std(spark, sf)), "s1", "s2").select("series_id", "component", "t", "s1", "s2")


def sums_sql(source: str, low: int, high: int) -> str:
    """Window sums of a series table by the band of lengths, as CTEs ending in `wins`."""
    return f"""
pre AS MATERIALIZED (SELECT series_id, component, t, sum(x) OVER w AS s1, sum(x * x) OVER w AS s2 FROM {source} WINDOW w AS (PARTITION BY series_id, component ORDER BY t)),
heads AS (SELECT series_id, component, t, s1, s2 FROM pre UNION ALL SELECT DISTINCT series_id, component, 0, 0.0, 0.0 FROM pre),
wins AS MATERIALIZED (
  SELECT b.series_id, a.t AS s, b.t AS e, b.component, b.s1 - a.s1 AS total, b.s2 - a.s2 AS squares, (b.t - a.t)::DOUBLE AS n
  FROM pre b JOIN range({low}, {high} + 1) AS r(len) ON b.t >= r.len JOIN heads a ON a.series_id = b.series_id AND a.component = b.component AND a.t = b.t - r.len)"""


_LOW, _HIGH = 2, 8


@query(f"WITH {HOURLY_STD}, {sums_sql('std', _LOW, _HIGH)} SELECT series_id, s, e, component, round(total * total / n + 3e-9, 6) AS saving FROM wins")
def mean_saving_windows(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(relational.window_savings_long(data.hourly_std(spark, sf), _LOW, _HIGH), "saving")


@query(f"""WITH {HOURLY_STD}, {sums_sql('std', 5, 5)}
SELECT w.series_id, w.s, w.e, w.component, round(sum(y.x * y.x) - sum((y.x - w.total / w.n) ** 2) + 3e-9, 6) AS saving
FROM wins w JOIN std y ON y.series_id = w.series_id AND y.component = w.component AND y.t > w.s AND y.t <= w.e GROUP BY ALL""")
def mean_saving_residual_form(spark: SparkSession, sf: str) -> DataFrame:
    std = data.hourly_std(spark, sf)
    wins = relational.window_sums(std, 5, 5).select("series_id", "s", "e").distinct()
    return rounded(relational.saving_by_residuals(std, wins), "saving")


@query(f"""WITH {HOURLY}, {sums_sql('hourly', _LOW, _HIGH)}, rate AS (SELECT series_id, component, avg(x) AS mu FROM hourly GROUP BY ALL)
SELECT series_id, s, e, component, round(2 * (CASE WHEN total > 0 THEN total * ln(total / (n * mu)) ELSE 0 END - (total - n * mu)) + 3e-9, 6) AS saving FROM wins JOIN rate USING (series_id, component)""")
def poisson_saving_windows(spark: SparkSession, sf: str) -> DataFrame:
    counts = data.hourly(spark, sf)
    return rounded(relational.window_savings_long(counts, _LOW, _HIGH, "poisson", baseline.fit_typical(counts, "rate")), "saving")


@query(f"WITH {HOURLY_STD}, {sums_sql('std', 4, _HIGH)} SELECT series_id, s, e, component, round(squares - n * (1 + ln(greatest(squares / n - (total / n) ** 2, 1e-8))), 4) AS saving FROM wins WHERE squares / n - (total / n) ** 2 > 1e-4")
def meanvar_saving_windows(spark: SparkSession, sf: str) -> DataFrame:
    sums = relational.window_sums(data.hourly_std(spark, sf), 4, _HIGH)
    n = (F.col("e") - F.col("s")).cast("double")
    return sums.where(F.col("squares") / n - F.pow(F.col("total") / n, F.lit(2.0)) > 1e-4).select("series_id", "s", "e", "component", F.round(relational.saving_column("meanvar"), 4).alias("saving"))


@query(f"WITH {HOURLY_STD}, {sums_sql('std', _LOW, _HIGH)} SELECT series_id, s, e, component, round(squares - n - n * ln(greatest(squares / n, 1e-8)), 5) AS saving FROM wins WHERE squares / n > 1e-4")
def var_saving_windows(spark: SparkSession, sf: str) -> DataFrame:
    sums = relational.window_sums(data.hourly_std(spark, sf), _LOW, _HIGH)
    n = (F.col("e") - F.col("s")).cast("double")
    return sums.where(F.col("squares") / n > 1e-4).select("series_id", "s", "e", "component", F.round(relational.saving_column("var"), 5).alias("saving"))


_P, _PSI = 500, 2 * math.log(10_000)
_WEIGHTS = ", ".join(f"({k}, {pen.chi2_weight(k / _P)!r})" for k in range(1, _P + 1))


@query(f"""WITH c AS (SELECT {_P}::DOUBLE AS p, 2 * ln(10000) AS psi), q(k, af) AS (VALUES {_WEIGHTS}),
v AS (SELECT k, p + 2 * sqrt(p * psi) + 2 * psi AS flat, 2 * psi + 2 * k * ln(p) AS linear, psi + ln(p) AS h, k + 2 * p * af AS v FROM q, c),
z AS (SELECT k, flat, linear, 2 * h + v + 2 * sqrt(v * h) AS curve FROM v)
SELECT k::INTEGER AS k, round(flat + 3e-9, 6) AS flat, round(linear + 3e-9, 6) AS linear, round(curve + 3e-9, 6) AS curve, round(least(flat, linear, curve) + 3e-9, 6) AS composite,
  CASE WHEN flat <= linear AND flat <= curve THEN 'flat' WHEN linear <= curve THEN 'linear' ELSE 'curve' END AS binding FROM z""")
def penalty_table(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(pen.penalty_table(spark, _P, _PSI), "flat", "linear", "curve", "composite")


_SIZE = "size AS (SELECT count(DISTINCT {p})::DOUBLE AS p, (date_diff('day', min({t})::DATE, max({t})::DATE) + 1)::DOUBLE AS n FROM {table})"


def _size(spark: SparkSession, sf: str, table: str, p: str, t: str) -> tuple[int, int]:
    """Components and days of a table."""
    day = F.col(t).cast("date")
    got = load(spark, sf, table).agg(F.count_distinct(p).alias("p"), (F.datediff(F.max(day), F.min(day)) + 1).alias("n")).first()
    return got["p"], got["n"]


@query(f"""WITH {_SIZE.format(p="l_suppkey", t="l_shipdate", table="lineitem")}, g AS (SELECT w, k FROM (VALUES (0), (10), (20), (40)) AS a(w), range(1, 11) AS b(k))
SELECT w::INTEGER AS w, k::INTEGER AS k, round(2 * 1.05 * 2 * ln(n) + 2 * k * 1.05 * (ln(p) + ln(w + 1)) + 3e-9, 6) AS lag_linear, round(2 * 1.05 * ln(w + 1) + 3e-9, 6) AS lag_charge, round(2 * ln(p) + 2 * 2 * ln(n) + 3e-9, 6) AS point FROM g, size WHERE k <= p""")
def lag_penalties(spark: SparkSession, sf: str) -> DataFrame:
    """Prices of lags for the lines by day and supplier."""
    p, n = _size(spark, sf, "lineitem", "l_suppkey", "l_shipdate")
    psi = 2 * math.log(n)
    rows = [(w, k, v, pen.lag_charge(w), pen.point_penalty(p, psi)) for w in (0, 10, 20, 40) for k, v in enumerate(pen.lag_linear_penalty(p, psi, w)[:10], 1)]
    return rounded(spark.createDataFrame(rows, "w int, k int, lag_linear double, lag_charge double, point double"), "lag_linear", "lag_charge", "point")


@query(f"""WITH {_SIZE.format(p="l_suppkey", t="l_shipdate", table="lineitem")}, g AS (SELECT unnest(range(1, p::BIGINT + 1)) AS k, 2 * ln(n) AS psi, p FROM size)
SELECT k::INTEGER AS k, round(CASE WHEN k <= sqrt(p) * psi / ln(p) THEN 3 * psi + 3 * k * ln(p) ELSE p + 3 * psi + 3 * sqrt(p * psi) END + 3e-9, 6) AS price FROM g""")
def consistency_penalty_table(spark: SparkSession, sf: str) -> DataFrame:
    """The curve for the lines by day and supplier."""
    p, n = _size(spark, sf, "lineitem", "l_suppkey", "l_shipdate")
    curve = pen.consistency_penalty(p, 2 * math.log(n), 3.0)
    return rounded(spark.createDataFrame(list(enumerate(curve, 1)), "k int, price double"), "price")


@query("""SELECT setting, n::INTEGER AS n, p::INTEGER AS p, round(CASE setting WHEN 'panel' THEN ln(p) WHEN 'stream' THEN ln(n) WHEN 'both' THEN ln(n) + ln(p) WHEN 'twice' THEN 2 * ln(n) ELSE 2 * ln(n) + 2 * ln(ln(p)) END + 3e-9, 6) AS psi
FROM (VALUES ('panel'), ('stream'), ('both'), ('twice'), ('power')) AS a(setting), (VALUES (100, 1000), (5000, 100)) AS b(n, p)""")
def psi_presets(spark: SparkSession, sf: str) -> DataFrame:
    rows = [(s, n, p, pen.psi_for(s, n, p)) for s in ("panel", "stream", "both", "twice", "power") for n, p in ((100, 1000), (5000, 100))]
    return rounded(spark.createDataFrame(rows, "setting string, n int, p int, psi double"), "psi")


@query(f"""WITH {VECTORS} SELECT series_id, t, sum(x)::DOUBLE AS total, len(list(x)) AS p FROM vectors GROUP BY ALL""".replace("sum(x)::DOUBLE AS total", "round(sum(x), 5) AS total"))
def wide_rows(spark: SparkSession, sf: str) -> DataFrame:
    wide = to_wide(data.vectors(spark, sf))
    return wide.select("series_id", "t", F.round(F.aggregate("xs", F.lit(0.0), lambda a, v: a + v), 5).alias("total"), F.size("xs").cast("long").alias("p"))
