"""The series that the queries work on, as frames and as SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baseline, simulate
from ..sources import densify, explode_vectors, load, series_from_table

#: Injected windows (k, s, e, components, strength) and points (t, component) of the fixtures; strengths in standard deviations.
WINDOWS = ((1, 150, 170, (1, 2, 3), 4.0), (2, 350, 370, (3, 4), 4.0))
POINTS = ((50, 1), (100, 2), (250, 3), (500, 4), (600, 5))
POINT_SIZE = 12.0


def hourly(spark: SparkSession, sf: str) -> DataFrame:
    """Hourly counts of events by type."""
    return densify(series_from_table(load(spark, sf, "events"), "ts", F.col("event_type")), "hour")


HOURLY = """
cells AS (SELECT date_trunc('hour', ts) AS tick, event_type AS label, count(*)::DOUBLE AS x FROM events GROUP BY 1, 2),
bounds AS (SELECT min(tick) AS lo, max(tick) AS hi FROM cells),
labels AS (SELECT label, (row_number() OVER (ORDER BY label))::INTEGER AS component FROM (SELECT DISTINCT label FROM cells)),
grid AS (SELECT lo, unnest(range(0, date_diff('hour', lo, hi) + 1)) AS i FROM bounds),
hourly AS MATERIALIZED (
  SELECT 'all' AS series_id, (g.i + 1)::BIGINT AS t, l.component, coalesce(c.x, 0)::DOUBLE AS x
  FROM grid g CROSS JOIN labels l LEFT JOIN cells c ON c.label = l.label AND c.tick = g.lo + g.i * INTERVAL 1 HOUR)"""

_SCALE = """
typical AS (
  SELECT series_id, component, quantile_cont(x, 0.5) AS mu, (quantile_cont(x, 0.75) - quantile_cont(x, 0.25)) / 1.349 AS sigma
  FROM {source} GROUP BY ALL),
std AS MATERIALIZED (
  SELECT h.series_id, h.t, h.component, CASE WHEN p.sigma > 1e-9 THEN (h.x - p.mu) / p.sigma ELSE 0.0 END AS x
  FROM {source} h JOIN typical p USING (series_id, component))"""

HOURLY_STD = HOURLY + "," + _SCALE.format(source="hourly")

VECTORS = """
vectors AS MATERIALIZED (
  SELECT 'all' AS series_id, (vec_id + 1)::BIGINT AS t, i::INTEGER AS component, embedding[i]::DOUBLE AS x
  FROM embeddings, range(1, 65) AS r(i))"""

VECTORS_STD = VECTORS + "," + _SCALE.format(source="vectors")


def hourly_std(spark: SparkSession, sf: str) -> DataFrame:
    return baseline.scaled(hourly(spark, sf))


def vectors(spark: SparkSession, sf: str) -> DataFrame:
    return explode_vectors(load(spark, sf, "embeddings"))


def vectors_std(spark: SparkSession, sf: str) -> DataFrame:
    return baseline.scaled(vectors(spark, sf))


def truth(spark: SparkSession, lags: tuple[int, int] = (0, 0)) -> DataFrame:
    """The fixture's windows; with lags, component c starts (c % first) later and ends (c % second) earlier."""
    rows = [("all", k, s, e, c, c % (lags[0] + 1), c % (lags[1] + 1), mu) for k, s, e, parts, mu in WINDOWS for c in parts]
    return simulate.truth_frame(spark, rows)


def truth_points(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([("all", t, c, POINT_SIZE) for t, c in POINTS], "series_id string, t bigint, component int, delta double")


def _truth_sql(lags: tuple[int, int] = (0, 0)) -> str:
    rows = ", ".join(f"('all', {k}, {s}, {e}, {c}, {c % (lags[0] + 1)}, {c % (lags[1] + 1)}, {mu})" for k, s, e, parts, mu in WINDOWS for c in parts)
    return f"truth(series_id, k, s, e, component, d, f, mu) AS (VALUES {rows})"


def injected_sql(source: str = HOURLY_STD, points: bool = False, lags: tuple[int, int] = (0, 0)) -> str:
    spots = ", ".join(f"({t}, {c})" for t, c in POINTS)
    extra = f" + CASE WHEN (t, component) IN ({spots}) THEN {POINT_SIZE} ELSE 0 END" if points else ""
    return f"""{source},
{_truth_sql(lags)},
inj AS MATERIALIZED (
  SELECT series_id, t, component, x + coalesce((SELECT sum(mu) FROM truth w WHERE w.component = y.component AND y.t > w.s + w.d AND y.t <= w.e - w.f), 0){extra} AS x
  FROM std y)"""


def injected(spark: SparkSession, sf: str, points: bool = False, lags: tuple[int, int] = (0, 0)) -> DataFrame:
    """Hourly counts, scaled, with the fixture's windows (and points) added."""
    return simulate.inject(hourly_std(spark, sf), truth(spark, lags), truth_points(spark) if points else None)


def injected_vectors(spark: SparkSession, sf: str) -> DataFrame:
    return simulate.inject(vectors_std(spark, sf), truth(spark))
