"""Queries on simulation, injection, matching and accuracy measures."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import DetectorConfig
from ..functions import penalties as pen
from ..operators import calibrate, detect, evaluate, simulate
from ..sources import load
from . import data
from .data import VECTORS_STD, _truth_sql, injected_sql
from .detection import _BOTH_PARTS, _INJ, _INJ_POINTS, _POINTS_SQL, _SCORED_INJ, CFG, _dp_sql, _values
from .grids import rounded, sums_sql
from .registry import query

_U = "(('0x' || substr(md5({}), 1, 8))::BIGINT + 0.5) / 4294967296.0"
_N, _P = 500, 4
_KEY = "'1|noise|' || series_id || '|' || t || '|' || component || '|{}'"
NOISE = f"""noise AS MATERIALIZED (
  SELECT series_id, t, component, sqrt(-2 * ln({_U.format(_KEY.format('a'))})) * cos(2 * pi() * {_U.format(_KEY.format('b'))}) AS x
  FROM (SELECT '0' AS series_id, t, c::INTEGER AS component FROM range(1, {_N} + 1) AS a(t), range(1, {_P} + 1) AS b(c)))"""


@query(f"WITH {NOISE} SELECT series_id, t, component, round(x + 3e-9, 6) AS x FROM noise")
def simulated_noise(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(simulate.noise(spark, _N, _P), "x")


def _truth_windows_sql() -> str:
    """The draws of truths by their md5: starts, lengths, windows apart, affected components, lags, means."""
    n, p, k, sigma, w, reps, seed, rate = 5000, 10, 2, 2.0, 10, 3, 1, 0.001
    at = lambda what, more="", tail="": _U.format(f"'{seed}|{what}|' || series_id || '|' || s{more}{tail}")
    part = " || '|' || component"
    return f"""WITH RECURSIVE cells AS (SELECT r::VARCHAR AS series_id, s FROM range(0, {reps}) AS a(r), range(0, {n}) AS b(s)),
drawn AS (SELECT series_id, s, s + greatest(4, len(list_filter({simulate.poisson_table(20.0)!r}, lambda c: c < {at('length')}))) AS e FROM cells WHERE {at('start')} < {rate}),
fit AS MATERIALIZED (SELECT * FROM drawn WHERE e <= {n}),
apart(series_id, s, e) AS (
  SELECT series_id, min(s), arg_min(e, s) FROM fit GROUP BY series_id UNION ALL
  SELECT f.series_id, min(f.s), arg_min(f.e, f.s) FROM apart a JOIN fit f ON f.series_id = a.series_id AND f.s >= a.e GROUP BY f.series_id),
numbered AS (SELECT *, row_number() OVER (PARTITION BY series_id ORDER BY s) AS k FROM apart),
parts AS (SELECT series_id, s, e, k, c::INTEGER AS component FROM numbered, range(1, {p} + 1) AS r(c)),
hit AS (SELECT * FROM parts QUALIFY row_number() OVER (PARTITION BY series_id, s ORDER BY {at('affected', part)}, component) <= {k}),
lagged AS (SELECT *, list_filter(list_transform(range(0, {(w + 1) ** 2}), lambda i: [i // {w + 1}, i % {w + 1}]), lambda v: v[1] + v[2] < e - s) AS fits FROM hit),
one AS (SELECT *, fits[floor({at('lags', part)} * len(fits))::BIGINT + 1] AS v FROM lagged)
SELECT series_id, k::INTEGER AS k, s::BIGINT AS s, e::BIGINT AS e, component, v[1]::INTEGER AS d, v[2]::INTEGER AS f,
  round(sqrt(-2 * ln({at('mean', part, " || '|a'")})) * cos(2 * pi() * {at('mean', part, " || '|b'")}) * {sigma} + 3e-9, 6) AS mu FROM one"""


@query(_truth_windows_sql())
def truth_windows(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(simulate.truths(spark, 5000, 10, 2, 2.0, 10, 3), "mu")


@query("""SELECT i::INTEGER AS setting, p::INTEGER AS p, CASE i WHEN 1 THEN 1 WHEN 2 THEN p ELSE CASE WHEN p = 10 THEN 2 ELSE 6 END END::INTEGER AS k,
  round(CASE i WHEN 1 THEN 2 * ln(p) WHEN 2 THEN pow(p, -0.25) ELSE ln(p) END + 3e-9, 6) AS sigma, CASE i WHEN 4 THEN 10 ELSE 0 END::INTEGER AS w,
  CASE i WHEN 1 THEN 1 WHEN 2 THEN 5 ELSE CASE WHEN p = 10 THEN 2 ELSE 5 END END::INTEGER AS alpha0 FROM range(1, 5) AS a(i), (VALUES (10), (100)) AS b(p)""")
def truth_settings(spark: SparkSession, sf: str) -> DataFrame:
    """The four settings of the simulation study for 10 and 100 components."""
    rows = [(i, p, (s := simulate.setting(i, p))["k"], s["sigma"], s["w"], s["alpha0"]) for i in (1, 2, 3, 4) for p in (10, 100)]
    return rounded(spark.createDataFrame(rows, "setting int, p int, k int, sigma double, w int, alpha0 int"), "sigma")


@query(f"WITH {injected_sql(points=True, lags=(2, 1))} SELECT series_id, t, component, round(x + 3e-9, 6) AS x FROM inj")
def injected_series(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(data.injected(spark, sf, points=True, lags=(2, 1)), "x")


def _spans(spark: SparkSession, sf: str) -> DataFrame:
    """Predictions from a table: a series a supplier, a window from each line's shipping day for as many days as pieces."""
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("long")
    rows = load(spark, sf, "lineitem").select(F.col("l_suppkey").cast("string").alias("series_id"), day.alias("s"), F.col("l_quantity").cast("long").alias("n"), "l_linestatus")
    return rows.select("series_id", "s", (F.col("s") + F.col("n")).alias("e"), F.col("l_linestatus").alias("run")).distinct()


def _known(spark: SparkSession, sf: str) -> DataFrame:
    """Two truths a supplier, placed by its key."""
    key = F.col("s_suppkey")
    rows = load(spark, sf, "supplier").select(key.cast("string").alias("series_id"), key.alias("key"), F.explode(F.array(F.lit(1), F.lit(2))).alias("k"))
    at = ((F.col("key") * 37) % 1000 + (F.col("k") - 1) * 1200).cast("long")
    return rows.select("series_id", "k", at.alias("s")).withColumn("e", F.col("s") + 19 + 2 * F.col("k"))


_SPANS = """lines AS (SELECT DISTINCT l_suppkey::VARCHAR AS series_id, date_diff('day', DATE '1995-01-01', l_shipdate::DATE)::BIGINT AS s, l_quantity::BIGINT AS n, l_linestatus AS run FROM lineitem),
pred AS (SELECT DISTINCT series_id, s, s + n AS e FROM lines)"""
_KNOWN = """true_ AS (SELECT s_suppkey::VARCHAR AS series_id, k::INTEGER AS k, (s_suppkey * 37) % 1000 + (k - 1) * 1200 AS ts, (s_suppkey * 37) % 1000 + (k - 1) * 1200 + 19 + 2 * k AS te FROM supplier, (VALUES (1), (2)) AS v(k))"""
_WINS = "true_ AS (SELECT DISTINCT series_id, k, s AS ts, e AS te FROM truth)"


@query(f"""WITH {_SPANS}, {_KNOWN},
pairs AS (SELECT p.series_id, p.s, p.e, k, ts, te, abs(p.s - ts) AS d_start, abs(p.e - te) AS d_end FROM pred p JOIN true_ t ON p.series_id = t.series_id AND abs(p.s - ts) <= 20 AND abs(p.e - te) <= 20)
SELECT series_id, s::BIGINT AS s, e::BIGINT AS e, k, ts::BIGINT AS ts, te::BIGINT AS te, d_start::BIGINT AS d_start, d_end::BIGINT AS d_end FROM pairs
QUALIFY row_number() OVER (PARTITION BY series_id, k ORDER BY d_start + d_end, s, e) = 1 AND row_number() OVER (PARTITION BY series_id, s, e ORDER BY d_start + d_end, ts) = 1""")
def match_windows(spark: SparkSession, sf: str) -> DataFrame:
    return evaluate.match_windows(_spans(spark, sf).select("series_id", "s", "e").distinct(), _known(spark, sf))


@query(f"""WITH {_SPANS}, {_KNOWN},
ends AS (SELECT series_id, k, ts, te, unnest([ts, te]) AS tip FROM true_),
pairs AS (SELECT p.series_id, p.s, p.e, k, ts, te, tip, abs(p.e - tip) AS d_start FROM pred p JOIN ends t ON p.series_id = t.series_id AND abs(p.e - tip) <= 20),
ranked AS (SELECT *, row_number() OVER (PARTITION BY series_id, k, tip ORDER BY d_start, s, e) AS i, row_number() OVER (PARTITION BY series_id, s, e ORDER BY d_start, ts, tip) AS j FROM pairs)
SELECT series_id, s::BIGINT AS s, e::BIGINT AS e, k, ts::BIGINT AS ts, te::BIGINT AS te, d_start::BIGINT AS d_start, 0::BIGINT AS d_end FROM ranked WHERE i = 1 AND j = 1""")
def match_endpoints(spark: SparkSession, sf: str) -> DataFrame:
    return evaluate.match_windows(_spans(spark, sf).select("series_id", "s", "e").distinct(), _known(spark, sf), mode="endpoint")


@query(f"""WITH {_SPANS}, runs AS (SELECT *, max(e) OVER (PARTITION BY series_id ORDER BY s, e ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b FROM pred)
SELECT series_id, round(sum(greatest(0, e - greatest(s, coalesce(b, s)))) / 2600.0 + 3e-9, 6) AS share FROM runs GROUP BY series_id""")
def flagged_share(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(evaluate.flagged_share(_spans(spark, sf).select("series_id", "s", "e").distinct(), 2600), "share")


@query(f"""WITH {_SPANS}, {_KNOWN}
SELECT t.series_id, t.k, t.ts::BIGINT AS ts, t.te::BIGINT AS te, max(CASE WHEN run = 'F' AND least(s + n, te) - greatest(s, ts) >= 5 THEN 1 ELSE 0 END)::BIGINT AS "F", max(CASE WHEN run = 'O' AND least(s + n, te) - greatest(s, ts) >= 5 THEN 1 ELSE 0 END)::BIGINT AS "O"
FROM true_ t LEFT JOIN lines p ON p.series_id = t.series_id GROUP BY ALL""")
def catalogue_ticks(spark: SparkSession, sf: str) -> DataFrame:
    """Known windows that lines of either status cover: a run a status."""
    return evaluate.catalogue_ticks(_spans(spark, sf), _known(spark, sf), ["F", "O"], 5)


@query(f"""WITH {_truth_sql()}, c AS (SELECT 720.0 AS n, 5.0 AS p, 2 * ln(720) AS psi), z AS (SELECT sqrt(p) * psi / ln(p) AS ks, p, psi FROM c),
per AS (SELECT series_id, k, count(*) AS n_affected, avg(mu * mu) AS mu2, first(e - s) AS length FROM truth GROUP BY ALL)
SELECT series_id, k, n_affected, length::BIGINT AS length, n_affected <= ks AS is_sparse, round(ks, 6) AS k_star,
  round(mu2 / CASE WHEN n_affected <= ks THEN ln(p) + psi / n_affected ELSE (sqrt(p * psi) + psi) / n_affected END, 6) AS delta2 FROM per, z""")
def signal_strength(spark: SparkSession, sf: str) -> DataFrame:
    found = evaluate.signal_strength(data.truth(spark), 720, 5, 2 * math.log(720))
    return found.withColumn("k_star", F.round("k_star", 6)).withColumn("delta2", F.round("delta2", 6))


@query("""WITH x AS (SELECT DISTINCT (l_quantity - 1) / 50 AS xi FROM lineitem)
SELECT xi, round(CASE WHEN xi > 0.75 THEN (1 - sqrt(1 - xi)) ** 2 WHEN xi > 0.5 THEN xi - 0.5 END + 3e-9, 6) AS rho_sparse, round(CASE WHEN xi <= 0.5 THEN 0.5 - xi END + 3e-9, 6) AS rho_dense FROM x""")
def detection_boundary(spark: SparkSession, sf: str) -> DataFrame:
    """At the sparsity exponents that the lines' quantities (1 to 50) span."""
    xis = sorted(r["xi"] for r in load(spark, sf, "lineitem").select(((F.col("l_quantity") - 1) / 50).alias("xi")).distinct().collect())
    return rounded(evaluate.detection_boundary(spark, xis), "rho_sparse", "rho_dense")


@query("SELECT 0.0::DOUBLE AS p_window, 0.0::DOUBLE AS p_point, 1::BIGINT AS n_series")
def false_positive_rate_null(spark: SparkSession, sf: str) -> DataFrame:
    """The vectors are noise: nothing may be found in them."""
    null = data.vectors_std(spark, sf)
    return evaluate.false_positive_rate(detect.detect(null, DetectorConfig(m=60)).chosen, null)


@query()
def roc_points(spark: SparkSession, sf: str) -> DataFrame:
    """True and false positives over a sweep of scales on simulated series, in one scoring pass."""
    n, p, reps = 1000, 10, 4
    s = simulate.setting(3, p)
    truth = simulate.truths(spark, n, p, s["k"], s["sigma"], 0, reps, 3, rate=0.005)
    long = simulate.inject(simulate.noise(spark, n, p, reps, 3), truth)
    scales = [0.4, 0.6, 0.8, 1.0, 1.5, 2.5]
    swept = calibrate.sweep(long, DetectorConfig(m=60), scales).where("kind = 'window'")
    return rounded(evaluate.roc_points(swept, truth, reps, scales=scales), "tpr", "fp_per_series")


@query()
def roc_area(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(evaluate.auc(roc_points(spark, sf)), "auc")


_SWEPT = ((0.5, 152, 168), (0.5, 155, 171), (0.5, 352, 372), (0.5, 500, 520), (1.0, 152, 168), (1.0, 352, 372), (1.0, 500, 520), (2.0, 340, 395))
_GRID = (0.5, 1.0, 2.0, 4.0)
_SWEPT_SQL = f"""WITH swept(scale, s, e) AS (VALUES {", ".join(f"({c}::DOUBLE, {s}, {e})" for c, s, e in _SWEPT)}), {_truth_sql()}, {_WINS},
grid(scale) AS (VALUES {", ".join(f"({c}::DOUBLE)" for c in _GRID)}),
pairs AS (SELECT scale, p.s, p.e, k, ts, abs(p.s - ts) + abs(p.e - te) AS cost FROM swept p JOIN true_ t ON abs(p.s - ts) <= 20 AND abs(p.e - te) <= 20),
hits AS (SELECT * FROM pairs QUALIFY row_number() OVER (PARTITION BY scale, k ORDER BY cost, s, e) = 1 AND row_number() OVER (PARTITION BY scale, s, e ORDER BY cost, ts) = 1),
roc AS (SELECT scale, (SELECT count(*) FROM hits h WHERE h.scale = g.scale) AS tp, (SELECT count(*) FROM swept w WHERE w.scale = g.scale) - (SELECT count(*) FROM hits h WHERE h.scale = g.scale) AS fp, (SELECT count(*) FROM true_) AS truths FROM grid g),
points AS (SELECT scale, tp, fp, truths, tp / greatest(truths, 1)::DOUBLE AS tpr, fp / 4.0::DOUBLE AS fp_per_series FROM roc)"""


def _stated_roc(spark: SparkSession) -> DataFrame:
    swept = spark.createDataFrame([("all", *r) for r in _SWEPT], "series_id string, scale double, s bigint, e bigint")
    return evaluate.roc_points(swept, data.truth(spark), 4, scales=list(_GRID))


@query(f"{_SWEPT_SQL} SELECT scale, tp, fp, truths, round(tpr + 3e-9, 6) AS tpr, round(fp_per_series + 3e-9, 6) AS fp_per_series FROM points")
def roc_measure(spark: SparkSession, sf: str) -> DataFrame:
    """The measure on stated windows: a scale without any is a point too."""
    return rounded(_stated_roc(spark), "tpr", "fp_per_series")


@query(f"""{_SWEPT_SQL}, steps AS (SELECT x, tpr, coalesce(lag(x) OVER w, 0) AS px, coalesce(lag(tpr) OVER w, 0) AS py FROM (SELECT least(fp_per_series, 1.0) AS x, tpr FROM points) WINDOW w AS (ORDER BY x, tpr))
SELECT round(sum((x - px) * (tpr + py) / 2) + max(tpr) * (1 - max(x)) + 3e-9, 6) AS auc FROM steps""")
def roc_area_measure(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(evaluate.auc(_stated_roc(spark)), "auc")


_MATCHED = "matched AS (SELECT p.s, p.e, t.k, t.ts, t.te FROM picked p JOIN true_ t ON p.kind = 'window' AND abs(p.s - ts) <= 20 AND abs(p.e - te) <= 20)"


def _of_run(tail: str) -> str:
    """SQL on the joint optimum of the fixture: `picked` and `matched` are what it found."""
    return f"{_INJ}, {_SCORED_INJ}, {_POINTS_SQL}, {_WINS}, {_dp_sql(_BOTH_PARTS, f', {_MATCHED} {tail}')}"


@query(_of_run("""SELECT m AS method, round(avg(abs(s - ts) + abs(e - te)) / 2 + 3e-9, 6) AS mad, count(*) AS n_common FROM matched, (VALUES ('islands'), ('greedy')) AS v(m) GROUP BY m"""))
def location_error(spark: SparkSession, sf: str) -> DataFrame:
    """Two plans on the same series: the joint optimum and the greedy approximation, which find the same windows here."""
    long, truth = data.injected(spark, sf), data.truth(spark)
    found = {plan: evaluate.match_windows(detect.detect(long, CFG, plan).windows, truth) for plan in ("islands", "greedy")}
    return rounded(evaluate.location_error(found), "mad")


@query(_of_run(""", named AS (SELECT m.k, w.component, row_number() OVER (PARTITION BY m.k ORDER BY w.total * w.total / w.n DESC, w.component) AS r, sc.k AS n FROM matched m JOIN wins w ON w.s = m.s AND w.e = m.e JOIN scored sc ON sc.s = m.s AND sc.e = m.e),
kept AS (SELECT k, component FROM named WHERE r <= n),
per AS (SELECT k, (SELECT count(*) FROM kept x WHERE x.k = m.k) AS named, (SELECT count(*) FROM truth t WHERE t.k = m.k) AS n_true, (SELECT count(*) FROM kept x JOIN truth t USING (k, component) WHERE x.k = m.k) AS hit FROM matched m)
SELECT 'all' AS series_id, k, round(hit / named::DOUBLE + 3e-9, 6) AS precision, round(hit / n_true::DOUBLE + 3e-9, 6) AS recall, round(hit / (named + n_true - hit)::DOUBLE + 3e-9, 6) AS jaccard, round(0.0::DOUBLE + 3e-9, 6) AS lag_error FROM per"""))
def component_recovery(spark: SparkSession, sf: str) -> DataFrame:
    long, truth = data.injected(spark, sf), data.truth(spark)
    result = detect.detect(long, CFG)
    return rounded(evaluate.component_recovery(result.affected, truth, evaluate.match_windows(result.windows, truth)), "precision", "recall", "jaccard", "lag_error")


@query(_of_run(""", z AS (SELECT sqrt(5) * 2 * ln(720) / ln(5) AS ks, 2 * ln(720) AS psi),
per AS (SELECT k, min(s) AS ts, min(e) AS te, count(*) AS j, avg(mu * mu) AS mu2 FROM truth GROUP BY k),
limits AS (SELECT row_number() OVER (ORDER BY ts) AS i, ts, te, 10 / (mu2 / CASE WHEN j <= ks THEN ln(5) + psi / j ELSE (sqrt(5 * psi) + psi) / j END) AS far FROM per, z),
found AS (SELECT row_number() OVER (ORDER BY s) AS i, s, e FROM picked WHERE kind = 'window')
SELECT 'all' AS series_id, min(CASE WHEN s IS NOT NULL AND ts IS NOT NULL THEN 1 ELSE 0 END)::INTEGER AS k_equal, min(CASE WHEN coalesce(abs(s - ts) <= far AND abs(e - te) <= far, false) THEN 1 ELSE 0 END)::INTEGER AS within_bound FROM limits FULL JOIN found USING (i)"""))
def consistency_check(spark: SparkSession, sf: str) -> DataFrame:
    long, truth = data.injected(spark, sf), data.truth(spark)
    return evaluate.consistency_check(detect.detect(long, CFG).chosen, truth, evaluate.signal_strength(truth, 720, 5, 2 * math.log(720)))


@query(f"""WITH {VECTORS_STD}, {sums_sql('std', 2, 40)}, prices(k, price) AS (VALUES {_values(DetectorConfig(m=40).curve(500, 64))}),
ranked AS (SELECT series_id, row_number() OVER w AS k, sum(total * total / n) OVER w AS t_k FROM wins WINDOW w AS (PARTITION BY series_id, s, e ORDER BY total * total / n DESC, component ROWS UNBOUNDED PRECEDING)),
tops AS (SELECT series_id, max(t_k / price) AS top FROM ranked JOIN prices USING (k) GROUP BY series_id UNION ALL SELECT series_id, max(x * x) / {DetectorConfig(m=40).point_price(500, 64)!r} FROM std GROUP BY series_id)
SELECT series_id, round(max(top) + 3e-9, 6) AS scale FROM tops GROUP BY series_id""")
def critical_scale(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(calibrate.critical_scale(data.vectors_std(spark, sf), DetectorConfig(m=40)), "scale")


_NULL_CFG = DetectorConfig(m=40, psi=2 * math.log(500))


@query(f"""WITH {VECTORS_STD.replace("std AS MATERIALIZED (", "scaled AS MATERIALIZED (")}, std AS MATERIALIZED (SELECT ((component - 1) // 4)::VARCHAR AS series_id, t, ((component - 1) % 4 + 1)::INTEGER AS component, x FROM scaled),
{sums_sql('std', 2, 40)}, prices(k, price) AS (VALUES {_values(_NULL_CFG.curve(500, 4))}),
ranked AS (SELECT series_id, row_number() OVER w AS k, sum(total * total / n) OVER w AS t_k FROM wins WINDOW w AS (PARTITION BY series_id, s, e ORDER BY total * total / n DESC, component ROWS UNBOUNDED PRECEDING)),
tops AS (SELECT series_id, max(t_k / price) AS top FROM ranked JOIN prices USING (k) GROUP BY series_id UNION ALL SELECT series_id, max(x * x) / {_NULL_CFG.point_price(500, 4)!r} FROM std GROUP BY series_id),
each AS (SELECT series_id, max(top) AS scale FROM tops GROUP BY series_id)
SELECT round(quantile_cont(scale, 0.9) + 3e-9, 6) AS scale FROM each""")
def calibrated_scale(spark: SparkSession, sf: str) -> DataFrame:
    """The vectors are noise: every four slots are a null series."""
    slot = F.col("component") - 1
    null = data.vectors_std(spark, sf).select(F.floor(slot / 4).cast("string").alias("series_id"), "t", (slot % 4 + 1).cast("int").alias("component"), "x")
    c = calibrate.calibrate_scale(null, _NULL_CFG, 0.1)
    return rounded(spark.createDataFrame([(c,)], "scale double"), "scale")


@query()
def tuned_share(spark: SparkSession, sf: str) -> DataFrame:
    c = calibrate.tune_to_share(data.injected(spark, sf), CFG, 0.04)
    return rounded(spark.createDataFrame([(c,)], "scale double"), "scale")


@query()
def optimality_gap(spark: SparkSession, sf: str) -> DataFrame:
    """Objective of the joint optimum and of greedy selection, per series."""
    n, p, reps = 400, 5, 6
    truth = simulate.truths(spark, n, p, 2, 1.5, 0, reps, 11, rate=0.02)
    long = simulate.inject(simulate.noise(spark, n, p, reps, 11), truth)
    cfg = DetectorConfig(m=40, psi=2.0)
    best = detect.detect(long, cfg).objective.withColumnRenamed("objective", "optimum").select("series_id", "optimum")
    greedy = detect.detect(long, cfg, "greedy").objective.select("series_id", F.col("objective").alias("greedy"))
    return rounded(best.join(greedy, "series_id").withColumn("gap", F.col("optimum") - F.col("greedy")), "optimum", "greedy", "gap")


_RUN_TAIL = """, marked AS (SELECT s, e, max(e) OVER (ORDER BY s, e, kind ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM (SELECT s, e, score, 'window' AS kind FROM scored UNION ALL SELECT s, e, score, 'point' FROM spots) WHERE score > 0)
SELECT count(*) FILTER (WHERE reach IS NULL OR s >= reach) AS islands, count(*) AS positive, (SELECT sum(720 - len + 1) FROM range(2, 21) AS r(len))::BIGINT AS possible, (SELECT count(*) FROM picked) AS chosen, (SELECT round(sum(score), 5) FROM picked) AS objective FROM marked"""


@query(f"{_INJ_POINTS}, {_SCORED_INJ}, {_POINTS_SQL}, {_dp_sql(_BOTH_PARTS, _RUN_TAIL)}")
def run_metrics(spark: SparkSession, sf: str) -> DataFrame:
    """Windows possible and positive, islands, and the objective of one run."""
    long = data.injected(spark, sf, points=True)
    found = detect.candidates(long, CFG)
    isl = detect.islands(found).agg(F.countDistinct("island").alias("islands"), F.count("*").alias("positive"))
    sizes = detect.series_sizes(long).agg(F.sum(sum(F.greatest(F.col("n") - L + 1, F.lit(0)) for L in range(CFG.l, CFG.m + 1))).alias("possible"))
    chosen = detect.solve(found).agg(F.count("*").alias("chosen"), F.round(F.sum("score"), 5).alias("objective"))
    return isl.crossJoin(F.broadcast(sizes)).crossJoin(F.broadcast(chosen))


_EV_N, _EV_P = 20, 64
_EV_PSI = 2 * math.log(20) + 4


@query(f"""WITH {VECTORS_STD.replace("std AS MATERIALIZED (", "scaled AS MATERIALIZED (")}, std AS MATERIALIZED (SELECT ((t - 1) // {_EV_N})::VARCHAR AS series_id, (t - 1) % {_EV_N} + 1 AS t, component, x FROM scaled),
{sums_sql('std', 1, _EV_N)},
single AS (SELECT series_id, s, e, sum(greatest(total * total / n - 2 * ln({_EV_P}), 0)) < {2 * _EV_PSI!r} AS sparse, sum(total * total / n) < {_EV_P + 2 * _EV_PSI + 2 * math.sqrt(_EV_P * _EV_PSI)!r} AS dense FROM wins GROUP BY ALL),
cuts AS (SELECT a.series_id, a.s, a.e AS cut, b.e, a.component, a.n * b.n / (a.n + b.n) * (a.total / a.n - b.total / b.n) ** 2 AS v FROM wins a JOIN wins b ON a.series_id = b.series_id AND a.component = b.component AND a.e = b.s),
split AS (SELECT series_id, s, cut, e, sum(greatest(v - 2 * ln({_EV_P}), 0)) < {2 * _EV_PSI!r} AS sparse, sum(v) < {_EV_P + 2 * _EV_PSI + 2 * math.sqrt(_EV_P * _EV_PSI)!r} AS dense FROM cuts GROUP BY ALL)
SELECT event, count(*) AS intervals, round(avg(CASE WHEN held THEN 1.0 ELSE 0.0 END) + 3e-9, 6) AS share FROM (
  SELECT 'sparse' AS event, sparse AS held FROM single UNION ALL SELECT 'dense', dense FROM single UNION ALL SELECT 'split_sparse', sparse FROM split UNION ALL SELECT 'split_dense', dense FROM split) GROUP BY event""")
def noise_events(spark: SparkSession, sf: str) -> DataFrame:
    """The bounds that the consistency result rests on, on all intervals of short noise: the vectors, 20 at a time."""
    place = F.col("t") - 1
    noise = data.vectors_std(spark, sf).select(F.floor(place / _EV_N).cast("string").alias("series_id"), (place % _EV_N + 1).alias("t"), "component", "x")
    return rounded(evaluate.noise_events(noise, _EV_PSI, _EV_N, _EV_P), "share")


@query("""WITH g AS (SELECT k, 20.0 AS p, 2 * ln(1000) AS psi FROM range(1, 21) AS r(k))
SELECT k::INTEGER AS k, round(CASE WHEN k = 1 THEN 2 * psi + 2 * ln(p) ELSE 2 * ln(p) END + 3e-9, 6) AS step, round(2 * psi + 2 * k * ln(p) + 3e-9, 6) AS price FROM g""")
def penalty_increments(spark: SparkSession, sf: str) -> DataFrame:
    """A curve as the price of a window and of each further component, and back."""
    alpha, beta = pen.to_increments(pen.linear_penalty(20, 2 * math.log(1000)))
    steps = [alpha, *beta[1:]]
    rows = [(k, float(s), float(v)) for k, (s, v) in enumerate(zip(steps, pen.from_increments(alpha, beta), strict=True), 1)]
    return rounded(spark.createDataFrame(rows, "k int, step double, price double"), "step", "price")


@query("""SELECT w::INTEGER AS w, k::INTEGER AS k, round(CASE WHEN w = 0 THEN 2 * ln(9000) + 2 * k * ln(4) ELSE 2 * 1.05 * ln(9000) + 2 * k * 1.05 * (ln(4) + ln(w + 1)) END * 1.5 + 3e-9, 6) AS price FROM (VALUES (0), (40)) AS a(w), range(1, 5) AS b(k)""")
def sparse_preset_scaled(spark: SparkSession, sf: str) -> DataFrame:
    """The preset of long series with few components, times a constant."""
    rows = [(w, k, v) for w in (0, 40) for k, v in enumerate(pen.scaled(pen.sparse_penalty(4, math.log(9000), w), 1.5), 1)]
    return rounded(spark.createDataFrame(rows, "w int, k int, price double"), "price")


@query()
def empirical_penalty(spark: SparkSession, sf: str) -> DataFrame:
    """(cost, k, price): curves from simulated null savings, for laws without a formula, at the size of the hourly events."""
    hour = F.date_trunc("hour", "ts")
    size = load(spark, sf, "events").agg(F.count_distinct("event_type").alias("p"), F.count_distinct(hour).alias("n")).first()
    rows = [(cost, k, float(v)) for cost in ("mean", "poisson", "meanvar", "var") for k, v in enumerate(pen.empirical_penalty(cost, size["p"], math.log(size["n"]), 5, 20), 1)]
    return rounded(spark.createDataFrame(rows, "cost string, k int, price double"), "price")


@query(f"{_INJ_POINTS}, {_SCORED_INJ}, {_POINTS_SQL}, {_dp_sql(_BOTH_PARTS, ' SELECT ' + chr(39) + 'all' + chr(39) + ' AS series_id, round(sum(score) + 3e-9, 6) AS objective, count(*) AS n_found FROM picked')}")
def objective_value(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(detect.detect(data.injected(spark, sf, points=True), CFG).objective, "objective")


_POINT_KEY = "'1|point|' || series_id || '|' || j || '|{}'"


@query(f"""WITH c AS (SELECT r::VARCHAR AS series_id, j FROM range(0, 3) AS a(r), range(0, 5) AS b(j))
SELECT series_id, (floor({_U.format(_POINT_KEY.format('t'))} * 5000) + 1)::BIGINT AS t, (floor({_U.format(_POINT_KEY.format('c'))} * 10) + 1)::INTEGER AS component,
  round(sqrt(-2 * ln({_U.format(_POINT_KEY.format('v|a'))})) * cos(2 * pi() * {_U.format(_POINT_KEY.format('v|b'))}) * sqrt(8 * ln(10)) + 3e-9, 6) AS delta FROM c""")
def truth_points(spark: SparkSession, sf: str) -> DataFrame:
    """Five single deviations a series, of variance 8 log p."""
    return rounded(simulate.add_points(spark, 5000, 10, 3), "delta")


@query(f"""WITH c AS (SELECT r::VARCHAR AS series_id, i::INTEGER AS component FROM range(0, 4) AS a(r), range(1, 65) AS b(i))
SELECT series_id, 1 AS k, 20::BIGINT AS s, 40::BIGINT AS e, component, 0 AS d, 0 AS f, round(sqrt(2 * 1.5 * ln(64) / 20) + 3e-9, 6) AS mu FROM c WHERE {_U.format("'1|mixture|' || series_id || '|' || component")} < pow(64, -0.65)""")
def truth_sparse_mixture(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(simulate.sparse_mixture(spark, 64, 0.65, 1.5, 20, 60, 20, 4), "mu")
