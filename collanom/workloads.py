"""The experiments, re-expressed: each workload returns its result frame.

Simulated series are made of seeded noise; given tables get seeded injections. `replicates` scales a
study; comparisons are about directions (who is closer, how a measure moves), not about single numbers.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .comparators import changepoints, higher_criticism
from .config import DetectorConfig
from .functions import penalties as pen
from .operators import baseline, calibrate, detect, evaluate, simulate
from .plans.stages import materialised
from .sources import densify, explode_vectors, load, series_from_table

N, L, M, TOL = 5000, 2, 100, 20
DETECTOR_SCALES = [0.4, 0.6, 0.8, 1.0, 1.3, 1.8, 2.5, 4.0]


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def simulated(spark: SparkSession, number: int, p: int, points: bool, replicates: int, n: int = N, doubled: bool = False, seed: int = 7, rate: float = 0.001) -> tuple[DataFrame, DataFrame, dict]:
    """Series, truths and setting of the simulation study."""
    s = simulate.setting(number, p, doubled)
    truth = simulate.truths(spark, n, p, s["k"], s["sigma"], s["w"], replicates, seed, rate)
    extra = simulate.add_points(spark, n, p, replicates, seed) if points else None
    return simulate.inject(simulate.noise(spark, n, p, replicates, seed), truth, extra), truth, s


def detector(w: int = 0, n: int = N) -> DetectorConfig:
    return DetectorConfig(l=L, m=M, w=w, psi=2 * math.log(n), regime="lag" if w else "composite")


H_CUTS = [6.0, 8.0, 10.0, 15.0, 20.0, 40.0, 80.0, 200.0, 600.0, 3000.0]
S_CUTS = [3.0, 3.5, 4.0, 4.5, 5.0, 5.5, 6.0, 7.0, 8.0, 10.0, 13.0, 18.0]


def _at_cuts(found: DataFrame, column: str, cuts: list[float]) -> DataFrame:
    """Every row once for each cut that its column exceeds, as `scale`."""
    grid = F.array(*[F.lit(float(c)) for c in cuts])
    return found.withColumn("scale", F.explode(grid)).where(F.col(column) > F.col("scale"))


def higher_criticism_at(long: DataFrame, cfg: DetectorConfig, alpha0: int, cuts: list[float]) -> DataFrame:
    """Comparator H's windows and points at several thresholds, from one scoring pass: (series_id, scale, s, e, ..)."""
    low = min(cuts)
    found = higher_criticism.hc_windows(long, cfg, alpha0, low).withColumn("hc", F.col("score") + low)
    kept = _at_cuts(found, "hc", cuts).persist()
    kept.count()  # made once, before the branches that read them run side by side
    return detect.solve(kept, greedy=True, by=("series_id", "scale"))


def projection_at(long: DataFrame, cuts: list[float], intervals: int = 30) -> DataFrame:
    """Comparator S's changes at several thresholds, from one search: (series_id, scale, s, e), the change being e."""
    cps = changepoints.sparse_projection_changepoints(long, threshold=min(cuts), intervals=intervals).persist()
    return _at_cuts(cps, "level", cuts).select("series_id", "scale", F.lit(0).cast("long").alias("s"), F.col("cp").alias("e"))


def roc_of(long: DataFrame, truth: DataFrame, replicates: int, n: int, m: int, alpha0: int, lags: tuple[int, ...] = (0,)) -> DataFrame:
    """(method, scale, tp, fp, truths, tpr, fp_per_series): sweeps of the detector with each lag and of both comparators."""
    parts = []
    for w in lags:
        scales = DETECTOR_SCALES if not w else DETECTOR_SCALES[2:]
        swept = calibrate.sweep(long, detector(w, n).with_(m=m), scales).where("kind = 'window'")
        parts.append(evaluate.roc_points(swept, truth, replicates, TOL, scales=scales).withColumn("method", F.lit(f"detector w={w}")))
    hc = higher_criticism_at(long, DetectorConfig(m=m), alpha0, H_CUTS).where("e - s > 1")
    parts.append(evaluate.roc_points(hc, truth, replicates, TOL, scales=H_CUTS).withColumn("method", F.lit("higher criticism")))
    parts.append(evaluate.roc_points(projection_at(long, S_CUTS), truth, replicates, TOL, "endpoint", S_CUTS).withColumn("method", F.lit("sparse projection")))
    return _union(parts).select("method", "scale", "tp", "fp", "truths", "tpr", "fp_per_series")


def roc_study(spark: SparkSession, number: int, p: int, points: bool, replicates: int = 4, n: int = 1500, m: int = 60, rate: float = 0.004) -> DataFrame:
    """(setting, p, points, method, scale, tp, fp, truths, tpr, fp_per_series): sweeps of the detector (with several lags in settings 3 and 4) and of both comparators."""
    long, truth, s = simulated(spark, number, p, points, replicates, n, rate=rate)
    out = roc_of(long.persist(), truth, replicates, n, m, s["alpha0"], (0, 10, 20) if number in (3, 4) else (0,))
    return out.select(F.lit(number).alias("setting"), F.lit(p).alias("p"), F.lit(points).alias("points"), *out.columns)


def location_of(long: DataFrame, truth: DataFrame, n: int, m: int, alpha0: int, lags: tuple[int, ...] = (0,)) -> DataFrame:
    """(method, mad, n_common): mean distance of the ends over truths that all methods find.

    The detector and comparator H run at their defaults. Comparator S runs at the threshold whose true and
    false positives are closest to the detector's: of its changes, which are two a window.
    """
    found, own, hits = {}, 0, 0
    for w in lags:
        result = detect.detect(long, detector(w, n).with_(m=m))
        windows = materialised(result.windows)  # a method at a time: the plans of later steps hold small tables, not whole searches
        result.release()
        matches = found[f"detector w={w}"] = materialised(evaluate.match_windows(windows, truth, TOL))
        if w == lags[0]:
            own, hits = windows.count(), matches.count()
    scored = higher_criticism.hc_windows(long, DetectorConfig(m=m), alpha0, 20.0).persist()
    hc = materialised(detect.solve(scored, greedy=True).where("kind = 'window'"))
    scored.unpersist()
    found["higher criticism"] = materialised(evaluate.match_windows(hc, truth, TOL))
    changes = materialised(projection_at(long, S_CUTS))
    rates = {r["scale"]: r for r in evaluate.roc_points(changes, truth, 1, TOL, "endpoint", S_CUTS).collect()}
    counts = {r["scale"]: r["n"] for r in changes.groupBy("scale").agg(F.count("*").alias("n")).collect()}
    cut = min(S_CUTS, key=lambda c: abs(rates[c]["tp"] - hits) + abs(counts.get(c, 0) - 2 * own))
    ends = evaluate.match_windows(changes.where(F.col("scale") == cut).select("series_id", "s", "e"), truth, TOL, "endpoint")
    found["sparse projection"] = materialised(evaluate.windows_of_ends(ends))
    return materialised(evaluate.location_error(found))


def location_study(spark: SparkSession, number: int, p: int, points: bool, replicates: int = 4, n: int = 1500, m: int = 60, rate: float = 0.004) -> DataFrame:
    """(setting, p, points, method, mad, n_common): one cell row of the location table, a row a method."""
    long, truth, s = simulated(spark, number, p, points, replicates, n, doubled=True, rate=rate)
    long, truth = materialised(long), materialised(truth)
    out = location_of(long, truth, n, m, s["alpha0"], (0, 10, 20) if number in (3, 4) else (0,))
    return out.select(F.lit(number).alias("setting"), F.lit(p).alias("p"), F.lit(points).alias("points"), "method", F.round("mad", 4).alias("mad"), "n_common")


def injected_tables(spark: SparkSession, sf_dir: str, number: int = 3, p: int = 10, rate: float = 0.006) -> dict[str, tuple[DataFrame, DataFrame, int, int]]:
    """Series of the given tables with truths of a setting added: name to (series, truths, n, alpha0)."""
    events, lineitem = load(spark, sf_dir, "events"), load(spark, sf_dir, "lineitem")
    raw = {
        "events by hour and user": densify(series_from_table(events, "ts", F.col("user_id") % p, F.col("value"), "sum"), "hour"),
        "lineitem by day and supplier": densify(series_from_table(lineitem, "l_shipdate", F.col("l_suppkey") % p, F.col("l_extendedprice"), "sum", "day"), "day"),
    }
    out = {}
    s = simulate.setting(number, p)
    for name, cells in raw.items():
        z = baseline.scaled(cells, "moments").withColumn("series_id", F.lit("0"))
        n = int(detect.series_sizes(z).agg(F.max("n")).first()[0])
        truth = simulate.truths(spark, n, p, s["k"], s["sigma"], s["w"], 1, 7, rate)
        out[name] = (simulate.inject(z, truth), truth, n, s["alpha0"])
    return out


def tables_roc(spark: SparkSession, sf_dir: str, m: int = 60) -> DataFrame:
    """The sweeps on the given tables with injected windows: (series, method, scale, tp, ..)."""
    parts = []
    for name, (long, truth, n, alpha0) in injected_tables(spark, sf_dir).items():
        out = roc_of(long.persist(), truth, 1, n, m, alpha0, (0, 10))
        parts.append(out.select(F.lit(name).alias("series"), *out.columns))
    return _union(parts)


def tables_location(spark: SparkSession, sf_dir: str, m: int = 60) -> DataFrame:
    """The location table on the given tables with injected windows: (series, method, mad, n_common)."""
    parts = []
    for name, (long, truth, n, alpha0) in injected_tables(spark, sf_dir).items():
        out = location_of(materialised(long), materialised(truth), n, m, alpha0, (0, 10))
        parts.append(out.select(F.lit(name).alias("series"), "method", F.round("mad", 4).alias("mad"), "n_common"))
    return _union(parts)


def _timed(make: Callable[[], DataFrame]) -> float:
    """Seconds of building a frame, which may run jobs of its own, and of counting it."""
    began = time.perf_counter()
    make().agg(F.count("*")).collect()
    return time.perf_counter() - began


def runtime_study(spark: SparkSession, axis: str, anomalies: bool = False, sizes: tuple[int, ...] | None = None, uncapped_up_to: int = 4000) -> DataFrame:
    """(method, n, p, seconds) over growing n (p = 10) or p (n = 100): the detector with M = 100, its pruned recursion without a cap on lengths, and both comparators.

    Everything runs once before it is timed, so that start-up is not. The uncapped recursion is left out
    above `uncapped_up_to` observations, where it is quadratic without anomalies.
    """
    rows = []
    cfg = DetectorConfig(m=M)
    for size in sizes or ((1000, 4000, 16000) if axis == "n" else (10, 100, 400)):
        n, p = (size, 10) if axis == "n" else (100, size)
        long = simulate.noise(spark, n, p)
        if anomalies:
            long = simulate.inject(long, simulate.truths(spark, n, p, 2, 3.0, every=100))
        long = long.persist()
        long.count()
        made = {
            "detector": lambda: detect.detect(long, detector(n=n), "islands").chosen,
            "higher criticism": lambda: higher_criticism.higher_criticism_scan(long, cfg),
            "sparse projection": lambda: changepoints.sparse_projection_changepoints(long, intervals=30),
        }
        if n <= uncapped_up_to:
            made["detector without a cap"] = lambda: detect.per_series(long, detector(n=n), "pruned")
        for name, make in made.items():
            if not rows or all(r[0] != name for r in rows):
                _timed(make)
            rows.append((name, n, p, float(_timed(make))))
        long.unpersist()
    return spark.createDataFrame(rows, "method string, n int, p int, seconds double")


def _lineitem_panel(spark: SparkSession, sf_dir: str, parts: int) -> DataFrame:
    cells = series_from_table(load(spark, sf_dir, "lineitem"), "l_shipdate", F.col("l_suppkey"), F.col("l_extendedprice"), "sum", "day")
    return densify(cells, "day")


def _tuned_threshold(long: DataFrame, cfg: DetectorConfig, share: float, alpha0: int = 2) -> tuple[float, DataFrame]:
    """Comparator H's threshold whose windows flag a share of the positions closest to the wanted one, and its windows there."""
    n = detect.series_sizes(long).agg(F.sum("n")).first()[0]
    cuts = [4.0 * 1.25**i for i in range(24)]
    chosen = higher_criticism_at(long, cfg, alpha0, cuts).where("e - s > 1").persist()
    flagged = {r["scale"]: r["share"] for r in chosen.groupBy("scale").agg((F.sum(F.col("e") - F.col("s")) / n).alias("share")).collect()}
    cut = min(cuts, key=lambda c: abs(flagged.get(c, 0.0) - share))
    return cut, chosen.where(F.col("scale") == cut).drop("scale")


def catalogue_runs(spark: SparkSession, sf_dir: str, m: int = M, share: float = 0.04, lags: tuple[int, ...] = (0, 40)) -> tuple[DataFrame, dict[str, DataFrame], list[str]]:
    """Windows (panel, series_id, s, e, method) of every method in three replicates of two panels, each tuned to flag the wanted share; the known windows; the methods.

    The vectors' slots and the suppliers' daily revenue stand in for the two panels; components are dealt
    into replicates by number, and the same lagged windows are injected in all of them.
    """
    panels = {"a": (explode_vectors(load(spark, sf_dir, "embeddings")), 7), "b": (_lineitem_panel(spark, sf_dir, 3), 18)}
    runs, known_windows = [], {}
    for name, (raw, known) in panels.items():
        z = baseline.scaled(raw)
        dealt = z.select(F.concat(F.lit(f"{name}-"), (F.col("component") % 3).cast("string")).alias("series_id"), "t", F.floor((F.col("component") - 1) / 3).cast("int").alias("c"), "x")
        ranked = dealt.withColumn("component", (F.col("c") - F.min("c").over(_by_series()) + 1).cast("int")).drop("c")
        n = int(z.agg(F.max("t")).first()[0])
        step = n // (known + 1)
        truth = simulate.truth_frame(spark, [(f"{name}-{r}", k, k * step, k * step + 18 + k % 5, c, (k * c) % 5, (k + c) % 4, 1.0 + 0.25 * (k % 5)) for r in range(3) for k in range(1, known + 1) for c in range(1, 2 + k % 3)])
        long = materialised(simulate.inject(ranked, truth))
        known_windows[name] = truth.where(F.col("series_id") == f"{name}-0").withColumn("series_id", F.lit(name))
        for w in lags:
            cfg = DetectorConfig(l=L, m=m, w=w, psi=2 * math.log(n), regime="lag" if w else "linear", points=False)
            scale = calibrate.tune_to_share(long, cfg, share, [0.3, 0.5, 0.8, 1.2, 2.0])
            result = detect.detect(long, cfg.with_(scale=scale))
            result.candidates.count()  # made once, before the branches that read them run side by side
            windows = materialised(result.windows)
            result.release()
            runs.append(windows.select(F.lit(name).alias("panel"), "series_id", "s", "e", F.lit(f"w={w}").alias("method"), F.lit(n).alias("n")))
        _, hc = _tuned_threshold(long, DetectorConfig(m=m), share)
        runs.append(hc.select(F.lit(name).alias("panel"), "series_id", "s", "e", F.lit("hc").alias("method"), F.lit(n).alias("n")))
    return _union(runs), known_windows, [*(f"w={w}" for w in lags), "hc"]


def catalogue_study(spark: SparkSession, sf_dir: str, m: int = M, share: float = 0.04, lags: tuple[int, ...] = (0, 40)) -> DataFrame:
    """Known windows found by each method in each of three replicates, all methods tuned to the same share of flagged positions; and the shares that were reached (`share ..`)."""
    runs, known, methods = catalogue_runs(spark, sf_dir, m, share, lags)
    columns = [f"{method} r{r}" for method in methods for r in range(3)]
    pred = runs.select(F.col("panel").alias("series_id"), "s", "e", F.concat("method", F.lit(" r"), F.substring("series_id", 3, 1)).alias("run"))
    ticks = _union([evaluate.catalogue_ticks(pred.where(F.col("series_id") == name), windows, columns, 5) for name, windows in known.items()])
    flagged = runs.groupBy(F.col("panel").alias("series_id")).pivot("method", methods).agg(F.round(F.sum((F.col("e") - F.col("s")) / F.col("n")) / 3, 6))
    return ticks.join(flagged.select("series_id", *[F.col(f"`{m_}`").alias(f"share {m_}") for m_ in methods]), "series_id", "left")


def _by_series():
    from pyspark.sql import Window

    return Window.partitionBy("series_id")


def false_positive_study(spark: SparkSession, sf_dir: str, replicates: int = 8) -> DataFrame:
    """(data, regime, p_window, p_point, bound, n_series) of every regime, that for lags too, on tables without anomalies and on noise; `bound` is the order n M exp(-psi)."""
    daily = densify(series_from_table(load(spark, sf_dir, "orders"), "o_orderdate", F.col("o_orderpriority"), unit="day"), "day")
    hourly = densify(series_from_table(load(spark, sf_dir, "events"), "ts", F.col("event_type")), "hour")
    null = {"vectors": baseline.scaled(explode_vectors(load(spark, sf_dir, "embeddings"))), "orders": baseline.scaled(daily, "moments"), "events": baseline.scaled(hourly), "noise": simulate.noise(spark, 500, 8, replicates, 5)}
    parts = []
    for name, long in null.items():
        n = int(detect.series_sizes(long).agg(F.max("n")).first()[0])
        for regime in ("flat", "linear", "curve", "composite", "consistency", "lag"):
            cfg = DetectorConfig(m=40, regime=regime, w=5 if regime == "lag" else 0)
            rate = evaluate.false_positive_rate(detect.detect(long, cfg).chosen, long)
            bound = pen.false_positive_bound(n, cfg.resolved_psi(n), cfg.m)
            parts.append(rate.select(F.lit(name).alias("data"), F.lit(regime).alias("regime"), "p_window", "p_point", F.lit(bound).alias("bound"), "n_series"))
    return _union(parts)


def power_study(spark: SparkSession, p: int = 64, replicates: int = 8, length: int = 20) -> DataFrame:
    """(xi, r, regime, power): how often a sparse or dense mixture is seen."""
    parts = []
    for xi, strengths in ((0.3, (0.05, 0.15, 0.3)), (0.65, (0.3, 0.8, 2.0)), (0.85, (0.5, 1.5, 3.0))):
        for r in strengths:
            truth = simulate.sparse_mixture(spark, p, xi, r, length, 60, 20, replicates)
            long = simulate.inject(simulate.noise(spark, 60, p, replicates, 13), truth)
            for regime in ("two", "composite"):
                cfg = DetectorConfig(m=30, psi=pen.psi_for("power", 60, p), regime=regime, points=False)
                hit = detect.detect(long, cfg).windows.select("series_id").distinct().agg((F.count("*") / replicates).alias("power"))
                parts.append(hit.select(F.lit(xi).alias("xi"), F.lit(r).alias("r"), F.lit(regime).alias("regime"), "power"))
    return _union(parts)


def consistency_study(spark: SparkSession, c: float = 3.0) -> DataFrame:
    """(n, k_equal, within_bound): share of series with the right number of windows and ends within the bound, as n and K grow."""
    parts = []
    for n in (400, 800, 1600):
        p, reps = 20, 4
        psi = 2 * math.log(n)
        rows = [(str(r), k + 1, 60 + 100 * k, 80 + 100 * k, comp, 0, 0, 2.5) for r in range(reps) for k in range(n // 100 - 1) for comp in range(1, 5)]
        truth = simulate.truth_frame(spark, rows)
        long = simulate.inject(simulate.noise(spark, n, p, reps, 17), truth)
        chosen = detect.detect(long, DetectorConfig(m=60, psi=psi, regime="consistency", points=False)).chosen
        check = evaluate.consistency_check(chosen, truth, evaluate.signal_strength(truth, n, p, psi), c)
        parts.append(check.agg(F.avg("k_equal").alias("k_equal"), F.avg("within_bound").alias("within_bound")).select(F.lit(n).alias("n"), "k_equal", "within_bound"))
    return _union(parts)


def toy(spark: SparkSession, lags: bool = False) -> DataFrame:
    """Two windows over four components, with and without lags: what is found."""
    rows = [("0", 1, 150, 200, c, 3 * c if lags else 0, 2 * c if lags else 0, 2.0) for c in (1, 2, 3)] + [("0", 2, 350, 400, c, 2 * c if lags else 0, c if lags else 0, 2.0) for c in (3, 4)]
    truth = simulate.truth_frame(spark, rows)
    long = simulate.inject(simulate.noise(spark, 500, 4, 1, 19), truth)
    cfg = DetectorConfig(m=80, w=12 if lags else 0, psi=2 * math.log(500))
    result = detect.detect(long, cfg)
    return result.affected.withColumn("lags", F.lit(lags)).withColumn("saving", F.round("saving", 5)).withColumn("estimate", F.round("estimate", 5))


def table_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(series, kind, n_found) on the tables as they are."""
    events, lineitem, orders = (load(spark, sf_dir, t) for t in ("events", "lineitem", "orders"))
    made = {
        "events by hour and type": densify(series_from_table(events, "ts", F.col("event_type")), "hour"),
        "events by day and user": densify(series_from_table(events, "ts", F.col("user_id") % 100, unit="day"), "day"),
        "lineitem by day and flag": densify(series_from_table(lineitem, "l_shipdate", F.concat("l_returnflag", "l_linestatus"), unit="day"), "day"),
        "orders by day and priority": densify(series_from_table(orders, "o_orderdate", F.col("o_orderpriority"), unit="day"), "day"),
        "vectors": explode_vectors(load(spark, sf_dir, "embeddings")),
    }
    parts = []
    for name, raw in made.items():
        long = baseline.scaled(raw, "moments")
        found = detect.detect(long, DetectorConfig(m=min(60, 20 if "user" in name else 60))).chosen
        parts.append(found.groupBy("kind").agg(F.count("*").alias("n_found"), F.min("s").alias("first_s")).select(F.lit(name).alias("series"), "kind", "n_found", "first_s"))
    return _union(parts)
