"""Measures: matching, ROC points, location errors, flagged share, catalogue ticks, rates, bounds."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import penalties as pen

TOLERANCE = 20


def match_windows(pred: DataFrame, truth: DataFrame, tol: int = TOLERANCE, mode: str = "window", by: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """One-to-one matches (by..., s, e, k, ts, te, d_start, d_end): both ends within the tolerance.

    `mode='endpoint'`: the prediction's e is a changepoint and may match either end of a truth. A band
    join: both sides are hashed into buckets wider than the tolerance, neighbours included.
    """
    wide = tol + 1
    true = truth.select(*by, F.col("k"), F.col("s").alias("ts"), F.col("e").alias("te")).distinct()
    if mode == "endpoint":
        ends = true.withColumn("at", F.explode(F.array("ts", "te")))
        left = pred.select(*by, "s", "e").withColumn("b", F.explode(F.sequence(F.floor((F.col("e") - tol) / wide), F.floor((F.col("e") + tol) / wide))))
        pairs = left.join(ends.withColumn("b", F.floor(F.col("at") / wide)), [*by, "b"]).where(F.abs(F.col("e") - F.col("at")) <= tol)
        pairs = pairs.withColumn("d_start", F.abs(F.col("e") - F.col("at"))).withColumn("d_end", F.lit(0).cast("long")).withColumn("truth", F.struct("k", "at"))
    else:
        left = pred.select(*by, "s", "e").withColumn("b", F.explode(F.sequence(F.floor((F.col("s") - tol) / wide), F.floor((F.col("s") + tol) / wide))))
        pairs = left.join(true.withColumn("b", F.floor(F.col("ts") / wide)), [*by, "b"])
        pairs = pairs.where((F.abs(F.col("s") - F.col("ts")) <= tol) & (F.abs(F.col("e") - F.col("te")) <= tol))
        pairs = pairs.withColumn("d_start", F.abs(F.col("s") - F.col("ts"))).withColumn("d_end", F.abs(F.col("e") - F.col("te"))).withColumn("truth", F.struct("k"))
    cost = F.col("d_start") + F.col("d_end")
    of_truth = Window.partitionBy(*by, "truth").orderBy(cost, "s", "e")
    of_pred = Window.partitionBy(*by, "s", "e").orderBy(cost, "ts")
    best = pairs.withColumn("i", F.row_number().over(of_truth)).withColumn("j", F.row_number().over(of_pred)).where("i = 1 and j = 1")
    return best.select(*by, "s", "e", "k", "ts", "te", "d_start", "d_end")


def roc_points(chosen: DataFrame, truth: DataFrame, series: int, tol: int = TOLERANCE, mode: str = "window", scales: list[float] | None = None) -> DataFrame:
    """(scale, tp, fp, truths, tpr, fp_per_series) from windows chosen at each scale: columns series_id, scale, s, e.

    `scales` are the scales of the sweep, few numbers; without them those that chose anything are fetched.
    Every truth is held against each of them.
    """
    grid = sorted(scales if scales is not None else [r["scale"] for r in chosen.select("scale").distinct().collect()])
    values = F.array(*[F.lit(float(c)) for c in grid]).cast("array<double>")
    by = ("series_id", "scale")
    each = truth.withColumn("scale", F.explode(values))
    matches = match_windows(chosen, each, tol, mode, by)
    tp = matches.select(*by, "k").distinct().groupBy("scale").agg(F.count("*").alias("tp"))
    false = chosen.select(*by, "s", "e").join(matches.select(*by, "s", "e").distinct(), [*by, "s", "e"], "left_anti").groupBy("scale").agg(F.count("*").alias("fp"))
    n_true = truth.select("series_id", "k").distinct().agg(F.count("*").alias("truths")).select("truths", F.explode(values).alias("scale"))
    out = n_true.join(tp, "scale", "left").join(false, "scale", "left").fillna(0, ["tp", "fp"])
    return out.select("scale", "tp", "fp", "truths", (F.col("tp") / F.greatest(F.col("truths"), F.lit(1))).alias("tpr"), (F.col("fp") / series).alias("fp_per_series"))


def auc(roc: DataFrame, most: float = 1.0) -> DataFrame:
    """Area under (fp_per_series, tpr) up to `most` false positives per series, as a share of it."""
    order = Window.orderBy("x", "tpr")
    pts = roc.select(F.least("fp_per_series", F.lit(most)).alias("x"), "tpr")
    pts = pts.withColumn("px", F.lag("x", 1, 0.0).over(order)).withColumn("py", F.lag("tpr", 1, 0.0).over(order))
    return pts.agg((F.sum((F.col("x") - F.col("px")) * (F.col("tpr") + F.col("py")) / 2) / most + F.max("tpr") * (1 - F.max("x") / most)).alias("auc"))


def location_error(matches: dict[str, DataFrame]) -> DataFrame:
    """(method, mad, n_common): mean absolute distance of both ends over the truths that every method found."""
    common = None
    for m in matches.values():
        found = m.select("series_id", "k").distinct()
        common = found if common is None else common.intersect(found)
    parts = [m.join(common, ["series_id", "k"], "left_semi").agg(((F.sum("d_start") + F.sum("d_end")) / (2 * F.count("*"))).alias("mad"), F.count("*").alias("n_common")).select(F.lit(name).alias("method"), "mad", "n_common") for name, m in matches.items()]
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def windows_of_ends(matches: DataFrame) -> DataFrame:
    """Matches of end points (`mode='endpoint'`) as matches of windows: truths of which both ends were found, with both distances."""
    at_start = F.abs(F.col("e") - F.col("ts")) <= F.abs(F.col("e") - F.col("te"))
    per = matches.groupBy("series_id", "k", "ts", "te").agg(F.min(F.when(at_start, F.col("d_start"))).alias("d_start"), F.min(F.when(~at_start, F.col("d_start"))).alias("d_end"))
    return per.where("d_start is not null and d_end is not null")


def flagged_share(pred: DataFrame, n: int) -> DataFrame:
    """(series_id, share): positions under any window, overlaps once."""
    order = Window.partitionBy("series_id").orderBy("s", "e")
    before = F.max("e").over(order.rowsBetween(Window.unboundedPreceding, -1))
    new = F.greatest(F.lit(0), F.col("e") - F.greatest(F.col("s"), F.coalesce(before, F.col("s"))))
    return pred.select("series_id", "s", "e", new.alias("new")).groupBy("series_id").agg((F.sum("new") / n).alias("share"))


def catalogue_ticks(pred: DataFrame, catalogue: DataFrame, columns: list[str], min_overlap: int = 1, bucket: int = 256) -> DataFrame:
    """One row per known window and a 0/1 column per method and replicate; `pred` has a column `run`. Both sides meet in time buckets."""
    covered = lambda s, e: F.explode(F.sequence(F.floor(F.col(s) / bucket), F.floor(F.col(e) / bucket)))
    known = catalogue.select(F.col("series_id"), F.col("k"), F.col("s").alias("ts"), F.col("e").alias("te")).distinct()
    over = F.least("e", "te") - F.greatest("s", "ts")
    near = known.withColumn("b", covered("ts", "te")).join(pred.select("series_id", "s", "e", "run").withColumn("b", covered("s", "e")), ["series_id", "b"])
    hits = near.where(over >= min_overlap).select("series_id", "k", "ts", "te", "run").distinct()
    ticks = hits.groupBy("series_id", "k", "ts", "te").pivot("run", columns).agg(F.count(F.lit(1)))
    return known.join(ticks, ["series_id", "k", "ts", "te"], "left").fillna(0).orderBy("series_id", "k")


def false_positive_rate(chosen: DataFrame, series: DataFrame) -> DataFrame:
    """(p_window, p_point, n_series) over null series."""
    flags = chosen.groupBy("series_id").agg(F.max(F.when(F.col("kind") == "window", 1).otherwise(0)).alias("w"), F.max(F.when(F.col("kind") == "point", 1).otherwise(0)).alias("o"))
    return series.select("series_id").distinct().join(flags, "series_id", "left").agg(F.avg(F.coalesce("w", F.lit(0))).alias("p_window"), F.avg(F.coalesce("o", F.lit(0))).alias("p_point"), F.count("*").alias("n_series"))


def signal_strength(truth: DataFrame, n: int, p: int, psi: float) -> DataFrame:
    """Per true window: affected components, squared strength, whether it is sparse, and the strength over the noise's share."""
    k_star, log_p = pen.sparse_threshold(p, psi), math.log(p)
    per = truth.groupBy("series_id", "k").agg(F.count("*").alias("n_affected"), F.avg(F.col("mu") * F.col("mu")).alias("mu2"), F.first(F.col("e") - F.col("s")).alias("length"))
    sparse = F.col("n_affected") <= k_star
    bound = F.when(sparse, log_p + psi / F.col("n_affected")).otherwise((math.sqrt(p * psi) + psi) / F.col("n_affected"))
    return per.select("series_id", "k", "n_affected", "length", sparse.alias("is_sparse"), F.lit(k_star).alias("k_star"), (F.col("mu2") / bound).alias("delta2"))


def detection_boundary(spark: SparkSession, xis: list[float]) -> DataFrame:
    """(xi, rho_sparse, rho_dense): weakest detectable strengths by the sparsity exponent."""
    rows = []
    for xi in xis:
        sparse = (1 - math.sqrt(1 - xi)) ** 2 if xi > 0.75 else xi - 0.5 if xi > 0.5 else None
        rows.append((float(xi), sparse, 0.5 - xi if xi <= 0.5 else None))
    return spark.createDataFrame(rows, "xi double, rho_sparse double, rho_dense double")


def consistency_check(chosen: DataFrame, truth: DataFrame, strength: DataFrame, c: float = 1.0) -> DataFrame:
    """(series_id, k_equal, within_bound): right number of windows, and every end within 10 C over its strength."""
    true = truth.select("series_id", "k", "s", "e").distinct().join(strength.select("series_id", "k", "delta2"), ["series_id", "k"])
    order, order_t = Window.partitionBy("series_id").orderBy("s"), Window.partitionBy("series_id").orderBy("ts")
    p = chosen.where("kind = 'window'").select("series_id", "s", "e").withColumn("i", F.row_number().over(order))
    t = true.select("series_id", F.col("s").alias("ts"), F.col("e").alias("te"), "delta2").withColumn("i", F.row_number().over(order_t))
    both = t.join(p, ["series_id", "i"], "full")
    limit = 10 * c / F.col("delta2")
    inside = (F.abs(F.col("s") - F.col("ts")) <= limit) & (F.abs(F.col("e") - F.col("te")) <= limit)
    return both.groupBy("series_id").agg(F.min(F.when(F.col("s").isNotNull() & F.col("ts").isNotNull(), 1).otherwise(0)).alias("k_equal"), F.min(F.when(F.coalesce(inside, F.lit(False)), 1).otherwise(0)).alias("within_bound"))


def component_recovery(pred: DataFrame, truth: DataFrame, matches: DataFrame) -> DataFrame:
    """Per matched window: precision, recall and Jaccard index of the components, and mean lag error of those in both."""
    p = matches.select("series_id", "s", "e", "k").join(pred.select("series_id", "s", "e", "component", "start_lag", "end_lag"), ["series_id", "s", "e"])
    t = truth.select("series_id", "k", "component", "d", "f")
    both = p.join(t, ["series_id", "k", "component"], "full").join(matches.select("series_id", "k"), ["series_id", "k"], "left_semi")
    hit = F.col("s").isNotNull() & F.col("d").isNotNull()
    agg = both.groupBy("series_id", "k").agg(F.sum(F.when(hit, 1).otherwise(0)).alias("hit"), F.count("s").alias("named"), F.count("d").alias("true"), F.avg(F.when(hit, (F.abs(F.col("start_lag") - F.col("d")) + F.abs(F.col("end_lag") - F.col("f"))) / 2)).alias("lag_error"))
    return agg.select("series_id", "k", (F.col("hit") / F.col("named")).alias("precision"), (F.col("hit") / F.col("true")).alias("recall"), (F.col("hit") / (F.col("named") + F.col("true") - F.col("hit"))).alias("jaccard"), "lag_error")


def runtime_slopes(rows: DataFrame, axis: str = "n") -> DataFrame:
    """(method, slope): median of the pairwise slopes of log2 seconds over log2 size."""
    a, b = rows.select("method", F.col(axis).alias("x"), "seconds"), rows.select(F.col("method").alias("m2"), F.col(axis).alias("y"), F.col("seconds").alias("seconds2"))
    pairs = a.join(b, (F.col("method") == F.col("m2")) & (F.col("x") < F.col("y")))
    return pairs.groupBy("method").agg(F.median((F.log2("seconds2") - F.log2("seconds")) / (F.log2("y") - F.log2("x"))).alias("slope"))


def _held(group: pa.Table, psi: float, p: int) -> dict[str, tuple[int, int]]:
    """For each event the windows (or cuts of windows) of a series that its bound covers, and those on which it holds."""
    sparse, dense = 2 * psi, p + 2 * psi + 2 * math.sqrt(p * psi)
    s, e, component, total = (group.column(c).to_numpy() for c in ("s", "e", "component", "total"))
    order = np.argsort(component, kind="stable")
    s, e, component, total = s[order], e[order], component[order], total[order]
    times = np.unique(np.concatenate([s, e]))
    start, end = np.searchsorted(times, s), np.searchsorted(times, e)

    def counted(at: np.ndarray, v: np.ndarray) -> np.ndarray:
        """The number of places, and of those whose values stay below either bound."""
        n = np.bincount(at)
        over = np.bincount(at, np.maximum(v - 2 * math.log(p), 0.0))
        return np.array([np.count_nonzero(n), np.count_nonzero((over < sparse) & (n > 0)), np.count_nonzero((np.bincount(at, v) < dense) & (n > 0))])

    single, split = counted(start * len(times) + end, total * total / (e - s)), np.zeros(3, dtype=np.int64)
    for cut in range(1, len(times) - 1):
        left, right = np.flatnonzero(end == cut), np.flatnonzero(start == cut)
        low, high = (np.searchsorted(component[right], component[left], side) for side in ("left", "right"))
        n = high - low  # each row on the left meets all rows on the right of its component
        i = np.repeat(left, n)
        j = right[np.arange(len(i)) + np.repeat(low - (np.cumsum(n) - n), n)]
        na, nb = e[i] - s[i], e[j] - s[j]
        split += counted(start[i] * len(times) + end[j], na * nb / (na + nb) * (total[i] / na - total[j] / nb) ** 2)
    return {"sparse": (single[0], single[1]), "dense": (single[0], single[2]), "split_sparse": (split[0], split[1]), "split_dense": (split[0], split[2])}


def noise_events(noise: DataFrame, psi: float, n: int, p: int) -> DataFrame:
    """(event, intervals, share): how often four bounds hold on simulated noise, over all intervals of a short series.

    `sparse` and `dense` bound the savings of windows, for every set of components; `split_sparse` and
    `split_dense` bound what is gained by cutting a window in two. Series are dealt over the tasks once; the
    window sums of a series are joined with themselves at every cut in its task, and only its counts leave it.
    """
    from .relational import window_sums

    # a stated number of tasks is not merged again, however few bytes the cells have
    spark = noise.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    sums = window_sums(noise.repartition(tasks, "series_id"), 1, n, ordered=True).select("series_id", "s", "e", "component", "total")

    def count(group):
        rows = [(event, int(of), int(held)) for event, (of, held) in _held(group, psi, p).items() if of]
        events, intervals, held = zip(*rows, strict=True)
        return pa.table({"event": pa.array(events, pa.string()), "intervals": pa.array(intervals, pa.int64()), "held": pa.array(held, pa.int64())})

    counts = sums.groupBy("series_id").applyInArrow(count, "event string, intervals bigint, held bigint").groupBy("event")
    return counts.agg(F.sum("intervals").alias("intervals"), (F.sum("held") / F.sum("intervals")).alias("share"))
