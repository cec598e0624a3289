"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import math
import os
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from collanom.comparators import changepoints, higher_criticism
from collanom.config import DetectorConfig
from collanom.operators import baseline, detect, evaluate, simulate
from collanom.queries import QUERIES, data
from collanom.sources import densify, load, series_from_table

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
#: Sizes of the slope: large enough that the work outweighs fixed costs.
SIZES = (60_000, 250_000, 1_000_000)


def suppliers(spark: SparkSession) -> DataFrame:
    cells = series_from_table(load(spark, SF_DIR, "lineitem"), "l_shipdate", F.col("l_suppkey"), F.col("l_extendedprice"), "sum", "day")
    return baseline.scaled(densify(cells, "day"))


def panel(spark: SparkSession, w: int) -> DataFrame:
    """A series of the size of a chromosome's panel: long, few components, sparse penalty, M = 100."""
    n = 30_000
    cfg = DetectorConfig(m=100, w=w, psi=2 * math.log(n), regime="lag" if w else "linear", points=False)
    return detect.detect(simulate.noise(spark, n, 4), cfg).chosen


def work() -> dict[str, Callable[[SparkSession], DataFrame]]:
    null = lambda s, n, p=10: simulate.noise(s, n, p)
    return {
        "detect_events_720x5": lambda s: detect.detect(data.injected(s, SF_DIR, points=True), DetectorConfig(m=100)).chosen,
        "detect_suppliers_2500x1000": lambda s: detect.detect(suppliers(s), DetectorConfig(m=60)).chosen,
        "detect_null_100000x10": lambda s: detect.detect(null(s, 100_000), DetectorConfig(m=100)).chosen,
        "panel_w0": lambda s: panel(s, 0),
        "panel_w40": lambda s: panel(s, 40),
        "panel_greedy": lambda s: detect.detect(null(s, 30_000, 4), DetectorConfig(m=100), "greedy").chosen,
        "uncapped_pruned_2000x10": lambda s: detect.per_series(simulate.inject(null(s, 2000), simulate.truths(s, 2000, 10, 2, 3.0, every=100)), DetectorConfig(m=100)),
        "panel_comparator_s": lambda s: changepoints.sparse_projection_changepoints(null(s, 5000, 10), intervals=30),
        "panel_comparator_h": lambda s: higher_criticism.higher_criticism_scan(null(s, 30_000, 4), DetectorConfig(m=100)),
        "detect_vectors": lambda s: detect.detect(data.injected_vectors(s, SF_DIR), DetectorConfig(m=60)).chosen,
        "window_savings": lambda s: QUERIES["mean_saving_windows"](s, SF_DIR),
    }


def timed(make: Callable[[], DataFrame]) -> float:
    """Seconds of building the frame, which may run jobs of its own, and of writing it out."""
    began = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .appName("bench")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "6g"))
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    # workers and compiled code are warm before anything is timed
    for w in (0, 3):
        timed(lambda: detect.detect(simulate.noise(spark, 2000, 4), DetectorConfig(m=20, w=w)).chosen)
    timed(lambda: QUERIES["mean_saving_windows"](spark, SF_DIR))
    seconds = {name: round(timed(lambda: make(spark)), 3) for name, make in work().items()}
    try:
        from collanom.llm import queries as llm

        seconds |= {name: round(timed(lambda: make(spark, SF_DIR)), 3) for name, make in llm.queries().items()}
    except ImportError:
        pass
    rows = [("null", n, 10, timed(lambda: detect.detect(simulate.noise(spark, n, 10), DetectorConfig(m=100)).chosen)) for n in SIZES]
    slope = evaluate.runtime_slopes(spark.createDataFrame(rows, "method string, n int, p int, seconds double")).first()["slope"]
    total = round(sum(seconds.values()), 3)
    print(json.dumps({"metric": "headline queries", "value": total, "unit": "sec", "queries": seconds, "sf": os.path.basename(SF_DIR.rstrip("/")), "slope_n_null": round(slope, 3)}))


if __name__ == "__main__":
    main()
