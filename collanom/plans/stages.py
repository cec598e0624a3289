"""A run over a raw table in stages: every stage is a written table, so the raw table is scanned once."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import DetectorConfig
from ..operators import baseline, detect
from ..sources import densify, series_from_table


def materialised(df: DataFrame) -> DataFrame:
    """Written below spark.checkpoint.dir (a temporary folder only where that is unset) and read again."""
    spark = df.sparkSession
    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="collanom-")
    path = f"{base.rstrip('/')}/stage-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def detect_table(df: DataFrame, time: str, label: Column, cfg: DetectorConfig, value: Column | None = None, agg: str = "count", unit: str = "hour", series: Column | str = "all", approximate: bool | None = None) -> detect.DetectionResult:
    """From a raw table to windows and points: cells (the one scan of the table), scaled series, candidates.

    The cells are as many as time units times labels, whatever the table's rows; scaling and scoring read
    them from the written stage. `approximate` takes quantiles by sketches; None decides by the cells' number.
    """
    cells = materialised(series_from_table(df, time, label, value, agg, unit, series))
    long = densify(cells, unit)
    scaled = materialised(baseline.scaled(long, cfg.how, approximate))
    found = materialised(detect.candidates(scaled, cfg, few=True))
    return detect.DetectionResult(detect.solve(found, cfg.min_gap, longest=cfg.m, widest=cfg.widest), found, scaled, cfg)


def flagged_rows(raw: DataFrame, time: str, windows: DataFrame, origin: str, unit_seconds: int) -> DataFrame:
    """Rows of the raw table inside any found window; `origin` is the series' first tick. Windows are few and broadcast by Spark's own size check."""
    t = F.floor((F.unix_timestamp(F.col(time).cast("timestamp")) - F.unix_timestamp(F.lit(origin).cast("timestamp"))) / unit_seconds) + 1
    ticks = windows.select(F.explode(F.sequence(F.col("s") + 1, F.col("e"))).alias("__t")).distinct()
    return raw.withColumn("__at", t).join(ticks, F.col("__at") == F.col("__t"), "left_semi").drop("__at")
