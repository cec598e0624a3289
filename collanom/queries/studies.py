"""The experiments as queries; the simulated ones and the catalogue at the published sizes with fewer replicates, the others smaller."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import workloads as w
from ..functions import penalties as pen
from ..operators import evaluate
from .registry import query


#: Components of the simulated series.
SIZES = (10, 100)


def _roc(number: int, points: bool):
    def made(spark: SparkSession, sf: str) -> DataFrame:
        return w._union([w.roc_study(spark, number, p, points, replicates=2, n=w.N, m=w.M, rate=0.001) for p in SIZES])

    return made


def _location(number: int):
    def made(spark: SparkSession, sf: str) -> DataFrame:
        return w._union([w.location_study(spark, number, p, points, replicates=3, n=w.N, m=w.M, rate=0.001) for p in SIZES for points in (False, True)])

    return made


for _number in (1, 2, 3, 4):
    query(name=f"w{_number:02d}_roc_setting{_number}")(_roc(_number, False))
    query(name=f"w{_number + 4:02d}_roc_setting{_number}_points")(_roc(_number, True))
    query(name=f"w10_location_setting{_number}")(_location(_number))


@query()
def w09_roc_tables(spark: SparkSession, sf: str) -> DataFrame:
    """The sweeps on the given tables with injected windows."""
    return w.tables_roc(spark, sf)


@query()
def w10_location_tables(spark: SparkSession, sf: str) -> DataFrame:
    return w.tables_location(spark, sf)


@query()
def w11_runtime_null(spark: SparkSession, sf: str) -> DataFrame:
    return w.runtime_study(spark, "n", sizes=(1000, 2000, 4000, 16_000))


@query()
def w12_runtime_anomalies(spark: SparkSession, sf: str) -> DataFrame:
    return w.runtime_study(spark, "n", True, sizes=(1000, 2000, 4000, 16_000))


@query()
def w13_runtime_components(spark: SparkSession, sf: str) -> DataFrame:
    return w.runtime_study(spark, "p", sizes=(10, 100, 400))


@query()
def w13_runtime_slopes(spark: SparkSession, sf: str) -> DataFrame:
    return evaluate.runtime_slopes(w.runtime_study(spark, "n", sizes=(1000, 2000, 4000, 16_000)))


@query()
def w14_catalogue(spark: SparkSession, sf: str) -> DataFrame:
    return w.catalogue_study(spark, sf)


@query()
def w15_penalty_curves(spark: SparkSession, sf: str) -> DataFrame:
    """Where each curve binds, for several numbers of components."""
    import math

    parts = [pen.penalty_table(spark, p, 2 * math.log(5000)).groupBy("binding").agg(F.min("k").alias("first_k"), F.max("k").alias("last_k")).withColumn("p", F.lit(p)) for p in (10, 64, 100, 500)]
    return w._union(parts)


@query()
def w16_false_positives(spark: SparkSession, sf: str) -> DataFrame:
    return w.false_positive_study(spark, sf, replicates=4)


@query()
def w17_power(spark: SparkSession, sf: str) -> DataFrame:
    return w.power_study(spark, replicates=4)


@query()
def w18_consistency(spark: SparkSession, sf: str) -> DataFrame:
    return w.consistency_study(spark)


@query()
def w19_toy(spark: SparkSession, sf: str) -> DataFrame:
    return w.toy(spark).unionByName(w.toy(spark, True))


@query()
def w20_tables(spark: SparkSession, sf: str) -> DataFrame:
    return w.table_sweep(spark, sf)


@query()
def staged_detection(spark: SparkSession, sf: str) -> DataFrame:
    """A raw table to its windows in stages, each written: the table itself is scanned once."""
    from ..config import DetectorConfig
    from ..plans import detect_table
    from ..sources import load

    found = detect_table(load(spark, sf, "lineitem"), "l_shipdate", F.concat("l_returnflag", "l_linestatus"), DetectorConfig(m=60), unit="day")
    return found.chosen.select("series_id", "s", "e", F.round("score", 4).alias("score"), "kind")


@query()
def plan_choices(spark: SparkSession, sf: str) -> DataFrame:
    """What the planner decides for series of several sizes."""
    from ..config import DetectorConfig
    from ..plans import choose

    rows = []
    for name, cfg, n, p in (("long", DetectorConfig(m=100), 10**7, 10), ("panel", DetectorConfig(m=20), 100, 1000), ("lagged", DetectorConfig(w=40), 10**5, 4), ("uncapped", DetectorConfig(m=5000), 5000, 10), ("wide", DetectorConfig(m=20), 200, 100_000), ("small", DetectorConfig(m=10), 500, 5)):
        plan = choose(cfg, n, p)
        rows.append((name, plan.statistic, plan.programme, plan.chunk, plan.pairs))
    return spark.createDataFrame(rows, "name string, statistic string, programme string, chunk int, pairs bigint")
