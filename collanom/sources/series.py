"""Adapters from tables to series: long rows (series_id, t, component, x) on a dense grid."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import SERIES_LONG


def _lit(value) -> Column:
    return value if isinstance(value, Column) else F.lit(value)


def components_of(df: DataFrame, label: Column) -> DataFrame:
    """(component, label): dense numbers from 1 in label order; one row per component."""
    from pyspark.sql import Window

    labels = df.select(label.cast("string").alias("label")).distinct()
    return labels.select(F.row_number().over(Window.orderBy("label")).alias("component"), "label")


def series_from_table(df: DataFrame, time: str, label: Column, value: Column | None = None, agg: str = "count", unit: str = "hour", series: Column | str = "all") -> DataFrame:
    """Aggregates a table to (series_id, tick, label, x): one value per series, time unit and label.

    The projection and the time bucket stay in the scan's stage; the aggregate combines map-side.
    """
    measure = {"count": F.count(F.lit(1)).cast("double"), "sum": F.sum(value) if value is not None else None, "mean": F.avg(value) if value is not None else None}[agg]
    # tied to a column, so that a stated name is not folded out of later joins, which would leave them without a key
    name = F.when(F.col(time).isNotNull(), _lit(series).cast("string"))
    rows = df.select(name.alias("series_id"), F.date_trunc(unit, F.col(time)).alias("tick"), label.cast("string").alias("label"), *([value.alias("v")] if value is not None else []))
    if value is not None:
        measure = {"count": F.count(F.lit(1)).cast("double"), "sum": F.sum("v"), "mean": F.avg("v")}[agg]
    return rows.groupBy("series_id", "tick", "label").agg(measure.alias("x"))


#: Grid cells that one row makes; also the bucket of keys that are ranked together.
STEP = 1 << 16


def _partitions(df: DataFrame) -> int:
    """A stated number of partitions is not merged again, however few bytes the seeds of a grid have."""
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def densify(cells: DataFrame, unit: str = "hour", fill: str = "zero") -> DataFrame:
    """Long rows on the full grid: t from 1 at the first tick of the series, components numbered by label.

    The grid grows out of one row per series, label and `STEP` ticks, dealt over the tasks: nothing is
    broadcast and no task makes a whole series. `fill`: zero, typical (the cell stays null until it is
    scaled, then counts as typical) or error.
    """
    from pyspark.sql import Window

    seconds = {"minute": 60, "hour": 3600, "day": 86400, "week": 604800}[unit]
    bounds = cells.groupBy("series_id").agg(F.unix_timestamp(F.min("tick")).alias("lo"), F.unix_timestamp(F.max("tick")).alias("hi"))
    bounds = bounds.select("series_id", "lo", ((F.col("hi") - F.col("lo")) / seconds).cast("long").alias("last"))
    labels = cells.select("series_id", "label").distinct().withColumn("component", F.row_number().over(Window.partitionBy("series_id").orderBy("label")))
    seeds = labels.join(bounds, "series_id").withColumn("at", F.explode(F.sequence(F.lit(0).cast("long"), F.col("last"), F.lit(STEP).cast("long"))))
    dealt = seeds.repartition(_partitions(cells), "series_id", "label", "at")
    grid = dealt.withColumn("i", F.explode(F.sequence("at", F.least(F.col("last"), F.col("at") + (STEP - 1)))))
    full = grid.select("series_id", (F.col("i") + 1).alias("t"), "component", "label", (F.col("lo") + F.col("i") * seconds).alias("sec"))
    known = cells.select("series_id", F.unix_timestamp("tick").alias("sec"), "label", "x")
    joined = full.join(known, ["series_id", "sec", "label"], "left")
    x = {"zero": F.coalesce("x", F.lit(0.0)), "typical": F.col("x"), "error": F.coalesce(F.col("x"), F.raise_error(F.lit("the grid has a missing cell")).cast("double"))}[fill]
    return joined.select("series_id", F.col("t").cast("long"), F.col("component").cast("int"), x.cast("double").alias("x"))


def explode_vectors(df: DataFrame, key: str = "vec_id", vector: str = "embedding", series: str = "all", ranked: bool = False) -> DataFrame:
    """A vector column as a series in key order: one component per slot.

    t is the key + 1, for keys without gaps, which may begin anywhere. With `ranked` keys that have gaps are
    replaced by their ranks: counted in buckets, so that no task orders all of them; equal keys are an error
    of the detector, as repeated times are.
    """
    from pyspark.sql import Window

    rows = df.where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("key"), F.col(vector).alias("v"))
    if ranked:
        rows = rows.withColumn("bucket", F.floor(F.col("key") / STEP))
        counts = rows.groupBy("bucket").agg(F.count("*").alias("n"))
        before = counts.select("bucket", F.coalesce(F.sum("n").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
        place = F.rank().over(Window.partitionBy("bucket").orderBy("key"))
        rows = rows.withColumn("place", place).join(before, "bucket").select((F.col("before") + F.col("place") - 1).alias("key"), "v")
    # the name is tied to a column, so that it is not folded out of later joins
    name = F.when(F.col("key").isNotNull(), F.lit(series)).alias("series_id")
    slots = rows.select(name, (F.col("key") + 1).alias("t"), F.posexplode("v").alias("pos", "x"))
    return slots.select("series_id", "t", (F.col("pos") + 1).cast("int").alias("component"), F.col("x").cast("double").alias("x"))


def to_wide(long: DataFrame) -> DataFrame:
    """(series_id, t, xs): one row per time with the components in order."""
    return long.groupBy("series_id", "t").agg(F.transform(F.array_sort(F.collect_list(F.struct("component", "x"))), lambda c: c["x"]).alias("xs"))


def read_series(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """A long series from csv (with a header) or json lines."""
    reader = spark.read.schema(SERIES_LONG)
    return reader.csv(path, header=True) if fmt == "csv" else reader.json(path)
