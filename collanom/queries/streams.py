"""Streaming queries, drained over what the files hold."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import load, to_wide
from ..streaming import stream
from . import data
from .detection import _BOTH_PARTS, _INJ_POINTS, _POINTS_SQL, _SCORED_INJ, CFG, _dp_sql
from .registry import query

#: Cells are final once the watermark, two hours behind the last event, has passed their end.
_LAST = "SELECT max(ts) - INTERVAL 2 HOUR AS mark FROM events"


@query(f"SELECT epoch(h)::BIGINT AS sec, event_type, count(*) AS n FROM (SELECT date_trunc('hour', ts) AS h, event_type FROM events) WHERE h + INTERVAL 1 HOUR <= ({_LAST}) GROUP BY ALL")
def stream_hourly_counts(spark: SparkSession, sf: str) -> DataFrame:
    return stream.drain_to_parquet(stream.hourly_counts(stream.read_events(spark, sf)))


@query(f"SELECT epoch(h)::BIGINT AS sec, event_type, count(*) AS n FROM (SELECT date_trunc('hour', ts) - k * INTERVAL 1 HOUR AS h, event_type FROM events, range(0, 2) AS r(k)) WHERE h + INTERVAL 2 HOUR <= ({_LAST}) GROUP BY ALL")
def stream_sliding_counts(spark: SparkSession, sf: str) -> DataFrame:
    return stream.drain_to_parquet(stream.sliding_counts(stream.read_events(spark, sf)))


@query(f"""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT floor(epoch(min(ts)))::BIGINT AS sec, user_id, count(*) AS n FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 6 HOUR <= ({_LAST})""")
def stream_sessions(spark: SparkSession, sf: str) -> DataFrame:
    return stream.drain_to_parquet(stream.user_sessions(stream.read_events(spark, sf)))


@query("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1")
def stream_dedup(spark: SparkSession, sf: str) -> DataFrame:
    events = stream.read_events(spark, sf)
    twice = events.unionByName(stream.read_events(spark, sf))
    return stream.drain_to_parquet(stream.deduplicated(twice).select("event_id", "event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


@query("SELECT event_type, upper(event_type) AS label, count(*) AS n FROM events GROUP BY ALL")
def stream_join_labels(spark: SparkSession, sf: str) -> DataFrame:
    """A stream against a static table."""
    labels = load(spark, sf, "events").select(F.col("event_type").alias("kind"), F.upper("event_type").alias("label")).distinct()
    joined = stream.read_events(spark, sf).join(F.broadcast(labels), F.col("event_type") == F.col("kind")).select("event_type", "label", "event_id")
    return stream.drain_to_parquet(joined).groupBy("event_type", "label").agg(F.count("*").alias("n"))


@query("SELECT c.event_id AS click, p.event_id AS purchase FROM events p JOIN events c ON p.user_id = c.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 HOUR")
def stream_interval_join(spark: SparkSession, sf: str) -> DataFrame:
    return stream.drain_to_parquet(stream.interval_join(stream.read_events(spark, sf), stream.read_events(spark, sf)))


def _days(spark: SparkSession, sf: str) -> DataFrame:
    """The injected series as a stream of one file a day."""
    path = stream.work_folder(spark)
    wide = to_wide(data.injected(spark, sf, points=True)).withColumn("day", F.floor((F.col("t") - 1) / 24).cast("int"))
    wide.repartitionByRange(30, "day").drop("day").sortWithinPartitions("t").write.parquet(path)
    return spark.readStream.schema("series_id string, t bigint, xs array<double>").option("maxFilesPerTrigger", 4).parquet(path)


@query(f"{_INJ_POINTS}, {_SCORED_INJ}, {_POINTS_SQL}, {_dp_sql(_BOTH_PARTS)}")
def stream_detect_closed(spark: SparkSession, sf: str) -> DataFrame:
    """The online detector over the stream; islands that are still open at its end are not in it."""
    found = stream.drain_to_parquet(stream.detect_closed(_days(spark, sf), CFG, 720))
    return found.withColumn("score", F.round("score", 5))


@query(f"SELECT epoch(h)::BIGINT AS sec, event_type, count(*) AS n FROM (SELECT date_trunc('hour', ts) AS h, event_type FROM events) WHERE h + INTERVAL 1 HOUR <= ({_LAST}) GROUP BY ALL")
def stream_for_each_batch(spark: SparkSession, sf: str) -> DataFrame:
    """Counts handed over batch by batch, appended to a table of files."""
    path = stream.work_folder(spark)
    stream.for_each_batch(stream.hourly_counts(stream.read_events(spark, sf)), lambda df, _: df.write.mode("append").parquet(path))
    return spark.read.schema("sec bigint, event_type string, n bigint").parquet(path)


@query("""WITH early AS (SELECT date_trunc('hour', ts) AS h, event_type, ts FROM events WHERE day(ts) = 20)
SELECT epoch(h)::BIGINT AS sec, event_type, count(*) AS n, true AS late_were_dropped FROM early WHERE h + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 2 HOUR FROM early) GROUP BY ALL""")
def stream_late_rows(spark: SparkSession, sf: str) -> DataFrame:
    """Rows behind the watermark are dropped and counted: the counts of one day, whose file comes first, stay as they are when an earlier day's file follows."""
    path = stream.work_folder(spark)
    events = load(spark, sf, "events").select(F.col("ts").cast("timestamp").alias("ts"), "event_type")
    day = F.dayofmonth("ts")
    events.where(day == 20).coalesce(1).write.parquet(f"{path}/in")
    dropped = 0
    for late in (None, 2):
        if late:
            events.where(day == late).coalesce(1).write.mode("append").parquet(f"{path}/in")
        counts = stream.hourly_counts(spark.readStream.schema("ts timestamp, event_type string").parquet(f"{path}/in"))
        run = counts.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start()
        run.awaitTermination()
        dropped += sum(int(op["numRowsDroppedByWatermark"]) for p in run.recentProgress for op in p["stateOperators"])
    return spark.read.schema("sec bigint, event_type string, n bigint").parquet(f"{path}/out").withColumn("late_were_dropped", F.lit(dropped > 0))
