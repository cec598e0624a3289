"""Structured Streaming: sources, windowed counts, joins, and a detector that emits islands once they are closed.

The detector's recursion looks back over the longest window only, so its state per series is that many
rows and the candidates of the open island. An island is final once no later window can reach it.
"""

from __future__ import annotations

import pickle
import tempfile
import uuid
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..config import DetectorConfig
from ..operators.blocks import Kernel, best_chain
from ..schema import TABLES


def work_folder(spark: SparkSession) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="collanom-")
    return f"{base.rstrip('/')}/stream-{uuid.uuid4().hex}"


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream."""
    raw = spark.readStream.schema(TABLES["events"]).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def hourly_counts(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """Tumbling counts per hour and type; rows later than the watermark are dropped, the cell being final."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n")).select(F.unix_timestamp("window.start").alias("sec"), "event_type", "n")


def sliding_counts(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.window("ts", "2 hours", "1 hour"), "event_type").agg(F.count("*").alias("n")).select(F.unix_timestamp("window.start").alias("sec"), "event_type", "n")


def user_sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.unix_timestamp("session_window.start").alias("sec"), "user_id", "n")


def deduplicated(events: DataFrame) -> DataFrame:
    """Each event once within the watermark, however often it is delivered."""
    return events.withWatermark("ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"])


def interval_join(events: DataFrame, other: DataFrame) -> DataFrame:
    """Pairs of a user's purchase and earlier click within an hour, both sides streams."""
    a = events.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("t0"), F.col("event_id").alias("click")).withWatermark("t0", "2 hours")
    b = other.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase")).withWatermark("ts", "2 hours")
    return b.join(a, F.expr("user_id = u AND t0 <= ts AND t0 >= ts - INTERVAL 1 HOUR")).select("click", "purchase")


def drain(df: DataFrame, mode: str = "append", name: str | None = None) -> DataFrame:
    """Runs a stream over what is there into a memory table and returns it."""
    spark = df.sparkSession
    table = name or f"collanom_{uuid.uuid4().hex[:12]}"
    run = df.writeStream.format("memory").queryName(table).outputMode(mode).option("checkpointLocation", work_folder(spark)).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.table(table)


def drain_to_parquet(df: DataFrame) -> DataFrame:
    """The same into files, exactly once by the checkpoint."""
    spark, path = df.sparkSession, work_folder(df.sparkSession)
    df.writeStream.format("parquet").option("checkpointLocation", f"{path}-log").option("path", path).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(path)


def for_each_batch(df: DataFrame, put: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    df.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", work_folder(df.sparkSession)).trigger(availableNow=True).start().awaitTermination()


class OnlineDetector:
    """State of one series: the last rows, and the candidates of the open island."""

    def __init__(self, cfg: DetectorConfig, n: int) -> None:
        self.cfg, self.n = cfg, n
        self.rows: list[tuple[int, list[float]]] = []
        self.waiting: dict[int, list[float]] = {}
        self.open: list[tuple[int, int, float, str]] = []
        self.kernel: Kernel | None = None

    def feed(self, rows: list[tuple[int, list[float]]]) -> list[tuple[int, int, float, str]]:
        """Takes new rows, which may come out of order, and returns what has become final. Rows wait until those before them are there; repeated times are ignored."""
        known = self.rows[-1][0] if self.rows else 0
        self.waiting |= {t: x for t, x in rows if t > known and t not in self.waiting}
        fresh = []
        while known + 1 in self.waiting:
            known += 1
            fresh.append((known, self.waiting.pop(known)))
        if not fresh:
            return []
        keep = self.rows[-self.cfg.m :]
        block = keep + fresh
        x = np.array([v for _, v in block], float)
        if self.kernel is None:
            p = x.shape[1]
            self.kernel = Kernel(self.cfg.l, self.cfg.m, self.cfg.curve(self.n, p), self.cfg.cost, self.cfg.w, self.cfg.gamma, self.cfg.point_price(self.n, p), self.cfg.points)
        base, first = block[0][0] - 1, len(keep)
        f = self.kernel.scores(x, first)
        self.open += [(int(s) + base, int(e) + base, float(v), "window") for s, e, v in zip(f["s"], f["e"], f["score"], strict=True)]
        if self.kernel.points:
            self.open += [(base + first + i, base + first + i + 1, float(v), "point") for i, v in enumerate(self.kernel.point_savings(x[first:])) if v > 0]
        self.rows = block[-self.cfg.m :]
        return self.closed(block[-1][0])

    def closed(self, now: int) -> list[tuple[int, int, float, str]]:
        """Islands that end at or before now - m + 1 can't be reached by a window that ends later."""
        self.open.sort()
        out, group, reach, rest = [], [], -1, []
        groups: list[tuple[list, int]] = []
        for c in self.open:
            if group and c[0] >= reach + self.cfg.min_gap:
                groups.append((group, reach))
                group, reach = [], -1
            group.append(c)
            reach = max(reach, c[1])
        if group:
            groups.append((group, reach))
        for group, reach in groups:
            if reach <= now + 1 - self.cfg.m:
                out += [group[i] for i in best_chain(group, self.cfg.min_gap)[1]]
            else:
                rest += group
        self.open = rest
        return out


def detect_closed(wide: DataFrame, cfg: DetectorConfig, n: int) -> DataFrame:
    """A stream of (series_id, t, xs) to the final windows and points; `n` is the length that the penalties are set for."""

    def step(key, pdfs, state):
        own = pickle.loads(state.get[0]) if state.exists else OnlineDetector(cfg, n)
        rows = [(int(t), list(x)) for pdf in pdfs for t, x in zip(pdf["t"], pdf["xs"], strict=True)]
        found = own.feed(rows)
        state.update((pickle.dumps(own),))
        yield pd.DataFrame([(key[0], *c) for c in found], columns=["series_id", "s", "e", "score", "kind"])

    return wide.groupBy("series_id").applyInPandasWithState(step, "series_id string, s bigint, e bigint, score double, kind string", "detector binary", "append", GroupStateTimeout.NoTimeout)
