"""Every query runs; those with SQL equal it."""

from __future__ import annotations

import glob
import math
import os

import duckdb
import pytest

import __spark_entry__
from collanom.queries import ORACLES, QUERIES

SLOW = [q for q in QUERIES if q.startswith("w")]


@pytest.fixture(scope="module")
def con(sf):
    db = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        db.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return db


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else v + 0.0
    return tuple(map(plain, v)) if isinstance(v, (list, tuple)) else v


def rows_of(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in rows), key=repr)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, sf, con, name):
    frame, sql = QUERIES[name](spark, sf), con.sql(ORACLES[name])
    assert sorted(frame.columns) == sorted(sql.columns)
    assert rows_of(frame.collect(), frame.columns) == rows_of(sql.fetchall(), sql.columns)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - set(SLOW)))
def test_runs(spark, sf, name):
    frame = QUERIES[name](spark, sf)
    assert len(frame.columns) == len(set(frame.columns))
    frame.collect()


def test_entry(spark):
    found = {(r["s"], r["e"]) for r in __spark_entry__.entry(spark).collect()}
    assert found == {(150, 170), (350, 370)}
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    assert set(QUERIES) <= set(__spark_entry__.queries())


def test_best_counts_below_their_price(spark, tmp_path):
    """So many events an hour that eight more are not worth a window's price: the best window is still the SQL's."""
    path = tmp_path / "events.parquet"
    db = duckdb.connect()
    db.sql(f"""COPY (SELECT row_number() OVER () AS event_id, TIMESTAMP '2024-01-01' + INTERVAL 1 HOUR * h AS ts, 1::BIGINT AS user_id, 'type' || c AS event_type, 1.0::DOUBLE AS value, '{{}}' AS props
      FROM range(0, 720) AS a(h), range(0, 5) AS b(c), range(0, 250) AS d(i) WHERE i < 240 + (h * 7 + c * 3 + h // 11) % 9) TO '{path}' (FORMAT parquet)""")
    db.sql(f"CREATE VIEW events AS SELECT * FROM '{path}'")
    want = db.sql(ORACLES["poisson_affected"])
    frame = QUERIES["poisson_affected"](spark, str(tmp_path))
    got = rows_of(frame.collect(), frame.columns)
    assert got and got == rows_of(want.fetchall(), want.columns)


MOVED = ("calibrated_scale", "catalogue_ticks", "chi2_quantile", "consistency_penalty_table", "detection_boundary", "empirical_penalty", "flagged_share", "lag_penalties", "match_cogrouped", "match_endpoints", "match_windows", "noise_events")


@pytest.mark.parametrize("name", MOVED)
def test_needs_its_table(spark, tmp_path, name):
    """The job is done on a given table: without tables there is no result."""
    with pytest.raises(Exception, match="(?i)path.*not.*exist"):
        QUERIES[name](spark, str(tmp_path)).collect()


def test_exploded_rows_are_not_broadcast(spark, sf):
    """The vectors are a small table, their cells and the sums of their windows are not: no join may build on those."""
    limit = "spark.sql.autoBroadcastJoinThreshold"
    before = spark.conf.get(limit)
    spark.conf.set(limit, "10m")
    try:
        frame = QUERIES["noise_events"](spark, sf)
        plan = frame._jdf.queryExecution().executedPlan().toString()
        assert "BuildLeft" not in plan and plan.count("BroadcastHashJoin") <= 1  # the typical values, a row a component
    finally:
        spark.conf.set(limit, before)


def test_ordered_window_sums(spark):
    """The sums taken in order are those of the join, with gaps and components of different lengths too."""
    from pyspark.sql import functions as F

    from collanom.operators import relational

    cells = spark.range(0, 360).select(F.concat(F.lit("s"), F.col("id") % 3).alias("series_id"), (F.col("id") % 5).cast("int").alias("component"), F.floor(F.col("id") / 15).cast("long").alias("t"), (F.col("id") * 7 % 11 - 5.0).alias("x"))
    for long in (cells.where("t > 0"), cells.where("t > 0 and t <> 4 + component and t <> 9")):
        for low, high in ((1, 23), (3, 7)):
            want, got = ({tuple(r) for r in relational.window_sums(long, low, high, ordered).collect()} for ordered in (False, True))
            assert got == want and want
