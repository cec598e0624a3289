"""The relational operators around the methods, each on a given table with its SQL."""

from __future__ import annotations

import math
import tempfile

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import penalties as pen
from ..functions import udfs
from ..operators import baseline, detect, relational
from ..sources import explode_vectors, load, read_series, to_wide, write_result
from . import data
from .data import HOURLY, HOURLY_STD, VECTORS, _truth_sql, injected_sql
from .detection import _INJ, _SCORED_INJ, CFG
from .grids import rounded
from .measures import _KNOWN, _SPANS, _known, _spans
from .registry import query


@query("SELECT l_orderkey, l_suppkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-03-01' AND l_shipdate < TIMESTAMP '1996-03-08'")
def scan_pushdown(spark: SparkSession, sf: str) -> DataFrame:
    """Declared schema; the date range and the columns reach the parquet scan."""
    return load(spark, sf, "lineitem").where("l_shipdate >= timestamp_ntz'1996-03-01' and l_shipdate < timestamp_ntz'1996-03-08'").select("l_orderkey", "l_suppkey", "l_quantity")


def _shared(spark: SparkSession) -> str:
    """A folder for files that a query writes and reads: the session's shared one, else a temporary one."""
    import uuid

    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="collanom-")
    return f"{base.rstrip('/')}/files-{uuid.uuid4().hex}"


@query(f"WITH {HOURLY} SELECT series_id, t, component, x FROM hourly")
def source_csv(spark: SparkSession, sf: str) -> DataFrame:
    path = _shared(spark)
    data.hourly(spark, sf).write.option("header", True).csv(path)
    return read_series(spark, path, "csv")


@query(f"WITH {HOURLY} SELECT series_id, t, component, x FROM hourly")
def source_json(spark: SparkSession, sf: str) -> DataFrame:
    path = _shared(spark)
    data.hourly(spark, sf).write.json(path)
    return read_series(spark, path, "json")


@query(f"WITH {HOURLY} SELECT series_id, t, component, x FROM hourly")
def sink_partitioned(spark: SparkSession, sf: str) -> DataFrame:
    path = _shared(spark)
    write_result(data.hourly(spark, sf), path)
    return spark.read.schema("t bigint, component int, x double, series_id string").parquet(path).select("series_id", "t", "component", "x")


@query(f"WITH {VECTORS} SELECT series_id, t, component, round(x + 3e-9, 6) AS x FROM vectors")
def explode_vector_slots(spark: SparkSession, sf: str) -> DataFrame:
    return rounded(explode_vectors(load(spark, sf, "embeddings")), "x")


@query(f"WITH {HOURLY_STD} SELECT series_id, t, component, round(x + 3e-9, 6) AS x FROM std WHERE t BETWEEN 100 AND 240 AND component IN (1, 3)")
def restrict_range(spark: SparkSession, sf: str) -> DataFrame:
    """A time range with its margin of the longest window, and some components."""
    return rounded(data.hourly_std(spark, sf).where(F.col("t").between(120 - CFG.m, 220 + CFG.m) & F.col("component").isin(1, 3)), "x")


@query("SELECT event_id, (props->>'$.k')::INTEGER AS k FROM events WHERE (props->>'$.k')::INTEGER >= 5")
def json_props(spark: SparkSession, sf: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("int")
    return load(spark, sf, "events").select("event_id", k.alias("k")).where("k >= 5")


@query(f"WITH {HOURLY_STD}, g AS (SELECT *, sum(CASE WHEN x = 0 THEN 1 ELSE 0 END) OVER () AS z FROM std) SELECT component, count(*) AS n, round(avg(x) + 3e-9, 6) AS mean FROM g GROUP BY component")
def join_broadcast_params(spark: SparkSession, sf: str) -> DataFrame:
    long = data.hourly(spark, sf)
    params = baseline.guard_scale(baseline.fit_typical(long))
    z = long.join(F.broadcast(params.select("series_id", "component", "mu", "sigma", "degenerate")), ["series_id", "component"])
    x = F.when(F.col("degenerate"), 0.0).otherwise((F.col("x") - F.col("mu")) / F.col("sigma"))
    return rounded(z.groupBy("component").agg(F.count("*").alias("n"), F.avg(x).alias("mean")), "mean")


@query(f"""WITH {HOURLY_STD}, {_truth_sql()}
SELECT y.series_id, y.t, y.component, round(y.x + 3e-9, 6) AS x, w.k FROM std y JOIN truth w ON w.series_id = y.series_id AND w.component = y.component AND y.t > w.s + w.d AND y.t <= w.e - w.f""")
def label_rows(spark: SparkSession, sf: str) -> DataFrame:
    """Range join through time buckets: rows inside a true window, with its number."""
    wins = data.truth(spark).select("series_id", (F.col("s") + F.col("d")).alias("s"), (F.col("e") - F.col("f")).alias("e"), "k", F.col("component").alias("c"))
    inside = detect.rows_in_windows(data.hourly_std(spark, sf), wins).where("component = c")
    return rounded(inside.select("series_id", "t", "component", "x", "k"), "x")


@query(f"""{_INJ}, {_SCORED_INJ}, pos AS (SELECT series_id, s, e FROM scored WHERE score > 200), t AS (SELECT DISTINCT series_id, k, s AS ts, e AS te FROM truth)
SELECT p.s, p.e, t.k, (least(p.e, te) - greatest(p.s, ts))::BIGINT AS shared FROM pos p JOIN t ON p.s < te AND ts < p.e""")
def join_interval_overlap(spark: SparkSession, sf: str) -> DataFrame:
    found = detect.candidates(data.injected(spark, sf), CFG.with_(points=False)).where("score > 200").select("series_id", "s", "e")
    size = 64
    cover = lambda s, e: F.explode(F.sequence(F.floor(F.col(s) / size), F.floor(F.col(e) / size)))
    true = data.truth(spark).select("series_id", "k", F.col("s").alias("ts"), F.col("e").alias("te")).distinct().withColumn("b", cover("ts", "te"))
    pairs = found.withColumn("b", cover("s", "e")).join(true, ["series_id", "b"]).where((F.col("s") < F.col("te")) & (F.col("ts") < F.col("e")))
    return pairs.select("s", "e", "k", (F.least("e", "te") - F.greatest("s", "ts")).alias("shared")).distinct()


@query("""WITH daily AS (SELECT date_trunc('day', ts) AS d, event_type, avg(value) AS mu FROM events GROUP BY 1, 2)
SELECT e.event_id, round(e.value - p.mu + 3e-9, 6) AS dev FROM events e ASOF JOIN daily p ON e.event_type = p.event_type AND date_trunc('day', e.ts) - INTERVAL 1 DAY >= p.d""")
def join_asof_typical(spark: SparkSession, sf: str) -> DataFrame:
    """Each event against the latest earlier day's mean of its type: a union and a running last value, no inequality join."""
    events = load(spark, sf, "events").select("event_id", "event_type", "value", F.date_trunc("day", "ts").alias("d"))
    daily = events.groupBy("event_type", "d").agg(F.avg("value").alias("mu")).select("event_type", (F.col("d") + F.expr("interval 1 day")).alias("at"), "mu", F.lit(0).alias("order_"), F.lit(None).cast("long").alias("event_id"), F.lit(None).cast("double").alias("value"))
    rows = events.select("event_type", F.col("d").alias("at"), F.lit(None).cast("double").alias("mu"), F.lit(1).alias("order_"), "event_id", "value")
    w = Window.partitionBy("event_type").orderBy("at", "order_", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    joined = daily.unionByName(rows).withColumn("mu", F.last("mu", ignorenulls=True).over(w)).where("event_id is not null and mu is not null")
    return rounded(joined.select("event_id", (F.col("value") - F.col("mu")).alias("dev")), "dev")


@query(f"""{_INJ}, {_SCORED_INJ}, top AS (SELECT series_id, s, e FROM scored WHERE score > 0 ORDER BY score DESC LIMIT 1)
SELECT series_id, t, component, round(x + 3e-9, 6) AS x FROM inj i WHERE EXISTS (SELECT 1 FROM top w WHERE w.series_id = i.series_id AND i.t > w.s AND i.t <= w.e)""")
def semi_flagged_rows(spark: SparkSession, sf: str) -> DataFrame:
    long = data.injected(spark, sf)
    best = detect.single_window_test(long, CFG).where("detected").select("series_id", F.explode(F.sequence(F.col("s") + 1, F.col("e"))).alias("t"))
    return rounded(long.join(best, ["series_id", "t"], "left_semi").select("series_id", "t", "component", "x"), "x")


@query(f"""{_INJ}, {_SCORED_INJ}, top AS (SELECT series_id, s, e FROM scored WHERE score > 0 ORDER BY score DESC LIMIT 1), t AS (SELECT DISTINCT series_id, k, s AS ts, e AS te FROM truth)
SELECT k, ts::BIGINT AS ts, te::BIGINT AS te FROM t WHERE NOT EXISTS (SELECT 1 FROM top p WHERE p.s < te AND ts < p.e)""")
def anti_missed_truths(spark: SparkSession, sf: str) -> DataFrame:
    best = detect.single_window_test(data.injected(spark, sf), CFG).where("detected")
    true = data.truth(spark).select("series_id", "k", F.col("s").alias("ts"), F.col("e").alias("te")).distinct()
    return true.join(F.broadcast(best.select(F.col("series_id").alias("q"), "s", "e")), (F.col("q") == F.col("series_id")) & (F.col("s") < F.col("te")) & (F.col("ts") < F.col("e")), "left_anti").select("k", "ts", "te")


_SCALES = (0.5, 1.0, 2.0)


@query(f"""{_INJ}, {_SCORED_INJ}, sc(scale) AS (VALUES {", ".join(f"({c}::DOUBLE)" for c in _SCALES)})
SELECT scale, count(*) FILTER (WHERE score > (scale - 1) * 50) AS n FROM scored CROSS JOIN sc WHERE score > 0 GROUP BY scale""")
def sweep_scales(spark: SparkSession, sf: str) -> DataFrame:
    """Candidates against a broadcast list of scales."""
    scales = spark.createDataFrame([(c,) for c in _SCALES], "scale double")
    found = detect.candidates(data.injected(spark, sf), CFG.with_(points=False)).crossJoin(F.broadcast(scales))
    return found.groupBy("scale").agg(F.count(F.when(F.col("score") > (F.col("scale") - 1) * 50, 1)).alias("n"))


@query("""SELECT a.c_custkey AS a, b.c_custkey AS b FROM customer a JOIN customer b ON a.c_custkey < b.c_custkey AND abs(a.c_acctbal - b.c_acctbal) < 0.5""")
def pairs_within(spark: SparkSession, sf: str) -> DataFrame:
    """A pure inequality join by bands of the value instead of a nested loop."""
    c = load(spark, sf, "customer").select("c_custkey", "c_acctbal", F.floor(F.col("c_acctbal") / 0.5).alias("band"))
    right = c.select(F.col("c_custkey").alias("b"), F.col("c_acctbal").alias("v"), F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"))
    return c.join(right, "band").where((F.col("c_custkey") < F.col("b")) & (F.abs(F.col("c_acctbal") - F.col("v")) < 0.5)).select(F.col("c_custkey").alias("a"), "b")


@query(f"{_INJ}, {_SCORED_INJ} SELECT count(DISTINCT s) AS starts, count(DISTINCT e) AS ends FROM scored WHERE score > 0")
def affected_distinct(spark: SparkSession, sf: str) -> DataFrame:
    found = detect.candidates(data.injected(spark, sf), CFG.with_(points=False))
    return found.agg(F.countDistinct("s").alias("starts"), F.countDistinct("e").alias("ends"))


@query()
def approx_users(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


_HT = "SELECT hour(ts)::INTEGER AS h, event_type FROM events"


@query(f"SELECT h, event_type, count(*) AS n, (grouping(h) * 2 + grouping(event_type))::BIGINT AS g FROM ({_HT}) GROUP BY GROUPING SETS ((h), (event_type), ())")
def grouping_sets_hour_type(spark: SparkSession, sf: str) -> DataFrame:
    load(spark, sf, "events").select(F.hour("ts").alias("h"), "event_type").createOrReplaceTempView("collanom_hours")
    return spark.sql("SELECT h, event_type, count(*) AS n, grouping_id(h, event_type) AS g FROM collanom_hours GROUP BY GROUPING SETS ((h), (event_type), ())")


@query(f"SELECT h, event_type, count(*) AS n, (grouping(h) * 2 + grouping(event_type))::BIGINT AS g FROM ({_HT}) GROUP BY CUBE (h, event_type)")
def cube_hour_type(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "events").select(F.hour("ts").alias("h"), "event_type").cube("h", "event_type").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("SELECT y, m, d, count(*) AS n, round(sum(o_totalprice), 2) AS revenue FROM (SELECT year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, day(o_orderdate)::INTEGER AS d, o_totalprice FROM orders) GROUP BY ROLLUP (y, m, d)")
def rollup_calendar(spark: SparkSession, sf: str) -> DataFrame:
    rows = load(spark, sf, "orders").select(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofmonth("o_orderdate").alias("d"), "o_totalprice")
    return rows.rollup("y", "m", "d").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("revenue"))


@query(f"WITH {HOURLY}, w AS (SELECT t, max(CASE WHEN component = 1 THEN x END) AS c1, max(CASE WHEN component = 2 THEN x END) AS c2 FROM hourly GROUP BY t) SELECT t, 'c1' AS which, c1 AS x FROM w UNION ALL SELECT t, 'c2', c2 FROM w")
def pivot_unpivot(spark: SparkSession, sf: str) -> DataFrame:
    wide = data.hourly(spark, sf).where("component <= 2").groupBy("t").pivot("component", [1, 2]).agg(F.first("x")).toDF("t", "c1", "c2")
    return wide.unpivot("t", ["c1", "c2"], "which", "x")


@query(f"""WITH {HOURLY_STD} SELECT t, component, row_number() OVER w AS rn, rank() OVER (PARTITION BY t ORDER BY x DESC) AS rk, dense_rank() OVER (PARTITION BY t ORDER BY x DESC) AS dr, ntile(2) OVER w AS half
FROM std WINDOW w AS (PARTITION BY t ORDER BY x DESC, component)""")
def rank_components(spark: SparkSession, sf: str) -> DataFrame:
    full, ties = Window.partitionBy("t").orderBy(F.desc("x"), "component"), Window.partitionBy("t").orderBy(F.desc("x"))
    std = data.hourly_std(spark, sf)
    cast = lambda c: c.cast("long")
    return std.select("t", "component", cast(F.row_number().over(full)).alias("rn"), cast(F.rank().over(ties)).alias("rk"), cast(F.dense_rank().over(ties)).alias("dr"), cast(F.ntile(2).over(full)).alias("half"))


@query(f"""WITH {HOURLY} SELECT component, t, lag(x) OVER w AS before, lead(x) OVER w AS after, first(x) OVER w AS head, last(x) OVER (PARTITION BY component ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS tail, nth_value(x, 3) OVER w AS third
FROM hourly WINDOW w AS (PARTITION BY component ORDER BY t)""")
def lag_lead_gaps(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("component").orderBy("t")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return data.hourly(spark, sf).select("component", "t", F.lag("x").over(w).alias("before"), F.lead("x").over(w).alias("after"), F.first("x").over(w).alias("head"), F.last("x").over(whole).alias("tail"), F.nth_value("x", 3).over(w).alias("third"))


@query(f"WITH {HOURLY} SELECT component, t, round(avg(x) OVER (PARTITION BY component ORDER BY t ROWS BETWEEN 5 PRECEDING AND CURRENT ROW) + 3e-9, 6) AS m FROM hourly")
def moving_mean_rows(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("component").orderBy("t").rowsBetween(-5, 0)
    return rounded(data.hourly(spark, sf).select("component", "t", F.avg("x").over(w).alias("m")), "m")


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY event_type ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) + 3e-9, 6) AS m FROM events")
def moving_mean_range(spark: SparkSession, sf: str) -> DataFrame:
    events = load(spark, sf, "events").withColumn("sec", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1000000))
    w = Window.partitionBy("event_type").orderBy("sec").rangeBetween(-3600, 0)
    return rounded(events.select("event_id", F.avg("value").over(w).alias("m")), "m")


@query(f"WITH {HOURLY} SELECT component, t, x FROM hourly")
def sorted_series(spark: SparkSession, sf: str) -> DataFrame:
    """Each series in time order within its partition; no global sort."""
    return data.hourly(spark, sf).repartition("series_id", "component").sortWithinPartitions("series_id", "component", "t").select("component", "t", "x")


@query("SELECT l_suppkey, l_orderkey, l_linenumber, l_quantity FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_suppkey ORDER BY l_quantity DESC, l_orderkey, l_linenumber) <= 3")
def topk_series(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("l_suppkey").orderBy(F.desc("l_quantity"), "l_orderkey", "l_linenumber")
    return load(spark, sf, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", "l_quantity", F.row_number().over(w).alias("rn")).where("rn <= 3").drop("rn")


def _two(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """Truths found by two settings of the detector; the second sees the first window only."""
    best = detect.candidates(data.injected(spark, sf), CFG.with_(points=False)).drop("k")
    true = data.truth(spark).select("series_id", "k", F.col("s").alias("ts"), F.col("e").alias("te")).distinct()
    hit = best.join(F.broadcast(true), "series_id").where("s = ts and e = te").select("k", "score")
    return hit.where("score > 0").select("k"), hit.where("score > 500").select("k")


_TWO = f"""{_INJ}, {_SCORED_INJ}, hit AS (SELECT t.k, score FROM scored s JOIN (SELECT DISTINCT k, s AS ts, e AS te FROM truth) t ON s.s = t.ts AND s.e = t.te), a AS (SELECT k FROM hit WHERE score > 0), b AS (SELECT k FROM hit WHERE score > 500)"""


@query(f"{_TWO} SELECT 'a' AS method, k FROM a UNION ALL SELECT 'b', k FROM b")
def union_methods(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _two(spark, sf)
    return a.select(F.lit("a").alias("method"), "k").unionByName(b.select(F.lit("b").alias("method"), "k"))


@query(f"{_TWO} SELECT k FROM a INTERSECT SELECT k FROM b")
def intersect_detected(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _two(spark, sf)
    return a.intersect(b)


@query(f"{_TWO} SELECT k FROM a EXCEPT ALL SELECT k FROM b")
def except_detected(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _two(spark, sf)
    return a.exceptAll(b)


@query("SELECT p_partkey, upper(p_brand) AS brand, concat_ws('/', p_type, p_size::VARCHAR) AS label, regexp_extract(p_name, '^([^ ]+)', 1) AS head, substring(p_type, 1, 4) AS short FROM part")
def label_strings(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "part").select("p_partkey", F.upper("p_brand").alias("brand"), F.concat_ws("/", "p_type", F.col("p_size").cast("string")).alias("label"), F.regexp_extract("p_name", "^([^ ]+)", 1).alias("head"), F.substring("p_type", 1, 4).alias("short"))


@query("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, weekofyear(o_orderdate)::INTEGER AS w, dayofyear(o_orderdate)::INTEGER AS j, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INTEGER AS d FROM orders")
def calendar_fields(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.weekofyear("o_orderdate").alias("w"), F.dayofyear("o_orderdate").alias("j"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("d"))


@query(f"""{_INJ}, {_SCORED_INJ}, best AS (SELECT series_id, s, e, k FROM scored WHERE score > 0 ORDER BY score DESC LIMIT 1),
parts AS (SELECT w.component, w.total / w.n AS m, row_number() OVER (ORDER BY w.total * w.total / w.n DESC, w.component) AS r, b.k FROM wins w JOIN best b USING (series_id, s, e))
SELECT string_agg(component || '=' || printf('%.4f', m), ',' ORDER BY component) AS estimates FROM parts WHERE r <= k AND abs(m) > 1""")
def estimates_map(spark: SparkSession, sf: str) -> DataFrame:
    """Component to estimate as a map, filtered, written out."""
    long = data.injected(spark, sf)
    best = detect.single_window_test(long, CFG).where("detected")
    parts = detect.affected_components(long, best, CFG).groupBy("series_id", "s", "e").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("component", "estimate")))).alias("m"))
    big = F.map_filter("m", lambda _, v: F.abs(v) > 1)
    return parts.select(F.array_join(F.transform(F.map_entries(big), lambda x: F.concat(x["key"].cast("string"), F.lit("="), F.format_string("%.4f", x["value"]))), ",").alias("estimates"))


@query(f"""{_INJ}, {_SCORED_INJ} SELECT '{{"s":' || s || ',"e":' || e || ',"k":' || k || '}}' AS doc, s::BIGINT AS s FROM scored WHERE score > 0""")
def result_json(spark: SparkSession, sf: str) -> DataFrame:
    found = detect.candidates(data.injected(spark, sf), CFG.with_(points=False)).select(F.to_json(F.struct("s", "e", "k")).alias("doc"))
    return found.select("doc", F.from_json("doc", "s bigint, e bigint, k int")["s"].alias("s"))


@query()
def normal_sf(spark: SparkSession, sf: str) -> DataFrame:
    z = spark.range(0, 81).select((F.col("id") / 10 - 4).alias("z"))
    return rounded(z.select("z", udfs.normal_sf("z").alias("upper")), "z", "upper")


@query()
def chi2_quantile(spark: SparkSession, sf: str) -> DataFrame:
    """At the shares of a hundred that the lines' quantities are."""
    upper = load(spark, sf, "lineitem").select((F.col("l_quantity") / 100).alias("upper")).distinct()
    return rounded(upper.select("upper", udfs.chi2_quantile("upper").alias("a")), "a")


@query(f"WITH {HOURLY_STD}, sq AS (SELECT series_id, t, component, x * x AS v FROM std), prices(k, price) AS (VALUES {', '.join(f'({k}, {v!r})' for k, v in enumerate(pen.composite_penalty(5, 2 * math.log(720)), 1))}), r AS (SELECT t, row_number() OVER w AS k, sum(v) OVER w AS tk FROM sq WINDOW w AS (PARTITION BY t ORDER BY v DESC, component ROWS UNBOUNDED PRECEDING)) SELECT t, round(max(tk - price) + 3e-9, 6) AS score FROM r JOIN prices USING (k) GROUP BY t")
def penalised_saving_udaf(spark: SparkSession, sf: str) -> DataFrame:
    best = udfs.penalised_saving_udaf(pen.composite_penalty(5, 2 * math.log(720)))
    return rounded(data.hourly_std(spark, sf).withColumn("v", F.col("x") * F.col("x")).groupBy("t").agg(best("v").alias("score")), "score")


@query(f"WITH {_SPANS}, {_KNOWN} SELECT t.series_id, t.k, count(p.s)::BIGINT AS hits FROM true_ t LEFT JOIN pred p ON p.series_id = t.series_id AND abs(p.s - ts) <= 20 AND abs(p.e - te) <= 20 GROUP BY ALL")
def match_cogrouped(spark: SparkSession, sf: str) -> DataFrame:
    """Predictions and truths of a series brought together in one call."""
    pred = _spans(spark, sf).select("series_id", "s", "e").distinct()
    true = _known(spark, sf).select("series_id", "k", F.col("s").alias("ts"), F.col("e").alias("te"))

    def both(p, t):
        hits = [int(((p["s"] - a).abs().le(20) & (p["e"] - b).abs().le(20)).sum()) for a, b in zip(t["ts"], t["te"], strict=True)]
        return pd.DataFrame({"series_id": t["series_id"], "k": t["k"], "hits": hits})

    return pred.groupBy("series_id").cogroup(true.groupBy("series_id")).applyInPandas(both, "series_id string, k int, hits bigint")


@query()
def udtf_detect(spark: SparkSession, sf: str) -> DataFrame:
    """The table function from SQL, partitioned by series."""
    udfs.register(spark)
    to_wide(data.injected(spark, sf, points=True)).createOrReplaceTempView("collanom_wide")
    return rounded(spark.sql("SELECT * FROM detect_windows(TABLE(collanom_wide) PARTITION BY series_id ORDER BY t)"), "score")


@query(f"WITH {HOURLY} SELECT component, count(*) AS n, max(x) AS top FROM hourly GROUP BY component")
def sql_views(spark: SparkSession, sf: str) -> DataFrame:
    data.hourly(spark, sf).createOrReplaceTempView("collanom_series")
    return spark.sql("SELECT component, count(*) AS n, max(x) AS top FROM collanom_series GROUP BY component")


@query(f"WITH {injected_sql()}, q AS (SELECT t, round(sum(x * x) + 3e-9, 6) AS v FROM inj GROUP BY t) SELECT a.t, (SELECT max(b.v) FROM q b WHERE b.t = a.t + 1) > a.v AS rising FROM q a WHERE a.t < 720")
def sql_best_end(spark: SparkSession, sf: str) -> DataFrame:
    """A common table expression with a correlated scalar subquery, which Spark turns into a join."""
    data.injected(spark, sf).createOrReplaceTempView("collanom_inj")
    return spark.sql("WITH q AS (SELECT t, round(sum(x * x) + 3e-9, 6) AS v FROM collanom_inj GROUP BY t) SELECT a.t, (SELECT max(b.v) FROM q b WHERE b.t = a.t + 1) > a.v AS rising FROM q a WHERE a.t < 720")


@query("""WITH d AS (SELECT lang, source, doc_id, n_chars FROM documents) SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM d GROUP BY ALL""")
def document_profile(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query(f"WITH {HOURLY_STD} SELECT component, round(corr(x, t) + 3e-9, 6) AS trend, round(var_samp(x) + 3e-9, 6) AS v FROM std GROUP BY component")
def residual_spread(spark: SparkSession, sf: str) -> DataFrame:
    """Whether scaling left unit spread and no trend: what the unit-variance assumption needs."""
    return rounded(data.hourly_std(spark, sf).groupBy("component").agg(F.corr("x", "t").alias("trend"), F.var_samp("x").alias("v")), "trend", "v")


__all__ = ["relational"]
