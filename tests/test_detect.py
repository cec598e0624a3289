"""Plans of the detector: equal results, invariances, edges."""

from __future__ import annotations

import math

import pytest
from pyspark.sql import functions as F

from collanom.config import DetectorConfig
from collanom.operators import baseline, calibrate, detect, evaluate, relational, simulate
from collanom.operators.blocks import best_chain, greedy_chain
from collanom.operators.tiles import tiled_candidates
from collanom.plans import choose
from collanom.queries import data
from collanom.sources import explode_vectors

CFG = DetectorConfig(m=30, psi=2 * math.log(300))


@pytest.fixture(scope="module")
def series(spark):
    truth = simulate.truth_frame(spark, [("0", 1, 60, 80, c, 0, 0, 2.0) for c in (1, 2)] + [("0", 2, 80, 95, 3, 0, 0, -3.0)] + [("1", 1, 200, 215, c, 0, 0, 1.5) for c in (1, 2, 3, 4)])
    return simulate.inject(simulate.noise(spark, 300, 4, 3, 4), truth, simulate.add_points(spark, 300, 4, 3, 4, 2)).persist(), truth


def chosen(result):
    return sorted((r["series_id"], r["s"], r["e"], round(r["score"], 6), r["kind"]) for r in result.collect())


def test_plans_agree(series):
    long, _ = series
    want = chosen(detect.detect(long, CFG).chosen)
    assert want and {"window", "point"} == {w[4] for w in want}
    assert chosen(detect.detect(long, CFG, "reference").chosen) == want
    assert chosen(detect.per_series(long, CFG, "pruned", cap=30)) == want


@pytest.mark.parametrize("chunk", [31, 47, 500])
def test_chunks_and_partitions_do_not_matter(series, chunk):
    long, _ = series
    want = chosen(detect.detect(long, CFG).chosen)
    assert chosen(detect.solve(detect.candidates(long.repartition(13), CFG, chunk=chunk))) == want


@pytest.mark.parametrize("cfg", [CFG.with_(w=4), CFG.with_(w=3, regime="linear", gamma=2.0), CFG.with_(regime="flat"), CFG.with_(regime="curve"), CFG.with_(cost="meanvar", l=5)])
def test_variants_agree_with_the_reference(series, cfg):
    long, _ = series
    assert chosen(detect.detect(long, cfg).chosen) == chosen(detect.detect(long, cfg, "reference").chosen)


def test_windows_and_components_are_found(series):
    long, truth = series
    result = detect.detect(long, CFG)
    matches = evaluate.match_windows(result.windows, truth, 5)
    assert matches.count() == 3
    named = {(r["series_id"], r["component"]) for r in result.affected.collect()}
    assert {("0", 1), ("0", 2), ("0", 3), ("1", 1)} <= named
    assert result.points.count() == result.point_components.select("series_id", "t").distinct().count()


def test_relational_scores_equal_the_kernel(series):
    long, _ = series
    one = long.where("series_id = '0'")
    sql = relational.penalised_saving(relational.window_savings_long(one, 2, 12), CFG.curve(300, 4)).where("score > 0")
    block = detect.candidates(one, CFG.with_(m=12, points=False))
    a = sorted((r["s"], r["e"], round(r["score"], 6), r["k"]) for r in sql.collect())
    b = sorted((r["s"], r["e"], round(r["score"], 6), r["k"]) for r in block.collect())
    assert a == b


def test_lags_are_recovered(spark):
    truth = simulate.truth_frame(spark, [("0", 1, 100, 130, c, 3 * (c - 1), 2 * (c - 1), 5.0) for c in (1, 2, 3)])
    long = simulate.inject(simulate.noise(spark, 250, 4, 1, 8), truth)
    cfg = DetectorConfig(m=50, w=6, psi=2 * math.log(250), points=False)
    result = detect.detect(long, cfg)
    got = {r["component"]: (r["s"] + r["start_lag"], r["e"] - r["end_lag"]) for r in result.affected.collect()}
    assert got == {1: (100, 130), 2: (103, 128), 3: (106, 126)}


def test_null_tables_show_nothing(spark, sf):
    assert detect.detect(data.vectors_std(spark, sf), DetectorConfig(m=60)).chosen.count() == 0
    assert detect.detect(data.hourly_std(spark, sf), DetectorConfig(m=60)).chosen.count() == 0


def test_edges(spark):
    schema = "series_id string, t bigint, component int, x double"
    none = spark.createDataFrame([], schema)
    assert detect.detect(none, CFG).chosen.count() == 0
    short = spark.createDataFrame([("a", 1, 1, 0.5)], schema)
    assert detect.detect(short, CFG).chosen.count() == 0
    one = simulate.inject(simulate.noise(spark, 200, 1, 1, 2), simulate.truth_frame(spark, [("0", 1, 50, 70, 1, 0, 0, 3.0)]))
    assert detect.detect(one, CFG.with_(points=False)).windows.count() == 1
    for broken in (one.where("t <> 100"), one.where("t not between 55 and 140"), one.unionByName(one.where("t = 7")), one.withColumn("x", F.when(F.col("t") != 60, F.col("x")))):
        with pytest.raises(Exception, match="gaps|repeated|missing"):
            detect.candidates(broken, CFG, chunk=40).collect()
    two = simulate.noise(spark, 150, 2, 1, 3)
    with pytest.raises(Exception, match="without all components"):
        detect.detect(two.where("component = 1 or t < 145"), CFG).chosen.collect()


def test_a_series_may_begin_anywhere(series):
    long, _ = series
    want = chosen(detect.detect(long, CFG).chosen)
    late = long.withColumn("t", F.col("t") + 997)
    got = [(a, s - 997, e - 997, v, k) for a, s, e, v, k in chosen(detect.detect(late, CFG).chosen)]
    assert got == want
    assert [(a, s - 997, e - 997, v, k) for a, s, e, v, k in chosen(detect.detect(late, CFG, "reference").chosen)] == want
    assert detect.detect(long, CFG, "reference").affected.count() == detect.detect(long, CFG).affected.count() > 0


@pytest.mark.parametrize("regime", ["linear", "composite"])
def test_tiles_of_components(series, regime):
    long, _ = series
    cfg = CFG.with_(regime=regime)
    near = lambda rows: [(*r[:3], round(r[3], 4), r[4]) for r in rows]
    assert near(chosen(detect.solve(tiled_candidates(long, cfg, tile=3).persist(), longest=30))) == near(chosen(detect.detect(long, cfg, "islands").chosen))
    with pytest.raises(ValueError, match="no lags"):
        tiled_candidates(long, CFG.with_(w=2, regime="lag"))


def test_the_planner_decides(spark):
    assert choose(DetectorConfig(m=100), 10**7, 10).programme == "islands"
    assert choose(DetectorConfig(m=5000), 5000, 10).programme == "pruned"
    assert choose(DetectorConfig(m=20), 200, 50_000).programme == "tiles"
    assert choose(DetectorConfig(m=20, w=3), 200, 50_000).programme == "islands"
    long = simulate.inject(simulate.noise(spark, 1100, 1, 1, 2), simulate.truth_frame(spark, [("0", 1, 500, 540, 1, 0, 0, 3.0)]))
    cfg = DetectorConfig(m=1200)
    assert chosen(detect.detect(long, cfg).chosen) == chosen(detect.per_series(long, cfg, "pruned"))
    found = chosen(detect.detect(long, cfg).chosen)
    assert len(found) == 1 and abs(found[0][1] - 500) <= 2 and abs(found[0][2] - 540) <= 2


def test_one_island_over_a_whole_series(spark):
    """Islands are streamed: a long one gives what the whole programme gives, with a gap between windows and at every scale."""
    import random

    rng = random.Random(5)
    rows = [(name, c, s, s + rng.randint(1, 12), rng.uniform(0.1, 5.0)) for name in "ab" for c in (1.0, 2.0) for s in sorted(rng.sample(range(2000), 700))]
    rows = [(name, c, s, e, v, "point" if e - s == 1 else "window") for name, c, s, e, v in rows]
    frame = spark.createDataFrame(rows, "series_id string, scale double, s bigint, e bigint, score double, kind string").repartition(7)
    for gap in (0, 2):
        got = detect.solve(frame, gap, by=("series_id", "scale"), longest=12).groupBy("series_id", "scale").agg(F.sum("score").alias("v")).collect()
        greedy = {(r["series_id"], r["scale"]): r["v"] for r in detect.solve(frame, gap, True, ("series_id", "scale"), 12).groupBy("series_id", "scale").agg(F.sum("score").alias("v")).collect()}
        for r in got:
            spans = [x[2:] for x in rows if x[:2] == (r["series_id"], r["scale"])]
            assert r["v"] == pytest.approx(best_chain(spans, gap)[0])
            assert greedy[r["series_id"], r["scale"]] == pytest.approx(sum(spans[i][2] for i in greedy_chain(spans, gap)))
            picked = sorted(spans[i] for i in greedy_chain(spans, gap))
            assert all(b[0] >= a[1] + (gap if b[3] == "window" else 0) for a, b in zip(picked, picked[1:], strict=False))


def test_vectors_by_rank(spark):
    rows = [(5 + 3 * i + (70_000 if i > 6 else 0), [float(i), 1.0]) for i in range(10)]
    frame = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>")
    ranked = explode_vectors(frame, ranked=True).where("component = 1").orderBy("t").collect()
    assert [(r["t"], r["x"]) for r in ranked] == [(i + 1, float(i)) for i in range(10)]


def test_truths_are_apart(spark):
    rows = simulate.truths(spark, 4000, 6, 3, 1.0, 5, 2, 3, rate=0.03).collect()
    spans = {(r["series_id"], r["k"]): (r["s"], r["e"]) for r in rows}
    assert len(spans) > 60 and all(r["d"] + r["f"] < r["e"] - r["s"] and 0 <= r["d"] <= 5 and 0 <= r["f"] <= 5 for r in rows)
    for (name, k), (s, _) in spans.items():
        assert (name, k - 1) not in spans or spans[name, k - 1][1] <= s
    assert len(rows) == 3 * len(spans)


def test_islands_over_many_buckets(spark):
    import random

    rng = random.Random(2)
    spans = sorted({(s, s + rng.randint(1, 60)) for s in (rng.randint(0, 60_000) for _ in range(1500))})
    spans += [(s, s + 50) for s in range(20_000, 29_000, 30)]
    frame = spark.createDataFrame([("a", s, e, 1, 1.0, "window") for s, e in spans], "series_id string, s bigint, e bigint, k int, score double, kind string")
    want, first, reach = {}, None, -1
    for s, e in sorted(spans):
        if first is None or s >= reach:
            first = s
        reach = max(reach, e)
        want[s, e] = first
    got = {(r["s"], r["e"]): r["island"] for r in detect.islands(frame, longest=60).collect()}
    assert got == want
    assert len(set(want.values())) > 100


def test_scaling(spark):
    rows = [("a", t, 1, float(t % 7)) for t in range(1, 71)] + [("a", t, 2, 5.0) for t in range(1, 71)] + [("a", 1, 3, None), ("a", 2, 3, 1.0)]
    long = spark.createDataFrame(rows, "series_id string, t bigint, component int, x double")
    for how in ("iqr", "mad", "moments", "rate"):
        params = baseline.guard_scale(baseline.fit_typical(long, how))
        assert {r["component"]: r["degenerate"] for r in params.collect()}[2] is (how != "rate")
        z = baseline.standardise(long, params)
        assert z.where("x is null").count() == 0
    assert baseline.fit_typical(long, "iqr", approximate=True).count() == 3


def test_critical_scale_is_exact(spark):
    null = simulate.noise(spark, 200, 5, 4, 21)
    cfg = DetectorConfig(m=25, psi=1.0)
    for row in calibrate.critical_scale(null, cfg).collect():
        one = null.where(F.col("series_id") == row["series_id"])
        assert detect.detect(one, cfg.with_(scale=row["scale"] * 1.001)).chosen.count() == 0
        assert detect.detect(one, cfg.with_(scale=row["scale"] * 0.999)).chosen.count() > 0


def test_sweep_equals_single_runs(series):
    long, _ = series
    swept = calibrate.sweep(long, CFG, [0.7, 1.4])
    for c in (0.7, 1.4):
        want = [(*r[:4], r[4]) for r in chosen(detect.detect(long, CFG.with_(scale=c)).chosen)]
        assert chosen(swept.where(F.col("scale") == c)) == want


def test_greedy_is_never_better(series):
    long, _ = series
    best = {r["series_id"]: r["objective"] for r in detect.detect(long, CFG).objective.collect()}
    for r in detect.detect(long, CFG, "greedy").objective.collect():
        assert r["objective"] <= best[r["series_id"]] + 1e-9


def test_noise_does_not_depend_on_partitions(spark):
    a = simulate.noise(spark, 50, 3).repartition(7).agg(F.sum("x"), F.sum(F.col("x") * F.col("x"))).first()
    b = simulate.noise(spark, 50, 3).coalesce(1).agg(F.sum("x"), F.sum(F.col("x") * F.col("x"))).first()
    assert a[0] == pytest.approx(b[0]) and a[1] == pytest.approx(b[1]) and 100 < a[1] < 210


def test_plan_of_scoring(spark, sf):
    """The scan reads the needed columns only; nothing is a Cartesian product."""
    frame = detect.candidates(data.hourly_std(spark, sf), DetectorConfig(m=20))
    plan = frame._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan
    assert "props" not in plan and "user_id" not in plan
