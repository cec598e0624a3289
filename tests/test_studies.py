"""The studies are registered at the published sizes."""

from __future__ import annotations

import inspect

from collanom import workloads
from collanom.queries import QUERIES


def test_studies_have_the_published_sizes(spark, monkeypatch):
    seen = []

    def record(kind):
        def study(session, number, p, points, replicates, n, m, rate):
            seen.append((kind, number, p, points, n, m, rate))
            return session.range(1)

        return study

    monkeypatch.setattr(workloads, "roc_study", record("roc"))
    monkeypatch.setattr(workloads, "location_study", record("location"))
    for name in QUERIES:
        if "_roc_setting" in name or "_location_setting" in name:
            QUERIES[name](spark, "")
    want = [(kind, number, p, points, 5000, 100, 0.001) for kind in ("roc", "location") for number in (1, 2, 3, 4) for p in (10, 100) for points in (False, True)]
    assert sorted(seen) == sorted(want)


def test_catalogue_has_the_published_lags(spark, sf, monkeypatch):
    default = {k: v.default for k, v in inspect.signature(workloads.catalogue_study).parameters.items()}
    assert default["m"] == 100 and default["lags"] == (0, 40)
    asked = {}
    monkeypatch.setattr(workloads, "catalogue_study", lambda session, folder, **more: asked.update(more))
    QUERIES["w14_catalogue"](spark, sf)
    assert not asked


def test_location_keeps_no_plans_and_no_cache(spark):
    """A row a method comes from a written table: the searches' plans and caches are gone."""
    long, truth, s = workloads.simulated(spark, 3, 5, False, 1, 600, rate=0.01)
    spark.catalog.clearCache()
    out = workloads.location_of(long, truth, 600, 20, s["alpha0"], (0, 5))
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "MapInArrow" not in plan and "Aggregate" not in plan
    assert [r["method"] for r in out.collect()] == ["detector w=0", "detector w=5", "higher criticism", "sparse projection"]


def test_chunks_are_not_joined_in_one_task(spark):
    from collanom.config import DetectorConfig
    from collanom.operators import detect, simulate

    long = simulate.noise(spark, 5000, 4)
    cfg = DetectorConfig(m=50)
    sizes = detect.known_sizes(long)
    assert detect.with_halo(long, sizes, cfg, detect.chunk_rows(cfg, 4)).rdd.getNumPartitions() == 10
