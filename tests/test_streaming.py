"""The online detector and the streams."""

from __future__ import annotations

import math

import numpy as np

from collanom.config import DetectorConfig
from collanom.operators import detect
from collanom.operators.blocks import best_chain
from collanom.queries import data
from collanom.queries.streams import stream_detect_closed
from collanom.streaming.stream import OnlineDetector


def test_stream_equals_batch_for_closed_islands(spark, sf):
    cfg = DetectorConfig(l=2, m=20, psi=2 * math.log(720))
    batch = {(r["s"], r["e"], round(r["score"], 5), r["kind"]) for r in detect.detect(data.injected(spark, sf, points=True), cfg).chosen.collect() if r["e"] <= 700}
    assert {(r["s"], r["e"], r["score"], r["kind"]) for r in stream_detect_closed(spark, sf).collect()} == batch


def test_any_batching_gives_the_same():
    rng = np.random.default_rng(5)
    x = rng.normal(size=(200, 3))
    x[50:60, :2] += 3
    x[120, 1] += 9
    cfg = DetectorConfig(m=15, psi=6.0)
    rows = [(t + 1, x[t].tolist()) for t in range(200)]
    found = []
    for size in (1, 7, 200):
        own, out = OnlineDetector(cfg, 200), []
        for at in range(0, 200, size):
            part = rows[at : at + size]
            out += own.feed(part[::-1] + part[:1])
        found.append([(s, e, round(v, 9), k) for s, e, v, k in out])
        assert len(own.rows) <= 15
    assert found[0] == found[1] == found[2] and len(found[0]) >= 2
    assert best_chain([])[0] == 0.0
