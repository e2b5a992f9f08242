"""A hand-made example: nine cells, one split, all four cases."""

from __future__ import annotations

import math

import pytest
from pyspark.sql import functions as F

from tileaqp.plans.baselines import ExactTileIndex, SampleOnlyIndex
from tileaqp.plans.engine import evaluate
from tileaqp.plans.geometry import Domain, with_codes
from tileaqp.plans.index import Stats, TileIndex
from tileaqp.plans.estimators import moment_columns, moments_of
from tileaqp.plans.model import KEY_SPACE, Agg, IndexConfig, SamplingPolicy, Viewport, ViewportQuery

ROWS = [
    (1, 12, 12, 10, 0.35), (2, 15, 15, 12, 0.55), (3, 18, 11, 14, 0.20), (4, 21, 12, 5, 0.10), (5, 22, 13, 7, 0.20), (6, 24, 15, 9, 0.60), (7, 25, 18, 11, 0.80), (8, 27, 14, 100, 0.05),
    (9, 11, 6, 4, 0.15), (10, 12, 7, 8, 0.30), (11, 13, 8, 2, 0.70), (12, 14, 9, 6, 0.90), (13, 16, 3, 20, 0.40), (14, 18, 4, 22, 0.50), (15, 17, 1, 50, 0.25), (16, 12, 2, 60, 0.45),
    (17, 5, 5, 70, 0.5), (18, 3, 15, 80, 0.5), (19, 8.5, 20.5, 90, 0.5), (20, 15, 25, 91, 0.5), (21, 26, 22, 92, 0.5), (22, 28, 5, 93, 0.5),
]
WINDOW = Viewport(9, 25, 3, 21)
# the key of object 14 is exactly one half: a limit of one half leaves it out, as u < 0.5 says, but small strata are read whole
POLICY = SamplingPolicy(rate0=0.5, floor=2, pooled_floor=2, exhaust_below=2)


def query(bound: float, fn: str = "sum") -> ViewportQuery:
    return ViewportQuery(WINDOW, (Agg(fn, "v"),), bound)


@pytest.fixture
def index(spark):
    domain = Domain(Viewport(0, 30, 0, 30), 3, 3)
    rows = spark.createDataFrame([(float(x), float(y), float(v), int(u * KEY_SPACE)) for _, x, y, v, u in ROWS], "ax double, ay double, v double, rkey long")
    objects = with_codes(rows, domain).coalesce(2)
    out = TileIndex(objects, domain, IndexConfig(grid=(3, 3), split_min=6))
    got = {r["root"]: r.asDict() for r in objects.groupBy("root").agg(F.count("*").alias("n"), *moment_columns("v")).collect()}
    for r in range(9):
        t = out.add(0, r, 0, 1 << 30, got[r]["n"] if r in got else 0)
        if r in got:
            out.stats[t.tile_id, "v"] = Stats(KEY_SPACE, moments_of(got[r], "v"))
    return out


def test_one_round(index):
    r = evaluate(index, query(0.10), POLICY)
    a = r.answers[0]
    assert (r.pop, r.io_ops, r.rounds) == (13, 6, 1)
    assert a.estimate == pytest.approx(126) and (a.ci_low, a.ci_high) == (pytest.approx(113.6041, abs=1e-4), pytest.approx(138.3959, abs=1e-4))
    assert a.eps_est == pytest.approx(0.098380, abs=1e-6)
    kept = {index.tiles[t].depth: s for (t, _), s in index.stats.items() if index.tiles[t].depth == 1}
    assert kept[1].moments.n == 2 and kept[1].moments.mean == 6 and kept[1].moments.m2 == 8 and kept[1].theta == KEY_SPACE // 2
    assert len([1 for (t, _) in index.stats if index.tiles[t].depth == 1]) == 1  # partial parts aren't kept
    again = evaluate(index, query(0.10), POLICY)
    assert again.io_ops == 4 and again.answers[0].estimate == pytest.approx(126)
    tighter = evaluate(index, query(0.05), POLICY)
    assert tighter.io_ops == 8 and tighter.answers[0].estimate == pytest.approx(130) and tighter.answers[0].exact


def test_mean_has_the_same_error(index):
    r = evaluate(index, query(0.10, "mean"), POLICY)
    assert r.answers[0].estimate == pytest.approx(126 / 13) and r.answers[0].eps_est == pytest.approx(0.098380, abs=1e-6)


def test_tighter_bound_from_the_start(index):
    r = evaluate(index, query(0.05), POLICY)
    assert (r.io_ops, r.rounds) == (10, 2) and r.answers[0].exact and r.answers[0].estimate == pytest.approx(130)


def test_exact_methods(index):
    r = ExactTileIndex(index).evaluate(query(0.10))
    assert r.io_ops == 10 and r.answers[0].estimate == pytest.approx(130) and r.answers[0].ci_low == r.answers[0].ci_high


def test_extreme(index):
    r = evaluate(index, query(0.10, "max"), POLICY)
    assert r.answers[0].estimate == 22 and r.io_ops == 10


def test_sample_only(index):
    r = SampleOnlyIndex(index, POLICY).evaluate(query(0.10))
    assert r.io_ops == 13 and r.rounds == 2 and r.answers[0].estimate == pytest.approx(130)
    assert r.round_log[0]["new_reads"] == 7 and r.round_log[0]["eps_est"] == pytest.approx(math.sqrt(436) * 1.959964 / 124, abs=1e-6)
