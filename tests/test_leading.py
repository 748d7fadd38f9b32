"""Joins on the least tile in common of a packing: what is routed, and what comes out."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilewright import queries as q
from tilewright.functions.geometry import BOX
from tilewright.operators import route, tilejoin
from tilewright.plans import methods, twolevel
from tilewright.sources import fixtures


def crowded(spark, n=3000, seed=3):
    """Boxes whose centres share few x, so that the tiles of many buckets lie over each other."""
    rng = np.random.default_rng(seed)
    x, y, w, h = rng.integers(0, 40, n) * 1000, rng.integers(0, 400_000, n), rng.integers(1, 8, n) * 500, rng.integers(1, 12, n) * 300
    w[:5], h[:5] = 30_000, 200_000
    return fixtures.rows(spark, [(i, a - c, b - d, a + c, b + d) for i, (a, b, c, d) in enumerate(zip(x, y, w, h))])


def pairs_of(boxes):
    b = np.array(sorted(tuple(r) for r in boxes.select("id", *BOX).collect()))
    r, s = b[b[:, 0] % 2 == 0], b[b[:, 0] % 2 == 1]
    meet = (r[:, None, 1] <= s[:, 3]) & (r[:, None, 3] >= s[:, 1]) & (r[:, None, 2] <= s[:, 4]) & (r[:, None, 4] >= s[:, 2])
    i, j = np.nonzero(meet)
    return sorted(zip(r[i, 0].astype(int).tolist(), s[j, 0].astype(int).tolist()))


@pytest.mark.parametrize("local", ["nested", "sweep"])
def test_crowded_packing(spark, local):
    """Few of the tiles that a box meets are routed, and all pairs come out once."""
    boxes = crowded(spark).persist()
    layout = twolevel.two_level(boxes, 15, "sort_tile", coarse=75)
    found = tilejoin.join(*fixtures.halves(boxes), layout, local=local)
    assert sorted(map(tuple, found.collect())) == pairs_of(boxes)
    routed = route.leading_tiles(boxes, layout).count()
    assert 2 * routed < route.explode_tiles(boxes, layout).count()


def test_too_many_tiles_for_a_broadcast(spark, monkeypatch):
    boxes = crowded(spark, 400).persist()
    layout = methods.plan_sort_tile(boxes, 10)
    monkeypatch.setattr(route, "BROADCAST_ROWS", 3)
    assert sorted(map(tuple, tilejoin.join(*fixtures.halves(boxes), layout).collect())) == pairs_of(boxes)


def test_boxes_that_no_tile_holds(spark):
    """After sampling a packing may hold some boxes in part or not at all; those that meet in a tile are pairs."""
    boxes = crowded(spark, 600).persist()
    layout = methods.plan_sort_tile(boxes.filter("id % 7 = 0"), 5)
    lists = {r["id"]: set(r["t"]) for r in route.explode_tiles(boxes, layout).groupBy("id").agg(F.collect_set("tile_id").alias("t")).collect()}
    want = [p for p in pairs_of(boxes) if lists.get(p[0], set()) & lists.get(p[1], set())]
    assert sorted(map(tuple, tilejoin.join(*fixtures.halves(boxes), layout).collect())) == want


@pytest.mark.parametrize("name", ["sampled_hilbert_keyrange_skew", "twolevel_sorttile_even"])
def test_boxes_are_made_once(spark, sf, name):
    """The join reads written boxes: it neither orders the events again nor groups by id for the lists of tiles."""
    plan = q.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in plan and "collect_set" not in plan
