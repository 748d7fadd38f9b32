"""Worked examples, invariants and edge cases of layouts, joins, measures and the cost model."""

import io
import math
from contextlib import redirect_stdout

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilewright import costmodel, measures
from tilewright.functions.curves import with_curve_key
from tilewright.functions.geometry import Box, require_boxes, split_invalid
from tilewright.functions.sql import register_functions
from tilewright.functions import wkt
from tilewright.functions.wkt import rings_meet
from tilewright.operators import route, tilejoin
from tilewright.plans import kernels, methods, sampling, twolevel
from tilewright.plans.layout import payload_of
from tilewright.sources import fixtures
from tilewright.streaming import tileload


def loads(boxes, layout):
    return [r.payload for r in measures.payloads(route.explode_tiles(boxes, layout), layout).orderBy("tile_id").collect()]


def test_grid_side_is_the_rounded_up_root(spark):
    boxes = fixtures.rows(spark, [(i, i, i, i, i) for i in range(100)])
    assert methods.plan_fixed_grid(boxes, 30).count == 4


def test_four_tiles(spark):
    boxes = fixtures.toy_four_tiles(spark)
    layout = methods.plan_fixed_grid(boxes, cells=2)
    assert loads(boxes, layout) == [3, 3, 6, 3]
    assert measures.quality(boxes, layout).first()["lambda"] == pytest.approx(0.25)


def test_strip_counts(spark):
    boxes = fixtures.toy_strip(spark)
    live, fresh = (methods.plan_strip(boxes, 2, count=c) for c in ("live", "fresh"))
    assert [t.xmax for t in live.rows()] == [5, 6, 8.5, 11] and loads(boxes, live) == [3, 3, 3, 2]
    assert [t.xmax for t in fresh.rows()] == [5, 8.5, 11] and loads(boxes, fresh) == [3, 4, 2]


def test_split_axis_with_the_more_even_areas():
    b = np.array([[2, 2, 2, 2]] * 3 + [[2, 1, 2, 1], [1, 2, 1, 2]], float)
    tiles = kernels.split_tree(b, Box(0, 0, 10, 4), 4, max_depth=1)
    assert sorted(t[:4] for t in tiles) == [(0, 0, 10, 2), (0, 2, 10, 4)]


@pytest.mark.parametrize("curve", ["hilbert", "z", "gray"])
def test_curves_are_bijective(spark, curve):
    u = Box(0, 0, 8, 8)
    cells = fixtures.rows(spark, [(8 * i + j, i + 0.5, j + 0.5, i + 0.5, j + 0.5) for i in range(8) for j in range(8)])
    rows = with_curve_key(cells, u, curve, 3).orderBy("curve_key").collect()
    assert [r.curve_key for r in rows] == list(range(64))
    if curve == "hilbert":
        assert all(abs(a.xmin - b.xmin) + abs(a.ymin - b.ymin) == 1 for a, b in zip(rows, rows[1:]))


def test_hilbert_of_four_cells_and_its_sql_form(spark):
    register_functions(spark)
    u = Box(0, 0, 2, 2)
    cells = fixtures.rows(spark, [(0, 0.5, 0.5, 0.5, 0.5), (1, 0.5, 1.5, 0.5, 1.5), (2, 1.5, 1.5, 1.5, 1.5), (3, 1.5, 0.5, 1.5, 0.5)])
    assert [r.curve_key for r in with_curve_key(cells, u, "hilbert", 1).orderBy("id").collect()] == [0, 1, 2, 3]
    wide = Box(0, 0, 256, 256)
    spots = fixtures.rows(spark, [(k, (37 * k) % 256, (91 * k) % 256, (37 * k) % 256, (91 * k) % 256) for k in range(200)])
    keyed = with_curve_key(spots, wide, "hilbert", 8)
    keyed.createOrReplaceTempView("spots")
    assert spark.sql("SELECT count(*) FROM spots WHERE hilbert2d(CAST(xmin AS BIGINT), CAST(ymin AS BIGINT)) <> curve_key").first()[0] == 0
    got = spark.sql("SELECT s.id, t.tile_id FROM spots s, LATERAL tiles_of(xmin, ymin, xmax, ymax, 0D, 0D, 256D, 256D, 4) t")
    assert got.count() == 200


def test_cost_model():
    assert costmodel.join_cost(1000, 1000, 100, 0.1, 2) == pytest.approx(16100)
    k, alpha = costmodel.uniform_optimum(0.01)
    assert (k, alpha) == (pytest.approx(1e4), pytest.approx(3))
    best = min(range(1, 400), key=lambda m: (1 + costmodel.uniform_alpha(0.01, m * m)) ** 2 / (m * m))
    assert best == 100
    assert costmodel.makespan([5, 3, 3, 3], 2) == 8 and payload_of(0.01, 15000) == 150 and payload_of(0.00001, 600000) == 6


@pytest.mark.parametrize("method", list(methods.PLANS))
def test_layouts_cover_and_account(spark, sf, method):
    boxes = fixtures.skew_boxes(spark, sf).persist()
    layout = methods.PLANS[method](boxes, 50, **({"max_cross": 0.5} if method == "binary" else {}))
    u = layout.universe
    assigned = route.explode_tiles(boxes, layout)
    assert assigned.select("id").distinct().count() == 1000 and assigned.groupBy("id", "tile_id").count().filter("count > 1").isEmpty()
    q = measures.quality(boxes, layout).first()
    assert q["total"] == assigned.count() and q["lambda"] == pytest.approx(q["total"] / 1000 - 1) and q["lambda"] >= 0
    if layout.kind == "tiling":
        area = sum((t.xmax - t.xmin) * (t.ymax - t.ymin) for t in layout.rows())
        assert area == pytest.approx(u.width * u.height)
    else:
        assert route.with_home(boxes, layout).filter("home_tile is null").isEmpty()
        assert all(t.planned <= 50 for t in layout.rows()) and layout.count == math.ceil(1000 / 50)
    r, s = fixtures.halves(boxes)
    want = {tuple(x) for x in tilejoin.brute_force(r, s).collect()}
    assert len(want) == 311
    for how in ({}, {"assign": "single"}, {"assign": "one_sided"}, {"dedup": "distinct"}):
        got = [tuple(x) for x in tilejoin.join(r, s, layout, **how).collect()]
        assert len(got) == len(set(got)) and set(got) == want, how


def test_points_have_one_tile(spark, sf):
    boxes = fixtures.diag_points(spark, sf)
    assert measures.quality(boxes, methods.plan_fixed_grid(boxes, 10)).first()["lambda"] == 0
    assert measures.quality(boxes, methods.plan_strip(boxes, 10)).first()["lambda"] == 0


def test_repeatable_whatever_the_partitions(spark, sf):
    boxes = fixtures.even_boxes(spark, sf)
    plans = (lambda b: methods.plan_curve_pack(b, 40), lambda b: methods.plan_sort_tile(b, 40), lambda b: methods.plan_least_cut_strip(b, 200))
    for plan in plans:
        assert [tuple(t) for t in plan(boxes).rows()] == [tuple(t) for t in plan(boxes.repartition(7)).rows()]


def test_edge_cases(spark):
    none = fixtures.rows(spark, [(0, 0, 0, 1, 1)]).filter("id > 0")
    one = fixtures.rows(spark, [(0, 1, 1, 1, 1)])
    equal = fixtures.rows(spark, [(i, 1, 2, 3, 4) for i in range(20)])
    for name, plan in methods.PLANS.items():
        for boxes, n in ((one, 1), (equal, 20)):
            layout = plan(boxes, 3)
            assert route.explode_tiles(boxes, layout).select("id").distinct().count() == n, name
        plan(none, 3).rows()
    assert methods.plan_binary_split(equal, 1).count == 1


def test_incremental_split_and_quad(spark, sf):
    boxes = fixtures.even_boxes(spark, sf)
    for layout in (methods.plan_binary_split(boxes, 100, order="incremental"), methods.plan_quad_split(boxes, 200), methods.plan_binary_split(boxes, 100, cut="approx")):
        u = layout.universe
        assert sum((t.xmax - t.xmin) * (t.ymax - t.ymin) for t in layout.rows()) == pytest.approx(u.width * u.height)


def test_brackets_find_the_exact_median(spark):
    rng = np.random.default_rng(6)
    values = {1: rng.normal(0, 100, 3001), 2: np.r_[np.full(900, 7.0), rng.integers(0, 50, 300)], 3: rng.integers(0, 3, 700).astype(float), 4: np.array([5.0])}
    rows = [(k, float(v), 0.0, float(v), 1.0) for k, vs in values.items() for v in vs]
    work = spark.createDataFrame(rows, "node long, xmin double, ymin double, xmax double, ymax double")
    got = methods.bracketed_medians(work, {k: len(v) for k, v in values.items()}, "x", enough=100)
    assert got == {k: np.sort(v)[(len(v) - 1) // 2] for k, v in values.items()}


def test_binary_split_by_brackets_is_the_same(spark, sf, monkeypatch):
    boxes = fixtures.skew_boxes(spark, sf)
    want = [tuple(r) for r in methods.plan_binary_split(boxes, 60, max_cross=0.5).rows()]
    monkeypatch.setattr(methods, "BRACKETS_ABOVE", 100)
    monkeypatch.setattr(methods.bracketed_medians, "__defaults__", (100,))
    assert [tuple(r) for r in methods.plan_binary_split(boxes, 60, max_cross=0.5).rows()] == want


def test_strips_at_any_number_of_coordinates(spark, sf, monkeypatch):
    boxes = fixtures.skew_boxes(spark, sf)
    want = {c: [tuple(r) for r in methods.plan_strip(boxes, 79, count=c).rows()] for c in ("live", "fresh")}
    b = methods.arrays_of(boxes)
    for c in want:
        assert [r[1:5] for r in want[c]] == [t[:4] for t in kernels.strips(b, methods.extent_of(boxes)[0], 79, count=c)]
    monkeypatch.setattr(methods, "MOST_CUT_CANDIDATES", 50)
    assert [tuple(r) for r in methods.plan_strip(boxes, 79, count="fresh").rows()] == want["fresh"]
    with pytest.raises(ValueError, match="quantiles"):
        methods.plan_strip(boxes, 79)
    # Quantiles keep real weights: strips stay near the payload.
    loads_q = loads(boxes, methods.plan_strip(boxes, 79, quantiles=400))
    assert abs(len(loads_q) - len(want["live"])) <= 0.2 * len(want["live"])


def test_ranks_part_equal_values(spark):
    from tilewright.plans.ranks import global_rank, with_interval

    df = spark.range(5000).select("id", F.when(F.col("id") % 3 > 0, 7.0).otherwise(F.col("id").cast("double")).alias("v"))
    got = [r["rank"] for r in global_rank(df, "v", "id", parts=8).orderBy("v", "id").collect()]
    assert got == list(range(5000))
    cuts = sorted({float(x) for x in range(0, 5000, 41)})
    for n in (0, 5, len(cuts)):
        at = with_interval(df, "v", cuts[:n], "at")
        assert all(r["at"] == sum(c <= r["v"] for c in cuts[:n]) for r in at.limit(200).collect())


def test_nearest_tiles():
    rng = np.random.default_rng(7)
    low = rng.uniform(0, 100, (300, 2))
    tiles = np.c_[low, low + rng.uniform(0, 30, (300, 2)) ** 1.2]
    x, y = rng.uniform(-20, 140, (2, 500))
    dx = np.maximum(0, np.maximum(tiles[:, 0] - x[:, None], x[:, None] - tiles[:, 2]))
    dy = np.maximum(0, np.maximum(tiles[:, 1] - y[:, None], y[:, None] - tiles[:, 3]))
    assert sampling.nearest_tiles(tiles, x, y).tolist() == (dx * dx + dy * dy).argmin(axis=1).tolist()


def test_optimal_strips_beat_all_others():
    rng = np.random.default_rng(5)
    near = rng.integers(0, 60, 14).astype(float)
    far = near + rng.integers(0, 20, 14)
    centres = (near + far) / 2
    _, load = kernels.optimal_1d(kernels.Sorted(centres), kernels.Sorted(far), kernels.Sorted(near), 3)
    spots = np.unique(centres)
    best = min(
        max(int(((near < hi) & (far >= lo)).sum()) for lo, hi in zip((-np.inf, a, b), (a, b, np.inf))) for a in spots for b in spots if a < b
    )
    assert load == best


def test_samples(spark, sf):
    boxes = fixtures.skew_boxes(spark, sf)
    full, all_of_it = methods.plan_strip(boxes, 100), sampling.sampled_layout(boxes, 100, "strip", ratio=1.0)
    assert [tuple(t) for t in full.rows()] == [tuple(t) for t in all_of_it.rows()]
    with pytest.raises(ValueError, match="uncovered"):
        sampling.sampled_layout(boxes, 100, "hilbert", ratio=0.1)
    assert sampling.fixed_sample(boxes, 10).count() == 10


def test_one_bucket_is_the_single_layout(spark, sf):
    boxes = fixtures.skew_boxes(spark, sf)
    a, b = methods.plan_least_cut_strip(boxes, 100), twolevel.two_level(boxes, 100, "least_cut", coarse=2000)
    assert sorted(t[1:5] for t in map(tuple, a.rows())) == sorted(t[1:5] for t in map(tuple, b.rows()))
    assert measures.layout_agreement(boxes, a, b).first()["agreement"] == pytest.approx(1)


def test_bad_boxes(spark):
    inf, nan = float("inf"), float("nan")
    bad = spark.createDataFrame(
        [(1, 0.0, 0.0, 1.0, 1.0), (2, None, 0.0, 1.0, 1.0), (3, nan, 0.0, 1.0, 1.0), (4, 0.0, 0.0, inf, 1.0), (5, 2.0, 0.0, 1.0, 1.0), (None, 0.0, 0.0, 1.0, 1.0)],
        "id long, xmin double, ymin double, xmax double, ymax double",
    )
    good, rejected = split_invalid(bad)
    assert [r.id for r in good.collect()] == [1] and rejected.count() == 5
    with pytest.raises(ValueError):
        require_boxes(bad)
    with pytest.raises(ValueError, match="repeat"):
        require_boxes(good.unionByName(good))


def explained(df) -> str:
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_plan_shape(spark, sf):
    r, s = fixtures.halves(fixtures.even_boxes(spark, sf))
    plan = explained(tilejoin.join(r, s, methods.plan_joint(r, s, "strip", 50)))
    assert "BroadcastNestedLoopJoin" not in plan and "CartesianProduct" not in plan
    assert "ReadSchema: struct<o_orderkey" in plan and "o_comment" not in plan


def test_diamonds():
    a = np.array([[0, 1], [1, 0], [2, 1], [1, 2], [0, 1]], float)
    assert rings_meet(a, a + [2, 0]) and not rings_meet(a, a + [1.6, 1.6]) and rings_meet(a, (a - [1, 1]) / 4 + [1, 1])


def test_stream_equals_batch(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    layout = methods.plan_fixed_grid(tileload.event_points(events), cells=8)
    events.orderBy("ts").coalesce(1).write.option("maxRecordsPerFile", 300).parquet(str(tmp_path / "in"))
    points = tileload.event_points(tileload.replay(spark, str(tmp_path / "in"), events.schema))
    q = tileload.tile_load(points, layout, late="40 days").writeStream.format("memory").queryName("tile_load").outputMode("complete").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    batch = tileload.tile_load(tileload.event_points(events), layout)
    assert sorted(map(tuple, spark.table("tile_load").collect())) == sorted(map(tuple, batch.collect()))


def test_late_points_are_counted(spark, sf):
    points = tileload.event_points(spark.read.parquet(f"{sf}/events.parquet"))
    late = points.withColumn("ts", F.when(F.col("id") % 97 == 0, F.col("ts") - F.expr("INTERVAL 40 DAYS")).otherwise(F.lit("2024-02-01").cast("timestamp")))
    assert tileload.late_share(late).first()["late"] >= 9


def test_least_cut_over_any_axes(spark, sf):
    boxes = fixtures.skew_boxes(spark, sf)
    b = methods.arrays_of(boxes)
    u = methods.extent_of(boxes)[0]
    plane = kernels.peel(b, u, 40)
    flat = boxes.select("id", F.array("xmin", "ymin", F.lit(0.0)).alias("lo"), F.array("xmax", "ymax", F.lit(1.0)).alias("hi"))
    got = methods.least_cut_axes(flat, 40).orderBy("tile_id").collect()
    assert [(*r.lo[:2], *r.hi[:2], r.planned) for r in got] == plane
    # With three real axes the strips part the space and hold about the payload each.
    rng = np.random.default_rng(1)
    near = rng.uniform(0, 100, (500, 3))
    tiles = kernels.peel_axes(near, near + rng.uniform(0, 2, (500, 3)), [0, 0, 0], [102, 102, 102], 50)
    assert sum(np.prod(np.subtract(h, l)) for l, h, _ in tiles) == pytest.approx(102**3) and all(n <= 50 for *_, n in tiles) and len(tiles) >= 9


def test_incremental_split_box_by_box(spark):
    """Against a version that keeps every leaf's boxes in plain lists."""
    rng = np.random.default_rng(2)
    low = rng.integers(0, 60, (80, 2)).astype(float)
    b = np.c_[low, low + rng.integers(0, 6, (80, 2))]
    region = Box(*b[:, :2].min(0), *b[:, 2:].max(0))
    leaves = [((region.xmin, region.ymin, region.xmax, region.ymax), [])]

    def meets(t, x):
        return x[2] >= t[0] and x[3] >= t[1] and (x[0] < t[2] or t[2] >= region.xmax) and (x[1] < t[3] or t[3] >= region.ymax)

    for x in b.tolist():
        now = []
        for t, own in leaves:
            if not meets(t, x):
                now.append((t, own))
                continue
            own = [*own, x]
            ways = []
            for d in (0, 1):
                cs = sorted((y[d] + y[d + 2]) / 2 for y in own)
                m = cs[(len(cs) - 1) // 2]
                if t[d] < m < t[d + 2]:
                    f = (m - t[d]) / (t[d + 2] - t[d])
                    ways.append((-f * (1 - f), d, m))
            if len(own) > 12 and ways:
                _, d, m = min(ways)
                one, two = list(t), list(t)
                one[d + 2] = two[d] = m
                parts = [y for y in own if y[d] < m], [y for y in own if y[d + 2] >= m]
                if all(parts) and not len(parts[0]) == len(parts[1]) == len(own):
                    now += [(tuple(h), [y for y in own if meets(h, y)]) for h in (one, two)]
                    continue
            now.append((t, own))
        leaves = now
    got = sorted(kernels.split_incremental(b, region, 12))
    assert got == sorted((*t, len(own)) for t, own in leaves)


def test_streams(spark, sf, tmp_path):
    """Overload alarms, de-duplication and loads of a replayed stream against batch counts."""
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.repartition(4, "event_id").write.parquet(str(tmp_path / "in"))
    points = tileload.event_points(events)
    layout = methods.plan_fixed_grid(points, cells=3)
    total = {r["tile_id"]: r["count"] for r in tileload.routed(points, layout).groupBy("tile_id").count().collect()}
    stream = tileload.event_points(tileload.replay(spark, str(tmp_path / "in")))

    def run(df, name, mode="append"):
        df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start().awaitTermination()
        return spark.table(name).collect()

    limit = sorted(total.values())[len(total) // 2]
    alarms = run(tileload.overloads(stream, layout, limit), "alarms")
    assert {r.tile_id for r in alarms} == {t for t, n in total.items() if n > limit} and all(r.load > limit for r in alarms)
    twice = stream.union(tileload.event_points(tileload.replay(spark, str(tmp_path / "in"))))
    assert len({r.id for r in run(tileload.distinct_objects(twice, "3650 days"), "once")}) == points.count() == spark.table("once").count()


def test_advice(spark, sf):
    r, s = fixtures.halves(fixtures.even_boxes(spark, sf))
    rows = costmodel.sweep(r, s, "grid", (0.005, 0.01, 0.05, 0.2), least=5)
    assert costmodel.advise_payload(r, s, "grid", (0.005, 0.01, 0.05, 0.2))["model"] == min(x["model"] for x in rows if x["payload"] >= 10)
    assert costmodel.makespan([5.0, 4.0, 3.0, 3.0], 2) == 8.0


def test_least_cut_over_more_boxes_than_one_group_takes(spark, sf, monkeypatch):
    """Against strips that look at all live boxes again each time."""
    boxes = fixtures.skew_boxes(spark, sf)
    b, u, payload, want = methods.arrays_of(boxes), methods.extent_of(boxes)[0], 40, []
    near, far, low, high = b[:, :2], b[:, 2:], [u.xmin, u.ymin], [u.xmax, u.ymax]
    while True:
        live = (far >= low).all(axis=1)
        found = []
        for d in (0, 1) if live.sum() > payload else ():
            c = np.sort((near[live, d] + far[live, d]) / 2)
            cut = c[payload] if c[payload] > low[d] else next(iter(c[c > low[d]]), high[d])
            if cut < high[d]:
                found.append((int((near[live, d] < cut).sum() - (far[live, d] < cut).sum()), d, float(cut)))
        if not found:
            want.append((*low, *high, int(live.sum())))
            break
        _, d, cut = min(found)
        top = [cut if k == d else high[k] for k in (0, 1)]
        want.append((*low, *top, int(((near[live, d] + far[live, d]) / 2 < cut).sum())))
        low[d] = cut
    monkeypatch.setattr(methods, "MOST_IN_ONE_TASK", 100)
    layout = methods.plan_least_cut_strip(boxes, payload)
    assert [(*r[1:5], r["planned"]) for r in layout.rows()] == want


def test_live_strips_by_ranges_of_coordinates(spark, sf, monkeypatch):
    boxes = fixtures.even_boxes(spark, sf)
    want = [tuple(r) for r in methods.plan_strip(boxes, 30, axis="y").rows()]
    assert len(want) > 30
    monkeypatch.setattr(methods, "MOST_CUT_CANDIDATES", 200)
    for axis, rows in (("y", want), ("x", None)):
        found = methods.plan_strip(boxes, 30, axis=axis, ranges=True)
        assert rows is None or [tuple(r) for r in found.rows()] == rows
        b = methods.arrays_of(boxes)
        assert [r[1:5] for r in map(tuple, found.rows())] == [t[:4] for t in kernels.strips(b, found.universe, 30, axis)]


def test_sort_tiles_of_equal_centres_follow_the_slab():
    """Eight boxes of one height in two slabs: in each, y ties go by x, as the two-level SQL ranks them, and not by id."""
    x = np.arange(8)[::-1] * 10.0
    b = np.column_stack([x, np.zeros(8), x + 1, np.ones(8)])
    tiles = kernels.sort_tiles(b, Box(0, 0, 71, 1), 2)
    assert [(t[0], t[2], t[4]) for t in tiles] == [(0, 11, 2), (20, 31, 2), (40, 51, 2), (60, 71, 2)]
    x = np.array([0.0, 30, 10, 20])
    tiles = kernels.sort_tiles(np.column_stack([x, np.zeros(4), x + 1, np.ones(4)]), Box(0, 0, 31, 1), 2)
    assert [(t[0], t[2]) for t in tiles] == [(0, 11), (20, 31)]


def test_nested_loop_by_blocks(spark, sf, monkeypatch):
    """Blocks of few boxes, against all pairs in arrays."""
    boxes = fixtures.skew_boxes(spark, sf)
    r, s = fixtures.halves(boxes)
    rows = [np.array([tuple(x) for x in side.select("id", "xmin", "ymin", "xmax", "ymax").collect()]) for side in (r, s)]
    (ri, *p), (si, *q) = (x.T for x in rows)
    p = [c[:, None] for c in p]
    dx, dy = (np.maximum(0, np.maximum(p[k] - q[k + 2], q[k] - p[k + 2])) for k in (0, 1))
    want = {
        "intersects": (p[0] <= q[2]) & (p[2] >= q[0]) & (p[1] <= q[3]) & (p[3] >= q[1]), "overlaps": (p[0] < q[2]) & (p[2] > q[0]) & (p[1] < q[3]) & (p[3] > q[1]),
        "within": (p[0] >= q[0]) & (p[2] <= q[2]) & (p[1] >= q[1]) & (p[3] <= q[3]), ("dwithin", 900.0): dx * dx + dy * dy <= 900.0**2,
    }
    monkeypatch.setattr(tilejoin, "BLOCK", 64)
    for kind, hit in want.items():
        found = tilejoin.brute_force(r, s, predicate=kind)
        assert "NestedLoop" not in found._jdf.queryExecution().executedPlan().toString() and "Cartesian" not in found._jdf.queryExecution().executedPlan().toString()
        i, j = np.nonzero(hit)
        assert sorted(map(tuple, found.collect())) == sorted(zip(ri[i].astype(int).tolist(), si[j].astype(int).tolist())) and len(i)


def test_no_broadcast_of_many_listed_tiles(spark, sf, monkeypatch):
    """A few tiles in a small file may be listed under any number of cells."""
    from tilewright import store

    boxes = fixtures.even_boxes(spark, sf)
    layout = methods.plan_sort_tile(boxes, 30)
    want = sorted(map(tuple, route.explode_tiles(boxes, layout).select("id", "tile_id").collect()))
    monkeypatch.setattr(store, "BROADCAST_ROWS", 10)
    met = route.explode_tiles(boxes, layout).select("id", "tile_id")
    assert layout.params["_listed"] > 10 and "Broadcast" not in met._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, met.collect())) == want


@pytest.mark.parametrize("bands", [1, 2, 32])
def test_middle_cuts_by_counts(spark, monkeypatch, bands):
    """As a split that moves the boxes, whether counts tell all of it, a part or nothing."""
    rng = np.random.default_rng(5)
    low = rng.integers(0, 1000, (300, 2)) / 8
    far = low + rng.integers(0, 60, (300, 2)) / 8
    boxes = fixtures.rows(spark, [(i, *a, *b) for i, (a, b) in enumerate(zip(low.tolist(), far.tolist()))]).cache()

    def split(b, box, depth):
        n, cut = len(b), None
        if n > 25 and depth < 9:
            for k in (0, 1):
                at = (box[k] + box[k + 2]) / 2
                if box[k] < at < box[k + 2]:
                    f = (at - box[k]) / (box[k + 2] - box[k])
                    if cut is None or f * (1 - f) > cut[0]:
                        cut = (f * (1 - f), k, at)
        if cut:
            _, k, at = cut
            x, y = b[b[:, k] < at], b[b[:, k + 2] >= at]
            if len(x) and len(y) and not len(x) == len(y) == n:
                one, two = list(box), list(box)
                one[k + 2] = two[k] = at
                return split(x, one, depth + 1) + split(y, two, depth + 1)
        return [(*box, n)]

    b = np.column_stack([low, far])
    want = split(b, [*low.min(0), *far.max(0)], 0)
    monkeypatch.setattr(methods, "MOST_BANDS", bands)
    got = methods.plan_binary_split(boxes, 25, cut="middle", max_depth=9).rows()
    assert sorted(tuple(r[c] for c in ("xmin", "ymin", "xmax", "ymax", "planned")) for r in got) == sorted(want)
    assert any(y0 > want[0][1] for _, y0, *_ in want) or len(want) > 8


def test_middle_cuts_move_no_box(spark, monkeypatch):
    """One edge that no cut ever frees is halved to the last level, which took a pass over all boxes each."""
    boxes = fixtures.rows(spark, [(i, *((0, 0, 301, 1000) if i % 2 else (301, 0, 1000, 1000))) for i in range(20)])
    monkeypatch.setattr(methods, "settled", lambda df: pytest.fail("a level was written") if "node" in df.columns else df)
    tiles = methods.plan_binary_split(boxes, 5, cut="middle").rows()
    assert max(r["level"] for r in tiles) == 40


def test_refined_pairs_read_each_text_once(monkeypatch):
    """Many pairs of few polygons, of several sizes, as pair by pair."""
    import pyarrow as pa

    rng = np.random.default_rng(3)

    def text(k):
        turn, c, size = np.linspace(0, 2 * np.pi, k, endpoint=False), rng.random(2) * 10, 1 + rng.random()
        ring = [(c[0] + size * math.cos(a), c[1] + size * math.sin(a)) for a in turn]
        return "POLYGON ((" + ", ".join(f"{x} {y}" for x, y in [*ring, ring[0]]) + "))"

    x, y = (pa.table({"geom": [text(3 + n % 3) for n in range(40)]}) for _ in range(2))
    i, j = (v.ravel() for v in np.meshgrid(np.arange(40), np.arange(40)))
    read, ring = [], wkt._ring
    rings = [[ring(g) for g in t.column("geom").to_pylist()] for t in (x, y)]
    monkeypatch.setattr(wkt, "_ring", lambda g: read.append(g) or ring(g))
    got = wkt.polygons_meet(x, y, i, j)
    assert len(read) == 80 and 0 < got.sum() < len(got)
    assert got.tolist() == [rings_meet(rings[0][a], rings[1][b]) for a, b in zip(i.tolist(), j.tolist())]


def test_crowded_packings_get_finer_lookup_cells(spark):
    """Nearly all tiles in one corner of the universe: cells are halved, and each box meets its tiles as before."""
    spots = [(k, k % 20 * 3.0, k // 20 * 3.0) for k in range(400)]
    boxes = fixtures.rows(spark, [*((k, x, y, x + 1, y + 1) for k, x, y in spots), (400, 9000, 9000, 9001, 9001)]).cache()
    layout = methods.plan_curve_pack(boxes, 4)
    met = {(r["id"], r["tile_id"]) for r in route.explode_tiles(boxes, layout).collect()}
    assert layout.params["_cells"] > route._lookup_cells(layout.count)
    tiles, found = layout.rows(), set()
    for k, *b in (tuple(r) for r in boxes.collect()):
        found |= {(k, t["tile_id"]) for t in tiles if b[0] <= t["xmax"] and b[2] >= t["xmin"] and b[1] <= t["ymax"] and b[3] >= t["ymin"]}
    assert met == found
