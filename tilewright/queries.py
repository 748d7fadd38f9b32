"""The registered queries: every method, variant, baseline and measure on its fixture, with SQL for each."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import costmodel, measures, oracles, store
from .functions.geometry import BOX, Box, universe
from .functions.wkt import boxes_of_wkt, diamond_wkt, geometry_type, polygons_meet
from .operators import query as staged_query
from .operators import route, tilejoin
from .plans import methods, sampling, twolevel
from .plans.layout import Layout, payload_of
from .sources import fixtures
from .store import shared_folder
from .streaming import tileload

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _tiles(layout: Layout) -> DataFrame:
    return layout.tiles.select("tile_id", *BOX, "planned")


def _quality(boxes: DataFrame, layout: Layout) -> DataFrame:
    q = measures.quality(boxes, layout)
    return q.select("k", "objects", "total", F.round("lambda", 6).alias("lambda"), F.round("sigma", 6).alias("sigma"), "largest", F.round("largest_to_mean", 6).alias("largest_to_mean"), "empty")


PAYLOAD = {"even": 150, "skew": 100, "skew_wide": 100, "span": 40}


def _universe(fixture: str) -> None:
    @register(f"universe_{fixture}", oracles.universe(fixture))
    def run(spark: SparkSession, d: str) -> DataFrame:
        boxes = fixtures.FIXTURES[fixture](spark, d)
        return boxes.agg(F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax"), F.count(F.lit(1)).alias("n"))


for _f in ("even", "skew", "skew_wide", "span", "line"):
    _universe(_f)


def _grid(fixture: str) -> None:
    b = PAYLOAD[fixture]

    @register(f"grid_payload_{fixture}", f"WITH {oracles.base(fixture)}, {oracles.grid(b)}, {oracles.GRID_ROUTED}, {oracles.LOADS} SELECT tile_id, payload FROM p")
    def loads(spark: SparkSession, d: str) -> DataFrame:
        boxes = fixtures.FIXTURES[fixture](spark, d)
        layout = methods.plan_fixed_grid(boxes, b)
        return measures.payloads(route.explode_tiles(boxes, layout), layout)

    @register(f"grid_quality_{fixture}", oracles.quality(fixture, oracles.grid(b), oracles.GRID_ROUTED))
    def quality(spark: SparkSession, d: str) -> DataFrame:
        boxes = fixtures.FIXTURES[fixture](spark, d)
        return _quality(boxes, methods.plan_fixed_grid(boxes, b))


for _f in ("even", "skew", "span"):
    _grid(_f)


@register("grid1000_skew", f"""WITH {oracles.base('skew')}, {oracles.grid(cells=1000)}, {oracles.GRID_ROUTED}, {oracles.LOADS}
SELECT count(*) AS k, max(payload) AS largest, round(max(payload) / avg(payload), 6) AS largest_to_mean FROM p""")
def grid1000_skew(spark: SparkSession, d: str) -> DataFrame:
    """Skew of a million equal tiles."""
    boxes = fixtures.skew_boxes(spark, d)
    layout = methods.plan_fixed_grid(boxes, cells=1000)
    q = measures.quality(boxes, layout)
    return q.select("k", "largest", F.round("largest_to_mean", 6).alias("largest_to_mean"))


@register("grid_assign_toy", f"WITH {oracles.base('even')}, {oracles.grid(cells=2)}, {oracles.ROUTED} SELECT id, tile_id FROM a")
def grid_assign_toy(spark: SparkSession, d: str) -> DataFrame:
    """All even boxes with the tiles of a two by two grid that they meet; the SQL compares them with each tile."""
    boxes = fixtures.even_boxes(spark, d)
    return route.explode_tiles(boxes, methods.plan_fixed_grid(boxes, cells=2)).select("id", "tile_id")


def _layout(name: str, fixture: str, sql: str, plan: Callable[[DataFrame], Layout], closed: bool | None = False) -> None:
    """name: the tiles of a plan; name with quality in place of tiles: its measures."""

    @register(name, oracles.tiles(fixture, sql))
    def tiles(spark: SparkSession, d: str) -> DataFrame:
        return _tiles(plan(fixtures.FIXTURES[fixture](spark, d)))

    if closed is not None:
        @register(f"quality_{name}", oracles.quality(fixture, sql, oracles.ROUTED_CLOSED if closed else oracles.ROUTED))
        def quality(spark: SparkSession, d: str) -> DataFrame:
            boxes = fixtures.FIXTURES[fixture](spark, d)
            return _quality(boxes, plan(boxes))


_layout("binary_tiles_even", "even", oracles.binary(150, 11), lambda b: methods.plan_binary_split(b, 150))
_layout("binary_tiles_skew", "skew", oracles.binary(500, 14), lambda b: methods.plan_binary_split(b, 500))
_layout("binary_middle_even", "even", oracles.binary(1000, 14, "middle"), lambda b: methods.plan_binary_split(b, 1000, cut="middle"), None)
_layout("quad_tiles_skew", "skew", oracles.quad(1000, 12), lambda b: methods.plan_quad_split(b, 1000), None)
_layout("strip_x_even", "even", oracles.strip(150), lambda b: methods.plan_strip(b, 150))
_layout("strip_x_skew", "skew", oracles.strip(100), lambda b: methods.plan_strip(b, 100))
_layout("strip_y_even", "even", oracles.strip(150, "y"), lambda b: methods.plan_strip(b, 150, axis="y", ranges=True), None)
_layout("strip_fresh_skew", "skew", oracles.strip(100, count="fresh"), lambda b: methods.plan_strip(b, 100, count="fresh"))
_layout("strip_fresh_even", "even", oracles.strip(150, count="fresh"), lambda b: methods.plan_strip(b, 150, count="fresh"))
_layout("leastcut_tiles_even", "even", oracles.least_cut(1000, 18), lambda b: methods.plan_least_cut_strip(b, 1000))
_layout("leastcut_tiles_skew", "skew", oracles.least_cut(1000, 14), lambda b: methods.plan_least_cut_strip(b, 1000))
_layout("leastcut_tiles_skew_wide", "skew_wide", oracles.least_cut(1000, 14), lambda b: methods.plan_least_cut_strip(b, 1000), None)
_layout("hilbert_tiles_even", "even", oracles.curve_pack(150), lambda b: methods.plan_curve_pack(b, 150), True)
_layout("hilbert_tiles_skew", "skew", oracles.curve_pack(100), lambda b: methods.plan_curve_pack(b, 100), True)
_layout("zcurve_tiles_even", "even", oracles.curve_pack(150, "z"), lambda b: methods.plan_curve_pack(b, 150, curve="z"), None)
_layout("gray_tiles_even", "even", oracles.curve_pack(150, "gray"), lambda b: methods.plan_curve_pack(b, 150, curve="gray"), None)
_layout("sorttile_tiles_even", "even", oracles.sort_tile(150), lambda b: methods.plan_sort_tile(b, 150), True)
_layout("sorttile_tiles_skew", "skew", oracles.sort_tile(100), lambda b: methods.plan_sort_tile(b, 100), True)
_layout("sorttile_even_fill", "even", oracles.sort_tile_even(150), lambda b: methods.plan_sort_tile(b, 150, fill="even"), None)
_layout("grid_nonsquare_even", "even", oracles.grid_xy(12, 7), lambda b: methods.plan_fixed_grid(b, cells=(12, 7)), False)
_layout("hilbert_order8_even", "even", oracles.curve_pack(150, order=8), lambda b: methods.plan_curve_pack(b, 150, order=8), None)
_layout("twolevel_grid_tiles_even", "even", oracles.grid(150), lambda b: twolevel.two_level(b, 150, "grid"), None)
_layout("twolevel_hilbert_tiles_even", "even", oracles.curve_pack(150), lambda b: twolevel.two_level(b, 150, "hilbert"), None)
ANCHORS = [0.0, 600_000.0, 1_200_000.0]
_layout("twolevel_sorttile_tiles_even", "even", oracles.sort_tile_in_buckets(150, ANCHORS), lambda b: twolevel.two_level(b, 150, "sort_tile", cuts=ANCHORS), True)
_layout("sorttile_slab_even", "even", oracles.sort_tile(150, "slab"), lambda b: methods.plan_sort_tile(b, 150, edges="slab"), None)

SWEEP = [
    (name, b, make(b), routed)
    for b in (300, 750, 1500)
    for name, make, routed in (
        ("grid", oracles.grid, oracles.GRID_ROUTED), ("strip", oracles.strip, oracles.ROUTED), ("binary", lambda b: oracles.binary(b, 9), oracles.ROUTED),
        ("hilbert", oracles.curve_pack, oracles.ROUTED_CLOSED), ("sort_tile", oracles.sort_tile, oracles.ROUTED_CLOSED),
    )
] + [("least_cut", 1500, oracles.least_cut(1500, 13), oracles.ROUTED)]


def _sweep_sql(fixture: str, sweep: list) -> str:
    return " UNION ALL ".join(
        f"SELECT '{m}' AS method, {b} AS payload, k, \"lambda\", sigma FROM (WITH RECURSIVE {oracles.base(fixture)}, {sql}, {routed}, {oracles.LOADS} {oracles.QUALITY})" for m, b, sql, routed in sweep
    )


def _swept(boxes: DataFrame, sweep: list) -> DataFrame:
    boxes, out = boxes.persist(), None
    for m, b, *_ in sweep:
        q = _quality(boxes, methods.PLANS[m](boxes, b)).select(F.lit(m).alias("method"), F.lit(b).alias("payload"), "k", "lambda", "sigma")
        out = q if out is None else out.unionByName(q)
    return out


@register("quality_sweep", _sweep_sql("even", SWEEP))
def quality_sweep(spark: SparkSession, d: str) -> DataFrame:
    """lambda and sigma of the methods over payloads."""
    return _swept(fixtures.even_boxes(spark, d), SWEEP)


SWEEP_SKEW = [x for x in SWEEP if x[0] not in ("binary", "least_cut") and x[1] < 1500]


@register("quality_sweep_skew", _sweep_sql("skew", SWEEP_SKEW))
def quality_sweep_skew(spark: SparkSession, d: str) -> DataFrame:
    return _swept(fixtures.skew_boxes(spark, d), SWEEP_SKEW)


@register("advice_even", f"""WITH q AS MATERIALIZED ({_sweep_sql("even", SWEEP)})
SELECT payload, 'sigma' AS criterion, arg_min(method, sigma) AS method FROM q GROUP BY payload UNION ALL SELECT payload, 'lambda', arg_min(method, "lambda") FROM q GROUP BY payload""")
def advice_even(spark: SparkSession, d: str) -> DataFrame:
    """The method of least sigma and of least lambda per payload."""
    q = store.settled(_swept(fixtures.even_boxes(spark, d), SWEEP))
    best = [q.groupBy("payload").agg(F.min_by("method", c).alias("method")).select("payload", F.lit(c).alias("criterion"), "method") for c in ("sigma", "lambda")]
    return best[0].unionByName(best[1])


_SIX = {"grid": oracles.grid(4), "binary": oracles.binary(4, 8), "strip": oracles.strip(4), "least_cut": oracles.least_cut(4, 16), "hilbert": oracles.curve_pack(4), "sort_tile": oracles.sort_tile(4)}


@register("layouts_of_32", " UNION ALL ".join(
    f"SELECT '{m}' AS method, * FROM (WITH RECURSIVE b AS MATERIALIZED (SELECT * FROM ({oracles.EVEN}) ORDER BY id LIMIT 32), {oracles.U}, {sql} {oracles.TILES})" for m, sql in _SIX.items()))
def layouts_of_32(spark: SparkSession, d: str) -> DataFrame:
    """The six layouts of 32 boxes, four to a tile."""
    boxes, out = fixtures.toy_32(spark, d).persist(), None
    for m in _SIX:
        t = _tiles(methods.PLANS[m](boxes, 4)).select(F.lit(m).alias("method"), "*")
        out = t if out is None else out.unionByName(t)
    return out


def _join(name: str, fixture: str, method: str, payload: int, sql: str | None = None, plan: dict | None = None, **opts) -> None:
    @register(name, sql or oracles.join(fixture))
    def run(spark: SparkSession, d: str) -> DataFrame:
        r, s = fixtures.halves(fixtures.FIXTURES[fixture](spark, d))
        return tilejoin.join(r, s, methods.plan_joint(r, s, method, payload, **(plan or {})), **opts)


_join("join_grid_even", "even", "grid", 150)
_join("join_grid_skew_wide", "skew_wide", "grid", 100)
_join("join_binary_skew", "skew", "binary", 500)
_join("join_binary_guarded_skew", "skew", "binary", 100, plan={"max_cross": 0.5})
_join("join_strip_even", "even", "strip", 150)
_join("join_leastcut_skew", "skew", "least_cut", 500)
_join("join_hilbert_even", "even", "hilbert", 150)
_join("join_sorttile_skew", "skew", "sort_tile", 100)
_join("join_distinct_even", "even", "grid", 150, dedup="distinct")
_join("join_single_assign_even", "even", "grid", 150, assign="single")
_join("join_single_assign_packing", "skew", "sort_tile", 100, assign="single")
_join("join_one_sided_skew", "skew", "strip", 100, assign="one_sided")
_join("join_one_sided_packing", "even", "hilbert", 150, assign="one_sided")
_join("join_sweep_even", "even", "grid", 500, local="sweep")
_join("join_sweep_packing", "even", "sort_tile", 500, local="sweep")
_join("join_subgrid_even", "even", "grid", 500, local="subgrid")
_join("join_dwithin_even", "even", "grid", 150, oracles.join("even", oracles.within_distance(2000.0)), predicate=("dwithin", 2000.0))
_join("join_within_skew", "skew", "grid", 100, oracles.join("skew", oracles.CONTAINS.replace("r.", "q.").replace("s.", "r.").replace("q.", "s.")), predicate="within")
_join("join_overlaps_even", "even", "strip", 150, oracles.join("even", oracles.MEET.replace("=", "")), predicate="overlaps")


@register("join_brute_force_even", oracles.join("even"))
def join_brute_force_even(spark: SparkSession, d: str) -> DataFrame:
    return tilejoin.brute_force(*fixtures.halves(fixtures.even_boxes(spark, d)))


@register("join_contains_span", oracles.join("span", oracles.CONTAINS))
def join_contains_span(spark: SparkSession, d: str) -> DataFrame:
    r, s = fixtures.halves(fixtures.span_boxes(spark, d))
    return tilejoin.join(r, s, methods.plan_joint(r, s, "grid", 40), predicate="contains")


@register("self_join_span", oracles.self_join("span"))
def self_join_span(spark: SparkSession, d: str) -> DataFrame:
    boxes = fixtures.span_boxes(spark, d)
    return tilejoin.self_join(boxes, methods.plan_fixed_grid(boxes, 200))


@register("type_join_skew", oracles.join("skew", r="event_type IN ('view', 'click')", s="event_type NOT IN ('view', 'click')"))
def type_join_skew(spark: SparkSession, d: str) -> DataFrame:
    boxes = fixtures.typed_skew_boxes(spark, d)
    chosen = F.col("event_type").isin("view", "click")
    r, s = boxes.filter(chosen).drop("event_type"), boxes.filter(~chosen).drop("event_type")
    return tilejoin.join(r, s, methods.plan_joint(r, s, "sort_tile", 100), assign="one_sided")


@register("partners_top_skew", f"SELECT r_id, count(*) AS partners FROM ({oracles.join('skew')}) GROUP BY r_id ORDER BY partners DESC, r_id LIMIT 20")
def partners_top_skew(spark: SparkSession, d: str) -> DataFrame:
    r, s = fixtures.halves(fixtures.skew_boxes(spark, d))
    return tilejoin.match_counts(tilejoin.join(r, s, methods.plan_joint(r, s, "strip", 200)), 20)


@register("lonely_boxes_even", f"SELECT count(*) AS lonely FROM ({oracles.EVEN}) b WHERE id % 2 = 0 AND id NOT IN (SELECT r_id FROM ({oracles.join('even')}))")
def lonely_boxes_even(spark: SparkSession, d: str) -> DataFrame:
    r, s = fixtures.halves(fixtures.even_boxes(spark, d))
    pairs = tilejoin.join(r, s, methods.plan_joint(r, s, "grid", 150))
    return tilejoin.with_matches(r, pairs, matched=False).agg(F.count(F.lit(1)).alias("lonely"))


_RS = "ra AS (SELECT * FROM a WHERE id % 2 = 0), sa AS (SELECT * FROM a WHERE id % 2 = 1)"


@register("dup_pairs_grid", f"""WITH {oracles.base('skew')}, {oracles.grid(100)}, {oracles.GRID_ROUTED}, {_RS},
f AS (SELECT ra.id AS r_id, sa.id AS s_id, count(*) AS n FROM ra JOIN sa USING (tile_id) JOIN b r ON r.id = ra.id JOIN b s ON s.id = sa.id WHERE {oracles.MEET} GROUP BY 1, 2)
SELECT CAST(sum(n) AS BIGINT) AS found, count(*) AS pairs, CAST(sum(n - 1) AS BIGINT) AS repeats FROM f""")
def dup_pairs_grid(spark: SparkSession, d: str) -> DataFrame:
    r, s = fixtures.halves(fixtures.skew_boxes(spark, d))
    return tilejoin.duplicate_stats(r, s, methods.plan_joint(r, s, "grid", 100))


@register("realised_cost_skew", f"""WITH {oracles.base('skew')}, {oracles.grid(100)}, {oracles.GRID_ROUTED}, {_RS},
c AS (SELECT t.tile_id, coalesce(r.n, 0) AS r_n, coalesce(s.n, 0) AS s_n FROM t LEFT JOIN (SELECT tile_id, count(*) AS n FROM ra GROUP BY 1) r USING (tile_id) LEFT JOIN (SELECT tile_id, count(*) AS n FROM sa GROUP BY 1) s USING (tile_id))
SELECT CAST(sum(r_n * s_n) AS BIGINT) AS work, max(r_n * s_n) AS largest, CAST(sum(r_n * s_n) + 2 * sum(r_n + s_n) AS DOUBLE) AS cost FROM c""")
def realised_cost_skew(spark: SparkSession, d: str) -> DataFrame:
    r, s = fixtures.halves(fixtures.skew_boxes(spark, d))
    return costmodel.realised(r, s, methods.plan_joint(r, s, "grid", 100), 2.0)


@register("cost_model_sweep", f"""WITH n AS (SELECT CAST(count(*) FILTER (id % 2 = 0) AS DOUBLE) AS r, CAST(count(*) FILTER (id % 2 = 1) AS DOUBLE) AS s FROM ({oracles.EVEN}))
SELECT k, alpha, r, s, (1 + alpha) * (1 + alpha) * r * s / k + 2.0::DOUBLE * (r + s) AS cost
FROM n, (SELECT unnest([1, 10, 100, 1000, 10000]) AS k), (SELECT unnest([0.0::DOUBLE, 0.1::DOUBLE, 0.5::DOUBLE]) AS alpha)""")
def cost_model_sweep(spark: SparkSession, d: str) -> DataFrame:
    """The closed model of a join of the even boxes' halves, over tiles and replicated shares."""
    n = fixtures.even_boxes(spark, d).agg(*(F.count_if(F.col("id") % 2 == i).cast("double").alias(c) for i, c in enumerate("rs")))
    rows = spark.createDataFrame([(k, a) for k in (1, 10, 100, 1000, 10000) for a in (0.0, 0.1, 0.5)], "k int, alpha double")
    return n.join(rows, F.lit(True)).select("k", "alpha", "r", "s", costmodel.join_cost_column("r", "s", "k", "alpha", 2.0).alias("cost"))


@register("boundary_objects_span", f"""WITH {oracles.base('span')}, {oracles.grid(40)}, {oracles.GRID_ROUTED}, m AS (SELECT id, count(*) AS n FROM a GROUP BY id)
SELECT count(*) FILTER (n > 1) AS boundary_objects, count(*) AS objects, count(*) FILTER (n > 1) / count(*) AS share, max(n) AS most_tiles FROM m""")
def boundary_objects_span(spark: SparkSession, d: str) -> DataFrame:
    boxes = fixtures.span_boxes(spark, d)
    return measures.boundary_objects(route.explode_tiles(boxes, methods.plan_fixed_grid(boxes, 40)))


WINDOW = Box(500_000.0, 200_000.0, 900_000.0, 900_000.0)


@register("window_query_even", f"SELECT id, xmin, ymin, xmax, ymax FROM ({oracles.EVEN}) WHERE xmin <= {WINDOW.xmax} AND xmax >= {WINDOW.xmin} AND ymin <= {WINDOW.ymax} AND ymax >= {WINDOW.ymin}")
def window_query_even(spark: SparkSession, d: str) -> DataFrame:
    import uuid

    boxes = fixtures.even_boxes(spark, d)
    layout = methods.plan_fixed_grid(boxes, 150)
    path = f"{shared_folder(spark)}/staged/{uuid.uuid4().hex}"
    route.stage(boxes, layout, path, 16)
    return staged_query.window_query(staged_query.read_staged(spark, path), layout, WINDOW, 16)


@register("knn_even", f"""SELECT id, dx * dx + dy * dy AS d2 FROM (SELECT id, greatest(0, xmin - 700000.0, 700000.0 - xmax) AS dx, greatest(0, ymin - 500000.0, 500000.0 - ymax) AS dy FROM ({oracles.EVEN}))
ORDER BY d2, id LIMIT 25""")
def knn_even(spark: SparkSession, d: str) -> DataFrame:
    boxes = fixtures.even_boxes(spark, d)
    return staged_query.nearest(boxes, methods.plan_sort_tile(boxes, 150), 700_000.0, 500_000.0, 25)


@register("twolevel_strip_even", f"WITH {oracles.base('even')} SELECT n AS objects, n AS covered, 1.0::DOUBLE AS area_share FROM u")
def twolevel_strip_even(spark: SparkSession, d: str) -> DataFrame:
    """The union of per-bucket strips covers the universe once: objects, objects with a tile, area."""
    boxes = fixtures.even_boxes(spark, d)
    layout = twolevel.two_level(boxes, 150, "strip", coarse=2000)
    u = layout.universe
    area = layout.tiles.agg(F.round(F.sum((F.col("xmax") - F.col("xmin")) * (F.col("ymax") - F.col("ymin"))) / (u.width * u.height), 6).alias("area_share"))
    covered = route.explode_tiles(boxes, layout).agg(F.count_distinct("id").alias("covered"))
    return boxes.agg(F.count(F.lit(1)).alias("objects")).join(covered, F.lit(True)).join(area, F.lit(True))


def _twolevel(name: str, fixture: str, method: str, payload: int, coarse: int, anchor: str, **opts) -> None:
    @register(name, oracles.join(fixture))
    def run(spark: SparkSession, d: str) -> DataFrame:
        boxes = store.settled(fixtures.FIXTURES[fixture](spark, d))  # read several times
        layout = twolevel.two_level(boxes, payload, method, coarse=coarse, anchor=anchor, **opts)
        return tilejoin.join(*fixtures.halves(boxes), layout)


_twolevel("twolevel_join_skew", "skew", "least_cut", 100, 2500, "x")
_twolevel("twolevel_binary_skew", "skew", "binary", 200, 2500, "x", max_cross=0.5)
_twolevel("twolevel_sorttile_even", "even", "sort_tile", 150, 4000, "x")
_twolevel("twolevel_strip_hilbert_even", "even", "strip", 150, 4000, "hilbert")


def _sample_tiles(name: str, fixture: str, method: str, payload: int, every: int, make: Callable[[str], str]) -> None:
    """The tiles of the layout of the boxes whose id is divisible by `every`."""

    @register(name, f"WITH RECURSIVE {oracles.sampled_base(fixture, every)}, {make(oracles.scaled(payload))} {oracles.TILES}")
    def run(spark: SparkSession, d: str) -> DataFrame:
        boxes = fixtures.FIXTURES[fixture](spark, d)
        return _tiles(sampling.sampled_layout(boxes, payload, method, sample=boxes.filter(F.col("id") % every == 0)))


_sample_tiles("sample_strip_skew", "skew", "strip", 100, 20, oracles.strip)
_sample_tiles("sample_binary_even", "even", "binary", 500, 4, lambda b: oracles.binary(b, 9))

RATIOS = (20, 10, 4, 1)


@register("sampling_quality_even", " UNION ALL ".join(
    f"SELECT '{m}' AS method, {e} AS every, k, \"lambda\", sigma FROM (WITH RECURSIVE {oracles.sampled_base('even', e)}, {make(oracles.scaled(500))}, {oracles.ROUTED_ALL}, {oracles.LOADS} {oracles.QUALITY_ALL})"
    for e in RATIOS for m, make in (("strip", oracles.strip), ("binary", lambda b: oracles.binary(b, 9)))))
def sampling_quality_even(spark: SparkSession, d: str) -> DataFrame:
    """lambda and sigma of all boxes in layouts of ever larger samples."""
    boxes, out = fixtures.even_boxes(spark, d).persist(), None
    for e in RATIOS:
        for m in ("strip", "binary"):
            layout = sampling.sampled_layout(boxes, 500, m, sample=boxes.filter(F.col("id") % e == 0))
            q = _quality(boxes, layout).select(F.lit(m).alias("method"), F.lit(e).alias("every"), "k", "lambda", "sigma")
            out = q if out is None else out.unionByName(q)
    return out


def _sampled(name: str, fixture: str, method: str, payload: int, **opts) -> None:
    @register(name, oracles.join(fixture))
    def run(spark: SparkSession, d: str) -> DataFrame:
        boxes = store.settled(fixtures.FIXTURES[fixture](spark, d))  # read several times
        layout = sampling.sampled_layout(boxes, payload, method, **opts)
        return tilejoin.join(*fixtures.halves(boxes), layout)


_sampled("sampled_join_even", "even", "binary", 500, ratio=0.1)
_sampled("sampled_leastcut_skew", "skew", "least_cut", 500, ratio=0.1)
_sampled("sampled_hilbert_nearest_even", "even", "hilbert", 500, ratio=0.1, cover="nearest")
_sampled("sampled_hilbert_keyrange_skew", "skew", "hilbert", 500, ratio=0.1, cover="keyrange")
_sampled("sampled_slab_even", "even", "sort_tile", 500, size=1500, cover="slab")


@register("optimal_1d_even", f"WITH {oracles.base('even')} SELECT n AS objects, 12 AS most_tiles, TRUE AS no_worse FROM u")
def optimal_1d_even(spark: SparkSession, d: str) -> DataFrame:
    """The best 12 strips are never worse than 12 strips at quantiles."""
    boxes = fixtures.even_boxes(spark, d)
    best = methods.plan_optimal_1d(boxes, 12)
    plain = methods.plan_strip(boxes, payload_of(1 / 12, boxes.count()), count="fresh")
    a, b = (measures.quality(boxes, x).first() for x in (best, plain))
    return spark.createDataFrame([(a["objects"], 12, a["k"] <= 12 and (a["largest"] <= b["largest"] or b["k"] > 12))], "objects long, most_tiles int, no_worse boolean")


@register("hash_range_balance", f"WITH {oracles.base('skew')}, h AS (SELECT (row_number() OVER (ORDER BY (xmin + xmax) / 2, id) - 1) * 16 // (SELECT n FROM u) AS t FROM b) SELECT CAST(t AS INTEGER) AS tile_id, count(*) AS payload FROM h GROUP BY t")
def hash_range_balance(spark: SparkSession, d: str) -> DataFrame:
    return methods.plan_range(fixtures.skew_boxes(spark, d), 16).groupBy("tile_id").agg(F.count(F.lit(1)).alias("payload"))


@register("hash_balance_skew", f"SELECT CAST(CAST('0x' || substr(md5(CAST(id AS VARCHAR)), 1, 8) AS BIGINT) % 16 AS INTEGER) AS tile_id, count(*) AS payload FROM ({oracles.SKEW}) GROUP BY 1")
def hash_balance_skew(spark: SparkSession, d: str) -> DataFrame:
    return methods.plan_hash(fixtures.skew_boxes(spark, d), 16).groupBy("tile_id").agg(F.count(F.lit(1)).alias("payload"))


@register("optimal_1d_toy", f"""WITH b AS MATERIALIZED (SELECT * FROM ({oracles.EVEN}) ORDER BY id LIMIT 32), c AS (SELECT DISTINCT (xmin + xmax) / 2 AS c FROM b),
p AS (SELECT c1.c AS a, c2.c AS z FROM c c1 JOIN c c2 ON c1.c < c2.c)
SELECT min(greatest(l, m, r)) AS load FROM (SELECT a, z, count(*) FILTER (xmin < a) AS l, count(*) FILTER (xmin < z AND xmax >= a) AS m, count(*) FILTER (xmax >= z) AS r FROM p, b GROUP BY a, z)""")
def optimal_1d_toy(spark: SparkSession, d: str) -> DataFrame:
    """The largest load of the best three strips of 32 boxes; the SQL tries all pairs of cuts."""
    boxes = fixtures.toy_32(spark, d)
    layout = methods.plan_optimal_1d(boxes, 3)
    return measures.payloads(route.explode_tiles(boxes, layout), layout).agg(F.max("payload").alias("load"))


@register("alpha_per_tile_span", f"""WITH {oracles.base('span')}, {oracles.grid(40)}, {oracles.GRID_ROUTED},
h AS (SELECT b.id, CAST(greatest(0, least(m - 1, CAST(floor(((ymin + ymax) / 2 - y0) * m / h) AS BIGINT))) * m + greatest(0, least(m - 1, CAST(floor(((xmin + xmax) / 2 - x0) * m / w) AS BIGINT))) AS INTEGER) AS home FROM b, g)
SELECT a.tile_id, round(count(*) FILTER (a.tile_id <> h.home) / ((SELECT n FROM u) / (SELECT CAST(count(*) AS DOUBLE) FROM t)), 6) AS alpha FROM a JOIN h USING (id) GROUP BY a.tile_id""")
def alpha_per_tile_span(spark: SparkSession, d: str) -> DataFrame:
    """The share of replicas in each tile."""
    boxes = fixtures.span_boxes(spark, d)
    found = measures.replica_share_per_tile(boxes, methods.plan_fixed_grid(boxes, 40))
    return found.select("tile_id", F.round("alpha", 6).alias("alpha"))


@register("fullest_tiles_skew", f"WITH {oracles.base('skew')}, {oracles.grid(100)}, {oracles.GRID_ROUTED}, {oracles.LOADS} SELECT tile_id, payload FROM p ORDER BY payload DESC, tile_id LIMIT 10")
def fullest_tiles_skew(spark: SparkSession, d: str) -> DataFrame:
    """The ten fullest tiles."""
    boxes = fixtures.skew_boxes(spark, d)
    layout = methods.plan_fixed_grid(boxes, 100)
    return measures.fullest(measures.payloads(route.explode_tiles(boxes, layout), layout))


@register("join_difference_skew", f"SELECT 0::BIGINT AS missing, 0::BIGINT AS extra, count(*) AS pairs FROM ({oracles.join('skew')})")
def join_difference_skew(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of the tile join that the nested loop lacks, and the other way round."""
    r, s = fixtures.halves(fixtures.skew_boxes(spark, d))
    found = tilejoin.join(r, s, methods.plan_joint(r, s, "strip", 200))
    want = store.settled(tilejoin.brute_force(r, s))
    diff = tilejoin.pair_difference(found, want)
    return diff.agg(F.count_if(F.col("only_in") == "right").alias("missing"), F.count_if(F.col("only_in") == "left").alias("extra")).join(want.agg(F.count(F.lit(1)).alias("pairs")), F.lit(True))


@register("overlap_area_even", f"""WITH b AS MATERIALIZED ({oracles.EVEN}) SELECT r.id AS r_id, s.id AS s_id,
  (least(r.xmax, s.xmax) - greatest(r.xmin, s.xmin)) * (least(r.ymax, s.ymax) - greatest(r.ymin, s.ymin)) AS area FROM (SELECT * FROM b WHERE id % 2 = 0) r JOIN (SELECT * FROM b WHERE id % 2 = 1) s ON {oracles.MEET}""")
def overlap_area_even(spark: SparkSession, d: str) -> DataFrame:
    """Pairs with the area of their intersection."""
    r, s = fixtures.halves(fixtures.even_boxes(spark, d))
    return tilejoin.overlap_areas(tilejoin.join(r, s, methods.plan_joint(r, s, "grid", 150)), r, s)


@register("model_and_work_even", " UNION ALL ".join(
    f"""SELECT {c} AS cells, k, round(alpha, 6) AS alpha, round((1 + alpha) * (1 + alpha) * nr * ns / k + 2.0 * (nr + ns), 3) AS model, work, largest FROM (
WITH {oracles.base('even')}, {oracles.grid(cells=c)}, {oracles.GRID_ROUTED}, w AS (SELECT tile_id, count(*) FILTER (id % 2 = 0) AS r, count(*) FILTER (id % 2 = 1) AS s FROM a GROUP BY 1)
SELECT (SELECT count(*) FROM t) AS k, (SELECT count(*) FROM a) / (SELECT CAST(n AS DOUBLE) FROM u) - 1 AS alpha, (SELECT CAST(count(*) AS DOUBLE) FROM b WHERE id % 2 = 0) AS nr, (SELECT CAST(count(*) AS DOUBLE) FROM b WHERE id % 2 = 1) AS ns,
  CAST(sum(r * s) AS BIGINT) AS work, max(r * s) AS largest FROM w)""" for c in (4, 8, 16, 32)))
def model_and_work_even(spark: SparkSession, d: str) -> DataFrame:
    """The closed model beside the comparisons that a nested tile join makes, over grids."""
    boxes = fixtures.even_boxes(spark, d).persist()
    r, s = fixtures.halves(boxes)
    nr, ns, rows = r.count(), s.count(), []
    for cells in (4, 8, 16, 32):
        layout = methods.plan_fixed_grid(boxes, cells=cells)
        alpha = measures.quality(boxes, layout).first()["lambda"]
        done = costmodel.realised(r, s, layout).first()
        rows.append((cells, layout.count, alpha, costmodel.join_cost(nr, ns, layout.count, alpha, 2.0), done["work"], done["largest"]))
    found = spark.createDataFrame(rows, "cells int, k long, alpha double, model double, work long, largest long")
    return found.withColumns({"alpha": F.round("alpha", 6), "model": F.round("model", 3)})


@register("wkt_roundtrip", f"SELECT id, 'POLYGON' AS kind, xmin, ymin, xmax, ymax FROM ({oracles.EVEN})")
def wkt_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    text = diamond_wkt(fixtures.even_boxes(spark, d)).select("id", "geom")
    return boxes_of_wkt(text).select("id", geometry_type().alias("kind"), *BOX)


@register("refined_join_even", f"""WITH p AS ({oracles.join('even')}), b AS ({oracles.EVEN}),
q AS (SELECT r_id, s_id, (r.xmin + r.xmax) / 2 AS rx, (r.ymin + r.ymax) / 2 AS ry, (r.xmax - r.xmin) / 2 AS ra, (r.ymax - r.ymin) / 2 AS rb, (s.xmin + s.xmax) / 2 AS sx, (s.ymin + s.ymax) / 2 AS sy, (s.xmax - s.xmin) / 2 AS sa, (s.ymax - s.ymin) / 2 AS sb
  FROM p JOIN b r ON r.id = r_id JOIN b s ON s.id = s_id),
v AS (SELECT *, [(sx - sa, sy), (sx, sy - sb), (sx + sa, sy), (sx, sy + sb)] AS sv, [(rx - ra, ry), (rx, ry - rb), (rx + ra, ry), (rx, ry + rb)] AS rv FROM q)
SELECT r_id, s_id FROM v WHERE
  -- two convex diamonds are apart iff an edge normal of one separates them
  abs(rx - sx) * rb + abs(ry - sy) * ra <= ra * rb + greatest(sa * rb, sb * ra) AND abs(rx - sx) * sb + abs(ry - sy) * sa <= sa * sb + greatest(ra * sb, rb * sa)""")
def refined_join_even(spark: SparkSession, d: str) -> DataFrame:
    """Box join, with the exact test on the polygons' text of each tile's pairs."""
    r, s = fixtures.halves(diamond_wkt(fixtures.even_boxes(spark, d)))
    return tilejoin.join(r, s, methods.plan_joint(r, s, "grid", 150), local="sweep", refine=polygons_meet)


@register("stream_tile_load", """WITH p AS (SELECT CAST(CAST(ts AS DATE) AS TIMESTAMP) AS window_start, CAST(hour(ts) * 60 + minute(ts) AS DOUBLE) AS x, round(value * 100) AS y FROM events),
u AS (SELECT min(x) AS x0, min(y) AS y0, max(x) - min(x) AS w, max(y) - min(y) AS h FROM p)
SELECT window_start, CAST(least(7, CAST(floor((y - y0) * 8 / h) AS BIGINT)) * 8 + least(7, CAST(floor((x - x0) * 8 / w) AS BIGINT)) AS INTEGER) AS tile_id, count(*) AS load FROM p, u GROUP BY 1, 2""")
def stream_tile_load(spark: SparkSession, d: str) -> DataFrame:
    """The streaming plan over the whole table as a batch."""
    points = tileload.event_points(fixtures.read(spark, d, "events"))
    layout = methods.plan_fixed_grid(points, cells=8)
    return tileload.tile_load(points, layout, "1 day").withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


_POINTS = """p AS (SELECT event_id AS id, ts, CAST(hour(ts) * 60 + minute(ts) AS DOUBLE) AS x, round(value * 100) AS y FROM events),
u AS (SELECT min(x) AS x0, min(y) AS y0, max(x) - min(x) AS w, max(y) - min(y) AS h FROM p),
q AS (SELECT id, ts, CAST(least(1, CAST(floor((y - y0) * 2 / h) AS BIGINT)) * 2 + least(1, CAST(floor((x - x0) * 2 / w) AS BIGINT)) AS INTEGER) AS tile_id FROM p, u)"""


@register("session_load", f"""WITH {_POINTS}, s AS (SELECT tile_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY tile_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM q),
g AS (SELECT tile_id, ts, sum(new) OVER (PARTITION BY tile_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM s)
SELECT min(ts) AS session_start, max(ts) + INTERVAL 30 MINUTE AS session_end, tile_id, count(*) AS load FROM g GROUP BY tile_id, k""")
def session_load(spark: SparkSession, d: str) -> DataFrame:
    """Sessions of activity per tile, the streaming plan as a batch."""
    points = tileload.event_points(fixtures.read(spark, d, "events"))
    found = tileload.session_load(points, methods.plan_fixed_grid(points, cells=2))
    return found.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("session_start", "session_end")})


@register("late_points", """SELECT count(*) FILTER (floor(epoch(top)) - floor(epoch(ts)) > 3600) AS late, count(*) AS points FROM (
SELECT ts, max(ts) OVER (ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM events)""")
def late_points(spark: SparkSession, d: str) -> DataFrame:
    """Points over an hour behind the latest before them, in order of arrival."""
    return tileload.late_share(tileload.event_points(fixtures.read(spark, d, "events")), bin_ids=100)


@register("latest_layout_even", f"WITH {oracles.base('even')}, {oracles.grid(cells=5)} SELECT 2 AS version, tile_id, xmin, ymin, xmax, ymax FROM t")
def latest_layout_even(spark: SparkSession, d: str) -> DataFrame:
    """Of two versions of a layout, the newer one."""
    boxes = fixtures.even_boxes(spark, d)
    old, new = (methods.plan_fixed_grid(boxes, cells=c).tiles.withColumn("version", F.lit(v)) for v, c in ((1, 4), (2, 5)))
    return tileload.latest_layouts(old.unionByName(new))


@register("balance_cube", f"""WITH {oracles.base('even')}, {oracles.grid(150)}, {oracles.GRID_ROUTED}, {oracles.LOADS}
SELECT tile_id // 10 AS band, payload > 150 AS over, count(*) AS tiles, CAST(sum(payload) AS BIGINT) AS objects FROM p GROUP BY CUBE (tile_id // 10, payload > 150)""")
def balance_cube(spark: SparkSession, d: str) -> DataFrame:
    """A sweep-style report over all combinations of two groupings."""
    boxes = fixtures.even_boxes(spark, d)
    layout = methods.plan_fixed_grid(boxes, 150)
    p = measures.payloads(route.explode_tiles(boxes, layout), layout)
    p = p.select(F.floor(F.col("tile_id") / 10).cast("int").alias("band"), (F.col("payload") > 150).alias("over"), "payload")
    return p.cube("band", "over").agg(F.count(F.lit(1)).alias("tiles"), F.sum("payload").alias("objects"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Skewed boxes joined by parity over a sampled, boundary-optimised layout."""
    boxes = fixtures.skew_boxes(spark, sf_dir)
    layout = sampling.sampled_layout(boxes, 100, "least_cut", size=20_000)
    return tilejoin.join(*fixtures.halves(boxes), layout)


register("flagship_join_skew", oracles.join("skew"))(flagship)
