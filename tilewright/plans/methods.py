"""The layout methods as plans over distributed boxes.

Each plan_* takes boxes (id and four corners) and the payload, the wanted number of objects per
tile, and returns a Layout. The driver sees aggregates, cuts and tiles, never all objects. Where a
method is inherently sequential it runs in one task: least-cut strips over any number of boxes, at
about 120 bytes of memory each; the incremental split refuses more than `MOST_IN_ONE_TASK`. Beyond
that they scale through `sampled_layout` and `two_level`.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.curves import with_curve_key
from ..functions.geometry import BOX, Box, centre, universe as extent_of
from ..store import settled, small
from . import kernels
from .layout import Layout, make_tiles, packed
from .ranks import global_rank

MOST_IN_ONE_TASK = 5_000_000
#: Most distinct coordinates (with their counts) that the driver takes for an exact recurrence over cuts.
MOST_CUT_CANDIDATES = 2_000_000
#: Boxes of a node above which its exact median is found by narrowing brackets, not by one aggregate.
BRACKETS_ABOVE = 200_000
#: Bands of y, each with two jobs and its sorted edges, up to which middle cuts are counted and not carried out.
MOST_BANDS = 32


def _measure(boxes: DataFrame, universe: Box | None) -> tuple[Box, int]:
    u, n = extent_of(boxes)
    return universe or u, n


def plan_fixed_grid(boxes: DataFrame, payload: int | None = None, *, cells: int | tuple[int, int] | None = None, universe: Box | None = None) -> Layout:
    """mx x my equal cells (m x m of about `payload` objects unless given)."""
    u, n = _measure(boxes, universe)
    if cells is None:
        cells = max(1, math.ceil(math.sqrt(n / payload)))
    mx, my = cells if isinstance(cells, tuple) else (cells, cells)
    spark = boxes.sparkSession
    i = F.col("tile_id") % mx
    j = F.floor(F.col("tile_id") / mx)
    w, h = F.lit(u.width), F.lit(u.height)
    tiles = spark.range(mx * my).select(
        F.col("id").cast("int").alias("tile_id")
    ).select(
        "tile_id", (u.xmin + w * i / mx).alias("xmin"), (u.ymin + h * j / my).alias("ymin"),
        F.when(i == mx - 1, F.lit(u.xmax)).otherwise(u.xmin + w * (i + 1) / mx).alias("xmax"),
        F.when(j == my - 1, F.lit(u.ymax)).otherwise(u.ymin + h * (j + 1) / my).alias("ymax"),
        (i == mx - 1).alias("last_x"), (j == my - 1).alias("last_y"),
        F.lit(None).cast("long").alias("planned"), F.lit(None).cast("int").alias("level"), F.lit(None).cast("int").alias("bucket"),
    )
    return Layout("tiling", u, tiles, "fixed_grid", mx * my, {"cells": (mx, my)})


def _level_stats(work: DataFrame, cut: str) -> list:
    """Per open node: number of boxes and, for median cuts, both medians."""
    aggs = [F.count(F.lit(1)).alias("n")]
    for axis in "xy":
        if cut == "median":
            aggs.append(F.expr(f"percentile_disc(0.5) WITHIN GROUP (ORDER BY ({axis}min + {axis}max) / 2)").alias(f"m{axis}"))
        elif cut == "approx":
            aggs.append(F.percentile_approx(centre(axis), 0.5, 10_000).alias(f"m{axis}"))
        else:
            aggs.append(F.lit(None).cast("double").alias(f"m{axis}"))
    return work.groupBy("node").agg(*aggs).collect()


def bracketed_medians(work: DataFrame, sizes: dict[int, int], axis: str, enough: int = BRACKETS_ABOVE) -> dict[int, float]:
    """Exact lower medians of the centres of large nodes.

    Mergeable quantiles bracket each median, a count below the bracket moves the wanted rank, and only
    what lies inside is looked at again, until few enough centres are left for one aggregate.
    """
    spark = work.sparkSession
    inside = work.select("node", centre(axis).alias("c"))
    rank = {k: (n + 1) // 2 for k, n in sizes.items()}
    while True:
        table = spark.createDataFrame([(k, int(r), int(sizes[k])) for k, r in rank.items()], "node long, r long, n long")
        inside = inside.join(small(table.select("node"), len(rank)), "node", "left_semi")
        if max(sizes.values()) <= enough:
            break
        # The median's place among what is left, and a margin around it, as shares.
        ask = [i / 64 for i in range(65)]
        found = {r["node"]: r["q"] for r in inside.groupBy("node").agg(F.percentile_approx("c", ask, 10_000).alias("q")).collect()}
        brackets = []
        for k, q in found.items():
            at = (rank[k] - 0.5) / sizes[k] * 64
            brackets.append((k, float(q[max(0, int(at) - 1)]), float(q[min(64, int(at) + 2)])))
        table = spark.createDataFrame(brackets, "node long, low double, high double")
        joined = inside.join(small(table, len(brackets)), "node")
        counts = joined.groupBy("node").agg(F.count_if(F.col("c") < F.col("low")).alias("below"), F.count_if((F.col("c") >= F.col("low")) & (F.col("c") <= F.col("high"))).alias("n"), F.min("low").alias("low"), F.max("high").alias("high")).collect()
        flat = {r["node"]: r["low"] for r in counts if r["low"] == r["high"]}
        for r in counts:
            k = r["node"]
            if not r["below"] < rank[k] <= r["below"] + r["n"]:
                raise AssertionError("a bracket misses its median")
            rank[k], sizes[k] = rank[k] - r["below"], 1 if k in flat else r["n"]
        # Of a bracket of one value nothing but that value is needed.
        inside = joined.filter((F.col("c") >= F.col("low")) & (F.col("c") <= F.col("high"))).withColumn("flat", F.col("low") == F.col("high"))
        one = inside.filter("flat").select("node", "c").distinct()
        inside = settled(inside.filter("not flat").select("node", "c").unionByName(one))
        rank = {k: 1 if k in flat else r for k, r in rank.items()}
    table = spark.createDataFrame([(k, int(r)) for k, r in rank.items()], "node long, r long")
    lists = inside.groupBy("node").agg(F.sort_array(F.collect_list("c")).alias("cs"))  # `enough` centres at most
    return {r["node"]: r["m"] for r in lists.join(small(table, len(rank)), "node").select("node", F.get("cs", (F.col("r") - 1).cast("int")).alias("m")).collect()}


def _node_stats(work: DataFrame, cut: str, counts: dict[int, int] | None) -> list[dict]:
    """_level_stats(), with brackets for the medians of nodes known to be large."""
    large = {k: n for k, n in (counts or {}).items() if n > BRACKETS_ABOVE} if cut == "median" else {}
    if not large:
        return [r.asDict() for r in _level_stats(work, cut)]
    table = work.sparkSession.createDataFrame([(k,) for k in large], "node long")
    medians = {a: bracketed_medians(work, dict(large), a) for a in "xy"}
    out = [{"node": k, "n": n, "mx": medians["x"][k], "my": medians["y"][k]} for k, n in large.items()]
    return out + [r.asDict() for r in _level_stats(work.join(small(table, len(large)), "node", "left_anti"), cut)]


def _choice(box: Box, middle: dict[str, float]) -> tuple[str, float] | None:
    """The axis and place of a cut inside box, of two places, that leaves the more even areas, x on ties."""
    choice = None
    for axis in "xy":
        lo, hi, at = box.low(axis), box.high(axis), middle[axis]
        if lo < at < hi:
            f = (at - lo) / (hi - lo)
            if choice is None or f * (1 - f) > choice[0]:
                choice = (f * (1 - f), axis, float(at))
    return choice and choice[1:]


def _middle(box: Box) -> dict[str, float]:
    return {a: (box.low(a) + box.high(a)) / 2 for a in "xy"}


def _middle_bands(boxes: DataFrame, u: Box, n: int, payload: int, max_depth: int, max_cross: float | None) -> tuple[list[tuple], dict[int, tuple[Box, int, int]]]:
    """Middle cuts by counts alone: the leaves, and the nodes (box, depth, count) that lie in too many bands for it.

    Nodes between the same cuts on y are a band. Of the boxes that meet a band, the sorted near and far edges on x
    tell how many meet any node in it, so no box is moved. At most MOST_BANDS bands are counted so.
    """
    bands: dict[tuple[float, float], tuple] = {}

    def met(x0: float, y0: float, x1: float, y1: float) -> int:
        if (y0, y1) not in bands:
            inside = boxes.filter((F.col("ymin") < y1) | F.lit(y1 >= u.ymax)).filter((F.col("ymax") >= y0) | F.lit(y0 <= u.ymin))
            bands[y0, y1] = tuple(_sorted(inside, F.col(c), None, ranges=True) for c in ("xmin", "xmax"))
        near, far = bands[y0, y1]
        return (len(near) if x1 >= u.xmax else int(near.below(x1))) - (int(far.below(x0)) if x0 > u.xmin else 0)

    leaves, left, level = [], {}, [(u, 0, n)]
    while level:
        below = []
        for box, depth, count in level:
            cut = _choice(box, _middle(box)) if count > payload and depth < max_depth else None
            if cut:
                axis, at = cut
                halves = (Box(box.xmin, box.ymin, at, box.ymax), Box(at, box.ymin, box.xmax, box.ymax)) if axis == "x" else (Box(box.xmin, box.ymin, box.xmax, at), Box(box.xmin, at, box.xmax, box.ymax))
                if len(bands.keys() | {(h.ymin, h.ymax) for h in halves}) > MOST_BANDS:
                    left[len(left) + 1] = (box, depth, count)
                    continue
                a, b = (met(*(getattr(h, c) for c in BOX)) for h in halves)
                if a and b and not a == b == count and (max_cross is None or a + b - count <= max_cross * count):
                    below += [(h, depth + 1, k) for h, k in zip(halves, (a, b))]
                    continue
            leaves.append((box.xmin, box.ymin, box.xmax, box.ymax, count, depth))
        level = below
    return leaves, left


def plan_binary_split(
    boxes: DataFrame, payload: int, *, order: str = "bulk", cut: str = "median", max_depth: int = 40, max_cross: float | None = None, universe: Box | None = None
) -> Layout:
    """Halve nodes of more than `payload` boxes, level by level.

    cut: `median` of the centres (exact; `approx` for a sketch) on the axis that leaves the more even
    areas, x on ties, or `middle`. A node is a leaf, too, if a child would be empty, both would keep
    everything, at max_depth, or if more than max_cross of its boxes would cross the cut.
    order `incremental`: boxes arrive by id and overflowing leaves split at once, in one task.

    Each level is written once, and the counts of the children tell whether a split stands. Middle cuts
    are counted from sorted edges, as long as the nodes lie in few bands of y.
    """
    if order == "incremental":
        return _in_one_task(boxes, payload, universe, "binary_split", lambda b, u, p: kernels.split_incremental(b, u, p, max_depth), order=order)
    u, n = _measure(boxes, universe)
    spark = boxes.sparkSession
    leaves: list[tuple] = []
    work = boxes.select("id", *BOX).withColumn("node", F.lit(1).cast("long"))
    # Open nodes: their box and depth, and the split that made them (parent's number, box, count, depth).
    nodes: dict[int, tuple[Box, int]] = {1: (u, 0)}
    counts: dict[int, int] = {1: n}
    name = 1
    if not n:
        leaves, nodes = [(u.xmin, u.ymin, u.xmax, u.ymax, 0, 0)], {}
    elif cut == "middle":
        leaves, kept = _middle_bands(boxes, u, n, payload, max_depth, max_cross)
        nodes, counts, name = {k: v[:2] for k, v in kept.items()}, {k: v[2] for k, v in kept.items()}, len(kept) + 1
        if nodes and 0 not in (v[1] for v in kept.values()):
            from ..operators.route import explode_tiles

            table = spark.createDataFrame([(k, *(getattr(b, c) for c in BOX), b.xmax >= u.xmax, b.ymax >= u.ymax) for k, (b, _) in nodes.items()], "tile_id int, xmin double, ymin double, xmax double, ymax double, last_x boolean, last_y boolean")
            work = explode_tiles(boxes.select("id", *BOX), Layout("tiling", u, table, "bands", len(nodes))).withColumnRenamed("tile_id", "node")
            work = settled(work.withColumn("node", F.col("node").cast("long")))
    while nodes:
        split: dict[int, tuple] = {}
        for r in _node_stats(work, cut, counts):
            box, depth = nodes[r["node"]]
            choice = None
            if r["n"] > payload and depth < max_depth:
                choice = _choice(box, _middle(box) if cut == "middle" else {"x": r["mx"], "y": r["my"]})
            if choice:
                split[r["node"]] = (*choice, name + 1, name + 2)
                name += 2
            else:
                leaves.append((box.xmin, box.ymin, box.xmax, box.ymax, r["n"], depth))
            counts[r["node"]] = r["n"]
        if not split:
            break
        table = spark.createDataFrame([(k, *v) for k, v in split.items()], "node long, axis string, cut double, a long, b long")
        near = F.when(F.col("axis") == "x", F.col("xmin")).otherwise(F.col("ymin"))
        far = F.when(F.col("axis") == "x", F.col("xmax")).otherwise(F.col("ymax"))
        to = F.filter(F.array(F.when(near < F.col("cut"), F.col("a")), F.when(far >= F.col("cut"), F.col("b"))), lambda v: v.isNotNull())
        work = settled(work.join(small(table, len(split)), "node").select("id", *BOX, F.explode(to).alias("node")))
        kids = {r["node"]: r["n"] for r in work.groupBy("node").agg(F.count(F.lit(1)).alias("n")).collect()}
        parents, nodes, undone = nodes, {}, []
        for k, (axis, at, a, b) in split.items():
            box, depth = parents[k]
            left, right, count = kids.get(a, 0), kids.get(b, 0), counts[k]
            if not left or not right or left == right == count or (max_cross is not None and left + right - count > max_cross * count):
                leaves.append((box.xmin, box.ymin, box.xmax, box.ymax, count, depth))
                undone += [a, b]
            elif axis == "x":
                nodes[a], nodes[b] = (Box(box.xmin, box.ymin, at, box.ymax), depth + 1), (Box(at, box.ymin, box.xmax, box.ymax), depth + 1)
            else:
                nodes[a], nodes[b] = (Box(box.xmin, box.ymin, box.xmax, at), depth + 1), (Box(box.xmin, at, box.xmax, box.ymax), depth + 1)
        counts = kids
        # Children that need no cut are leaves at once, and their boxes go no further.
        for k in [k for k, (_, depth) in nodes.items() if kids[k] <= payload or depth >= max_depth]:
            box, depth = nodes.pop(k)
            leaves.append((box.xmin, box.ymin, box.xmax, box.ymax, kids[k], depth))
            undone.append(k)
        if undone and nodes:
            work = work.join(small(spark.createDataFrame([(k,) for k in nodes], "node long"), len(nodes)), "node", "left_semi")
    leaves.sort(key=lambda t: t[:4])
    return make_tiles(spark, u, leaves, "binary_split", payload=payload, cut=cut, max_cross=max_cross)


def plan_quad_split(boxes: DataFrame, payload: int, *, max_depth: int = 30, universe: Box | None = None) -> Layout:
    """Quarter nodes of more than `payload` boxes in the middle of both axes."""
    u, n = _measure(boxes, universe)
    spark = boxes.sparkSession
    nodes = {1: u}
    leaves: list[tuple] = []
    work = boxes.select("id", *BOX).withColumn("node", F.lit(1).cast("long"))
    depth, name = 0, 1
    while nodes:
        counts = {r["node"]: r["n"] for r in _level_stats(work, "middle")}
        plan, children = [], {}
        for k, box in nodes.items():
            mx, my = (box.xmin + box.xmax) / 2, (box.ymin + box.ymax) / 2
            if counts.get(k, 0) <= payload or depth >= max_depth or not (box.xmin < mx < box.xmax and box.ymin < my < box.ymax):
                leaves.append((box.xmin, box.ymin, box.xmax, box.ymax, counts.get(k, 0), depth))
                continue
            plan.append((k, mx, my, name + 1))
            quarters = (Box(box.xmin, box.ymin, mx, my), Box(mx, box.ymin, box.xmax, my), Box(box.xmin, my, mx, box.ymax), Box(mx, my, box.xmax, box.ymax))
            children |= {name + 1 + i: q for i, q in enumerate(quarters)}
            name += 4
        nodes = children
        if nodes:
            table = spark.createDataFrame(plan, "node long, mx double, my double, first long")
            left, right = F.col("xmin") < F.col("mx"), F.col("xmax") >= F.col("mx")
            low, high = F.col("ymin") < F.col("my"), F.col("ymax") >= F.col("my")
            to = [F.when(a & b, F.col("first") + i) for i, (a, b) in enumerate(((left, low), (right, low), (left, high), (right, high)))]
            work = work.join(small(table, len(plan)), "node").select("id", *BOX, F.explode(F.filter(F.array(*to), lambda v: v.isNotNull())).alias("node"))
            depth += 1
            if depth % 4 == 0:
                work = settled(work)
    leaves.sort(key=lambda t: t[:4])
    return make_tiles(spark, u, leaves, "quad_split", payload=payload)


class Ranged:
    """kernels.Sorted of any number of distinct values: written by ranges of about `size` of them, of which
    the driver holds two at a time. Cuts only rise, so each range is read about once."""

    def __init__(self, runs: DataFrame, n: int, size: int):
        ranked = global_rank(runs, "v", parts=max(2, math.ceil(n / size)))
        self.runs = settled(ranked.select("v", "n", F.floor(F.col("rank") / size).alias("part")))
        parts = self.runs.groupBy("part").agg(F.min("v").alias("low"), F.sum("n").alias("n")).orderBy("part").collect()
        self.lows, self.upto = np.array([r["low"] for r in parts], np.float64), np.cumsum([r["n"] for r in parts])
        self.held: dict[int, kernels.Sorted] = {}

    def _part(self, k: int) -> kernels.Sorted:
        if k not in self.held:
            while len(self.held) > 1:
                del self.held[min(self.held)]
            got = self.runs.filter(F.col("part") == k).select("v", "n").toArrow().sort_by("v")
            self.held[k] = kernels.Sorted(got.column("v").to_numpy().astype(np.float64), got.column("n").to_numpy())
        return self.held[k]

    def _before(self, k: int) -> int:
        return int(self.upto[k - 1]) if k else 0

    def __len__(self) -> int:
        return int(self.upto[-1]) if len(self.upto) else 0

    def below(self, edge: float) -> int:
        k = int(np.searchsorted(self.lows, edge)) - 1
        return self._before(k) + int(self._part(k).below(edge)) if k >= 0 else 0

    def __getitem__(self, rank: int) -> float:
        k = min(int(np.searchsorted(self.upto, rank, "right")), len(self.upto) - 1)
        return self._part(k)[rank - self._before(k)]

    def beyond(self, edge: float) -> float | None:
        k = int(np.searchsorted(self.lows, edge, "right")) - 1
        found = self._part(k).beyond(edge) if k >= 0 else None
        if found is None and k + 1 < len(self.lows):
            return float(self.lows[k + 1])
        return found


def _sorted(boxes: DataFrame, column, quantiles: int | None, ranges: bool = False) -> kernels.Sorted | Ranged:
    """The values of a column, in order: distinct ones with counts, or so many quantiles if the caller asks for them.

    ranges: more than MOST_CUT_CANDIDATES distinct values are read a range at a time and not refused.
    """
    if quantiles:
        n, cuts = boxes.agg(F.count(F.lit(1)), F.percentile_approx(column, [i / quantiles for i in range(1, quantiles + 1)], 10 * quantiles)).first()
        values, times = np.unique(np.array(cuts or [], np.float64), return_counts=True)
        return kernels.Sorted(values, times * (n / quantiles))
    runs = boxes.select(column.alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("n"))
    if ranges:
        runs = settled(runs)
        if (n := runs.count()) > MOST_CUT_CANDIDATES:
            return Ranged(runs, n, max(1, MOST_CUT_CANDIDATES // 4))
    got = runs.limit(MOST_CUT_CANDIDATES + 1).toArrow()
    if got.num_rows > MOST_CUT_CANDIDATES:
        raise ValueError(f"over {MOST_CUT_CANDIDATES} distinct coordinates: ask for ranges=True, quantiles=, count='fresh', sampled_layout or two_level")
    got = got.sort_by("v")
    return kernels.Sorted(got.column("v").to_numpy().astype(np.float64), got.column("n").to_numpy())


def plan_strip(
    boxes: DataFrame, payload: int, *, axis: str = "x", count: str = "live", min_fresh: int = 0, quantiles: int | None = None, ranges: bool = False, universe: Box | None = None
) -> Layout:
    """Strips across the other axis, cut at centres, of about `payload` objects each.

    count `live`: objects that reach into a strip from before count, a recurrence over the distinct
    coordinates; with more than MOST_CUT_CANDIDATES of them it is refused, unless `ranges` asks for
    the same recurrence over one range of coordinates after the other, or `quantiles` for one over so
    many quantiles of centres and edges. `fresh`: only objects whose centre lies in the strip count,
    which makes the cuts plain quantiles; it always takes ranges where there are too many centres.
    """
    u, _ = _measure(boxes, universe)
    if count == "fresh" and not quantiles and not min_fresh:
        centres = _sorted(boxes, centre(axis), None, ranges=True)
        cuts = kernels.strip_cuts(centres, centres, payload, "fresh")
    else:
        centres, far = (_sorted(boxes, c, quantiles, ranges) for c in (centre(axis), F.col(f"{axis}max")))
        cuts = kernels.strip_cuts(centres, far, payload, count, min_fresh)
    tiles = kernels.tiles_of_cuts(u, [c for c in cuts if u.low(axis) < c < u.high(axis)], axis)
    return make_tiles(boxes.sparkSession, u, tiles, "strip", axis=axis, count=count, payload=payload)


def plan_optimal_1d(boxes: DataFrame, tiles: int, *, axis: str = "x", quantiles: int | None = None, universe: Box | None = None) -> Layout:
    """At most `tiles` strips whose largest load (replicas included) is as small as cuts at centres allow."""
    u, _ = _measure(boxes, universe)
    centres, far, near = (_sorted(boxes, c, quantiles) for c in (centre(axis), F.col(f"{axis}max"), F.col(f"{axis}min")))
    cuts, load = kernels.optimal_1d(centres, far, near, tiles)
    out = kernels.tiles_of_cuts(u, [c for c in cuts if u.low(axis) < c < u.high(axis)], axis)
    return make_tiles(boxes.sparkSession, u, out, "optimal_1d", axis=axis, load=load)


def arrays_of(boxes: DataFrame, most: int = MOST_IN_ONE_TASK) -> np.ndarray:
    """The boxes by id as an (n, 4) array on the driver, for samples and small sets only."""
    n = boxes.count()
    if n > most:
        raise ValueError(f"{n} boxes are too many for one process; use sampled_layout or two_level")
    got = boxes.select("id", *BOX).toPandas().sort_values("id", kind="stable")
    return got[list(BOX)].to_numpy(np.float64)


def _in_one_task(boxes: DataFrame, payload: int, universe: Box | None, method: str, kernel, **params) -> Layout:
    """Run a sequential kernel as the only group of a grouped map."""
    u, n = _measure(boxes, universe)
    if n > MOST_IN_ONE_TASK:
        raise ValueError(f"{method} is sequential: {n} boxes are too many for one task; use sampled_layout or two_level")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        b = np.column_stack([t.column(c).to_numpy() for c in BOX])
        tiles = kernel(b, u, payload)
        names = [*BOX, "planned"]
        return pa.table({c: pa.array([x[i] for x in tiles], pa.int64() if i == 4 else pa.float64()) for i, c in enumerate(names)}).append_column("k", pa.array(range(len(tiles)), pa.int64()))

    if not n:
        return make_tiles(boxes.sparkSession, u, [(*(getattr(u, c) for c in BOX), 0)], method, payload=payload, **params)
    got = boxes.select("id", *BOX, F.lit(0).alias("_all")).groupBy("_all").applyInArrow(run, "xmin double, ymin double, xmax double, ymax double, planned long, k long")
    rows = sorted(got.collect(), key=lambda r: r["k"])
    return make_tiles(boxes.sparkSession, u, [tuple(r)[:5] for r in rows], method, payload=payload, **params)


def plan_least_cut_strip(boxes: DataFrame, payload: int, *, axes: tuple[str, ...] = ("x", "y"), universe: Box | None = None) -> Layout:
    """Strips off the remaining region, along x or y, whichever cut crosses fewer objects."""
    u, n = _measure(boxes, universe)
    if not n:
        return make_tiles(boxes.sparkSession, u, [(*(getattr(u, c) for c in BOX), 0)], "least_cut_strip", payload=payload, axes=axes)

    def run(batches):
        # No box is told from another here, so they come as they are, without ids or order.
        b = np.concatenate([np.column_stack([batch.column(c).to_numpy() for c in BOX]) for batch in batches])
        tiles = kernels.peel(b, u, payload, axes)
        for i in range(0, len(tiles), 10_000):
            some = tiles[i : i + 10_000]
            columns = [pa.array([x[j] for x in some], pa.int64() if j == 4 else pa.float64()) for j in range(5)]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(range(i, i + len(some)), pa.int64())], [*BOX, "planned", "k"])

    got = boxes.select(*BOX).repartition(1).mapInArrow(run, "xmin double, ymin double, xmax double, ymax double, planned long, k long")
    rows = sorted(got.collect(), key=lambda r: r["k"])
    return make_tiles(boxes.sparkSession, u, [tuple(r)[:5] for r in rows], "least_cut_strip", payload=payload, axes=axes)


def least_cut_axes(boxes: DataFrame, payload: int) -> DataFrame:
    """Least-cut strips of boxes (id, lo, hi: arrays of d coordinates): tile_id, lo, hi, planned.

    In one task, as the plane's form; the region is the boxes' extent.
    """
    n = boxes.count()
    if n > MOST_IN_ONE_TASK:
        raise ValueError(f"{n} boxes are too many for one task; take a sample of them")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        near, far = (np.array(t.column(c).to_pylist(), np.float64) for c in ("lo", "hi"))
        rows = kernels.peel_axes(near, far, near.min(axis=0).tolist(), far.max(axis=0).tolist(), payload)
        kinds = (pa.int32(), pa.list_(pa.float64()), pa.list_(pa.float64()), pa.int64())
        return pa.table({c: pa.array(v, k) for c, v, k in zip(("tile_id", "lo", "hi", "planned"), (range(len(rows)), *zip(*rows)), kinds)})

    return boxes.select("id", "lo", "hi", F.lit(0).alias("_all")).groupBy("_all").applyInArrow(run, "tile_id int, lo array<double>, hi array<double>, planned long")


def curve_members(boxes: DataFrame, payload: int, curve: str, order: int, u: Box) -> DataFrame:
    keyed = with_curve_key(boxes.select("id", *BOX), u, curve, order)
    return global_rank(keyed, "curve_key", "id").withColumn("home_tile", F.floor(F.col("rank") / payload).cast("int"))


def plan_curve_pack(boxes: DataFrame, payload: int, *, curve: str = "hilbert", order: int = 16, universe: Box | None = None) -> Layout:
    """Each `payload` objects in the order of their centres on a space-filling curve are a tile."""
    u, _ = _measure(boxes, universe)
    return packed(_extents(curve_members(boxes, payload, curve, order, u)), u, "curve_pack", payload=payload, curve=curve, order=order)


def _extents(members: DataFrame) -> DataFrame:
    return members.groupBy(F.col("home_tile").alias("tile_id")).agg(
        F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax"), F.count(F.lit(1)).alias("planned")
    )


def sort_tile_members(boxes: DataFrame, payload: int, fill: str, n: int) -> DataFrame:
    """boxes with slab and home_tile."""
    from pyspark.sql.window import Window

    m = max(1, math.ceil(math.sqrt(n / payload)))
    keyed = boxes.select("id", *BOX, centre("x").alias("cx"), centre("y").alias("cy"))
    ranked = global_rank(keyed, "cx", "id", parts=m if m > 1 else 2)
    per = m * payload if fill == "packed" else max(1, -(-n // m))
    slabs = ranked.withColumn("slab", F.floor(F.col("rank") / per).cast("int"))
    # A slab holds about sqrt(n * payload) objects.
    w = Window.partitionBy("slab").orderBy("cy", "id")
    in_slab = F.row_number().over(w) - 1
    tile = F.floor(in_slab / payload) if fill == "packed" else F.floor(in_slab / max(1, -(-per // m)))
    per_slab = -(-per // payload) + 1 if fill == "packed" else m + 1
    return slabs.withColumn("home_tile", (F.col("slab").cast("long") * per_slab + tile).cast("long"))


def plan_sort_tile(boxes: DataFrame, payload: int, *, fill: str = "packed", edges: str = "tight", universe: Box | None = None) -> Layout:
    """Slabs of centres in x, tiles of centres in y in each; a tile is its members' extent.

    fill `packed`: slabs of m * payload objects, `even`: ranks parted evenly. edges `slab`: tiles end
    where the next one's centres begin, which makes them a tiling.
    """
    u, n = _measure(boxes, universe)
    if not n:
        return make_tiles(boxes.sparkSession, u, [(*(getattr(u, c) for c in BOX), 0)], "sort_tile", payload=payload)
    members = sort_tile_members(boxes, payload, fill, n)
    if edges == "tight":
        return packed(_extents(members), u, "sort_tile", payload=payload, fill=fill)
    cuts = members.groupBy("slab", "home_tile").agg(F.min("cx").alias("cx"), F.min("cy").alias("cy"), F.count(F.lit(1)).alias("n")).collect()
    slabs: dict[int, list] = {}
    for r in sorted(cuts, key=lambda r: (r["slab"], r["home_tile"])):
        slabs.setdefault(r["slab"], []).append((r["cy"], r["n"], r["cx"]))
    begins = [(min(c for *_, c in rows), rows) for _, rows in sorted(slabs.items())]
    tiles = []
    for i, (x, rows) in enumerate(begins):
        x0, x1 = (u.xmin if i == 0 else x), (u.xmax if i + 1 == len(begins) else begins[i + 1][0])
        for j, (y, count, _) in enumerate(rows):
            y0, y1 = (u.ymin if j == 0 else y), (u.ymax if j + 1 == len(rows) else rows[j + 1][0])
            if x0 < x1 and y0 < y1 or len(begins) == len(rows) == 1:
                tiles.append((x0, y0, x1, y1, count))
    return make_tiles(boxes.sparkSession, u, tiles, "sort_tile", payload=payload, fill=fill, edges=edges)


def plan_hash(boxes: DataFrame, tiles: int) -> DataFrame:
    """Conventional hash partitioning (by a digest of the id's text, which other engines have, too):
    only its balance can be measured, as its tiles have no extent."""
    first = F.conv(F.substring(F.md5(F.col("id").cast("string")), 1, 8), 16, 10).cast("long")
    return boxes.withColumn("tile_id", (first % tiles).cast("int"))


def plan_range(boxes: DataFrame, tiles: int, axis: str = "x") -> DataFrame:
    """Conventional range partitioning on one coordinate."""
    _, n = extent_of(boxes)
    ranked = global_rank(boxes.withColumn("_c", centre(axis)), "_c", "id")
    return ranked.withColumn("tile_id", F.floor(F.col("rank") * tiles / max(1, n)).cast("int")).drop("_c", "rank")


PLANS = {
    "grid": plan_fixed_grid,
    "binary": plan_binary_split,
    "strip": plan_strip,
    "least_cut": plan_least_cut_strip,
    "hilbert": plan_curve_pack,
    "sort_tile": plan_sort_tile,
}


def plan_joint(r: DataFrame, s: DataFrame, method: str, payload: int, **opts) -> Layout:
    """One layout of two datasets together."""
    both = r.select(*BOX, F.lit("R").alias("side"), "id").unionByName(s.select(*BOX, F.lit("S").alias("side"), "id"))
    both = both.withColumn("id", F.col("id") * 2 + (F.col("side") == "S").cast("long"))
    return PLANS[method](both, payload, **opts)
