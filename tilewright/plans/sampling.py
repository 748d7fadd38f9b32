"""Layouts of a uniform sample, mapped onto all objects."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import BOX, Box, universe as extent_of
from ..store import settled
from .layout import Layout, packed
from .methods import PLANS, plan_sort_tile


def sample_boxes(boxes: DataFrame, ratio: float, seed: int = 1) -> DataFrame:
    """A repeatable share of the boxes, chosen by a hash of the id whatever the partitions."""
    if ratio >= 1:
        return boxes
    span = 1 << 30
    return boxes.filter(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(span)) < int(ratio * span))


def fixed_sample(boxes: DataFrame, size: int, seed: int = 1) -> DataFrame:
    """At most `size` boxes, those of least hash: a bound on what reaches one process."""
    return boxes.orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(size)


def sampled_layout(
    boxes: DataFrame, payload: int, method: str, *, ratio: float | None = None, size: int | None = None, seed: int = 1, cover: str = "error", sample: DataFrame | None = None, **opts
) -> Layout:
    """The layout of a sample with the payload scaled alike, over the universe of all boxes.

    Tilings cover the universe anyway. Packings of a sample need not; cover says what then happens:
    `error` refuses them, `nearest` grows the closest tile, `keyrange` gives each object the tile of
    its curve interval, `slab` uses the tiling form of sort-tile.
    """
    u, n = extent_of(boxes)
    if sample is None:
        sample = fixed_sample(boxes, size, seed) if size else sample_boxes(boxes, ratio, seed)
    sample = settled(sample.select("id", *BOX))
    m = sample.count()
    scaled = max(1, round(payload * m / max(1, n)))
    packing = method in ("hilbert", "sort_tile") and opts.get("edges") != "slab"
    if packing and m < n:
        if cover == "error":
            raise ValueError("a packing of a sample may leave objects uncovered; choose cover='nearest', 'keyrange' or 'slab'")
        if cover == "slab":
            if method != "sort_tile":
                raise ValueError("only sort_tile has slab edges")
            return plan_sort_tile(sample, scaled, edges="slab", universe=u, **opts)
        if cover == "keyrange":
            return _by_key_range(boxes, sample, scaled, u, **opts)
        layout = PLANS[method](sample, scaled, universe=u, **opts)
        return _grown(boxes, layout) if cover == "nearest" else layout
    return PLANS[method](sample, scaled, universe=u, **opts)


def _by_key_range(boxes: DataFrame, sample: DataFrame, payload: int, u: Box, curve: str = "hilbert", order: int = 16) -> Layout:
    """Curve intervals of the sample; a tile is the extent of all objects of its interval."""
    from ..functions.curves import with_curve_key
    from .methods import _extents
    from .ranks import global_rank, with_interval

    ranked = global_rank(with_curve_key(sample, u, curve, order), "curve_key", "id")
    starts = ranked.filter((F.col("rank") % payload == 0) & (F.col("rank") > 0)).select("curve_key").distinct()
    cuts = sorted(r[0] for r in starts.collect())  # one row per tile
    keyed = with_curve_key(boxes.select("id", *BOX), u, curve, order)
    return packed(_extents(with_interval(keyed, "curve_key", cuts, "home_tile")), u, "curve_pack", curve=curve, cover="keyrange")


def nearest_tiles(tiles: np.ndarray, cx: np.ndarray, cy: np.ndarray) -> np.ndarray:
    """The row of tiles (xmin, ymin, xmax, ymax) nearest to each point, the first of equals.

    Tiles are taken in order of their lower x; a point looks at tiles from its own place outwards, in
    growing steps, until what is left of the x distance alone is farther than the best.
    """
    order = np.argsort(tiles[:, 0], kind="stable")
    t = tiles[order]
    reach = np.maximum.accumulate(t[:, 2])
    best, who = np.full(len(cx), np.inf), np.zeros(len(cx), np.int64)
    left = np.searchsorted(t[:, 0], cx, "right") - 1
    right = left + 1
    todo, step = np.arange(len(cx)), 16
    while len(todo):
        spans = left[todo][:, None] - np.arange(step), right[todo][:, None] + np.arange(step)
        for at in spans:
            ok = (at >= 0) & (at < len(t))
            k = np.where(ok, at, 0)
            dx = np.maximum(0, np.maximum(t[k, 0] - cx[todo][:, None], cx[todo][:, None] - t[k, 2]))
            dy = np.maximum(0, np.maximum(t[k, 1] - cy[todo][:, None], cy[todo][:, None] - t[k, 3]))
            d = np.where(ok, dx * dx + dy * dy, np.inf)
            low = d.min(axis=1)
            first = np.where(d == low[:, None], order[k], len(t)).min(axis=1)
            better = (low < best[todo]) | (low == best[todo]) & (first < who[todo])
            best[todo[better]], who[todo[better]] = low[better], first[better]
        left[todo] -= step
        right[todo] += step
        more_left = (left[todo] >= 0) & (np.maximum(0, cx[todo] - reach[np.maximum(left[todo], 0)]) ** 2 <= best[todo])
        more_right = (right[todo] < len(t)) & (np.maximum(0, t[np.minimum(right[todo], len(t) - 1), 0] - cx[todo]) ** 2 <= best[todo])
        todo, step = todo[more_left | more_right], min(step * 2, 1024)
    return who


def _grown(boxes: DataFrame, layout: Layout) -> Layout:
    """Each object that no tile holds whole makes the tile nearest to its centre grow over it."""
    from ..operators.route import with_home

    homed = with_home(boxes.select("id", *BOX), layout)
    lost = homed.filter("home_tile is null").select("id", *BOX)
    rows = sorted(layout.rows(), key=lambda r: r["tile_id"])  # the layout, whose size is counted
    ids, corners = np.array([r["tile_id"] for r in rows]), np.array([[r[c] for c in BOX] for r in rows], np.float64)
    shared = boxes.sparkSession.sparkContext.broadcast((ids, corners))

    def homes(batches):
        ids, corners = shared.value
        for batch in batches:
            b = [batch.column(c).to_numpy(zero_copy_only=False) for c in BOX]
            at = np.concatenate([np.zeros(0, np.int64), *(nearest_tiles(corners, (b[0][i : i + 1024] + b[2][i : i + 1024]) / 2, (b[1][i : i + 1024] + b[3][i : i + 1024]) / 2) for i in range(0, len(b[0]), 1024))])
            yield pa.RecordBatch.from_arrays([pa.array(ids[at], pa.int32()), *(pa.array(x) for x in b)], ["tile_id", *BOX])

    best = lost.mapInArrow(homes, "tile_id int, xmin double, ymin double, xmax double, ymax double")
    members = best.select("tile_id", *BOX, F.lit(0).alias("planned")).unionByName(layout.tiles.select("tile_id", *BOX, "planned"))
    grown = members.groupBy("tile_id").agg(F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax"), F.sum("planned").alias("planned"))
    return packed(grown, layout.universe, layout.method, cover="nearest")
