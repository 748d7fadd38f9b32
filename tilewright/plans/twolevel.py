"""Two-level layouts: anchors of a sample deal objects into coarse buckets, and a method runs in each."""

from __future__ import annotations

import math
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.curves import with_curve_key
from ..functions.geometry import BOX, Box, centre, universe as extent_of
from . import kernels
from .layout import Layout, make_tiles, packed
from .methods import PLANS
from .ranks import with_interval

#: Boxes that one Arrow group may hold.
MOST_IN_BUCKET = 5_000_000


def anchors(keyed: DataFrame, key: str, buckets: int) -> list:
    """Sorted cuts of the anchor key that part the objects into about even buckets."""
    if buckets < 2:
        return []
    q = [i / buckets for i in range(1, buckets)]
    return sorted(set(keyed.select(F.percentile_approx(key, q, 100 * buckets)).first()[0] or []))


def two_level(
    boxes: DataFrame, payload: int, method: str, *, coarse: int | None = None, cuts: list | None = None, anchor: str = "x", universe: Box | None = None, **opts
) -> Layout:
    """Layout by `method` inside coarse buckets of about `coarse` objects each (or between given cuts of
    the anchor), all at once.

    anchor `x`: buckets are slabs between anchors, tiles are cut to their slab, and together tile the
    universe (packings stay packings). anchor `hilbert`: a bucket's region is its objects' extent; the
    union is a packing. Each object counts in the bucket of its anchor only; routing is a later step
    over all objects. grid and hilbert need no buckets: arithmetic and one range sort do. The kernel's
    own time in each bucket is kept with the layout (`bucket_seconds`).
    """
    if method == "grid":
        return PLANS["grid"](boxes, payload, universe=universe)
    if method == "hilbert":
        return PLANS["hilbert"](boxes, payload, universe=universe, **opts)
    u, n = extent_of(boxes)
    u = universe or u
    keyed = boxes.select("id", *BOX)
    if anchor == "x":
        keyed = keyed.withColumn("_key", centre("x"))
    elif anchor == "hilbert":
        keyed = with_curve_key(keyed, u, key="_key")
    else:
        raise ValueError(f"unknown anchor {anchor}")
    cuts = sorted(cuts) if cuts is not None else anchors(keyed, "_key", max(1, math.ceil(n / coarse)))
    if anchor == "x":
        cuts = [c for c in cuts if u.xmin < c < u.xmax]
    dealt = with_interval(keyed, "_key", cuts, "_bucket")
    kernel = kernels.KERNELS[method]
    edges = [u.xmin, *cuts, u.xmax] if anchor == "x" else None
    most = MOST_IN_BUCKET

    def run(t: pa.Table) -> pa.Table:
        if len(t) > most:
            raise ValueError(f"a bucket holds {len(t)} boxes, over {most}: lower `coarse`")
        t = t.sort_by("id")
        k = t.column("_bucket")[0].as_py()
        b = np.column_stack([t.column(c).to_numpy() for c in BOX])
        if edges:
            region = Box(edges[k], u.ymin, edges[k + 1], u.ymax)
        else:
            region = Box(*map(float, b[:, :2].min(0)), *map(float, b[:, 2:].max(0)))
        began = time.perf_counter()
        tiles = kernel(b, region, payload, **opts)
        took = time.perf_counter() - began
        data = {c: pa.array([x[i] for x in tiles], pa.int64() if i == 4 else pa.float64()) for i, c in enumerate((*BOX, "planned"))}
        return pa.table(data | {"bucket": pa.array([k] * len(tiles), pa.int32()), "seconds": pa.array([took] * len(tiles), pa.float64())})

    found = dealt.drop("_key").groupBy("_bucket").applyInArrow(run, "xmin double, ymin double, xmax double, ymax double, planned long, bucket int, seconds double")
    rows = [tuple(r) for r in found.collect()]  # tiles, not objects
    rows.sort(key=lambda r: (r[5], *r[:4]))
    seconds = {r[5]: r[6] for r in rows}
    rows = [r[:6] for r in rows]
    packing = method == "sort_tile" and opts.get("edges", "tight") == "tight"
    if anchor == "hilbert" or packing:
        frame = boxes.sparkSession.createDataFrame([(i, *r[:4], r[4]) for i, r in enumerate(rows)], "tile_id int, xmin double, ymin double, xmax double, ymax double, planned long")
        return packed(frame, u, f"two_level_{method}", coarse=coarse, anchor=anchor, bucket_seconds=seconds)
    if edges and (missing := set(range(len(cuts) + 1)) - {r[5] for r in rows}):
        rows += [(edges[k], u.ymin, edges[k + 1], u.ymax, 0, k) for k in sorted(missing)]
    return make_tiles(boxes.sparkSession, u, [(*r[:5], 1, r[5]) for r in rows], f"two_level_{method}", coarse=coarse, anchor=anchor, payload=payload, bucket_seconds=seconds)


__all__ = ["anchors", "two_level"]
