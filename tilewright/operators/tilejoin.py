"""Tile-parallel spatial joins.

A theta join on boxes becomes an equi-join on the tile and a residual predicate, so Spark shuffles
each side once and no nested loop over the whole inputs is planned. What differs is who is
replicated and how repeated pairs go:

assign
  multi      both sides go to all tiles they meet, each tile is joined once
  single     both stay in their home tile; tiles are paired by the reach of their objects
  one_sided  R stays at home, S goes to all tiles whose R objects it may meet; no repeats arise
dedup (of multi)
  owner_point   only the tile with the low corner of the common part keeps a pair (tilings)
  least_common  only the least tile common to both keeps it (packings); tiles that cannot be the least
                one are left out, and a box is held against those of its bands of the tile (route.leading_tiles)
  distinct      repeats are removed by a second shuffle
local
  nested, sweep (sorted sweep in one Arrow group a tile), subgrid (second-level cells)
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import BOX, corner, inflate, predicate
from ..functions.geometry import predicate as predicate_of
from ..plans.layout import Layout
from ..plans.ranks import global_rank
from ..store import settled, small
from .route import _cell, assign, explode_tiles, leading_tiles, with_home


def _side(boxes: DataFrame, side: str) -> DataFrame:
    return boxes.select("id", *BOX, *(c for c in boxes.columns if c in ("tile_id", "tiles", "home_tile")), F.lit(side).alias("side"))


def _owner(layout: Layout):
    """The pair's tile owns the low corner of the common part of r and s."""
    u = layout.universe
    x, y = F.greatest(F.col("r.xmin"), F.col("s.xmin")), F.greatest(F.col("r.ymin"), F.col("s.ymin"))
    if layout.method == "fixed_grid":
        mx, my = layout.params["cells"]
        return F.col("r.tile_id") == (_cell(y, u.ymin, u.height, my) * mx + _cell(x, u.xmin, u.width, mx)).cast("int")
    in_x = ((F.col("t.xmin") <= x) | (F.col("t.xmin") <= u.xmin)) & ((x < F.col("t.xmax")) | F.col("t.last_x"))
    in_y = ((F.col("t.ymin") <= y) | (F.col("t.ymin") <= u.ymin)) & ((y < F.col("t.ymax")) | F.col("t.last_y"))
    return in_x & in_y


def _spread(r: DataFrame, s: DataFrame, kind) -> tuple[DataFrame, DataFrame, object]:
    """Both sides as routed: a distance join grows S for routing and keeps its own corners."""
    if isinstance(kind, tuple):
        s = s.select("id", *(F.col(c).alias(f"o_{c}") for c in BOX), *BOX)
        return r, inflate(s, float(kind[1])), kind
    return r, s, kind


def _test(kind):
    if isinstance(kind, tuple):
        zero = F.lit(0.0)
        dx = F.greatest(zero, F.col("r.xmin") - F.col("s.o_xmax"), F.col("s.o_xmin") - F.col("r.xmax"))
        dy = F.greatest(zero, F.col("r.ymin") - F.col("s.o_ymax"), F.col("s.o_ymin") - F.col("r.ymax"))
        return predicate("intersects", "r", "s") & (dx * dx + dy * dy <= float(kind[1]) ** 2)
    test = predicate(kind, "r", "s")
    return test if kind == "intersects" else predicate("intersects", "r", "s") & test


def join(
    r: DataFrame, s: DataFrame, layout: Layout, *, predicate: str | tuple = "intersects", assign: str = "multi", dedup: str | None = None, local: str = "nested", refine=None
) -> DataFrame:
    """All pairs (r_id, s_id) of which the predicate holds, each once.

    refine (of sweeps): an exact test of the pairs that a tile is about to report, which gets the tile's
    rows of both sides, with all their columns, and the pairs' places in them; so no pair leaves its tile for it.
    """
    if refine and (assign != "multi" or local != "sweep"):
        raise ValueError("pairs are refined in a sweep")
    r, s, kind = _spread(r, s, predicate)
    if assign == "single":
        return _single(r, s, layout, kind)
    if assign == "one_sided":
        return _one_sided(r, s, layout, kind)
    if assign != "multi":
        raise ValueError(f"unknown assignment {assign}")
    dedup = dedup or ("owner_point" if layout.kind == "tiling" else "least_common")
    if dedup == "owner_point" and layout.kind != "tiling":
        raise ValueError("owner points need a tiling")
    pairs = _multi(r, s, layout, kind, dedup, local, refine)
    return pairs.dropDuplicates(["r_id", "s_id"]) if dedup == "distinct" else pairs


def _multi(r: DataFrame, s: DataFrame, layout: Layout, kind, dedup: str, local: str, refine=None) -> DataFrame:
    lists = dedup == "least_common"
    if lists and layout.kind == "packing":
        size = _mean_size(r, s) if local == "nested" else (0.0, 0.0)
        a, b = leading_tiles(r, layout, size), leading_tiles(s, layout, size)
    else:
        a, b = assign(r, layout, tiles=lists), assign(s, layout, tiles=lists)
    if local == "sweep":
        return _sweep(a, b, layout, kind, dedup, refine)
    on, test = F.col("r.tile_id") == F.col("s.tile_id"), _test(kind)
    if local == "subgrid":
        if layout.kind != "tiling":
            raise ValueError("second-level cells need a tiling, whose tiles hold a part of every pair they own")
        a, b = _sub_cells(a, layout), _sub_cells(b, layout)
        on = on & (F.col("r.sub") == F.col("s.sub"))
        test = test & _sub_owner(layout)
    elif local != "nested":
        raise ValueError(f"unknown local join {local}")
    keep = F.lit(True)
    if dedup == "owner_point":
        keep = _owner(layout)
    elif lists:
        keep = _least_common()
        if layout.kind == "packing" and local == "nested":
            on = on & (F.col("r.band") == F.col("s.band"))
            keep = (F.col("r.band") == F.greatest("r.low", "s.low")) & keep
    if dedup == "owner_point" and layout.method != "fixed_grid":
        a = a.join(small(layout.tiles.select("tile_id", F.struct(*BOX, "last_x", "last_y").alias("t")), layout.count), "tile_id")
        keep = _owner_in("r.t", layout)
    return a.alias("r").join(b.alias("s"), on & test & keep).select(F.col("r.id").alias("r_id"), F.col("s.id").alias("s_id"))


def _least_common():
    """This tile is the least of r's and s's. Lists are in order, so their first tiles settle most pairs without a look at the others."""
    r, s, tile = F.get("r.tiles", F.lit(0)), F.get("s.tiles", F.lit(0)), F.col("r.tile_id")
    least = (F.size("r.tiles") == 1) | (F.size("s.tiles") == 1) | (F.array_min(F.array_intersect("r.tiles", "s.tiles")) == tile)
    return F.when(r == s, r == tile).otherwise(least)


def _mean_size(r: DataFrame, s: DataFrame) -> tuple[float, float]:
    """Mean width and height of the boxes of both sides."""
    row = r.select(*BOX).unionByName(s.select(*BOX)).agg(F.avg(F.col("xmax") - F.col("xmin")), F.avg(F.col("ymax") - F.col("ymin"))).first()
    return float(row[0] or 0.0), float(row[1] or 0.0)


def _owner_in(tile: str, layout: Layout):
    """As _owner, with the tile as a struct column."""
    u, t = layout.universe, F.col(tile)
    x, y = F.greatest(F.col("r.xmin"), F.col("s.xmin")), F.greatest(F.col("r.ymin"), F.col("s.ymin"))
    in_x = ((t["xmin"] <= x) | (t["xmin"] <= u.xmin)) & ((x < t["xmax"]) | t["last_x"])
    in_y = ((t["ymin"] <= y) | (t["ymin"] <= u.ymin)) & ((y < t["ymax"]) | t["last_y"])
    return in_x & in_y


SUB_CELLS = 64


def _sub_step(layout: Layout) -> tuple[float, float]:
    """Size of the second-level cells: a fixed mesh over the universe, finer than the tiles."""
    side = max(1.0, layout.count**0.5) * SUB_CELLS / 8
    return max(layout.universe.width / side, 1e-9), max(layout.universe.height / side, 1e-9)


def _sub_cells(a: DataFrame, layout: Layout) -> DataFrame:
    """A row for each second-level cell of a box that lies in (the extent of) its tile."""
    dx, dy = _sub_step(layout)
    u = layout.universe
    t = layout.tiles.select("tile_id", *(F.col(c).alias(f"_{c}") for c in BOX))
    a = a.join(small(t, layout.count), "tile_id")

    def spots(axis: str, low: float, d: float):
        first = F.floor((F.greatest(F.col(f"{axis}min"), F.col(f"_{axis}min")) - low) / d)
        last = F.floor((F.least(F.col(f"{axis}max"), F.col(f"_{axis}max")) - low) / d)
        # A box beside its tile (universe edges) still has one cell.
        return F.sequence(F.least(first, last), F.greatest(first, last))

    a = a.withColumn("_i", F.explode(spots("x", u.xmin, dx))).withColumn("_j", F.explode(spots("y", u.ymin, dy)))
    return a.withColumn("sub", F.struct("_i", "_j")).drop("_i", "_j")


def _sub_owner(layout: Layout):
    """Only the cell of the low corner of r, s and the tile in common reports a pair of this tile."""
    dx, dy = _sub_step(layout)
    u = layout.universe
    x = F.greatest(F.col("r.xmin"), F.col("s.xmin"), F.col("r._xmin"))
    y = F.greatest(F.col("r.ymin"), F.col("s.ymin"), F.col("r._ymin"))
    return (F.col("r.sub._i") == F.floor((x - u.xmin) / dx)) & (F.col("r.sub._j") == F.floor((y - u.ymin) / dy))


def sweep_pairs(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of intersecting boxes of two arrays: both sorted by low x, each box meets those of
    the other side that begin inside its x extent."""
    out_a, out_b = [], []
    ia, ib = np.argsort(a[:, 0], kind="stable"), np.argsort(b[:, 0], kind="stable")
    sa, sb = a[ia], b[ib]
    for left, right, il, ir, flip, side in ((sa, sb, ia, ib, False, "left"), (sb, sa, ib, ia, True, "right")):
        begin = np.searchsorted(right[:, 0], left[:, 0], side)
        end = np.searchsorted(right[:, 0], left[:, 2], "right")
        n = np.maximum(end - begin, 0)
        for at in range(0, len(left), 4096):
            m = n[at : at + 4096]
            i = np.repeat(np.arange(at, at + len(m)), m)
            j = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m) + np.repeat(begin[at : at + 4096], m)
            hit = (left[i, 1] <= right[j, 3]) & (left[i, 3] >= right[j, 1])
            x, y = il[i[hit]], ir[j[hit]]
            out_a.append(y if flip else x)
            out_b.append(x if flip else y)
    return np.concatenate(out_a) if out_a else np.zeros(0, int), np.concatenate(out_b) if out_b else np.zeros(0, int)


def _sweep(a: DataFrame, b: DataFrame, layout: Layout, kind, dedup: str, refine=None) -> DataFrame:
    """One Arrow group a tile. Candidates are the box intersections; what else the predicate, the
    owner or the tile lists ask is tested on the joined pairs, vectorised."""
    if kind not in ("intersects", "overlaps", "contains", "within"):
        raise ValueError("the sweep has no distance predicate; use local='nested'")
    u = layout.universe
    bounds = layout.tiles.select("tile_id", *(F.col(c).alias(f"_{c}") for c in BOX), "last_x", "last_y")
    lists = dedup == "least_common"
    if dedup == "owner_point":
        a = a.join(small(bounds, layout.count), "tile_id")

    def run(x: pa.Table, y: pa.Table) -> pa.Table:
        r = np.column_stack([x.column(c).to_numpy() for c in BOX]) if len(x) else np.zeros((0, 4))
        s = np.column_stack([y.column(c).to_numpy() for c in BOX]) if len(y) else np.zeros((0, 4))
        i, j = sweep_pairs(r, s)
        p, q = r[i], s[j]
        ok = np.ones(len(i), bool)
        if kind == "overlaps":
            ok &= (p[:, 0] < q[:, 2]) & (p[:, 2] > q[:, 0]) & (p[:, 1] < q[:, 3]) & (p[:, 3] > q[:, 1])
        elif kind != "intersects":
            big, little = (p, q) if kind == "contains" else (q, p)
            ok &= (big[:, :2] <= little[:, :2]).all(1) & (big[:, 2:] >= little[:, 2:]).all(1)
        if len(i) and dedup == "owner_point":
            t = [x.column(f"_{c}")[0].as_py() for c in BOX]
            low = np.maximum(p[:, :2], q[:, :2])
            for d, (edge, last) in enumerate(((u.xmin, "last_x"), (u.ymin, "last_y"))):
                if t[d] > edge:
                    ok &= low[:, d] >= t[d]
                if not x.column(last)[0].as_py():
                    ok &= low[:, d] < t[d + 2]
        elif len(i) and lists:
            tile = x.column("tile_id")[0].as_py()
            own, other = x.column("tiles").to_pylist(), y.column("tiles").to_pylist()
            ok &= np.array([min(set(own[k]) & set(other[m])) == tile for k, m in zip(i.tolist(), j.tolist())], bool)
        if refine and ok.any():
            ok[ok] = refine(x, y, i[ok], j[ok])
        r_id = x.column("id").to_numpy()[i[ok]] if len(x) else np.zeros(0, np.int64)
        s_id = y.column("id").to_numpy()[j[ok]] if len(y) else np.zeros(0, np.int64)
        return pa.table({"r_id": pa.array(r_id, pa.int64()), "s_id": pa.array(s_id, pa.int64())})

    # Fresh attribute ids: both sides may come from one dataset.
    a, b = (x.select(*(F.col(c).alias(c) for c in x.columns)) for x in (a, b))
    return a.groupBy("tile_id").cogroup(b.groupBy("tile_id")).applyInArrow(run, "r_id long, s_id long")


def reach(homed: DataFrame) -> DataFrame:
    """tile_id and the extent of the objects at home in it."""
    return homed.groupBy(F.col("home_tile").alias("tile_id")).agg(
        F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax")
    )


def tile_pairs(a: DataFrame, b: DataFrame, layout: Layout) -> DataFrame:
    """Pairs of tiles whose reaches meet, found through the layout's own tiles and not all with all."""
    sides = [explode_tiles(x.withColumnRenamed("tile_id", "id"), layout).select("tile_id", F.struct("id", *BOX).alias("z")) for x in (a, b)]
    met = sides[0].select("tile_id", F.col("z").alias("r")).join(sides[1].select("tile_id", F.col("z").alias("s")), "tile_id")
    met = met.filter(predicate("intersects", "r", "s"))
    return met.select(F.col("r.id").alias("r_tile"), F.col("s.id").alias("s_tile")).distinct()


def _single(r: DataFrame, s: DataFrame, layout: Layout, kind) -> DataFrame:
    a, b = with_home(r, layout), with_home(s, layout)
    pairs = tile_pairs(reach(a), reach(b), layout)
    left = a.alias("r").join(pairs.alias("p"), F.col("r.home_tile") == F.col("p.r_tile"))
    both = left.join(b.alias("s"), (F.col("p.s_tile") == F.col("s.home_tile")) & _test(kind))
    return both.select(F.col("r.id").alias("r_id"), F.col("s.id").alias("s_id"))


def _one_sided(r: DataFrame, s: DataFrame, layout: Layout, kind) -> DataFrame:
    a = with_home(r, layout)
    near = tile_reach_assignment(s, reach(a), layout)
    on = (F.col("r.home_tile") == F.col("s.tile_id")) & _test(kind)
    return a.alias("r").join(near.alias("s"), on).select(F.col("r.id").alias("r_id"), F.col("s.id").alias("s_id"))


def tile_reach_assignment(boxes: DataFrame, reaches: DataFrame, layout: Layout) -> DataFrame:
    """boxes with the tiles whose reach they meet."""
    around = Layout("packing", layout.universe, reaches.select("tile_id", *BOX, F.lit(False).alias("last_x"), F.lit(False).alias("last_y")), "reach", layout.count)
    return explode_tiles(boxes, around)


def self_join(boxes: DataFrame, layout: Layout, **opts) -> DataFrame:
    """Pairs of one dataset, r_id < s_id."""
    return join(boxes, boxes, layout, **opts).filter("r_id < s_id")


#: Boxes of a block of the nested loop, and comparisons that it makes at once.
BLOCK, AT_ONCE = 4096, 1 << 22


def brute_force(r: DataFrame, s: DataFrame, *, predicate: str | tuple = "intersects") -> DataFrame:
    """The baseline without tiles: a nested loop over blocks of boxes in order of their low x, in which every
    box of one block is held against every box of the other, and all blocks against all. Of two blocks
    whose extents are apart no box can meet, which settles all their pairs at once."""
    by = float(predicate[1]) if isinstance(predicate, tuple) else 0.0
    gap_squared = by * by
    predicate_of(predicate, "r", "s")  # refuses unknown names

    def blocks(boxes: DataFrame) -> DataFrame:
        return settled(global_rank(boxes.select("id", *BOX), "xmin", "id").withColumn("block", F.floor(F.col("rank") / BLOCK)).drop("rank"))

    a, b = blocks(r), blocks(s)
    extents = [x.groupBy("block").agg(*(F.min(c).alias(c) for c in BOX[:2]), *(F.max(c).alias(c) for c in BOX[2:])) for x in (a, b)]
    met = inflate(extents[0], by).alias("r").join(extents[1].alias("s"), predicate_of("intersects", "r", "s"))
    met = settled(met.select(F.col("r.block").alias("r_block"), F.col("s.block").alias("block")))
    near = b.join(small(met, met.count()), "block").select(F.col("r_block").alias("block"), "id", *BOX)

    def run(x: pa.Table, y: pa.Table) -> pa.Table:
        p, q = ([t.column(c).to_numpy() for c in BOX] for t in (x, y))
        r_id, s_id = x.column("id").to_numpy(), y.column("id").to_numpy()
        left, right = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        step = max(1, AT_ONCE // max(1, len(s_id)))
        for at in range(0, len(r_id) if len(s_id) else 0, step):
            u = [c[at : at + step, None] for c in p]
            if isinstance(predicate, tuple):
                dx, dy = (np.maximum(0, np.maximum(u[k] - q[k + 2], q[k] - u[k + 2])) for k in (0, 1))
                ok = dx * dx + dy * dy <= gap_squared
            elif predicate == "overlaps":
                ok = (u[0] < q[2]) & (u[2] > q[0]) & (u[1] < q[3]) & (u[3] > q[1])
            elif predicate == "intersects":
                ok = (u[0] <= q[2]) & (u[2] >= q[0]) & (u[1] <= q[3]) & (u[3] >= q[1])
            else:
                big, little = (u, q) if predicate == "contains" else (q, u)
                ok = (big[0] <= little[0]) & (big[1] <= little[1]) & (big[2] >= little[2]) & (big[3] >= little[3])
            i, j = np.nonzero(ok)
            left.append(r_id[at + i])
            right.append(s_id[j])
        return pa.table({"r_id": pa.array(np.concatenate(left), pa.int64()), "s_id": pa.array(np.concatenate(right), pa.int64())})

    return a.groupBy("block").cogroup(near.groupBy("block")).applyInArrow(run, "r_id long, s_id long")


def duplicate_stats(r: DataFrame, s: DataFrame, layout: Layout) -> DataFrame:
    """Pairs found over all tiles, distinct pairs, and the repeats a de-duplication removes."""
    found = _multi(r, s, layout, "intersects", "none", "nested")
    return found.groupBy("r_id", "s_id").agg(F.count(F.lit(1)).alias("n")).agg(
        F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("found"), F.count(F.lit(1)).alias("pairs"), F.coalesce(F.sum(F.col("n") - 1), F.lit(0)).cast("long").alias("repeats")
    )


def pair_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Pairs of one result that the other lacks (precision and recall are 1 if there is none)."""
    cols = ["r_id", "s_id"]
    return a.select(cols).exceptAll(b.select(cols)).withColumn("only_in", F.lit("left")).unionByName(b.select(cols).exceptAll(a.select(cols)).withColumn("only_in", F.lit("right")))


def overlap_areas(pairs: DataFrame, r: DataFrame, s: DataFrame) -> DataFrame:
    """pairs with the area that their boxes have in common (post-processing of a join)."""
    a, b = (x.select(F.col("id").alias(f"{n}_id"), F.struct(*BOX).alias(n)) for x, n in ((r, "r"), (s, "s")))
    both = pairs.join(a, "r_id").join(b, "s_id")
    side = [F.greatest(F.lit(0.0), F.least(f"r.{c}max", f"s.{c}max") - F.greatest(f"r.{c}min", f"s.{c}min")) for c in "xy"]
    return both.select("r_id", "s_id", (side[0] * side[1]).alias("area"))


def with_matches(boxes: DataFrame, pairs: DataFrame, side: str = "r", matched: bool = True) -> DataFrame:
    """Boxes with at least one partner (semi join), or with none (anti join)."""
    ids = pairs.select(F.col(f"{side}_id").alias("id")).distinct()
    return boxes.join(ids, "id", "left_semi" if matched else "left_anti")


def match_counts(pairs: DataFrame, top: int | None = None) -> DataFrame:
    """Partners per object; the `top` largest, if wanted."""
    n = pairs.groupBy("r_id").agg(F.count(F.lit(1)).alias("partners"))
    return n.orderBy(F.desc("partners"), "r_id").limit(top) if top else n
