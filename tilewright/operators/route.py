"""Which tiles a box meets. Assignment is a predicate on every box, apart from how a layout was found."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.geometry import BOX, Box, centre, corner
from ..plans.layout import Layout
from ..store import BROADCAST_ROWS, small

#: Coarse lookup cells per axis at most; a tile or box in many cells is listed in each.
MOST_LOOKUP_CELLS = 512


def _cell(value: Column, low: float, extent: float, cells: int) -> Column:
    """Number of the cell that holds a coordinate; outside ones go to the nearest cell."""
    if extent <= 0:
        return F.lit(0).cast("long")
    at = F.floor((value - low) * float(cells) / extent)
    return F.greatest(F.lit(0), F.least(F.lit(cells - 1), at)).cast("long")


def _cell_range(axis: str, u: Box, cells: int, alias: str = "") -> Column:
    extent = u.high(axis) - u.low(axis)
    return F.sequence(
        _cell(corner(f"{axis}min", alias), u.low(axis), extent, cells), _cell(corner(f"{axis}max", alias), u.low(axis), extent, cells)
    )


def grid_tiles(layout: Layout) -> Column:
    """Array of the grid cells a box meets, by arithmetic alone."""
    mx, my = layout.params["cells"]
    u = layout.universe
    xs, ys = _cell_range("x", u, mx), _cell_range("y", u, my)
    return F.flatten(F.transform(ys, lambda j: F.transform(xs, lambda i: (j * mx + i).cast("int"))))


def meets(layout: Layout, box: str, tile: str, touch: str = "half_open") -> Column:
    """A box meets a tile: half-open for tilings (closed on the far edges), closed for packings."""
    b, t = box, tile
    if layout.kind == "packing" or touch == "closed":
        return (
            (corner("xmin", b) <= corner("xmax", t)) & (corner("xmax", b) >= corner("xmin", t))
            & (corner("ymin", b) <= corner("ymax", t)) & (corner("ymax", b) >= corner("ymin", t))
        )
    right = (corner("xmin", b) < corner("xmax", t)) | corner("last_x", t)
    upper = (corner("ymin", b) < corner("ymax", t)) | corner("last_y", t)
    u = layout.universe
    left = (corner("xmax", b) >= corner("xmin", t)) | (corner("xmin", t) <= u.xmin)
    lower = (corner("ymax", b) >= corner("ymin", t)) | (corner("ymin", t) <= u.ymin)
    return right & upper & left & lower


def _lookup_cells(k: int) -> int:
    return max(1, min(MOST_LOOKUP_CELLS, math.ceil(math.sqrt(k)) * 2))


#: Lookup cells that a tile of a packing may be listed in, on average, for the sake of finer cells.
CELLS_A_TILE = 16


def _cells_of(layout: Layout) -> int:
    """Lookup cells per axis. The tiles of a packing may crowd in a few cells, where each box is held against all of
    them; so cells are halved as long as the tiles, and with them the boxes, which are no larger, stay in few cells."""
    if "_cells" not in layout.params:
        u, cells = layout.universe, _lookup_cells(layout.count)
        if layout.kind == "packing":
            sizes = [cells << k for k in range(6)]
            per = [F.sum(F.size(_cell_range("x", u, c)).cast("long") * F.size(_cell_range("y", u, c))) for c in sizes]
            listed = layout.tiles.agg(*per).first()
            cells = max([cells, *(c for c, n in zip(sizes, listed) if (n or 0) <= min(CELLS_A_TILE * layout.count, BROADCAST_ROWS))])
        layout.params["_cells"] = cells
    return layout.params["_cells"]


def _low_corner_cell(u: Box, cells: int, b: str, t: str) -> tuple[Column, Column]:
    """The lookup cell of the low corner of box and tile in common: the one that reports the pair."""
    return tuple(
        _cell(F.greatest(corner(f"{a}min", b), corner(f"{a}min", t)), u.low(a), u.high(a) - u.low(a), cells) for a in ("x", "y")
    )


def _listed(layout: Layout, tiles: DataFrame, cells: int) -> int:
    """How many lookup cells the tiles are listed in; counted once for a layout."""
    if "_listed" not in layout.params:
        u = layout.universe
        per = F.size(_cell_range("x", u, cells)).cast("long") * F.size(_cell_range("y", u, cells))
        layout.params["_listed"] = tiles.agg(F.sum(per)).first()[0] or 0
    return layout.params["_listed"]


def explode_tiles(boxes: DataFrame, layout: Layout, touch: str = "half_open") -> DataFrame:
    """boxes with tile_id: a row for each tile that a box meets, in no particular order.

    A grid needs arithmetic only. Other layouts go through a coarse lookup grid: tiles and boxes are
    listed under the cells they meet, joined on the cell, and a pair is reported by the one cell that
    holds the low corner of their common part, so nothing has to be made distinct afterwards.
    """
    if layout.method == "fixed_grid" and touch == "half_open":
        return boxes.withColumn("tile_id", F.explode(grid_tiles(layout)))
    u, cells = layout.universe, _cells_of(layout)
    tiles = layout.tiles.select("tile_id", *BOX, "last_x", "last_y")
    listed = tiles.withColumn("_cy", F.explode(_cell_range("y", u, cells))).withColumn("_cx", F.explode(_cell_range("x", u, cells)))
    listed = listed.select(F.struct("tile_id", *BOX, "last_x", "last_y").alias("t"), "_cx", "_cy")
    spread = boxes.select(F.struct(*boxes.columns).alias("b")).withColumn("_cy", F.explode(_cell_range("y", u, cells, "b"))).withColumn("_cx", F.explode(_cell_range("x", u, cells, "b")))
    met = spread.join(small(listed, _listed(layout, tiles, cells)), ["_cx", "_cy"])
    ox, oy = _low_corner_cell(u, cells, "b", "t")
    met = met.filter(meets(layout, "b", "t", touch) & (F.col("_cx") == ox) & (F.col("_cy") == oy))
    return met.select("b.*", F.col("t.tile_id").alias("tile_id"))


def with_home(boxes: DataFrame, layout: Layout) -> DataFrame:
    """boxes with home_tile: of a tiling, the tile of the centre; of a packing, the first tile that
    holds the whole box (null where none does, as after sampling)."""
    if layout.kind == "tiling":
        spots = boxes.select(F.struct(*boxes.columns).alias("_row"), centre("x").alias("xmin"), centre("y").alias("ymin"), centre("x").alias("xmax"), centre("y").alias("ymax"))
        return explode_tiles(spots, layout).select("_row.*", F.col("tile_id").alias("home_tile"))
    tiles = layout.tiles.select("tile_id", *(F.col(c).alias(f"t{c}") for c in BOX))
    met = explode_tiles(boxes, layout).join(small(tiles, layout.count), "tile_id")
    inside = (F.col("txmin") <= F.col("xmin")) & (F.col("txmax") >= F.col("xmax")) & (F.col("tymin") <= F.col("ymin")) & (F.col("tymax") >= F.col("ymax"))
    home = met.groupBy("id").agg(F.min(F.when(inside, F.col("tile_id"))).alias("home_tile"))
    return boxes.join(home, "id", "left")


def assign(boxes: DataFrame, layout: Layout, *, tiles: bool | None = None, touch: str = "half_open") -> DataFrame:
    """The assignment relation: each box with tile_id, and for packings (or tiles=True) the array
    `tiles` of all its tiles, which costs a shuffle on the id."""
    out = explode_tiles(boxes, layout, touch)
    if tiles if tiles is not None else layout.kind == "packing":
        lists = out.groupBy("id").agg(F.array_sort(F.collect_set("tile_id")).alias("tiles"))
        out = boxes.join(lists, "id").withColumn("tile_id", F.explode("tiles"))
    return out


#: Cells per axis of a Lookup, candidates that it tests at once, and boxes that are looked up together. The order of tiles is that of their numbers times MIXED, modulo 2^31.
MOST_CELLS, AT_ONCE, ROWS, MIXED = 1 << 14, 1 << 20, 2048, 0x9E3779B1

#: A tile's band is so many boxes of mean size wide, and a tile has so many bands at most.
BOXES_A_BAND, MOST_BANDS = 4, 64


class Lookup:
    """Which of k closed boxes (rows of corners) others meet, by a grid whose cells follow the boxes' shape.

    An axis is halved, always the one that adds fewer entries, as long as a box is listed in
    CELLS_A_TILE cells on average.
    """

    def __init__(self, corners: np.ndarray):
        self.corners = corners
        k = len(corners)
        self.low = corners[:, :2].min(0) if k else np.zeros(2)
        self.extent = corners[:, 2:].max(0) - self.low if k else np.zeros(2)
        self.n = [1, 1]
        while k:
            more = [[self.n[0] * (1 + (d == 0)), self.n[1] * (1 + (d == 1))] for d in (0, 1) if self.extent[d] > 0 and self.n[d] < MOST_CELLS]
            listed = [int(np.prod(self.span(corners, n)[1], axis=0).sum()) for n in more]
            if not more or min(listed) > CELLS_A_TILE * k:
                break
            self.n = more[listed.index(min(listed))]
        self.first, size = self.span(corners, self.n)
        box, cell = self.cells(self.first, size, np.arange(k))
        self.code = np.sort(cell * max(1, k) + box)
        self.box = self.code % max(1, k)

    def span(self, b: np.ndarray, n: list[int]) -> tuple[np.ndarray, np.ndarray]:
        """The lowest cell per axis of each box, and how many cells it has on that axis."""
        lows, sizes = [], []
        for d in (0, 1):
            scale = n[d] / self.extent[d] if self.extent[d] > 0 else 0.0
            low, high = (np.clip(np.floor((b[:, c] - self.low[d]) * scale), 0, n[d] - 1).astype(np.int64) for c in (d, d + 2))
            lows.append(low)
            sizes.append(high - low + 1)
        return np.array(lows), np.array(sizes)

    def cells(self, low: np.ndarray, size: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """A row number and a cell's number for each cell of the rows."""
        each = size[0, rows] * size[1, rows]
        at = np.repeat(rows, each)
        k = np.arange(len(at)) - np.repeat(np.cumsum(each) - each, each)
        return at, (low[0, at] + k // size[1, at]) * self.n[1] + low[1, at] + k % size[1, at]

    def holder(self, b: np.ndarray, cell: np.ndarray) -> np.ndarray:
        """The first of the corners that hold each row of b whole (the last of all if none does), of those in the row's lowest cell."""
        k = len(self.corners)
        out = np.full(len(b), k - 1)
        at, end = (np.searchsorted(self.code, (cell + d) * k) for d in (0, 1))
        todo, step = np.flatnonzero(at < end), 4
        while len(todo):
            spot = at[todo][:, None] + np.arange(step)
            t, p = self.box[np.minimum(spot, len(self.box) - 1)], b[todo][:, None]
            q = self.corners[t]
            ok = (spot < end[todo][:, None]) & (q[..., :2] <= p[..., :2]).all(2) & (q[..., 2:] >= p[..., 2:]).all(2)
            hit = ok.any(1)
            out[todo[hit]] = t[hit, ok[hit].argmax(1)]
            at[todo] += step
            todo = todo[~hit & (at[todo] < end[todo])]
            step = min(step * 2, 64)
        return out

    def leading(self, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows of b and of the corners that meet (closed), in order, up to the first of the corners that holds the row whole."""
        low, size = self.span(b, self.n)
        each, k = size[0] * size[1], len(self.corners)
        if not k or not len(b):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        last = self.holder(b, low[0] * self.n[1] + low[1])
        out = [np.zeros(0, np.int64)]

        def test(i, j, cell=None):
            p, q = b[i], self.corners[j]
            ok = (p[:, 0] <= q[:, 2]) & (p[:, 2] >= q[:, 0]) & (p[:, 1] <= q[:, 3]) & (p[:, 3] >= q[:, 1])
            if cell is not None:  # Of the cells in common, the lowest reports the pair.
                ok &= np.maximum(low[0, i], self.first[0, j]) * self.n[1] + np.maximum(low[1, i], self.first[1, j]) == cell
            out.append(i[ok] * k + j[ok])

        # Boxes of more cells than there are tiles are held against all tiles.
        for i in np.flatnonzero(each > k):
            test(np.full(last[i] + 1, i), np.arange(last[i] + 1))
        at, cell = self.cells(low, size, np.flatnonzero(each <= k))
        begin = np.searchsorted(self.code, cell * k)
        n = np.searchsorted(self.code, cell * k + last[at], "right") - begin
        done = np.cumsum(n)
        i = 0
        while i < len(at):
            j = max(i + 1, int(np.searchsorted(done, (done[i - 1] if i else 0) + AT_ONCE, "right")))
            m = n[i:j]
            spot = np.repeat(np.arange(i, j), m)
            entry = np.arange(len(spot)) - np.repeat(np.cumsum(m) - m, m) + begin[spot]
            test(at[spot], self.box[entry], cell[spot])
            i = j
        pairs = np.sort(np.concatenate(out))
        return pairs // k, pairs % k


def leading_tiles(boxes: DataFrame, layout: Layout, size: tuple[float, float] = (0.0, 0.0)) -> DataFrame:
    """boxes with what a join on the least tile in common needs of the assignment to a packing: tile_id, `tiles` (those
    up to this one), and the bands `band` (from `low` on) of the tile that the box is in.

    Tiles are numbered in another order, which takes neighbours apart. Those after the first that holds a box
    whole are left out: whatever meets the box meets that tile, too, so no later one is the least in common
    with anything. Bands cut a tile along the axis on which boxes of mean `size` are the smaller part of it;
    a box beside the tile is in the nearest one. Two boxes that meet have bands in common, of which the larger
    `low` is one. Tiles too many for a broadcast are found by shuffles, and are one band each.
    """
    if layout.kind != "packing" or layout.count > BROADCAST_ROWS:
        return assign(boxes, layout, tiles=True).withColumns({"low": F.lit(0), "band": F.lit(0)})
    rows = layout.rows()  # the layout, whose size is counted
    number = np.array([r["tile_id"] for r in rows], np.int64) * MIXED & 0x7FFFFFFF
    corners = np.array([[r[c] for c in BOX] for r in rows], np.float64).reshape(-1, 4)[number.argsort()]
    number = np.sort(number).astype(np.int32)
    parts = np.array([(corners[:, d + 2] - corners[:, d]) / max(size[d], 1e-9) / BOXES_A_BAND for d in (0, 1)])
    axis = parts.argmax(0)
    bands = np.clip(parts.max(0), 1, MOST_BANDS).astype(np.int64) if any(size) else np.ones(len(corners), np.int64)
    shared = boxes.sparkSession.sparkContext.broadcast((corners, number, axis, bands))

    def found(batches):
        corners, number, axis, bands = shared.value
        lookup, spots = Lookup(corners), np.arange(len(corners))
        low, extent = corners[spots, axis], corners[spots, axis + 2] - corners[spots, axis]
        scale = np.divide(bands, extent, out=np.zeros(len(corners)), where=extent > 0)
        for batch in (whole.slice(k, ROWS) for whole in batches for k in range(0, whole.num_rows, ROWS)):
            b = np.column_stack([batch.column(c).to_numpy(zero_copy_only=False) for c in BOX])
            i, t = lookup.leading(b)
            edge = np.flatnonzero(np.r_[True, i[1:] != i[:-1]][: len(i)])
            first, last = (np.clip(np.floor((b[i, axis[t] + d] - low[t]) * scale[t]), 0, bands[t] - 1).astype(np.int32) for d in (0, 2))
            lists = pa.ListArray.from_arrays(pa.array(np.r_[edge, len(i)].astype(np.int32)), pa.StructArray.from_arrays([pa.array(number[t]), pa.array(first), pa.array(last)], ["t", "low", "high"]))
            yield pa.RecordBatch.from_arrays([*batch.take(pa.array(i[edge])).columns, lists], [*batch.schema.names, "_met"])

    kind = T.ArrayType(T.StructType([T.StructField(c, T.IntegerType()) for c in ("t", "low", "high")]))
    met = boxes.mapInArrow(found, T.StructType([*boxes.schema, T.StructField("_met", kind)]))
    met = met.select(*boxes.columns, F.col("_met.t").alias("tiles"), F.posexplode("_met").alias("_k", "_at"))
    return met.select(*boxes.columns, F.slice("tiles", F.lit(1), F.col("_k") + 1).alias("tiles"), F.col("_at.t").alias("tile_id"), F.col("_at.low").alias("low"), F.explode(F.sequence("_at.low", "_at.high")).alias("band"))


def uncovered(boxes: DataFrame, layout: Layout) -> DataFrame:
    """Boxes that meet no tile (possible only for packings made from a sample)."""
    return boxes.join(explode_tiles(boxes, layout).select("id").distinct(), "id", "left_anti")


def stage(boxes: DataFrame, layout: Layout, path: str, groups: int = 64) -> None:
    """Write the assignment clustered by tile: a directory per group of tiles, tiles sorted inside."""
    out = assign(boxes, layout, tiles=False).withColumn("tile_group", (F.col("tile_id") % groups).cast("int"))
    out.repartition(groups, "tile_group").sortWithinPartitions("tile_id").write.partitionBy("tile_group").parquet(path, mode="overwrite")


def prefilter(boxes: DataFrame, window: Box) -> DataFrame:
    """Boxes that meet a window; plain comparisons, which reach the parquet scan."""
    return boxes.filter(
        (F.col("xmin") <= window.xmax) & (F.col("xmax") >= window.xmin) & (F.col("ymin") <= window.ymax) & (F.col("ymax") >= window.ymin)
    )
