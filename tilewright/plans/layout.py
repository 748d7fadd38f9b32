"""A layout is a small table of tiles with the universe they cut."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geometry import Box

TILE_SCHEMA = (
    "tile_id int, xmin double, ymin double, xmax double, ymax double, last_x boolean, last_y boolean, planned long, level int, bucket int"
)


@dataclass
class Layout:
    """tiles: TILE_SCHEMA rows. kind `tiling`: half-open tiles that cover the universe once, closed on
    its far edges. kind `packing`: closed extents of groups of objects, which may overlap."""

    kind: str
    universe: Box
    tiles: DataFrame
    method: str
    count: int
    params: dict[str, Any] = field(default_factory=dict)

    def rows(self) -> list:
        """The tiles on the driver (k rows, not objects)."""
        return self.tiles.orderBy("tile_id").collect()


def payload_of(fraction: float, n: int) -> int:
    """Objects per tile for a share of the dataset."""
    return max(1, -(-int(round(fraction * n * 1e9)) // 10**9))


def make_tiles(spark: SparkSession, universe: Box, boxes: list[tuple], method: str, kind: str = "tiling", **params) -> Layout:
    """A layout of driver-side tiles (xmin, ymin, xmax, ymax[, planned[, level[, bucket]]])."""
    rows = []
    for i, (x0, y0, x1, y1, *more) in enumerate(boxes):
        planned, level, bucket = (*more, *(None, None, None)[len(more) :])
        rows.append((i, float(x0), float(y0), float(x1), float(y1), x1 >= universe.xmax, y1 >= universe.ymax, planned, level, bucket))
    return Layout(kind, universe, spark.createDataFrame(rows, TILE_SCHEMA), method, len(rows), params)


def packed(groups: DataFrame, universe: Box, method: str, **params) -> Layout:
    """A packing of a frame with tile_id, extent and planned."""
    tiles = groups.select(
        F.col("tile_id").cast("int"), "xmin", "ymin", "xmax", "ymax", F.lit(False).alias("last_x"), F.lit(False).alias("last_y"),
        F.col("planned").cast("long"), F.lit(None).cast("int").alias("level"), F.lit(None).cast("int").alias("bucket"),
    )
    from ..store import settled

    tiles = settled(tiles)
    return Layout("packing", universe, tiles, method, tiles.count(), params)


TAXONOMY = [
    ("binary_split", "non-overlapping", "top-down", "space"),
    ("fixed_grid", "non-overlapping", "n/a", "space"),
    ("strip", "non-overlapping", "bottom-up", "data"),
    ("least_cut_strip", "non-overlapping", "bottom-up", "data"),
    ("sort_tile", "overlapping", "bottom-up", "data"),
    ("curve_pack", "overlapping", "bottom-up", "data"),
]


def describe(spark: SparkSession) -> DataFrame:
    """How the methods differ: boundary, search strategy, split criterion. (The binary split is filed
    under space although its cut is a median of the data.)"""
    return spark.createDataFrame(TAXONOMY, "method string, boundary string, search string, criterion string")
