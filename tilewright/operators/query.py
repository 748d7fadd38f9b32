"""Window and nearest-neighbour queries on boxes staged by tile."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geometry import BOX, Box
from ..plans.layout import Layout
from .route import prefilter


def window_query(staged: DataFrame, layout: Layout, window: Box, groups: int = 64) -> DataFrame:
    """Boxes that meet a window, from the tile groups whose tiles meet it (partition pruning), each once."""
    met = layout.tiles.filter(
        (F.col("xmin") <= window.xmax) & (F.col("xmax") >= window.xmin) & (F.col("ymin") <= window.ymax) & (F.col("ymax") >= window.ymin)
    )
    wanted = sorted({r[0] for r in met.select(F.col("tile_id") % groups).distinct().collect()})  # at most `groups` rows
    found = staged.filter(F.col("tile_group").isin(wanted)) if wanted else staged.filter(F.lit(False))
    return prefilter(found, window).dropDuplicates(["id"]).select("id", *BOX)


def read_staged(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def distance_squared(x: float, y: float):
    zero = F.lit(0.0)
    dx = F.greatest(zero, F.col("xmin") - x, F.lit(float(x)) - F.col("xmax"))
    dy = F.greatest(zero, F.col("ymin") - y, F.lit(float(y)) - F.col("ymax"))
    return dx * dx + dy * dy


def nearest(boxes: DataFrame, layout: Layout, x: float, y: float, n: int) -> DataFrame:
    """The n boxes nearest to a point, ties by id.

    Tiles are taken by their distance; once they plan to hold n objects, the n-th distance among them
    bounds the ring that is searched (a window, which prunes), so far tiles are not read.
    """
    near = boxes
    found = prefilter(boxes, _ring(layout, x, y, n)).withColumn("d2", distance_squared(x, y))
    top = found.orderBy("d2", "id").limit(n).collect()
    if len(top) == n:
        reach = top[-1]["d2"] ** 0.5
        near = prefilter(boxes, Box(x - reach, y - reach, x + reach, y + reach))
    return near.withColumn("d2", distance_squared(x, y)).orderBy("d2", "id").limit(n).select("id", "d2")


def _ring(layout: Layout, x: float, y: float, n: int) -> Box:
    """A window over the nearest tiles that together are planned for n objects or more."""
    zero = F.lit(0.0)
    dx = F.greatest(zero, F.col("xmin") - x, F.lit(float(x)) - F.col("xmax"))
    dy = F.greatest(zero, F.col("ymin") - y, F.lit(float(y)) - F.col("ymax"))
    per = layout.params.get("payload") or n
    rows = layout.tiles.orderBy(dx * dx + dy * dy, "tile_id").limit(max(1, -(-n // per)) + 1).collect()
    return Box(min(r.xmin for r in rows), min(r.ymin for r in rows), max(r.xmax for r in rows), max(r.ymax for r in rows))
