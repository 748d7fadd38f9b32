"""Tile loads of a stream of events over a static layout, with watermarks and overload alarms."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geometry import BOX
from ..operators.route import explode_tiles
from ..plans.layout import Layout

EVENT_SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_points(events: DataFrame) -> DataFrame:
    """Events as points: hour of day by value in cents."""
    hour = (F.hour("ts") * 60 + F.minute("ts")).cast("double")
    cents = F.round(F.col("value") * 100)
    return events.select(F.col("event_id").alias("id"), F.col("ts").cast("timestamp").alias("ts"), "user_id", hour.alias("xmin"), cents.alias("ymin"), hour.alias("xmax"), cents.alias("ymax"))


def replay(spark: SparkSession, path: str, schema=None, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files under path as a stream."""
    return spark.readStream.schema(schema or EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def routed(points: DataFrame, layout: Layout) -> DataFrame:
    """Stream-static routing by the broadcast layout."""
    return explode_tiles(points, layout)


def tile_load(points: DataFrame, layout: Layout, window: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Objects per tile and tumbling (or sliding) window; the same plan for batches and streams."""
    if points.isStreaming:
        points = points.withWatermark("ts", late)
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return routed(points, layout).groupBy(w.alias("w"), "tile_id").agg(F.count(F.lit(1)).alias("load")).select(F.col("w.start").alias("window_start"), "tile_id", "load")


def session_load(points: DataFrame, layout: Layout, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Objects per tile and session of activity."""
    if points.isStreaming:
        points = points.withWatermark("ts", late)
    return routed(points, layout).groupBy(F.session_window("ts", gap).alias("w"), "tile_id").agg(F.count(F.lit(1)).alias("load")).select(
        F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"), "tile_id", "load"
    )


def overloads(points: DataFrame, layout: Layout, limit: int) -> DataFrame:
    """A row (tile_id, load) whenever a tile's running count first passes the limit: a wish to split it."""

    def count(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        (n,) = state.get if state.exists else (0,)
        before = n
        for f in frames:
            n += len(f)
        state.update((n,))
        if before <= limit < n:
            yield pd.DataFrame({"tile_id": [key[0]], "load": [n]})

    at = routed(points, layout).select("tile_id", "id")
    return at.groupBy("tile_id").applyInPandasWithState(count, "tile_id int, load long", "n long", "append", "NoTimeout")


def distinct_objects(points: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each id once within the watermark."""
    return points.withWatermark("ts", late).dropDuplicatesWithinWatermark(["id"])


def late_share(points: DataFrame, late_seconds: int = 3600, bin_ids: int = 3600) -> DataFrame:
    """How many points arrive over late_seconds behind the latest before them, in id (arrival) order:
    those a watermark of that delay may drop. Ids are cut into bins, and bins into bins of bins, until
    one row is left: no window spans more than `bin_ids` bins."""
    from pyspark.sql.window import Window

    levels = [points.select("id", "ts").groupBy(F.floor(F.col("id") / bin_ids).alias("bin")).agg(F.max("ts").alias("top"))]
    for _ in range(5):  # bin_ids ** 6 is beyond any id
        levels.append(levels[-1].groupBy(F.floor(F.col("bin") / bin_ids).alias("bin")).agg(F.max("top").alias("top")))
    before = levels[-1].select("bin", F.lit(None).cast("timestamp").alias("before"))
    for level in reversed(levels[:-1]):
        parts = level.withColumn("up", F.floor(F.col("bin") / bin_ids)).join(before.withColumnRenamed("bin", "up"), "up", "left")
        w = Window.partitionBy("up").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
        before = parts.select("bin", F.greatest(F.max("top").over(w), "before").alias("before"))
    both = points.withColumn("bin", F.floor(F.col("id") / bin_ids)).join(before, "bin", "left")
    running = F.max("ts").over(Window.partitionBy("bin").orderBy("id").rowsBetween(Window.unboundedPreceding, -1))
    seen = F.greatest(running, F.col("before"))
    return both.select((seen.cast("long") - F.col("ts").cast("long") > late_seconds).alias("late")).agg(F.count_if("late").alias("late"), F.count(F.lit(1)).alias("points"))


def latest_layouts(versions: DataFrame) -> DataFrame:
    """Of versioned tile rows (version, tile_id, ...), those of the newest version."""
    newest = versions.agg(F.max("version").alias("version"))
    return versions.join(F.broadcast(newest), "version", "left_semi").select("version", "tile_id", *BOX)
