"""Quality of a layout: balance, boundary objects, agreement with another layout."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions.geometry import BOX
from .operators.route import explode_tiles
from .plans.layout import Layout
from .store import small


def payloads(assigned: DataFrame, layout: Layout) -> DataFrame:
    """tile_id and payload (objects, replicas included) of every tile, empty ones too."""
    counted = assigned.groupBy("tile_id").agg(F.count(F.lit(1)).alias("n"))
    return counted.join(layout.tiles.select("tile_id"), "tile_id", "right").select("tile_id", F.coalesce("n", F.lit(0)).cast("long").alias("payload"))


def quality_of_payloads(loads: DataFrame, objects: int, payload: int | None = None) -> DataFrame:
    """One row: k, objects, total, lambda (replicated share), sigma (population, over all tiles), its
    sample and non-empty variants, largest and mean payload, their ratio, empty tiles, overflow share."""
    n = F.col("payload")
    return loads.agg(
        F.count(F.lit(1)).alias("k"), F.lit(objects).cast("long").alias("objects"), F.sum(n).alias("total"),
        (F.sum(n) / F.lit(max(1, objects)) - 1).alias("lambda"), F.stddev_pop(n).alias("sigma"), F.stddev_samp(n).alias("sigma_sample"),
        F.stddev_pop(F.when(n > 0, n)).alias("sigma_non_empty"), F.max(n).alias("largest"), F.avg(n).alias("mean"), (F.max(n) / F.avg(n)).alias("largest_to_mean"),
        F.count_if(n == 0).alias("empty"), (F.count_if(n > F.lit(payload)) / F.count(F.lit(1))).alias("overflow_share"),
    )


def quality(boxes: DataFrame, layout: Layout, payload: int | None = None) -> DataFrame:
    assigned = explode_tiles(boxes.select("id", *BOX), layout)
    return quality_of_payloads(payloads(assigned, layout), boxes.count(), payload or layout.params.get("payload"))


def boundary_ratio(assigned: DataFrame, objects: int | None = None, approximate: bool = False) -> DataFrame:
    """lambda: replicas per object. approximate: count distinct objects by a sketch."""
    if objects is not None:
        distinct = F.lit(objects)
    else:
        distinct = F.approx_count_distinct("id") if approximate else F.count_distinct("id")
    return assigned.agg((F.count(F.lit(1)) / distinct - 1).alias("lambda"))


def boundary_objects(assigned: DataFrame) -> DataFrame:
    """Number and share of objects that meet more than one tile, and the most tiles of one object."""
    per = assigned.groupBy("id").agg(F.count(F.lit(1)).alias("n"))
    return per.agg(
        F.count_if(F.col("n") > 1).alias("boundary_objects"), F.count(F.lit(1)).alias("objects"),
        (F.count_if(F.col("n") > 1) / F.count(F.lit(1))).alias("share"), F.max("n").alias("most_tiles"),
    )


def replica_share_per_tile(boxes: DataFrame, layout: Layout) -> DataFrame:
    """alpha of each tile: its boxes at home elsewhere, as a share of the mean tile's objects."""
    from .operators.route import with_home

    homed = with_home(boxes.select("id", *BOX), layout)
    met = explode_tiles(homed, layout)
    n = boxes.count()
    return met.groupBy("tile_id").agg((F.count_if(~F.col("home_tile").eqNullSafe(F.col("tile_id"))) / F.lit(max(1, n) / layout.count)).alias("alpha"))


def fullest(loads: DataFrame, n: int = 10) -> DataFrame:
    return loads.orderBy(F.desc("payload"), "tile_id").limit(n)


def layout_agreement(boxes: DataFrame, a: Layout, b: Layout, pairs: int = 20_000, seed: int = 1) -> DataFrame:
    """How alike two layouts group objects: adjusted agreement over neighbouring pairs in a random
    order, 1 for equal groupings and about 0 for unrelated ones; with both sigma and lambda differences."""
    from .operators.route import with_home

    ids = boxes.select("id", *BOX)
    left = with_home(ids, a).select("id", F.col("home_tile").alias("ta"))
    right = with_home(ids, b).select("id", F.col("home_tile").alias("tb"))
    both = left.join(right, "id").select("id", "ta", "tb")
    # The adjusted Rand index from the contingency table: its sums need no pair to be formed.
    choose = lambda c: F.col(c) * (F.col(c) - 1) / 2
    cells = both.groupBy("ta", "tb").agg(F.count(F.lit(1)).alias("n"))
    inner = cells.agg(F.sum(choose("n")).alias("joint"), F.sum("n").alias("total"))
    rows = cells.groupBy("ta").agg(F.sum("n").alias("n")).agg(F.sum(choose("n")).alias("ra"))
    cols = cells.groupBy("tb").agg(F.sum("n").alias("n")).agg(F.sum(choose("n")).alias("rb"))
    i, r, c = inner.first(), rows.first(), cols.first()
    qa, qb = quality(boxes, a).first(), quality(boxes, b).first()
    total = (i["total"] or 0) * ((i["total"] or 0) - 1) / 2
    expected = (r["ra"] or 0) * (c["rb"] or 0) / total if total else 0.0
    most = ((r["ra"] or 0) + (c["rb"] or 0)) / 2
    value = ((i["joint"] or 0) - expected) / (most - expected) if most != expected else 1.0
    return boxes.sparkSession.createDataFrame(
        [(float(value), float(qb["sigma"] - qa["sigma"]), float(qb["lambda"] - qa["lambda"]))], "agreement double, sigma_change double, lambda_change double"
    )


def products(r: DataFrame, s: DataFrame, layout: Layout) -> DataFrame:
    """tile_id, objects of either side and their product: the comparisons of a nested tile join."""
    a = explode_tiles(r.select("id", *BOX), layout).groupBy("tile_id").agg(F.count(F.lit(1)).alias("r_n"))
    b = explode_tiles(s.select("id", *BOX), layout).groupBy("tile_id").agg(F.count(F.lit(1)).alias("s_n"))
    both = a.join(b, "tile_id", "full").join(small(layout.tiles.select("tile_id"), layout.count), "tile_id", "right")
    both = both.select("tile_id", F.coalesce("r_n", F.lit(0)).alias("r_n"), F.coalesce("s_n", F.lit(0)).alias("s_n"))
    return both.withColumn("work", F.col("r_n") * F.col("s_n"))
