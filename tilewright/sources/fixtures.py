"""Box datasets built on the given tables. All coordinates of the box sets are whole numbers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

BOX_COLUMNS = ["id", "xmin", "ymin", "xmax", "ymax"]


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _around(df: DataFrame, cx, cy, hx, hy, *more: str) -> DataFrame:
    return df.select(
        "id", *more, (cx - hx).cast("double").alias("xmin"), (cy - hy).cast("double").alias("ymin"),
        (cx + hx).cast("double").alias("xmax"), (cy + hy).cast("double").alias("ymax"),
    )


def even_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Evenly spread small boxes: order date by price."""
    o = read(spark, sf_dir, "orders").withColumn("id", F.col("o_orderkey"))
    cx = F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")) * F.lit(1000)
    cy = F.floor(F.round(F.col("o_totalprice") * 100) / 20)
    return _around(o, cx, cy, 500 + 500 * (F.col("o_custkey") % 7), 500 + 300 * (F.col("o_orderkey") % 11))


def _skewed(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events")
    n = e.count()
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    k = F.get_json_object("props", "$.k").cast("long")
    size = F.lit(int(1_000_000 // n**0.5 if n else 0)).cast("long")
    return e.select(
        F.col("event_id").alias("id"), "event_type",
        (F.round(F.col("value") * 100) * 100).alias("cx"),
        (F.round(F.coalesce(F.lead("value").over(w), F.col("value")) * 100) * 100).alias("cy"),
        (size * k * k * k * k * k * k).alias("_scaled"),
    ).withColumn("h", F.expr(f"_scaled div {99**6}")).withColumn("o", F.expr("(id div 2) % 2")).drop("_scaled")


def skew_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A hotspot with few large and many tiny boxes: an event's value by the user's next one."""
    e = _skewed(spark, sf_dir)
    return _around(e, F.col("cx"), F.col("cy"), F.col("h") * (1 + F.col("o")), F.col("h") * (2 - F.col("o")))


def typed_skew_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """skew_boxes with event_type."""
    e = _skewed(spark, sf_dir)
    return _around(e, F.col("cx"), F.col("cy"), F.col("h") * (1 + F.col("o")), F.col("h") * (2 - F.col("o")), "event_type")


def skew_wide_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same, every box twice as wide as high."""
    e = _skewed(spark, sf_dir)
    return _around(e, F.col("cx"), F.col("cy"), F.col("h") * 2, F.col("h"))


def span_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Large stacked boxes: each user-day's extent in time and value."""
    e = read(spark, sf_dir, "events").select(
        "user_id", F.to_date("ts").alias("day"), F.dayofmonth("ts").alias("dom"),
        F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)").cast("double").alias("t"), F.round(F.col("value") * 100).alias("v"),
    )
    return e.groupBy("user_id", "day", "dom").agg(F.min("t").alias("xmin"), F.min("v").alias("ymin"), F.max("t").alias("xmax"), F.max("v").alias("ymax")).select(
        (F.col("user_id") * 100 + F.col("dom")).alias("id"), "xmin", "ymin", "xmax", "ymax"
    )


def line_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Volume: line items, ship day by price."""
    l = read(spark, sf_dir, "lineitem").withColumn(
        "id", ((F.col("l_orderkey") * 8 + F.col("l_linenumber")) * 100000 + F.col("l_partkey")) * 10000 + F.col("l_suppkey")
    )
    cx = F.datediff("l_shipdate", F.lit("1995-01-01").cast("date")) * F.lit(1000)
    cy = F.floor(F.round(F.col("l_extendedprice") * 100) / 4)
    b = _around(l, cx, cy, F.col("l_quantity") * 10, F.round(F.col("l_discount") * 100) * 500)
    return b.groupBy("id").agg(F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax"))


def diag_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Extremely skewed points: characters by blank-separated tokens of a document."""
    x, y = F.col("n_chars").cast("double"), F.size(F.split("text", " ")).cast("double")
    return read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), x.alias("xmin"), y.alias("ymin"), x.alias("xmax"), y.alias("ymax"))


def gauss_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mildly clustered points: the first two components of an embedding."""
    x, y = F.get("embedding", 0).cast("double"), F.get("embedding", 1).cast("double")
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), x.alias("xmin"), y.alias("ymin"), x.alias("xmax"), y.alias("ymax"))


FIXTURES = {
    "even": even_boxes, "skew": skew_boxes, "skew_wide": skew_wide_boxes, "span": span_boxes,
    "line": line_boxes, "diag": diag_points, "gauss": gauss_points,
}


def halves(boxes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Boxes of even and of odd id."""
    return boxes.filter(F.col("id") % 2 == 0), boxes.filter(F.col("id") % 2 == 1)


def rows(spark: SparkSession, values: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(int(i), *map(float, b)) for i, *b in values], "id long, xmin double, ymin double, xmax double, ymax double")


def toy_strip(spark: SparkSession) -> DataFrame:
    spans = [(0, 1), (0.5, 5.5), (4, 6), (5, 7), (8, 9), (9, 11)]
    return rows(spark, [(i, a, 0, b, 1) for i, (a, b) in enumerate(spans)])


def toy_four_tiles(spark: SparkSession) -> DataFrame:
    """A 4 x 4 universe of 2 x 2 tiles: 2, 2, 5 and 2 small boxes, and one over the middle."""
    spots = [(0, 0), (1, 1.2), (2.3, 0), (3.2, 1), (0, 2.2), (0.2, 3), (0.6, 2.4), (1, 3), (1.3, 2.5), (2.4, 3), (3.5, 3.5)]
    small = [(i, x, y, x + 0.5, y + 0.5) for i, (x, y) in enumerate(spots)]
    return rows(spark, [*small, (11, 1.5, 1.5, 2.5, 2.5)])


def toy_32(spark: SparkSession, sf_dir: str) -> DataFrame:
    return even_boxes(spark, sf_dir).orderBy("id").limit(32)
