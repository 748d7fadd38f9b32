"""Boxes as four flat double columns, and predicates on them as column expressions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BOX = ("xmin", "ymin", "xmax", "ymax")


@dataclass(frozen=True)
class Box:
    xmin: float
    ymin: float
    xmax: float
    ymax: float

    @property
    def width(self) -> float:
        return self.xmax - self.xmin

    @property
    def height(self) -> float:
        return self.ymax - self.ymin

    def low(self, axis: str) -> float:
        return self.xmin if axis == "x" else self.ymin

    def high(self, axis: str) -> float:
        return self.xmax if axis == "x" else self.ymax


def corner(name: str, alias: str = "") -> Column:
    return F.col(f"{alias}.{name}" if alias else name)


def centre(axis: str, alias: str = "") -> Column:
    return (corner(f"{axis}min", alias) + corner(f"{axis}max", alias)) / 2


def intersects(a: str, b: str) -> Column:
    """Closed boxes a and b share a point."""
    return (
        (corner("xmin", a) <= corner("xmax", b)) & (corner("xmax", a) >= corner("xmin", b))
        & (corner("ymin", a) <= corner("ymax", b)) & (corner("ymax", a) >= corner("ymin", b))
    )


def overlaps(a: str, b: str) -> Column:
    """The interiors of a and b share a point: touching is not enough."""
    return (
        (corner("xmin", a) < corner("xmax", b)) & (corner("xmax", a) > corner("xmin", b))
        & (corner("ymin", a) < corner("ymax", b)) & (corner("ymax", a) > corner("ymin", b))
    )


def contains(a: str, b: str) -> Column:
    return (
        (corner("xmin", a) <= corner("xmin", b)) & (corner("xmax", a) >= corner("xmax", b))
        & (corner("ymin", a) <= corner("ymin", b)) & (corner("ymax", a) >= corner("ymax", b))
    )


def gap_squared(a: str, b: str) -> Column:
    """Squared distance between the nearest points of two boxes."""
    zero = F.lit(0.0)
    dx = F.greatest(zero, corner("xmin", a) - corner("xmax", b), corner("xmin", b) - corner("xmax", a))
    dy = F.greatest(zero, corner("ymin", a) - corner("ymax", b), corner("ymin", b) - corner("ymax", a))
    return dx * dx + dy * dy


def predicate(name: str | tuple, a: str, b: str) -> Column:
    """A topology predicate by name: intersects, overlaps, contains, within or ("dwithin", d)."""
    if isinstance(name, tuple):
        kind, d = name
        if kind != "dwithin":
            raise ValueError(f"unknown predicate {name}")
        return gap_squared(a, b) <= float(d) ** 2
    found = {"intersects": intersects(a, b), "overlaps": overlaps(a, b), "contains": contains(a, b), "within": contains(b, a)}
    if name not in found:
        raise ValueError(f"unknown predicate {name}")
    return found[name]


def inflate(boxes: DataFrame, by: float) -> DataFrame:
    """Grow every box by `by` on each side."""
    return boxes.withColumns({"xmin": F.col("xmin") - by, "ymin": F.col("ymin") - by, "xmax": F.col("xmax") + by, "ymax": F.col("ymax") + by})


def as_struct(boxes: DataFrame, name: str = "box") -> DataFrame:
    return boxes.withColumn(name, F.struct(*BOX))


def _fault() -> Column:
    bad = F.lit(None).cast("string")
    infinite = [F.isnan(c) | (F.abs(F.col(c)) == float("inf")) for c in BOX]
    for test, why in (
        (F.col("xmin") > F.col("xmax"), "xmin > xmax"), (F.col("ymin") > F.col("ymax"), "ymin > ymax"),
        (infinite[0] | infinite[1] | infinite[2] | infinite[3], "not finite"),
        (F.col("id").isNull() | F.col("xmin").isNull() | F.col("ymin").isNull() | F.col("xmax").isNull() | F.col("ymax").isNull(), "null"),
    ):
        bad = F.when(test, F.lit(why)).otherwise(bad)
    return bad


def split_invalid(boxes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Valid boxes, and the rejected rows with their reason."""
    judged = boxes.withColumn("reason", _fault())
    return judged.filter("reason is null").drop("reason"), judged.filter("reason is not null")


def require_boxes(boxes: DataFrame, unique: bool = True) -> DataFrame:
    """boxes, or ValueError if a row is invalid or an id repeats."""
    tests = [F.count_if(_fault().isNotNull()).alias("bad"), F.count(F.lit(1)).alias("n")]
    got = boxes.agg(*tests, *([F.count_distinct("id").alias("ids")] if unique else [])).first()
    if got["bad"]:
        raise ValueError(f"{got['bad']} of {got['n']} boxes are null, not finite or inverted")
    if unique and got["ids"] != got["n"]:
        raise ValueError(f"{got['n'] - got['ids']} box ids repeat")
    return boxes


def universe(boxes: DataFrame) -> tuple[Box, int]:
    """Extent and number of the boxes, in one partial and one final aggregate."""
    r = boxes.agg(F.min("xmin"), F.min("ymin"), F.max("xmax"), F.max("ymax"), F.count(F.lit(1))).first()
    if not r[4]:
        return Box(0.0, 0.0, 0.0, 0.0), 0
    return Box(float(r[0]), float(r[1]), float(r[2]), float(r[3])), int(r[4])
