"""SQL functions: box predicates and curve keys that Catalyst inlines, and a table function of tiles."""

from __future__ import annotations

import math

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

_BOX8 = "ax0 DOUBLE, ay0 DOUBLE, ax1 DOUBLE, ay1 DOUBLE, bx0 DOUBLE, by0 DOUBLE, bx1 DOUBLE, by1 DOUBLE"


def _hilbert_sql(order: int = 8) -> str:
    """The Hilbert key of (x, y) as nested subqueries would be; here as a fold over the bits."""
    step = (
        "named_struct('k', s.k * 4 + CASE WHEN (shiftright(s.x, b) & 1) = 0 THEN (shiftright(s.y, b) & 1) ELSE 3 - (shiftright(s.y, b) & 1) END,"
        " 'x', CASE WHEN (shiftright(s.y, b) & 1) = 1 THEN s.x & (shiftleft(1L, b) - 1) WHEN (shiftright(s.x, b) & 1) = 1 THEN shiftleft(1L, b) - 1 - (s.y & (shiftleft(1L, b) - 1)) ELSE s.y & (shiftleft(1L, b) - 1) END,"
        " 'y', CASE WHEN (shiftright(s.y, b) & 1) = 1 THEN s.y & (shiftleft(1L, b) - 1) WHEN (shiftright(s.x, b) & 1) = 1 THEN shiftleft(1L, b) - 1 - (s.x & (shiftleft(1L, b) - 1)) ELSE s.x & (shiftleft(1L, b) - 1) END)"
    )
    bits = ", ".join(str(b) for b in range(order - 1, -1, -1))
    return f"aggregate(array({bits}), named_struct('k', 0L, 'x', hx, 'y', hy), (s, b) -> {step}, s -> s.k)"


def register_functions(spark: SparkSession) -> None:
    """box_intersects, box_contains, box_gap_squared, hilbert2d (8 bits an axis), grid_cell_of and tiles_of."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION box_intersects({_BOX8}) RETURNS BOOLEAN RETURN ax0 <= bx1 AND ax1 >= bx0 AND ay0 <= by1 AND ay1 >= by0")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION box_contains({_BOX8}) RETURNS BOOLEAN RETURN ax0 <= bx0 AND ax1 >= bx1 AND ay0 <= by0 AND ay1 >= by1")
    spark.sql(
        f"CREATE OR REPLACE TEMPORARY FUNCTION box_gap_squared({_BOX8}) RETURNS DOUBLE RETURN "
        "power(greatest(0D, ax0 - bx1, bx0 - ax1), 2) + power(greatest(0D, ay0 - by1, by0 - ay1), 2)"
    )
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION hilbert2d(hx BIGINT, hy BIGINT) RETURNS BIGINT RETURN {_hilbert_sql()}")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION grid_cell_of(v DOUBLE, low DOUBLE, extent DOUBLE, cells INT) RETURNS BIGINT RETURN "
        "greatest(0L, least(cells - 1L, CAST(floor((v - low) * cells / extent) AS BIGINT)))"
    )
    spark.udtf.register("tiles_of", TilesOf)


@udtf(returnType="tile_id int")
class TilesOf:
    """tiles_of(xmin, ymin, xmax, ymax, x0, y0, x1, y1, m): the cells of an m x m grid that a box meets."""

    def eval(self, xmin: float, ymin: float, xmax: float, ymax: float, x0: float, y0: float, x1: float, y1: float, m: int):
        def cell(v: float, low: float, extent: float) -> int:
            return max(0, min(m - 1, math.floor((v - low) * m / extent))) if extent > 0 else 0

        for j in range(cell(ymin, y0, y1 - y0), cell(ymax, y0, y1 - y0) + 1):
            for i in range(cell(xmin, x0, x1 - x0), cell(xmax, x0, x1 - x0) + 1):
                yield (j * m + i,)
