"""Space-filling curve keys of box centres: Z and Gray keys as code-generated column expressions,
Hilbert keys by a kernel over Arrow batches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .geometry import Box, centre

ORDER = 16


def cell(axis: str, universe: Box, order: int = ORDER) -> Column:
    """Number of the centre's cell on an axis of 2^order cells."""
    side = 1 << order
    low, extent = universe.low(axis), universe.high(axis) - universe.low(axis)
    if extent <= 0:
        return F.lit(0).cast("long")
    at = F.floor((centre(axis) - low) * float(side) / extent)
    return F.greatest(F.lit(0), F.least(F.lit(side - 1), at)).cast("long")


def _bit(c: Column, k: int) -> Column:
    return F.shiftright(c, k).bitwiseAND(F.lit(1))


def with_z_key(df: DataFrame, x: str, y: str, key: str, order: int = ORDER) -> DataFrame:
    """Interleaved bits, x in the higher place of each pair."""
    out = F.lit(0).cast("long")
    for k in range(order - 1, -1, -1):
        out = out * 4 + _bit(F.col(x), k) * 2 + _bit(F.col(y), k)
    return df.withColumn(key, out)


def with_gray_key(df: DataFrame, x: str, y: str, key: str, order: int = ORDER) -> DataFrame:
    """Rank of the interleaved bits in the binary-reflected Gray code."""
    df = with_z_key(df, x, y, key, order)
    shift = 1
    while shift < 2 * order:
        df = df.withColumn(key, F.col(key).bitwiseXOR(F.shiftright(key, shift)))
        shift *= 2
    return df


def hilbert_keys(x: np.ndarray, y: np.ndarray, order: int = ORDER) -> np.ndarray:
    """Places of cells (x, y) on the Hilbert curve, from the highest bit down.

    Each bit pair picks a quadrant (0, 1, 2, 3 in visiting order) and turns the frame for the bits
    below: quadrant 0 swaps the axes, quadrant 3 swaps and mirrors them.
    """
    key = np.zeros(len(x), np.int64)
    for k in range(order - 1, -1, -1):
        below = (1 << k) - 1
        bx, by = (x >> k) & 1, (y >> k) & 1
        key = key * 4 + np.where(bx == 1, 3 - by, by)
        x, y = x & below, y & below
        mirror = np.where((bx == 1) & (by == 0), below, 0)
        turn = by == 0
        x, y = np.where(turn, y ^ mirror, x), np.where(turn, x ^ mirror, y)
    return key


def with_hilbert_key(df: DataFrame, x: str, y: str, key: str, order: int = ORDER) -> DataFrame:
    """Hilbert keys of whole batches; as a column expression the turns of each bit would be inlined
    into the next one's, or be folded by an interpreted lambda."""

    def keyed(batches):
        for batch in batches:
            xs, ys = (batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in (x, y))
            yield batch.append_column(key, pa.array(hilbert_keys(xs, ys, order)))

    return df.mapInArrow(keyed, T.StructType([*df.schema, T.StructField(key, T.LongType())]))


CURVES = {"hilbert": with_hilbert_key, "z": with_z_key, "gray": with_gray_key}


def with_curve_key(boxes: DataFrame, universe: Box, curve: str = "hilbert", order: int = ORDER, key: str = "curve_key") -> DataFrame:
    """boxes with the key of their centre on a curve."""
    if not 1 <= order <= 31:
        raise ValueError("a curve has 1 to 31 bits per axis")
    df = boxes.withColumns({"_cx": cell("x", universe, order), "_cy": cell("y", universe, order)})
    return CURVES[curve](df, "_cx", "_cy", key, order).drop("_cx", "_cy")
