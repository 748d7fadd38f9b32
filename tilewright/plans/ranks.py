"""Exact global ranks and interval numbers without a single-partition window."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..store import settled, small


def global_rank(df: DataFrame, *order: str, name: str = "rank", parts: int | None = None) -> DataFrame:
    """df with its 0-based rank by `order` (which must tell rows apart for a repeatable result).

    Rows are range-partitioned and sorted by all order columns (so equal values of the first may be
    parted), numbered in their partition and written; each partition starts after the counts of those
    before it. No task sees more than a range, and nothing is sorted twice.
    """
    spark = df.sparkSession
    parts = parts or max(2, int(spark.conf.get("spark.sql.shuffle.partitions")))
    # The number of a row is its partition's number, shifted by 33 bits, and its place in it.
    numbered = settled(df.repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn("_m", F.monotonically_increasing_id()))
    part = F.shiftright("_m", 33)
    sizes = numbered.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()  # one row per range
    base, bases = 0, []
    for p, n in sorted((r["p"], r["n"]) for r in sizes):
        bases.append((p, base))
        base += n
    starts = spark.createDataFrame(bases or [(0, 0)], "_part long, _base long")
    ranked = numbered.withColumn("_part", part).join(small(starts, len(bases)), "_part")
    return ranked.withColumn(name, F.col("_base") + F.col("_m").bitwiseAND(F.lit((1 << 33) - 1))).drop("_part", "_base", "_m")


def with_interval(df: DataFrame, value: str, cuts: list, name: str) -> DataFrame:
    """df with the number of sorted cuts that are not above the value, by binary search in a broadcast array."""
    cuts = np.asarray(cuts)
    if len(cuts) <= 32:
        edges = F.array(*(F.lit(c.item()) for c in cuts)) if len(cuts) else None
        at = F.size(F.filter(edges, lambda e: e <= F.col(value))) if edges is not None else F.lit(0)
        return df.withColumn(name, at.cast("int"))
    shared = df.sparkSession.sparkContext.broadcast(cuts)

    def search(batches):
        for batch in batches:
            at = np.searchsorted(shared.value, batch.column(value).to_numpy(zero_copy_only=False), "right")
            yield batch.append_column(name, pa.array(at.astype(np.int32)))

    return df.mapInArrow(search, T.StructType([*df.schema, T.StructField(name, T.IntegerType())]))
