"""Intermediate tables in the shared checkpoint folder, and size-checked broadcasts."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Most rows (of a tile or a few numbers each, about 160 bytes, so 32 MB) of a side that may be broadcast.
BROADCAST_ROWS = 200_000

_local: dict[str, str] = {}


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; only a local session without it gets a temporary folder."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _local:
        _local[app] = tempfile.mkdtemp(prefix="tilewright-")
        atexit.register(shutil.rmtree, _local[app], ignore_errors=True)
    return f"file://{_local[app]}"


def settled(df: DataFrame) -> DataFrame:
    """df as a written table: its lineage ends there and lost executors cost no recomputation."""
    path = f"{shared_folder(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int) -> DataFrame:
    """df with a broadcast hint if it has few enough rows, as the caller has counted, and else with one for a
    merge join: Spark's own estimate goes by the written file and knows nothing of rows that explode from it."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df.hint("merge")
