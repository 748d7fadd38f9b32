"""Session helpers shared by the training-data operators."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WS_CLASS = r"[\x20\x09-\x0D]"
WS_CHARS = " \t\n\x0b\x0c\r"
#: A side of a join is broadcast only when its rows were counted and are known to take at most so many bytes.
BROADCAST_BYTES = 32 << 20
#: Bytes of a value in a broadcast relation (of other kinds 1024, if the caller knows no width).
_WIDTHS = {"bigint": 8, "double": 8, "float": 8, "int": 8, "boolean": 8, "string": 64, "binary": 64}

#: While a table is written: shuffle files go when they are no longer needed, and workers get short batches of (long) texts.
_WRITING = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxRecordsPerBatch": "2000"}
_own: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a temporary one in local mode."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _own:
        _own[app] = tempfile.mkdtemp(prefix="tilewright-")
        atexit.register(shutil.rmtree, _own[app], ignore_errors=True)
    return f"file://{_own[app]}"


def materialize(df: DataFrame) -> DataFrame:
    """Write df to the shared folder and read it back, which cuts its lineage.

    The shuffle files behind it are of no more use then, and go at once. The settings for it are as before after it.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/tilewright/{uuid.uuid4().hex}"
    before = {k: spark.conf.get(k, None) for k in _WRITING}
    for k, v in _WRITING.items():
        spark.conf.set(k, v)
    try:
        df.write.parquet(path)
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    out = spark.read.schema(df.schema).parquet(path)
    out._tilewright_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete materialized tables that no later step reads."""
    for t in tables:
        path = t.sparkSession._jvm.org.apache.hadoop.fs.Path(t._tilewright_path)
        path.getFileSystem(t.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def maybe_broadcast(df: DataFrame, rows: int | None = None, width: int | None = None) -> DataFrame:
    """Hint a broadcast if the counted rows, of `width` bytes each, are small; a larger side is left to a shuffle join."""
    width = width or sum(_WIDTHS.get(kind, 1024) for _, kind in df.dtypes)
    n = df.count() if rows is None else rows
    return F.broadcast(df) if n * (width + 32) <= BROADCAST_BYTES else df


def identified(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """docs with __row_id, unique and never null; and the rows' own (__row_id, doc_id) where these differ.

    __row_id is doc_id, but a number of its own for a row whose doc_id is null or stands in several rows:
    so what is decided by __row_id is decided for one row. None in place of the second: there are no such rows.
    """
    doc_id = F.col("doc_id").cast("long")
    counted = docs.select(doc_id.alias("doc_id")).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    shared = materialize(counted.filter("n > 1 or doc_id is null").select(F.col("doc_id").alias("__shared")))
    n = shared.count()
    if not n:
        discard(shared)
        return docs.withColumn("__row_id", doc_id), None
    same = doc_id.eqNullSafe(F.col("__shared"))
    top = docs.agg(F.max(doc_id)).first()[0]
    if (top or 0) > 1 << 62:
        raise ValueError("no numbers above the largest doc_id are left for rows that share one")
    own = F.monotonically_increasing_id() + F.lit(max(top or 0, 0) + 1)
    again = materialize(docs.join(maybe_broadcast(shared, n), same, "left_semi").withColumn("__row_id", own))
    alone = docs.join(maybe_broadcast(shared, n), same, "left_anti").withColumn("__row_id", doc_id)
    return alone.unionByName(again), again.select("__row_id", doc_id.alias("doc_id"))


def original(df: DataFrame, again: DataFrame | None) -> DataFrame:
    """df, which has __row_id, with orig: the doc_id that the row came with."""
    if again is None:
        return df.withColumn("orig", F.col("__row_id"))
    again = again.select("__row_id", F.col("doc_id").alias("orig"), F.lit(True).alias("__own"))
    return df.join(maybe_broadcast(again), "__row_id", "left").withColumn("orig", F.when(F.col("__own"), F.col("orig")).otherwise(F.col("__row_id"))).drop("__own")


def without_rows(docs: DataFrame, gone: DataFrame, n: int | None = None) -> DataFrame:
    """docs (of identified()) without the rows whose __row_id is in gone, and without __row_id."""
    return docs.join(maybe_broadcast(gone.select("__row_id"), n), "__row_id", "left_anti").drop("__row_id")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id) -> "F.Column":
    """crc32 of the id's decimal text, modulo 5, is 0: rows kept from every fit."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def texts(docs: DataFrame) -> DataFrame:
    """doc_id and text only; other columns, whatever their names, stay out of the operators."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
