"""Exact de-duplication by content-defined chunk recipes.

Each text, without white space, is cut where a rolling hash of its last 16 bytes says so; its
recipe is the ordered list of chunk fingerprints. Only documents whose recipe occurs again send
their chunks on; equal fingerprints are then verified on the chunks' bytes, and a fingerprint with
more than one content gets one identifier per content. Texts are equal when their identifier lists
are; lists are grouped by a 256-bit digest of theirs. Long texts never move as a whole.

Null texts count as empty; empty texts are equal to each other. A null doc_id sorts last among the
rows that may stay. Verdicts are on rows: of rows that share a doc_id (or have none) and an equal
text exactly one may stay, and such rows of different texts are judged apart. An empty table gives
an empty result. Columns other than doc_id and text are not read; drop_copies() keeps all.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WS_CHARS, discard, identified, materialize, maybe_broadcast, original, texts, without_rows
from .textkit import column_bytes, trimmed

WS_BYTES = WS_CHARS.encode()
MIN_CHUNK, MAX_CHUNK, MASK_BITS = 256, 8192, 10
_GEAR = np.random.default_rng(7).integers(0, 2**32, 256, dtype=np.uint32)


def cut_points(data: bytes) -> list[int]:
    """Ends of the chunks of data; they depend on its bytes alone."""
    n = len(data)
    if n <= MIN_CHUNK:
        return [n] if n else []
    h = _GEAR[np.frombuffer(data, np.uint8)]
    for step in (1, 2, 4, 8):
        h[step:] = h[step:] + (h[:-step] << np.uint32(step))
    ends, last = [], 0
    for e in (np.flatnonzero(h >> np.uint32(32 - MASK_BITS) == 0) + 1).tolist():
        while e - last > MAX_CHUNK:
            last += MAX_CHUNK
            ends.append(last)
        if e - last >= MIN_CHUNK:
            ends.append(e)
            last = e
    while n - last > MAX_CHUNK:
        last += MAX_CHUNK
        ends.append(last)
    if last < n:
        ends.append(n)
    return ends


def _squeezed(batch: pa.RecordBatch) -> Iterator[bytes]:
    data, off = column_bytes(batch.column("text"))
    for a, b in zip(off[:-1].tolist(), off[1:].tolist()):
        yield data[a:b].tobytes().translate(None, WS_BYTES)


def _recipes(batches):
    for batch in batches:
        sha, recipe, key = [], [], []
        for t in _squeezed(batch):
            sha.append(hashlib.sha256(t).hexdigest())
            a, ids = 0, []
            for b in cut_points(t):
                ids.append(xxhash.xxh3_64_intdigest(t[a:b]))
                a = b
            recipe.append(np.array(ids, np.uint64).view(np.int64))
            key.append(hashlib.sha256(recipe[-1].tobytes()).digest())
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), batch.column("n_code_points"), pa.array(sha, pa.string()), pa.array(recipe, pa.list_(pa.int64())), pa.array(key, pa.binary())],
            ["doc_id", "n_code_points", "text_sha256", "recipe", "recipe_key"],
        )


def _chunks(batches):
    for batch in batches:
        ids, at, fp, content = [], [], [], []
        for d, t in zip(batch.column("doc_id").to_pylist(), _squeezed(batch)):
            a = 0
            for k, b in enumerate(cut_points(t)):
                ids.append(d)
                at.append(k)
                fp.append(np.uint64(xxhash.xxh3_64_intdigest(t[a:b])).astype(np.int64))
                content.append(t[a:b])
                a = b
        yield pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array(at, pa.int32()), pa.array(fp, pa.int64()), pa.array(content, pa.binary())],
            ["doc_id", "at", "fp", "content"],
        )


def chunk_recipes(docs: DataFrame) -> DataFrame:
    """doc_id, n_code_points, text_sha256 (of the text without white space), recipe and its digest, of every row."""
    t = texts(docs).withColumn("n_code_points", F.length("text").cast("long"))
    return t.mapInArrow(trimmed(_recipes), "doc_id long, n_code_points long, text_sha256 string, recipe array<long>, recipe_key binary")


def _groups(rows: DataFrame, key: str) -> DataFrame:
    best = F.min(F.struct((-F.col("n_code_points")).alias("less"), F.col("orig").isNull().alias("none"), F.col("orig").alias("id"), F.col("__row_id").alias("row")))
    return rows.groupBy(key).agg(F.count(F.lit(1)).alias("group_size"), best.alias("best")).filter("group_size > 1").select(
        key, "group_size", F.col("best.id").alias("best_id"), F.col("best.row").alias("best_row")
    )


def _verdicts(docs: DataFrame, again: DataFrame | None, recipes=chunk_recipes) -> DataFrame:
    """__row_id, orig, keep_id, group_size, kept, text_sha256 of every row of docs (of identified())."""
    t = docs.select(F.col("__row_id").alias("doc_id"), "text")
    rows = materialize(original(recipes(t).drop("recipe").withColumnRenamed("doc_id", "__row_id"), again))
    key = "recipe_key"
    groups = materialize(_groups(rows, key))
    n = groups.count()
    repeated = materialize(rows.join(maybe_broadcast(groups.select(key), n), key, "left_semi").select(F.col("__row_id").alias("doc_id")))
    chunks = texts(t).join(maybe_broadcast(repeated), "doc_id", "left_semi").mapInArrow(trimmed(_chunks), "doc_id long, at int, fp long, content binary")
    contents = chunks.groupBy("fp", "content").agg(F.count(F.lit(1)).alias("copies"))
    clashing = materialize(contents.groupBy("fp").agg(F.count(F.lit(1)).alias("contents")).filter("contents > 1").select("fp"))
    if clashes := clashing.count():
        # Equal fingerprints of different bytes: the content's own digest tells them apart.
        told = chunks.join(maybe_broadcast(clashing, clashes), "fp", "left_semi").select(F.col("doc_id").alias("__row_id"), F.struct("at", F.sha2("content", 256).alias("id")).alias("v"))
        told = told.groupBy("__row_id").agg(F.sha2(F.to_json(F.array_sort(F.collect_set("v"))), 256).alias("variants"))
        rows = materialize(rows.join(told, "__row_id", "left").withColumn("variant_key", F.concat(F.hex("recipe_key"), F.coalesce("variants", F.lit("")))))
        key = "variant_key"
        groups = materialize(_groups(rows, key))
        n = groups.count()
    discard(repeated)
    out = rows.join(maybe_broadcast(groups, n, 160), key, "left")
    alone = F.col("group_size").isNull()
    return out.select(
        "__row_id", "orig", F.when(alone, F.col("orig")).otherwise(F.col("best_id")).alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        (alone | (F.col("__row_id") == F.col("best_row"))).alias("kept"), "text_sha256",
    )


def exact_groups(docs: DataFrame, recipes=chunk_recipes) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    return _verdicts(*identified(docs), recipes).drop("__row_id").withColumnRenamed("orig", "doc_id")


def drop_copies(docs: DataFrame) -> DataFrame:
    """docs with one row of each group of equal texts, the one that exact_groups() keeps; columns as given."""
    t, again = identified(docs)
    return without_rows(t, materialize(_verdicts(t, again).filter("not kept").select("__row_id"))).select(*docs.columns)
