"""Language identification by nearest centroids of TF-IDF n-gram vectors.

A text is the log-scaled TF-IDF vector of its hashed byte trigrams (letters only, ASCII lower
case), of unit length. Each language has several centroids, found by spherical k-means. A text gets
the language of the centroid of largest cosine; one that is farther from it than `reject_share` of
the distance scale of its training members is rejected.

The fit reads at most `per_language` rows of each of the `MOST_LANGUAGES` most frequent languages:
those whose hash lies below a threshold set from the language's count (so no language is ranked in
one task), never held-out ones, and rows that repeat a doc_id once. The driver gets their sparse
counts and fits one language at a time. Whatever else is computed covers all rows. Null texts and
texts without a letter are `und` with score 0, and rejected. With no labelled row, all is `und`.
Rows of a null doc_id are learned from and predicted like others. Repeated rows get equal
predictions. Only doc_id and text (and lang, in the fit) are read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import held_out
from .textkit import column_bytes, slices, trimmed

DIMS = 8192
ROWS = 256
#: Rows of each language that the fit may read.
PER_LANGUAGE = 600
#: Languages that are learned, the most frequent ones.
MOST_LANGUAGES = 256
CENTROIDS = 3
REJECT_SHARE = 0.25

_FOLD = np.full(256, 32, np.uint32)
_FOLD[97:123] = np.arange(97, 123)
_FOLD[65:91] = np.arange(97, 123)
_FOLD[128:] = np.arange(128, 256)


def trigram_counts(data: np.ndarray, off: np.ndarray) -> np.ndarray:
    """rows x DIMS counts of the byte trigrams inside each row (blank-only ones left out)."""
    rows = len(off) - 1
    b = _FOLD[data]
    if len(b) < 3:
        return np.zeros((rows, DIMS), np.float32)
    row = np.repeat(np.arange(rows), np.diff(off))
    code = (b[:-2] * np.uint32(0x9E3779B1) ^ b[1:-1] * np.uint32(0x85EBCA77) ^ b[2:] * np.uint32(0xC2B2AE3D)) * np.uint32(0x27D4EB2F)
    keep = (row[:-2] == row[2:]) & ((b[:-2] != 32) | (b[1:-1] != 32)) & ((b[1:-1] != 32) | (b[2:] != 32))
    at = row[:-2][keep] * DIMS + (code[keep] >> np.uint32(19)).astype(np.int64)
    return np.bincount(at, minlength=rows * DIMS).reshape(rows, DIMS).astype(np.float32)


def _matrices(batch: pa.RecordBatch):
    data, off = column_bytes(batch.column("text"))
    for i, j in slices(off):
        for a in range(i, j, ROWS):
            b = min(j, a + ROWS)
            yield a, b, trigram_counts(data[off[a] : off[b]], off[a : b + 1] - off[a])


def _sparse(batches):
    for batch in batches:
        at, n = [], []
        for _, _, m in _matrices(batch):
            for r in m:
                k = np.flatnonzero(r)
                at.append(k.astype(np.int16))
                n.append(r[k].astype(np.int32))
        yield pa.RecordBatch.from_arrays([batch.column("lang"), batch.column("h"), pa.array(at, pa.list_(pa.int16())), pa.array(n, pa.list_(pa.int32()))], ["lang", "h", "at", "n"])


def _unit(m: np.ndarray) -> np.ndarray:
    return m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-12)


def _kmeans(x: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    """Spherical k-means; the first centre is the mean's, the next ones the farthest rows."""
    centres = _unit(x.mean(axis=0, keepdims=True))
    while len(centres) < min(k, len(x)):
        centres = np.vstack([centres, x[np.argmin((x @ centres.T).max(axis=1))]])
    for _ in range(rounds):
        own = (x @ centres.T).argmax(axis=1)
        centres = _unit(np.vstack([x[own == c].mean(axis=0) if (own == c).any() else centres[c] for c in range(len(centres))]))
    return centres


class CentroidModel:
    """Languages, their centroids, inverse document frequencies and rejection limits."""

    def __init__(self, langs: np.ndarray, first: np.ndarray, at: np.ndarray, n: np.ndarray, k: int = CENTROIDS):
        """Row i, of language langs[i], has counts n at dimensions at, both from first[i] to first[i + 1]."""
        self.idf = (np.log((1 + len(langs)) / (1 + np.bincount(at, minlength=DIMS))) + 1).astype(np.float32)
        self.langs: list[str] = sorted(set(langs.tolist()))
        self.owner, self.limit, centres = np.zeros(0, np.int64), np.zeros(0), [np.zeros((0, DIMS), np.float32)]
        for i, lang in enumerate(self.langs):
            own = np.flatnonzero(langs == lang)
            x = np.zeros((len(own), DIMS), np.float32)
            for row, r in zip(x, own):
                row[at[first[r] : first[r + 1]]] = n[first[r] : first[r + 1]]
            x = self.vectors(x)
            c = _kmeans(x, k)
            centres.append(c)
            self.owner = np.r_[self.owner, np.full(len(c), i)]
            near = (x @ c.T).max(axis=1)
            self.limit = np.r_[self.limit, np.full(len(c), REJECT_SHARE * np.quantile(near, 0.05))]
        self.centres = np.vstack(centres)

    def vectors(self, counts: np.ndarray) -> np.ndarray:
        """Unit TF-IDF rows, made in the place of counts."""
        np.log1p(counts, out=counts)
        counts *= self.idf
        counts /= np.maximum(np.linalg.norm(counts, axis=1, keepdims=True), 1e-12)
        return counts

    def predict(self, counts: np.ndarray) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, cosine, and whether the distance rejects the row."""
        if not len(self.centres):
            return ["und"] * len(counts), np.zeros(len(counts)), np.ones(len(counts), bool)
        cos = self.vectors(counts) @ self.centres.T
        best = cos.argmax(axis=1)
        top = np.clip(cos[np.arange(len(cos)), best].astype(np.float64), 0, 1)
        return [self.langs[i] for i in self.owner[best]], top, top < self.limit[best]


def training_rows(docs: DataFrame, per_language: int = PER_LANGUAGE) -> DataFrame:
    """lang, h, text: about per_language rows of each learned language, none of them held out."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("lang").cast("string").alias("lang"))
    rows = rows.filter(F.col("text").isNotNull() & F.col("lang").isNotNull() & ~held_out(F.col("doc_id")))
    counts = rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "lang").limit(MOST_LANGUAGES).collect()
    # Hashes are 63 bits long; all rows of a small language are below its limit.
    limits = [(r["lang"], min(2**63 - 1, per_language * 2**63 // r["n"])) for r in counts]
    limits = docs.sparkSession.createDataFrame(limits, "lang string, most long")  # MOST_LANGUAGES rows
    near = rows.withColumn("h", F.shiftrightunsigned(F.xxhash64("doc_id", F.when(F.col("doc_id").isNull(), F.col("text"))), 1))
    return near.join(F.broadcast(limits), "lang").filter("h <= most").groupBy("lang", "h").agg(F.min("text").alias("text"))


def fit(docs: DataFrame, per_language: int = PER_LANGUAGE, centroids: int = CENTROIDS) -> CentroidModel:
    """Fit on at most per_language rows of each learned value of lang, none of them held out."""
    counts = training_rows(docs, per_language).mapInArrow(trimmed(_sparse), "lang string, h long, at array<short>, n array<int>").toArrow().combine_chunks()
    langs, h = np.array(counts.column("lang").to_pylist(), object), counts.column("h").to_numpy()
    order = np.lexsort((h, langs)) if len(h) else np.zeros(0, np.int64)
    turn = np.arange(len(h)) - np.searchsorted(langs[order], langs[order]) if len(h) else order
    order = order[turn < per_language]
    parts = [counts.column(c).combine_chunks() if len(h) else pa.array([], pa.list_(pa.int32())) for c in ("at", "n")]
    off, (at, n) = parts[0].offsets.to_numpy(), (x.values.to_numpy(zero_copy_only=False) for x in parts)
    size = np.diff(off)[order]
    first = np.r_[0, np.cumsum(size)]
    take = np.repeat(off[:-1][order] - first[:-1], size) + np.arange(first[-1]) if len(order) else np.zeros(0, np.int64)
    return CentroidModel(langs[order], first, at[take].astype(np.int64), n[take], centroids)


def identify(docs: DataFrame, model: CentroidModel) -> DataFrame:
    """row (a struct of all columns of docs), lang_pred, lang_score, lang_rejected."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)
    inner = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"),
        F.coalesce(F.col("text"), F.lit("")).alias("text"),
        F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)).alias("lettered"),
    )

    def predict(batches):
        m = shared.value
        for batch in batches:
            langs, scores, out = [], [], []
            for _, _, counts in _matrices(batch):
                a, b, c = m.predict(counts)
                langs += a
                scores.append(b)
                out.append(c)
            ok = batch.column("lettered").to_numpy(zero_copy_only=False).astype(bool)
            scores = np.where(ok, np.concatenate(scores) if scores else np.zeros(0), 0.0)
            out = ~ok | (np.concatenate(out) if out else np.zeros(0, bool))
            yield pa.RecordBatch.from_arrays(
                [batch.column("row"), pa.array([x if y else "und" for x, y in zip(langs, ok)], pa.string()), pa.array(scores, pa.float64()), pa.array(out, pa.bool_())],
                ["row", "lang_pred", "lang_score", "lang_rejected"],
            )

    schema = T.StructType([inner.schema["row"]]).add("lang_pred", "string").add("lang_score", "double").add("lang_rejected", "boolean")
    return inner.mapInArrow(trimmed(predict), schema)


def predictions(docs: DataFrame, model: CentroidModel | None = None) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected of every row."""
    model = model or fit(docs)
    found = identify(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model)
    return found.select(
        F.col("row.doc_id").alias("doc_id"), held_out(F.col("row.doc_id")).alias("held_out"), "lang_pred",
        F.col("lang_score").alias("score"), F.col("lang_rejected").alias("rejected"),
    )


def keep_identified(docs: DataFrame) -> DataFrame:
    """The rows of docs whose language is recognised; columns as given."""
    return identify(docs, fit(docs)).filter("not lang_rejected").select("row.*")
