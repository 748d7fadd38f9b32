"""Quality classifier: a generalised additive model with pairwise interactions.

Each feature of a text is put into quantile bins; cyclic boosting goes round the features and adds
to each one's lookup table the leaf values of a shallow tree on its bins. Then the pairs of features
that explain most of the remaining gradient on a coarse grid get tables of their own, boosted alike
by one cut on each axis. A score is the intercept and a few table look-ups, added for whole batches.

The fit reads at most `sample_rows` labelled rows, those of smallest hash of doc_id, never held-out
ones. Null and empty texts have features of zero and a score like any other. With no labelled row
every score is 0.5. Rows that repeat get equal scores. Only doc_id and text (and quality, in the
fit) are read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, texts
from .fertility import base_counts, duplicate_lines, per_row
from .textkit import Words, column_bytes, slices, trimmed

#: Labelled rows that the fit may read.
SAMPLE_ROWS = 16_000
BINS, PAIR_BINS, PAIRS, ROUNDS, RATE, LEAVES = 48, 8, 6, 80, 0.1, 4
CUTOFF = 0.3

FEATURES = [
    "log_words", "word_length", "symbol_share", "dup_line_share", "repeat_share", "distinct_share", "top_word_share",
    "upper_share", "digit_share", "punctuation_share", "non_ascii_share", "log_line_words", "sentence_words", "byte_entropy", "long_word_share",
]
_KIND = np.zeros(256, np.uint8)
_KIND[65:91] = 1
_KIND[48:58] = 2
_KIND[list(b".,;:!?'\"()-")] = 3
_KIND[128:] = 4
_KIND[10] = 5


def text_features(batch: pa.RecordBatch) -> np.ndarray:
    data, off = column_bytes(batch.column("text"))
    out = []
    for i, j in slices(off):
        part, o = data[off[i] : off[j]], off[i : j + 1] - off[i]
        w = Words(part, o)
        rows = j - i
        n, chars, symbols, again = base_counts(part, o, w)
        kinds = [per_row(_KIND[part] == k, o) for k in range(1, 6)]
        stops = per_row(np.isin(part, np.frombuffer(b".!?", np.uint8)), o)
        long = np.r_[0, np.cumsum(w.end - w.start > 12)]
        m = np.zeros((rows, len(FEATURES)), np.float64)
        size = np.maximum(1, np.diff(o)).astype(np.float64)
        words = np.maximum(1, n).astype(np.float64)
        m[:, 0], m[:, 1], m[:, 2] = np.log1p(n), chars / words, symbols / size
        m[:, 4], m[:, 14] = again / words, (long[w.first[1:]] - long[w.first[:-1]]) / words
        m[:, 7], m[:, 8], m[:, 9], m[:, 10] = (k / size for k in kinds[:4])
        m[:, 11], m[:, 12] = np.log1p(n / (kinds[4] + 1)), n / (stops + 1)
        for r in range(rows):
            raw = part[o[r] : o[r + 1]]
            m[r, 3] = duplicate_lines(raw.tobytes().decode()) / (kinds[4][r] + 1)
            h = w.hash[w.first[r] : w.first[r + 1]]
            if len(h):
                c = np.unique(h, return_counts=True)[1]
                m[r, 5], m[r, 6] = len(c) / len(h), c.max() / len(h)
                p = np.bincount(raw, minlength=256)
                p = p[p > 0] / len(raw)
                m[r, 13] = -(p * np.log2(p)).sum()
        out.append(m)
    return np.vstack(out) if out else np.zeros((0, len(FEATURES)))


def shallow_tree(g: np.ndarray, h: np.ndarray, leaves: int, ridge: float = 1.0) -> np.ndarray:
    """Leaf value per bin of the tree with `leaves` leaves grown best-first on gradient sums g and hessian sums h."""
    G, H = np.r_[0, np.cumsum(g)], np.r_[0, np.cumsum(h)]

    def gain(a: int, b: int) -> tuple[float, int]:
        if b - a < 2:
            return 0.0, a
        c = np.arange(a + 1, b)
        left, right = (G[c] - G[a]) ** 2 / (H[c] - H[a] + ridge), (G[b] - G[c]) ** 2 / (H[b] - H[c] + ridge)
        total = left + right - (G[b] - G[a]) ** 2 / (H[b] - H[a] + ridge)
        k = int(total.argmax())
        return float(total[k]), int(c[k])

    parts = [(0, len(g), *gain(0, len(g)))]
    while len(parts) < leaves:
        k = max(range(len(parts)), key=lambda i: parts[i][2])
        a, b, better, c = parts[k]
        if better <= 1e-9:
            break
        parts[k : k + 1] = [(a, c, *gain(a, c)), (c, b, *gain(c, b))]
    out = np.zeros(len(g))
    for a, b, *_ in parts:
        out[a:b] = (G[b] - G[a]) / (H[b] - H[a] + ridge)
    return out


def _corner_tree(g: np.ndarray, h: np.ndarray, ridge: float = 1.0) -> tuple[float, np.ndarray]:
    """The best cut on each axis of a grid: gain and the four leaf values as a table."""
    G, H = (np.pad(x.cumsum(0).cumsum(1), ((1, 0), (1, 0))) for x in (g, h))
    r, c = G.shape[0] - 1, G.shape[1] - 1
    i, j = np.meshgrid(np.arange(1, r), np.arange(1, c), indexing="ij")

    def quads(S):
        return S[i, j], S[i, c] - S[i, j], S[r, j] - S[i, j], S[r, c] - S[i, c] - S[r, j] + S[i, j]

    gq, hq = quads(G), quads(H)
    total = sum(a * a / (b + ridge) for a, b in zip(gq, hq))
    if not total.size:
        return 0.0, np.zeros_like(g)
    k = np.unravel_index(total.argmax(), total.shape)
    leaf = [a[k] / (b[k] + ridge) for a, b in zip(gq, hq)]
    out = np.empty_like(g)
    a, b = k[0] + 1, k[1] + 1
    out[:a, :b], out[:a, b:], out[a:, :b], out[a:, b:] = leaf
    return float(total[k]) - float(G[r, c] ** 2 / (H[r, c] + ridge)), out


class AdditiveModel:
    """Bin edges, a lookup table per feature and per chosen pair, and an intercept."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.edges = [np.unique(np.quantile(c, np.linspace(0, 1, BINS + 1)[1:-1])) if len(c) else np.zeros(0) for c in x.T]
        self.coarse = [np.unique(np.quantile(c, np.linspace(0, 1, PAIR_BINS + 1)[1:-1])) if len(c) else np.zeros(0) for c in x.T]
        self.tables = [np.zeros(len(e) + 1) for e in self.edges]
        self.pairs: list[tuple[int, int]] = []
        self.pair_tables: list[np.ndarray] = []
        share = (y.sum() + 1) / (len(y) + 2)
        self.intercept = float(np.log(share / (1 - share)))
        if not len(y):
            return
        bins = self._bins(x, self.edges)
        score = np.full(len(y), self.intercept)
        for _ in range(ROUNDS):
            for f, table in enumerate(self.tables):
                p = 1 / (1 + np.exp(-score))
                n = len(table)
                step = RATE * shallow_tree(np.bincount(bins[f], y - p, n), np.bincount(bins[f], p * (1 - p), n), LEAVES)
                table += step
                score += step[bins[f]]
        grid = self._bins(x, self.coarse)
        shape = [len(e) + 1 for e in self.coarse]

        def sums(i, j, v):
            return np.bincount(grid[i] * shape[j] + grid[j], v, shape[i] * shape[j]).reshape(shape[i], shape[j])

        p = 1 / (1 + np.exp(-score))
        gains = [(_corner_tree(sums(i, j, y - p), sums(i, j, p * (1 - p)))[0], i, j) for i in range(len(shape)) for j in range(i)]
        self.pairs = [(i, j) for g, i, j in sorted(gains, reverse=True)[:PAIRS] if g > 1e-6]
        self.pair_tables = [np.zeros((shape[i], shape[j])) for i, j in self.pairs]
        for _ in range(ROUNDS):
            for (i, j), table in zip(self.pairs, self.pair_tables):
                p = 1 / (1 + np.exp(-score))
                step = RATE * _corner_tree(sums(i, j, y - p), sums(i, j, p * (1 - p)))[1]
                table += step
                score += step[grid[i], grid[j]]

    @staticmethod
    def _bins(x: np.ndarray, edges: list[np.ndarray]) -> list[np.ndarray]:
        return [np.searchsorted(e, c, "right") for e, c in zip(edges, x.T)]

    def score(self, x: np.ndarray) -> np.ndarray:
        fine, grid = self._bins(x, self.edges), self._bins(x, self.coarse)
        s = np.full(len(x), self.intercept)
        for table, b in zip(self.tables, fine):
            s += table[b]
        for (i, j), table in zip(self.pairs, self.pair_tables):
            s += table[grid[i], grid[j]]
        return 1 / (1 + np.exp(-s))


def _features(batches):
    for batch in batches:
        m = text_features(batch)
        yield pa.RecordBatch.from_arrays([batch.column("y"), pa.array(list(m), pa.list_(pa.float64()))], ["y", "x"])


def fit(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> AdditiveModel:
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("double").alias("y")).dropna()
    known = known.filter(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("y").alias("y"))
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    rows = texts(docs).join(F.broadcast(known), "doc_id").select("y", "text")  # bounded by sample_rows
    got = rows.mapInArrow(trimmed(_features), "y double, x array<double>").collect()
    return AdditiveModel(np.array([r["x"] for r in got]).reshape(len(got), len(FEATURES)), np.array([r["y"] for r in got]))


def quality_scores(docs: DataFrame, model: AdditiveModel, cutoff: float = CUTOFF) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def scored(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(shared.value.score(text_features(batch)), pa.float64())], ["doc_id", "score"])

    out = texts(docs).mapInArrow(trimmed(scored), "doc_id long, score double")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= cutoff).cast("int").alias("predicted"))
