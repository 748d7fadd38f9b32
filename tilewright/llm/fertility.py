"""Quality rules on tokeniser fertility.

Per text and public vocabulary: code points per token; of a piece vocabulary also the share of byte
fallback tokens; the entropy of the tokens' distribution against its largest possible value. Bands
are set per language and size class (texts of 2^k to 2^(k+1) tokens, as entropy falls with length)
from all rows that pass the base rules: the median and so many scaled median deviations on the side
where faults lie. Fewer characters a token or a piece than the band, a larger share of bytes, or
tokens less varied reject a text; more characters a token or more variety are no fault. A size class
of fewer than `LEAST_ROWS` such rows takes the bands of its whole language (but no entropy band, as
entropy depends on size), a language of fewer has none: rows of other languages never decide.

Null texts have no words and fail the base rules. A null language is `und`. Repeated rows get equal
verdicts. An empty table gives an empty result. Only doc_id, text and lang are read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WS_CHARS, materialize, maybe_broadcast
from .lattice import MARK, PieceTable
from .lattice import Units as PieceUnits
from .packing import SLICE, Memo, coder, remembered
from .textkit import SPACE, U, Words, column_bytes, distinct, mix, slices, trimmed

SYMBOLS = b"#*$%&|<>"
BASE_MIN_WORDS, BASE_REPEAT_PERCENT = 50, 50
DEVIATIONS = 6.0
LEAST_ROWS = 50

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(SYMBOLS)] = True
_pieces: dict[str, "PieceCounts"] = {}


class PieceCounts:
    """Numbers of pieces and of byte pieces of units under a SentencePiece vocabulary."""

    def __init__(self, path: str):
        import sentencepiece

        self.table, self.memo = PieceTable(path), Memo()
        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.byte = np.array([self.model.is_byte(i) for i in range(self.model.get_piece_size())])

    def encode(self, units: list[str]) -> list[list[int]]:
        # The mark that the model puts before a text, and a line break that joins with nothing, come first.
        ids = self.model.encode(["\n" + u.replace(MARK, " ") for u in units], num_threads=1)
        return [[len(x) - 2, int(self.byte[x[2:]].sum())] for x in ids]

    def __call__(self, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pieces and byte pieces of each row."""
        units = PieceUnits(self.table, data, off)
        counts, _ = remembered(self.memo, units, self.encode)
        counts = counts.astype(np.int64).reshape(-1, 2)
        return tuple(np.r_[0, np.cumsum(c)][units.first[1:]] - np.r_[0, np.cumsum(c)][units.first[:-1]] for c in counts.T)


def repeated_words(h: np.ndarray, first: np.ndarray, at: np.ndarray, rows: int) -> np.ndarray:
    """Words of each row that lie in a window (hash h, first word at) found twice or more in the row."""
    row = np.searchsorted(first, at, "right") - 1
    which, _ = distinct(mix(h + mix(row.astype(U) + U(1))))
    again = at[np.bincount(which)[which] > 1] if len(which) else at
    edge = np.zeros(int(first[-1]) + 4, np.int32)
    np.add.at(edge, again, 1)
    np.add.at(edge, again + 3, -1)
    return per_row(np.cumsum(edge)[: int(first[-1])] > 0, first)


def entropy_bits(ids: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Entropy of the distribution of each row's ids."""
    size = np.diff(at)
    row = np.repeat(np.arange(len(size)), size)
    which, first = distinct(row * (1 << 32) + ids.astype(np.int64))
    n = np.bincount(which, minlength=len(first)) if len(which) else np.zeros(0)
    total = np.bincount(row[first], n * np.log2(np.maximum(n, 1)), len(size))
    whole = np.maximum(size, 1)
    return np.log2(whole) - total / whole


def per_row(flags: np.ndarray, off: np.ndarray) -> np.ndarray:
    """How many flags are set in each row."""
    total = np.r_[0, np.cumsum(flags)]
    return total[off[1:]] - total[off[:-1]]


def duplicate_lines(text: str) -> int:
    lines = [x for x in text.split("\n") if x.strip(WS_CHARS)]
    return len(lines) - len(set(lines))


def base_counts(data: np.ndarray, off: np.ndarray, w: Words) -> tuple:
    """n_words, word_chars, n_symbols, n_repeat_words of each row."""
    rows = len(off) - 1
    chars = per_row(((data & 0xC0) != 0x80) & ~SPACE[data], off)
    h, at = w.windows(3)
    return np.diff(w.first), chars, per_row(_SYMBOL[data], off), repeated_words(h, w.first, at, rows)


def measures(docs: DataFrame, byte_vocabulary: str, piece_vocabulary: str) -> DataFrame:
    """Base counts and fertility measures of every row."""
    names = ["doc_id", "lang", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_tokens", "chars_per_token", "chars_per_piece", "byte_share", "entropy_share", "n_pieces"]
    arrow = [pa.int64()] * 6 + [pa.float64()] * 4 + [pa.int64()]

    def measure(batches):
        from tilewright.llm import fertility as me

        code = coder(byte_vocabulary)
        if piece_vocabulary not in me._pieces:
            me._pieces[piece_vocabulary] = PieceCounts(piece_vocabulary)
        pieces = me._pieces[piece_vocabulary]
        for batch in batches:
            data, off = column_bytes(batch.column("text"))
            for i, j in slices(off, SLICE):
                part, o = data[off[i] : off[j]], off[i : j + 1] - off[i]
                w = Words(part, o, lower=False)
                base = base_counts(part, o, w)
                lines = [duplicate_lines(part[a:b].tobytes().decode()) for a, b in zip(o[:-1], o[1:])]
                ids, at = code(part, o)
                n_ids, chars = np.diff(at), per_row((part & 0xC0) != 0x80, o)
                n_pieces, n_bytes = pieces(part, o)
                bits = entropy_bits(ids, at)
                most = np.log2(np.maximum(n_ids, 2))
                columns = (*base[:3], lines, base[3], n_ids, chars / np.maximum(1, n_ids), chars / np.maximum(1, n_pieces), n_bytes / np.maximum(1, n_pieces), np.where(n_ids > 1, bits / most, 1.0), n_pieces)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), batch.column("lang").slice(i, j - i), *(pa.array(c, k) for c, k in zip(columns, arrow))], names)

    t = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("lang").cast("string"), F.lit("und")).alias("lang"), F.coalesce("text", F.lit("")).alias("text"))
    kinds = ["long", "string"] + ["long"] * 6 + ["double"] * 4 + ["long"]
    return t.mapInArrow(trimmed(measure), ", ".join(f"{a} {b}" for a, b in zip(names, kinds)))


#: Measures by the side of the median on which a text is rejected, and which of them depend on size.
SIDES = {"chars_per_token": -1, "chars_per_piece": -1, "byte_share": 1, "entropy_share": -1}
SIZED = {"entropy_share"}


def bands(rows: DataFrame, *by: str, deviations: float = DEVIATIONS) -> DataFrame:
    """By language (and size) of at least LEAST_ROWS base-passing rows, the bound of each measure."""
    good = rows.filter("not base_failed").select(*by, *SIDES)
    mid = good.groupBy(*by).agg(F.count(F.lit(1)).alias("_rows"), *(F.percentile_approx(c, 0.5, 1000).alias(f"{c}_mid") for c in SIDES))
    mid = materialize(mid.filter(F.col("_rows") >= LEAST_ROWS))
    far = good.join(maybe_broadcast(mid), list(by)).groupBy(*by, *(f"{c}_mid" for c in SIDES))
    far = far.agg(*(F.percentile_approx(F.abs(F.col(c) - F.col(f"{c}_mid")), 0.5, 1000).alias(f"{c}_mad") for c in SIDES))
    # Deviations so small that they come from rounding count as 0.005.
    reach = {c: deviations * 1.4826 * F.greatest(F.col(f"{c}_mad"), F.lit(0.005)) for c in SIDES}
    return materialize(far.select(*by, *((F.col(f"{c}_mid") + side * reach[c]).alias(f"{c}_{len(by)}") for c, side in SIDES.items())))


def verdicts(docs: DataFrame, byte_vocabulary: str, piece_vocabulary: str) -> DataFrame:
    """One row per document: base counts, base_failed, the measures, kept."""
    rows = measures(docs, byte_vocabulary, piece_vocabulary)
    failed = (F.col("n_words") < BASE_MIN_WORDS) | (100 * F.col("n_repeat_words") > BASE_REPEAT_PERCENT * F.col("n_words"))
    size = F.floor(F.log2(F.greatest(F.lit(1), F.col("n_tokens")))).cast("int")
    rows = materialize(rows.withColumns({"base_failed": failed, "size": size}))
    out = rows.join(maybe_broadcast(bands(rows, "lang", "size")), ["lang", "size"], "left").join(maybe_broadcast(bands(rows, "lang")), "lang", "left")
    inside = F.lit(True)
    for c, side in SIDES.items():
        bound = F.col(f"{c}_2") if c in SIZED else F.coalesce(f"{c}_2", f"{c}_1")
        inside = inside & F.coalesce(side * F.col(c) <= side * bound, F.lit(True))
    return out.select(*rows.columns, (~F.col("base_failed") & inside).alias("kept"))
