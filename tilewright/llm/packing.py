"""Packing of token pieces into fixed-length sequences, shortest pack first, over a histogram.

Documents become token ids (with a closing id) and are cut into full pieces and one remainder. The
driver sees only the histogram of piece lengths (at most `capacity` rows): lengths are placed from
the longest on, each on the shortest open pack it fits; packs of one make-up are one pattern with a
count. Patterns become slots (length, first rank, first sequence, offset), and a piece finds its
place through its rank among the pieces of its length. Ranks are counted per (length, salt), so that
no length is ranked in one task.

Units of text are told by 64-bit hashes within a worker. Null texts are empty: their document is the closing id alone. Null doc_ids are packed as any other.
Rows that repeat are packed as often as they occur. An empty table gives an empty result. Only
doc_id and text are read; pack_pieces() keeps whatever other columns its input has.
"""

from __future__ import annotations

import heapq
import os
import re
import unicodedata
from collections.abc import Callable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialize, maybe_broadcast, texts
from .textkit import U, char_hash, column_bytes, distinct, mix, powers, slices, trimmed

CAPACITY = 2048
CLOSING_ID = 1
MEMO_UNITS = 600_000
CHECKED_UNITS = 3000
#: Bytes of text at a time.
SLICE = 1 << 19
ROWS_PER_SALT = 100_000

# The code points that the public pre-tokeniser's \s stands for.
BLANKS = [*range(9, 14), 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
# Fixed value: the public pre-tokeniser's pattern.
PRE_TOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Code points below this are sorted into letters, numbers and others; between any of the rest no cut is made.
SORTED_BELOW = 0x530
_BLANK, _LETTER, _NUMBER, _OTHER, _QUOTE, _UNSORTED = range(6)

_coders: dict[str, "UnitCoder"] = {}
_kinds: list[np.ndarray] = []


def _byte_characters() -> dict[str, int]:
    """The printable stand-ins of bytes in a byte-level vocabulary: themselves, or else 256 upwards."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def kinds() -> np.ndarray:
    """What the pre-tokeniser takes each code point for."""
    if not _kinds:
        kind = np.full(0x110000, _UNSORTED, np.uint8)
        for c in range(SORTED_BELOW):
            name = unicodedata.category(chr(c))
            kind[c] = _UNSORTED if name == "Cn" else {"L": _LETTER, "N": _NUMBER}.get(name[0], _OTHER)
        kind[BLANKS], kind[ord("'")] = _BLANK, _QUOTE
        _kinds.append(kind)
    return _kinds[0]


class Units:
    """The units of some rows: no pre-token crosses their ends, so each can be encoded on its own.

    A unit is a run of characters of one kind with the space before it, or a run of blanks without that
    space. Around apostrophes, where contractions begin, and around unsorted characters nothing is cut.
    Added tokens are units of their own, and what stands beside them is encoded as if a text ended there.
    """

    def __init__(self, data: np.ndarray, off: np.ndarray, added: re.Pattern):
        self.text = data.tobytes().decode()
        code = np.frombuffer(self.text.encode("utf-32-le"), np.uint32)
        n = len(code)
        rows = np.r_[0, np.cumsum((data & 0xC0) != 0x80)][off]
        special = [m.span() for m in added.finditer(self.text)]
        edge = np.zeros(n + 1, bool)
        edge[rows] = True
        edge[[x for span in special for x in span]] = True
        kind = kinds()[code]
        blank = kind == _BLANK
        cut = edge[:-1].copy()
        if n > 1:
            old, new, here, after = kind[:-1], kind[1:], blank[1:], blank[:-1]
            # The last blank of several goes with what follows, or stands alone.
            follows = np.r_[~blank[2:] & ~edge[2:-1], False]
            sure = np.maximum(old, new) < _QUOTE
            cut[1:] |= here & ~after | here & after & follows | ~here & after & (code[:-1] != 32) | ~here & ~after & sure & (old != new)
        for a, b in special:
            cut[a + 1 : b] = False
        self.start = np.flatnonzero(cut)
        self.end = np.r_[self.start[1:], n].astype(np.int64)
        self.first = np.searchsorted(self.start, rows)
        p, q = powers(n + 1)
        total = np.zeros(n + 1, U)
        np.cumsum(char_hash()[code] * p[:-1], out=total[1:])
        self.hash = mix((total[self.end] - total[self.start]) * q[self.start] + (self.end - self.start).astype(U))

    def __getitem__(self, i: int) -> str:
        return self.text[self.start[i] : self.end[i]]


class Memo:
    """Ids of units by their 64-bit hashes, at most MEMO_UNITS of them."""

    def __init__(self):
        self.hash, self.at, self.size, self.ids = np.zeros(0, U), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32)

    def learn(self, h: np.ndarray, ids: list[list[int]]) -> None:
        size = np.fromiter(map(len, ids), np.int64, len(ids))
        at = len(self.ids) + np.cumsum(size) - size
        self.ids = np.concatenate([self.ids, np.fromiter(chain.from_iterable(ids), np.uint32, int(size.sum()))])
        order = np.argsort(np.r_[self.hash, h], kind="stable")
        self.hash, self.at, self.size = (np.r_[x, y][order] for x, y in ((self.hash, h), (self.at, at), (self.size, size)))

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The place of each hash, and which are known."""
        at = np.minimum(np.searchsorted(self.hash, h), max(0, len(self.hash) - 1))
        return at, self.hash[at] == h if len(self.hash) else np.zeros(len(h), bool)


def remembered(memo: Memo, units, encode: Callable[[list[str]], list[list[int]]]) -> tuple[np.ndarray, np.ndarray]:
    """Of all units of some rows: their ids one after the other, and how many each has."""
    which, first = distinct(units.hash)
    h = units.hash[first]
    at, known = memo.find(h)
    if not known.all():
        if len(memo.hash) > MEMO_UNITS:
            memo.__init__()
            known = np.zeros(len(h), bool)
        new = np.flatnonzero(~known)
        memo.learn(h[new], encode([units[k] for k in first[new].tolist()]))
        at, _ = memo.find(h)
    begin, size = memo.at[at][which], memo.size[at][which]
    end = np.cumsum(size)
    return memo.ids[np.repeat(begin - end + size, size) + np.arange(end[-1] if len(end) else 0)], size


class UnitCoder:
    """Ids of units under a byte-level vocabulary.

    The vocabulary of the tokenizer file is run by the faster of the two public byte-pair engines;
    the tokenizer itself checks it on the first units of each worker.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import tiktoken
        from tokenizers import Tokenizer

        self.judge = Tokenizer.from_file(path)
        added = self.judge.get_added_tokens_decoder()
        if any(t.single_word or t.lstrip or t.rstrip for t in added.values()):
            raise ValueError("added tokens that depend on what stands beside them")
        self.special = {t.content: [i] for i, t in added.items()}
        self.added = re.compile("|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) or r"(?!)")
        byte = _byte_characters()
        ranks = {bytes(byte[c] for c in token): i for token, i in self.judge.get_vocab().items() if token not in self.special}
        self.engine = tiktoken.Encoding("units", pat_str=PRE_TOKEN, mergeable_ranks=ranks, special_tokens={})
        self.memo, self.unchecked = Memo(), CHECKED_UNITS

    def encode(self, units: list[str]) -> list[list[int]]:
        ids = [self.special.get(u) or self.engine.encode_ordinary(u) for u in units]
        if self.unchecked > 0:
            probe = units[: self.unchecked]
            self.unchecked -= len(probe)
            for u, e, own in zip(probe, self.judge.encode_batch(probe, add_special_tokens=False), ids):
                if e.ids != own:
                    raise ValueError(f"the engines disagree on {u!r}")
        return ids

    def __call__(self, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of some rows, one after the other, and where each row's begin and end."""
        units = Units(data, off, self.added)
        ids, size = remembered(self.memo, units, self.encode)
        return ids, np.r_[0, np.cumsum(size)][units.first]


def coder(path: str) -> UnitCoder:
    if path not in _coders:
        _coders[path] = UnitCoder(path)
    return _coders[path]


def encode_rows(batch: pa.RecordBatch, path: str) -> Iterator[bytes]:
    """The ids of each row's text, as little-endian unsigned 32-bit bytes."""
    code = coder(path)
    data, off = column_bytes(batch.column("text"))
    for i, j in slices(off, SLICE):
        ids, at = code(data[off[i] : off[j]], off[i : j + 1] - off[i])
        for a, b in zip(at[:-1].tolist(), at[1:].tolist()):
            yield ids[a:b].astype("<u4").tobytes()


def tokenized_pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, closing: int = CLOSING_ID) -> DataFrame:
    """doc_id, start, length, ids (binary, little-endian unsigned 32-bit), doc_tokens: whole pieces and a remainder."""
    end = np.array([closing], "<u4").tobytes()

    def pieces(batches):
        for batch in batches:
            ids, start, length, body, total = [], [], [], [], []
            for d, raw in zip(batch.column("doc_id").to_pylist(), encode_rows(batch, vocabulary)):
                raw += end
                n = len(raw) // 4
                for a in range(0, n, capacity):
                    ids.append(d)
                    start.append(a)
                    length.append(min(capacity, n - a))
                    body.append(raw[4 * a : 4 * (a + capacity)])
                    total.append(n)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip((ids, start, length, body, total), kinds)], ["doc_id", "start", "length", "ids", "doc_tokens"])

    return texts(docs).mapInArrow(trimmed(pieces), "doc_id long, start long, length long, ids binary, doc_tokens long")


def pack_histogram(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[tuple[int, int], ...], int]]:
    """Patterns and their counts; a pattern is ((length, times), ...) in order of placement.

    Each piece, the longest first, goes to the shortest open pack if it fits there, else to a new one:
    all packs of one pattern take a piece each before any takes a second, and a new pack takes all it
    can, as it stays the shortest that has room.
    """
    packs: list[tuple[int, int, tuple, int]] = []  # used, tie breaker, pattern, count: the shortest on top
    done, tie = [], 0
    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left:
            if packs and packs[0][0] + length <= capacity:
                used, _, pattern, n = heapq.heappop(packs)
                if n > left:
                    tie += 1
                    heapq.heappush(packs, (used, tie, pattern, n - left))
                n, times = min(n, left), 1
                pattern = (*pattern[:-1], (length, pattern[-1][1] + 1)) if pattern[-1][0] == length else (*pattern, (length, 1))
            else:
                times = min(left, capacity // length)
                used, n, pattern = 0, left // times, ((length, times),)
            left -= n * times
            used += length * times
            tie += 1
            if used < capacity:
                heapq.heappush(packs, (used, tie, pattern, n))
            else:
                done.append((pattern, n))
    return done + [(p, n) for _, _, p, n in sorted(packs)]


def pattern_slots(patterns) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, ranks, times, first sequence, offset) of each pattern entry."""
    rank: dict[int, int] = {}
    out, sequence = [], 0
    for pattern, n in patterns:
        offset = 0
        for length, times in pattern:
            a = rank.get(length, 0)
            out.append((length, a, n * times, times, sequence, offset))
            rank[length] = a + n * times
            offset += length * times
        sequence += n
    return out


def pack_pieces(pieces: DataFrame, order: list[str], capacity: int = CAPACITY, packer: Callable = pack_histogram) -> DataFrame:
    """pieces with sequence_id and offset; order: columns that tell pieces of one length apart."""
    spark = pieces.sparkSession
    pieces = materialize(pieces)
    n = pieces.count()
    salts = max(8, min(1 << 16, n // ROWS_PER_SALT))
    salted = pieces.withColumn("_salt", F.pmod(F.xxhash64(*order), F.lit(salts)))
    counts = materialize(salted.groupBy("length", "_salt").agg(F.count(F.lit(1)).alias("_n")))
    histogram = {r[0]: r[1] for r in counts.groupBy("length").agg(F.sum("_n")).collect()}
    slots = pattern_slots(packer(histogram, capacity))
    slots = spark.createDataFrame(slots, "length long, _rank0 long, _ranks long, _times long, _seq0 long, _offset0 long")
    before = Window.partitionBy("length").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.withColumn("_base", F.coalesce(F.sum("_n").over(before), F.lit(0))).select("length", "_salt", "_base")
    within = Window.partitionBy("length", "_salt").orderBy(*order)
    ranked = salted.withColumn("_at", F.row_number().over(within) - 1).join(maybe_broadcast(bases, min(n, salts * capacity)), ["length", "_salt"])
    ranked = ranked.withColumn("_rank", F.col("_base") + F.col("_at"))
    # The slots are bounded by the capacity, not by the data.
    placed = ranked.join(F.broadcast(slots), "length").filter("_rank >= _rank0 and _rank < _rank0 + _ranks")
    turn = F.col("_rank") - F.col("_rank0")
    return placed.select(
        *pieces.columns,
        (F.col("_seq0") + F.floor(turn / F.col("_times"))).cast("long").alias("sequence_id"),
        (F.col("_offset0") + F.col("length") * (turn % F.col("_times"))).cast("long").alias("offset"),
    )


def packed_sequences(placed: DataFrame) -> DataFrame:
    """sequence_id, ids (binary), parts: the sequences themselves, from placed pieces with their ids."""
    parts = F.array_sort(F.collect_list(F.struct("offset", "doc_id", "start", "length", "ids")))
    return placed.groupBy("sequence_id").agg(parts.alias("parts")).select(
        "sequence_id", F.aggregate("parts", F.lit(b""), lambda a, p: F.concat(a, p["ids"])).alias("ids"),
        F.transform("parts", lambda p: F.struct(p["offset"], p["doc_id"], p["start"], p["length"])).alias("parts"),
    )
