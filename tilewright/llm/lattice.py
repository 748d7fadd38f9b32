"""SentencePiece encoding and decoding as a relational lattice.

Two characters that stand side by side in no piece can't end up in one, so a text is cut between
all such pairs into units that can be encoded alone. Distinct units are counted, exploded into their
substrings of bounded length, those are equi-joined with the piece table (its size is the
vocabulary's, so it is broadcast), the edges are grouped by unit, and a higher-order aggregate folds
them into ids:

* `viterbi`, for unigram models: the path of largest total score, position by position;
* `merge`, for BPE models, whose scores are merge ranks and not log-probabilities, so that the best
  path is not the model's segmentation: the adjacent pair whose joint substring is the edge of
  largest score is merged, the leftmost of equals, until no pair is an edge.

All distinct units are encoded so. The ids of the most frequent ones (at most `head`) are broadcast
by the units' hashes; occurrences of the others are joined with their ids on the unit, and put into
their documents' lists. Only a unit of over MAX_UNIT characters (a run such as a long row of one
letter), for which the fold would be quadratic, is merged with a heap in the worker. The decoded
ids are compared with the text's digest. Characters outside the vocabulary become byte pieces.

Null and empty texts have no pieces. Rows that share a doc_id or have none are encoded apart.
Repeated rows get equal rows. An empty table gives an empty result. Only doc_id and text are read.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, identified, materialize, original, texts
from .textkit import U, char_hash, column_bytes, distinct, mix, powers, slices, trimmed

MARK = "▁"
#: Most units whose ids are broadcast.
HEAD_UNITS = 1 << 19
#: Longest unit that is folded: its places are the bits of a long.
MAX_UNIT = 60
#: Bytes of text at a time.
SLICE = 1 << 18
_NONE = -2e9


class PieceTable:
    """Pieces, scores and byte pieces of a SentencePiece model file."""

    def __init__(self, path: str):
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        n = m.get_piece_size()
        self.piece = [m.id_to_piece(i) for i in range(n)]
        self.byte_id = np.zeros(256, np.int32)
        self.ids: dict[str, int] = {}
        self.score: dict[str, float] = {}
        raw: list[bytes] = []
        for i, p in enumerate(self.piece):
            if m.is_byte(i):
                self.byte_id[int(p[3:5], 16)] = i
                raw.append(bytes([int(p[3:5], 16)]))
            elif m.is_control(i) or m.is_unknown(i) or m.is_unused(i):
                raw.append(b"")
            else:
                self.ids[p], self.score[p] = i, m.get_score(i)
                raw.append(p.replace(MARK, " ").encode())
        self.longest = max(map(len, self.ids))
        self.raw, self.raw_at = np.frombuffer(b"".join(raw), np.uint8), np.r_[0, np.cumsum([len(x) for x in raw])]
        # Characters by number (0: side by side with none), and which pairs stand in a piece.
        pairs = {(ord(x), ord(y)) for p in self.ids for x, y in zip(p, p[1:])}
        chars = sorted({c for pair in pairs for c in pair})
        self.number = np.zeros(0x110000, np.int32)
        self.number[chars] = np.arange(1, len(chars) + 1)
        self.joined = np.zeros((len(chars) + 1) ** 2, bool)
        self.width = len(chars) + 1
        for x, y in pairs:
            self.joined[self.number[x] * self.width + self.number[y]] = True

    def frame(self, spark: SparkSession) -> DataFrame:
        """piece, id, score: one row per piece."""
        return spark.createDataFrame(pa.table({"piece": list(self.ids), "id": pa.array(list(self.ids.values()), pa.int32()), "score": pa.array([self.score[p] for p in self.ids], pa.float64())}))

    def merge(self, unit: str) -> list[int]:
        """The ids of one unit by the merge fold, in order of a heap."""
        parts: list[str | None] = list(unit)
        after, before = list(range(1, len(parts) + 1)), list(range(-1, len(parts) - 1))
        heap: list[tuple[float, int, str]] = []

        def offer(i: int) -> None:
            if i >= 0 and after[i] < len(parts):
                p = parts[i] + parts[after[i]]
                if p in self.score:
                    heapq.heappush(heap, (-self.score[p], i, p))

        for i in range(len(parts) - 1):
            offer(i)
        while heap:
            _, i, p = heapq.heappop(heap)
            if parts[i] is None or after[i] >= len(parts) or parts[i] + parts[after[i]] != p:
                continue
            j = after[i]
            parts[i], parts[j], after[i] = p, None, after[j]
            if after[j] < len(parts):
                before[after[j]] = i
            offer(before[i])
            offer(i)
        out: list[int] = []
        for p in parts:
            if p is not None:
                out += [self.ids[p]] if p in self.ids else self.byte_id[list(p.encode())].tolist()
        return out

    def bytes_of(self, ids: np.ndarray) -> bytes:
        """The bytes of ids, without the mark that begins a text."""
        size = (self.raw_at[1:] - self.raw_at[:-1])[ids]
        end = np.cumsum(size)
        at = np.repeat(self.raw_at[ids] - end + size, size) + np.arange(end[-1] if len(end) else 0)
        return self.raw[at].tobytes()[1:] if len(at) else b""

    def decode(self, ids) -> str:
        """The text of ids; bytes that are no UTF-8 become replacement characters."""
        text = self.bytes_of(np.asarray(ids, np.int64))
        return text.decode("utf-8", "replace")


class Units:
    """The units of some rows: places in their joint marked text, hashes, first unit of each row."""

    def __init__(self, table: PieceTable, data: np.ndarray, off: np.ndarray):
        text = data.tobytes().decode()
        code = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        chars = np.r_[0, np.cumsum((data & 0xC0) != 0x80)][off]
        full = np.flatnonzero(np.diff(chars))
        code = np.insert(np.where(code == 32, np.uint32(ord(MARK)), code), chars[full], ord(MARK))
        begin = chars[full] + np.arange(len(full))  # where the full rows begin
        self.text = code.astype("<u4").tobytes().decode("utf-32-le")
        number = table.number[code]
        cut = np.ones(len(code), bool)
        cut[1:] = ~table.joined[number[:-1] * table.width + number[1:]]
        cut[begin] = True
        self.start = np.flatnonzero(cut)
        self.end = np.r_[self.start[1:], len(code)].astype(np.int64)
        self.first = np.searchsorted(self.start, np.r_[begin, len(code)])
        self.first = np.r_[self.first[np.searchsorted(full, np.arange(len(off) - 1))], len(self.start)]
        p, q = powers(len(code) + 1)
        total = np.zeros(len(code) + 1, U)
        np.cumsum(char_hash()[code] * p[:-1], out=total[1:])
        self.hash = mix((total[self.end] - total[self.start]) * q[self.start] + (self.end - self.start).astype(U))

    def __getitem__(self, i: int) -> str:
        return self.text[self.start[i] : self.end[i]]


def _shift(x: Column, n: Column) -> Column:
    return F.call_function("shiftleft", x, n)


def lattice(units: DataFrame, pieces: DataFrame, longest: int, bits: bool = False) -> DataFrame:
    """units (unit and what else describes it) with edges: the pieces at each place of each distinct unit.

    An edge is (start, len, id, score); with bits it is (late, start, ends, inner, id): the negative score,
    and as bits of a long the places at its ends and those between. With bits the pieces of one character,
    of which each place has one at most and which merge nothing, are left out.
    """
    # The empty substring meets a row of its own, so that a unit without any piece stays.
    none = pieces.sparkSession.createDataFrame([("", -1, 0.0)], "piece string, id int, score double")
    n = F.length("unit")
    # Numbered as they come, units are in order for the grouping, whose sort then has little to do.
    numbered = units.withColumn("_number", F.monotonically_increasing_id())
    spots = numbered.select(*numbered.columns, F.explode(F.sequence(F.lit(0), n - 1)).alias("start"))
    if bits:
        pieces = pieces.filter(F.length("piece") > 1)
    least = F.when(F.col("start") == 0, 0).otherwise(1)
    subs = spots.select(*numbered.columns, "start", F.explode(F.sequence(least, F.least(F.lit(longest), n - F.col("start")))).alias("len"))
    subs = subs.withColumn("piece", F.substring("unit", F.col("start") + 1, F.col("len")))
    edges = subs.join(F.broadcast(pieces.unionByName(none)), "piece")
    edge = F.struct("start", "len", "id", "score")
    if bits:
        one = F.lit(1).cast("long")
        ends = _shift(one, F.col("start")).bitwiseOR(_shift(one, F.col("start") + F.col("len")))
        edge = F.struct((-F.col("score")).alias("late"), "start", ends.alias("ends"), _shift(_shift(one, F.col("len") - 1) - 1, F.col("start") + 1).alias("inner"), "id")
    return edges.groupBy("_number", *units.columns).agg(F.collect_list(F.when(F.col("len") > 0, edge)).alias("edges")).drop("_number")


def _char_bytes(unit: Column, start: Column, byte_base: int) -> Column:
    """Byte-piece ids of the character at start (byte pieces have consecutive ids)."""
    code = F.hex(F.encode(F.substring(unit, start + 1, F.lit(1)), "UTF-8"))
    return F.transform(F.sequence(F.lit(1), F.length(code) - 1, F.lit(2)), lambda k: (F.conv(F.substring(code, k, F.lit(2)), 16, 10).cast("int") + byte_base))


def in_rank_order(table: PieceTable) -> bool:
    """Whether merging one pass over the edges, best score first, is the merge fold.

    It is if no merge makes a better one possible. What is merged inside a span that becomes one piece is
    what is merged in that piece alone, so it is enough to merge every piece by itself.
    """
    for p in table.ids:
        parts, last = list(p), 1e18
        while len(parts) > 1:
            score, turn = max((table.score.get(a + b, _NONE), -i) for i, (a, b) in enumerate(zip(parts, parts[1:])))
            if score <= _NONE:
                break
            if score > last:
                return False
            parts[-turn : 2 - turn], last = [parts[-turn] + parts[1 - turn]], score
    return True


def character_ids(table: PieceTable) -> Column:
    """The ids of pieces of one character by its code point, -1 where there is none; one constant."""
    single = {ord(p): i for p, i in table.ids.items() if len(p) == 1}
    return F.split(F.lit(",".join(str(single.get(c, -1)) for c in range(max(single, default=0) + 1))), ",").cast("array<int>")


def merge_fold(lat: DataFrame, table: PieceTable) -> DataFrame:
    """unit, ids of a lattice with bits: adjacent parts merged by the best edge until none is left; for vocabularies in_rank_order().

    Edges are taken from the best score on, the leftmost of equals first. The state has one bit for each
    place between characters at which a part ends; an edge merges two parts if its ends are such places
    and just one is between them.
    """
    columns = [c for c in lat.columns if c != "edges"]
    n, two = F.length("unit"), F.lit(3).cast("long")

    def step(s: Column, e: Column) -> Column:
        m = s.bitwiseAND(e["inner"])
        return F.when((m != 0) & (m == m.bitwiseAND(-m)) & (s.bitwiseAND(e["ends"]) == e["ends"]), s - m).otherwise(s)

    lat = lat.withColumn("at", F.aggregate(F.sort_array("edges"), _shift(F.lit(1).cast("long"), n + 1) - 1, step))
    at, by_code = F.col("at"), character_ids(table)
    parts = F.filter("edges", lambda e: (at.bitwiseAND(e["inner"]) == 0) & (at.bitwiseAND(e["ends"]) == e["ends"]))
    parts = F.transform(parts, lambda e: F.struct(e["start"].alias("start"), e["id"].alias("id")))
    # Parts of one character end at two places side by side.
    single = F.filter(F.sequence(F.lit(0), n - 1), lambda i: at.bitwiseAND(_shift(two, i)) == _shift(two, i))
    single = F.transform(single, lambda i: F.struct(i.alias("start"), F.coalesce(F.get(by_code, F.ascii(F.substring(F.col("unit"), i + 1, F.lit(1)))), F.lit(-1)).alias("id")))
    lat = lat.withColumn("parts", F.sort_array(F.concat(parts, single)))
    base = int(table.byte_id[0])
    bytes_too = F.flatten(F.transform("parts", lambda p: F.when(p["id"] >= 0, F.array(p["id"])).otherwise(_char_bytes(F.col("unit"), p["start"], base))))
    return lat.select(*columns, F.when(F.array_contains("parts.id", -1), bytes_too).otherwise(F.col("parts.id")).alias("ids"))


def viterbi_fold(lat: DataFrame, table: PieceTable, byte_score: float = -20.0) -> DataFrame:
    """unit, ids: the best-scoring path; a character without an edge costs byte_score."""
    # best[i]: score of the best path to position i, the start of its last edge and that edge's id (-1: bytes).
    first = F.array(F.struct(F.lit(0.0).alias("score"), F.lit(-1).alias("from"), F.lit(-1).alias("id")))

    def step(best: Column, end: Column) -> Column:
        ways = F.transform(
            F.filter("edges", lambda e: e["start"] + e["len"] == end),
            lambda e: F.struct((F.get(best, e["start"])["score"] + e["score"]).alias("score"), e["start"].alias("from"), e["id"].alias("id")),
        )
        single = F.struct((F.get(best, end - 1)["score"] + byte_score).alias("score"), (end - 1).alias("from"), F.lit(-1).alias("id"))
        return F.concat(best, F.array(F.array_max(F.concat(ways, F.array(single)))))

    best = F.aggregate(F.sequence(F.lit(1), F.length("unit")), first, step)
    back = F.aggregate(
        F.sequence(F.lit(1), F.length("unit")),
        F.struct(F.length("unit").alias("at"), F.array().cast("array<struct<from:int,id:int>>").alias("path")),
        lambda s, _: F.when(s["at"] <= 0, s).otherwise(F.struct(
            F.get(F.col("best"), s["at"])["from"].alias("at"),
            F.concat(F.array(F.struct(F.get(F.col("best"), s["at"])["from"].alias("from"), F.get(F.col("best"), s["at"])["id"].alias("id"))), s["path"]).alias("path"),
        )),
    )["path"]
    ids = F.flatten(F.transform("path", lambda p: F.when(p["id"] >= 0, F.array(p["id"])).otherwise(_char_bytes(F.col("unit"), p["from"], int(table.byte_id[0])))))
    columns = [c for c in lat.columns if c != "edges"]
    return lat.withColumn("best", best).withColumn("path", back).select(*columns, ids.alias("ids"))


def unit_counts(docs: DataFrame, model: str) -> DataFrame:
    """unit, n: how often each unit of at most MAX_UNIT characters occurs (pre-counted in each slice)."""

    def count(batches):
        table = _table(model)
        for batch in batches:
            data, off = column_bytes(batch.column("text"))
            for i, j in slices(off, SLICE):
                u = Units(table, data[off[i] : off[j]], off[i : j + 1] - off[i])
                short = np.flatnonzero(u.end - u.start <= MAX_UNIT)
                which, at = distinct(u.hash[short])
                yield pa.RecordBatch.from_arrays([pa.array([u[k] for k in short[at].tolist()], pa.string()), pa.array(np.bincount(which, minlength=len(at)))], ["unit", "n"])

    return texts(docs).mapInArrow(trimmed(count), "unit string, n long").groupBy("unit").agg(F.sum("n").alias("n"))


_state: dict[str, tuple] = {}


def _table(model: str) -> PieceTable:
    if model not in _state:
        _state[model] = PieceTable(model)
    return _state[model]


def unit_hash(units: list[str]) -> np.ndarray:
    """The hash that each unit has in a text."""
    code = np.frombuffer("".join(units).encode("utf-32-le"), np.uint32)
    size = np.array([len(u) for u in units], np.int64)
    end = np.cumsum(size)
    p, q = powers(len(code) + 1)
    total = np.r_[U(0), np.cumsum(char_hash()[code] * p[:-1], dtype=U)]
    return mix((total[end] - total[end - size]) * q[end - size] + size.astype(U))


def unit_codes(docs: DataFrame, model: str, fold=merge_fold) -> DataFrame:
    """unit, n, ids (a written table) of every distinct unit, by lattice and fold."""
    t = _table(model)
    base = int(t.byte_id[0])
    if (t.byte_id != base + np.arange(256)).any():
        raise ValueError("byte pieces are not consecutive")
    if fold is merge_fold and not in_rank_order(t):
        raise ValueError("a merge of this vocabulary makes a better one possible")
    # Counting deals out units; their substrings and edges stay where they are, with no further exchange.
    return materialize(fold(lattice(unit_counts(docs, model), t.frame(docs.sparkSession), t.longest, fold is merge_fold), t))


class Head:
    """Ids of the most frequent units, by their sorted hashes."""

    def __init__(self, h: np.ndarray, off: np.ndarray, ids: np.ndarray):
        order = np.argsort(h)
        # Of units with one hash none is here: they are joined as the rarer ones are.
        alone = np.ones(len(h), bool)
        same = h[order][1:] == h[order][:-1]
        alone[1:] &= ~same
        alone[:-1] &= ~same
        order = order[alone]
        self.hash, size = h[order], np.diff(off)[order]
        self.at = np.r_[0, np.cumsum(size)].astype(np.int32)
        self.ids = ids[np.repeat(off[:-1][order] - self.at[:-1], size) + np.arange(self.at[-1])].astype(np.int32)

    def find(self, h: np.ndarray) -> np.ndarray:
        """The place of each hash, or -1."""
        if not len(self.hash):
            return np.full(len(h), -1)
        which, first = distinct(h)
        h = h[first]
        at = np.searchsorted(self.hash, h)
        at[at == len(self.hash)] = 0
        return np.where(self.hash[at] == h, at, -1)[which]


def encoded(docs: DataFrame, model: str, head: int = HEAD_UNITS, fold=merge_fold) -> DataFrame:
    """doc_id, n_pieces, ids, round_trip (the decoded ids give the text back)."""
    spark = docs.sparkSession
    t, again = identified(docs)
    t = t.select(F.col("__row_id").alias("doc_id"), "text")
    codes = unit_codes(t, model, fold)
    narrow = len(_table(model).piece) < 1 << 15  # ids move as 16 bits
    power = F.floor(F.log2("n")).cast("int")
    sizes = dict(codes.groupBy(power.alias("k")).agg(F.count(F.lit(1))).collect())  # at most 63 rows
    k, total = 64, 0
    while k > 0 and total + sizes.get(k - 1, 0) <= head:
        k -= 1
        total += sizes.get(k, 0)
    often = F.col("n") >= F.lit(float(2**k))

    def hashed(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(unit_hash(batch.column("unit").to_pylist()).view(np.int64)), batch.column("ids")], ["h", "ids"])

    top = codes.filter(often).select("unit", "ids").mapInArrow(hashed, "h long, ids array<int>").toArrow().combine_chunks()  # at most `head` short rows
    ids = top.column("ids").combine_chunks() if top.num_rows else pa.array([], pa.list_(pa.int32()))
    top = Head(top.column("h").to_numpy().view(U), ids.offsets.to_numpy(), ids.values.to_numpy(zero_copy_only=False))
    here = len(top.hash)
    known = spark.sparkContext.broadcast(top)
    del top, ids

    def looked_up(batch):
        table, top = _table(model), known.value
        data, off = column_bytes(batch.column("text"))
        for i, j in slices(off, SLICE):
            u = Units(table, data[off[i] : off[j]], off[i : j + 1] - off[i])
            yield i, j, data, off, u, top.find(u.hash)

    def rare(batches):
        for batch in batches:
            for i, j, _, _, u, at in looked_up(batch):
                gap = np.flatnonzero((at < 0) & (u.end - u.start <= MAX_UNIT))
                row = np.searchsorted(u.first, gap, "right") - 1
                turn = np.arange(len(gap)) - np.searchsorted(row, row)
                ids = batch.column("doc_id").to_numpy(zero_copy_only=False)[i:j][row] if len(row) else np.zeros(0, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(turn.astype(np.int32)), pa.array([u[k] for k in gap.tolist()], pa.string())], ["doc_id", "turn", "unit"])

    def encode(batches):
        for batch in batches:
            for i, j, data, off, u, at in looked_up(batch):
                table, top = _table(model), known.value
                hit = np.flatnonzero(at >= 0)
                n = (top.at[1:] - top.at[:-1])[at[hit]].astype(np.int64)
                size = np.ones(len(at), np.int64)
                size[hit] = n
                long = {x: np.array(table.merge(u[x]), np.int32) for x in np.flatnonzero((at < 0) & (u.end - u.start > MAX_UNIT)).tolist()}
                for x, ids in long.items():
                    size[x] = len(ids)
                end = np.cumsum(size)
                # A unit without ids here leaves -1 in its place.
                out = np.full(end[-1] if len(end) else 0, -1, np.int16 if narrow else np.int32)
                turn = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
                out[np.repeat(end[hit] - n, n) + turn] = top.ids[np.repeat(top.at[at[hit]], n) + turn]
                for x, ids in long.items():
                    out[end[x] - len(ids) : end[x]] = ids
                lists = pa.ListArray.from_arrays(pa.array(np.r_[0, end][u.first].astype(np.int32)), pa.array(out))
                digest = np.array([xxhash.xxh3_64_intdigest(data[off[r] : off[r + 1]].tobytes()) for r in range(i, j)], np.uint64)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), pa.array(digest.view(np.int64)), lists], ["doc_id", "digest", "ids"])

    def fill(batches):
        for batch in batches:
            table = _table(model)
            n, ids, ok = [], [], []
            off, values = batch.column("ids").offsets.to_numpy(), batch.column("ids").values.to_numpy(zero_copy_only=False)
            if "fills" in batch.schema.names:
                fills = batch.column("fills")
                fill_off, inner = fills.offsets.to_numpy(), fills.values
                in_off, in_values = inner.offsets.to_numpy(), inner.values.to_numpy(zero_copy_only=False)
            for r, want in enumerate(batch.column("digest").to_numpy().view(np.uint64).tolist()):
                got = values[off[r] : off[r + 1]]
                gap = np.flatnonzero(got < 0)
                if len(gap):
                    spans = in_off[fill_off[r] : fill_off[r + 1] + 1]
                    size = np.ones(len(got), np.int64)
                    size[gap] = np.diff(spans)
                    end = np.cumsum(size)
                    whole = np.empty(end[-1], np.int32)  # every place is filled
                    rest = np.flatnonzero(got >= 0)
                    whole[end[rest] - 1] = got[rest]
                    m = size[gap]
                    turn = np.arange(int(m.sum())) - np.repeat(np.cumsum(m) - m, m)
                    whole[np.repeat(end[gap] - m, m) + turn] = in_values[spans[0] : spans[-1]]
                    got = whole
                got = got.astype(np.int32, copy=False)
                n.append(len(got))
                ids.append(got)
                ok.append(xxhash.xxh3_64_intdigest(table.bytes_of(got)) == want)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids, pa.list_(pa.int32())), pa.array(ok, pa.bool_())], ["__row_id", "n_pieces", "ids", "round_trip"])

    rows = texts(t).mapInArrow(trimmed(encode), f"doc_id long, digest long, ids array<{'short' if narrow else 'int'}>")
    if total < sum(sizes.values()) or here < total:
        left = codes if here < total else codes.filter(~often)
        gaps = texts(t).mapInArrow(trimmed(rare), "doc_id long, turn int, unit string").join(left.select("unit", "ids"), "unit")
        fills = gaps.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("turn", "ids"))).alias("fills"))
        # Written before the rows move, so that the disk never holds the shuffles of units and of rows at once.
        fills = materialize(fills.select("doc_id", F.col("fills.ids").alias("fills")))
        rows = rows.join(fills.hint("merge"), "doc_id", "left")
    discard(codes)
    out = rows.mapInArrow(trimmed(fill), "__row_id long, n_pieces long, ids array<int>, round_trip boolean")
    return original(out, again).select(F.col("orig").alias("doc_id"), "n_pieces", "ids", "round_trip")


def decoded(rows: DataFrame, model: str) -> DataFrame:
    """doc_id and text of rows (doc_id, ids)."""

    def decode(batches):
        t = _table(model)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([t.decode(x or []) for x in batch.column("ids").to_pylist()], pa.string())], ["doc_id", "text"])

    return rows.select("doc_id", "ids").mapInArrow(decode, "doc_id long, text string")
