"""N-gram Jaccard join by partition-and-enumerate signatures.

Two sets with Jaccard similarity of at least 0.8 and sizes a <= b differ in at most (a + b) / 9
elements, and b <= 1.25 a. Sets are put in size bands; a set also visits the next band when its
partners may lie there. In a band, the feature domain (a 64-bit hash of each shingle) is cut into
`blocks` equal ranges and each range into three parts. If fewer than two elements differ in some
block, leaving out one of its parts makes the projections equal: so a block gives three
signatures, one per subset of two parts. A set of at most k differences that can afford two of
them per block needs only its first k // 2 + 1 blocks whose projections are all non-empty; of a
similar pair, the set with the shorter such prefix shares a non-empty projection with the other.
Sets without enough such blocks are alike in that, so they alone repeat the scheme under another
hash, and at last use prefix signatures (their a - ceil(0.8 a) + 1 smallest elements). No link is
lost at any step, and nothing is capped.

Signatures are dealt in buckets and met there by sorting; those that are frequent in a bounded sample are
dealt out by their documents, too, so that no task gets all of one, and are put together by aggregates.
Signatures of one value form groups. Instead of all pairs of a group, every member is first
compared with the group's hub, under two orders; members of one component need no further test. What
is still open, groups of several components, is settled exactly: in groups of at most `SMALL_GROUP`
members those of different components meet, and members of larger ones meet where they share one of
their rarest elements (a set's a - ceil(0.8 a) + 1 rarest ones hold one in common with any similar set),
so that what a whole group has in common makes no pairs. A 512-bit parity sketch, whose Hamming distance
never exceeds the sets' difference, removes pairs before any set is moved; the rest is verified
on whole sets of 64-bit shingle hashes.

Null or wordless texts have an empty set, link with nothing and are their own component. Rows that
share a doc_id, or have none, are nodes of their own; component_id is the smallest doc_id of any row
in the component (null if none has one). An empty table gives an empty result. Only doc_id and text
are read; drop_near_copies() keeps all columns.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, identified, materialize, maybe_broadcast, original, texts, without_rows
from .components import connected_components
from .textkit import U, mix, mix1, shingle_sets, trim, trimmed, word_batches

BAND = 1.5
SLACK = 1.2
LEVELS = 3
HUB_ROUNDS = 2
SKETCH_LONGS = 8
#: Sets of so many elements get wide sketches, too.
WIDE_FROM = 800
#: Open groups of at most so many members are paired directly.
SMALL_GROUP = 24
#: Documents whose signatures tell which ones are hot, how often one must occur among them, and how many may be.
HOT_SAMPLE, HOT_TIMES, HOT_SIGNATURES = 4096, 8, 1 << 16
#: Signatures that a task gathers before it deals them out, and shingles of whose signatures a bucket is made.
FLUSH_SIGNATURES, BUCKET_SHINGLES = 1 << 18, 1_000_000


def band_of(n: np.ndarray) -> np.ndarray:
    return np.floor(np.log(n) / np.log(BAND) + 1e-9).astype(np.int64)


def band_top(band: int) -> int:
    """The largest size in a band."""
    return int(np.ceil(BAND ** (band + 1) - 1e-6)) + 1


def _scheme(sizes: np.ndarray, flat: np.ndarray, at: np.ndarray, band: int, seed: int):
    """Signatures of sets of one band: (set number, signature) and which sets had too few blocks.

    sizes: per set; flat: their elements, sorted in each set; at: where each set begins.
    """
    top = band_top(band)
    k = np.minimum(sizes // 4, 2 * top // 9)
    need = k // 2 + 1
    blocks = int(np.ceil(SLACK * (2 * top // 9 // 2 + 1)))
    h = mix(flat ^ U(mix1(seed * 1000 + 17)))
    owner = np.repeat(np.arange(len(sizes)), sizes)
    block = ((h >> U(32)) * U(blocks) >> U(32)).astype(np.int64)
    part = ((h & U(0xFFFFFFFF)) * U(3) >> U(32)).astype(np.int64)
    cell = (owner * blocks + block) * 3 + part
    order = np.argsort(cell, kind="stable")
    cell, value = cell[order], mix(h[order] + U(0x51))
    begins = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]]) if len(cell) else np.zeros(0, np.int64)
    total = np.zeros(len(sizes) * blocks * 3, U)
    if len(begins):
        total[cell[begins]] = np.add.reduceat(value, begins)
    total = total.reshape(len(sizes), blocks, 3)
    full = total != 0
    left = total.sum(axis=2, dtype=U)[:, :, None] - total
    present = np.stack([full[:, :, 1] | full[:, :, 2], full[:, :, 0] | full[:, :, 2], full[:, :, 0] | full[:, :, 1]], axis=2)
    sound = np.cumsum(present.all(axis=2), axis=1)
    short = sound[:, -1] < need
    used = (np.c_[np.zeros(len(sizes), np.int64), sound[:, :-1]] < need[:, None])[:, :, None] & present
    who, b, j = np.nonzero(used)
    return who, mix(left[who, b, j] + mix(((b * 3 + j) + 1).astype(U) * U(0x9E3779B97F4A7C15) + U(mix1(band * 64 + seed)))), short


def signatures(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(set number, signature) rows; any two sets with 0.8 or more similarity share a signature."""
    sizes = np.array([len(s) for s in sets], np.int64)
    who_all, sig_all = [], []
    alive = np.flatnonzero(sizes)
    if not len(alive):
        return np.zeros(0, np.int64), np.zeros(0, U)
    own = band_of(sizes[alive])
    visits = [(alive, own)]
    reach = alive[[5 * s >= 4 * (int(np.floor(BAND ** (b + 1) - 1e-9)) + 1) - 5 for s, b in zip(sizes[alive], own)]]
    visits.append((reach, band_of(sizes[reach]) + 1))
    for members, bands in visits:
        for band in np.unique(bands).tolist():
            now = members[bands == band]
            for level in range(LEVELS):
                n = sizes[now]
                flat = np.concatenate([sets[i] for i in now])
                who, sig, short = _scheme(n, flat, np.r_[0, np.cumsum(n)[:-1]], band, level)
                who_all.append(now[who])
                sig_all.append(sig)
                now = now[short]
                if not len(now):
                    break
            for i in now.tolist():
                s = np.sort(mix(sets[i]))[: len(sets[i]) - -(-4 * len(sets[i]) // 5) + 1]
                who_all.append(np.full(len(s), i))
                sig_all.append(mix(s + U(mix1(band * 64 + 63))))
    return np.concatenate(who_all), np.concatenate(sig_all)


def sketch(s: np.ndarray) -> np.ndarray:
    """Parity of the number of elements in each of 512 buckets, as eight longs."""
    bits = np.bincount((mix(s) >> U(55)).astype(np.int64), minlength=512).astype(np.uint8) & 1
    return np.packbits(bits).view(np.int64)


def wide_sketches(s: np.ndarray) -> list[np.ndarray]:
    """For large sets, parity sketches of about one bit an element and of half as many: any two sets
    that could be similar have one length in common."""
    if len(s) < WIDE_FROM:
        return []
    bits = int(len(s) - 1).bit_length()
    low = mix(s ^ U(0x5BD1E995))
    out = []
    for k in (bits, bits - 1):
        odd = np.bincount((low >> U(64 - k)).astype(np.int64), minlength=1 << k).astype(np.uint8) & 1
        out.append(np.packbits(odd).view(np.int64))
    return out


def _wide_apart(batches):
    """Keeps the pairs whose wide sketches differ in no more places than similar sets may."""
    for batch in batches:
        keep = []
        for n, u, v in zip(batch.column("n").to_pylist(), batch.column("u").to_pylist(), batch.column("v").to_pylist()):
            apart = [int(np.bitwise_count((np.array(x, np.int64) ^ np.array(y, np.int64)).view(U)).sum()) for x in u for y in v if len(x) == len(y)]
            keep.append(not apart or 9 * max(apart) <= n)
        yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))


def _summaries(batches):
    for batch in batches:
        n, key, sk, wide = [], [], [], []
        for _, _, w in word_batches(batch):
            for s in shingle_sets(w):
                n.append(len(s))
                key.append(s.sum(dtype=U).tobytes() + mix(s).sum(dtype=U).tobytes() if len(s) else None)
                sk.append(sketch(s))
                wide.append(wide_sketches(s))
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(key, pa.binary()), pa.array(sk, pa.list_(pa.int64())), pa.array(wide, pa.list_(pa.list_(pa.int64())))],
            ["doc_id", "n_shingles", "set_key", "sketch", "wide"],
        )


def _signed(batches):
    for batch in batches:
        ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
        for i, _, w in word_batches(batch):
            who, sig = signatures(shingle_sets(w))
            yield pa.RecordBatch.from_arrays([pa.array(sig.view(np.int64)), pa.array(ids[i + who], pa.int64())], ["sig", "doc_id"])


def _dealt(buckets: int, hot: np.ndarray):
    """Rows of a bucket's signatures: sig, node. A hot signature's bucket is told by its document, too."""

    def found(batches):
        parts, size = [], 0

        def row():
            sig, node = (np.concatenate(x) for x in zip(*parts))
            sig = sig.view(U)
            bucket = mix(sig)
            if len(hot):
                often = np.isin(sig, hot)
                bucket[often] = mix(node[often].view(U))
            bucket = (bucket % U(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            edge = np.flatnonzero(np.diff(bucket[order], prepend=-1))
            off = pa.array(np.r_[edge, len(order)].astype(np.int32))
            lists = [pa.ListArray.from_arrays(off, pa.array(x[order], pa.int64())) for x in (sig.view(np.int64), node)]
            return pa.RecordBatch.from_arrays([pa.array(bucket[order][edge].astype(np.int32)), *lists], ["bucket", "sig", "node"])

        for batch in _signed(batches):
            parts.append([batch.column(c).to_numpy(zero_copy_only=False) for c in ("sig", "doc_id")])
            size += batch.num_rows
            if size >= FLUSH_SIGNATURES:
                yield row()
                parts, size = [], 0
        if size:
            yield row()

    return found


def _grouped(hot: np.ndarray):
    """sig, node of signatures that several documents of the bucket have, sig being a fingerprint of the
    group's members (were two to clash, they would only have more pairs to verify); of hot ones all."""

    def found(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        sig, node = (t.column(c).combine_chunks().flatten().to_numpy(zero_copy_only=False).view(U) for c in ("sig", "node"))
        order = np.lexsort((node, sig))
        sig, node = sig[order], node[order]
        new = np.r_[True, (sig[1:] != sig[:-1]) | (node[1:] != node[:-1])][: len(sig)]
        sig, node = sig[new], node[new]
        edge = np.flatnonzero(np.r_[True, sig[1:] != sig[:-1]][: len(sig)])
        size = np.diff(np.r_[edge, len(sig)])
        often = np.isin(sig[edge], hot) if len(hot) else np.zeros(len(edge), bool)
        total = np.add.reduceat(mix(node), edge) if len(edge) else edge.astype(U)
        prints = mix(total + mix(size.astype(U) + U(77)))
        # Of groups with the same members one is enough.
        first = np.zeros(len(edge), bool)
        first[np.unique(prints, return_index=True)[1]] = True
        keep = np.repeat((size > 1) & first & ~often, size)
        same = np.repeat(often, size)
        out = np.r_[np.repeat(prints, size)[keep], sig[same]], np.r_[node[keep], node[same]]
        trim()
        return pa.table({"hot": pa.array(np.r_[np.zeros(int(keep.sum()), bool), np.ones(int(same.sum()), bool)]), "sig": pa.array(out[0].view(np.int64)), "node": pa.array(out[1].view(np.int64))})

    return found


def signature_groups(docs: DataFrame, nodes: int, shingles: int) -> DataFrame:
    """sig, node (a written table): the groups of documents that share a signature. nodes, shingles: how many sign, with how many."""
    spark = docs.sparkSession
    share = min(2**63 - 1, HOT_SAMPLE * 2**63 // max(1, nodes))
    sample = set_signatures(docs.filter(F.shiftrightunsigned(F.xxhash64(F.col("doc_id").cast("long"), F.lit(5)), 1) <= share))
    often = sample.groupBy("sig").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= HOT_TIMES).orderBy(F.desc("n"), "sig").limit(HOT_SIGNATURES)
    shared = spark.sparkContext.broadcast(np.array([r["sig"] for r in often.collect()], np.int64).view(U))
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), shingles // BUCKET_SHINGLES)
    signed = texts(docs).filter("doc_id is not null").mapInArrow(trimmed(lambda b: _dealt(buckets, shared.value)(b)), "bucket int, sig array<long>, node array<long>")
    found = materialize(signed.groupBy("bucket").applyInArrow(lambda t: _grouped(shared.value)(t), "hot boolean, sig long, node long"))
    hot = found.filter("hot")
    prints = hot.groupBy("sig").agg(F.xxhash64(F.bit_xor(F.xxhash64("node")), F.bit_xor(F.xxhash64("node", F.lit(1))), F.count(F.lit(1))).alias("print"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    one = materialize(prints.groupBy("print").agg(F.min("sig").alias("sig")).select("sig"))  # HOT_SIGNATURES rows at most
    members = found.filter("not hot").unionByName(hot.join(F.broadcast(one), "sig", "left_semi")).select("sig", "node").distinct()
    members = materialize(members)
    discard(found, one)
    return members


def _sets(batches):
    for batch in batches:
        sets = [s.view(np.int64) for _, _, w in word_batches(batch) for s in shingle_sets(w)]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sets, pa.list_(pa.int64()))], ["node", "items"])


def set_summaries(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, set_key (128 bits; null for an empty set), sketch, wide (of large sets)."""
    return texts(docs).mapInArrow(trimmed(_summaries), "doc_id long, n_shingles long, set_key binary, sketch array<long>, wide array<array<long>>")


def set_signatures(docs: DataFrame) -> DataFrame:
    """sig, doc_id: the signatures of every document's shingle set."""
    return texts(docs).filter("doc_id is not null").mapInArrow(trimmed(_signed), "sig long, doc_id long")


def _possible(a: str, b: str):
    """False only if the pair can't reach the threshold."""
    apart = sum((F.bit_count(F.col(f"{a}.sketch")[i].bitwiseXOR(F.col(f"{b}.sketch")[i])) for i in range(SKETCH_LONGS)), F.lit(0))
    na, nb = F.col(f"{a}.n"), F.col(f"{b}.n")
    return (5 * F.least(na, nb) >= 4 * F.greatest(na, nb)) & (9 * apart <= na + nb)


def _verified(pairs: DataFrame, docs: DataFrame, wide: DataFrame, tested: DataFrame | None) -> tuple[DataFrame, DataFrame]:
    """Of distinct pairs (a, b), those whose sets reach the threshold; and all pairs tested so far."""
    if tested is not None:
        pairs = pairs.join(tested, ["a", "b"], "left_anti")
    left, right = (wide.select(F.col("node").alias(c), F.col("n").alias(f"n{c}"), F.col("wide").alias(w)) for c, w in (("a", "u"), ("b", "v")))
    pairs = pairs.join(left, "a").join(right, "b").select("a", "b", (F.col("na") + F.col("nb")).alias("n"), "u", "v")
    small = F.size("u") * F.size("v") == 0
    pairs = pairs.filter(small).select("a", "b").unionByName(pairs.filter(~small).mapInArrow(trimmed(_wide_apart), "a long, b long"))
    pairs = materialize(pairs)
    ids = materialize(pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct())
    sets = texts(docs).join(maybe_broadcast(ids), "doc_id", "left_semi").mapInArrow(trimmed(_sets), "node long, items array<long>")
    sets = materialize(sets)
    n = pairs.count()
    left = maybe_broadcast(pairs, n).join(sets.select(F.col("node").alias("a"), F.col("items").alias("x")), "a")
    both = left.join(sets.select(F.col("node").alias("b"), F.col("items").alias("y")), "b")
    common = F.size(F.array_intersect("x", "y"))
    found = materialize(both.filter(100 * common >= 80 * (F.size("x") + F.size("y") - common)).select("a", "b"))
    discard(ids, sets)
    return found, pairs if tested is None else tested.unionByName(pairs)


def _labelled(nodes: DataFrame, links: DataFrame) -> DataFrame:
    """nodes (node, n, sketch) with comp, the component under links."""
    found = connected_components(links)
    return materialize(nodes.join(found, "node", "left").select("node", "n", "sketch", F.coalesce("component", "node").alias("comp")))


def _components(docs: DataFrame, again: DataFrame | None) -> DataFrame:
    """__row_id, orig, n_shingles, comp (a __row_id), component_id, lead (the __row_id that stays for it) of every row of docs (of identified())."""
    t = docs.select(F.col("__row_id").alias("doc_id"), "text")
    rows = materialize(set_summaries(t))
    rep = rows.filter("set_key is not null").groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.max("doc_id").alias("last"))
    rep = materialize(rep.filter("rep < last").select("set_key", "rep"))
    with_rep = materialize(rows.join(maybe_broadcast(rep), "set_key", "left").select("doc_id", "n_shingles", "sketch", "wide", F.coalesce("rep", "doc_id").alias("rep")))
    discard(rows, rep)
    links = signature_links(t, with_rep)
    found = connected_components(links)
    out = with_rep.join(found, with_rep["rep"] == found["node"], "left")
    out = original(out.select(F.col("doc_id").alias("__row_id"), "n_shingles", F.coalesce("component", "rep").alias("comp")), again)
    if again is None:
        # The smallest __row_id of a component is its smallest doc_id.
        return out.withColumns({"component_id": F.col("comp"), "lead": F.col("comp")})
    out = materialize(out)
    lead = out.groupBy("comp").agg(F.min(F.struct(F.col("orig").isNull().alias("none"), "orig", "__row_id")).alias("l"))
    return out.join(lead.select("comp", F.col("l.orig").alias("component_id"), F.col("l.__row_id").alias("lead")), "comp")


def jaccard_components(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (smallest doc_id of its component)."""
    return _components(*identified(docs)).select(F.col("orig").alias("doc_id"), "n_shingles", "component_id")


def signature_links(docs: DataFrame, with_rep: DataFrame) -> DataFrame:
    """Verified links (a, b) that connect whatever is similar; with_rep: doc_id, n_shingles, sketch, rep."""
    # Of equal sets only the representative signs.
    nodes = with_rep.filter("doc_id = rep and n_shingles > 0").select(F.col("rep").alias("node"), F.col("n_shingles").alias("n"), "sketch", "wide").dropDuplicates(["node"])
    copies = materialize(with_rep.filter("doc_id <> rep").select("doc_id"))
    count, total = nodes.agg(F.count(F.lit(1)), F.sum("n")).first()
    members = signature_groups(docs.join(maybe_broadcast(copies), "doc_id", "left_anti"), count, total or 0)
    discard(copies)
    nodes = materialize(nodes.join(members.select("node").distinct(), "node", "left_semi"))

    wide = nodes.select("node", "n", "wide")
    # Hub rounds: each member with its group's hub, under one order of the nodes after the other.
    links, tested, known = None, None, nodes.withColumn("comp", F.col("node"))
    for turn in range(HUB_ROUNDS):
        hubs = members.groupBy("sig").agg(F.min(F.struct(F.xxhash64("node", F.lit(turn)), F.col("node").alias("id")))["id"].alias("hub"))
        met = members.join(hubs, "sig").filter("node <> hub").select(F.least("node", "hub").alias("a"), F.greatest("node", "hub").alias("b")).distinct()
        met = met.join(known.alias("p"), F.col("a") == F.col("p.node")).join(known.alias("q"), F.col("b") == F.col("q.node"))
        found, tested = _verified(met.filter((F.col("p.comp") != F.col("q.comp")) & _possible("p", "q")).select("a", "b"), docs, wide, tested)
        links = found if links is None else links.unionByName(found)
        known = _labelled(nodes, links)

    # What is open after the hubs: groups of several components.
    placed = materialize(members.join(known.select("node", "comp"), "node").select("sig", "node", "comp"))
    discard(members)
    sizes = placed.groupBy("sig", "comp").agg(F.count(F.lit(1)).alias("c")).groupBy("sig")
    sizes = materialize(sizes.agg(F.max(F.struct("c", "comp"))["comp"].alias("main"), F.count(F.lit(1)).alias("comps"), F.sum("c").alias("m")).filter("comps > 1"))
    small = placed.join(sizes.filter(F.col("m") <= SMALL_GROUP), "sig").select("sig", "node", "comp", (F.col("comp") != F.col("main")).alias("out"))
    small = materialize(small.join(nodes.select("node", "n", "sketch"), "node"))
    large = placed.join(sizes.filter(F.col("m") > SMALL_GROUP).select("sig"), "sig", "left_semi").select("node", "comp").distinct()
    large = materialize(large.join(nodes.select("node", "n", "sketch"), "node"))
    discard(placed, sizes)
    p, q = small.filter("out").alias("p"), small.alias("q")
    cross = (F.col("p.sig") == F.col("q.sig")) & (F.col("p.comp") != F.col("q.comp")) & (~F.col("q.out") | (F.col("p.node") < F.col("q.node"))) & _possible("p", "q")
    pairs = p.join(q, cross).select(F.least("p.node", "q.node").alias("a"), F.greatest("p.node", "q.node").alias("b"))
    if not large.isEmpty():
        pairs = pairs.unionByName(rare_pairs(docs, large))
    found, _ = _verified(pairs.distinct(), docs, wide, tested)
    discard(small, large)
    return links.unionByName(found)


def rare_pairs(docs: DataFrame, open_nodes: DataFrame) -> DataFrame:
    """a, b: of open_nodes (node, comp, n, sketch) those of different components that share one of their rarest elements."""
    ids = open_nodes.select(F.col("node").alias("doc_id"))
    sets = materialize(texts(docs).join(maybe_broadcast(ids), "doc_id", "left_semi").mapInArrow(trimmed(_sets), "node long, items array<long>"))
    items = sets.select("node", F.explode("items").alias("item"))
    times = items.groupBy("item").agg(F.count(F.lit(1)).alias("f"))
    ordered = items.join(times, "item").groupBy("node").agg(F.sort_array(F.collect_list(F.struct("f", "item"))).alias("items"))
    # In integers: a - ceil(0.8 a) + 1 elements. One of a single document meets none.
    first = F.slice("items", 1, F.size("items") - F.ceil(F.size("items") * 4 / F.lit(5)).cast("int") + 1)
    rare = materialize(ordered.select("node", F.explode(F.filter(first, lambda x: x["f"] > 1)["item"]).alias("item")).join(open_nodes, "node"))
    discard(sets)
    p, q = rare.alias("p"), rare.alias("q")
    cross = (F.col("p.item") == F.col("q.item")) & (F.col("p.node") < F.col("q.node")) & (F.col("p.comp") != F.col("q.comp")) & _possible("p", "q")
    return p.join(q, cross).select(F.col("p.node").alias("a"), F.col("q.node").alias("b"))


def drop_near_copies(docs: DataFrame) -> DataFrame:
    """docs with one row, that of the smallest doc_id, of each component; columns as given."""
    t, again = identified(docs)
    return without_rows(t, materialize(_components(t, again).filter("lead <> __row_id").select("__row_id"))).select(*docs.columns)
