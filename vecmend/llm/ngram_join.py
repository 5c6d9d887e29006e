"""N-gram Jaccard self-join by partition-enumeration signatures.

A document is the set of its word 5-grams.  Sets are put in bands of sizes; a set
also joins the next band if a similar set could lie there.  In a band, the feature
domain is hashed into groups of three cells.  A signature is a set's content of a
subset of two of a group's cells: all three subsets of each group are enumerated.
Two sets of Jaccard similarity t differ in at most d features.  One feature spoils two of a
group's three signatures, a second one the third, so that with more than d/2
groups some signature stays equal.  Only as many signatures are shown as can be spoiled,
and m more: the first non-empty ones in one order for all, which puts those that hold a
feature that a sample does not find frequent before the others.  A set that has too
few non-empty ones also shows its empty ones.  Similar sets share m signatures, so that each set then
leaves out the m - 1 that most sets show, and with them what stands in many otherwise different texts.

Signatures are range-partitioned and sorted, so that a hot signature is cut
into several sorted runs, which are linked across their boundaries.  Every set of
a run is checked against the run's head, the member with most frequent features.  Links give
components.  Only two members of a run that are in different components, one of them
not linked to the head, can still be a link that counts.  Such members are described by
their differences from the head.  Two similar members must share a known number of these,
so those that no other member has and a prefix filter by rarity exclude nearly all pairs.
Members so far from the head that they cannot be similar to one that is linked to it are described by a prefix of
their own features instead.  What is left is compared exactly.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import byte_slices, deal, durable, in_slices, let_go, mix, prefix_hashes, span_hashes, splitters, utf8
from .components import connected_components

SHINGLE = 5
#: Similarity of 0.75 as a fraction, so that all comparisons are in integers.
SHARE = (75, 100)
#: Rows of ids up to which a side is broadcast instead of shuffled (16 bytes a row).
BROADCAST_ROWS = 2_000_000
#: Documents in the sample that finds frequent features, and how many of those come last.
#: The order of signatures and features follows from it; any order keeps the join exact.
SAMPLE_DOCS, COMMON_MIN, COMMON_MOST = 16_000, 3, 200_000

_BLANK = np.zeros(256, dtype=bool)
_BLANK[[32, *range(9, 14)]] = True
_LOWER = np.array([c + 32 if 65 <= c <= 90 else c for c in range(256)], dtype=np.uint8)
_TURN = np.uint64(0xC2B2AE3D27D4EB4F)
#: Cells of a group; a signature is the content of all but one of them.
CELLS = 3
#: Stands for the excess of a member that is far from its head.
FAR = 1 << 62
#: Signatures that a range should hold, and those that a task gathers before it sends them to ranges.
PART_ROWS, BLOCK_ROWS = 4_000_000, 500_000


def feature_sets(texts: list[bytes], width: int = SHINGLE) -> list[np.ndarray]:
    """Sorted distinct 64-bit feature hashes of each text.

    Words are ASCII lower-cased runs of bytes that are not white space.  A text of
    fewer than ``width`` words, but not none, has one feature.
    """
    if not texts:
        return []
    data = _LOWER[np.frombuffer(b" " + b" ".join(texts) + b" ", dtype=np.uint8)]
    lengths = np.array([len(t) for t in texts], dtype=np.int64)
    doc_start = 1 + np.cumsum(lengths + 1) - (lengths + 1)
    blank = _BLANK[data]
    start = np.flatnonzero(blank[:-1] & ~blank[1:]) + 1
    end = np.flatnonzero(~blank[:-1] & blank[1:]) + 1
    words = span_hashes(prefix_hashes(data), start, end)
    bounds = np.searchsorted(start, [*doc_start, len(data)])
    rolled = np.zeros(max(len(words) - width + 1, 0), dtype=np.uint64)
    for i in range(width):
        rolled = rolled * _TURN + words[i : i + len(rolled)]
    rolled = mix(rolled)
    out = []
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b - a >= width:
            own = np.sort(rolled[a : b - width + 1])
            out.append(own[np.concatenate([[True], own[1:] != own[:-1]])])
        elif b > a:
            one = np.uint64(b - a)
            for w in words[a:b].tolist():
                one = mix(np.array([one], dtype=np.uint64) * _TURN + np.array([w], dtype=np.uint64))[0]
            out.append(np.array([one], dtype=np.uint64))
        else:
            out.append(np.zeros(0, dtype=np.uint64))
    return out


def most_differing(size: int, top: int | None = None) -> int:
    """Most features in which a set of this size can differ from a similar one of at most ``top`` features."""
    t, whole = SHARE
    largest = size * whole // t
    if top is not None and top >= size:
        largest = min(largest, top)
    return (size + largest) * (whole - t) // (whole + t)


def bands_of(size: int) -> list[int]:
    """Bands of sizes [2**j, 2**(j+1)) in which a set shows signatures."""
    own = size.bit_length() - 1
    t, whole = SHARE
    return [own, own + 1] if size * whole >= t * (1 << (own + 1)) else [own]


def groups_in(band: int) -> int:
    """Groups of cells of a band: more than half of the most differing features would do.

    With half as many again as these, a set need show less than half of its signatures, and can leave out what many sets share.
    """
    most = most_differing((1 << (band + 1)) - 1, (1 << (band + 1)) - 1)
    return most // 2 + 1 + most


def shared_at_least(band: int) -> int:
    """Signatures of a band that similar sets are made to share: one, and one more for each sixteen features."""
    return 1 + (1 << band) // 16


def most_spoiled(differing: int, groups: int) -> int:
    """Most signatures that so many differing features can change."""
    return 2 * differing if differing <= groups else min(groups + differing, CELLS * groups)


def _subsets(features: np.ndarray, usual: np.ndarray, band: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Contents of all subsets of cells of all groups, which of them are not empty, and which hold a feature that is not usual."""
    n = CELLS * groups_in(band)
    content, filled, odd = np.zeros(n, dtype=np.uint64), np.zeros(n, dtype=bool), np.zeros(n, dtype=bool)
    seeded = mix(features ^ np.uint64(0xA5A5 + band))
    cell = ((seeded >> np.uint64(11)) % np.uint64(n)).astype(np.int64)
    odd[cell[~usual]] = True
    order = np.argsort(cell, kind="stable")
    cell, seeded = cell[order], seeded[order]
    first = np.flatnonzero(np.concatenate([[True], cell[1:] != cell[:-1]]))
    content[cell[first]] = mix(np.add.reduceat(mix(seeded), first))
    filled[cell[first]] = True

    def of_two(x: np.ndarray, join) -> np.ndarray:
        x = x.reshape(-1, CELLS)
        return join(np.roll(x, -1, axis=1), np.roll(x, 1, axis=1)).ravel()  # without the cell itself

    return of_two(content, lambda p, q: p * _TURN + q), of_two(filled, np.logical_or), of_two(odd, np.logical_or)


def signatures(features: np.ndarray, common: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Signatures of one set of features, and their bands; those that hold more than frequent features (``common``) come first."""
    size = len(features)
    if not size:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.uint8)
    usual = _among(features, common)
    out, bands = [], []
    for band in bands_of(size):
        need = most_spoiled(most_differing(size, (1 << (band + 1)) - 1), groups_in(band)) + shared_at_least(band)
        content, filled, odd = _subsets(features, usual, band)
        place = np.concatenate([np.flatnonzero(odd), np.flatnonzero(filled & ~odd)])
        place = place[:need] if len(place) >= need else np.arange(len(filled))
        salt = np.uint64(band * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        out.append(mix(content[place] + mix(place.astype(np.uint64) ^ salt)))
        bands.append(np.full(len(place), band, dtype=np.uint8))
    return np.concatenate(out), np.concatenate(bands)


def _among(features: np.ndarray, common: np.ndarray) -> np.ndarray:
    if not len(common):
        return np.zeros(len(features), dtype=bool)
    return common[np.minimum(np.searchsorted(common, features), len(common) - 1)] == features


def _digest(features: np.ndarray) -> tuple[int, int]:
    a = mix(features + np.uint64(0x51ED2701)).sum(dtype=np.uint64)
    b = mix(features ^ np.uint64(0xB492B66FBE98F273)).sum(dtype=np.uint64)
    return tuple(np.array([a, b], dtype=np.uint64).view(np.int64).tolist())


def _signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def _typed(df: DataFrame, column: str) -> str:
    return dict(df.dtypes)[column]


def set_table(docs: DataFrame) -> DataFrame:
    """(doc_id, n, d1, d2): size and 128-bit digest of each document's set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, texts in byte_slices(batch.column(0).to_pylist(), utf8(batch.column(1))):
                sets = feature_sets(texts)
                pairs = [_digest(s) for s in sets]
                yield pa.RecordBatch.from_arrays([pa.array(ids, batch.column(0).type), pa.array([len(s) for s in sets], pa.int64()), pa.array([p[0] for p in pairs], pa.int64()), pa.array([p[1] for p in pairs], pa.int64())], names=["doc_id", "n", "d1", "d2"])

    return docs.select("doc_id", "text").mapInArrow(in_slices(run), f"doc_id {_typed(docs, 'doc_id')}, n bigint, d1 bigint, d2 bigint")


def frequent_features(docs: DataFrame, rows: int, sample_docs: int = SAMPLE_DOCS) -> np.ndarray:
    """Features that several documents of a bounded sample share, sorted."""
    every = max(1, rows // sample_docs)
    sample = docs.where(F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(every)) == 0).select("doc_id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, texts in byte_slices([0] * batch.num_rows, utf8(batch.column(1))):
                sets = feature_sets(texts)
                yield pa.RecordBatch.from_arrays([pa.array(_signed(np.concatenate(sets)), pa.int64())], names=["f"])

    often = sample.mapInArrow(in_slices(run), "f bigint").groupBy("f").count().where(F.col("count") >= COMMON_MIN).orderBy(F.desc("count"), "f").limit(COMMON_MOST)
    return np.sort(np.array([r["f"] for r in often.select("f").collect()], dtype=np.int64).view(np.uint64))


def _signed_sets(ids: list, texts: list[bytes], known: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """48-bit signature, node and tag of all signatures of some documents.

    The tag holds the band and, above it, the share of its document's features that are not frequent, in 255 steps.
    """
    sets = feature_sets(texts)
    own = [signatures(s, known) for s in sets]
    n = [len(x) for x, _ in own]
    odd = np.array([int(255 * (1 - _among(s, known).mean())) if len(s) else 255 for s in sets], dtype=np.uint16)
    tag = np.repeat(odd << 8, n) | np.concatenate([b for _, b in own])
    # of two sets that share no signature, few share 48 bits of one; these only cost a comparison
    return _signed(np.concatenate([x for x, _ in own]) >> np.uint64(16)), np.repeat(np.array(ids, dtype=np.int64), n), tag


def _signature_sample(docs: DataFrame, common: np.ndarray, every: int) -> DataFrame:
    """(sig, node) of one signature in ``every``."""
    shared = docs.sparkSession.sparkContext.broadcast(common)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, texts in byte_slices(batch.column(0).to_pylist(), utf8(batch.column(1))):
                keys = _signed_sets(ids, texts, shared.value)[:2]
                few = mix(keys[0].view(np.uint64) + mix(keys[1].view(np.uint64))) % np.uint64(every) == 0
                yield pa.RecordBatch.from_arrays([pa.array(k[few]) for k in keys], names=["sig", "node"])

    return docs.select("doc_id", "text").mapInArrow(in_slices(run), "sig bigint, node bigint")


def _signature_blocks(docs: DataFrame, common: np.ndarray, cuts: np.ndarray) -> DataFrame:
    """(bucket, n, sigs, who, nodes, tags): the signatures of many documents, cut by range and sorted within it.

    ``sigs`` holds the gaps between sorted signatures in six planes of bytes, ``who`` the place of each one's node and tag in ``nodes``
    and ``tags``.  This is half the bytes of one row a signature, and the shuffle moves few rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast((common, cuts))

    def blocks(held: list) -> Iterator[pa.RecordBatch]:
        sig, node, tag = (np.concatenate([h[i] for h in held]) for i in range(3))
        held.clear()
        bounds = shared.value[1]
        bucket = deal([sig, node], bounds).astype(np.int32) if len(bounds) else np.zeros(len(sig), dtype=np.int32)
        order = np.lexsort((sig, bucket))
        sig, node, tag, bucket = sig[order], node[order], tag[order], bucket[order]
        first = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]])) if len(bucket) else np.zeros(0, dtype=np.int64)
        for i, j in zip(first.tolist(), [*first[1:].tolist(), len(bucket)], strict=True):
            pair = np.lexsort((tag[i:j], node[i:j]))
            new = np.concatenate([[True], (node[i:j][pair][1:] != node[i:j][pair][:-1]) | (tag[i:j][pair][1:] != tag[i:j][pair][:-1])])
            who = np.zeros(j - i, dtype="<u4")
            who[pair] = np.cumsum(new) - 1
            gaps = np.diff(sig[i:j], prepend=0).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6]
            packed = [np.ascontiguousarray(gaps.T).tobytes(), who.view(np.uint8).reshape(-1, 4).T.tobytes(), node[i:j][pair[new]].astype("<i8").tobytes(), tag[i:j][pair[new]].astype("<u2").tobytes()]
            yield pa.RecordBatch.from_arrays([pa.array([bucket[i]], pa.int32()), pa.array([j - i], pa.int64()), *(pa.array([x], pa.binary()) for x in packed)], names=["bucket", "n", "sigs", "who", "nodes", "tags"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            for ids, texts in byte_slices(batch.column(0).to_pylist(), utf8(batch.column(1))):
                held.append(_signed_sets(ids, texts, shared.value[0]))
                size += len(held[-1][1])
                if size >= BLOCK_ROWS:
                    yield from blocks(held)
                    size = 0
        if size:
            yield from blocks(held)

    return docs.select("doc_id", "text").mapInArrow(in_slices(run), "bucket int, n bigint, sigs binary, who binary, nodes binary, tags binary")


def _sample_cuts(docs: DataFrame, common: np.ndarray, rows: int, parts: int, sample_docs: int = 2000, per_part: int = 40) -> np.ndarray:
    """Splitters from the signatures of about ``sample_docs`` documents, thinned to a bounded number."""
    sample = docs.where(F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(max(1, rows // sample_docs))) == 0)
    thin = max(1, sample_docs * 150 // (parts * per_part))
    return splitters(_signature_sample(sample, common, thin).limit(parts * per_part * 20), parts)


def _runs(blocks: DataFrame) -> DataFrame:
    """(sig, node, band, odd, n, edge) of ranges of signature blocks: members of runs of at least two, with the run's length.

    A partition holds one range, of a size that its splitters bound.  Members of the runs at its two ends have edge true, since
    the signature may go on in the next range, and are given even where they stand alone.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sigs, nodes, tags = [], [], []
        for batch in batches:
            for i in range(batch.num_rows):
                n, raw, who, own, tag = (batch.column(c)[i].as_py() for c in range(1, 6))
                gaps = np.zeros((n, 8), dtype=np.uint8)
                gaps[:, :6] = np.frombuffer(raw, dtype=np.uint8).reshape(6, n).T
                place = np.ascontiguousarray(np.frombuffer(who, dtype=np.uint8).reshape(4, n).T).view("<u4").ravel()
                sigs.append(np.cumsum(gaps.view("<u8").ravel()).astype(np.int64))
                nodes.append(np.frombuffer(own, dtype="<i8")[place])
                tags.append(np.frombuffer(tag, dtype="<u2")[place])
        if not sigs:
            return
        sig, node, tag = np.concatenate(sigs), np.concatenate(nodes), np.concatenate(tags)
        sigs, nodes, tags = [], [], []
        order = np.argsort(sig, kind="stable")
        sig = sig[order]
        same = sig[1:] == sig[:-1]
        edge = (sig == sig[0]) | (sig == sig[-1])
        kept = np.concatenate([[False], same]) | np.concatenate([same, [False]]) | edge
        order, sig, edge = order[kept], sig[kept], edge[kept]
        node, tag = node[order], tag[order]
        first = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))
        size = np.diff(np.concatenate([first, [len(sig)]]))
        length = np.repeat(size, size)
        for i in range(0, len(sig), 1 << 16):
            m = slice(i, i + (1 << 16))
            yield pa.RecordBatch.from_arrays(
                [pa.array(sig[m]), pa.array(node[m]), pa.array((tag[m] & 0xFF).astype(np.int32)), pa.array((tag[m] >> 8).astype(np.int32)), pa.array(length[m].astype(np.int64)), pa.array(edge[m])],
                names=["sig", "node", "band", "odd", "n", "edge"],
            )

    return blocks.mapInArrow(in_slices(run), "sig bigint, node bigint, band int, odd int, n bigint, edge boolean")


def _members(runs: DataFrame) -> DataFrame:
    """(sig, first, node) of the members of runs, with the run's head, after each set left out its most shown signatures.

    The order is by the whole length of a run, over ranges too.
    """
    # the runs that range ends cut: at most two a partition
    cut = runs.where("edge").groupBy("sig").agg(F.count(F.lit(1)).alias("whole"))
    rows = runs.where("not edge").select("sig", "node", "band", "odd", "n")
    rows = rows.union(runs.where("edge").join(F.broadcast(cut), "sig").select("sig", "node", "band", "odd", F.col("whole").alias("n")).where("n > 1"))
    own = Window.partitionBy("node", "band")
    left_out = F.expr("1 + shiftleft(1, band) div 16 - 1")
    place = F.row_number().over(own.orderBy("n", "sig"))
    kept = rows.withColumn("k", place).withColumn("c", F.count(F.lit(1)).over(own)).where(F.col("k") <= F.col("c") - left_out).select("sig", "node", "odd")
    kept = durable(kept)
    head = kept.groupBy("sig").agg(F.min(F.struct("odd", "node"))["node"].alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("sig", "first")
    return kept.join(head, "sig").where("node <> first").select("sig", "first", "node")


def _sized(ids: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast a checkpointed id table if its row count allows it, else leave the join to a shuffle."""
    return F.broadcast(ids) if ids.count() <= most else ids


def _sides(docs: DataFrame, pairs: DataFrame, half: bool) -> DataFrame:
    """(a, b, na, nb, fa, fb): both documents' sizes and features for each pair of a written pair table.

    The features of ``b`` travel once for each pair, those of ``a`` once.  With ``half``, only features of one half of
    the domain are sent, cut to 32 bits: an eighth to a quarter of the bytes.
    """
    heads = _sized(durable(pairs.select(F.col("a").alias("doc_id")).distinct()))

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, texts in byte_slices(list(zip(*(batch.column(i).to_pylist() for i in (0, 2)), strict=True)), utf8(batch.column(1))):
                sets = feature_sets(texts)
                sent = [np.unique((s[: np.searchsorted(s, np.uint64(1 << 63))] >> np.uint64(24)).astype(np.uint32)) for s in sets] if half else sets
                yield pa.RecordBatch.from_arrays(
                    [pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.list_(pa.int64())), pa.array([len(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sent], pa.binary())],
                    names=["doc_id", "with", "n", "f"],
                )

    kind = "doc_id bigint, with array<bigint>, n bigint, f binary"
    text = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    left = text.join(heads, "doc_id", "left_semi").select("doc_id", "text", F.lit(None).cast("array<bigint>").alias("with")).mapInArrow(in_slices(features), kind).select(F.col("doc_id").alias("a"), F.col("n").alias("na"), F.col("f").alias("fa"))
    # a document's text is read once for up to an eighth of its partners, not once for each
    partners = durable(pairs.groupBy(F.col("b").alias("doc_id"), F.pmod(F.xxhash64("a"), F.lit(8)).alias("part")).agg(F.collect_list("a").alias("with")).drop("part"))
    partners = F.broadcast(partners) if pairs.count() <= BROADCAST_ROWS else partners
    right = text.join(partners, "doc_id").select("doc_id", "text", "with").mapInArrow(in_slices(features), kind).select(F.explode("with").alias("a"), F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.col("f").alias("fb"))
    return left.join(right, "a").select("a", "b", "na", "nb", "fa", "fb")


def _common(sides: DataFrame, kind: type) -> DataFrame:
    """(a, b, na, nb, fa, fb, both): sizes of the sent features and of their intersection."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts = []
            for x, y in zip(batch.column(4), batch.column(5), strict=True):
                p, q = np.frombuffer(x.as_py(), dtype=kind), np.frombuffer(y.as_py(), dtype=kind)
                both = np.sort(np.concatenate([p, q]))
                counts.append((len(p), len(q), int((both[1:] == both[:-1]).sum())))
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), *(pa.array([c[i] for c in counts], pa.int64()) for i in range(3))], names=["a", "b", "na", "nb", "fa", "fb", "both"])

    return sides.mapInArrow(in_slices(compare), "a bigint, b bigint, na bigint, nb bigint, fa bigint, fb bigint, both bigint").distinct()


def _check(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, linked, far) of distinct pairs of documents; links are exactly decided.

    First the features of one half of the domain are compared.  Similar sets differ in few features, in that half too; where
    more differ, the pair is no link.  The other pairs are compared in full.  ``far``: nothing similar to one is linked to the other.
    """
    t, whole = SHARE
    half = durable(_common(_sides(docs, durable(pairs), True), np.uint32).withColumn("apart", F.greatest(F.col("fa") + F.col("fb") - 2 * F.col("both"), F.abs(F.col("na") - F.col("nb")))))
    near = (whole + t) * F.col("apart") <= (whole - t) * (F.col("na") + F.col("nb"))
    full = _common(_sides(docs, durable(half.where(near).select("a", "b")), False), np.uint64)
    linked = whole * F.col("both") >= t * (F.col("na") + F.col("nb") - F.col("both"))
    # x similar to b, and linked to a, has at most least(na, nb) whole/t features; both distances together stay below this
    reach = (whole - t) * (t * (F.col("na") + F.col("nb")) + 2 * whole * F.least("na", "nb"))
    far = t * (whole + t) * F.col("apart") > reach
    return full.select("a", "b", linked.alias("linked"), F.lit(False).alias("far")).union(half.where(~near).select("a", "b", F.lit(False).alias("linked"), far.alias("far")))


def _differences(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, e, w, f): the features in which ``b`` differs from the head ``a``, one a row; a row without f if b is far from a.

    With h differences, sizes na and nb and similarity t/whole: b is linked to a if e <= 0, and if b, not linked to a, is
    similar to c, they have at least (e(b) + w(c)) / (2 (whole + t)) differences from a in common.
    """
    t, whole = SHARE

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, na, nb = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(4))
            out: list[list] = [[], [], [], [], []]
            for i in range(batch.num_rows):
                f = np.setxor1d(*(np.frombuffer(batch.column(c)[i].as_py(), dtype=np.uint64) for c in (4, 5)), assume_unique=True)
                h = len(f)
                e = (whole + t) * h - (whole - t) * (na[i] + nb[i])
                w = (whole + t) * h - (whole - t) * (nb[i] - na[i])
                far = t * (whole + t) * h > (whole - t) * (t * (na[i] + nb[i]) + 2 * whole * min(na[i], nb[i]))
                n = 1 if far else h
                for column, x in zip(out, (a[i], b[i], e, w), strict=False):
                    column.append(np.full(n, x, dtype=np.int64))
                out[4].append(np.zeros(1, dtype=np.int64) if far else _signed(f))
                if far:
                    out[2][-1][0] = FAR
            columns = [np.concatenate(c) if c else np.zeros(0, dtype=np.int64) for c in out]
            yield pa.RecordBatch.from_arrays([*map(pa.array, columns[:4]), pa.array(columns[4], mask=columns[2] == FAR)], names=["a", "b", "e", "w", "f"])

    return _sides(docs, pairs, False).mapInArrow(in_slices(run), "a bigint, b bigint, e bigint, w bigint, f bigint")


def _apart_from_head(d: DataFrame, component: DataFrame) -> DataFrame:
    """(a, b): pairs around a common head that may be similar, in different components, one of them not linked to the head.

    Differences that a single member has cannot be shared.  Of the others, each member keeps its rarest: all but as many,
    less one, as it must share with any partner.  Similar members meet in their first common difference, from which on
    both must have as many left as they share.
    """
    t, whole = SHARE
    df = d.groupBy("a", "f").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    # one row a head; broadcast up to a checked size, so that a head's members stay in many tasks
    closest = _sized(durable(d.where("e > 0").groupBy("a").agg(F.min("e").alias("least_e"))))
    own = Window.partitionBy("a", "b")
    ranked = d.join(df, ["a", "f"]).join(closest, "a").withColumn("left", F.count(F.lit(1)).over(own) - F.row_number().over(own.orderBy("df", "f")) + 1)
    # what a member shares with a partner that is not linked to the head; what one that is not linked shares with any partner
    loose, scale = F.col("e") > 0, 2 * (whole + t)
    as_loose = F.when(loose, F.greatest(F.lit(1), F.ceil(F.col("e") / (2 * whole)))).otherwise(1)
    with_loose = F.greatest(as_loose, F.ceil((F.col("least_e") + F.col("w")) / scale))
    kept = ranked.withColumn("meets_loose", F.col("left") >= with_loose).where(F.col("meets_loose") | (loose & (F.col("left") >= as_loose)))
    kept = durable(kept.join(component, F.col("b") == F.col("node"), "left").select("a", "b", "f", "e", "w", "left", loose.alias("loose"), "meets_loose", F.coalesce("component", "b").alias("component")))
    x, y = kept.where("loose").alias("x"), kept.where("meets_loose").alias("y")
    apart = (F.col("x.component") != F.col("y.component")) & (~F.col("y.loose") | (F.col("x.meets_loose") & (F.col("x.b") < F.col("y.b"))))
    enough = scale * F.least("x.left", "y.left") >= F.col("x.e") + F.col("y.w")
    pairs = x.join(y, (F.col("x.a") == F.col("y.a")) & (F.col("x.f") == F.col("y.f")) & apart & enough)
    return pairs.select(F.least("x.b", "y.b").alias("a"), F.greatest("x.b", "y.b").alias("b")).distinct()


def _far_from_head(docs: DataFrame, loose: DataFrame, component: DataFrame, common: np.ndarray) -> DataFrame:
    """(a, b): pairs that may be similar, in different components, at least one of them far from a head.

    ``loose`` has the members (a, b, far) that are not linked to a head.  Similar sets share three quarters of either, so they meet in a prefix of
    their own features, in one order that puts frequent ones last, and from there on both have as many left as they share.
    """
    t, whole = SHARE
    shared = docs.sparkSession.sparkContext.broadcast(common)
    whose = durable(loose.groupBy(F.col("b").alias("doc_id")).agg(F.max("far").alias("far")))
    text = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = text.join(_sized(whose), "doc_id").select("doc_id", "far", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        for batch in batches:
            for ids, texts in byte_slices(list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)), utf8(batch.column(2))):
                out: list[list[np.ndarray]] = [[], [], [], [], []]
                for (doc, far), s in zip(ids, feature_sets(texts), strict=True):
                    order = np.concatenate([s[~(usual := _among(s, known))], s[usual]])
                    kept = order[: len(s) - -(-t * len(s) // whole) + 1]
                    for column, x in zip(out, (doc, far, len(s)), strict=False):
                        column.append(np.full(len(kept), x))
                    out[3].append(len(s) - np.arange(len(kept)))
                    out[4].append(_signed(kept))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), k) for c, k in zip(out, (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["b", "far", "n", "left", "f"])

    flat = rows.mapInArrow(in_slices(run), "b bigint, far boolean, n bigint, left bigint, f bigint")
    # most features stand in one text alone; the others are few
    several = flat.groupBy("f").agg(F.count(F.lit(1)).alias("df"), F.max("far").alias("far")).where("df > 1 and far").select("f")
    flat = flat.join(several, "f", "left_semi").join(component, F.col("b") == F.col("node"), "left").withColumn("component", F.coalesce("component", "b")).drop("node")
    flat = durable(flat)
    x, y = flat.where("far").alias("x"), flat.alias("y")
    apart = (F.col("x.component") != F.col("y.component")) & (~F.col("y.far") | (F.col("x.b") < F.col("y.b")))
    enough = (whole + t) * F.least("x.left", "y.left") >= t * (F.col("x.n") + F.col("y.n"))
    pairs = x.join(y, (F.col("x.f") == F.col("y.f")) & apart & enough)
    return pairs.select(F.least("x.b", "y.b").alias("a"), F.greatest("x.b", "y.b").alias("b")).distinct()


def similar_links(docs: DataFrame, sets: DataFrame) -> DataFrame:
    """Links (a, b) between first documents of different sets, enough to connect every pair of similar sets."""
    size = sets.agg(F.count(F.lit(1)), F.sum("n")).first()
    n, parts = size[0], max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), (size[1] or 0) // PART_ROWS)
    # copies have the signatures of their set's first document, which stands for them
    reps = durable(sets.where("n > 0").groupBy("d1", "d2").agg(F.min("doc_id").alias("node")).where("node is not null").select("node"))
    copies = durable(sets.where("n > 0 and doc_id is not null").select("doc_id").join(reps, F.col("doc_id") == F.col("node"), "left_anti"))
    named = docs.where(F.col("doc_id").isNotNull())
    few_copies = copies.count() <= BROADCAST_ROWS
    if few_copies:  # otherwise their rows go after the shuffle of the much smaller signatures
        named = named.join(F.broadcast(copies), "doc_id", "left_anti")
    common = frequent_features(docs, n)
    runs = durable(_runs(_signature_blocks(named, common, _sample_cuts(named, common, n, parts)).repartitionById(parts, F.col("bucket"))))
    let_go(docs.sparkSession)
    kept = reps.select(F.col("node").cast("bigint").alias("node"))
    if not few_copies:
        runs = runs.join(kept, "node", "left_semi")
    members = durable(_members(runs))
    checked = durable(_check(docs, members.select(F.col("first").alias("a"), F.col("node").alias("b")).distinct()))
    links = checked.where("linked").select("a", "b")
    if checked.where("not linked").isEmpty():
        return links
    component = durable(connected_components(links.select(F.col("a").alias("u"), F.col("b").alias("v"))))
    placed = members.join(component, "node", "left").withColumn("component", F.coalesce("component", "node"))
    several = placed.groupBy("sig").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo <> hi").select("sig")
    active = members.join(several, "sig", "left_semi").select(F.col("first").alias("a"), F.col("node").alias("b")).distinct()
    active = durable(active.join(checked, ["a", "b"]))
    found = durable(_differences(docs, durable(active.where("not far").select("a", "b"))))
    let_go(docs.sparkSession)
    gone = found.where("f is null").select("a", "b", F.lit(True).alias("gone"))
    loose = active.where("not linked").join(gone, ["a", "b"], "left").select("a", "b", (F.col("far") | F.coalesce("gone", F.lit(False))).alias("far"))
    heads = loose.groupBy("a").agg(F.count(F.lit(1)).alias("n"), F.count_if("far").alias("n_far")).where("n > 1 and n_far > 0").select("a")
    rest = _apart_from_head(found.where("f is not null"), component).union(_far_from_head(docs, loose.join(heads, "a", "left_semi"), component, common)).distinct()
    return links.union(_check(docs, rest.join(checked.select("a", "b"), ["a", "b"], "left_anti")).where("linked").select("a", "b"))


def _own_numbers(docs: DataFrame) -> DataFrame | None:
    """(doc_id, text, key, own): rows without repeats, with a number for each text where an id has several; None if ids are distinct."""
    keyed = docs.where(F.col("doc_id").isNotNull()).select("doc_id", "text", F.xxhash64("text", F.col("text").isNull()).alias("key"))
    seen = keyed.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"), F.min("key").alias("first"))
    repeated = durable(seen.where("n > 1").select("doc_id", "first"))
    if repeated.isEmpty():
        return None
    own = F.when(F.col("key") != F.col("first"), F.xxhash64("doc_id", "key", F.lit(7))).otherwise(F.col("doc_id").cast("bigint"))
    return durable(keyed.dropDuplicates(["doc_id", "key"]).join(_sized(repeated), "doc_id", "left").select("doc_id", "text", "key", own.alias("own")))


def _groups(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, class_id, component_id) of rows with distinct ids or none."""
    sets = durable(set_table(docs))
    links = similar_links(docs, sets)
    parts = connected_components(links.select(F.col("a").alias("u"), F.col("b").alias("v")))
    classes = sets.where("n > 0").groupBy("d1", "d2").agg(F.min("doc_id").alias("class_id"))
    named = classes.join(parts, F.col("class_id") == F.col("node"), "left").select("d1", "d2", "class_id", F.coalesce("component", "class_id").alias("component_id"))
    out = sets.where("n > 0 and doc_id is not null").join(named, ["d1", "d2"]).select("doc_id", F.col("n").alias("n_shingles"), "class_id", "component_id")
    alone = sets.where("n = 0 or doc_id is null").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("class_id"), F.col("doc_id").alias("component_id"))
    return out.union(alone)


def jaccard_groups(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, class_id, component_id) of every document row; ``doc_id`` is a whole number.

    Documents of equal sets form a class, named by its smallest doc_id; a component
    is what links of similarity 0.75 or more connect, named likewise.  Null and
    wordless texts have an empty set and stand alone.  A null doc_id stands alone
    with null names.  Different texts under one doc_id are documents of their own; equal rows count
    once and are all returned.  An empty table gives an empty one; other columns are ignored.
    """
    numbered = _own_numbers(docs)
    if numbered is None:
        return _groups(docs)
    found = _groups(numbered.select(F.col("own").alias("doc_id"), "text")).withColumnRenamed("doc_id", "own").join(numbered.select("own", "doc_id", "key"), "own")
    names = [found.groupBy(c).agg(F.min("doc_id").alias(f"{c}_name")) for c in ("class_id", "component_id")]
    for c, name in zip(("class_id", "component_id"), names, strict=True):
        found = found.join(name, c)
    found = found.select("doc_id", "key", "n_shingles", F.col("class_id_name").alias("class_id"), F.col("component_id_name").alias("component_id"))
    rows = docs.select("doc_id", F.xxhash64("text", F.col("text").isNull()).alias("key"))
    nameless = set_table(docs.where(F.col("doc_id").isNull())).select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("class_id"), F.col("doc_id").alias("component_id"))
    return rows.join(found, ["doc_id", "key"]).select("doc_id", "n_shingles", "class_id", "component_id").union(nameless)


def keep_one_of_each(docs: DataFrame) -> DataFrame:
    """Documents without those that another of their component, with a smaller doc_id, stands for.

    Rows of equal doc_id and text stay once.  Different texts under one doc_id are
    documents of their own, ordered by text hash.  Rows with a null doc_id all stay.
    """
    numbered = _own_numbers(docs)
    if numbered is None:
        gone = durable(jaccard_groups(docs).where("doc_id <> component_id").select("doc_id"))
        return docs.join(_sized(gone), "doc_id", "left_anti").select(*docs.columns)
    groups = _groups(numbered.select(F.col("own").alias("doc_id"), "text")).select(F.col("doc_id").alias("own"), "component_id")
    members = durable(numbered.select("own", "doc_id", "key").join(groups, "own"))
    keepers = members.groupBy("component_id").agg(F.min(F.struct("doc_id", "key")).alias("keeper"))
    gone = durable(members.join(keepers, "component_id").where(F.struct("doc_id", "key") != F.col("keeper")).select("doc_id", F.col("key").alias("__key")))
    once = docs.withColumn("__key", F.xxhash64("text", F.col("text").isNull())).where(F.col("doc_id").isNotNull()).dropDuplicates(["doc_id", "__key"])
    kept = once.join(_sized(gone), ["doc_id", "__key"], "left_anti").select(*docs.columns)
    return kept.unionByName(docs.where(F.col("doc_id").isNull()))
