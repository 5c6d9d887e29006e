"""Benchmark decontamination over a distributed positional inverted index.

Documents are cut into shards of about a megabyte.  A shard's index holds its distinct terms as sorted
64-bit hashes and, for each, the sorted list of positions at which it stands; texts end with a gap that no
window bridges.  The index of all documents is written as a table, one row a shard, and answers any number of
query sets.  A window of a benchmark item is answered from its rarest term in the shard: that list, shifted by the
term's place in the window, is intersected with the shifted lists of the other terms, from rare to frequent, by binary search.
What is left are the exact occurrences.  ``proximity_matches`` asks instead for all terms of an item within a span.

The benchmark is the stated query set; it is broadcast in blocks of at most ``max_terms`` words, one after the other.
"""

from __future__ import annotations

import hashlib
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_slices, durable, in_slices, prefix_hashes, span_hashes, utf8

WINDOW = 13
#: Words of benchmark text that one pass may broadcast.
MAX_TERMS = 2_000_000
#: Bytes of text in a shard, and positions between the texts of one, beyond any window or span.
SHARD_BYTES, GAP = 1 << 20, 1 << 10

_WORD = np.zeros(256, dtype=bool)
_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_LOWER = np.array([c + 32 if 65 <= c <= 90 else c for c in range(256)], dtype=np.uint8)


def term_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words of the texts, lower-cased, and the number of words of each text."""
    if not texts:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    data = _LOWER[np.frombuffer(b" " + b" ".join(texts) + b" ", dtype=np.uint8)]
    word = _WORD[data]
    start = np.flatnonzero(~word[:-1] & word[1:]) + 1
    end = np.flatnonzero(word[:-1] & ~word[1:]) + 1
    lengths = np.array([len(t) for t in texts], dtype=np.int64)
    bounds = np.searchsorted(start, np.concatenate([[0], 1 + np.cumsum(lengths + 1)]))
    return span_hashes(prefix_hashes(data), start, end), np.diff(bounds)


class PhraseSet:
    """Windows of benchmark items as rows of term numbers."""

    def __init__(self, items: list[tuple[object, str | None]], width: int = WINDOW):
        hashes, counts = term_hashes([(text or "").encode() for _, text in items])
        self.terms, coded = np.unique(hashes, return_inverse=True)
        ends = np.cumsum(counts)
        self.item_ids = [item for item, _ in items]
        windows: dict[tuple[int, ...], list[int]] = {}
        self.bags: list[np.ndarray] = []
        for n, (a, b) in enumerate(zip((ends - counts).tolist(), ends.tolist(), strict=True)):
            own = coded[a:b].tolist()
            self.bags.append(np.unique(coded[a:b]))
            for i in range(max(1, len(own) - width + 1) if own else 0):
                owners = windows.setdefault(tuple(own[i : i + width]), [])
                if not owners or owners[-1] != n:
                    owners.append(n)
        self.by_length: dict[int, tuple[np.ndarray, list[list[int]]]] = {}
        for length in {len(w) for w in windows}:
            own = [w for w in windows if len(w) == length]
            self.by_length[length] = (np.array(own, dtype=np.int64).reshape(-1, length), [windows[w] for w in own])


class Shard:
    """Positional index of a run of texts: sorted terms, where their lists begin, positions, and where texts begin."""

    def __init__(self, terms: np.ndarray, first: np.ndarray, positions: np.ndarray, counts: np.ndarray):
        self.terms, self.first, self.positions, self.counts = terms, first, positions, counts
        self.starts = np.concatenate([[0], np.cumsum(counts + GAP)])
        # one key a posting, in order: the lists of all terms side by side
        self.keys = np.repeat(np.arange(len(terms)), np.diff(first)) * int(self.starts[-1] + 1) + positions

    @classmethod
    def of(cls, texts: list[bytes]) -> Shard:
        hashes, counts = term_hashes(texts)
        at = np.arange(len(hashes)) + np.repeat(np.arange(len(counts)) * GAP, counts)
        order = np.argsort(hashes, kind="stable")
        terms, first = np.unique(hashes[order], return_index=True)
        return cls(terms, np.concatenate([first, [len(hashes)]]).astype(np.int64), at[order].astype(np.int64), counts.astype(np.int64))

    def numbers(self, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For wanted terms: their numbers in the shard, and how often they stand there (0: not at all)."""
        if not len(self.terms):
            return np.zeros(len(wanted), dtype=np.int64), np.zeros(len(wanted), dtype=np.int64)
        at = np.minimum(np.searchsorted(self.terms, wanted), len(self.terms) - 1)
        return at, np.where(self.terms[at] == wanted, np.diff(self.first)[at], 0)

    def holds(self, term: np.ndarray, position: np.ndarray) -> np.ndarray:
        """Whether the lists of the terms (by number) hold the positions, by binary search."""
        key = term * int(self.starts[-1] + 1) + position
        return self.keys[np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)] == key

    def phrases(self, windows: np.ndarray, number: np.ndarray, df: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(window, start) of every exact occurrence, in blocks of windows."""
        length = windows.shape[1]
        alive = np.flatnonzero((df[windows] > 0).all(axis=1))
        if not len(alive):
            return
        ranked = np.argsort(df[windows[alive]], axis=1, kind="stable")
        rarest = number[windows[alive, ranked[:, 0]]]
        sizes = np.diff(self.first)[rarest]
        bounds = np.cumsum(sizes)
        cuts = np.searchsorted(bounds, np.arange(0, bounds[-1], 500_000), "left")
        for lo, hi in zip(cuts, [*cuts[1:], len(alive)], strict=True):
            if lo == hi:
                continue
            n = sizes[lo:hi]
            which = np.repeat(np.arange(lo, hi), n)
            inside = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            start = self.positions[np.repeat(self.first[rarest[lo:hi]], n) + inside] - ranked[which, 0]
            for step in range(1, length):
                if not len(which):
                    break
                place = ranked[which, step]
                ok = (start >= 0) & self.holds(number[windows[alive[which], place]], start + place)
                which, start = which[ok], start[ok]
            ok = start >= 0
            if ok.any():
                yield alive[which[ok]], start[ok]

    def document_of(self, positions: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.starts, positions, "right") - 1

    def occurrences(self, phrases: PhraseSet) -> tuple[np.ndarray, list[set]]:
        """Marks at the begins (+1) and ends (-1) of all occurrences, and the items that occur in each text."""
        marks = np.zeros(int(self.starts[-1]) + 1, dtype=np.int32)
        found: list[set] = [set() for _ in self.counts]
        number, df = self.numbers(phrases.terms)
        for length, (windows, owners) in phrases.by_length.items():
            for which, start in self.phrases(windows, number, df):
                np.add.at(marks, start, 1)
                np.add.at(marks, start + length, -1)
                pairs = np.unique(np.stack([self.document_of(start), which]), axis=1)
                for d, w in pairs.T.tolist():
                    found[d].update(owners[w])
        return marks, found

    def covered(self, marks: np.ndarray) -> np.ndarray:
        """Words of each text that lie in an occurrence."""
        total = np.concatenate([[0], np.cumsum(np.cumsum(marks) > 0)])
        return total[self.starts[1:]] - total[self.starts[:-1]]

    def together(self, phrases: PhraseSet, span: int) -> Iterator[tuple[int, int]]:
        """(text, item): texts that hold all terms of an item within ``span`` consecutive words."""
        number, df = self.numbers(phrases.terms)
        for n, bag in enumerate(phrases.bags):
            if not len(bag) or len(bag) > span or not (df[bag] > 0).all():
                continue
            lists = [self.positions[self.first[t] : self.first[t + 1]] for t in number[bag[np.argsort(df[bag], kind="stable")]].tolist()]
            # a span that holds all terms begins with one of them: only their positions near the rarest term are tried
            start = np.concatenate(lists)
            near = np.searchsorted(lists[0], start - span, "right")
            start = start[(near < len(lists[0])) & (lists[0][np.minimum(near, len(lists[0]) - 1)] < start + span)]
            for own in lists:
                at = np.searchsorted(own, start)
                start = start[(at < len(own)) & (own[np.minimum(at, len(own) - 1)] < start + span)]
            for d in np.unique(self.document_of(start)).tolist():
                yield d, n


def phrase_blocks(benchmark: DataFrame, item_col: str = "item_id", text_col: str = "text", max_terms: int = MAX_TERMS) -> Iterator[list[tuple]]:
    """Benchmark rows in blocks of at most about ``max_terms`` words; the driver holds one at a time."""
    block, held = [], 0
    for row in benchmark.select(F.col(item_col).alias("i"), F.col(text_col).alias("t")).toLocalIterator():
        n = int(term_hashes([(row["t"] or "").encode()])[1][0])
        if held and held + n > max_terms:
            yield block
            block, held = [], 0
        block.append((row["i"], row["t"]))
        held += n
    if block:
        yield block


def build_index(documents: DataFrame) -> DataFrame:
    """(shard, ids, counts, terms, first, positions): the stored index, one row a shard; arrays as little-endian binary."""
    id_type = dict(documents.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, texts in byte_slices(batch.column(0).to_pylist(), utf8(batch.column(1)), SHARD_BYTES):
                x = Shard.of(texts)
                number = int.from_bytes(os.urandom(8), "little") >> 1
                arrays = [x.counts.astype("<i4"), x.terms.astype("<u8"), x.first.astype("<i4"), x.positions.astype("<i4")]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([number], pa.int64()), pa.array([ids], pa.list_(batch.column(0).type)), *(pa.array([a.tobytes()], pa.binary()) for a in arrays)],
                    names=["shard", "ids", "counts", "terms", "first", "positions"],
                )

    schema = f"shard bigint, ids array<{id_type}>, counts binary, terms binary, first binary, positions binary"
    return documents.select("doc_id", "text").mapInArrow(in_slices(run), schema)


def _shards(batch: pa.RecordBatch) -> Iterator[tuple[int, list, Shard]]:
    for i in range(batch.num_rows):
        counts, terms, first, positions = (np.frombuffer(batch.column(c)[i].as_py(), dtype=t) for c, t in ((2, "<i4"), (3, "<u8"), (4, "<i4"), (5, "<i4")))
        yield batch.column(0)[i].as_py(), batch.column(1)[i].as_py(), Shard(terms, first.astype(np.int64), positions.astype(np.int64), counts.astype(np.int64))


def _named(items: set) -> list[str]:
    return sorted("" if x is None else str(x) for x in items)


def phrase_matches(index: DataFrame, phrases: PhraseSet) -> DataFrame:
    """(shard, place, doc_id, n_words, n_hit, items, spans) of every text: covered words, items, and covered runs as (first, end)."""
    shared = index.sparkSession.sparkContext.broadcast(phrases)
    id_type = dict(index.dtypes)["ids"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            id_kind = batch.schema.field("ids").type.value_type
            for number, ids, x in _shards(batch):
                marks, found = x.occurrences(shared.value)
                on = np.concatenate([[0], (np.cumsum(marks) > 0).astype(np.int8), [0]])
                begin, end = np.flatnonzero(np.diff(on) > 0), np.flatnonzero(np.diff(on) < 0)
                doc = x.document_of(begin)
                spans: list[list] = [[] for _ in ids]
                for d, a, b in zip(doc.tolist(), (begin - x.starts[doc]).tolist(), (end - x.starts[doc]).tolist(), strict=True):
                    spans[d] += (a, b)
                items = [_named({shared.value.item_ids[i] for i in f}) for f in found]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([number] * len(ids), pa.int64()), pa.array(range(len(ids)), pa.int32()), pa.array(ids, id_kind), pa.array(x.counts, pa.int64()), pa.array(x.covered(marks), pa.int64()),
                     pa.array(items, pa.list_(pa.string())), pa.array(spans, pa.list_(pa.int32()))],
                    names=["shard", "place", "doc_id", "n_words", "n_hit", "items", "spans"],
                )

    return index.mapInArrow(run, f"shard bigint, place int, doc_id {id_type[6:-1]}, n_words bigint, n_hit bigint, items array<string>, spans array<int>")


def _merged(rows: DataFrame) -> DataFrame:
    """One row a text of the matches of several blocks: items together, covered runs united."""

    def last(acc, s):
        top = F.element_at(acc, -1)
        grown = F.struct(top["a"].alias("a"), F.greatest(top["b"], s["b"]).alias("b"))
        meets = (F.size(acc) > 0) & (s["a"] <= F.when(F.size(acc) > 0, top["b"]))
        return F.when(meets, F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(grown))).otherwise(F.concat(acc, F.array(s)))

    runs = F.transform(F.sequence(F.lit(0), F.floor(F.size("spans") / 2).cast("int") - 1), lambda i: F.struct(F.get("spans", 2 * i).alias("a"), F.get("spans", 2 * i + 1).alias("b")))
    placed = rows.withColumn("runs", F.when(F.size("spans") > 0, runs).otherwise(F.array().cast("array<struct<a:int,b:int>>")))
    one = placed.groupBy("shard", "place").agg(F.first("doc_id").alias("doc_id"), F.first("n_words").alias("n_words"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), F.sort_array(F.flatten(F.collect_list("runs"))).alias("runs"))
    united = F.aggregate("runs", F.array().cast("array<struct<a:int,b:int>>"), last)
    return one.withColumn("n_hit", F.aggregate(united, F.lit(0).cast("bigint"), lambda n, s: n + s["b"] - s["a"]))


def find_contamination(documents: DataFrame, benchmark: DataFrame, width: int = WINDOW, max_terms: int = MAX_TERMS) -> DataFrame:
    """Per document: doc_id, n_words, n_hit, n_items, items (sorted item ids), items_sha256, contaminated.

    A word is hit if it lies in any occurrence of a window (``width``
    consecutive words of an item, or a whole shorter item; at most 1023).  Null and empty
    texts have no words; an empty benchmark hits nothing; items that repeat
    under one id count once and a null item id is shown as the empty string.  One row per
    input row, repeated ones too; other columns are ignored.
    """
    if not 0 < width < GAP:
        raise ValueError(f"windows of {width} words")
    index = durable(build_index(documents))
    found = [phrase_matches(index, PhraseSet(block, width)) for block in phrase_blocks(benchmark, max_terms=max_terms)] or [phrase_matches(index, PhraseSet([], width))]
    rows = found[0]
    if len(found) > 1:
        # a block's few texts with matches are kept; the texts themselves come from the first block's pass
        hits = [durable(f.where("n_hit > 0")) for f in found[1:]]
        for h in hits:
            rows = rows.unionByName(h)
        rows = _merged(rows)
    return rows.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"), "items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"),
    )


def clean_documents(documents: DataFrame, benchmark: DataFrame, width: int = WINDOW, max_terms: int = MAX_TERMS) -> DataFrame:
    """Documents that are not contaminated, with all their columns and in one pass.

    A batch's shards are indexed and asked where the rows are, since each is read once; blocks of the benchmark are
    loaded by a worker one at a time.
    """
    context = documents.sparkSession.sparkContext
    shared = [context.broadcast(PhraseSet(block, width)) for block in phrase_blocks(benchmark, max_terms=max_terms)]
    at = documents.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep: list[bool] = []
            for _, texts in byte_slices(list(range(batch.num_rows)), utf8(batch.column(at)), SHARD_BYTES):
                x = Shard.of(texts)
                marks = np.zeros(int(x.starts[-1]) + 1, dtype=np.int32)
                for block in shared:
                    marks += x.occurrences(block.value)[0]
                    if len(shared) > 1:
                        block.__dict__.pop("_value", None)  # it is read from its file again for the next shard
                keep += [not (h > 0 and 20 * h >= n) for h, n in zip(x.covered(marks).tolist(), x.counts.tolist(), strict=True)]
            yield batch.filter(pa.array(keep, pa.bool_()))

    return documents.mapInArrow(in_slices(run), documents.schema)


def proximity_matches(documents: DataFrame, benchmark: DataFrame, span: int, max_terms: int = MAX_TERMS) -> DataFrame:
    """(doc_id, item_id): documents that hold all terms of an item within ``span`` consecutive words, once a row and item.

    Items without words, or of more than ``span`` distinct ones, match nothing; ids keep their types.
    """
    if not 0 < span < GAP:
        raise ValueError(f"spans of {span} words")
    index = durable(build_index(documents))
    item_type = benchmark.schema["item_id"].dataType
    context, parts = documents.sparkSession.sparkContext, None
    id_type = dict(index.dtypes)["ids"][6:-1]

    def searcher(shared):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                id_kind = batch.schema.field("ids").type.value_type
                for _, ids, x in _shards(batch):
                    pairs = [(ids[d], n) for d, n in x.together(shared.value, span)]
                    yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in pairs], id_kind), pa.array([p[1] for p in pairs], pa.int32())], names=["doc_id", "n"])

        return run

    for block in phrase_blocks(benchmark, max_terms=max_terms):
        phrases = PhraseSet(block)
        names = documents.sparkSession.createDataFrame([(n, item) for n, item in enumerate(phrases.item_ids)], f"n int, item_id {item_type.simpleString()}")
        own = index.mapInArrow(searcher(context.broadcast(phrases)), f"doc_id {id_type}, n int").join(names, "n").select("doc_id", "item_id")
        parts = own if parts is None else parts.unionByName(own)
    if parts is None:
        return documents.sparkSession.createDataFrame([], f"doc_id {id_type}, item_id {item_type.simpleString()}")
    return parts
