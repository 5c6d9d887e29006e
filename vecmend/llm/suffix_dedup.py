"""Removal of repeated byte strings with a sparse, range-partitioned suffix array.

Every window of ``length`` bytes picks one anchor, the smallest hash of the
16-byte grams in it, so that equal windows pick equal anchors.  Only the
suffixes that start at anchors are sorted: Spark samples splitters, range-partitions
the suffixes by their leading gram and context, and sorts each bucket.  Equal neighbours
with a smaller document mark the anchor's windows as repeated as a whole.
Neighbours that agree in the gram and in a part of the context may
share some windows; those anchors' windows are compared one by one.  Suffixes
at the ends of buckets are compared across the boundaries in the same two ways.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_slices, deal, dealt, durable, in_slices, mix, prefix_hashes, span_hashes, splitters, utf8

LENGTH = 50
GRAM = 16
#: Documents up to which per-document lists are broadcast; beyond, the texts are shuffled to them.
BROADCAST_ROWS = 1_000_000
BROADCAST_BYTES = 64 << 20
#: Bytes of text whose anchors, or windows, a bucket should hold.
BUCKET_BYTES = 64 << 20


class Anchors:
    """Anchors of a run of texts laid end to end, with the windows each stands for."""

    def __init__(self, texts: list[bytes], length: int = LENGTH, gram: int = GRAM):
        lengths = np.array([len(t) for t in texts], dtype=np.int64)
        self.begin = np.concatenate([[0], np.cumsum(lengths)])
        data = np.frombuffer(b"".join(texts), dtype=np.uint8)
        self.prefix = prefix_hashes(data)
        self.length, self.gram = length, gram
        total, span = len(data), length - gram + 1
        none = np.zeros(0, dtype=np.int64)
        self.at = self.first = self.last = self.doc = none
        if total < length:
            return
        grams = span_hashes(self.prefix, np.arange(total - gram + 1), np.arange(gram, total + 1))
        low, width = grams, 1
        while width * 2 <= span:  # sliding minima by doubling
            low = np.minimum(low[: len(low) - width], low[width:])
            width *= 2
        low = np.minimum(low[: total - length + 1], low[span - width : span - width + total - length + 1])
        window = np.flatnonzero(self._inside(total - length + 1, lengths))
        if not len(window):
            return
        picked = self._leftmost(grams, window, low[window], span)
        fresh = np.concatenate([[True], (picked[1:] != picked[:-1]) | (window[1:] != window[:-1] + 1)])
        start = np.flatnonzero(fresh)
        end = np.concatenate([start[1:], [len(window)]]) - 1
        self.at, self.first, self.last = picked[start], window[start], window[end]
        self.doc = np.searchsorted(self.begin, self.at, "right") - 1
        self.grams = grams

    def _inside(self, n: int, lengths: np.ndarray) -> np.ndarray:
        """Which window starts keep the window inside its own text."""
        room = np.repeat(self.begin[1:] - self.length, lengths)
        return np.arange(n) <= room[:n]

    @staticmethod
    def _leftmost(grams: np.ndarray, window: np.ndarray, value: np.ndarray, span: int) -> np.ndarray:
        """Place of the first gram in each window that equals the window's minimum.

        It is searched for the first window of each run of equal minima; the rest of the run
        shares it, but for windows that begin after it (a minimum that occurs twice).
        """

        def search(which: np.ndarray) -> np.ndarray:
            place = np.zeros(len(which), dtype=np.int64)
            todo = np.arange(len(which))
            for step in range(span):
                at = window[which[todo]] + step
                hit = grams[at] == value[which[todo]]
                place[todo[hit]] = at[hit]
                todo = todo[~hit]
                if not len(todo):
                    break
            return place

        start = np.flatnonzero(np.concatenate([[True], (value[1:] != value[:-1]) | (window[1:] != window[:-1] + 1)]))
        place = np.repeat(search(start), np.diff(np.concatenate([start, [len(window)]])))
        passed = np.flatnonzero(place < window)
        if len(passed):
            place[passed] = search(passed)
        return place

    def ordinals(self) -> np.ndarray:
        """Number of each anchor within its text."""
        first = np.searchsorted(self.doc, np.arange(len(self.begin)))
        return np.arange(len(self.doc)) - first[self.doc]

    def keys(self) -> list[np.ndarray]:
        """Two sort keys of each anchor: 48 bits of its gram, 40 bits of all its context, 10 bits of each of four parts.

        Equal keys mean equal contexts (40 bits among anchors of one gram).  Two anchors can share
        a window only if they agree on l bytes to the left and r to the right with l + r no
        less than the window without the gram; then they agree on one of the
        four parts, which lie at quarters of that range (0: not inside the text).
        """
        reach = self.length - self.gram
        low, high = self.begin[self.doc], self.begin[self.doc + 1]
        after = self.at + self.gram
        a, b = np.maximum(low, self.at - reach), np.minimum(high, after + reach)
        whole = span_hashes(self.prefix, a, b) + mix(((self.at - a) * 131 + (b - after)).astype(np.uint64))
        whole = mix(whole)
        out = whole & np.uint64(0xFFFFFF << 40)
        steps = [reach * i // 4 for i in range(5)]
        for i in range(4):
            left, right = self.at - steps[i], after + (reach - steps[i + 1] + 1 if i < 3 else 0)
            there = (left >= low) & (right <= high)
            part = span_hashes(self.prefix, np.where(there, left, self.at), np.where(there, right, after))
            out |= np.where(there, (part >> np.uint64(54)) | np.uint64(1), np.uint64(0)) << np.uint64(10 * i)
        first = (self.grams[self.at] & ~np.uint64(0xFFFF)) | (whole & np.uint64(0xFFFF))
        return [first.view(np.int64), out.view(np.int64)]


def _suffix_rows(docs: DataFrame, length: int, cuts: np.ndarray | None = None, every: int = 1) -> DataFrame:
    """(bucket, gram, context, doc, ordinal) of every anchor; of one in ``every`` for the sample of splitters."""
    shared = docs.sparkSession.sparkContext.broadcast(cuts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bounds = shared.value
        for batch in batches:
            for ids, texts in byte_slices(batch.column(0).to_pylist(), utf8(batch.column(1))):
                x = Anchors(texts, length)
                if not len(x.at):
                    continue
                keys = [*x.keys(), np.array(ids, dtype=np.int64)[x.doc]]
                place = x.ordinals()
                if every > 1:
                    few = mix(x.grams[x.at] + mix(keys[2].view(np.uint64) + np.uint64(1)) * place.astype(np.uint64)) % np.uint64(every) == 0
                    keys, place = [k[few] for k in keys], place[few]
                bucket = deal(keys, bounds) if bounds is not None and len(bounds) else np.zeros(len(place), dtype=np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(bucket), *map(pa.array, keys), pa.array(place)], names=["bucket", "gram", "context", "doc", "ordinal"])

    return docs.select("doc_id", "text").mapInArrow(in_slices(run), "bucket bigint, gram bigint, context bigint, doc bigint, ordinal bigint")


def _sample_cuts(docs: DataFrame, length: int, parts: int, sample_docs: int = 2000, per_part: int = 40) -> np.ndarray:
    """Splitters from the anchors of about ``sample_docs`` documents, thinned to a bounded number."""
    every = max(1, docs.select("doc_id").count() // sample_docs)
    sample = docs.where(F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(every)) == 0)
    thin = max(1, sample_docs * 150 // (parts * per_part))
    return splitters(_suffix_rows(sample, length, every=thin).select("gram", "context", "doc").limit(parts * per_part * 20), parts)


def _shared_part(gram: np.ndarray, context: np.ndarray) -> np.ndarray:
    """Which of the given distinct (gram, context) rows agree with another one in gram and a part of the context."""
    flag = np.zeros(len(gram), dtype=bool)
    bits = context.view(np.uint64)
    for i in range(4):
        part = (bits >> np.uint64(10 * i)) & np.uint64(0x3FF)
        key = mix((gram >> 16).view(np.uint64) ^ mix(part + np.uint64(1)))
        order = np.argsort(key, kind="stable")
        same = key[order][1:] == key[order][:-1]
        near = np.concatenate([[False], same]) | np.concatenate([same, [False]])
        flag[order[near]] |= part[order[near]] != 0
    return flag


_MARKS = "kind string, gram bigint, context bigint, doc bigint, ordinal bigint"


def _compare(rows: DataFrame) -> DataFrame:
    """Marks from sorted suffixes: 'whole' (repeated), 'part' (windows to compare), 'edge' (bucket ends)."""

    def marks(kind: str, table: np.ndarray) -> pa.RecordBatch:
        n = table.shape[1]
        keys = [pa.array(c, pa.int64()) if kind == "edge" else pa.nulls(n, pa.int64()) for c in table[:2]]
        return pa.RecordBatch.from_arrays([pa.array([kind] * n, pa.string()), *keys, *(pa.array(c, pa.int64()) for c in table[2:])], names=["kind", "gram", "context", "doc", "ordinal"])

    def finish(table: np.ndarray, ends: set) -> Iterator[pa.RecordBatch]:
        gram, context, doc, _ = table
        fresh = np.concatenate([[True], (gram[1:] != gram[:-1]) | (context[1:] != context[:-1])])
        start = np.flatnonzero(fresh)
        least = np.repeat(doc[start], np.diff(np.concatenate([start, [len(gram)]])))
        whole = doc != least
        yield marks("whole", table[:, whole])
        at_end = np.isin(gram >> 16, list(ends)) if ends else np.zeros(len(gram), dtype=bool)
        if at_end.any():
            yield marks("edge", table[:, at_end & ~whole])
        several = np.concatenate([[True], gram[start][1:] >> 16 != gram[start][:-1] >> 16])
        group = np.cumsum(several) - 1
        size = np.bincount(group)
        cand = start[(size[group] > 1) & ~at_end[start]]
        if len(cand):
            flag = np.zeros(len(gram), dtype=bool)
            flag[cand[_shared_part(gram[cand], context[cand])]] = True
            run = np.cumsum(fresh) - 1
            part = flag[start][run] & ~whole
            yield marks("part", table[:, part])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        size, opening = 0, None
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns]))
            size += batch.num_rows
            if opening is None:
                opening = int(held[0][0, 0]) >> 16
            if size >= 200_000:
                table = np.concatenate(held, axis=1)
                cut = int(np.searchsorted(table[0] >> 16, table[0, -1] >> 16, "left"))
                if cut:
                    yield from finish(table[:, :cut], {opening})
                held, size = [table[:, cut:]], table.shape[1] - cut
        if size:
            table = np.concatenate(held, axis=1)
            yield from finish(table, {opening, int(table[0, -1]) >> 16})

    return rows.mapInArrow(run, _MARKS)


def _across(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Whole and part marks among suffixes whose gram lies at the end of a bucket."""
    # one row a context; a table of checked size goes to the rows, so that a context that many texts share is in many tasks
    least = _few(edges.groupBy("gram", "context").agg(F.min("doc").alias("least")))
    near = edges.join(least, ["gram", "context"])
    whole = near.where("doc > least").select("doc", "ordinal")
    parts = [F.struct(F.lit(i).alias("side"), F.shiftrightunsigned("context", 10 * i).bitwiseAND(0x3FF).alias("part")) for i in range(4)]
    keys = least.select("gram", "context", F.shiftright("gram", 16).alias("group"), F.explode(F.array(*parts)).alias("k")).select("gram", "context", "group", "k.*").where("part <> 0")
    both = F.struct("gram", "context")
    shared = _few(keys.groupBy("group", "side", "part").agg(F.min(both).alias("lo"), F.max(both).alias("hi")).where("lo <> hi").select("group", "side", "part"))
    flagged = keys.join(shared, ["group", "side", "part"], "left_semi").select("gram", "context").distinct()
    part = near.where("doc = least").join(flagged, ["gram", "context"], "left_semi").select("doc", "ordinal")
    return whole, part


def _few(rows: DataFrame) -> DataFrame:
    """Written rows, with a broadcast hint if there are few enough of them."""
    rows = durable(rows)
    return F.broadcast(rows) if rows.count() <= BROADCAST_ROWS else rows


def _per_document(marks: DataFrame, name: str) -> DataFrame:
    """(doc, packed): the marks of each document as sorted ranges, 16 bytes a range."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            packed = []
            for x in batch.column(1):
                own = np.unique(x.values.to_numpy(zero_copy_only=False))
                first = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1] + 1]))
                last = np.concatenate([first[1:], [len(own)]]) - 1
                packed.append(np.stack([own[first], own[last] + 1], axis=1).astype(np.int64).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(packed, pa.binary())], names=["doc", name])

    return marks.groupBy("doc").agg(F.collect_list("ordinal").alias("o")).mapInArrow(run, f"doc bigint, {name} binary")


def _placed(docs: DataFrame, lists: DataFrame, names: list[str], how: str) -> DataFrame:
    """Documents with their packed lists; the lists are broadcast only if they are known to be small."""
    lists = durable(lists)
    size = lists.agg(F.count(F.lit(1)).alias("n"), F.sum(sum((F.coalesce(F.length(c), F.lit(0)) for c in names), F.lit(0))).alias("b")).first()
    small = size["n"] <= BROADCAST_ROWS and (size["b"] or 0) <= BROADCAST_BYTES
    return docs.join(F.broadcast(lists) if small else lists, F.col("doc_id") == F.col("doc"), how).select("doc_id", "text", *names)


def _unpack(raw: bytes | None) -> np.ndarray:
    return np.frombuffer(raw or b"", dtype=np.int64).reshape(-1, 2)


def _members(ranges: np.ndarray) -> np.ndarray:
    return np.concatenate([np.arange(a, b) for a, b in ranges]) if len(ranges) else np.zeros(0, dtype=np.int64)


def _window_rows(placed: DataFrame, length: int) -> DataFrame:
    """(h, doc, ordinal): hash and place of each window of the listed anchors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, texts in byte_slices(list(zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), strict=True)), utf8(batch.column(1))):
                x = Anchors(texts, length)
                base = np.searchsorted(x.doc, np.arange(len(texts)))
                wanted = np.concatenate([base[i] + _members(_unpack(raw)) for i, (_, raw) in enumerate(rows)])
                wanted = wanted[wanted < len(x.at)]
                n = x.last[wanted] - x.first[wanted] + 1
                q = np.repeat(x.first[wanted], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                owner = np.repeat(x.doc[wanted], n)
                h = span_hashes(x.prefix, q, q + length).view(np.int64)
                nodes = np.array([r[0] for r in rows], dtype=np.int64)[owner]
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(nodes), pa.array(q - x.begin[owner], pa.int64())], names=["h", "doc", "ordinal"])

    return placed.mapInArrow(in_slices(run), "h bigint, doc bigint, ordinal bigint")


def _later(windows: DataFrame, parts: int) -> DataFrame:
    """(doc, ordinal) of windows that a smaller document has too.

    Only one document for each distinct context of an anchor gives windows, so a
    hash repeats once for each variant of a passage, not for each copy.  Sorted by hash and
    document, a run's later rows follow in one pass that holds no run.
    """

    def first_of_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last_h = last_doc = None
        for batch in batches:
            h, doc, ordinal = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            if not len(h):
                continue
            fresh = np.concatenate([[h[0] != last_h], h[1:] != h[:-1]])
            at = np.maximum.accumulate(np.where(fresh, np.arange(len(h)), -1))
            least = np.where(at >= 0, doc[np.maximum(at, 0)], last_doc if last_doc is not None else 0)
            late = doc != least
            yield pa.RecordBatch.from_arrays([pa.array(doc[late]), pa.array(ordinal[late])], names=["doc", "ordinal"])
            last_h, last_doc = h[-1], least[-1]

    ordered = windows.repartition(parts, "h").sortWithinPartitions("h", "doc", "ordinal")
    return ordered.mapInArrow(first_of_runs, "doc bigint, ordinal bigint")


def repeated_spans(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc, anchors, windows): packed anchor ranges and window-start ranges to remove, for documents that have any."""
    own = docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()).select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    size = own.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), size // BUCKET_BYTES)
    rows = _suffix_rows(own, length, _sample_cuts(own, length, parts))
    marks = durable(_compare(dealt(rows, parts, ["gram", "context", "doc", "ordinal"])))
    whole, part = _across(marks.where("kind = 'edge'").drop("kind"))
    whole = marks.where("kind = 'whole'").select("doc", "ordinal").union(whole)
    part = marks.where("kind = 'part'").select("doc", "ordinal").union(part)
    windows = _window_rows(_placed(own, _per_document(part, "packed"), ["packed"], "inner"), length)
    late = durable(_later(windows, parts))
    return _per_document(whole, "anchors").join(_per_document(late, "windows"), "doc", "full")


def remove_repeats(docs: DataFrame, length: int = LENGTH, with_text: bool = False) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept, the remaining bytes).

    A byte goes if a ``length``-byte string that covers it also starts in a
    document with a smaller doc_id; strings are judged on the input, and never
    cross documents.  Null texts are empty.  Rows with a null doc_id are left
    whole and count as no document.  Rows that share a doc_id are expected to be
    copies of one another; they lose the same bytes.
    """
    spans = repeated_spans(docs, length)
    columns = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + ["kept"] * with_text
    id_type = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            listed = list(zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True))
            for rows, texts in byte_slices(listed, utf8(batch.column(1))):
                marked = [i for i, r in enumerate(rows) if r[1]]
                x = Anchors([texts[i] for i in marked], length)
                base = dict(zip(marked, zip(np.searchsorted(x.doc, np.arange(len(marked))).tolist(), x.begin.tolist()), strict=False))
                out: list[list] = [[] for _ in columns]
                for i, ((doc_id, anchors, windows), text) in enumerate(zip(rows, texts, strict=True)):
                    kept, removed, n_spans = text, 0, 0
                    if anchors or windows:
                        edge = np.zeros(len(text) + 1, dtype=np.int32)
                        if anchors:
                            first, shift = base[i]
                            k = first + _members(_unpack(anchors))
                            k = k[k < len(x.at)]
                            np.add.at(edge, x.first[k] - shift, 1)
                            np.add.at(edge, x.last[k] - shift + length, -1)
                        for a, b in _unpack(windows).tolist():
                            edge[a] += 1
                            edge[b - 1 + length] -= 1
                        gone = np.cumsum(edge[:-1]) > 0
                        removed = int(gone.sum())
                        n_spans = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum()) if len(gone) else 0
                        kept = np.frombuffer(text, dtype=np.uint8)[~gone].tobytes()
                    row = [doc_id, len(text), removed, n_spans, hashlib.sha256(kept).hexdigest()] + [kept] * with_text
                    for c, v in zip(out, row, strict=True):
                        c.append(v)
                types = [batch.column(0).type, pa.int64(), pa.int64(), pa.int64(), pa.string()] + [pa.binary()] * with_text
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], names=columns)

    placed = _placed(docs.select("doc_id", "text"), spans, ["anchors", "windows"], "left")
    schema = f"doc_id {id_type}, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + ", kept binary" * with_text
    return placed.mapInArrow(in_slices(run), schema)
