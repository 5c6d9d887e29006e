"""Byte-level BPE by monoid tree reduction.

``encode`` is a monoid map: a text is cut into leaves, each leaf is encoded
alone, and neighbours are joined pairwise up a tree.  Only a window around each
seam is encoded again.  The window grows until it ends at *fences* on both
sides: a fence is a position with white space right of it and none left of it.
No alternative of the split pattern spans a fence, and a match that ends at one
looks at nothing beyond the fence's own character, so all tokens outside
the window are the same as in the encoding of the whole.  A text without fences is
encoded again as a whole, which is the growing window at its limit.

Decoding concatenates the byte strings of id runs up the same kind of tree.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_slices, once_per_worker

#: Characters in a leaf of the tree.
LEAF = 8192


class TreeCodec:
    """Encoder and decoder for one rank file."""

    def __init__(self, rank_file: bytes, pattern: str, leaf: int = LEAF):
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in rank_file.splitlines() if line)}
        self.base = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        size = max(ranks.values()) + 1
        self.names = [str(i) for i in range(size)]
        self.width = [0] * size
        for token, rank in ranks.items():
            self.width[rank] = len(token)
        self.leaf = leaf

    # -- encoding

    def encode(self, text: str) -> list[int]:
        """Ids of a whole text, equal to those of an encoder that reads it at once."""
        if len(text) <= self.leaf:
            return self.base.encode_ordinary(text)
        level = [(i, min(i + self.leaf, len(text))) for i in range(0, len(text), self.leaf)]
        nodes = [(a, b, self.base.encode_ordinary(text[a:b])) for a, b in level]
        while len(nodes) > 1:
            nodes = [self._join(text, *nodes[i : i + 2]) if i + 1 < len(nodes) else nodes[i] for i in range(0, len(nodes), 2)]
        return nodes[0][2]

    def _join(self, text: str, left: tuple, right: tuple) -> tuple:
        low, seam, high = left[0], left[1], right[1]
        start, end = self._fence_before(text, low, seam), self._fence_after(text, seam, high)
        head = left[2][: self._keep_head(left[2], len(text[start:seam].encode()))]
        tail = right[2][self._drop_head(right[2], len(text[seam:end].encode())) :]
        return low, high, head + self.base.encode_ordinary(text[start:end]) + tail

    @staticmethod
    def _fence_before(text: str, low: int, seam: int) -> int:
        """The last fence whose own character is left of the seam, else the node's start."""
        width = 16
        while True:
            floor = max(low, seam - width)
            for i in range(seam - 1, floor, -1):
                if text[i] in " \n\t\r" and not text[i - 1].isspace():
                    return i
            if floor == low:
                return low
            width *= 4

    @staticmethod
    def _fence_after(text: str, seam: int, high: int) -> int:
        width = 16
        while True:
            roof = min(high, seam + width)
            for i in range(seam + 1, roof):
                if text[i] in " \n\t\r" and not text[i - 1].isspace():
                    return i
            if roof == high:
                return high
            width *= 4

    def _keep_head(self, ids: list[int], cut: int) -> int:
        """How many ids stay when the last ``cut`` bytes are encoded again."""
        keep = len(ids)
        while cut > 0:
            keep -= 1
            cut -= self.width[ids[keep]]
        assert cut == 0, "a fence is a token boundary"
        return keep

    def _drop_head(self, ids: list[int], cut: int) -> int:
        drop = 0
        while cut > 0:
            cut -= self.width[ids[drop]]
            drop += 1
        assert cut == 0, "a fence is a token boundary"
        return drop

    # -- decoding

    def decode(self, ids: list[int]) -> bytes:
        """Bytes of an id list; runs are decoded alone and concatenated up the tree."""
        parts = [self.base.decode_bytes(ids[i : i + self.leaf]) for i in range(0, len(ids), self.leaf)] or [b""]
        while len(parts) > 1:
            parts = [b"".join(parts[i : i + 2]) for i in range(0, len(parts), 2)]
        return parts[0]


def _codec(rank_file: bytes, pattern: str, leaf: int) -> TreeCodec:
    key = "bpe_" + hashlib.sha256(rank_file + pattern.encode() + str(leaf).encode()).hexdigest()[:16]
    return once_per_worker(key, lambda: TreeCodec(rank_file, pattern, leaf))


def read_ranks(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def encode_documents(df: DataFrame, rank_file: bytes, pattern: str, leaf: int = LEAF, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Token ids of each text: (id_col, ids ARRAY<INT>).

    One row per input row; a null text counts as empty and has no ids.  Rows
    may repeat.  Columns other than the two named are ignored.
    """
    shared = df.sparkSession.sparkContext.broadcast(rank_file)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(shared.value, pattern, leaf)
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                ids = [codec.encode(x or "") for x in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.list_(pa.int32()))], names=[id_col, "ids"])

    source = df.select(F.col(id_col), F.col(text_col))
    return source.mapInArrow(in_slices(run), f"{_name(id_col)} {dict(source.dtypes)[id_col]}, ids array<int>")


def decode_ids(df: DataFrame, rank_file: bytes, pattern: str, leaf: int = LEAF, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """Bytes of each id list: (id_col, bytes BINARY); a null list decodes to no bytes."""
    shared = df.sparkSession.sparkContext.broadcast(rank_file)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(shared.value, pattern, leaf)
        for batch in batches:
            out = [codec.decode(x or []) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=[id_col, "bytes"])

    source = df.select(F.col(id_col), F.col(ids_col))
    return source.mapInArrow(in_slices(run), f"{_name(id_col)} {dict(source.dtypes)[id_col]}, bytes binary")


def round_trip_digest(df: DataFrame, rank_file: bytes, pattern: str, leaf: int = LEAF, return_text: bool = True) -> DataFrame:
    """Encode, decode and digest every text in one pass: no ids cross to the JVM.

    Keeps every input column (all but the text if ``return_text`` is false) and
    adds n_tokens, ids_sha256 and decoded_sha256; columns of those names in the
    input are replaced.  No shuffle; memory is bounded by one Arrow batch and
    one text's ids.
    """
    import pyspark.sql.types as T

    shared = df.sparkSession.sparkContext.broadcast(rank_file)
    added = {"n_tokens": T.LongType(), "ids_sha256": T.StringType(), "decoded_sha256": T.StringType()}
    kept = df.drop(*added)
    given = [f for f in kept.schema.fields if return_text or f.name != "text"]
    schema = T.StructType([*given, *(T.StructField(k, v) for k, v in added.items())])
    names, at = schema.names, kept.columns.index("text")
    back = [i for i, f in enumerate(kept.schema.fields) if f in given]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(shared.value, pattern, leaf)
        name = codec.names.__getitem__
        for batch in batches:
            counts, ids_sha, text_sha = [], [], []
            for scalar in batch.column(at):
                ids = codec.encode(scalar.as_py() or "")
                counts.append(len(ids))
                ids_sha.append(hashlib.sha256(" ".join(map(name, ids)).encode()).hexdigest())
                text_sha.append(hashlib.sha256(codec.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in back), pa.array(counts, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], names=names)

    return kept.mapInArrow(in_slices(run), schema)


def _name(column: str) -> str:
    return f"`{column}`"
