"""Greedy word-piece token counts by a linear longest-match automaton.

The vocabulary is a set of pieces; those that begin a word carry a start mark.
A word (with the mark before it) is cut greedily into longest pieces.  The
automaton is a trie with failure links: the link of a node leads to the node
for what is left after the greedy pieces of its string are taken off, and the
number of those pieces is stored with it.  So a word's length in
pieces follows from one pass over its characters, and no piece is built.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_slices, once_per_worker, utf8

START = "▁"
#: Words whose counts one worker remembers; the table is emptied when full.
REMEMBERED = 200_000


class PieceCounter:
    """Trie with failure links over a vocabulary; ``count(word)`` is linear in the word."""

    def __init__(self, pieces: Iterable[str]):
        self.step: list[dict[str, int]] = [{}]
        whole = [False]
        for piece in pieces:
            node = 0
            for c in piece:
                if c not in self.step[node]:
                    self.step[node][c] = len(self.step)
                    self.step.append({})
                    whole.append(False)
                node = self.step[node][c]
            whole[node] = node != 0
        n = len(self.step)
        self.fail, self.popped = [-1] * n, [0] * n
        queue = [0]
        for u in queue:
            for c, v in self.step[u].items():
                queue.append(v)
                if whole[v]:
                    self.fail[v], self.popped[v] = 0, 1
                    continue
                z, taken = self.fail[u], self.popped[u]
                while z >= 0 and c not in self.step[z]:
                    taken += self.popped[z]
                    z = self.fail[z]
                if z >= 0:
                    self.fail[v], self.popped[v] = self.step[z][c], taken
        #: Pieces that are left to take when the word ends in a node; -1 where its string cannot be cut.
        self.rest = [0] * n
        for u in queue[1:]:
            f = self.fail[u]
            self.rest[u] = -1 if f < 0 or self.rest[f] < 0 else self.popped[u] + self.rest[f]

    def count(self, word: str) -> int:
        """Greedy pieces of a word; one that cannot be cut counts as one unknown piece."""
        step, fail, popped = self.step, self.fail, self.popped
        node, taken = 0, 0
        for c in word:
            nxt = step[node].get(c)
            while nxt is None:
                if fail[node] < 0:
                    return 1
                taken += popped[node]
                node = fail[node]
                nxt = step[node].get(c)
            node = nxt
        return 1 if self.rest[node] < 0 else taken + self.rest[node]


def read_pieces(path: str) -> list[str]:
    """Ordinary pieces of a sentencepiece model file, bytes and control symbols left out."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    return [model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i))]


def count_tokens(df: DataFrame, pieces: list[str], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id_col, n_words, n_tokens) of each text, one row per input row.

    Words are separated by ASCII white space.  Null and empty texts have
    no words.  The vocabulary is broadcast: its size is fixed by its file.
    """
    shared = df.sparkSession.sparkContext.broadcast(pieces)
    key = f"pieces_{len(pieces)}_{hash(tuple(pieces)) & 0xFFFFFFFF:x}"
    start = START

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = once_per_worker(key, lambda: PieceCounter(shared.value))
        known: dict[bytes, int] = {}
        for batch in batches:
            words, tokens = [], []
            for text in utf8(batch.column(1)):
                parts = text.split()
                total = 0
                for part in parts:
                    n = known.get(part)
                    if n is None:
                        if len(known) >= REMEMBERED:
                            known.clear()
                        n = known[part] = counter.count(start + part.decode())
                    total += n
                words.append(len(parts))
                tokens.append(total)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(words, pa.int64()), pa.array(tokens, pa.int64())], names=[id_col, "n_words", "n_tokens"])

    source = df.select(F.col(id_col), F.col(text_col))
    return source.mapInArrow(in_slices(run), f"`{id_col}` {dict(source.dtypes)[id_col]}, n_words bigint, n_tokens bigint")
