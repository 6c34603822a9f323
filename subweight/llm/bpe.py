"""Byte-level BPE encoding and decoding by the ranks of a public vocabulary.

A piece of text starts as single bytes.  A segment tree over byte positions holds, for every live
part, the rank of the pair it makes with its right neighbour, and at each inner node the least of
its children; the first child with the root's least, level by level, is the next merge.  A merge
changes three leaves: the part, the one to its left and the one swallowed, so it costs the logarithm
of the piece's length and a piece of n bytes n log n, however long.  Nodes have many children, as
the least of a short list is one call: an ordinary piece is a single node.
"""

from __future__ import annotations

import base64
import sys
import types
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of pieces and their ids remembered by one worker, and what each takes besides.
MOST_REMEMBERED, PIECE_COST = 32 << 20, 150
#: Children of a node of the tree.
FAN = 32
_NONE = 1 << 62


def load_ranks(lines: bytes) -> dict[bytes, int]:
    """Ranks from the text of a rank file: base64 of the token, its rank."""
    return {base64.b64decode(a): int(b) for a, b in (line.split() for line in lines.splitlines() if line)}


def merge(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Token ids of one piece."""
    whole = ranks.get(piece)
    if whole is not None:
        return [whole]
    n, get, none = len(piece), ranks.get, _NONE
    leaves = [get(piece[i : i + 2], none) for i in range(n - 1)]
    leaves.append(none)
    tree = [leaves]
    while len(tree[-1]) > FAN:
        below = tree[-1]
        tree.append([min(below[a : a + FAN]) for a in range(0, len(below), FAN)])
    root, inner = tree[-1], tree[-2::-1]
    after = list(range(1, n + 2))  # start of the next part
    before = list(range(-1, n))  # start of the part to the left

    while (least := min(root)) != none:
        i = root.index(least)
        for level in inner:
            i = level.index(least, i * FAN)
        gone = after[i]
        end = after[i] = after[gone]
        before[end] = i
        leaves[gone] = none
        leaves[i] = get(piece[i : after[end]], none) if end < n else none
        left = before[i]
        if left >= 0:
            leaves[left] = get(piece[left:end], none)
        if inner:
            for node in {max(left, 0) // FAN, i // FAN, gone // FAN}:
                _lift(tree, node)
    ids, i = [], 0
    while i < n:
        ids.append(ranks[piece[i : after[i]]])
        i = after[i]
    return ids


def _lift(tree: list[list[int]], node: int) -> None:
    """After a change below the given node of the second level: the least of it and of those above, as far as they change."""
    for below, level in zip(tree, tree[1:], strict=False):
        least = min(below[node * FAN : node * FAN + FAN])
        if level[node] == least:
            return
        level[node] = least
        node //= FAN


class _Known(dict):
    """Ids of pieces by piece, worked out when first asked for; a full memory starts anew, and what alone is too large is not kept."""

    def __init__(self, ranks: dict[bytes, int]):
        super().__init__()
        self.ranks, self.held = ranks, 0

    def __missing__(self, piece: str) -> bytes:
        ids = b"".join([x.to_bytes(4, "little") for x in merge(piece.encode(), self.ranks)])
        cost = len(piece) + len(ids) + PIECE_COST
        if cost <= MOST_REMEMBERED:
            if self.held + cost > MOST_REMEMBERED:
                self.clear()
                self.held = 0
            self[piece] = ids
            self.held += cost
        return ids


class Encoder:
    """Texts to little-endian 32-bit ids; pieces seen before are remembered, up to a bound."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.known = _Known(ranks)
        self.pieces = regex.compile(pattern).findall
        self.tokens = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token

    @property
    def held(self) -> int:
        return self.known.held

    def encode(self, text: str) -> bytes:
        known = self.known
        return b"".join([known[p] for p in self.pieces(text)])

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.tokens.__getitem__, memoryview(ids).cast("I")))


def _encoder(lines: bytes, pattern: str) -> Encoder:
    """One for each worker process."""
    store = sys.modules.setdefault("_bpe_encoders", types.ModuleType("_bpe_encoders")).__dict__
    key = f"{hash(lines)} {pattern}"
    if key not in store:
        store[key] = Encoder(load_ranks(lines), pattern)
    return store[key]


def _mapped(df: DataFrame, column: str, new: str, convert) -> DataFrame:
    names = [c for c in df.columns if c != new]
    schema = T.StructType([*[df.schema[c] for c in names], T.StructField(new, T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 1000):
                part = batch.slice(a, 1000)
                values = convert(part.column(batch.num_columns - 1))
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(values, pa.binary())], names=[*names, new])

    return df.select(*[F.col(f"`{c}`") for c in names], F.col(f"`{column}`").alias("__in")).mapInArrow(run, schema)


def encode(df: DataFrame, rank_lines: bytes, pattern: str, text_column: str = "text", ids_column: str = "ids") -> DataFrame:
    """``df`` and the ids of a text as little-endian unsigned 32-bit integers, each match of ``pattern`` merged by itself.

    No special tokens: their strings are ordinary text.  A null or empty text has no ids; bytes that
    are not UTF-8 are read as U+FFFD; a column of the new name is replaced; no rows give no rows.
    """
    context = df.sparkSession.sparkContext
    sent = context.broadcast(rank_lines)  # the size of the vocabulary file, whatever the data

    def convert(column: pa.Array) -> list[bytes]:
        own = _encoder(sent.value, pattern)
        return [own.encode(t.decode("utf-8", "replace")) if t else b"" for t in column.cast(pa.binary()).to_pylist()]

    return _mapped(df, text_column, ids_column, convert)


def decode(df: DataFrame, rank_lines: bytes, pattern: str, ids_column: str = "ids", bytes_column: str = "decoded") -> DataFrame:
    """``df`` and the bytes that the ids stand for; null ids give none, an id that is no token raises."""
    sent = df.sparkSession.sparkContext.broadcast(rank_lines)

    def convert(column: pa.Array) -> list[bytes]:
        own = _encoder(sent.value, pattern)
        return [own.decode(x) if x else b"" for x in column.to_pylist()]

    return _mapped(df, ids_column, bytes_column, convert)
