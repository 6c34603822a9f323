"""Conflict-constrained best-fit packing of documents into bins of a fixed number of tokens.

Rows are dealt by a hash to shards of bounded size; a shard is packed alone, largest first.  Its
bins stand in order of residual room, each with a bitmap of the sources and one of the duplicate
clusters it holds.  A segment tree over residuals keeps, of the bins at each, the sources and
clusters that all of them hold; so the search for the next larger residual passes over what cannot be
compatible, and goes on until the tightest bin that holds neither the source nor the cluster is found.
A document longer than a bin fills bins of its own, and its rest is packed like a document.

Rows that are equal in all that counts are counted first and dealt one to each shard in turn, so that
a group of any number of them is spread over all shards.  A shard is one task's partition.
"""

from __future__ import annotations

from bisect import insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, word_array

#: Rows of a shard, about.
SHARD_ROWS = 8192


class Shelf:
    """Open bins by residual room; what a bin holds is one bitmap of sources and, above them, clusters."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.every = -1  # all bits: no bin here lacks anything
        self.tree = [self.every] * (2 * self.size)
        self.bins: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.held: list[int] = []

    def _set(self, room: int) -> None:
        common = self.every
        for b in self.bins[room]:
            common &= self.held[b]
            if not common:
                break
        i = room + self.size
        tree = self.tree
        while i and tree[i] != common:
            tree[i] = common
            common &= tree[i ^ 1]
            i >>= 1

    def _next(self, room: int, own: int) -> int:
        """The least residual of at least ``room`` whose bins do not all hold one of the bits; -1: none."""
        i = room + self.size
        if not self.tree[i] & own:
            return room
        while i > 1:
            if i % 2 == 0 and not self.tree[i + 1] & own:
                i += 1
                while i < self.size:
                    i = 2 * i if not self.tree[2 * i] & own else 2 * i + 1
                return i - self.size
            i >>= 1
        return -1

    def put(self, need: int, own: int) -> tuple[int, int]:
        """Place a document of ``need`` tokens whose source and cluster are the bits of ``own``; the bin and the room that was left before."""
        room = self._next(need, own) if need < len(self.bins) else -1
        while room >= 0:
            for b in self.bins[room]:  # the first opened comes first
                if not self.held[b] & own:
                    self.bins[room].remove(b)
                    self._set(room)
                    self._add(b, room - need, own)
                    return b, room
            room = self._next(room + 1, own) if room + 1 < len(self.bins) else -1
        b, room = len(self.held), len(self.bins) - 1
        self.held.append(0)
        self._add(b, room - need, own)
        return b, room

    def _add(self, b: int, room: int, own: int) -> None:
        self.held[b] |= own
        insort(self.bins[room], b)
        self._set(room)


def pack_shard(sizes: list[int], sources: list, clusters: list, capacity: int) -> list[tuple[int, int, int, int, int]]:
    """(row, piece, bin, start, tokens) of all pieces; rows are placed by size (of the rest after full bins), largest first, then by place."""
    shelf = Shelf(capacity)
    bits: dict = {}
    own = [1 << bits.setdefault(s, len(bits)) for s in sources]
    counted: dict = {}
    for c in clusters:
        counted[c] = counted.get(c, 0) + 1
    names = {c: len(bits) + i for i, c in enumerate(c for c, n in counted.items() if n > 1 and c is not None)}
    own = [o | 1 << names[c] if c in names else o for o, c in zip(own, clusters, strict=True)]
    out = []
    order = sorted(range(len(sizes)), key=lambda i: (-sizes[i], i))
    for i in order:
        for piece in range(sizes[i] // capacity if sizes[i] > capacity else 0):
            b, _ = shelf.put(capacity, 0)
            out.append((i, piece, b, 0, capacity))
    rest = [(s if s <= capacity else s % capacity) for s in sizes]
    for i in sorted(range(len(sizes)), key=lambda i: (-rest[i], i)):
        if sizes[i] > capacity and rest[i] == 0:
            continue
        b, room = shelf.put(rest[i], own[i])
        out.append((i, sizes[i] // capacity if sizes[i] > capacity else 0, b, capacity - room, rest[i]))
    return out


def best_fit(docs: DataFrame, capacity: int = 2048, id_column: str = "doc_id", size_column: str = "n_tokens", source_column: str = "source", cluster_column: str = "cluster", shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(bin_id, start, id, piece, n_tokens): every token of every row in one place, no bin over ``capacity``.

    No bin holds two rows of one source, or of one duplicate cluster (a null cluster is of one row
    alone; null sources are one source).  A null or negative size is 0: the row still gets a place.
    Rows are told apart by id and size; repeated rows, and rows of a null id, are packed as often as they come;
    no rows give no rows.  bin_id is a string of the shard and the bin's number in it.
    """
    sized = docs.select(F.col(f"`{id_column}`").cast("long").alias("id"), F.greatest(F.coalesce(F.col(f"`{size_column}`").cast("long"), F.lit(0)), F.lit(0)).alias("size"), F.xxhash64(F.col(f"`{source_column}`").cast("string")).alias("source"), F.col(f"`{cluster_column}`").cast("long").alias("cluster"))
    rows = durable(sized.groupBy("id", "size", "source", "cluster").agg(F.count("*").alias("n")))
    shards = max(1, -(-(rows.agg(F.sum("n")).first()[0] or 0) // shard_rows))
    # of n equal rows, starting at a shard picked by hash, each shard in turn gets one until all are dealt
    first, turns = F.xxhash64("id", "size", "cluster"), F.least(F.col("n"), F.lit(shards)).cast("int")
    dealt = rows.select("*", F.explode(F.sequence(F.lit(0), turns - 1)).alias("turn"))
    dealt = dealt.select(F.pmod(first + F.col("turn"), F.lit(shards)).cast("int").alias("shard"), "id", "size", "source", "cluster", F.floor((F.col("n") - 1 - F.col("turn")) / shards + 1).cast("int").alias("copies"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for shard, group in _by_first(batches):
            group = group.sort_by([("id", "ascending"), ("size", "ascending"), ("source", "ascending"), ("cluster", "ascending")])
            group = group.take(pa.array(np.repeat(np.arange(group.num_rows), group.column("copies").to_numpy())))
            got = group.to_pydict()
            found = pack_shard(got["size"], got["source"], got["cluster"], capacity)
            row, piece, number, start, size = zip(*found, strict=True)
            yield pa.RecordBatch.from_arrays(
                [pa.array([f"{shard}-{b}" for b in number]), pa.array(start, pa.int64()), pa.array([got["id"][i] for i in row], pa.int64()), pa.array(piece, pa.int64()), pa.array(size, pa.int64())],
                names=["bin_id", "start", "id", "piece", "n_tokens"],
            )

    parts = min(shards, max(1000, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))))  # dealt in turn: no two shards meet by chance
    apart = dealt.repartitionById(parts, F.pmod(F.col("shard"), F.lit(parts))).sortWithinPartitions("shard")
    return apart.mapInArrow(run, "bin_id string, start long, id long, piece long, n_tokens long")


def _by_first(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.Table]]:
    """Sorted rows as whole groups of the first column."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        key = batch.column(0).to_numpy()
        edge = [0, *(np.flatnonzero(np.diff(key)) + 1).tolist(), len(key)]
        for a, b in zip(edge, edge[1:], strict=False):
            if a == b:
                continue
            if held and held[0].column(0)[0].as_py() != key[a]:
                yield held[0].column(0)[0].as_py(), pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
    if held:
        yield held[0].column(0)[0].as_py(), pa.Table.from_batches(held)


def pack_documents(docs: DataFrame, capacity: int = 2048, text_column: str = "text") -> DataFrame:
    """``best_fit`` of documents: tokens are words and one end; rows of equal texts are a duplicate cluster."""
    sized = docs.select("doc_id", "source", (F.size(word_array(text_column)) + 1).alias("n_tokens"), F.xxhash64(F.coalesce(F.col(text_column), F.lit(""))).alias("cluster"))
    return best_fit(sized, capacity).withColumnRenamed("id", "doc_id")
