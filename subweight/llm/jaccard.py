"""Near copies by the exact Jaccard similarity of sets of shingles.

The shingles of a text are put in one order of all texts: by the number of texts that have them (its
binary logarithm), then by hash.  Two sets of a similarity t or more have a shingle in common among the
first size - ceil(t * size) + 1 of each, whatever the order is, so these *prefixes* are the keys; of
them only shingles of two or more texts can meet another's, and a text with enough shingles of its own
has no key at all.  At their common shingle the places in both orders bound how many can follow; pairs
that cannot reach the similarity by that bound are left out, and all other pairs are decided by their
sets.

A run is the sets of one key.  All are first paired with the run's head, the set with the least share of
shingles that no other text has: of a large group of copies the likely original.  Sets that links have
then not brought together with the head are compared with the whole run, a few of each run first and
then more, until each pair of the run is decided or connected; a large group of near copies costs about
its size.  Runs are grouped and joined by the engine and never held in one place.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import QUESTION_ARROW, QUESTION_SCHEMA, Words, arrow_rows, ask, bucket_count, durable, mix, release, split_buckets, to_blocks, unpack, utf8_columns, with_answers
from .components import components

SEED = 303
#: Sets of a run that are compared with the whole run in the first round after the heads; each later round takes so many times more.
PROBES = 8


class Sets:
    """The distinct shingles of several texts (A-Z lower-cased; fewer words: all as one), by text and hash; a size and a hash of each set."""

    def __init__(self, texts: list[bytes | None], shingle: int):
        words = Words([t.lower() if t else b"" for t in texts])
        at = np.flatnonzero(words.text[shingle - 1 :] == words.text[: len(words) - shingle + 1]) if len(words) >= shingle else np.zeros(0, np.int64)
        text, hashes = [words.text[at]], [words.hashes(shingle, SEED)[at]]
        for n in range(1, shingle):
            few = np.flatnonzero(words.counts == n)
            if len(few):
                text.append(few)
                hashes.append(words.hashes(n, SEED + n)[words.first[few]])
        text, hashes = np.concatenate(text), np.concatenate(hashes)
        order = np.lexsort((hashes, text))
        text, hashes = text[order], hashes[order]
        new = np.ones(len(text), bool)
        new[1:] = (text[1:] != text[:-1]) | (hashes[1:] != hashes[:-1])
        self.text, self.hash = text[new], hashes[new]
        self.size = np.bincount(self.text, minlength=len(texts))
        self.first = np.cumsum(self.size) - self.size
        self.node = np.zeros(len(texts), np.uint64)
        full = self.size > 0
        if full.any():
            self.node[full] = mix(np.add.reduceat(mix(self.hash), self.first[full]) + self.size[full].astype(np.uint64))

    def frequencies(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Sorted distinct shingles, each one's place among them, and the texts that have them."""
        return np.unique(self.hash, return_inverse=True, return_counts=True)


def needed(size_a, size_b, similarity: float):
    """Common shingles that two sets need."""
    return np.ceil(similarity / (1 + similarity) * (np.asarray(size_a, np.float64) + size_b) - 1e-9)


def answer_frequencies(keys: list[bytes], counts: list[bytes]) -> list[bytes | None]:
    """For each block's shingles (32 bits besides those of the bucket): a bit for those of two or more texts, then the bit length of the number of texts of these.

    Shingles that share the 32 bits count as one, for every block alike: the order stays one of all texts.
    """
    sizes = [len(k) // 4 for k in keys]
    distinct, index = np.unique(np.frombuffer(b"".join(keys), np.uint32), return_inverse=True)
    n = np.concatenate([np.frombuffer(c, np.uint16) for c in counts])
    level = np.frexp(np.bincount(index, n, len(distinct)))[1].astype(np.uint8)[index]
    out, at = [], 0
    for size in sizes:
        own = level[at : at + size]
        out.append(np.packbits(own > 1).tobytes() + own[own > 1].tobytes() if (own > 1).any() else None)
        at += size
    return out


def _levels(keys: np.ndarray, answers: dict[int, bytes], buckets: int) -> np.ndarray:
    out = np.ones(len(keys), np.int64)
    bounds, own = split_buckets(keys, buckets)
    for k, b in enumerate(own):
        blob, n = answers.get(int(b)), int(bounds[k + 1] - bounds[k])
        if blob is not None:
            shared = np.unpackbits(np.frombuffer(blob, np.uint8, (n + 7) // 8), count=n).astype(bool)
            out[bounds[k] : bounds[k + 1]][shared] = np.frombuffer(blob, np.uint8, offset=(n + 7) // 8)
    return out


def prefixes(sets: Sets, level: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Text, shingle and place of the keys of all sets, and each set's number of shingles of its own; ``level``: of each shingle of a set."""
    order = np.lexsort((mix(sets.hash), level, sets.text))
    place = np.arange(len(order)) - sets.first[sets.text]  # sorting keeps the texts in order
    length = sets.size - np.ceil(similarity * sets.size - 1e-9) + 1
    key = (place < length[sets.text]) & (level[order] > 1)
    return sets.text[key], sets.hash[order][key], place[key], np.bincount(sets.text[level == 1], minlength=len(sets.size))


SET_SCHEMA = "node long, size int, own_share double, keys binary, places binary, own binary"


def text_sets(docs: DataFrame, shingle: int, similarity: float) -> tuple[DataFrame, DataFrame]:
    """Of rows (id, text, text_key): (id, text_key, node) of each, node: its set's hash; and once for each set that has keys (node, size, own_share, keys, places, own). Both durable."""
    blocks = to_blocks(docs)
    buckets = bucket_count(blocks)

    def nodes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for payload in batch.column(0).to_pylist():
                rows = unpack(payload)
                node = Sets(utf8_columns(rows, "text"), shingle).node.view(np.int64)
                yield pa.RecordBatch.from_arrays([rows.column("id"), rows.column("text_key"), pa.array(node)], names=["id", "text_key", "node"])

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                keys, _, counts = Sets(utf8_columns(unpack(row["payload"]), "text"), shingle).frequencies()
                bounds, own = split_buckets(keys, buckets)
                short = (keys >> np.uint64(16)).astype(np.uint32)
                counts = np.minimum(counts, 0xFFFF).astype(np.uint16)  # a block has fewer than 8,192 rows
                parts = [slice(bounds[k], bounds[k + 1]) for k in range(len(own))]
                yield arrow_rows([(int(b), 0, row["block_id"], short[s].tobytes(), counts[s].tobytes()) for b, s in zip(own, parts, strict=True)], QUESTION_ARROW)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [c.split()[0] for c in SET_SCHEMA.split(", ")]
        for batch in batches:
            for row in batch.to_pylist():
                sets = Sets(utf8_columns(unpack(row["payload"]), "text"), shingle)
                keys, index, _ = sets.frequencies()
                level = _levels(keys, {x["bucket"]: x["answer"] for x in row["answers"] or []}, buckets)[index]
                text, key, place, single = prefixes(sets, level, similarity)
                edge = np.searchsorted(text, np.arange(len(sets.size) + 1))
                some = np.flatnonzero(np.diff(edge))
                some = some[np.unique(sets.node[some], return_index=True)[1]]  # equal sets of a block once
                cut = lambda array: pa.array([array[edge[i] : edge[i + 1]].tobytes() for i in some], pa.binary())
                own = pa.array([sets.hash[sets.first[i] : sets.first[i] + sets.size[i]].tobytes() for i in some], pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(sets.node.view(np.int64)[some]), pa.array(sets.size[some], pa.int32()), pa.array((single / np.maximum(sets.size, 1))[some]), cut(key), cut(place.astype(np.int32)), own], names=names)

    rows = durable(blocks.select("payload").mapInArrow(nodes, "id long, text_key long, node long"))
    answers = ask(blocks.mapInArrow(send, QUESTION_SCHEMA), answer_frequencies)
    release(docs)
    every = with_answers(blocks, [answers]).mapInArrow(run, SET_SCHEMA)
    sets = durable(every.groupBy("node").agg(*[F.first(c).alias(c) for c in every.columns[1:]]))
    release(docs)
    return rows, sets


def keyed(sets: DataFrame) -> DataFrame:
    """(key, node, size, own_share, place) of every key of distinct sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 1024):
                part = batch.slice(a, 1024)
                keys, places = ([np.frombuffer(x, t) for x in part.column(c).to_pylist()] for c, t in ((3, np.int64), (4, np.int32)))
                repeat = np.repeat(np.arange(part.num_rows), [len(k) for k in keys])
                spread = [pa.array(part.column(c).to_numpy()[repeat]) for c in range(3)]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([*keys, np.zeros(0, np.int64)])), *spread, pa.array(np.concatenate([*places, np.zeros(0, np.int32)]))], names=["key", "node", "size", "own_share", "place"])

    return sets.select("node", "size", "own_share", "keys", "places").mapInArrow(run, "key long, node long, size int, own_share double, place int")


def verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) of nodes whose sets have the similarity; sets: (node, own)."""

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                common = int((y[np.minimum(np.searchsorted(y, x), len(y) - 1)] == x).sum())
                keep.append(common >= needed(len(x), len(y), similarity))
            chosen = np.flatnonzero(keep)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(chosen), batch.column(1).take(chosen)], names=["a", "b"])

    side = lambda n, s: sets.select(F.col("node").alias(n), F.col("own").alias(s))
    both = pairs.join(side("a", "x"), "a").join(side("b", "y"), "b")
    return durable(both.select("a", "b", "x", "y").mapInArrow(decide, "a long, b long"))


def _possible(size: Column, place: Column, other_size: Column, other_place: Column, similarity: float) -> Column:
    """Can enough shingles follow the common one in both orders?"""
    return F.least(size - place, other_size - other_place) >= F.ceil(similarity / (1 + similarity) * (size + other_size) - 1e-9)


def _pairs(rows: DataFrame) -> DataFrame:
    """Distinct (a, b) of rows (node, other)."""
    return rows.select(F.least("node", "other").alias("a"), F.greatest("node", "other").alias("b")).distinct()


def similar_sets(sets: DataFrame, similarity: float) -> DataFrame:
    """(node, component) of the sets that links of the similarity or more connect; sets: (node, size, own_share, keys, places, own) once for each set, durable."""
    rows = keyed(sets)
    rank = F.struct("own_share", F.xxhash64("node").alias("h"), "node", "size", "place")
    heads = rows.groupBy(F.col("key").alias("of")).agg(F.min(rank).alias("head"), F.count("*").alias("n")).filter("n > 1").drop("n")
    runs = durable(rows.join(heads, F.col("key") == F.col("of")).select("key", "node", "size", "own_share", "place", F.col("head.node").alias("other"), F.col("head.size").alias("other_size"), F.col("head.place").alias("other_place")))
    release(sets)
    fits = _possible(F.col("size"), F.col("place"), F.col("other_size"), F.col("other_place"), similarity)
    links = verified(_pairs(runs.filter((F.col("node") != F.col("other")) & fits)), sets, similarity)
    release(sets)
    found = durable(components(links))
    of = lambda tag: found.select(F.col("node").alias(f"{tag}_node"), F.col("component").alias(f"{tag}_group"))
    grouped = runs.join(of("own"), F.col("node") == F.col("own_node"), "left").join(of("head"), F.col("other") == F.col("head_node"), "left")
    grouped = grouped.select("key", "node", "size", "own_share", "place", "other", F.coalesce("own_group", "node").alias("grp"), F.coalesce("head_group", "other").alias("head_grp"))
    apart = grouped.filter("grp <> head_grp")
    place = F.row_number().over(Window.partitionBy("key").orderBy("own_share", "node"))
    waiting = durable(apart.select("key", "node", "size", "place", "other", place.alias("turn")))
    if waiting.isEmpty():
        return found
    left = durable(runs.join(waiting.select("key").distinct(), "key", "left_semi").select("key", "node", "size", "place"))
    low, high = 0, PROBES
    while True:
        group = found.select(F.col("node").alias("g_node"), F.col("component").alias("g"))
        with_group = lambda df, c, name: df.join(group, F.col(c) == F.col("g_node"), "left").withColumn(name, F.coalesce("g", c)).drop("g", "g_node")
        # what has since come together with its run's head needs no turn: whatever is still apart from it has one
        due = with_group(with_group(waiting.filter((F.col("turn") > low) & (F.col("turn") <= high)), "node", "p_grp"), "other", "h_grp").filter("p_grp <> h_grp")
        probes = due.select(F.col("key").alias("p_key"), F.col("node").alias("other"), F.col("size").alias("other_size"), F.col("place").alias("other_place"), "p_grp")
        met = with_group(left, "node", "grp").join(probes, F.col("key") == F.col("p_key")).filter(F.col("grp") != F.col("p_grp")).filter(fits)
        more = verified(_pairs(met), sets, similarity)
        release(sets)
        if not more.isEmpty():
            links = durable(links.unionByName(more))
            found = durable(components(links))
        if waiting.filter(F.col("turn") > high).isEmpty():
            return found
        low, high = high, high * (1 + PROBES)


def jaccard_components(docs: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(id, text_key, component) of every row (id, text): links of the similarity or more connect the sets of a component; equal sets are linked."""
    from .simhash import text_key

    rows, sets = text_sets(docs.select("id", "text", text_key(F.col("text")).alias("text_key")), shingle, similarity)
    found = similar_sets(sets, similarity).withColumnRenamed("node", "of")
    joined = rows.join(found, F.col("node") == F.col("of"), "left")
    return joined.select("id", "text_key", F.coalesce("component", "node").alias("component"))


def jaccard_representatives(docs: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(id, text_key) of one row of each of these components: the one of the smallest id."""
    from .simhash import representatives

    return representatives(jaccard_components(docs, shingle, similarity))
