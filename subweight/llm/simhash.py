"""SimHash near-dedup with Golay-code fuzzy hashing.

A 64-bit fingerprint is cut into segments of 22, 21 and 21 bits, each read as a 23-bit vector.  The
perfect binary Golay code puts every vector within 3 bits of one codeword; a vector's *nearby*
codewords are those within 4 bits: one if its own is within 2, six if it is at 3.  Two vectors that
differ in up to 2 bits share a nearby codeword (that of a vector half way between them).  Of up to
4 differing bits, two of the three segments hold at most 2 each, so two linked fingerprints share a
pair of nearby codewords of the same two segments: about 3 x 28 keys a fingerprint.

Near copies of a given similarity differ in more bits than that: five-word shingles at a Jaccard
similarity of 0.8 leave some 14 of 64 bits apart, beyond what any number of such keys can find.  For
these ``drop_near_duplicates`` can add, to the links of fingerprints, exact ones of the shingle sets
themselves (see ``jaccard``).

Only distinct fingerprints get keys.  Rows of a key are brought together by sorting; within a run
each fingerprint is compared with those not yet reached, so a large group costs its size times its
number of separate pieces, and gives a tree of links, never all its pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import durable, release, utf8_columns
from .components import components
from .jaccard import jaccard_components, jaccard_representatives

#: Fixed value: a generator polynomial of the binary Golay code of length 23 (x^11 + x^9 + x^7 + x^6 + x^5 + x + 1).
GOLAY = 0b101011100011
SEGMENTS = ((0, 22), (22, 21), (43, 21))  # first bit and number of bits
MOST_BITS = 4
#: Distinct fingerprints above which the finer keys are used: more keys for each, of 34 to 36 bits in place of 24.
FINE_ABOVE = 50_000_000
SEED = 42


def shingle_hashes(text: bytes | None, shingle: int) -> np.ndarray:
    """XXH64 of all shingles of the words of a text, A-Z lower-cased; of fewer words, of all together."""
    import xxhash

    words = text.lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    normal = b" ".join(words)
    if len(words) < shingle:
        hashes = np.array([xxhash.xxh64_intdigest(normal, SEED)], np.uint64)
    else:
        gaps = np.flatnonzero(np.frombuffer(normal, np.uint8) == 32)
        starts = [0, *(gaps + 1).tolist()]
        ends = [*gaps.tolist(), len(normal)]
        digest = xxhash.xxh64_intdigest
        hashes = np.array([digest(normal[s:e], SEED) for s, e in zip(starts[: len(words) - shingle + 1], ends[shingle - 1 :], strict=True)], np.uint64)
    return hashes


def vote(hashes: np.ndarray) -> int:
    """Each bit by majority, as a signed 64-bit integer; 0 without hashes."""
    ones = np.zeros(64, np.int64)
    for a in range(0, len(hashes), 1 << 16):
        part = hashes[a : a + (1 << 16)]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.int64)[0])


def fingerprint(text: bytes | None, shingle: int = 4) -> int:
    """Majority vote of the XXH64 of all shingles of words; 0 without words."""
    return vote(shingle_hashes(text, shingle))


def fingerprints(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", shingle: int = 4, keyed: bool = False) -> DataFrame:
    """(id, fp) of every row, with ``keyed`` also text_key; computed once and kept."""
    more = ["text_key"] if keyed else []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 1024):
                part = batch.slice(a, 1024)
                fp = pa.array([fingerprint(t, shingle) for t in utf8_columns(part, "text")], pa.int64())
                yield pa.RecordBatch.from_arrays([part.column(0), fp, *([part.column(2)] if keyed else [])], names=["id", "fp", *more])

    text = F.col(f"`{text_column}`").cast("string")
    rows = docs.select(F.col(f"`{id_column}`").cast("long").alias("id"), text.alias("text"), *([text_key(text).alias("text_key")] if keyed else []))
    return durable(rows.mapInArrow(run, "id long, fp long" + ", text_key long" * keyed))


def whole_runs(batches: Iterator[pa.RecordBatch], columns: int) -> Iterator[list[np.ndarray]]:
    """Rows sorted by their first column, in pieces that do not cut a run of equal keys."""
    held: list[list[np.ndarray]] = []
    for batch in batches:
        now = [batch.column(i).to_numpy() for i in range(columns)]
        if not len(now[0]):
            continue
        cut = int(np.searchsorted(now[0], now[0][-1]))
        if cut == 0 and (not held or held[-1][0][-1] == now[0][0]):
            held.append(now)
            continue
        yield [np.concatenate([*[h[i] for h in held], now[i][:cut]]) for i in range(columns)]
        held = [[c[cut:] for c in now]]
    if held:
        yield [np.concatenate([h[i] for h in held]) for i in range(columns)]


class Golay:
    """Nearby codewords of 23-bit vectors, by syndromes."""

    def __init__(self):
        self.rest = np.zeros(1 << 12, np.int64)  # of the upper 12 bits, divided by the generator
        for i in range(1 << 12):
            r = i << 11
            for bit in range(22, 10, -1):
                if r >> bit & 1:
                    r ^= GOLAY << (bit - 11)
            self.rest[i] = r
        one = [1 << i for i in range(23)]
        errors = [0, *one, *(a | b for i, a in enumerate(one) for b in one[:i]), *(a | b | c for i, a in enumerate(one) for j, b in enumerate(one[:i]) for c in one[:j])]
        errors = np.array(errors, np.int64)
        self.error = np.zeros(1 << 11, np.int64)
        self.error[self.syndrome(errors)] = errors

    def syndrome(self, v: np.ndarray) -> np.ndarray:
        return (v & 0x7FF) ^ self.rest[v >> 11]

    def decode(self, v: np.ndarray) -> np.ndarray:
        """The index (12 bits) of the codeword within 3 bits."""
        return (v ^ self.error[self.syndrome(v)]) >> 11

    def nearby(self, v: np.ndarray) -> np.ndarray:
        """Rows of 6 indices: of the codewords within 4 bits, then -1."""
        found = self.decode(v[:, None] ^ np.concatenate([[0], 1 << np.arange(23)])[None, :])
        found.sort(axis=1)
        found[:, 1:][found[:, 1:] == found[:, :-1]] = -1
        found = -np.sort(-found, axis=1)
        return found[:, :6]


def keys_of(fp: np.ndarray, golay: Golay, fine: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Keys, and the row of ``fp`` that each is of."""
    u = fp.view(np.uint64)
    parts = [((u >> np.uint64(at)) & np.uint64((1 << n) - 1)).astype(np.int64) for at, n in SEGMENTS]
    near = [golay.nearby(p) for p in parts]
    keys, rows = [], []

    def add(kind: int, *factors: np.ndarray) -> None:
        key = np.full((len(u), 1), kind, np.int64)
        good = np.ones((len(u), 1), bool)
        for f, bits in factors:
            key = ((key[:, :, None] << bits) | np.maximum(f, 0)[:, None, :]).reshape(len(u), -1)
            good = (good[:, :, None] & (f >= 0)[:, None, :]).reshape(len(u), -1)
        row, _ = np.nonzero(good)
        keys.append(key[good])
        rows.append(row)

    pairs = [(0, 1), (0, 2), (1, 2)]
    if not fine:
        for kind, (a, b) in enumerate(pairs):
            add(kind, (near[a], 12), (near[b], 12))
    else:  # the two best segments differ by 0 and up to 2 bits, or by 1 each, and then no segment by more than 2
        for kind, (a, b) in enumerate([*pairs, *[(b, a) for a, b in pairs]]):
            add(kind, (parts[a][:, None], 23), (near[b], 12))
        add(6, (near[0], 12), (near[1], 12), (near[2], 12))
    return np.concatenate(keys), np.concatenate(rows)


def links_in_run(fp: np.ndarray, node: np.ndarray, most: int = MOST_BITS) -> list[tuple[int, int]]:
    """A tree of links for every set of fingerprints that are connected within the run."""
    left = np.arange(len(fp))
    links = []
    while len(left):
        reached, left = [left[0]], left[1:]
        while reached and len(left):
            i = reached.pop()
            close = np.bitwise_count(fp[left] ^ fp[i]) <= most
            if close.any():
                links += [(int(node[i]), int(node[j])) for j in left[close]]
                reached += left[close].tolist()
                left = left[~close]
    return links


def _linked(key: np.ndarray, fp: np.ndarray, node: np.ndarray, most: int, small: int = 8) -> np.ndarray:
    """Links within the runs of equal keys."""
    edge = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1], [True]]))
    size = np.diff(edge)
    out = [np.zeros((0, 2), np.int64)]
    keep = np.repeat((size > 1) & (size <= small), size)
    k, f, n = key[keep], fp[keep], node[keep]
    for lag in range(1, small):
        close = (k[lag:] == k[:-lag]) & (np.bitwise_count(f[lag:] ^ f[:-lag]) <= most)
        out.append(np.stack([n[:-lag][close], n[lag:][close]], axis=1))
    for i in np.flatnonzero(size > small):
        found = links_in_run(fp[edge[i] : edge[i + 1]], node[edge[i] : edge[i + 1]], most)
        out.append(np.array(found, np.int64).reshape(-1, 2))
    return np.concatenate(out)


def near_links(nodes: DataFrame, most: int = MOST_BITS) -> DataFrame:
    """(a, b) between the nodes of distinct fingerprints (fp, node) at ``most`` (up to 4) or fewer differing bits: enough of them to connect all."""
    if most > MOST_BITS:
        raise ValueError(f"the keys find up to {MOST_BITS} differing bits")
    fine = nodes.count() > FINE_ABOVE

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        golay = Golay()
        for batch in batches:
            for a in range(0, batch.num_rows, 2048):
                part = batch.slice(a, 2048)
                fp, node = part.column(0).to_numpy(), part.column(1).to_numpy()
                key, row = keys_of(fp, golay, fine)
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(fp[row]), pa.array(node[row])], names=["key", "fp", "node"])

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, fp, node in whole_runs(batches, 3):
            pairs = _linked(key, fp.view(np.uint64), node, most)
            yield pa.RecordBatch.from_arrays([pa.array(pairs.min(axis=1, initial=np.iinfo(np.int64).max)), pa.array(pairs.max(axis=1, initial=np.iinfo(np.int64).min))], names=["a", "b"])

    parts = int(nodes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keys = nodes.select("fp", "node").mapInArrow(keyed, "key long, fp long, node long")
    return keys.repartition(parts, "key").sortWithinPartitions("key", "fp").mapInArrow(link, "a long, b long").distinct()


def text_key(text: Column) -> Column:
    """Tells apart unlike texts of one id; a null text is an empty one."""
    return F.xxhash64(F.coalesce(text.cast("string"), F.lit("")))


def representatives(rows: DataFrame) -> DataFrame:
    """(id, text_key): of the rows (component, id, text_key) of each component the least."""
    least = rows.groupBy("component").agg(F.min(F.struct("id", "text_key")).alias("least"))
    return least.select("least.id", "least.text_key")


def _component_of(rows: DataFrame, most: int) -> DataFrame:
    """(of_fp, component) of every fingerprint in rows (id, fp): the smallest id that links reach."""
    nodes = durable(rows.filter("id IS NOT NULL").groupBy("fp").agg(F.min("id").alias("node")))
    # nodes of several fingerprints of one id are told apart by place, as unlike texts may share an id
    placed = durable(nodes.withColumn("at", F.monotonically_increasing_id()))
    found = components(near_links(placed.select("fp", F.col("at").alias("node")), most))
    of = placed.join(found.withColumnRenamed("node", "member"), F.col("at") == F.col("member"), "left").select("fp", F.col("node").alias("id"), F.coalesce("component", "at").alias("part"))
    of = durable(of)
    least = of.groupBy("part").agg(F.min("id").alias("component"))
    return durable(of.join(least, "part").select(F.col("fp").alias("of_fp"), "component", "part"))


def near_duplicates(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", shingle: int = 4, most: int = MOST_BITS) -> DataFrame:
    """(id, fp, component_id) of every row: the smallest id that is reached by links of ``most`` or fewer differing bits.

    Rows of equal fingerprints are linked.  A null text has no words: fingerprint zero, as an empty
    one.  Rows of a null id are returned with a null component and link nothing; repeated rows are
    returned as often as they come; unlike texts of one id are rows of their own, each linked by its
    text; no rows give no rows.
    """
    rows = fingerprints(docs, id_column, text_column, shingle)
    joined = rows.join(_component_of(rows, most), F.col("fp") == F.col("of_fp"), "left")
    return joined.select("id", "fp", F.when(F.col("id").isNotNull(), F.col("component")).alias("component_id"))


def _connected(one: DataFrame, other: DataFrame) -> DataFrame:
    """(id, text_key, component) of the components that links of either kind connect; both are (id, text_key, component) of the same rows."""
    left, right = one.distinct().withColumnRenamed("component", "part"), other.distinct()
    rows = durable(left.join(right, ["id", "text_key"]))
    parts = rows.select("part", "component").distinct()
    least = parts.groupBy("part").agg(F.min("component").alias("least"), F.count("*").alias("n")).filter("n > 1").drop("n")
    links = parts.join(least, "part").filter("component <> least").select(F.col("component").alias("a"), F.col("least").alias("b"))
    found = components(links).select(F.col("node").alias("of"), F.col("component").alias("whole"))
    joined = rows.join(found, F.col("component") == F.col("of"), "left")
    return joined.select("id", "text_key", F.coalesce("whole", "component").alias("component"))


def drop_near_duplicates(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", shingle: int = 5, most: int = MOST_BITS, similarity: float | None = 0.8, beyond: float | None = None) -> DataFrame:
    """The rows of ``docs`` without all but one of each group of near copies: the one of the smallest id stays.

    With ``similarity``, near copies are texts of that Jaccard similarity of shingles or more, exactly; without, of
    fingerprints of ``most`` or fewer differing bits, and with ``beyond`` also those of that Jaccard similarity or more
    whose fingerprints are farther apart: a group is what links of both kinds connect.

    Rows of a null id are not compared, and stay.  Unlike texts of one id are documents of their
    own; of rows of one id and equal texts (a null text is an empty one) one stays.  No rows give no
    rows; other columns are carried as they are.
    """
    own = docs.select(F.col(f"`{id_column}`").cast("long").alias("id"), F.col(f"`{text_column}`").cast("string").alias("text")).filter("id IS NOT NULL")
    if similarity is None:
        rows = fingerprints(own, "id", "text", shingle, keyed=True)
        groups = rows.join(_component_of(rows, most), F.col("fp") == F.col("of_fp")).select("id", "text_key", F.col("part").alias("component"))
        if beyond is not None:
            release(docs)
            groups = _connected(groups, jaccard_components(own, shingle, beyond))
        found = representatives(groups)
    else:
        found = jaccard_representatives(own, shingle, similarity)
    kept = durable(found.select(F.col("id").alias("__kept_id"), F.col("text_key").alias("__kept_key")))
    marked = docs.withColumn("__at_id", F.col(f"`{id_column}`").cast("long")).withColumn("__at_key", text_key(F.col(f"`{text_column}`")))
    stay = marked.join(kept, (F.col("__at_id") == F.col("__kept_id")) & (F.col("__at_key") == F.col("__kept_key")), "left_semi").dropDuplicates(["__at_id", "__at_key"])
    return docs.filter(F.col(f"`{id_column}`").isNull()).unionByName(stay.drop("__at_id", "__at_key"))
