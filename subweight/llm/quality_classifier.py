"""Quality classifier: random-indexing word vectors, pooled for each document, and a two-layer network.

Words are hashed to a fixed number of buckets.  Each bucket has a sparse random index vector; its
context vector is the sum of the index vectors of the words up to two places away, over the whole
corpus.  A document pools mean and spread of the normalised vectors of its words, the mean index
vector of the kinds of characters in them, and the likeness of index vectors a few places apart
(how often words repeat).  The network is trained on a bounded sample of labelled documents and a
temperature is fitted on a part of it that was kept aside.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Words

#: Buckets of words, size of a vector, non-zero entries of an index vector, words to each side, lags of likeness.
BUCKETS, SIZE, ENTRIES, REACH, LAGS = 1 << 14, 32, 4, 2, 4
#: Most labelled documents that the network is trained on (a bound of the sample, about).
MOST_LABELLED = 20_000
HIDDEN, EPOCHS, BATCH, RATE, DECAY = 32, 40, 128, 3e-3, 1e-4
SEED = 11
#: A document is kept if its score is at least this.
THRESHOLD = 0.3
#: Text bytes, and rows, worked on at a time.
STEP_BYTES, STEP_ROWS = 1_000_000, 1024

_KINDS = (b"abcdefghijklmnopqrstuvwxyz" + bytes(range(128, 256)), b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".,;:", b"!?", b"#*$%&|<>", b"'\"()-/")


def index_vectors(n: int, seed: int) -> np.ndarray:
    """Sparse ternary vectors: ENTRIES of SIZE entries are 1 or -1."""
    rng = np.random.Generator(np.random.PCG64(seed))
    out = np.zeros((n, SIZE), np.float32)
    places = rng.random((n, SIZE)).argsort(axis=1)[:, :ENTRIES]
    np.put_along_axis(out, places, rng.choice(np.array([-1, 1], np.float32), (n, ENTRIES)), axis=1)
    return out


def _kind_of_byte() -> np.ndarray:
    out = np.full(256, 1 << len(_KINDS), np.uint8)
    out[32] = 0
    for i, members in enumerate(_KINDS):
        out[np.frombuffer(members, np.uint8)] = 1 << i
    return out


def _slices(texts: list[bytes | None]) -> Iterator[tuple[int, int]]:
    start, held = 0, 0
    for i, t in enumerate(texts):
        if i > start and held + len(t or b"") > STEP_BYTES:
            yield start, i
            start, held = i, 0
        held += len(t or b"")
    if start < len(texts):
        yield start, len(texts)


def context_sums(texts: list[bytes | None], index: np.ndarray, step: int = 1 << 15) -> np.ndarray:
    """(BUCKETS, SIZE) sums of the index vectors of near words, of these texts."""
    total = np.zeros((BUCKETS, SIZE), np.float64)
    words = Words(texts)
    bucket = (words.hashes(1, SEED) >> np.uint64(64 - 14)).astype(np.int64)
    for a in range(0, len(bucket), step):
        low, high = max(0, a - REACH), min(len(bucket), a + step + REACH)
        near, text = index[bucket[low:high]], words.text[low:high]
        around = np.zeros_like(near)
        for d in range(1, REACH + 1):
            same = (text[d:] == text[:-d])[:, None]
            around[d:] += near[:-d] * same
            around[:-d] += near[d:] * same
        own = slice(a - low, min(a + step, len(bucket)) - low)
        b, c = bucket[low:high][own], around[own]
        order = np.argsort(b, kind="stable")
        first = np.flatnonzero(np.diff(b[order], prepend=-1))
        total[b[order][first]] += np.add.reduceat(c[order], first, axis=0)
    return total


def word_vectors(docs: DataFrame, text_column: str = "text") -> np.ndarray:
    """Normalised context vectors (BUCKETS, SIZE) of the words of all rows; sums are added on executors, what is gathered has a fixed size."""
    fields = ", ".join(f"v{i} double" for i in range(SIZE))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, total = index_vectors(BUCKETS, SEED), np.zeros((BUCKETS, SIZE), np.float64)
        for batch in batches:
            for start in range(0, batch.num_rows, STEP_ROWS):
                texts = batch.column(0).slice(start, STEP_ROWS).cast(pa.binary()).to_pylist()
                for a, b in _slices(texts):
                    total += context_sums(texts[a:b], index)
        rows = np.flatnonzero(np.abs(total).sum(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(rows, pa.int32()), *[pa.array(total[rows, i]) for i in range(SIZE)]], names=["bucket", *[f"v{i}" for i in range(SIZE)]])

    parts = docs.select(F.col(text_column).cast("string").alias("text")).mapInArrow(run, f"bucket int, {fields}")
    sums = parts.groupBy("bucket").agg(*[F.sum(f"v{i}").alias(f"v{i}") for i in range(SIZE)]).toArrow()
    out = np.zeros((BUCKETS, SIZE), np.float32)
    at = sums.column("bucket").to_numpy()
    for i in range(SIZE):
        out[at, i] = sums.column(f"v{i}").to_numpy()
    return out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)


def features(texts: list[bytes | None], vectors: np.ndarray, index: np.ndarray, kinds: np.ndarray, step: int = 1 << 16) -> np.ndarray:
    """(texts, 3 * SIZE + LAGS + 1) pooled features; zeros without words."""
    words = Words(texts)
    n = np.maximum(words.counts, 1)[:, None].astype(np.float64)
    sums = np.zeros((len(texts), 3 * SIZE + LAGS))
    if len(words):
        bucket = (words.hashes(1, SEED) >> np.uint64(64 - 14)).astype(np.int64)
        of_byte = _kind_of_byte()
        for a in range(0, len(words), step):
            b = min(a + step, len(words))
            low = int(words.starts[a])
            mask = np.bitwise_or.reduceat(of_byte[np.frombuffer(words.buffer, np.uint8)[low : int(words.ends[b - 1])]], words.starts[a:b] - low)
            v, text = vectors[bucket[a:b]], words.text[a:b]
            own = np.zeros((b - a, LAGS), np.float32)
            for lag in range(1, LAGS + 1):
                s = max(a, lag)
                if s < b:
                    near = (index[bucket[s:b]] * index[bucket[s - lag : b - lag]]).sum(axis=1) / ENTRIES
                    own[s - a :, lag - 1] = near * (words.text[s:b] == words.text[s - lag : b - lag])
            rows = np.concatenate([v, v * v, kinds[mask], own], axis=1)
            first = np.flatnonzero(np.diff(text, prepend=-1))
            sums[text[first]] += np.add.reduceat(rows, first, axis=0)
    pooled = sums / n
    pooled[:, SIZE : 2 * SIZE] = np.sqrt(np.maximum(pooled[:, SIZE : 2 * SIZE] - pooled[:, :SIZE] ** 2, 0))
    return np.concatenate([pooled, np.log1p(words.counts)[:, None]], axis=1)


@dataclass
class Network:
    """Two layers, standardised input, calibrated output."""

    shift: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def arrays(self) -> tuple:
        """What executors get: arrays and numbers only, as they may lack this class."""
        return self.shift, self.scale, self.w1, self.b1, self.w2, self.b2, self.temperature

    def logits(self, x: np.ndarray) -> np.ndarray:
        return logits_of(x, *self.arrays()[:-1])

    def score(self, x: np.ndarray) -> np.ndarray:
        return score_of(x, *self.arrays())


def logits_of(x: np.ndarray, shift: np.ndarray, scale: np.ndarray, w1: np.ndarray, b1: np.ndarray, w2: np.ndarray, b2: float) -> np.ndarray:
    return np.tanh((x - shift) / scale @ w1 + b1) @ w2 + b2


def score_of(x: np.ndarray, *network) -> np.ndarray:
    """From 0 to 1, by the arrays of a network."""
    return 1 / (1 + np.exp(-np.clip(logits_of(x, *network[:-1]) / network[-1], -40, 40)))


def train(x: np.ndarray, y: np.ndarray, seed: int = SEED) -> Network:
    """Fit by minibatches with adaptive steps on four fifths of the rows, the temperature on the rest; without both labels a constant."""
    rng = np.random.default_rng(seed)
    shift, scale = x.mean(axis=0) if len(x) else np.zeros(x.shape[1]), x.std(axis=0) + 1e-6 if len(x) else np.ones(x.shape[1])
    share = (y.sum() + 1) / (len(y) + 2)
    net = Network(shift, scale, rng.normal(0, x.shape[1] ** -0.5, (x.shape[1], HIDDEN)), np.zeros(HIDDEN), np.zeros(HIDDEN), float(np.log(share / (1 - share))))
    if len(np.unique(y)) < 2:
        return net
    order = rng.permutation(len(x))
    held, kept = order[: len(x) // 5], order[len(x) // 5 :]
    z = (x - shift) / scale
    parameters = [net.w1, net.b1, net.w2, np.array([net.b2])]
    first, second, t = [np.zeros_like(p) for p in parameters], [np.zeros_like(p) for p in parameters], 0
    for _ in range(EPOCHS):
        rng.shuffle(kept)
        for a in range(0, len(kept), BATCH):
            rows = kept[a : a + BATCH]
            h = np.tanh(z[rows] @ parameters[0] + parameters[1])
            p = 1 / (1 + np.exp(-np.clip(h @ parameters[2] + parameters[3], -40, 40)))
            d = (p - y[rows]) / len(rows)
            back = np.outer(d, parameters[2]) * (1 - h * h)
            slopes = [z[rows].T @ back + DECAY * parameters[0], back.sum(axis=0), h.T @ d + DECAY * parameters[2], np.array([d.sum()])]
            t += 1
            for i, g in enumerate(slopes):
                first[i] = 0.9 * first[i] + 0.1 * g
                second[i] = 0.999 * second[i] + 0.001 * g * g
                parameters[i] -= RATE * (first[i] / (1 - 0.9**t)) / (np.sqrt(second[i] / (1 - 0.999**t)) + 1e-8)
    net.w1, net.b1, net.w2, net.b2 = parameters[0], parameters[1], parameters[2], float(parameters[3][0])
    logit = net.logits(x[held])

    def loss(temperature: float) -> float:
        return float(np.logaddexp(0, -np.where(y[held] == 1, 1, -1) * logit / temperature).mean())

    net.temperature = min(np.geomspace(0.25, 8, 61), key=loss) if len(held) >= 20 else 1.0
    return net


@dataclass
class Model:
    vectors: np.ndarray
    network: Network


def held_out(id_column: str = "doc_id", fold: int = 0):
    return F.pmod(F.crc32(F.col(id_column).cast("string").cast("binary")), F.lit(5)) == fold


def _features_of(rows: DataFrame, vectors: np.ndarray, network: Network | None, name: str, text_column: str = "text", keep: bool = False) -> DataFrame:
    """``rows`` with features (an array) or the score of the text as the last column; the text itself is kept or not."""
    at = rows.columns.index(text_column)
    gone = -1 if keep else at
    sent = rows.sparkSession.sparkContext.broadcast((vectors, network.arrays() if network else None))  # 2 MB, whatever the data
    kind = T.DoubleType() if network else T.ArrayType(T.DoubleType())
    schema = T.StructType([*(f for i, f in enumerate(rows.schema.fields) if i != gone), T.StructField(name, kind)])
    names = schema.fieldNames()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vectors, network = sent.value
        index, kinds = index_vectors(BUCKETS, SEED), index_vectors(256, SEED + 1)
        for batch in batches:
            for start in range(0, batch.num_rows, STEP_ROWS):
                rows = batch.slice(start, STEP_ROWS)
                texts = rows.column(at).cast(pa.binary()).to_pylist()
                for a, b in _slices(texts):
                    x = features(texts[a:b], vectors, index, kinds)
                    values = pa.array(score_of(x, *network)) if network else pa.array(x.tolist(), pa.list_(pa.float64()))
                    kept = rows.slice(a, b - a).columns
                    yield pa.RecordBatch.from_arrays([*(c for i, c in enumerate(kept) if i != gone), values], names=names)

    return rows.mapInArrow(run, schema)


def fit(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED, id_column: str = "doc_id", text_column: str = "text", label_column: str = "quality") -> Model:
    """Word vectors of all ``docs``; the network from at most about ``most`` labelled rows whose id's crc32 is not 0 modulo 5, picked by a hash of the id."""
    own = labels.filter(~held_out(id_column) & F.col(label_column).isin(0, 1)).select(F.col(id_column).alias("__id"), F.col(label_column).cast("int").alias("label"))
    n = own.count()
    if n > most:
        own = own.filter(F.pmod(F.xxhash64("__id"), F.lit(1_000_000)) < int(1_000_000 * most / n))
    vectors = word_vectors(docs, text_column)
    joined = docs.select(F.col(id_column).alias("id"), F.col(text_column).cast("string").alias("text")).join(F.broadcast(own), F.col("id") == F.col("__id"))  # the sample is bounded
    got = _features_of(joined.select("id", "label", "text"), vectors, None, "x").orderBy("id").toArrow()
    x = np.array(got.column("x").to_pylist(), np.float64).reshape(-1, 3 * SIZE + LAGS + 1)
    return Model(vectors, train(x, got.column("label").to_numpy().astype(np.float64)))


def score(docs: DataFrame, model: Model, text_column: str = "text", score_column: str = "score") -> DataFrame:
    """``docs`` and a score from 0 to 1 (higher: quality 1 is likelier), from the text alone.

    A null text is scored as an empty one; a column of the score's name is replaced; repeated rows
    are scored as often as they come; without both labels all scores are the share of label 1; no
    rows give no rows.
    """
    names = [c for c in docs.columns if c != score_column]
    return _features_of(docs.select(*[F.col(f"`{c}`") for c in names]), model.vectors, model.network, score_column, text_column, keep=True)


def keep_by_score(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` with a score of at least ``threshold``, with all their columns."""
    name = "__score"
    while name in docs.columns:
        name += "_"
    return score(docs, model, score_column=name).filter(F.col(name) >= threshold).drop(name)
