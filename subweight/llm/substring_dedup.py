"""Substring dedup by level-wise doubling.

Level 0 looks at windows of half the wanted length, and only at the smallest-hashed one within
each wanted window (two equal wanted windows have the same one).  Windows repeated in different
documents are extended, at most to twice their length: a window is a candidate at the next length
only if the repeated windows of the last length cover it.  This ends at the wanted length, where
removal is decided, or, with ``longest=True``, when no candidates survive.

Each level is one exchange of block questions (see ``common``): a block sends its distinct window
hashes, gets a bit for each back.  Hashes at level 0 only choose candidates, so their collisions
cost time, not results; the wanted length is decided by 96 bits.  Beyond it texts are not read
again: a block keeps the hashes of its repeated windows, and a window of twice the length is two of
them end to end.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import QUESTION_ARROW, QUESTION_SCHEMA, Words, arrow_rows, ask, bucket_count, durable, mix, pack, release, split_buckets, to_blocks, unpack, utf8_columns, with_answers

#: Seeds of the window hashes.
SEED_A, SEED_B = 101, 202
#: Stands for a null id: larger than every id, so it makes no other text lose words.
NO_ID = np.iinfo(np.int64).max
#: Bytes of windows of a task beyond the wanted length.
TASK_BYTES = 16_000_000


def levels(min_words: int) -> list[int]:
    """Window lengths up to the decision: half, whole."""
    return [(min_words + 1) // 2, min_words]


def _bits(flags: np.ndarray) -> bytes:
    return np.packbits(flags).tobytes()


def _flags(blob: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(blob, np.uint8), count=n).astype(bool)


def answer_first(keys: list[bytes], several: list[bytes]) -> list[bytes | None]:
    """Level 0: a bit for each 6-byte key that has windows in two documents, of one block or of two."""
    sizes = [len(k) // 6 for k in keys]
    wide = np.zeros((sum(sizes), 8), np.uint8)
    wide[:, :6] = np.frombuffer(b"".join(keys), np.uint8).reshape(-1, 6)
    key = wide.view(np.uint64).ravel()
    flag = np.concatenate([_flags(s, n) for s, n in zip(several, sizes, strict=True)]) if keys else np.zeros(0, bool)
    order = np.argsort(key, kind="stable")
    key = key[order]
    same = key[1:] == key[:-1]
    flag[order[1:][same]] = True
    flag[order[:-1][same]] = True
    if len(key):  # a key that one block has twice is repeated for the others too; they have it in `same` already
        out, at = [], 0
        for n in sizes:
            out.append(_bits(flag[at : at + n]) if flag[at : at + n].any() else None)
            at += n
        return out
    return [None] * len(keys)


def _pack_ids(ids: np.ndarray) -> bytes:
    low = int(ids.min())
    span = ids.astype(np.uint64) - np.uint64(low % (1 << 64))
    width = next(w for w in (1, 2, 4, 8) if w == 8 or int(span.max()) < 1 << (8 * w))
    return low.to_bytes(8, "little", signed=True) + bytes([width]) + span.astype(f"u{width}").tobytes()


def _unpack_ids(blob: bytes) -> np.ndarray:
    low = int.from_bytes(blob[:8], "little", signed=True)
    return (np.frombuffer(blob, f"u{blob[8]}", offset=9).astype(np.uint64) + np.uint64(low % (1 << 64))).astype(np.int64)


def answer_next(keys: list[bytes], extras: list[bytes]) -> list[bytes | None]:
    """Later levels, for each 12-byte key: is it in a document of a smaller id than the block's smallest; is it in two documents."""
    sizes = [len(k) // 12 for k in keys]
    raw = np.frombuffer(b"".join(keys), np.uint8).reshape(-1, 12)
    a = np.ascontiguousarray(raw[:, :8]).view(np.uint64).ravel()
    b = np.ascontiguousarray(raw[:, 8:]).view(np.uint32).ravel()
    low = np.concatenate([_unpack_ids(x[(n + 7) // 8 :]) for x, n in zip(extras, sizes, strict=True)])
    several = np.concatenate([_flags(x[: (n + 7) // 8], n) for x, n in zip(extras, sizes, strict=True)])
    order = np.lexsort((b, a))
    new = np.ones(len(order), bool)
    new[1:] = (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])
    first = np.flatnonzero(new)
    group = np.cumsum(new) - 1
    least = np.minimum.reduceat(low[order], first)[group]
    most = np.maximum.reduceat(low[order], first)[group]
    smaller, repeated = np.empty(len(order), bool), np.empty(len(order), bool)
    smaller[order] = least < low[order]
    repeated[order] = (least < most) | np.logical_or.reduceat(several[order], first)[group]
    out, at = [], 0
    for n in sizes:
        s = slice(at, at + n)
        out.append(_bits(smaller[s]) + _bits(repeated[s]) if repeated[s].any() else None)
        at += n
    return out


class Block:
    """A block's words and, level by level, its candidate windows."""

    def __init__(self, texts: list[bytes | None], ids: np.ndarray, lengths: list[int], buckets: int):
        self.words, self.ids, self.lengths, self.buckets = Words(texts), ids, lengths, buckets
        self.id_of_word = ids[self.words.text] if len(self.words) else np.zeros(0, np.int64)

    def _valid(self, length: int) -> np.ndarray:
        text = self.words.text
        return text[length - 1 :] == text[: len(text) - length + 1] if len(text) >= length else np.zeros(0, bool)

    def first(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Level 0: starts of all wanted windows, their smallest part's hash as an index, those hashes (sorted), several documents or not."""
        half, whole = self.lengths[:2]
        starts = np.flatnonzero(self._valid(whole))
        part = self.words.hashes(half, SEED_A)
        n = len(self._valid(whole))
        low = part[:n].copy()
        for shift in range(1, whole - half + 1):
            np.minimum(low, part[shift : shift + n], out=low)
        return (starts, *self._distinct(low[starts], starts))

    def _distinct(self, key: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        keys, index = np.unique(key, return_inverse=True)
        low, high = self._id_range(index, starts, len(keys))
        return index, keys, low != high

    def _id_range(self, index: np.ndarray, starts: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        order = np.argsort(index, kind="stable")
        ids = self.id_of_word[starts[order]]
        at = np.searchsorted(index[order], np.arange(n))
        return (np.minimum.reduceat(ids, at), np.maximum.reduceat(ids, at)) if n else (ids[:0], ids[:0])

    def later(self, length: int, starts: np.ndarray) -> dict:
        """The candidate windows of this length: index into distinct (a, b) hashes in order, and the smallest id of each here."""
        a, b = self.words.hashes(length, SEED_A)[starts], (self.words.hashes(length, SEED_B)[starts] >> np.uint64(32)).astype(np.uint32)
        order = np.lexsort((b, a))
        new = np.ones(len(order), bool)
        new[1:] = (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])
        index = np.empty(len(order), np.int64)
        index[order] = np.cumsum(new) - 1
        low, high = self._id_range(index, starts, int(new.sum()))
        return {"starts": starts, "index": index, "a": a[order][new], "b": b[order][new], "low": low, "several": low != high}

    def read(self, keys: np.ndarray, answers: dict[int, bytes], parts: int) -> list[np.ndarray]:
        """The flags that came back for sorted distinct keys."""
        out = [np.zeros(len(keys), bool) for _ in range(parts)]
        bounds, buckets = split_buckets(keys, self.buckets)
        for k, bucket in enumerate(buckets):
            blob = answers.get(int(bucket))
            if blob is not None:
                n, size = int(bounds[k + 1] - bounds[k]), (int(bounds[k + 1] - bounds[k]) + 7) // 8
                for p in range(parts):
                    out[p][bounds[k] : bounds[k + 1]] = _flags(blob[p * size : (p + 1) * size], n)
        return out

    def run(self, answers: list[dict[int, bytes]]) -> dict:
        """Replay the levels that have answers; what stands at the next one, or at the end."""
        starts, index, keys, several = self.first()
        if not answers:
            return {"level": 0, "keys": keys, "several": several}
        (repeated,) = self.read(keys, answers[0], 1)
        at = starts[repeated[index]]
        state = self.later(self.lengths[1], at) | {"level": 1}
        if len(answers) == 1:
            return state
        smaller, repeated = self.read(state["a"], answers[1], 2)
        index = state["index"]
        hit = repeated[index] | state["several"][index]
        removed = at[smaller[index] | (self.id_of_word[at] > state["low"][index])]
        return {"level": 2, "removed": removed, "starts": at[hit], "hash": state["a"][index[hit]]}

    def questions(self, block_id: int, state: dict) -> list[tuple]:
        if state["level"] == 0:
            return _first_questions(block_id, 0, state["keys"], state["several"], self.buckets)
        keys = state["a"]
        bounds, buckets = split_buckets(keys, self.buckets)
        rows = []
        for k, bucket in enumerate(buckets):
            s = slice(bounds[k], bounds[k + 1])
            blob = np.hstack([keys[s].view(np.uint8).reshape(-1, 8), state["b"][s].view(np.uint8).reshape(-1, 4)]).tobytes()
            rows.append((int(bucket), 1, block_id, blob, _bits(state["several"][s]) + _pack_ids(state["low"][s])))
        return rows

    def kept(self, removed: np.ndarray, length: int) -> tuple[np.ndarray, list[bytes]]:
        """Removed words of each text, and its kept words joined by one space."""
        n = len(self.words)
        edge = np.bincount(removed, minlength=n + 1)[: n + 1] - np.bincount(removed + length, minlength=n + 1)[: n + 1]
        gone = np.cumsum(edge)[:n] > 0
        lost = np.bincount(self.words.text[gone], minlength=len(self.words.counts))
        out = []
        for normal, first, count, cut in zip(self.words.normal, self.words.first, self.words.counts, lost, strict=True):
            if cut == 0:
                out.append(normal)
            elif cut == count:
                out.append(b"")
            else:
                mask = gone[first : first + count]
                out.append(b" ".join([w for w, g in zip(normal.split(b" "), mask, strict=True) if not g]))
        return lost, out


class Runs:
    """The repeated windows of a block at one length: their starts, texts and hashes; and the longest length so far of each text."""

    def __init__(self, starts: np.ndarray, text: np.ndarray, hashes: np.ndarray, length: int, longest: dict[int, int]):
        self.starts, self.text, self.hashes, self.length = starts, text, hashes, length
        self.longest = longest | dict.fromkeys(np.unique(text).tolist(), length)

    def packed(self) -> tuple[bytes | None, bytes]:
        state = pack(pa.RecordBatch.from_arrays([pa.array(np.diff(self.starts, prepend=0)), pa.array(np.diff(self.text, prepend=0)), pa.array(self.hashes)], names=["starts", "text", "hash"]))
        return state if len(self.starts) else None, np.array([*self.longest.items()], np.int64).reshape(-1, 2).tobytes()

    @classmethod
    def unpacked(cls, state: bytes, longest: bytes, length: int) -> Runs:
        batch = unpack(state)
        return cls(np.cumsum(batch.column(0).to_numpy()), np.cumsum(batch.column(1).to_numpy()), batch.column(2).to_numpy(), length, dict(np.frombuffer(longest, np.int64).reshape(-1, 2).tolist()))

    def doubled(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Windows of twice the length, made of two: the first ones' places and the new hashes, in order of these; where each distinct hash begins, those hashes, and whether two texts here have each."""
        n = len(self.starts)
        at = np.full(int(self.starts[-1]) + self.length + 1, -1, np.int32)
        at[self.starts] = np.arange(n)
        other = at[self.starts + self.length]
        both = np.flatnonzero((other >= 0) & (self.text[other] == self.text))
        hashes = mix(mix(self.hashes[both]) + self.hashes[other[both]])
        order = np.argsort(hashes)
        both, hashes = both[order], hashes[order]
        first = np.flatnonzero(np.concatenate([[True], hashes[1:] != hashes[:-1]])) if len(both) else both
        text = self.text[both]
        several = np.minimum.reduceat(text, first) != np.maximum.reduceat(text, first) if len(both) else np.zeros(0, bool)
        return both, hashes, first, hashes[first], several

    def advanced(self, told: dict[int, bytes], buckets: int) -> Runs:
        """The doubled windows that the answers leave."""
        both, hashes, first, keys, several = self.doubled()
        repeated = several.copy()
        bounds, own = split_buckets(keys, buckets)
        for k, bucket in enumerate(own):
            if int(bucket) in told:
                repeated[bounds[k] : bounds[k + 1]] |= _flags(told[int(bucket)], int(bounds[k + 1] - bounds[k]))
        alive = np.repeat(repeated, np.diff(first, append=len(both)))
        both, hashes = both[alive], hashes[alive]
        order = np.argsort(both)
        both = both[order]
        return Runs(self.starts[both], self.text[both], hashes[order], 2 * self.length, self.longest)


def _first_questions(block_id: int, level: int, keys: np.ndarray, several: np.ndarray, buckets: int) -> list[tuple]:
    """48 bits of each key beside its bucket, and whether two texts of the block have it."""
    rows = []
    bounds, own = split_buckets(keys, buckets)
    for k, bucket in enumerate(own):
        s = slice(bounds[k], bounds[k + 1])
        blob = np.ascontiguousarray((keys[s] >> np.uint64(16)).view(np.uint8).reshape(-1, 8)[:, :6]).tobytes()
        rows.append((int(bucket), level, block_id, blob, _bits(several[s])))
    return rows


def _block(row_payload: bytes, id_column: str, text_column: str, lengths: list[int], buckets: int) -> tuple[pa.RecordBatch, Block]:
    batch = unpack(row_payload)
    ids = batch.column(id_column).cast(pa.int64()).fill_null(int(NO_ID)).to_numpy(zero_copy_only=False)
    return batch, Block(utf8_columns(batch, text_column), ids, lengths, buckets)


def _by_level(answers, levels_so_far: int) -> list[dict[int, bytes]]:
    out: list[dict[int, bytes]] = [{} for _ in range(levels_so_far)]
    for x in answers or []:
        out[x["level"]][x["bucket"]] = x["answer"]
    return out


STATE_SCHEMA = "block_id long, state binary, longest binary"


def longest_repeats(blocks: DataFrame, answers: list[DataFrame], load, min_words: int, buckets: int) -> DataFrame:
    """Answers (level -1, bucket 0) with the longest doubled length of the repeated windows of each text of a block; levels go on until no window is left."""

    def start(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                _, block = load(row["payload"])
                state = block.run(_by_level(row["answers"], 2))
                if len(state["starts"]):
                    packed, longest = Runs(state["starts"], block.words.text[state["starts"]], state["hash"], min_words, {}).packed()
                    yield pa.RecordBatch.from_arrays([pa.array([row["block_id"]], pa.int64()), pa.array([packed], pa.binary()), pa.array([longest], pa.binary())], names=["block_id", "state", "longest"])

    states = durable(with_answers(blocks, answers).mapInArrow(start, STATE_SCHEMA))
    length = min_words
    while True:

        def send(batches: Iterator[pa.RecordBatch], length=length) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    _, _, _, keys, several = Runs.unpacked(row["state"], row["longest"], length).doubled()
                    yield arrow_rows(_first_questions(row["block_id"], 0, keys, several, buckets), QUESTION_ARROW)

        def advance(batches: Iterator[pa.RecordBatch], length=length) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    state, longest = row["state"], row["longest"]
                    if state is not None:
                        state, longest = Runs.unpacked(state, longest, length).advanced({x["bucket"]: x["answer"] for x in row["answers"] or []}, buckets).packed()
                    yield pa.RecordBatch.from_arrays([pa.array([row["block_id"]], pa.int64()), pa.array([state], pa.binary()), pa.array([longest], pa.binary())], names=["block_id", "state", "longest"])

        # windows get fewer with each level, and many tiny tasks would only start many workers
        held = states.agg(F.sum(F.length("state"))).first()[0] or 0
        tasks = max(states.sparkSession.sparkContext.defaultParallelism, held // TASK_BYTES)
        told = ask(states.filter("state IS NOT NULL").coalesce(tasks).mapInArrow(send, QUESTION_SCHEMA), answer_first, tasks)
        if told.isEmpty():
            break
        states = durable(with_answers(states, [told]).coalesce(tasks).mapInArrow(advance, STATE_SCHEMA))
        release(states)
        length *= 2
    return states.select("block_id", F.lit(-1).alias("level"), F.lit(0).alias("bucket"), F.col("longest").alias("answer"))


def remove_repeats(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", min_words: int = 13, longest: bool = False, stats: bool = True) -> DataFrame:
    """Remove every word that a window of ``min_words`` words covers whose words also start in a row of a smaller id.

    Returns the columns of ``docs`` with the kept words, joined by one space, as text (rows that lose
    nothing keep their text as it is) and, with ``stats``, n_words, n_removed and kept_text (in place
    of columns of these names), with ``longest`` also longest_repeat: of the lengths min_words,
    doubled again and again, the largest with a window of the row that another row has too (0: none).

    A null text has no words and stays null (kept_text: empty); shorter texts than a window are kept
    whole; rows of one id do not remove each other's words (beyond min_words the longest repeat takes
    them for other rows); a row with a null id loses words to rows with ids and takes none; no rows give no rows.  A long text is worked on whole, in one task.
    """
    added = ["n_words", "n_removed", "kept_text", *(["longest_repeat"] if longest else [])] if stats else []
    docs = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c not in added])
    blocks = to_blocks(docs, text_column)
    buckets = bucket_count(blocks)
    lengths = levels(min_words)
    load = lambda payload: _block(payload, id_column, text_column, lengths, buckets)
    answers: list[DataFrame] = []
    for level in range(len(lengths)):

        def send(batches: Iterator[pa.RecordBatch], level=level) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    _, block = load(row["payload"])
                    yield arrow_rows(block.questions(row["block_id"], block.run(_by_level(row["answers"], level))), QUESTION_ARROW)

        answers.append(ask(with_answers(blocks, answers).mapInArrow(send, QUESTION_SCHEMA), answer_first if level == 0 else answer_next))
        release(docs)
    told = [*answers, *([longest_repeats(blocks, answers, load, min_words, buckets)] if longest else [])]

    long = T.LongType()
    schema = T.StructType([*docs.schema.fields, *[T.StructField(c, T.StringType() if c == "kept_text" else long) for c in added]])
    names = schema.fieldNames()
    text_at = names.index(text_column)

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                rows, block = load(row["payload"])
                state = block.run(_by_level([x for x in row["answers"] or [] if x["level"] >= 0], len(lengths)))
                lost, kept = block.kept(state["removed"], min_words)
                old = rows.column(text_at)
                changed = pa.array([k if n else None for k, n in zip(kept, lost, strict=True)], pa.binary()).cast(old.type)
                columns = list(rows.columns)
                columns[text_at] = pc.coalesce(changed, old)
                if added:
                    columns += [pa.array(block.words.counts), pa.array(lost, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())]
                if added and longest:
                    most = np.zeros(len(lost), np.int64)
                    for x in row["answers"] or []:
                        if x["level"] < 0:
                            text, value = np.frombuffer(x["answer"], np.int64).reshape(-1, 2).T
                            most[text] = value
                    columns.append(pa.array(most))
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return with_answers(blocks, told).mapInArrow(finish, schema)
