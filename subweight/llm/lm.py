"""Hashed maximum-entropy language model with a class-factored softmax, and exact unigram counts.

The text is a row of tokens: its words in lower case (A-Z), then one end.  Every token has a *cell*,
a hash of a short word or of a longer word's last bytes; 16 classes have 32 cells each.  The model
gives P(class | context), P(cell | class, context) and P(token | cell): the first two are softmaxes
over hashed features of the context, the last comes from the counts of the training tokens of the cell.
Features are of two kinds.  Dense ones, in tables of a fixed size, are of the cells before: the last
one, the one before that alone (a skip), and a constant.  Sparse ones are of the words themselves: the
last two words together with a class, or with a cell, that came after them in training; their table
has a row for each that was seen and grows with the corpus.

Counts: every block sends its distinct words with their counts to buckets and gets back the totals.
Dense training: in each round every task takes the weights as they are, makes gradient steps over the
training texts of its own blocks, and sends the changed rows; rows are averaged by how often they
were used.  Each round has other blocks, and the rounds together have all of them.  Sparse training:
every block sends its distinct (two words, cell) with their counts to buckets; a bucket has all that
came after its word pairs, and as their dense features are the same in every place, it makes the
gradient steps of their sparse weights over the whole corpus at once, and answers each block with
what the weights add to the log-probabilities.  Scoring adds both; the dense
chances of all contexts, a table of a fixed size, are broadcast.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import QUESTION_ARROW, QUESTION_SCHEMA, Words, arrow_rows, ask, bucket_count, mix, release, split_buckets, to_blocks, unpack, with_answers

CLASSES, MEMBERS = 16, 32
CELLS = CLASSES * MEMBERS
END, START = CELLS - 1, CELLS
#: Longest word, in bytes, with a cell by its whole hash.
SHORT = 4
#: Rows of the hashed tables for classes and for members.
CLASS_ROWS, MEMBER_ROWS = 1 << 12, 1 << 14
#: Rounds, tokens of a gradient step, rate of the steps; tokens scored at a time.
ROUNDS, BATCH, RATE, STEP = 3, 8192, 0.15, 1 << 19
#: Fewest training tokens after a pair of words that has sparse weights; the weight of their squares; their gradient steps, and the longest one.
LEAST_SEEN, RIDGE, PAIR_STEPS, LONGEST_STEP = 2, 0.25, 12, 1.0
#: Rows of a segment up to which they are added without reduceat, which is slow on short segments.
FEW = 8
#: What the squares of gradients start from: larger, and rarely used weights move less.
DAMPING = 0.01
#: Stands for the ends of texts among the words of a block, in a question of its own level; no word has a newline.
END_WORD, ENDS = b"\n", 2
SEED = 77
WIDTH = max(CLASSES, MEMBERS)


def held_out(id_column: str = "doc_id", fold: int = 1) -> Column:
    return F.pmod(F.crc32(F.col(id_column).cast("string").cast("binary")), F.lit(5)) == fold


def cells_of(words: Words, hashes: np.ndarray) -> np.ndarray:
    """The cell of every word."""
    if not len(words):
        return np.zeros(0, np.int64)
    data = np.frombuffer(words.buffer, np.uint8)
    size = words.ends - words.starts
    tail = data[words.ends - 1].astype(np.uint64)
    for back in (2, 3):
        tail = tail << np.uint64(8) | data[np.maximum(words.ends - back, 0)].astype(np.uint64)
    by_tail = (mix(tail) % np.uint64(CELLS // 2 - 1)).astype(np.int64) + CELLS // 2
    return np.where(size <= SHORT, (hashes >> np.uint64(56)).astype(np.int64) % (CELLS // 2), by_tail)


class Tokens:
    """The tokens of several texts: words and, after each text, its end."""

    def __init__(self, texts: list[bytes | None]):
        self.words = Words([t.lower() if t else b"" for t in texts])
        self.hashes = self.words.hashes(1, SEED)
        self.at = np.arange(len(self.words)) + self.words.text  # of a word, among the tokens
        self.counts = self.words.counts + 1
        self.text = np.repeat(np.arange(len(texts)), self.counts)
        self.cells = np.full(len(self.text), END)
        self.cells[self.at] = cells_of(self.words, self.hashes)

    def contexts(self) -> np.ndarray:
        """The two cells before every token, as one number."""
        before = np.full((2, len(self.cells)), START)
        for d in (1, 2):
            same = self.text[d:] == self.text[:-d]
            before[d - 1, d:][same] = self.cells[:-d][same]
        return before[0] * (CELLS + 1) + before[1]

    def pairs(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Distinct (two words before, cell): 64-bit keys in order, each token's place among them, and the keys' contexts and cells."""
        words = np.zeros(len(self.text), np.uint64)
        words[self.at] = self.hashes
        before = np.zeros((2, len(words)), np.uint64)  # 0: the start
        for d in (1, 2):
            same = self.text[d:] == self.text[:-d]
            before[d - 1, d:][same] = words[:-d][same]
        both = mix(before[0] + mix(before[1] + np.uint64(1)))
        token = both >> np.uint64(9) << np.uint64(9) | self.cells.astype(np.uint64)
        order = np.argsort(token)
        placed = token[order]
        new = np.ones(len(placed), bool)
        new[1:] = placed[1:] != placed[:-1]
        keys, first, index = placed[new], order[new], np.empty(len(token), np.int64)
        index[order] = np.cumsum(new) - 1
        return keys, index, self.contexts()[first], self.cells[first]


def _ranked(values: np.ndarray, below: int) -> tuple[np.ndarray, np.ndarray]:
    """The distinct values, in order, and each value's place among them; by marking, as values are under a known bound."""
    there = np.zeros(below, bool)
    there[values] = True
    place = np.cumsum(there, dtype=np.int32) - 1
    return np.flatnonzero(there), place[values]


def _features(context: np.ndarray) -> np.ndarray:
    """Hashes of the dense features of contexts: the cell before, and the one before that alone; both together are left to the sparse features of the words."""
    one, two = np.divmod(context.astype(np.uint64), np.uint64(CELLS + 1))
    return mix(np.stack([one + np.uint64(1 << 20), two + np.uint64(2 << 20)], axis=1))


def _softmax(x: np.ndarray) -> np.ndarray:
    x -= x.max(axis=1, keepdims=True)
    np.exp(x, out=x)
    x /= (x @ np.ones(x.shape[1], x.dtype))[:, None]
    return x


def _sums(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sums of the rows of each segment; most segments have few rows, which are added turn by turn in the order that reduceat has."""
    size = np.diff(first, append=len(values))
    out = values[first]
    few = np.flatnonzero((size > 1) & (size <= FEW))
    if len(few):
        few = few[np.argsort(-size[few], kind="stable")]  # the longest first
        at, n = first[few], size[few]
        rest = values[at + 1]
        for turn in range(2, int(n[0])):
            k = np.searchsorted(-n, -turn)
            rest[:k] += values[at[:k] + turn]
        out[few] += rest
    many = size > FEW
    if many.any():
        starts = np.cumsum(size[many]) - size[many]
        out[many] = np.add.reduceat(values[np.repeat(many, size)], starts, axis=0)
    return out


def _class_rows(mixed: np.ndarray) -> np.ndarray:
    return (mixed % np.uint64(CLASS_ROWS)).astype(np.uint16)


def _member_rows(mixed: np.ndarray, classes: np.ndarray) -> np.ndarray:
    return (mix(mixed + classes.astype(np.uint64)[:, None]) % np.uint64(MEMBER_ROWS)).astype(np.uint16)


def new_weights(of_cell: np.ndarray) -> list[np.ndarray]:
    """Tables of class and member weights; after the hashed rows, the constants: one row, and one for each class, that give the cells their training shares."""
    members = of_cell[0].reshape(CLASSES, MEMBERS) + 0.5
    return [np.concatenate([np.zeros((rows, part.shape[1])), np.log(part / part.sum(axis=1, keepdims=True))]).astype(np.float32) for rows, part in ((CLASS_ROWS, members.sum(axis=1)[None]), (MEMBER_ROWS, members))]


def _logits(table: np.ndarray, rows: np.ndarray, constant: np.ndarray) -> np.ndarray:
    x = table[constant]
    for j in range(rows.shape[1]):
        x += table[rows[:, j]]
    return x


def _rows() -> np.ndarray:
    """Rows of the two features of every cell before (CELLS + 1, 2): for the softmax of classes, then for those of each class's members."""
    cells = np.arange(CELLS + 1)
    mixed = _features(cells * (CELLS + 1) + cells)
    return np.stack([_class_rows(mixed), *[_member_rows(mixed, np.full(len(cells), k)) for k in range(CLASSES)]])


def chance_tables(weights: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each softmax: the weights of the last cell, those of the cell before it with the constant, and the log normaliser of every context.

    A target's weight in a context is a sum over the two cells, so its exponential is a product, and
    the normalisers of all contexts are one product of matrices.  20 MB, whatever the data.
    """
    left, right, normal = [], [], []
    for g, rows in enumerate(_rows()):
        table, constant = (weights[1], MEMBER_ROWS + g - 1) if g else (weights[0], CLASS_ROWS)
        one, two = table[rows[:, 0]].astype(np.float64), table[rows[:, 1]].astype(np.float64) + table[constant]
        tops = one.max(axis=1, keepdims=True), two.max(axis=1, keepdims=True)
        product = np.exp(one - tops[0]) @ np.exp(two - tops[1]).T
        normal.append((np.log(np.maximum(product, 1e-300)) + tops[0] + tops[1].T).ravel())
        gap = ((0, 0), (0, WIDTH - table.shape[1]))
        left.append(np.pad(one, gap))
        right.append(np.pad(two, gap))
    return tuple(np.stack(x).astype(np.float32) for x in (left, right, normal))


def log_chances(tables: tuple[np.ndarray, np.ndarray, np.ndarray], of: np.ndarray | int, context: np.ndarray, target: np.ndarray) -> np.ndarray:
    """Natural logs of the chances of targets by the softmaxes ``of`` (0: classes; 1 + k: members of class k)."""
    left, right, normal = tables
    one, two = np.divmod(context, CELLS + 1)
    out = left[of, one, target]
    out += right[of, two, target]
    out -= normal[of, context]
    return np.maximum(out, np.float32(np.log(1e-30)))


def log_cells(tokens: Tokens, weights: list[np.ndarray]) -> np.ndarray:
    """Natural log of P(cell | context) of every token."""
    return log_by_tables(tokens, chance_tables(weights))


def log_by_tables(tokens: Tokens, tables: tuple[np.ndarray, np.ndarray, np.ndarray]) -> np.ndarray:
    """The same, by ``chance_tables`` that many blocks share."""
    context = tokens.contexts()
    out = np.zeros(len(context))
    for a in range(0, len(out), STEP):
        s = slice(a, a + STEP)
        kind, member = np.divmod(tokens.cells[s], MEMBERS)
        out[s] = log_chances(tables, 0, context[s], kind).astype(np.float64) + log_chances(tables, 1 + kind, context[s], member)
    return out


class Trainer:
    """Gradient steps of one task, with steps that shrink by what each weight has moved.

    Tokens of a batch with the same context have the same probabilities, so a step works on distinct
    contexts with counts.
    """

    def __init__(self, weights: list[np.ndarray]):
        self.weights = [w.copy() for w in weights]
        self.squares = [np.full(w.shape, DAMPING, np.float32) for w in weights]
        self.used = [np.zeros(len(w), np.int64) for w in weights]

    def _move(self, t: int, rows: np.ndarray, g: np.ndarray, n: np.ndarray) -> None:
        g = g * (1 / np.sqrt(n)).astype(np.float32)[:, None]
        square = self.squares[t][rows]
        square += g * g
        self.squares[t][rows] = square
        np.sqrt(square, out=square)
        g /= square
        g *= np.float32(RATE)
        self.weights[t][rows] -= g
        self.used[t][rows] += n

    def _step(self, t: int, rows: np.ndarray, constant: np.ndarray, index: np.ndarray, target: np.ndarray) -> None:
        """Contexts come sorted by class, so that those of one constant stand together."""
        size = self.weights[t].shape[1]
        g = _softmax(_logits(self.weights[t], rows, constant))
        n = np.bincount(index, minlength=len(rows))
        g *= n[:, None].astype(np.float32)
        np.subtract.at(g.ravel(), index * size + target, np.float32(1))
        edges = np.flatnonzero(np.concatenate([[True], constant[1:] != constant[:-1]]))
        ends = np.append(edges[1:], len(constant))
        self._move(t, constant[edges], np.stack([g[x:y].sum(axis=0) for x, y in zip(edges, ends, strict=True)]), np.add.reduceat(n, edges))
        for own in rows.T:
            first = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
            if len(first) > len(own) // 2 or len(np.unique(own[first])) < len(first):  # equal rows stand apart
                order = np.argsort(own, kind="stable")
                placed, gs, ns = own[order], g[order], n[order]
                first = np.flatnonzero(np.concatenate([[True], placed[1:] != placed[:-1]]))
            else:
                placed, gs, ns = own, g, n
            self._move(t, placed[first].astype(np.int64), _sums(gs, first), np.add.reduceat(ns, first))

    def learn(self, tokens: Tokens) -> None:
        context = tokens.contexts()
        for a in range(0, len(context), BATCH):
            s = slice(a, a + BATCH)
            kind, member = np.divmod(tokens.cells[s], MEMBERS)
            distinct, index = _ranked(context[s], (CELLS + 1) ** 2)
            mixed = _features(distinct)
            self._step(0, _class_rows(mixed), np.full(len(distinct), CLASS_ROWS), index, kind)
            pairs, at = _ranked(kind * len(distinct) + index, CLASSES * len(distinct))
            own, of = np.divmod(pairs, len(distinct))
            self._step(1, _member_rows(mixed[of], own), MEMBER_ROWS + own, at, member)


def _block(payload: bytes) -> tuple[np.ndarray, np.ndarray, list[bytes | None]]:
    batch = unpack(payload)
    return batch.column("id"), batch.column("held").to_numpy(zero_copy_only=False), batch.column("text").cast(pa.binary()).to_pylist()


def train(blocks: DataFrame, of_cell: np.ndarray, rounds: int = ROUNDS) -> list[np.ndarray]:
    """Weights after all rounds over the training texts of all blocks."""
    weights = new_weights(of_cell)
    fields = ", ".join(f"d{i} float" for i in range(WIDTH))
    names = ["t", "row", "n", *[f"d{i}" for i in range(WIDTH)]]
    for turn in range(rounds):
        sent = blocks.sparkSession.sparkContext.broadcast(weights)  # 2.3 MB, whatever the data

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            trainer = Trainer(sent.value)
            for batch in batches:
                for payload in batch.column(0).to_pylist():
                    _, held, texts = _block(payload)
                    trainer.learn(Tokens([t for t, h in zip(texts, held, strict=True) if not h]))
            for t, (old, new, used) in enumerate(zip(sent.value, trainer.weights, trainer.used, strict=True)):
                row = np.flatnonzero(used)
                moved = np.zeros((len(row), WIDTH), np.float32)
                moved[:, : old.shape[1]] = (new[row] - old[row]) * used[row, None]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(row), t, np.int32)), pa.array(row, pa.int32()), pa.array(used[row]), *[pa.array(moved[:, i]) for i in range(WIDTH)]], names=names)

        part = blocks.filter(F.pmod(F.xxhash64("block_id"), F.lit(rounds)) == turn).select("payload")
        sums = part.mapInArrow(run, f"t int, row int, n long, {fields}").groupBy("t", "row").agg(F.sum("n").alias("n"), *[F.sum(f"d{i}").alias(f"d{i}") for i in range(WIDTH)]).toArrow()
        t, row, n = (sums.column(c).to_numpy() for c in ("t", "row", "n"))
        for k, table in enumerate(weights):
            own = t == k
            for i in range(table.shape[1]):
                table[row[own], i] += (sums.column(f"d{i}").to_numpy()[own] / n[own]).astype(np.float32)
        sent.unpersist()
    return weights


def _small(values: np.ndarray) -> bytes:
    width = next(w for w in (1, 2, 4, 8) if w == 8 or int(values.max(initial=0)) < 1 << (8 * w))
    return bytes([width]) + values.astype(f"u{width}").tobytes()


def _large(blob: bytes) -> np.ndarray:
    return np.frombuffer(blob, f"u{blob[0]}", offset=1).astype(np.int64)


def _distinct(tokens: Tokens) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes of the distinct words, and each word's place among them."""
    return np.unique(tokens.hashes, return_inverse=True)


def _spelt(tokens: Tokens, n: int, index: np.ndarray) -> list[bytes]:
    """The distinct words, in the order of their hashes."""
    w, at = tokens.words, np.empty(n, np.int64)
    at[index] = np.arange(len(index))
    return [w.buffer[s:e] for s, e in zip(w.starts[at].tolist(), w.ends[at].tolist(), strict=True)]


def answer_counts(keys: list[bytes], extras: list[bytes]) -> tuple[list[bytes], bytes]:
    """Totals for each block's words; and, of the bucket, the training tokens and distinct training words of each cell."""
    total: dict[bytes, int] = {}
    words = [k.split(b" ") for k in keys]
    for own, extra in zip(words, extras, strict=True):
        for w, n in zip(own, _large(extra).tolist(), strict=True):
            total[w] = total.get(w, 0) + n
    told = [_small(np.array([total[w] for w in own], np.int64)) for own in words]
    ends = total.pop(END_WORD, 0)
    known = [(w, n) for w, n in total.items() if n]
    line = Words([b" ".join([w for w, _ in known])])
    cell = cells_of(line, line.hashes(1, SEED))
    counts = np.array([n for _, n in known], np.float64)
    of_cell = np.stack([np.bincount(cell, counts, CELLS).astype(np.int64), np.bincount(cell, minlength=CELLS)])
    of_cell[:, END] += [ends, min(1, ends)]
    return told, of_cell.tobytes()


def count_words(blocks: DataFrame) -> tuple[DataFrame, np.ndarray]:
    """Answers with the training count of every distinct word of a block, and (2, CELLS): tokens and distinct words of each cell, ends included."""
    buckets = bucket_count(blocks)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                _, held, texts = _block(row["payload"])
                tokens = Tokens(texts)
                keys, index = _distinct(tokens)
                words = _spelt(tokens, len(keys), index)
                learnt = np.bincount(index[~held[tokens.words.text]], minlength=len(keys)) if len(keys) else np.zeros(0, np.int64)
                bounds, own = split_buckets(keys, buckets)
                rows = [(int(b), 0, row["block_id"], b" ".join(words[bounds[k] : bounds[k + 1]]), _small(learnt[bounds[k] : bounds[k + 1]])) for k, b in enumerate(own)]
                rows.append((0, ENDS, row["block_id"], END_WORD, _small(np.array([np.sum(~held)], np.int64))))
                yield arrow_rows(rows, QUESTION_ARROW)

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, CELLS), np.int64)
        for batch in batches:
            for blob in batch.column(0).to_pylist():
                total += np.frombuffer(blob, np.int64).reshape(2, CELLS)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(CELLS), pa.int32()), pa.array(total[0]), pa.array(total[1])], names=["cell", "n", "v"])

    answers = ask(blocks.mapInArrow(send, QUESTION_SCHEMA), answer_counts)
    sums = answers.filter("block_id = -1").select("answer").mapInArrow(cells, "cell int, n long, v long").groupBy("cell").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).toArrow()
    of_cell = np.zeros((2, CELLS), np.int64)
    of_cell[:, sums.column("cell").to_numpy()] = [sums.column("n").to_numpy(), sums.column("v").to_numpy()]
    return answers.filter((F.col("block_id") >= 0) & (F.col("level") != ENDS)), of_cell


# ---------------------------------------------------------------- sparse weights of word pairs

#: A question is 32 bits of the pair's hash (of others than give the bucket), 18 of its context, 9 of the cell and 5 of the count; the last value of the latter two stands for more.
_CONTEXT_AT, _CELL_AT, _MANY = 14, 5, 31
_AT_START = (1 << 18) - 1


def pair_questions(block_id: int, keys: np.ndarray, context: np.ndarray, cells: np.ndarray, learnt: np.ndarray, buckets: int) -> list[tuple]:
    place = np.minimum(context, _AT_START).astype(np.uint64)  # only START, START is above
    record = (keys >> np.uint64(9)) << np.uint64(32) | place << np.uint64(_CONTEXT_AT) | cells.astype(np.uint64) << np.uint64(_CELL_AT) | np.minimum(learnt, _MANY).astype(np.uint64)
    bounds, own = split_buckets(keys, buckets)
    rows = []
    for k, b in enumerate(own):
        s = slice(bounds[k], bounds[k + 1])
        rows.append((int(b), 1, block_id, record[s].tobytes(), _small(learnt[s][learnt[s] >= _MANY])))
    return rows


def fit_sparse(group: np.ndarray, chance: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Weights w of the entries of each group, and the log of each group's normaliser 1 + sum of chance * (exp(w) - 1).

    ``chance``: what the dense features give the entry; n: how often it came.  Gradient steps, scaled by
    the curvature of each weight, on the log-likelihood less RIDGE / 2 of the weights' squares.
    """
    w, e, whole = np.zeros(len(n)), np.ones(len(n)), np.bincount(group, n)
    total = whole[group]
    normal = np.ones(len(whole))
    for _ in range(PAIR_STEPS):
        p = chance * e / normal[group]
        slope, bend = n - total * p - RIDGE * w, total * p * (1 - p) + RIDGE
        w += np.clip(slope / bend, -LONGEST_STEP, LONGEST_STEP)
        e = np.exp(w)
        normal = 1 + np.bincount(group, chance * (e - 1), len(whole))
    return w, np.log(normal)


def _starts(sorted_values: np.ndarray) -> np.ndarray:
    """Marks of the first of each run of equal values."""
    out = np.ones(len(sorted_values), bool)
    out[1:] = sorted_values[1:] != sorted_values[:-1]
    return out


def pair_gains(pair: np.ndarray, context: np.ndarray, cell: np.ndarray, n: np.ndarray, tables: tuple[np.ndarray, np.ndarray, np.ndarray]) -> np.ndarray:
    """What sparse weights add to the natural log of P(cell | context), for distinct (pair, cell), sorted, with their training counts."""
    out = np.zeros(len(pair))
    start = _starts(pair)
    of = np.cumsum(start) - 1
    active = np.bincount(of, n) >= LEAST_SEEN
    rows = np.flatnonzero(active[of])
    if not len(rows):
        return out
    number = np.cumsum(active) - 1  # of an active pair
    of, cell, n, context = number[of[rows]], cell[rows], n[rows], context[np.flatnonzero(start)[active]]
    seen = n > 0
    kind = cell // MEMBERS
    entry, count = of[seen] * CELLS + cell[seen], n[seen]  # (pair, cell) with a weight
    there = np.where(seen, np.cumsum(seen) - 1, -1)
    group = np.cumsum(_starts(of * CLASSES + kind)) - 1
    known = np.bincount(group, seen) > 0
    here = np.where(known, np.cumsum(known) - 1, -1)[group]
    class_of = here[seen]
    classes = entry[_starts(class_of)] // MEMBERS  # (pair, class) with a weight
    p = np.exp(log_chances(tables, 0, context[classes // CLASSES], classes % CLASSES).astype(np.float64))  # what the dense features give
    q = np.exp(log_chances(tables, 1 + entry // MEMBERS % CLASSES, context[entry // CELLS], entry % MEMBERS).astype(np.float64))
    w, z = fit_sparse(classes // CLASSES, p, np.bincount(class_of, count))
    u, y = fit_sparse(class_of, q, count)
    out[rows] = np.where(here >= 0, w[here] - y[here], 0) + np.where(there >= 0, u[there], 0) - z[of]
    return out


def answer_pairs(keys: list[bytes], extras: list[bytes], tables: tuple[np.ndarray, np.ndarray, np.ndarray]) -> list[bytes | None]:
    """For each block's questions: a bit for each that has a gain, then those gains."""
    sizes = [len(k) // 8 for k in keys]
    record = np.frombuffer(b"".join(keys), np.uint64)
    n = (record & np.uint64(_MANY)).astype(np.int64)
    many = np.flatnonzero(n == _MANY)
    n[many] = np.concatenate([_large(x) for x in extras])
    distinct, index = np.unique(record >> np.uint64(_CELL_AT), return_inverse=True)
    n = np.bincount(index, n, len(distinct))
    context = ((distinct >> np.uint64(_CONTEXT_AT - _CELL_AT)) & np.uint64(_AT_START)).astype(np.int64)
    context[context == _AT_START] = START * (CELLS + 1) + START
    gain = pair_gains(distinct >> np.uint64(_CONTEXT_AT - _CELL_AT), context, (distinct & np.uint64(CELLS - 1)).astype(np.int64), n, tables)[index].astype(np.float32)
    out, at = [], 0
    for size in sizes:
        own = gain[at : at + size]
        out.append(np.packbits(own != 0).tobytes() + own[own != 0].tobytes() if own.any() else None)
        at += size
    return out


def _gains(blob: bytes, n: int) -> np.ndarray:
    out = np.zeros(n)
    there = np.unpackbits(np.frombuffer(blob, np.uint8, (n + 7) // 8), count=n).astype(bool)
    out[there] = np.frombuffer(blob, np.float32, offset=(n + 7) // 8)
    return out


def learn_pairs(blocks: DataFrame, tables, buckets: int) -> DataFrame:
    """Answers (level 1) with the gains of every distinct (two words, cell) of a block; ``tables``: the broadcast dense chances."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                _, held, texts = _block(row["payload"])
                tokens = Tokens(texts)
                keys, index, context, cells = tokens.pairs()
                learnt = np.bincount(index[~held[tokens.text]], minlength=len(keys))
                yield arrow_rows(pair_questions(row["block_id"], keys, context, cells, learnt, buckets), QUESTION_ARROW)

    return ask(blocks.mapInArrow(send, QUESTION_SCHEMA), lambda keys, extras: answer_pairs(keys, extras, tables.value))


def score_texts(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", held: Column | None = None, rounds: int = ROUNDS) -> DataFrame:
    """(id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row, learnt from the rows that ``held`` leaves.

    base_score: sum of log10 of unigram probabilities with half a count added, unknown tokens
    included; score: the model's log10 probability.  A null text is an empty one: one token, the
    end.  A null id is held out or not as its crc32 (null: not).  Repeated rows count and are scored
    as often as they come.  Without training rows all counts are 0 and the weights too.  No rows
    give no rows.
    """
    held = held_out(id_column) if held is None else held
    rows = docs.select(F.col(id_column).alias("id"), F.coalesce(held, F.lit(False)).alias("held"), F.col(text_column).cast("string").alias("text"))
    blocks = to_blocks(rows)
    answers, of_cell = count_words(blocks)
    release(docs)
    weights = train(blocks, of_cell, rounds)
    release(docs)
    n, v = int(of_cell[0].sum()), int(of_cell[1].sum())
    buckets = bucket_count(blocks)
    sent = docs.sparkSession.sparkContext.broadcast(chance_tables(weights))  # 20 MB, whatever the data
    pairs = learn_pairs(blocks, sent, buckets)
    release(docs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = sent.value
        in_cell = of_cell[0] + 0.5 * (of_cell[1] + 1)
        for batch in batches:
            for row in batch.to_pylist():
                ids, held, texts = _block(row["payload"])
                tokens = Tokens(texts)
                keys, index = _distinct(tokens)
                counts = np.zeros(len(keys), np.int64)
                told = {(x["level"], x["bucket"]): x["answer"] for x in row["answers"] or []}
                bounds, own = split_buckets(keys, buckets)
                for k, b in enumerate(own):
                    counts[bounds[k] : bounds[k + 1]] = _large(told[0, int(b)])
                keys, place, _, _ = tokens.pairs()
                gains = np.zeros(len(keys))
                bounds, own = split_buckets(keys, buckets)
                for k, b in enumerate(own):
                    if (1, int(b)) in told:
                        gains[bounds[k] : bounds[k + 1]] = _gains(told[1, int(b)], int(bounds[k + 1] - bounds[k]))
                c = np.full(len(tokens.cells), of_cell[0, END], np.float64)
                c[tokens.at] = counts[index]
                size = len(texts)
                base = np.bincount(tokens.text, np.log10((c + 0.5) / (n + 0.5 * (v + 1))), size)
                model = np.bincount(tokens.text, (log_by_tables(tokens, tables) + gains[place]) / np.log(10) + np.log10((c + 0.5) / in_cell[tokens.cells]), size)
                known = np.bincount(tokens.text, c > 0, size).astype(np.int64)
                yield pa.RecordBatch.from_arrays([ids, pa.array(held, pa.bool_()), pa.array(tokens.counts), pa.array(known), pa.array(np.full(size, n, np.int64)), pa.array(base), pa.array(model)], names=["id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    kind = docs.schema[id_column].dataType.simpleString()
    return with_answers(blocks, [answers, pairs]).mapInArrow(run, f"id {kind}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
