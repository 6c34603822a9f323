"""Sparse weights of word pairs, and the whole score, against a scorer in plain loops."""

import collections
import math
import zlib

import numpy as np
import pytest

from subweight.llm import lm

SF = "/root/testdata/sf0.001"


def words_of(text):
    return ["".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in w) for w in (text or "").replace("\t", " ").replace("\n", " ").replace("\r", " ").replace("\v", " ").replace("\f", " ").split(" ") if w]


def slow_fit(entries):
    """Weights of one group: {key: (chance, n)}."""
    w = dict.fromkeys(entries, 0.0)
    whole = sum(n for _, n in entries.values())
    normal = lambda: 1 + sum(c * (math.exp(w[e]) - 1) for e, (c, _) in entries.items())
    for _ in range(lm.PAIR_STEPS):
        z = normal()
        for e, (c, n) in entries.items():
            p = c * math.exp(w[e]) / z
            w[e] += max(-lm.LONGEST_STEP, min(lm.LONGEST_STEP, (n - whole * p - lm.RIDGE * w[e]) / (whole * p * (1 - p) + lm.RIDGE)))
    return w, math.log(normal())


class Slow:
    """The model by dictionaries; cells, dense weights and cell counts are taken as they are."""

    def __init__(self, weights, of_cell, train):
        self.weights, self.of_cell = weights, of_cell
        self.after = collections.defaultdict(collections.Counter)
        self.count = collections.Counter()
        for text in train:
            for pair, token, cell, _ in self.tokens(text):
                self.after[pair][cell] += 1
                self.count[token] += 1

    def tokens(self, text):
        words = words_of(text)
        own = lm.Tokens([(text or "").encode()])
        assert len(own.cells) == len(words) + 1
        line = [None, None, *words, ""]
        return [((line[i], line[i + 1]), line[i + 2], int(own.cells[i]), (int(own.cells[i - 1]) if i else lm.START, int(own.cells[i - 2]) if i > 1 else lm.START)) for i in range(len(words) + 1)]

    def dense(self, context):
        mixed = lm._features(np.array([context[0] * (lm.CELLS + 1) + context[1]]))
        soft = lambda x: np.exp(x - x.max()) / np.exp(x - x.max()).sum()
        p = soft(self.weights[0][lm._class_rows(mixed)[0].astype(int)].sum(axis=0) + self.weights[0][lm.CLASS_ROWS])
        q = [soft(self.weights[1][lm._member_rows(mixed, np.array([k]))[0].astype(int)].sum(axis=0) + self.weights[1][lm.MEMBER_ROWS + k]) for k in range(lm.CLASSES)]
        return p, q

    def log_cell(self, pair, context):
        """Natural logs of all cells' chances."""
        p, q = self.dense(context)
        p, q = np.log(p), np.log(np.array(q))
        seen = self.after[pair]
        if sum(seen.values()) >= lm.LEAST_SEEN:
            classes = collections.Counter()
            for c, n in seen.items():
                classes[c // lm.MEMBERS] += n
            w, z = slow_fit({k: (math.exp(p[k]), n) for k, n in classes.items()})
            for k in classes:
                p[k] += w[k]
                u, y = slow_fit({c: (math.exp(q[k][c % lm.MEMBERS]), n) for c, n in seen.items() if c // lm.MEMBERS == k})
                for c in u:
                    q[k][c % lm.MEMBERS] += u[c]
                q[k] -= y
            p -= z
        return (p[:, None] + q).ravel()

    def score(self, text):
        out = 0.0
        for pair, token, cell, context in self.tokens(text):
            logs = self.log_cell(pair, context)
            assert np.exp(logs).sum() == pytest.approx(1, abs=1e-4)
            out += logs[cell] / math.log(10) + math.log10((self.count[token] + 0.5) / (self.of_cell[0][cell] + 0.5 * (self.of_cell[1][cell] + 1)))
        return out


def test_score_by_plain_loops(spark, monkeypatch):
    rows = [(r.doc_id, r.text[:600]) for r in spark.read.parquet(f"{SF}/documents.parquet").limit(60).collect()]
    rows += [(5000, None), (5001, ""), (5002, "Unseen wörd\tand a\nrest"), (rows[0][0], rows[0][1]), (5003, rows[1][1]), (None, "null id")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    made = {}
    train = lm.train
    monkeypatch.setattr(lm, "train", lambda blocks, of_cell, rounds: made.setdefault("w", (train(blocks, of_cell, rounds), of_cell.copy()))[0])
    got = lm.score_texts(df).collect()
    slow = Slow(*made["w"], [t for i, t in rows if i is None or zlib.crc32(str(i).encode()) % 5 != 1])
    want = sorted((str(i), slow.score(t)) for i, t in rows)
    assert [x[0] for x in want] == sorted(str(r.id) for r in got)
    have = sorted((str(r.id), r.score) for r in got)
    assert [x[1] for x in have] == pytest.approx([x[1] for x in want], rel=1e-4)


def test_text_of_many_counts(spark):
    """Counts beyond those a question has room for, and one text of very many words."""
    rows = [(2, "tick tock " * 5000), (3, "tick tock " * 3), (4, " ".join(f"w{i}" for i in range(100_000)))]
    assert any(zlib.crc32(str(i).encode()) % 5 != 1 for i, _ in rows)
    got = {r.id: r for r in lm.score_texts(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[2].n_tokens == 10_001 and got[2].score / got[2].n_tokens > got[2].base_score / got[2].n_tokens


def test_texts_seen_twice_stand_out(spark):
    """Training texts that come twice score above those that come once; held-out texts gain over single words."""
    rng = np.random.default_rng(4)
    words = [f"v{i}" for i in range(2000)]
    texts = [" ".join(rng.choice(words, 60)) for _ in range(300)]
    rows = [(i, texts[i % 300]) for i in range(400)]
    got = lm.score_texts(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()
    rate = {r.id: r.score / r.n_tokens for r in got}
    learnt = {i for i in rate if zlib.crc32(str(i).encode()) % 5 != 1}
    twice = [rate[i] for i in learnt if i < 100 and i + 300 in learnt]
    once = [rate[i] for i in learnt if 100 <= i < 300]
    assert min(twice) > max(once)
