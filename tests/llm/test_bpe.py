import base64
import random
import sys

import public_tokenizers as P
import pytest
import tiktoken

from subweight.llm import bpe


@pytest.fixture(scope="module")
def lines():
    with open(P.path("byte_bpe_50k.tiktoken"), "rb") as f:
        return f.read()


def texts():
    rng = random.Random(5)
    kinds = [chr(c) for c in [*range(0, 0x180), *range(0x2000, 0x2070), 0x3000, 0x4E2D, 0x1F600, 0x85, 0xA0, 0x1680, 0xFEFF, 0x301, 0x660]]
    made = ["".join(rng.choices(kinds, k=rng.randint(1, 60))) for _ in range(400)]
    return [*made, "", " ", "  a", "a  ", "it's  we'll\n\n x", "<|endoftext|>", "a" * 5000, "ab" * 3000, " \n" * 50, "é" * 999, "1234567 89"]


def test_same_as_the_library(lines):
    ranks = bpe.load_ranks(lines)
    own = bpe.Encoder(ranks, P.PATTERN)
    other = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    for t in texts():
        ids = list(memoryview(own.encode(t)).cast("I"))
        assert ids == other.encode_ordinary(t), repr(t[:40])
        assert own.decode(own.encode(t)) == t.encode()


def test_leftmost_of_equal_ranks():
    ranks = {bytes([i]): 10 + i for i in range(256)} | {b"aa": 1}
    assert bpe.merge(b"aaaaa", ranks) == [1, 1, 107]


def plain(piece, ranks):
    """One pair after the other, by looking at all."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while True:
        found = [(ranks[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)) if a + b in ranks]
        if not found:
            return [ranks[x] for x in parts]
        i = min(found)[1]
        parts[i : i + 2] = [parts[i] + parts[i + 1]]


@pytest.mark.parametrize("fan", [2, 3, 32])
def test_trees_of_any_depth(monkeypatch, fan):
    monkeypatch.setattr(bpe, "FAN", fan, raising=False)
    rng = random.Random(fan)
    made = {bytes(rng.choices(b"abc", k=rng.randint(2, 6))) for _ in range(150)}
    ranks = {x: i for i, x in enumerate([*rng.sample(sorted(made), len(made)), b"a", b"b", b"c"])}
    for n in [*range(1, 70), 95, 96, 97, 300, 1023, 1024, 1025]:
        piece = bytes(rng.choices(b"abc", k=n))
        assert bpe.merge(piece, ranks) == ([ranks[piece]] if piece in ranks else plain(piece, ranks)), piece


def test_ordinary_pieces_are_merged_without_calls(lines):
    """The time a GB hangs on this: a node's least is found by one built-in call, not by a climb in Python for each changed leaf."""
    ranks, calls = bpe.load_ranks(lines), []
    sys.setprofile(lambda frame, event, _: calls.append(frame.f_code.co_name) if event == "call" else None)
    try:
        ids = bpe.merge(b" hehaoninchpfbelichen", ranks)
    finally:
        sys.setprofile(None)
    assert ids == plain(b" hehaoninchpfbelichen", ranks) and calls == ["merge"]


def test_repeats_after_full_memory(lines, monkeypatch):
    monkeypatch.setattr(bpe, "MOST_REMEMBERED", 600)
    merged, merge = [], bpe.merge
    monkeypatch.setattr(bpe, "merge", lambda piece, ranks: merged.append(piece) or merge(piece, ranks))
    own = bpe.Encoder(bpe.load_ranks(lines), P.PATTERN)
    own.encode(" aq bq cq dq eq fq" + " gq" * 50)
    assert merged.count(b" gq") == 1


def test_bounded_memory(lines, monkeypatch):
    monkeypatch.setattr(bpe, "MOST_REMEMBERED", 600)
    ranks = bpe.load_ranks(lines)
    own = bpe.Encoder(ranks, P.PATTERN)
    other = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    for t in texts()[:50]:
        assert list(memoryview(own.encode(t)).cast("I")) == other.encode_ordinary(t)
        assert len(own.known) <= 3 and own.held <= 600
    long = " ".join(f"{i}" + "x" * 300 for i in range(50))
    assert list(memoryview(own.encode(long)).cast("I")) == other.encode_ordinary(long) and own.held <= 600


def test_columns(spark, lines):
    df = spark.createDataFrame([(1, "one two", "x"), (2, None, "y"), (3, "", None), (1, "one two", "x")], "doc_id long, text string, ids string")
    out = bpe.decode(bpe.encode(df, lines, P.PATTERN), lines, P.PATTERN)
    rows = sorted((r.doc_id, bytes(r.decoded), len(r.ids)) for r in out.collect())
    assert rows == [(1, b"one two", 8), (1, b"one two", 8), (2, b"", 0), (3, b"", 0)]
    assert bpe.encode(df.limit(0), lines, P.PATTERN).count() == 0
    assert base64.b64encode(b"!") in lines
