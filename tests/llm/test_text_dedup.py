"""Substring dedup, SimHash and components against brute force."""

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from subweight.llm import simhash, substring_dedup
from subweight.llm.common import Words, durable
from subweight.llm.components import components


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, block_id string, n_removed int")


def brute(rows, k):
    first = {}
    for i, t in rows:
        w = (t or "").encode().split()
        for j in range(len(w) - k + 1):
            if i is not None:
                first[tuple(w[j : j + k])] = min(first.get(tuple(w[j : j + k]), 1 << 62), i)
    out = []
    for i, t in rows:
        w = (t or "").encode().split()
        gone = [False] * len(w)
        for j in range(len(w) - k + 1):
            if first.get(tuple(w[j : j + k]), 1 << 62) < (1 << 61 if i is None else i):
                gone[j : j + k] = [True] * k
        out.append((i, len(w), sum(gone), b" ".join(x for x, g in zip(w, gone, strict=True) if not g).decode()))
    return out


def corpus():
    rng = np.random.default_rng(8)
    words = [f"w{i}" for i in range(40)]
    text = lambda n: " ".join(rng.choice(words, n))
    shared = text(70)
    rows = [(i, text(int(rng.integers(0, 60))) + ("\n" + shared if i % 3 == 0 else "") + "\t " + text(5)) for i in range(40)]
    rows += [(40, None), (41, ""), (42, " \n "), (43, shared), (44, shared), (None, shared), (None, text(20)), (7, shared), (45, text(30000)), (46, "é\u00a0b " * 30), (47, "é\u00a0b " * 30)]
    return rows


@pytest.mark.parametrize("k", [3, 13])
def test_removed_words(spark, k, monkeypatch):
    rows = corpus()
    df = docs_of(spark, [(i, t, "x", 5) for i, t in rows]).repartition(3)
    out = substring_dedup.remove_repeats(df, min_words=k)
    assert out.columns == ["doc_id", "text", "block_id", "n_words", "n_removed", "kept_text"]
    got = [(r.doc_id, r.n_words, r.n_removed, r.kept_text) for r in out.collect()]
    key = lambda x: str(x)
    assert sorted(got, key=key) == sorted(brute(rows, k), key=key)
    plain = {(r.doc_id, r.text) for r in substring_dedup.remove_repeats(df, min_words=k, stats=False).collect()}
    assert (40, None) in plain and (42, " \n ") in plain


def test_levels_double(spark):
    base = " ".join(f"a{i}" for i in range(100))
    rows = [(1, base), (2, "x " + base + " y"), (3, " ".join(f"a{i}" for i in range(20)) + " z"), (4, "none of it")]
    out = substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), longest=True)
    assert {r.doc_id: r.longest_repeat for r in out.collect()} == {1: 52, 2: 52, 3: 13, 4: 0}
    rows = [(i, t) for i, (_, t) in enumerate(corpus())]
    out = substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), min_words=3, longest=True)
    words = [(t or "").encode().split() for _, t in rows]
    want = dict.fromkeys(range(len(rows)), 0)
    size = 3
    while any(len(w) >= size for w in words):
        seen = {}
        for i, w in enumerate(words):
            for j in range(len(w) - size + 1):
                seen.setdefault(tuple(w[j : j + size]), set()).add(i)
        want |= {i: size for s in seen.values() if len(s) > 1 for i in s}
        size *= 2
    assert {r.doc_id: r.longest_repeat for r in out.collect()} == want
    assert substring_dedup.remove_repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_window_hashes():
    texts = [b"a b c d e", None, b"", b"b  c\td", b"x"]
    w = Words(texts)
    assert w.counts.tolist() == [5, 0, 0, 3, 1]
    h = w.hashes(3, 1)
    assert h[1] == h[5] and len(set(h.tolist())) == len(h) - 1
    assert np.array_equal(h, w.hashes(3, 1, step=2))


def test_golay():
    g = simhash.Golay()
    rng = np.random.default_rng(0)
    v = rng.integers(0, 1 << 23, 400)
    for i in range(0, 23, 5):
        for j in range(0, 23, 4):
            a, b = g.nearby(v), g.nearby(v ^ (1 << i) ^ ((1 << j) if i != j else 0))
            assert all(set(x[x >= 0]) & set(y[y >= 0]) for x, y in zip(a, b, strict=True))


@pytest.mark.parametrize("fine", [False, True])
def test_keys_meet(fine):
    g = simhash.Golay()
    rng = np.random.default_rng(1)
    a = rng.integers(-(1 << 63), 1 << 63, 300, dtype=np.int64)
    b = a.copy()
    for i in range(300):
        for bit in rng.choice(64, 4, replace=False):
            b[i] ^= np.uint64(1 << int(bit)).view(np.int64)
    (ka, ra), (kb, rb) = simhash.keys_of(a, g, fine), simhash.keys_of(b, g, fine)
    assert {*zip(ra.tolist(), ka.tolist(), strict=True)} & {*zip(rb.tolist(), kb.tolist(), strict=True)}
    hit = {r for r, _ in {*zip(ra.tolist(), ka.tolist(), strict=True)} & {*zip(rb.tolist(), kb.tolist(), strict=True)}}
    assert hit == set(range(300))


def slow_fingerprint(t, k):
    w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (t or "")).encode().split()
    s = [b" ".join(w[i : i + k]) for i in range(max(1, len(w) - k + 1))] if w else []
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_components_of_near_copies(spark):
    rng = np.random.default_rng(2)
    base = [f"t{i}" for i in range(500)]
    rows = []
    for i in range(60):  # a chain of small edits
        base[int(rng.integers(0, 500))] = f"e{i}"
        rows.append((1000 - i, " ".join(base)))
    rows += [(i, " ".join(rng.choice(base, 30))) for i in range(30)] + [(50, None), (51, ""), (52, "One two"), (53, "one  TWO"), (52, "One two"), (None, "one two")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = simhash.near_duplicates(df).collect()
    ids = [r[0] for r in rows if r[0] is not None]
    fp = [slow_fingerprint(t, 4) for i, t in rows if i is not None]
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, i in enumerate(ids):
        for b in range(a):
            if (fp[a] ^ fp[b]).bit_count() <= 4:
                x, y = find(i), find(ids[b])
                parent[max(x, y)] = min(x, y)
    want = sorted((i, f, find(i)) for i, f in zip(ids, fp, strict=True))
    assert sorted((r.id, r.fp % (1 << 64), r.component_id) for r in got if r.id is not None) == want
    assert [r.component_id for r in got if r.id is None] == [None]
    kept = simhash.drop_near_duplicates(df, shingle=4, similarity=None).collect()
    assert sorted(r.doc_id for r in kept if r.doc_id is not None) == sorted({find(i) for i in ids})
    assert simhash.near_duplicates(df.limit(0)).count() == 0


def test_large_runs():
    rng = np.random.default_rng(3)
    centre = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    fp = np.concatenate([centre[i % 40] ^ np.uint64(1 << int(rng.integers(0, 64))) for i in range(800)], axis=None)
    links = simhash.links_in_run(fp, np.arange(800))
    assert len(links) == 800 - 40
    assert all((int(fp[a]) ^ int(fp[b])).bit_count() <= 4 for a, b in links)


def test_components(spark):
    rng = np.random.default_rng(4)
    chain = [(i, i + 1) for i in range(0, 120)] + [(200 + int(a), 200 + int(b)) for a, b in rng.integers(0, 60, (50, 2))] + [(500, x) for x in range(501, 560)] + [(3, 3), (None, 4)]
    got = {r.node: r.component for r in components(spark.createDataFrame(chain, "a long, b long")).collect()}
    parent: dict = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in chain:
        if a is not None and a != b:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    assert got == {i: find(i) for i in parent}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
    assert durable(spark.range(3)).count() == 3


def test_both_key_sets_link_alike(spark, monkeypatch):
    """The coarse keys and the fine ones, for very many fingerprints, give the same groups."""
    rng = np.random.default_rng(6)
    rows, base = [], [f"t{i}" for i in range(300)]
    for i in range(200):
        base[int(rng.integers(0, 300))] = f"e{i}"
        rows.append((i, " ".join(base)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    coarse = sorted(tuple(r) for r in simhash.near_duplicates(df).collect())
    monkeypatch.setattr(simhash, "FINE_ABOVE", 0)
    assert sorted(tuple(r) for r in simhash.near_duplicates(df).collect()) == coarse
    assert 1 < len({r[2] for r in coarse}) < 200


def test_unlike_texts_of_one_id(spark):
    """A different text that shares an id is a document of its own; equal ones are one; columns may have any name."""
    long = lambda tag, n=40: " ".join(f"{tag}{i}" for i in range(n))
    rows = [(1, long("a"), "x"), (1, long("b"), "y"), (2, long("a") + " more", "z"), (1, long("b"), "y"), (3, None, None), (4, "", "e"), (None, long("a"), "n"), (2, long("c"), "w")]
    df = spark.createDataFrame(rows, "doc_id long, text string, node string").withColumn("keys", F.lit(1)).withColumn("text_key", F.lit(2))
    for similarity in (0.8, None):
        out = simhash.drop_near_duplicates(df, similarity=similarity)
        assert out.columns == df.columns
        got = sorted((r.doc_id or 0, (r.text or "")[:2]) for r in out.collect())
        assert [x for x in got if x != (2, "a0")] == [(0, "a0"), (1, "a0"), (1, "b0"), (2, "c0"), (3, "")]
        assert similarity is None or (2, "a0") not in got
    assert simhash.drop_near_duplicates(df.limit(0)).count() == 0


def test_runs_are_not_cut():
    import pyarrow as pa

    key = np.sort(np.random.default_rng(0).integers(0, 9, 200))
    batches = [pa.RecordBatch.from_arrays([pa.array(key[a : a + 7]), pa.array(np.arange(a, min(a + 7, 200)))], names=["k", "v"]) for a in range(0, 200, 7)]
    pieces = list(simhash.whole_runs(iter(batches), 2))
    assert np.concatenate([p[1] for p in pieces]).tolist() == list(range(200))
    assert all(a[0][-1] != b[0][0] for a, b in zip(pieces, pieces[1:], strict=False) if len(a[0]) and len(b[0]))
    assert list(simhash.whole_runs(iter([]), 2)) == []
