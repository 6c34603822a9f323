"""Near copies of the pipeline's stage against brute-force Jaccard of five-word shingles."""

import numpy as np

from subweight.llm import simhash

WORDS = [f"v{i}" for i in range(100_000)]


def shingles(text, k=5):
    w = text.lower().split()
    return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()


def brute_kept(rows, similarity=0.8):
    sets, parent = [shingles(t) for _, t in rows], list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            common = len(sets[a] & sets[b])
            if sets[a] == sets[b] or common >= similarity * (len(sets[a]) + len(sets[b]) - common) - 1e-9:
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return [rows[i][0] for i in range(len(rows)) if find(i) == i]


def kept(spark, rows):
    return sorted(r.doc_id for r in simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect())


def test_recall_of_short_texts(spark):
    """Ends exchanged so far that the similarity is just 0.8 or more: 10 to 100 words, all found."""
    rng = np.random.default_rng(11)
    rows = []
    for n in (10, 13, 14, 18, 22, 23, 34, 46, 54, 64, 72, 100):
        for _ in range(12):
            base = rng.choice(WORDS, n).tolist()
            size = n - 4
            gone = max(g for g in range(size) if size - g >= 0.8 * (size + g) - 1e-9)
            rows += [(2 * len(rows), " ".join(base)), (2 * len(rows) + 1, " ".join(base[: n - gone] + rng.choice(WORDS, gone).tolist()))]
    rows = [(i, t) for i, (_, t) in enumerate(rows)]
    want = brute_kept(rows)
    assert len(want) <= len(rows) // 2
    assert kept(spark, rows) == want


def test_copies_within_a_template(spark):
    """Of texts that share most of one boilerplate, near copies are found whatever the first of their keys' runs is, and no others."""
    rng = np.random.default_rng(12)
    rows = []
    for common, own in ((84, 20), (44, 12)):
        template = rng.choice(WORDS, common).tolist()
        for i in range(100):
            rest = rng.choice(WORDS, own).tolist()
            rows.append((len(rows), " ".join(template + rest)))
            if i % 2:
                rows.append((len(rows), " ".join(template + rest[: own // 2] + rng.choice(WORDS, own - own // 2).tolist())))
    want = brute_kept(rows)
    assert len(want) < len(rows)
    assert kept(spark, rows) == want


def test_long_runs_go_on(spark):
    """Many pieces of one run: texts of few words in many orders, where most candidates of a key are no copies."""
    rng = np.random.default_rng(13)
    template = rng.choice(WORDS, 60).tolist()
    rows = []
    for i in range(150):
        text = list(template)
        for at in rng.choice(60, int(rng.integers(1, 4)), replace=False):
            text[int(at)] = f"x{i}"
        rows.append((i, " ".join(text)))
    assert kept(spark, rows) == brute_kept(rows)


def test_less_similar_texts_stay(spark):
    """Pairs of a similarity of 0.6 to 0.79 are no copies."""
    rng = np.random.default_rng(14)
    rows = []
    for i in range(120):
        base = rng.choice(WORDS, 104).tolist()
        gone = int(rng.integers(13, 25))
        rows += [(2 * i, " ".join(base)), (2 * i + 1, " ".join(base[: 104 - gone] + rng.choice(WORDS, gone).tolist()))]
    want = brute_kept(rows)
    assert len(want) == len(rows)
    assert kept(spark, rows) == want


def test_recall_of_planted_copies(spark):
    """1,000 planted copies of a similarity of 0.8 or more, of texts of 20 to 400 words with single words exchanged: all are found."""
    rng = np.random.default_rng(15)
    rows, planted = [], 0
    while planted < 1000:
        n = int(rng.choice([20, 40, 60, 120, 400]))
        base = rng.choice(WORDS, n).tolist()
        copy = list(base)
        for at in rng.choice(n, int(rng.integers(1, max(2, n // 20))), replace=False):
            copy[int(at)] = f"changed{planted}"
        a, b = shingles(" ".join(base)), shingles(" ".join(copy))
        if len(a & b) >= 0.8 * len(a | b):
            rows += [(2 * planted, " ".join(base)), (2 * planted + 1, "\n".join(copy))]
            planted += 1
    assert kept(spark, rows) == [2 * i for i in range(planted)]


def test_stage_links_by_fingerprints(spark):
    """The pipeline's stage: links of fingerprints hold whatever the sets' similarity is, exact ones join what fingerprints miss, and both kinds make one chain."""
    import corpus_pipeline

    rng = np.random.default_rng(16)
    word = lambda n: rng.choice(WORDS, n).tolist()
    body = word(7) * 60
    by_bits = [" ".join(body + word(12)), " ".join(body + word(12))]
    base = word(60)
    by_sets = [" ".join(base), " ".join([*base[:-6], *word(6)])]
    tail = word(60)
    chain = [" ".join(body[::-1] + tail), " ".join(body[::-1] + word(2) + tail[2:]), " ".join(body[::-1] + word(12))]
    texts = [*by_bits, *by_sets, *chain, " ".join(word(80))]
    bits = lambda i, j: (simhash.fingerprint(texts[i].encode(), 5) ^ simhash.fingerprint(texts[j].encode(), 5)) & (1 << 64) - 1
    same = lambda i, j: len(shingles(texts[i]) & shingles(texts[j])) / len(shingles(texts[i]) | shingles(texts[j]))
    assert bits(0, 1).bit_count() <= 4 and same(0, 1) < 0.8
    assert bits(2, 3).bit_count() > 4 and same(2, 3) >= 0.8
    assert same(4, 5) >= 0.8 and same(4, 6) < 0.8 and same(5, 6) < 0.8 and bits(4, 6).bit_count() <= 4
    rows = [(i, t, "en", "s", len(t)) for i, t in enumerate(texts)] + [(0, texts[0], "en", "s", 1), (None, texts[0], "en", "s", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted((r.doc_id if r.doc_id is not None else -1) for r in corpus_pipeline.near_copies(spark, df, "").collect()) == [-1, 0, 2, 4, 7]
    assert corpus_pipeline.near_copies(spark, df.limit(0), "").count() == 0
