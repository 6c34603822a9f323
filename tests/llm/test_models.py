"""Quality classifier, URL filters, quality rules, language model, chat, packing and the pipeline."""

import collections
import math
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from subweight.llm import chat, lm, packing, quality_classifier, quality_rules, url_filters
from subweight.llm.entry import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in ("documents", "conversations", "pages", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracles(spark, duck, name):
    got = QUERIES[name](spark, SF)
    want = duck.execute(ORACLES[name])
    columns = [c[0] for c in want.description]
    assert sorted(tuple(str(r[c]) for c in columns) for r in got.collect()) == sorted(tuple(str(x) for x in r) for r in want.fetchall())


def test_rules_edge_cases(spark, monkeypatch):
    rows = [(1, None, "en", None), (2, "", None, "s"), (3, "one two three", "en", "s"), (4, "a b c d e " * 4, "en", "s"), (5, " ".join(f"w{i}" for i in range(50)), "en", "s"), (5, " ".join(f"w{i}" for i in range(50)), "en", "s"), (6, "same line here\n" * 2 + " ".join(f"v{i}" for i in range(60)), "en", "s")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").withColumn("n_words", F.lit(7)).withColumn("kept", F.lit("x"))
    got = {r.id: r for r in quality_rules.verdicts(df).collect()}
    assert quality_rules.verdicts(df).count() == 7
    assert [got[i].base_failed for i in (1, 2, 3, 4, 5, 6)] == [True, True, True, True, False, False]
    assert got[4].n_repeat_words == 20 and got[6].n_dup_lines == 1 and got[1].n_words == 0
    kept = quality_rules.keep_by_rules(df)
    assert kept.columns == df.columns and sorted(r.doc_id for r in kept.collect()) == [5, 5, 6]
    assert quality_rules.keep_by_rules(df.limit(0)).count() == 0
    clash = df.select("*", *[F.lit(i).alias(c) for i, c in enumerate(("t", "t_lang", "t_source", "__q", "__c", "__h", "__l", "__salt", "row", "n", "a b", "features", "__kept"))])
    for most in (quality_rules.MOST_BROADCAST, 0):
        monkeypatch.setattr(quality_rules, "MOST_BROADCAST", most)
        kept = quality_rules.keep_by_rules(clash)
        assert kept.columns == clash.columns and sorted((r.doc_id, r["__salt"], r["t"]) for r in kept.collect()) == [(5, 7, 0), (5, 7, 0), (6, 7, 0)]
        assert quality_rules.verdicts(clash).count() == 7
    nulls = spark.createDataFrame([(None, "word " * 30, None, None), (None, None, None, None), (7, " ".join(f"x{i}" for i in range(200_000)), "en", "s")], "doc_id long, text string, lang string, source string")
    assert sorted((r.id or 0, r.n_words, r.base_failed) for r in quality_rules.verdicts(nulls).collect()) == [(0, 0, True), (0, 30, True), (7, 200_000, False)]
    a, b = df.filter("doc_id < 5"), df.filter("doc_id >= 5")
    parts = quality_rules.sketch(quality_rules.with_stats(a)).unionByName(quality_rules.sketch(quality_rules.with_stats(b))).groupBy("lang", "source", "feature", "bucket").agg(F.sum("n").alias("n"))
    assert {tuple(r) for r in parts.collect()} == {tuple(r) for r in quality_rules.sketch(quality_rules.with_stats(df)).collect()}


def test_salted_join_agrees(spark, monkeypatch):
    df = spark.read.parquet(f"{SF}/documents.parquet")
    before = sorted(tuple(r) for r in quality_rules.verdicts(df).collect())
    monkeypatch.setattr(quality_rules, "MOST_BROADCAST", 0)
    assert sorted(tuple(r) for r in quality_rules.verdicts(df).collect()) == before


def test_classifier(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = quality_classifier.fit(docs, labels)
    rows = quality_classifier.score(docs.withColumn("score", F.lit("old")), model).join(labels, "doc_id").filter(quality_classifier.held_out()).collect()
    right = sum((r.score >= 0.3) == (r.quality == 1) for r in rows)
    assert right / len(rows) > 0.95 and all(0 <= r.score <= 1 for r in rows)
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "wort " * 50_000), (3, "x")], "doc_id long, text string")
    assert quality_classifier.score(odd, model).count() == 4
    assert quality_classifier.score(odd.limit(0), model).count() == 0
    assert quality_classifier.train(np.zeros((0, 3)), np.zeros(0)).score(np.zeros((2, 3))).tolist() == [0.5, 0.5]
    one = quality_classifier.fit(docs.limit(3), labels.limit(0))
    assert quality_classifier.score(odd, one).count() == 4


def slow_rule(url):
    if url is None or "://" not in url:
        return "", "", None
    rest = url.split("://", 1)[1]
    host = rest
    for i, c in enumerate(rest):
        if c in "/?#":
            host = rest[:i]
            break
    path = rest[len(host) :].split("?")[0].split("#")[0]
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    best = None
    for rule, _ in url_filters.RULES:
        name, _, tail = rule.partition("/")
        if (host == name or host.endswith("." + name)) and path.startswith("/" + tail) and (best is None or len(rule) > len(best)):
            best = rule
    return host, path, best


def test_urls(spark):
    odd = [None, "", "no scheme", "http://", "HTTP://A.COM/en/x?y", "x://b.example.com/en/7#q", "a://example.com/en/70", "ftp://com/en/", "http://xcom/en/", "s://net/de/9", "s://example.net/de/8/://z", "s://o.org/es/\nx", "s://e.org?/es/", "http://a.com#/en/"]
    df = spark.createDataFrame([(i, u, "x") for i, u in enumerate(odd)], "page_id long, url string, host string")
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet").select(F.col("page_id") + 100, "url", F.lit("y")).toDF("page_id", "url", "host")
    both = df.unionByName(pages)
    urls = {r.page_id: r.url for r in both.collect()}
    verdict = dict(url_filters.RULES)
    seen = collections.Counter()
    for r in url_filters.judge_urls(both).collect():
        assert (r.host, r.path, r.rule) == slow_rule(urls[r.id]), urls[r.id]
        assert r.verdict == (verdict[r.rule] if r.rule else r.verdict) and r.verdict in ("allow", "block") and 0 <= r.score <= 1
        if r.rule:
            seen[verdict[r.rule] == ("block" if r.score > 0.5 else "allow")] += 1
    assert seen[True] > 4 * seen[False]
    assert {r.verdict for r in url_filters.judge_urls(df.filter("page_id < 4")).collect()} == {"allow"}
    assert url_filters.judge_urls(df.limit(0)).count() == 0


def test_ratio_is_a_difference_of_log_likelihoods():
    urls = [b"abc", b"abd", b"xyz"]
    pairs, contexts, of = url_filters.cells_of(urls)
    counts = np.zeros((2, url_filters.CELLS)), np.zeros((2, url_filters.CONTEXTS))
    for label, u in ((0, 0), (0, 1), (1, 2)):
        np.add.at(counts[0][label], pairs[:, of == u].ravel(), 1)
        np.add.at(counts[1][label], contexts[:, of == u].ravel(), 1)
    r = url_filters.log_ratio([b"abc", b"xyz", b""], *counts)
    assert r[0] < 0 < r[1] and len(r) == 3


def test_language_model(spark):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()] + [(5000, None), (5001, ""), (5002, "Unseen-wörd"), (0, "repeated row")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = lm.score_texts(df).collect()
    tokens = lambda t: (t or "").encode().lower().split() + [b" "]
    train = collections.Counter()
    for i, t in rows:
        if zlib.crc32(str(i).encode()) % 5 != 1:
            train.update(tokens(t))
    n, v = sum(train.values()), len(train)
    want = sorted((i, zlib.crc32(str(i).encode()) % 5 == 1, len(tokens(t)), sum(train[x] > 0 for x in tokens(t)), n, round(sum(math.log10((train[x] + 0.5) / (n + 0.5 * (v + 1))) for x in tokens(t)), 6)) for i, t in rows)
    assert sorted((r.id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got) == want
    held = [r for r in got if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)
    assert all(r.score < 0 for r in got)
    assert lm.score_texts(df.limit(0)).count() == 0


def test_model_is_a_distribution():
    t = lm.Tokens([b"the cat sat on the mat", b"la casa"])
    of = np.zeros((2, lm.CELLS), np.int64)
    of[0] = np.bincount(t.cells, minlength=lm.CELLS)
    trainer = lm.Trainer(lm.new_weights(of))
    for _ in range(5):
        trainer.learn(t)
    chances = np.zeros(len(t.cells))
    right = t.cells.copy()
    before = lm.log_cells(t, trainer.weights).copy()
    context = t.contexts()
    t.contexts = lambda: context
    for c in range(lm.CELLS):
        t.cells = np.full(len(right), c)
        chances += np.exp(lm.log_cells(t, trainer.weights))
    assert chances == pytest.approx(np.ones(len(right)), rel=1e-4)
    t.cells = right
    assert before.sum() > lm.log_cells(t, lm.new_weights(of)).sum()


def test_chat(spark):
    turns = lambda c, *texts: [(c, i, "user" if i % 2 == 0 else "assistant", t) for i, t in enumerate(texts)]
    rows = [*turns(1, "a", "b"), *turns(2, "a", "b", "c"), *turns(3, "a"), *turns(4, "a", "x"), *turns(5, "a", "b", "c"), *turns(6, "b", "c"), (7, 0, None, None), (None, 0, "user", "lost"), *turns(8, "<|user|>\nmark"), (9, None, "user", "a"), (9, 1, "user", "z"), (9, 1, "user", "z")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("place", F.lit("clash"))
    got = {r.id: r for r in chat.render(df).collect()}
    assert sorted(got) == [2, 4, 6, 7, 8, 9]
    assert got[2].copies == 2 and got[2].n_turns == 3 and got[9].n_turns == 3
    assert got[4].chat == "<|user|>\na<|end|>\n<|assistant|>\nx<|end|>\n"
    assert got[8].chat.count("<|") == 3 - 1 + 0 and "< |user|>" in got[8].chat
    assert chat.render(df.limit(0)).count() == 0


def naive_pack(sizes, sources, clusters, capacity):
    bins, out = [], []

    def put(need, source, cluster):
        fit = [b for b, (room, s, c) in enumerate(bins) if room >= need and source not in s and (cluster is None or cluster not in c)]
        best = min(fit, key=lambda b: (bins[b][0], b), default=None)
        if best is None:
            bins.append((capacity, frozenset(), frozenset()))
            best = len(bins) - 1
        room, s, c = bins[best]
        bins[best] = (room - need, s | ({source} - {"full"}), c | ({cluster} - {None}))
        return best, room

    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        for p in range(sizes[i] // capacity if sizes[i] > capacity else 0):
            out.append((i, p, put(capacity, "full", None)[0], 0, capacity))
    rest = [s if s <= capacity else s % capacity for s in sizes]
    for i in sorted(range(len(sizes)), key=lambda i: (-rest[i], i)):
        if sizes[i] > capacity and rest[i] == 0:
            continue
        b, room = put(rest[i], sources[i], clusters[i])
        out.append((i, sizes[i] // capacity if sizes[i] > capacity else 0, b, capacity - room, rest[i]))
    return out


def test_packing():
    import random

    rng = random.Random(3)
    for _ in range(150):
        n, capacity = rng.randint(1, 60), rng.choice([5, 16, 33, 64])
        sizes = [rng.choice([0, 1, rng.randint(0, capacity), rng.randint(0, 4 * capacity)]) for _ in range(n)]
        sources, clusters = [rng.choice("aaabcdefgh") for _ in range(n)], [rng.choice([None, None, 1, 2, 3, i + 10]) for i in range(n)]
        assert packing.pack_shard(sizes, sources, clusters, capacity) == naive_pack(sizes, sources, clusters, capacity)


def test_many_equal_rows(spark):
    """Rows that are equal, or of one text, are spread over all shards and packed in bins apart."""
    import time

    rows = spark.range(40_000).select(F.lit(None).cast("long").alias("doc_id"), F.lit(7).alias("n_tokens"), F.lit("s").alias("source"), F.lit(1).alias("cluster"))
    began = time.time()
    out = packing.best_fit(rows, capacity=64)
    assert out.groupBy("bin_id").count().filter("count > 1").count() == 0 and out.count() == 40_000
    assert max(r[1] for r in out.groupBy(F.split("bin_id", "-")[0]).count().collect()) <= 8192
    assert time.time() - began < 60
    mixed = spark.range(3000).select(F.col("id").alias("doc_id"), (F.col("id") % 9 + 1).alias("n_tokens"), F.concat(F.lit("s"), F.col("id") % 50).alias("source"), F.when(F.col("id") % 3 == 0, 1).alias("cluster"))
    one, many = (packing.best_fit(mixed.repartition(n), capacity=16, shard_rows=500) for n in (1, 7))
    assert sorted(map(tuple, one.collect()), key=str) == sorted(map(tuple, many.collect()), key=str)
    assert one.select(F.split("bin_id", "-")[0]).distinct().count() == 6


def test_packing_rows(spark):
    rows = [(1, "a b c", "s"), (2, "a b c", "t"), (3, None, None), (4, "", None), (5, "w " * 30, "s"), (1, "a b c", "s"), (None, "x", "u"), (6, "solo", "t")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumn("bin_id", F.lit(1))
    out = packing.pack_documents(df, capacity=8).collect()
    held = collections.defaultdict(int)
    for r in out:
        held[r.bin_id] += r.n_tokens
        assert 0 <= r.start <= 8 - r.n_tokens
    assert max(held.values()) <= 8
    assert sum(r.n_tokens for r in out) == sum(len((t or "").split()) + 1 for _, t, _ in rows)
    assert {r.doc_id for r in out} == {1, 2, 3, 4, 5, 6, None}
    where = {(r.doc_id, r.bin_id) for r in out if r.doc_id in (1, 2)}
    assert len({b for _, b in where}) == 3
    assert packing.pack_documents(df.limit(0), 8).count() == 0


def test_pipeline(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    columns, held = docs.columns, docs
    counts = []
    for _, stage in corpus_pipeline.STAGES:
        held = corpus_pipeline.durable(stage(spark, held, "/root/testdata/sf0.01"))
        counts.append(held)
    assert all(d.columns == columns for d in counts[:-1])
    n = [d.count() for d in counts[:-1]]
    assert docs.count() > n[0] >= n[1] > n[2] == n[3]
    good = docs.join(labels.filter("quality = 1"), "doc_id")
    kept = good.join(counts[1].select("doc_id"), "doc_id", "left_semi").count()
    assert kept / good.count() > 0.95
    assert counts[1].join(labels.filter("quality = 0"), "doc_id").count() <= 2
    words = lambda d: d.agg(F.sum(F.size(F.regexp_extract_all("text", F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))) + 1)).first()[0]
    assert counts[4].agg(F.sum("n_tokens")).first()[0] == words(counts[3])
    assert words(counts[3]) < words(counts[2])
    odd = spark.createDataFrame([(1, None, None, None, None), (2, "", "en", None, 0)], docs.schema)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, odd, "/root/testdata/sf0.001").count() >= 0
        assert stage(spark, odd.limit(0), "/root/testdata/sf0.001").count() == 0
