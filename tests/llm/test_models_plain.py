"""Features, scores and ratios against plain loops; executors without the package."""

import collections
import math
import os
import subprocess
import sys

import numpy as np
import pytest
from pyspark.sql import functions as F

from subweight.llm import chat, quality_classifier, url_filters
from subweight.llm.common import Words

REPO = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
SF = "/root/testdata/sf0.001"


def buckets_of(text):
    w = Words([text])
    return (w.hashes(1, quality_classifier.SEED) >> np.uint64(64 - 14)).astype(int).tolist(), text.split()


def slow_vectors(texts):
    index = quality_classifier.index_vectors(quality_classifier.BUCKETS, quality_classifier.SEED).astype(float)
    total = collections.defaultdict(lambda: np.zeros(quality_classifier.SIZE))
    for t in texts:
        b, _ = buckets_of(t or b"")
        for i, x in enumerate(b):
            for j in range(max(0, i - quality_classifier.REACH), min(len(b), i + quality_classifier.REACH + 1)):
                if j != i:
                    total[x] += index[b[j]]
    return {x: v / max(np.linalg.norm(v), 1e-9) for x, v in total.items()}


def slow_features(text, vectors):
    size, lags = quality_classifier.SIZE, quality_classifier.LAGS
    b, words = buckets_of(text or b"")
    if not b:
        return np.zeros(3 * size + lags + 1)
    index = quality_classifier.index_vectors(quality_classifier.BUCKETS, quality_classifier.SEED).astype(float)
    kinds = quality_classifier.index_vectors(256, quality_classifier.SEED + 1).astype(float)
    members = (b"abcdefghijklmnopqrstuvwxyz" + bytes(range(128, 256)), b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".,;:", b"!?", b"#*$%&|<>", b"'\"()-/")
    v = np.array([vectors.get(x, np.zeros(size)) for x in b])
    mask = []
    for w in words:
        m = 0
        for c in w:
            m |= next((1 << i for i, x in enumerate(members) if c in x), 1 << len(members))
        mask.append(m)
    near = [sum(float(index[b[i]] @ index[b[i - lag]]) / quality_classifier.ENTRIES for i in range(lag, len(b))) / len(b) for lag in range(1, lags + 1)]
    return np.concatenate([v.mean(axis=0), v.std(axis=0), kinds[mask].mean(axis=0), near, [math.log1p(len(b))]])


def test_classifier_by_plain_loops(spark):
    rows = [(r.doc_id, r.text[:800]) for r in spark.read.parquet(f"{SF}/documents.parquet").limit(50).collect()] + [(900, None), (901, ""), (902, "One 2 !? ÄÖ zwei\tzwei zwei")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    labels = spark.createDataFrame([(i, i % 2) for i, _ in rows] + [(901, 7), (None, 1)], "doc_id long, quality int")
    model = quality_classifier.fit(docs, labels)
    texts = {i: t.encode() if t else b"" for i, t in rows}
    vectors = slow_vectors(texts.values())
    for x, v in vectors.items():
        assert model.vectors[x] == pytest.approx(v, abs=1e-5)
    net = model.network
    for r in quality_classifier.score(docs.withColumn("__score", F.lit(1)), model).collect():
        x = slow_features(texts[r.doc_id], vectors)
        hidden = [math.tanh(sum((x[i] - net.shift[i]) / net.scale[i] * net.w1[i, j] for i in range(len(x))) + net.b1[j]) for j in range(quality_classifier.HIDDEN)]
        logit = (sum(h * w for h, w in zip(hidden, net.w2, strict=True)) + net.b2) / net.temperature
        assert r.score == pytest.approx(1 / (1 + math.exp(-logit)), abs=2e-3)
    kept = quality_classifier.keep_by_score(docs.withColumn("__score", F.lit(1)), model, 0.0)
    assert kept.columns == ["doc_id", "text", "__score"] and kept.count() == len(rows)


def test_ratio_by_plain_loops():
    """Counts by dictionaries of true contexts; few enough urls that no cells are shared."""
    rng = np.random.default_rng(2)
    letters = b"abcdefg./-"
    made = [bytes(rng.choice(list(letters), int(rng.integers(0, 9))).tolist()) for _ in range(8)]
    labels = [i % 2 for i in range(8)]
    pair_counts, context_counts = np.zeros((2, url_filters.CELLS)), np.zeros((2, url_filters.CONTEXTS))
    pairs, contexts, of = url_filters.cells_of(made)
    slow = [collections.Counter(), collections.Counter()]
    whole = [collections.Counter(), collections.Counter()]
    for label in (0, 1):
        own = np.isin(of, [i for i in range(8) if labels[i] == label])
        np.add.at(pair_counts[label], pairs[:, own].ravel(), 1)
        np.add.at(context_counts[label], contexts[:, own].ravel(), 1)
    for u, label in zip(made, labels, strict=True):
        line = b"\0" * url_filters.ORDER + u + b"\1"
        for i in range(url_filters.ORDER, len(line)):
            for order in range(url_filters.ORDER + 1):
                slow[label][order, line[i - order : i], line[i]] += 1
                whole[label][order, line[i - order : i]] += 1
    got = url_filters.log_ratio(made + [b"gfedcba", b""], pair_counts, context_counts)
    same = 0
    for u, r in zip(made + [b"gfedcba", b""], got, strict=True):
        line, total = b"\0" * url_filters.ORDER + u + b"\1", [0.0, 0.0]
        for label in (0, 1):
            for i in range(url_filters.ORDER, len(line)):
                p = 1 / 256
                for order in range(url_filters.ORDER + 1):
                    p = (slow[label][order, line[i - order : i], line[i]] + url_filters.PRIOR * p) / (whole[label][order, line[i - order : i]] + url_filters.PRIOR)
                total[label] += math.log(p)
        same += abs(r - (total[1] - total[0]) / (len(u) + 1)) < 1e-6
    assert same >= 8  # of 10; one or two may meet a shared cell


def test_urls_that_repeat_and_null_ids(spark):
    rows = [(1, "http://a.com/en/x"), (1, "http://a.com/en/x"), (None, "http://b.net/de/1"), (None, None), (3, "http://example.com/en/7" + "y" * 50_000)]
    got = url_filters.judge_urls(spark.createDataFrame(rows, "page_id long, url string")).collect()
    assert sorted((r.id or 0, r.verdict) for r in got) == [(0, "allow"), (0, "allow"), (1, "block"), (1, "block"), (3, "allow")]


def test_long_conversations(spark):
    long = [(1, i, "user", f"turn {i}") for i in range(3000)]
    rows = long + [(2, i, r, t) for _, i, r, t in long[:2999]] + [(3, 0, "user", "x" * 400_000)]
    got = {r.id: r for r in chat.render(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert sorted(got) == [1, 3] and got[1].n_turns == 3000 and len(got[3].chat) > 400_000


def test_executors_without_the_package(tmp_path):
    """A driver with the package, workers that cannot import it: models and the pipeline run."""
    script = tmp_path / "driver.py"
    script.write_text(
        f"""
import sys
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[2]").config("spark.sql.shuffle.partitions", "2").config("spark.ui.enabled", "false").config("spark.driver.memory", "2g").getOrCreate()
sys.path.insert(0, {REPO!r})
def seen(_):
    try:
        import subweight
        return ["yes"]
    except ModuleNotFoundError:
        return ["no"]
assert spark.sparkContext.parallelize([1], 1).mapPartitions(seen).collect() == ["no"]
import __spark_entry__ as e
found = e.queries()
for name in ("op1_quality_classifier", "op2_url_filters", "op6_byte_bpe", "pipeline"):
    print(name, found[name](spark, {SF!r}).count())
"""
    )
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    done = subprocess.run([sys.executable, str(script)], cwd=tmp_path, env=env, capture_output=True, text=True, timeout=600)
    assert done.returncode == 0, done.stderr[-3000:]
    assert len(done.stdout.split("\n")) >= 4
