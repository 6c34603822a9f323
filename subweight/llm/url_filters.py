"""URL filters: host and path rules, and a ratio of character language models for what no rule decides.

URLs that a rule allows or blocks teach two variable-order Markov models: counts of each next byte
after contexts of 0 to 5 bytes, in hashed tables of a fixed size, every order smoothed with the one
below it.  The difference of the two log-likelihoods, divided by the length, is calibrated by a
logistic curve on rule-decided URLs that were kept from training; what is likelier blocked than
allowed is blocked.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import mix

#: Longest context; cells of the tables of (context, byte) and of contexts; weight of the order below.
ORDER, CELLS, CONTEXTS, PRIOR = 5, 1 << 18, 1 << 16, 2.0
#: One in so many rule-decided URLs calibrates and does not train; width of a calibration bin.
FOLDS, BIN = 5, 0.02
RULES = (("com/en/", "block"), ("example.com/en/7", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"), ("org/es/", "block"))
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_PARTS = r"(?s)^.*?://([^/?#]*)([^?#]*)"


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), _PARTS, 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), _PARTS, 2)


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits; null: none.  Rules are a short list given by the caller."""
    out = F.lit(None).cast("string")
    for rule, _ in sorted(rules, key=lambda r: len(r[0])):
        name, slash, rest = rule.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


def cells_of(urls: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For every byte of every URL and its end: cells of (context, byte) and of the context, both (orders, bytes), and the URL's number."""
    pad = b"\0" * ORDER
    data = np.frombuffer(b"".join([pad + u + b"\1" for u in urls]), np.uint8).astype(np.uint64)
    sizes = np.array([len(u) + 1 for u in urls], np.int64)
    starts = np.cumsum(sizes + ORDER) - sizes
    at = np.arange(sizes.sum()) + np.repeat(starts - (np.cumsum(sizes) - sizes), sizes)
    pairs, contexts = [], []
    context = np.zeros(len(at), np.uint64)
    for order in range(ORDER + 1):
        if order:
            context = context * np.uint64(0x100000001B3) + data[at - order] + np.uint64(1)
        seen = mix(context ^ np.uint64(order << 56))
        contexts.append(seen >> np.uint64(64 - 16))
        pairs.append(mix(seen + data[at] * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - 18))
    return np.array(pairs, np.int64), np.array(contexts, np.int64), np.repeat(np.arange(len(urls)), sizes)


def log_ratio(urls: list[bytes], pair_counts: np.ndarray, context_counts: np.ndarray) -> np.ndarray:
    """Per byte: log-likelihood as a blocked URL less that as an allowed one.  Counts: (2, cells)."""
    if not urls:
        return np.zeros(0)
    pairs, contexts, of = cells_of(urls)
    logs = []
    for label in range(2):
        p = np.full(pairs.shape[1], 1 / 256)
        for order in range(ORDER + 1):
            p = (pair_counts[label][pairs[order]] + PRIOR * p) / (np.maximum(context_counts[label][contexts[order]], pair_counts[label][pairs[order]]) + PRIOR)
        logs.append(np.bincount(of, np.log(p), len(urls)))
    return (logs[1] - logs[0]) / np.bincount(of, minlength=len(urls))


def _normal(url: Column) -> Column:
    return F.translate(F.regexp_replace(F.coalesce(url, F.lit("")), r"(?s)^.*?://", ""), UPPER, LOWER)


def fit(urls: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Counts of (byte after context) and of contexts, from (url, label) rows; what is gathered is bounded by the tables' size."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, CELLS + CONTEXTS), np.int64)
        for batch in batches:
            labels = batch.column(1).to_numpy()
            texts = batch.column(0).cast(pa.binary()).to_pylist()
            for a in range(0, len(texts), 4096):
                pairs, contexts, of = cells_of(texts[a : a + 4096])
                own = labels[a : a + 4096][of]
                for label in range(2):
                    total[label, :CELLS] += np.bincount(pairs[:, own == label].ravel(), minlength=CELLS)
                    total[label, CELLS:] += np.bincount(contexts[:, own == label].ravel(), minlength=CONTEXTS)
        label, cell = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(label, pa.int32()), pa.array(cell, pa.int32()), pa.array(total[label, cell])], names=["label", "cell", "n"])

    sums = urls.mapInArrow(count, "label int, cell int, n long").groupBy("label", "cell").agg(F.sum("n").alias("n")).toArrow()
    whole = np.zeros((2, CELLS + CONTEXTS), np.float32)
    whole[sums.column("label").to_numpy(), sums.column("cell").to_numpy()] = sums.column("n").to_numpy()
    return whole[:, :CELLS], whole[:, CELLS:]


def _scored(df: DataFrame, model, name: str) -> DataFrame:
    """``df``, whose last column is the URL to score, with the score in its place."""
    sent = df.sparkSession.sparkContext.broadcast(model)  # 2.6 MB, whatever the data
    schema = T.StructType([*df.schema.fields[:-1], T.StructField(name, T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(batch.num_columns - 1).cast(pa.binary()).to_pylist()
            parts = [log_ratio(texts[a : a + 4096], *sent.value) for a in range(0, len(texts), 4096)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(np.concatenate(parts) if parts else np.zeros(0))], names=schema.fieldNames())

    return df.mapInArrow(run, schema)


def calibrate(bins: list[tuple[float, int, int]]) -> tuple[float, float]:
    """Slope and offset of a logistic curve for (score, allowed, blocked) bins, by Newton steps on the slightly shrunk likelihood; both classes weigh alike."""
    x = np.array([b[0] for b in bins])
    allowed, blocked = (np.array([b[i] for b in bins], float) for i in (1, 2))
    allowed, blocked = allowed / max(allowed.sum(), 1), blocked / max(blocked.sum(), 1)
    w = np.zeros(2)
    design = np.stack([x, np.ones_like(x)])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(w @ design, -30, 30)))
        slope = design @ (blocked * (1 - p) - allowed * p) - 1e-3 * w
        bend = (design * ((allowed + blocked) * p * (1 - p))) @ design.T + 1e-3 * np.eye(2)
        step = np.linalg.solve(bend, slope)
        w = w + step
        if np.abs(step).max() < 1e-9:
            break
    return float(w[0]), float(w[1])


def judge_urls(pages: DataFrame, id_column: str = "page_id", url_column: str = "url", rules=RULES) -> DataFrame:
    """(id, host, path, rule, verdict, score) of every row; score: the calibrated probability of a block by the models.

    A null URL, or one without ``://``, has an empty host and path, fits no rule and is scored as
    the string it is; repeated rows train and are returned as often as they come; without rows that
    rules allow and rows that they block there are no models: score 0, allowed; no rows give no rows.
    """
    url = F.col("url")
    rows = pages.select(F.col(id_column).alias("id"), F.col(url_column).cast("string").alias("url"))
    rows = rows.select("id", host_of(url).alias("host"), path_of(url).alias("path"), _normal(url).alias("normal"))
    rows = rows.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules))
    blocked = [r for r, v in rules if v == "block"]
    ruled = rows.filter("rule IS NOT NULL").select(F.col("rule").isin(blocked).cast("int").alias("label"), (F.pmod(F.xxhash64("normal"), F.lit(FOLDS)) == 0).alias("kept"), "normal")
    model = fit(ruled.filter("NOT kept").select("normal", "label"))
    held = _scored(ruled.filter("kept").select("label", "normal"), model, "score")
    bins = held.groupBy(F.round(F.col("score") / BIN).alias("bin")).agg(F.sum(1 - F.col("label")).alias("allowed"), F.sum("label").alias("blocked")).collect()  # scores are within 6 of 0: under 600 bins
    able = model[1].sum(axis=1).min() > 0 and sum(b.allowed for b in bins) and sum(b.blocked for b in bins)
    slope, offset = calibrate([(b.bin * BIN, b.allowed, b.blocked) for b in bins]) if able else (0.0, -1e9)
    out = _scored(rows.select("id", "host", "path", "rule", "normal"), model, "ratio")
    score = 1 / (1 + F.exp(-F.least(F.greatest(slope * F.col("ratio") + offset, F.lit(-500.0)), F.lit(500.0))))
    out = out.withColumn("score", score if able else F.lit(0.0))
    own = F.when(F.col("rule").isin(blocked), "block").when(F.col("rule").isNotNull(), "allow")
    return out.select("id", "host", "path", "rule", F.coalesce(own, F.when(F.col("score") > 0.5, "block").otherwise("allow")).alias("verdict"), "score")
