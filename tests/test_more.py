"""Laws of the chain, bounds against plain laws, streams in several batches, pruned parts."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from subweight.functions import ranks
from subweight.operators import adjusted, bounds
from subweight.operators import sketch as sk
from subweight.plans import metrics, workloads
from subweight.streaming import streams

W = np.array([5.0, 3.0, 2.0, 1.0, 1.0])


def drawn(rng):
    return lambda *at: rng.random()


def test_chain_is_unbiased_and_close():
    """Means over samples are the weights for a short chain; a long one is near exact subset conditioning."""
    rng = np.random.default_rng(5)
    sums, n = np.zeros(5), 4000
    for _ in range(n):
        order = np.argsort(rng.exponential(size=5) / W)[:3]
        sums[order] += adjusted.chain_weights(W[order], W.sum() - W[order].sum(), 5, 2, drawn(rng))
    assert sums / n == pytest.approx(W, rel=0.1)
    for redraws, steps in ((400, 1), (20, 20), (1, 400), (5, 2)):
        exact = adjusted.subset_weights(W[:3], 2.0)
        many = np.mean([adjusted.chain_weights(W[:3], 2.0, redraws, steps, drawn(rng)) for _ in range(60)], axis=0)
        assert many == pytest.approx(exact, rel=0.35 if steps == 1 else 0.12)


def sum_law(rates, tau):
    """Pr(a sum of exponentials of distinct rates is at most tau), in closed form."""
    total = 0.0
    for i, a in enumerate(rates):
        total += math.prod(b / (b - a) for j, b in enumerate(rates) if j != i) * (1 - math.exp(-a * tau))
    return total


def test_drawn_bounds_follow_the_exact_law(spark):
    """At the drawn upper bound x the closed form of the sum's law is near 0.95, at the lower one near 0.05."""
    df = spark.range(400).select(F.col("id"), (1 + F.col("id") % 7).cast("double").alias("w"))
    s = sk.bottomk(df, "id", "w", 6)
    low, high = bounds.bounds_total(s, solver="quantile", draws=2000).select("lower", "upper").first()
    head, w = s.header.first(), [r.weight for r in s.entries.orderBy("pos").collect()]
    before = np.concatenate([[0], np.cumsum(w)])
    for x, level in ((low, 0.05), (high, 0.95)):
        assert sum_law((x - before).tolist(), head.tau) == pytest.approx(level, abs=0.02)


def test_crossing_events_agree():
    """The weight solved for a draw is above a level exactly if the ranks there are too far apart: two forms of one event."""
    rng = np.random.default_rng(6)
    ins, outs, total, gap = np.array([3.0, 1.0]), np.array([2.0, 2.0, 1.0]), 20.0, 0.01
    e, f = rng.exponential(size=(300, 3)), rng.exponential(size=(300, 4))
    x = bounds.split_solutions(ins, outs, total, gap, e, f)
    s, r = np.concatenate([[0], np.cumsum(ins)]), np.concatenate([[0], np.cumsum(outs)])
    for level in (6.0, 9.0, 13.0):
        at = (f[:, :3] / (total - level - r[:3])).sum(axis=1) - (e[:, :2] / (level - s[:2])).sum(axis=1) - gap
        firm = np.abs(x - level) > 1e-6
        inside = (x > ins.sum() + 1e-6) & (x < total - outs.sum() - 1e-6)
        assert ((at < 0) == (x > level))[firm & inside].all()


def test_bounds_of_any_family_and_simulated_items():
    rng = np.random.default_rng(8)
    weights = np.concatenate([np.full(300, 1.0), np.full(20, 30.0)])
    hit = np.zeros(2)
    for _ in range(60):
        for i, (family, rank) in enumerate(((bounds.EXP_BOUNDS, rng.exponential(size=320) / weights), (bounds.PRIORITY_BOUNDS, rng.random(320) / weights))):
            order = np.argsort(rank)
            low, high = bounds.general_bounds(weights[order[:24]], rank[order[24]], 0.05, family)
            hit[i] += low <= weights.sum() <= high
    assert (hit / 60 > 0.8).all()


def test_maps_between_families(spark):
    df = spark.createDataFrame([(0.1, 2.0), (0.5, 3.0), (0.01, 40.0)], "r double, w double")
    for r in df.select("r", "w", ranks.remap_rank(F.col("r"), F.col("w"), "exp", "priority").alias("p")).collect():
        assert r.p * r.w == pytest.approx(1 - math.exp(-r.r * r.w))


def test_distinct_with_many_copies(spark):
    df = spark.range(20_000).select((F.col("id") % 300).alias("k")).unionByName(spark.range(20_000).select(F.lit(7).cast("long").alias("k")))
    got = sk.bottomk_distinct(df.repartition(5), "k", 20)
    want = sk.bottomk(spark.range(300).withColumnRenamed("id", "k"), "k", F.lit(1.0), 20)
    rows = lambda s: [(r.item_id, r.rank) for r in s.entries.orderBy("pos").collect()]
    assert rows(got) == rows(want) and got.header.first().tau == want.header.first().tau
    names = sk.bottomk_distinct(df.select(F.concat(F.lit("user"), "k").alias("k")), "k", 500).header.first()
    assert names.exact and names.n_seen == 300


def test_nested_sketches(spark):
    df = spark.range(500).select("id", (1 + F.col("id") % 9).cast("double").alias("w"))
    large, small = sk.bottomk_by(df, F.lit("g"), "id", "w", 40), sk.bottomk_by(df, F.lit("g"), "id", "w", 8)
    cut = sk.truncated(large, 8)
    assert sorted(map(tuple, cut.flat().drop("attrs").collect())) == sorted(map(tuple, small.flat().drop("attrs").collect()))
    sk.release_cached()


def test_few_parts_are_read(spark):
    """A sketch of twelve items reads the files of thirteen months at most, not all orders."""
    from subweight.plans.catalog import monthly_orders

    orders, part, catalogue, weight = monthly_orders(spark, "/root/testdata/sf0.001")
    s = sk.bottomk_partitioned(orders, part, catalogue, weight, "o_orderkey", "o_totalprice", 12)
    plan = s.entries._jdf.queryExecution().toString()
    assert "PartitionFilters: [part" in plan or "PartitionFilters: [isnotnull(part" in plan, plan[:3000]
    chosen = [r.part for r in sk.part_minima(catalogue, part, weight, "s1").orderBy("least", part).limit(13).collect()]
    read = metrics.plan_counters(orders.filter(F.col(part).isin(chosen)).select("o_orderkey"))["rows_scanned"]
    assert 0 < read < orders.count() / 2
    sk.release_cached()


def test_stream_of_several_batches(spark, tmp_path):
    """The latest snapshot holds all batches, repeats count once, and late rows are counted."""
    schema = "id long, w double, ts timestamp"
    rows = lambda ids, day: spark.createDataFrame([(i, 1.0 + i % 5) for i in ids], "id long, w double").select("id", "w", F.lit(f"2024-01-{day:02d} 00:00:00").cast("timestamp").alias("ts"))
    for i, (ids, day) in enumerate(((range(0, 60), 1), (range(40, 100), 9))):
        rows(ids, day).coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    stream = spark.readStream.schema(schema).option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    streams.stream_bottomk(stream, "id", "w", 10, f"{tmp_path}/store", f"{tmp_path}/state").awaitTermination()
    assert streams.latest_version(spark, f"{tmp_path}/store") == 1
    got = streams.read_snapshot(spark, f"{tmp_path}/store", None, 10).orderBy("pos").collect()
    want = sk.bottomk(rows(range(100), 1), "id", "w", 10).entries.orderBy("pos").collect()
    assert [r.item_id for r in got] == [r.item_id for r in want] and got[0].n_seen == 120
    for i, (ids, day) in enumerate(((range(100, 103), 9), (range(200, 205), 1)), 2):  # what is late is told by the watermark before the last
        rows(ids, day).coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    query = streams.stream_sessions(stream, "ts", "id", "w").writeStream.format("memory").queryName("late").option("checkpointLocation", f"{tmp_path}/late").trigger(availableNow=True).start()
    query.awaitTermination()
    assert streams.late_rows(query) >= 5


def test_items_without_weight_in_experiments(spark):
    """Weights of 0 or null are in no sketch of a repetition and change no estimate or total, only the counts."""
    rows = [("a", i, float(i % 7 + 1)) for i in range(40)]
    base = spark.createDataFrame(rows, "wt string, item_id long, weight double")
    more = spark.createDataFrame([*rows, ("a", 90, 0.0), ("a", 91, None)], base.schema)
    key = lambda df: sorted((r.method, r.sketch_id, round(r.estimate, 9)) for r in df.collect())
    assert key(workloads.total_estimates(more, 2, 5)) == key(workloads.total_estimates(base, 2, 5))
    header = workloads.sketches(more, 2, 5, "priority").header.collect()
    assert {(r.n_seen, r.total_weight) for r in header} == {(42, sum(w for _, _, w in rows))}
    sk.release_cached()


def test_source_gives_weights_to_a_table(spark):
    """The rows' own weights, in partitions of several ranges, wherever the ids are; repeated ids have a row each and a null one has no weight."""
    import hashlib

    from subweight.sources import pareto

    ids = [*range(5), 70_000, 70_001, 70_001, -3, 1 << 40, None]
    got = pareto.weights_of(spark.createDataFrame([(i,) for i in ids], "o_orderkey long"), "o_orderkey", 2.0).collect()
    u = lambda i: (int(hashlib.md5(f"pareto|{i}".encode()).hexdigest()[:13], 16) + 0.5) / 2.0**52
    want = [(i, None if i is None else (1 - u(i)) ** -0.5) for i in ids]
    assert sorted(got, key=str) == sorted(want, key=str)
    assert pareto.weights_of(spark.createDataFrame([], "o_orderkey long"), "o_orderkey", 2.0).count() == 0
    reader = pareto._Reader({"ranges": "0:9,20:24"})
    reader.part = 4
    parts = reader.partitions()
    assert [i for p in parts for a, b in p.ranges for i in range(a, b)] == [*range(10), *range(20, 25)]
    assert max(sum(b - a for a, b in p.ranges) for p in parts) == 4
    assert [b.num_rows for b in reader.read(pareto._Part([(0, 5)]), most=2)] == [2, 2, 1]
