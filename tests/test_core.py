"""Worked values, exact enumeration, identities and edge cases of the sketches and estimators."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from subweight.functions import ranks
from subweight.operators import adjusted, bounds, kmins, mle, query, sets
from subweight.operators import sketch as sk

W5 = (5.0, 3.0, 2.0, 1.0, 1.0)


def fixed(spark, weights, tau=0.4, total=12.0, family="exp", rank=None):
    """A sketch with given weights in rank order."""
    rows = [("all", i + 1, i, float(w), (rank or [0.05 * (j + 1) for j in range(len(weights))])[i], 0.5, (str(i),)) for i, w in enumerate(weights)]
    entries = spark.createDataFrame(rows, "sketch_id string, pos int, item_id long, weight double, rank double, u double, attrs struct<name:string>")
    header = spark.createDataFrame([("all", family, "s", len(weights), 5, total, tau, tau is None)], "sketch_id string, family string, seed string, k int, n_seen long, total_weight double, tau double, exact boolean")
    return sk.Sketch(entries, header)


def adj(df):
    return [r.adj_weight for r in df.orderBy("pos").collect()]


def test_golden_adjusted(spark):
    s = fixed(spark, (5, 3, 2))
    assert adj(adjusted.rank_conditioned(s)) == pytest.approx([5.782588213748328, 4.293038282079999, 3.631932441832188])
    assert adj(adjusted.rank_conditioned(fixed(spark, (5, 3, 2), family="priority"))) == pytest.approx([5, 3, 2.5])
    assert adj(adjusted.prefix_conditioned(s)) == pytest.approx([5.4, 3.620689655172414, 2.8474576271186445])
    assert adj(adjusted.subset_conditioned(s)) == pytest.approx([5.424107142857143, 3.683035714285715, 2.892857142857143], rel=1e-9)
    chain = np.array(adj(adjusted.subset_conditioned_chain(s, redraws=100, steps=400)))
    assert np.abs(chain - [5.424, 3.683, 2.893]).max() < 0.06
    mean = np.array(adj(adjusted.ordered_average(s, draws=4000)))
    assert np.abs(mean - [5.42, 3.68, 2.89]).max() < 0.3


def test_chances():
    w = (5.0, 3.0, 2.0)
    assert adjusted.chance_recurrence(w, 2.0) == pytest.approx(0.3555555555555555)
    assert adjusted.chance_inclusion_exclusion(w, 2.0) == pytest.approx(0.3555555555555555)
    for rest in (1e-3, 1.0, 50.0):
        w = (0.7, 2.0, 3.1, 9.0)
        exact = [x * adjusted.chance_recurrence(tuple(y for j, y in enumerate(w) if j != i), rest) / adjusted.chance_recurrence(w, rest) for i, x in enumerate(w)]
        got = adjusted.subset_weights(np.array(w), rest)
        assert got == pytest.approx(exact, rel=1e-8)
        assert got.sum() == pytest.approx(sum(w) + rest, rel=1e-9)


def prefix_weights(w, total):
    out = []
    for i, x in enumerate(w):
        others, left, miss = [y for j, y in enumerate(w) if j != i], total, 1.0
        for m in range(len(w)):
            miss *= 1 - x / left
            left -= others[m] if m < len(others) else 0
        out.append(x / (1 - miss))
    return out


def test_enumeration_of_orders():
    """Expectations over all ordered samples are the weights, and subset variances are at most prefix variances."""
    total, k = sum(W5), 3
    subset, prefix = np.zeros((2, 5)), np.zeros((2, 5))
    for order in itertools.permutations(range(5), k):
        p, left = 1.0, total
        for i in order:
            p *= W5[i] / left
            left -= W5[i]
        w = [W5[i] for i in order]
        for store, a in ((subset, adjusted.subset_weights(np.array(w), total - sum(w))), (prefix, prefix_weights(w, total))):
            for i, x in zip(order, a, strict=True):
                store[0, i] += p * x
                store[1, i] += p * x * x
    for store in (subset, prefix):
        assert store[0] == pytest.approx(W5, rel=1e-8)
    var = lambda s: s[1] - s[0] ** 2
    assert var(subset) == pytest.approx([2.91988, 2.78615, 2.51939, 1.85963, 1.85963], abs=1e-4)
    assert var(prefix) == pytest.approx([2.92189, 2.79537, 2.52618, 1.86326, 1.86326], abs=1e-4)


def one(df, c="estimate"):
    return df.first()[c]


def test_golden_likelihood(spark):
    s = fixed(spark, (5, 3, 2))
    assert one(mle.mle_total(s)) == pytest.approx(16.91115488048179, rel=1e-12)
    assert one(mle.mle_subpop(s, "item_id IN (0, 2)")) == pytest.approx(8.535533905932738)
    assert one(mle.mle_subpop_with_total(s, "item_id IN (0, 2)", clamp=False)) == pytest.approx(9.146768836303519)
    assert one(mle.mle_subpop_with_total(s, "item_id IN (0, 2)")) == pytest.approx(9)
    assert one(mle.mle_subpop(s, "false")) == 0 and one(mle.mle_subpop_with_total(s, "true")) == 12
    assert abs(one(mle.mle_total(s, redraws=50)) - 16.9) < 3


def test_small_sets_are_exact(spark):
    df = spark.createDataFrame([(i, w) for i, w in enumerate(W5)], "id long, w double")
    for family in ("exp", "priority", "uniform"):
        s = sk.bottomk(df, "id", "w", 8, family)
        assert s.header.first().exact and s.header.first().tau is None and s.entries.count() == 5
        assert sum(adj(adjusted.rank_conditioned(s, family))) == 12
    s = sk.bottomk(df, "id", "w", 8)
    for f in (adjusted.prefix_conditioned, adjusted.subset_conditioned, adjusted.ordered_average, adjusted.subset_conditioned_chain):
        assert sum(adj(f(s))) == 12
    assert one(mle.mle_total(s)) == 12
    b = bounds.bounds_total(s).first()
    assert (b.lower, b.upper) == (12, 12)
    empty = sk.bottomk(df.limit(0), "id", "w", 3)
    assert empty.entries.count() == 0 and empty.header.first().exact


def test_weight_policy(spark):
    df = spark.createDataFrame([(1, 2.0), (2, None), (3, 0.0), (4, float("nan")), (5, -3.0)], "id long, w double")
    with pytest.raises(Exception, match="negative"):
        sk.bottomk(df, "id", "w", 3)
    for policy, kept in (("drop", {1}), ("clip", {1}), ("abs", {1, 5})):
        s = sk.bottomk(df, "id", "w", 3, on_negative=policy)
        assert {r.item_id for r in s.entries.collect()} == kept and s.header.first().n_seen == 5
    with pytest.raises(Exception, match="infinite"):
        sk.bottomk(spark.createDataFrame([(1, float("inf"))], "id long, w double"), "id", "w", 3)


def pareto(spark, n=400):
    return spark.range(n).select(F.col("id"), F.pow(1 - ranks.hash_uniform("pareto", "id"), F.lit(-1 / 1.2)).alias("w"))


def keyed(s):
    return {(r.item_id, round(r.rank, 14)) for r in s.entries.collect()}


def test_merge_is_the_sketch_of_the_union(spark):
    df = pareto(spark)
    whole = sk.bottomk(df, "id", "w", 20)
    parts = [sk.bottomk(df.filter(F.col("id") % 3 == i), "id", "w", 20) for i in range(3)]
    for order in (parts, parts[::-1]):
        m = sk.merge(*order, k=20, distinct=False)
        assert keyed(m) == keyed(whole)
        assert m.header.first().tau == pytest.approx(whole.header.first().tau)
        assert m.header.first().total_weight == pytest.approx(whole.header.first().total_weight)
    nested = sk.merge(sk.merge(parts[0], parts[1], k=20, distinct=False), parts[2], k=20, distinct=False)
    assert keyed(nested) == keyed(whole)
    again = sk.merge(whole, parts[0], k=20)
    assert keyed(again) == keyed(whole)
    with pytest.raises(ValueError, match="merge"):
        sk.merge(whole, sk.bottomk(df, "id", "w", 10), k=20)


def test_families_agree_on_equal_weights(spark):
    df = spark.range(300).withColumn("w", F.lit(2.0))
    found = [{r.item_id for r in sk.bottomk(df, "id", "w", 12, f).entries.collect()} for f in ("priority", "uniform")]
    assert found[0] == found[1]
    exp = sk.bottomk(df, "id", "w", 12, "exp")
    assert exp.entries.count() == 12


def test_scale_invariance_and_prefilter(spark):
    df = pareto(spark)
    a, b = sk.bottomk(df, "id", "w", 15), sk.bottomk(df.withColumn("w", F.col("w") * 64), "id", "w", 15)
    assert [r.item_id for r in a.entries.orderBy("pos").collect()] == [r.item_id for r in b.entries.orderBy("pos").collect()]
    total = a.header.first().total_weight
    for below in ((15 + 1 + 6 * 4) / total, 1e-12):
        assert keyed(sk.bottomk(df, "id", "w", 15, below=below)) == keyed(a)


def test_plans(spark):
    df = pareto(spark)
    text = sk.ranked(df, "id", "w").orderBy("rank", "item_id").limit(9)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in text and "Python" not in text
    s = sk.bottomk_by(df.withColumn("g", F.col("id") % 5), "g", "id", "w", 7)
    plan = s.entries._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan and "Python" not in plan
    plan = mle.mle_total(s)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan


def test_cost_counters(spark):
    from subweight.plans import metrics
    from subweight.sources.io import table

    orders = table(spark, "/root/testdata/sf0.001", "orders")
    got = metrics.plan_counters(sk.ranked(orders, "o_orderkey", "o_totalprice").filter("weight IS NOT NULL").orderBy("rank", "item_id").limit(33))
    assert got["scans"] == 1 and got["rows_scanned"] == 1500 and got["exchanges"] == 0
    whole = metrics.plan_counters(orders.groupBy("o_custkey").agg(F.sum("o_totalprice")))
    assert whole["exchanges"] == 1 and whole["shuffle_rows"] > 33 and whole["shuffle_bytes"] > 0
    assert metrics.cost_counters(100, 20, 20, 200) == {"rank": 100, "prefix": 10000, "subset": 20000, "chain": 20 * (100 * 7 + 2000)}


def test_unbiased_over_seeds(spark):
    """Means over 300 seeds are within five standard errors; the variance of sums is least with subset conditioning."""
    from subweight.plans import workloads

    base = pareto(spark, 60).select(F.lit("p").alias("wt"), F.col("id").alias("item_id"), F.col("w").alias("weight"))
    reps, truth = 300, base.agg(F.sum("weight")).first()[0]
    exp, pri = workloads.sketches(base, reps, 10), workloads.sketches(base, reps, 10, "priority")
    deviation = {}
    for name in ("exp_rc", "priority_rc", "subset", "prefix"):
        rows = [r.e for r in workloads.adjusted_by(name, exp, pri).filter("item_id % 2 = 0").groupBy("sketch_id").agg(F.sum("adj_weight").alias("e")).collect()]
        rows += [0.0] * (reps - len(rows))
        half = base.filter("item_id % 2 = 0").agg(F.sum("weight")).first()[0]
        assert abs(np.mean(rows) - half) < 5 * np.std(rows) / math.sqrt(reps), name
        deviation[name] = np.std(rows)
    assert deviation["subset"] < deviation["exp_rc"] and deviation["prefix"] < deviation["exp_rc"]
    totals = [r.e for r in workloads.adjusted_by("subset", exp, pri).groupBy("sketch_id").agg(F.sum("adj_weight").alias("e")).collect()]
    assert totals == pytest.approx([truth] * reps, rel=1e-8)


def test_coverage(spark):
    """One-sided 95% bounds on a subpopulation, in 400 repetitions: neither vacuous nor wrong too often."""
    rng = np.random.default_rng(4)
    n, k, reps = 300, 30, 400
    w = (1 - rng.random(n)) ** (-1 / 1.2)
    inside = np.arange(n) % 4 == 0
    import pandas as pd

    over = under = 0
    widths = []
    for r in range(reps):
        rank = rng.exponential(size=n) / w
        o = np.argsort(rank)[: k + 1]
        g = pd.DataFrame({"sketch_id": str(r), "weight": w[o[:k]], "inside": inside[o[:k]], "rank": rank[o[:k]], "tau": rank[o[k]], "total_weight": w.sum()})
        low, high = bounds.split_bounds(g, None, 0.05, 200, "t")
        truth = w[inside].sum()
        over, under = over + (truth > high), under + (truth < low)
        widths.append((high - low) / truth)
    assert 0.02 <= over / reps <= 0.09 and 0.02 <= under / reps <= 0.09
    assert np.mean(widths) < 2


def test_total_bound_laws():
    rng = np.random.default_rng(5)
    n, k, reps = 200, 20, 250
    w = (1 - rng.random(n)) ** (-1 / 1.2)
    for make, key in ((bounds.set_bounds, lambda u: -np.log(u) / w), (bounds.priority_total_bounds, lambda u: u / w)):
        out = 0
        for _ in range(reps):
            rank = key(rng.random(n))
            o = np.argsort(rank)[: k + 1]
            low, high = make(w[o[:k]], rank[o[k]], 0.05)
            out += not low <= w.sum() <= high
        assert out / reps < 0.16
    assert bounds.poisson_tail(3, 2.0) == pytest.approx(0.857123, abs=1e-6)


def test_subpop_bounds_are_ordered(spark):
    df = pareto(spark)
    s = sk.bottomk(df, "id", "w", 40)
    p = sk.bottomk(df, "id", "w", 40, "priority")
    truth = df.filter("id % 2 = 0").agg(F.sum("w")).first()[0]
    for b in (bounds.bounds_subpop(s, "item_id % 2 = 0", True), bounds.bounds_subpop(s, "item_id % 2 = 0"), bounds.bounds_subpop(s, "item_id % 2 = 0", solver="normal"), bounds.bounds_priority(p, "item_id % 2 = 0"), bounds.bounds_priority(p, "item_id % 2 = 0", "poisson")):
        r = b.first()
        assert 0 < r.lower < r.upper and r.lower < truth * 1.2 and r.upper > truth * 0.8
    none = bounds.bounds_subpop(s, "false").first()
    assert none.lower == 0 and none.upper == pytest.approx(-math.log(0.05) / s.header.first().tau)
    whole, rest = bounds.bounds_subpop(s, "item_id % 2 = 0", True, draws=400).first(), bounds.bounds_subpop(s, "item_id % 2 = 1", True, draws=400).first()
    total = s.header.first().total_weight
    assert abs(whole.lower - (total - rest.upper)) / total < 0.05


def test_pieces_and_parts(spark):
    df = pareto(spark, 200).withColumn("item", F.col("id") % 40)
    totals = {r.item: r.w for r in df.groupBy("item").agg(F.sum("w").alias("w")).collect()}
    s = sk.bottomk_unaggregated(df, "item", ["id"], "w", 10)
    rows = s.entries.collect()
    assert len(rows) == 10 and all(r.weight == pytest.approx(totals[r.item_id]) for r in rows)
    assert s.header.first().n_seen == 40 and s.header.first().total_weight == pytest.approx(sum(totals.values()))
    parts = df.withColumn("part", F.col("id") % 30)
    catalogue = parts.groupBy("part").agg(F.sum("w").alias("pw"))
    got = sk.bottomk_partitioned(parts, "part", catalogue, "pw", "id", "w", 5)
    assert got.entries.count() == 5 and got.header.first().tau > got.entries.agg(F.max("rank")).first()[0]


def test_law_of_samplers():
    """Inclusion counts of the skip sampler and of sequential draws agree with plain heaps."""
    w, k, reps = np.array([5.0, 3, 2, 1, 1, 0.5]), 2, 6000
    counts = np.zeros((3, len(w)))
    rng = np.random.default_rng(2)
    for _ in range(reps):
        skip = sets.SkipSampler(k, rng)
        skip.feed(np.arange(3), w[:3])
        skip.feed(np.arange(3, 6), w[3:])
        for i in [r[1] for r in skip.rows()[:k]]:
            counts[0, i] += 1
        for i in np.argsort(rng.exponential(size=len(w)) / w)[:k]:
            counts[1, i] += 1
        for i in sets.sample_sequential(w, k, rng):
            counts[2, i] += 1
    for a, b in ((0, 1), (2, 1)):
        assert np.abs(counts[a] - counts[b]).max() < 5 * math.sqrt(reps / 2)


def test_with_replacement(spark):
    df = pareto(spark)
    total = df.agg(F.sum("w")).first()[0]
    s = kmins.kmins(df, "id", "w", 64)
    assert abs(one(kmins.kmins_weight(s)) / total - 1) < 0.6
    assert one(kmins.kmins_ratio(s)) == pytest.approx(total)
    parts = [kmins.kmins(df.filter(F.col("id") % 2 == i), "id", "w", 64) for i in range(2)]
    rows = lambda x: sorted((r.j, r.item_id) for r in x.rows.collect())
    assert rows(kmins.merge_kmins(*parts)) == rows(s)
    m = sets.mimic_with_replacement(sk.bottomk(df, "id", "w", 80), 60)
    assert m.rows.count() == 60 and abs(one(kmins.kmins_ht(m)) / total - 1) < 0.5


def test_redraw_and_remap(spark):
    df = spark.range(2000).select(ranks.hash_uniform("a", "id").alias("u"), F.lit(2.0).alias("w"))
    for family in ("exp", "priority"):
        r = ranks.redrawn_rank(F.col("u"), F.col("w"), F.lit(0.3), family)
        top, mean = df.agg(F.max(r), F.avg(ranks.FAMILIES[family].cdf(F.col("w"), r))).first()
        assert top <= 0.3 and mean == pytest.approx({"exp": (1 - math.exp(-0.6)) / 2, "priority": 0.3}[family], rel=0.05)
    back = df.select(F.max(F.abs(ranks.remap_rank(ranks.remap_rank(ranks.rank_exp(F.col("u"), F.col("w")), F.col("w"), "exp", "priority"), F.col("w"), "priority", "exp") - ranks.rank_exp(F.col("u"), F.col("w"))))).first()[0]
    assert back < 1e-9


def test_distances(spark):
    rows = [("x", i, float(w), float(d)) for i, (w, d) in enumerate(zip(np.random.default_rng(1).random(120) + 0.1, np.random.default_rng(2).integers(0, 30, 120), strict=True))]
    df = spark.createDataFrame(rows, "g string, id long, w double, d double")
    ads = sets.all_distances(df, "id", "w", "d", 8, "g")
    for limit in (3.0, 11.0, 40.0):
        near = sets.neighborhood(ads, limit, 8)
        direct = sk.bottomk(df.filter(F.col("d") <= limit), "id", "w", 8)
        assert keyed(near) == keyed(direct)
    truth = sum(r[2] * math.exp(-r[3] / 10) for r in rows)
    assert abs(one(sets.decayed_weight(ads, 8, lambda d: F.exp(-d / 10))) / truth - 1) < 0.8


def test_elapsed_state():
    from subweight.streaming.streams import ElapsedSketch

    rng = np.random.default_rng(3)
    rank = rng.random(200)
    e = ElapsedSketch(4)
    for i, r in enumerate(rank):
        e.add(float(i), i, 1.0, float(r))
    for since in (0, 100, 190):
        assert [x[1] for x in e.within(since)] == sorted(range(since, 200), key=lambda i: rank[i])[:5]
    assert len(e.kept) < 60


def test_queries_and_refusals(spark):
    df = pareto(spark).withColumn("kind", F.when(F.col("id") % 3 == 0, "a").otherwise("b"))
    s = sk.bottomk(df, "id", "w", 60, attrs=["kind"])
    for method in ("rank", "prefix", "subset", "ordered", "ml", "auto"):
        r = query.estimate(s, "kind = 'a'", method).first()
        assert r.lower <= r.upper and r.estimate > 0
    assert query.choose_estimator(s) == "subset"
    p = sk.bottomk(df, "id", "w", 60, "priority")
    for f in (adjusted.prefix_conditioned, adjusted.subset_conditioned, adjusted.ordered_average):
        with pytest.raises(ValueError, match="exponential"):
            f(p)
    a = adjusted.rank_conditioned(s)
    assert one(query.subpop_weight(a, "false")) == 0
    assert one(query.selectivity(a, "true")) == pytest.approx(1)


def test_families_of_bounds(spark):
    df = pareto(spark, 100)
    e, p, u = (sk.bottomk(df, "id", "w", 10, f) for f in ("exp", "priority", "uniform"))
    for f, s in ((bounds.bounds_total, p), (bounds.bounds_total, u), (bounds.bounds_priority, e), (bounds.bounds_priority_total, u)):
        with pytest.raises(ValueError, match="ranks"):
            f(s)
    with pytest.raises(ValueError, match="exponential"):
        sk.redraw_ordered(p)
    again = sk.redraw_ordered(e)
    rows = again.entries.orderBy("pos").collect()
    assert [r.item_id for r in rows] == [r.item_id for r in e.entries.orderBy("pos").collect()]
    assert all(a.rank < b.rank for a, b in zip(rows, rows[1:], strict=False)) and again.header.first().tau > rows[-1].rank
    assert sk.family_in(sk.Sketch(e.entries, e.header)) == "exp"


def test_late_and_repeated_events(spark, tmp_path):
    from subweight.streaming import streams

    df = pareto(spark, 90)
    for i in range(3):
        part = df.filter(F.col("id") % 3 == i)
        part.unionByName(part.limit(2)).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    source = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    q = streams.stream_bottomk(source, "id", "w", 12, f"{tmp_path}/store", f"{tmp_path}/state")
    q.awaitTermination()
    snap = streams.read_snapshot(spark, f"{tmp_path}/store", 2, 12)
    direct = sk.bottomk(df, "id", "w", 12)
    assert {(r.item_id, round(r.rank, 14)) for r in snap.collect()} == keyed(direct)
    assert snap.first().n_seen == 96 and snap.first().tau == pytest.approx(direct.header.first().tau)
