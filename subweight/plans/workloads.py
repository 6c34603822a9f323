"""The experiments on the given tables: each returns a tidy table of measures.

A repetition is another seed of the hash.  Repetitions, weights and sketches run side by side: the
small base table times the repetitions is ranked and cut to sketches in one pass.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.ranks import family_of, hash_uniform
from ..operators import adjusted, bounds, kmins, mle, query, sets
from ..operators import sketch as sk
from ..sources.io import pareto_weight, table
from . import metrics


def base_weights(spark: SparkSession, sf_dir: str, n: int | None = 1000, alphas: tuple[float, ...] = (1.0, 1.2, 2.0), uniform: bool = True) -> DataFrame:
    """(wt, item_id, weight): orders under heavy-tailed weights of each exponent, and uniform ones; all orders, or the n items that an experiment is defined on."""
    rows = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("item_id"))
    rows = rows if n is None else rows.filter(F.col("item_id") < n)
    parts = [rows.select(F.lit(f"pareto{a:g}").alias("wt"), "item_id", pareto_weight(a, "item_id").alias("weight")) for a in alphas]
    if uniform:
        parts.append(rows.select(F.lit("uniform").alias("wt"), "item_id", hash_uniform("pareto", "item_id").alias("weight")))
    return reduce(DataFrame.unionByName, parts)


def natural_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(wt, item_id, weight) of real columns: lengths of documents, values of events, prices of orders."""
    d, e, o = (table(spark, sf_dir, t) for t in ("documents", "events", "orders"))
    return d.select(F.lit("n_chars").alias("wt"), F.col("doc_id").alias("item_id"), F.col("n_chars").cast("double").alias("weight")).unionByName(e.select(F.lit("value").alias("wt"), F.col("event_id").alias("item_id"), F.col("value").alias("weight"))).unionByName(o.select(F.lit("totalprice").alias("wt"), F.col("o_orderkey").alias("item_id"), F.col("o_totalprice").alias("weight")))


def truth_of(base: DataFrame) -> DataFrame:
    return base.groupBy("wt").agg(F.sum("weight").alias("truth"))


def repeated(base: DataFrame, reps: int) -> DataFrame:
    """The base once for each repetition; sketch_id is wt#rep."""
    return base.crossJoin(base.sparkSession.range(reps).withColumnRenamed("id", "rep")).withColumn("sketch_id", F.concat_ws("#", "wt", "rep"))


def sketches(base: DataFrame, reps: int, k: int, family: str = "exp", seed: str = "w") -> sk.Sketch:
    """reps sketches of each weight; items without weight are counted and never sampled."""
    rows = repeated(base, reps).withColumn("weight", sk.checked_weight("weight")).withColumn("u", hash_uniform(seed, "rep", "item_id"))
    rows = rows.select("sketch_id", "item_id", "weight", family_of(family).rank(F.col("u"), F.col("weight")).alias("rank"), "u", F.struct("wt").alias("attrs"))
    return sk.top_by(rows, k, family, seed)


def kmins_sketches(base: DataFrame, reps: int, k: int, seed: str = "w") -> kmins.KMins:
    each = repeated(base, reps).withColumn("weight", sk.checked_weight("weight")).filter("weight IS NOT NULL").withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(k)))).withColumn("rank", -F.log(hash_uniform(seed, "rep", "j", "item_id")) / F.col("weight"))
    least = each.groupBy("sketch_id", "j").agg(F.min(F.struct("rank", "item_id", "weight")).alias("m")).select("sketch_id", "j", F.col("m.rank").alias("min_rank"), F.col("m.item_id").alias("item_id"), F.col("m.weight").alias("weight"))
    header = repeated(base, reps).groupBy("sketch_id").agg(F.lit(k).alias("k"), F.count("*").alias("n_seen"), F.sum("weight").alias("total_weight"))
    return kmins.KMins(least, header)


def _wt(df: DataFrame) -> DataFrame:
    return df.withColumn("wt", F.substring_index("sketch_id", "#", 1))


def _stack(parts: dict[str, DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, [df.withColumn("method", F.lit(name)) for name, df in parts.items()])


def total_estimates(base: DataFrame, reps: int, k: int) -> DataFrame:
    """(sketch_id, estimate, method) of the total weight by the four estimators that need no total."""
    exp, pri = sketches(base, reps, k), sketches(base, reps, k, "priority")
    return _stack({"exp_rc": query.subpop_weight(adjusted.rank_conditioned(exp, "exp")), "priority_rc": query.subpop_weight(adjusted.rank_conditioned(pri, "priority")), "exp_ml": mle.mle_total(exp), "with_replacement": kmins.kmins_weight(kmins_sketches(base, reps, k))})


def run_total_error(spark: SparkSession, sf_dir: str, reps: int = 20, ks: tuple[int, ...] = (4, 16, 64), base: DataFrame | None = None) -> DataFrame:
    """Error of the total against k: rows (wt, k, method, mean_abs_rel_error, bias, rmse, reps)."""
    base = base_weights(spark, sf_dir) if base is None else base
    est = reduce(DataFrame.unionByName, [total_estimates(base, reps, k).withColumn("k", F.lit(k)) for k in ks])
    return metrics.relative_error(_wt(est).join(truth_of(base), "wt"), ["wt", "k", "method"])


def total_bounds(base: DataFrame, reps: int, k: int, delta: float = 0.05, more: bool = False) -> DataFrame:
    exp, pri = sketches(base, reps, k), sketches(base, reps, k, "priority")
    parts = {"exp_order_normal": bounds.bounds_total(exp, delta=delta), "with_replacement_normal": bounds.bounds_kmins(kmins_sketches(base, reps, k), delta), "priority_chernoff": bounds.bounds_priority(pri, delta=delta)}
    if more:
        parts |= {"exp_set": bounds.bounds_total(exp, "set", delta=delta), "exp_order_quantile": bounds.bounds_total(exp, solver="quantile", delta=delta), "priority_total": bounds.bounds_priority_total(pri, delta), "priority_poisson": bounds.bounds_priority(pri, tail="poisson", delta=delta)}
    return _stack({n: b.select("sketch_id", "lower", "upper") for n, b in parts.items()})


def run_total_bounds(spark: SparkSession, sf_dir: str, reps: int = 20, ks: tuple[int, ...] = (16, 64), more: bool = False, base: DataFrame | None = None) -> DataFrame:
    """Bounds on the total: normalised bounds and width, and the rate inside, against k."""
    base = base_weights(spark, sf_dir) if base is None else base
    got = reduce(DataFrame.unionByName, [total_bounds(base, reps, k, more=more).withColumn("k", F.lit(k)) for k in ks])
    return metrics.bound_quality(_wt(got).join(truth_of(base), "wt"), ["wt", "k", "method"])


def run_in_bounds(spark: SparkSession, sf_dir: str, reps: int = 20, ks: tuple[int, ...] = (16, 64)) -> DataFrame:
    """The rate inside, averaged over k."""
    each = run_total_bounds(spark, sf_dir, reps, ks, base=base_weights(spark, sf_dir, uniform=False))
    return each.groupBy("wt", "method").agg(F.avg("in_bounds").alias("in_bounds"), F.max(F.greatest("over_upper", "under_lower")).alias("worst_side"))


def adjusted_by(name: str, exp: sk.Sketch, pri: sk.Sketch, chain: tuple[int, int] = (20, 20)) -> DataFrame:
    make = {
        "exp_rc": lambda: adjusted.rank_conditioned(exp, "exp"),
        "priority_rc": lambda: adjusted.rank_conditioned(pri, "priority"),
        "subset_chain": lambda: adjusted.subset_conditioned_chain(exp, redraws=chain[0], steps=chain[1]),
        "subset": lambda: adjusted.subset_conditioned(exp),
        "prefix": lambda: adjusted.prefix_conditioned(exp),
        "ordered": lambda: adjusted.ordered_average(exp, draws=50),
    }
    return make[name]().select("sketch_id", "item_id", "adj_weight")


def with_replacement_adjusted(base: DataFrame, reps: int, k: int) -> dict[str, DataFrame]:
    """Adjusted weights of the with-replacement baselines that know the total."""
    s = kmins_sketches(base, reps, k)
    rows = s.rows.join(s.header, "sketch_id").groupBy("sketch_id", "item_id").agg(F.max("weight").alias("weight"), F.count("*").alias("n"), F.max("k").alias("k"), F.max("total_weight").alias("w"))
    return {"wr_ht": rows.select("sketch_id", "item_id", F.when(F.col("weight") >= F.col("w"), F.col("weight")).otherwise(F.col("weight") / -F.expm1(F.col("k") * F.log1p(-F.col("weight") / F.col("w")))).alias("adj_weight")), "wr_ratio": rows.select("sketch_id", "item_id", (F.col("w") * F.col("n") / F.col("k")).alias("adj_weight"))}


def run_partition_error(
    spark: SparkSession,
    sf_dir: str,
    reps: int = 10,
    ks: tuple[int, ...] = (40,),
    gs: tuple[int, ...] = (1, 10, 100, 1000),
    methods: tuple[str, ...] = ("exp_rc", "priority_rc", "subset_chain", "subset", "prefix"),
    n: int | None = None,
    alphas: tuple[float, ...] = (1.2, 2.0),
    baselines: bool = False,
    chain: tuple[int, int] = (20, 20),
) -> DataFrame:
    """Sum of squared errors over groups of g items in order of weight: rows (wt, k, g, method, sse relative to the squared total).

    The smaller sketches are parts of the largest, and all group sizes are worked out in one pass.
    """
    base = base_weights(spark, sf_dir, n, alphas, uniform=False)
    exp, pri = sketches(base, reps, max(ks)), sketches(base, reps, max(ks), "priority")
    every = []
    for k in ks:
        parts = {m: adjusted_by(m, sk.truncated(exp, k), sk.truncated(pri, k), chain) for m in methods} | (with_replacement_adjusted(base, reps, k) if baselines else {})
        every.append(_wt(_stack(parts)).withColumn("sketch_id", F.concat_ws("@", "method", F.lit(k), "sketch_id")).drop("method"))
    sizes = F.explode(F.array(*[F.lit(g) for g in gs])).alias("g")
    adj = reduce(DataFrame.unionByName, every).select("*", sizes)
    grouped = metrics.weight_groups(base, 1, ["wt"]).select("wt", "item_id", "weight", F.col("grp").alias("place"), sizes).withColumn("grp", F.floor(F.col("place") / F.col("g"))).drop("place")
    sse = metrics.sse_by_partition(adj, grouped, ["wt", "g"])
    tag = F.split("sketch_id", "@")
    mean = sse.groupBy("wt", "g", tag[0].alias("method"), tag[1].cast("int").alias("k")).agg(F.avg("sse").alias("sse"))
    return mean.join(truth_of(base), "wt").select("wt", "k", "g", "method", (F.col("sse") / F.col("truth") ** 2).alias("rel_sse"))


def run_chain_settings(spark: SparkSession, sf_dir: str, reps: int = 5, k: int = 500, settings: tuple[tuple[int, int], ...] = ((400, 1), (20, 20), (1, 400), (5, 2)), gs: tuple[int, ...] = (1, 5000), n: int | None = None) -> DataFrame:
    """The chain's settings beside exact subset conditioning."""
    parts = [run_partition_error(spark, sf_dir, reps, (k,), gs, ("subset_chain",), n, chain=s).withColumn("method", F.lit(f"chain_{s[0]}_{s[1]}")) for s in settings]
    return reduce(DataFrame.unionByName, [*parts, run_partition_error(spark, sf_dir, reps, (k,), gs, ("subset", "exp_rc"), n)])


def run_subpop_bounds(spark: SparkSession, sf_dir: str, reps: int = 5, ks: tuple[int, ...] = (40,), g: int = 200, n: int | None = 1000, alphas: tuple[float, ...] = (1.0, 1.2, 2.0), draws: int = 200, delta: float = 0.05) -> DataFrame:
    """Bounds on every group of g items in order of weight, with and without the total, and by priority ranks: normalised, and averaged over all groups and repetitions."""
    base = metrics.weight_groups(base_weights(spark, sf_dir, n, alphas, uniform=False), g, ["wt"])
    groups = base.groupBy("wt", "grp").agg(F.sum("weight").alias("truth"))
    own = base.select(F.col("wt").alias("own_wt"), F.col("item_id").alias("own_id"), F.col("grp").alias("own_grp"))
    each = groups.select(F.col("wt").alias("of"), "grp")

    def by_group(s: sk.Sketch) -> sk.Sketch:
        """The sketch once for each group, beside whether an entry is in it."""
        name = F.concat_ws("#", "sketch_id", "grp")
        e = s.entries.join(own, (F.col("attrs.wt") == F.col("own_wt")) & (F.col("item_id") == F.col("own_id"))).join(each, F.col("own_wt") == F.col("of"))
        e = e.withColumn("chosen", F.col("own_grp") == F.col("grp")).withColumn("sketch_id", name)
        h = s.header.withColumn("of_wt", F.substring_index("sketch_id", "#", 1)).join(each, F.col("of_wt") == F.col("of")).withColumn("sketch_id", name)
        return sk.Sketch(e.select(*s.entries.columns, "chosen"), h.select(*s.header.columns), s.family)

    exp, pri = sketches(base.drop("grp"), reps, max(ks)), sketches(base.drop("grp"), reps, max(ks), "priority")
    got = []
    for k in ks:
        one, two = by_group(sk.truncated(exp, k)), by_group(sk.truncated(pri, k))
        parts = {
            "exp_total_known": bounds.bounds_subpop(one, "chosen", True, delta=delta, draws=draws),
            "exp_total_unknown": bounds.bounds_subpop(one, "chosen", None, delta=delta, draws=draws),
            "priority_chernoff": bounds.bounds_priority(two, "chosen", delta=delta),
        }
        got.append(_stack({m: b.select("sketch_id", "lower", "upper") for m, b in parts.items()}).withColumn("k", F.lit(k)))
    rows = _wt(reduce(DataFrame.unionByName, got)).withColumn("grp", F.substring_index("sketch_id", "#", -1).cast("long"))
    return metrics.bound_quality(rows.join(groups, ["wt", "grp"]), ["wt", "k", "method"])


def best_sum_of_variances(base: DataFrame, size: int) -> DataFrame:
    """(wt, best): the least sum of per-item variances of any sample of that expected size: each item by its weight over a threshold, the heaviest for certain."""
    order = Window.partitionBy("wt").orderBy(F.desc("weight"), "item_id")
    rows = base.withColumn("certain", F.row_number().over(order) - 1).withColumn("left", F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
    cut = rows.filter(F.col("certain") < size).withColumn("threshold", F.col("left") / (size - F.col("certain"))).filter(F.col("weight") <= F.col("threshold"))
    threshold = cut.groupBy("wt").agg(F.min(F.struct("certain", "threshold")).alias("c")).select("wt", "c.certain", "c.threshold")
    light = rows.select("wt", "weight", F.col("certain").alias("place")).join(threshold, "wt").filter(F.col("place") >= F.col("certain"))
    return light.groupBy("wt").agg(F.sum(F.col("weight") * (F.col("threshold") - F.col("weight"))).alias("best"))


def run_item_variance(spark: SparkSession, sf_dir: str, reps: int = 20, k: int = 40, methods: tuple[str, ...] = ("exp_rc", "priority_rc"), n: int | None = 1000) -> DataFrame:
    """Sum of per-item variances, variance of the total and their difference (twice the sum of covariances) relative to the squared total, beside the least sum at size k - 1 and the entries a method keeps and uses."""
    base = base_weights(spark, sf_dir, n, uniform=False)
    exp, pri = sketches(base, reps, k), sketches(base, reps, k, "priority")
    best, truth = best_sum_of_variances(base, k - 1), truth_of(base)
    out = []
    for m in methods:
        adj = _wt(adjusted_by(m, exp, pri))
        got = metrics.sum_covariances(adj, base, reps, ["wt"])
        kept = adj.groupBy("wt", "sketch_id").agg(F.count("*").alias("n")).groupBy("wt").agg(F.avg("n").alias("adjusted_items"))
        # rank conditioning needs the next rank beside its k items; conditioning on the set of the others does not
        out.append(got.join(kept, "wt").withColumn("method", F.lit(m)).withColumn("ranks_used", F.lit(k + 1 if m.endswith("_rc") else k)))
    rows = reduce(DataFrame.unionByName, out).join(best, "wt").join(truth, "wt")
    share = lambda c: (F.col(c) / F.col("truth") ** 2).alias(c)
    return rows.select("wt", "method", share("total_variance"), share("sum_variances"), share("sum_covariances"), share("best"), "adjusted_items", F.col("ranks_used").cast("long").alias("ranks_used"))


def run_event_shares(spark: SparkSession, sf_dir: str, k: int = 256) -> DataFrame:
    """Share of the value by kind of event and by hour, estimated from one sketch, beside the exact one."""
    ev = table(spark, sf_dir, "events").withColumn("hour", F.hour(F.col("ts").cast("timestamp")))
    adj = query.attributes(adjusted.rank_conditioned(sk.bottomk(ev, "event_id", "value", k, attrs=["event_type", "hour", "props"])))
    parts = []
    for name, c in (("event_type", F.col("event_type")), ("hour_of_day", F.col("hour").cast("string")), ("small_key", (F.get_json_object("props", "$.k").cast("int") < 10).cast("string"))):
        est = adj.groupBy(c.alias("part")).agg(F.sum("adj_weight").alias("estimate"))
        exact = ev.groupBy(c.alias("part")).agg(F.sum("value").alias("exact"))
        parts.append(exact.join(est, "part", "left").select(F.lit(name).alias("attribute"), "part", "exact", F.coalesce("estimate", F.lit(0.0)).alias("estimate")))
    return reduce(DataFrame.unionByName, parts)


def run_region_totals(spark: SparkSession, sf_dir: str, k: int = 256) -> DataFrame:
    """Total price of orders by region: subset-conditioned estimates from one sketch, joined to its dimensions, beside the exact totals."""
    o = table(spark, sf_dir, "orders")
    s = sk.bottomk(o, "o_orderkey", "o_totalprice", k, attrs=["o_custkey"])
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    dims = c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "r_name")
    adj = query.attributes(adjusted.subset_conditioned(s)).join(dims, F.col("o_custkey") == F.col("c_custkey"))
    exact = o.join(dims, F.col("o_custkey") == F.col("c_custkey")).groupBy("r_name").agg(F.sum("o_totalprice").alias("exact"))
    regions = r.select(F.col("r_name").alias("of"))
    entries = query.attributes(s.entries).join(dims, F.col("o_custkey") == F.col("c_custkey")).crossJoin(F.broadcast(regions)).withColumn("sketch_id", F.col("of"))  # k rows, five regions
    tagged = sk.Sketch(entries, s.header.crossJoin(regions).withColumn("sketch_id", F.col("of")).drop("of"), s.family)
    limits = bounds.bounds_subpop(tagged, F.col("r_name") == F.col("of"), True).select(F.col("sketch_id").alias("r_name"), "lower", "upper")
    return exact.join(adj.groupBy("r_name").agg(F.sum("adj_weight").alias("estimate")), "r_name", "left").join(limits, "r_name", "left")


def run_unaggregated(spark: SparkSession, sf_dir: str, piece: list[str], pieces: DataFrame, k: int = 64) -> DataFrame:
    """Estimated total from pieces: two passes beside the pre-aggregated baseline and the exact total."""
    two = query.subpop_weight(adjusted.rank_conditioned(sk.bottomk_unaggregated(pieces, "l_partkey", piece, "l_extendedprice", k), "exp"))
    pre = query.subpop_weight(adjusted.rank_conditioned(sk.bottomk_preagg(pieces, "l_partkey", "l_extendedprice", k), "exp"))
    exact = pieces.agg(F.sum("l_extendedprice").alias("exact"))
    return _stack({"two_pass": two, "pre_aggregated": pre}).crossJoin(exact).select("method", "estimate", "exact")


def run_baskets(spark: SparkSession, sf_dir: str, k: int = 64) -> DataFrame:
    """Union, intersection and likeness of the sets of parts of each pair of return flags, from coordinated sketches, beside the exact weights.

    The baskets are of lines of more than 45 pieces: nearly every part has some line of each flag, so
    that without a condition on lines all sets would be the same.
    """
    parts, li = table(spark, sf_dir, "part"), table(spark, sf_dir, "lineitem").filter("l_quantity > 45")
    own = {f: parts.join(li.filter(F.col("l_returnflag") == f), F.col("p_partkey") == F.col("l_partkey"), "left_semi") for f in ("A", "N", "R")}
    made = {f: sk.bottomk(d, "p_partkey", "p_retailprice", k) for f, d in own.items()}
    out = []
    for a, b in (("A", "N"), ("A", "R"), ("N", "R")):
        union = own[a].unionByName(own[b]).distinct().agg(F.sum("p_retailprice").alias("exact_union"))
        common = own[a].join(own[b].select("p_partkey"), "p_partkey", "left_semi").agg(F.sum("p_retailprice").alias("exact_intersection"))
        out.append(sets.set_relations(made[a], made[b], k).crossJoin(union).crossJoin(common).withColumn("pair", F.lit(a + b)))
    return reduce(DataFrame.unionByName, out)


def sampling_baseline(df: DataFrame, weight: Column | str, fraction: float, seed: int = 1) -> DataFrame:
    """Uniform row sampling, scaled up; for comparison only."""
    return df.sample(fraction=fraction, seed=seed).agg((F.sum(weight) / fraction).alias("estimate"))
