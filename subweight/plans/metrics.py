"""Measures of cost and accuracy over repetitions, items, groups and bounds."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def relative_error(estimates: DataFrame, by: list[str], truth: str = "truth") -> DataFrame:
    """Mean absolute relative error, bias and root mean square error relative to the truth."""
    r = F.col("estimate") / F.col(truth) - 1
    return estimates.groupBy(*by).agg(F.avg(F.abs(r)).alias("mean_abs_rel_error"), F.avg(r).alias("bias"), F.sqrt(F.avg(r * r)).alias("rmse"), F.count("*").alias("reps"))


def weight_groups(items: DataFrame, g: int, by: list[str]) -> DataFrame:
    """Items with ``grp``: g at a time in order of true weight."""
    from pyspark.sql import Window

    return items.withColumn("grp", F.floor((F.row_number().over(Window.partitionBy(*by).orderBy("weight", "item_id")) - 1) / g))


def sse_by_partition(adj: DataFrame, grouped: DataFrame, by: list[str]) -> DataFrame:
    """Sum over the groups of the squared error, for each value of ``by`` + sketch_id; groups without a sampled item count with their whole truth.

    ``adj``: by, sketch_id, item_id, adj_weight; ``grouped``: by, item_id, weight, grp.
    """
    truth = grouped.groupBy(*by, "grp").agg(F.sum("weight").alias("truth"))
    whole = truth.groupBy(*by).agg(F.sum(F.col("truth") * F.col("truth")).alias("squares"))
    est = adj.join(grouped.select(*by, "item_id", "grp"), [*by, "item_id"]).groupBy(*by, "sketch_id", "grp").agg(F.sum("adj_weight").alias("est"))
    gain = est.join(truth, [*by, "grp"]).groupBy(*by, "sketch_id").agg(F.sum(F.col("est") * F.col("est") - 2 * F.col("est") * F.col("truth")).alias("gain"))
    return gain.join(whole, by).select(*by, "sketch_id", (F.col("squares") + F.col("gain")).alias("sse"))


def item_variance(adj: DataFrame, items: DataFrame, reps: int, by: list[str]) -> DataFrame:
    """For each item the variance of its adjusted weight over ``reps`` sketches, zeros included."""
    sums = adj.groupBy(*by, "item_id").agg(F.sum("adj_weight").alias("s"), F.sum(F.col("adj_weight") * F.col("adj_weight")).alias("q"))
    rows = items.select(*by, "item_id", "weight").join(sums, [*by, "item_id"], "left").fillna(0.0, ["s", "q"])
    return rows.select(*by, "item_id", "weight", (F.col("q") / reps - 2 * F.col("weight") * F.col("s") / reps + F.col("weight") * F.col("weight")).alias("variance"))


def sum_covariances(adj: DataFrame, items: DataFrame, reps: int, by: list[str]) -> DataFrame:
    """Variance of the total, sum of item variances, and their difference: twice the sum of pair covariances."""
    total = items.groupBy(*by).agg(F.sum("weight").alias("truth"))
    est = adj.groupBy(*by, "sketch_id").agg(F.sum("adj_weight").alias("est")).join(total, by)
    whole = est.groupBy(*by).agg(F.avg((F.col("est") - F.col("truth")) ** 2).alias("total_variance"))
    parts = item_variance(adj, items, reps, by).groupBy(*by).agg(F.sum("variance").alias("sum_variances"))
    return whole.join(parts, by).withColumn("sum_covariances", F.col("total_variance") - F.col("sum_variances"))


def bound_quality(bounds: DataFrame, by: list[str], truth: str = "truth") -> DataFrame:
    """Normalised bounds and width, squared errors of the bounds, and rates: inside, over the upper, under the lower bound."""
    t, lo, hi = F.col(truth), F.col("lower"), F.col("upper")
    return bounds.groupBy(*by).agg(
        F.avg(lo / t).alias("lower"),
        F.avg(hi / t).alias("upper"),
        F.avg((hi - lo) / t).alias("width"),
        F.avg((hi / t - 1) ** 2).alias("upper_sq_error"),
        F.avg((lo / t - 1) ** 2).alias("lower_sq_error"),
        F.avg(F.when((lo <= t) & (t <= hi), 1.0).otherwise(0.0)).alias("in_bounds"),
        F.avg(F.when(t > hi, 1.0).otherwise(0.0)).alias("over_upper"),
        F.avg(F.when(t < lo, 1.0).otherwise(0.0)).alias("under_lower"),
    )


def with_replacement_theory(k: int) -> dict[str, float]:
    """Closed forms of the with-replacement total: relative deviation, mean absolute relative error, bias of maximum likelihood."""
    return {"deviation": 1 / math.sqrt(k - 2), "mean_abs_rel_error": math.sqrt(2 / (math.pi * (k - 2))), "ml_bias": 1 / (k - 1)}


def cost_counters(k: int, redraws: int, steps: int, nodes: int) -> dict[str, int]:
    """Operations on one sketch: rank conditioning, prefix conditioning, exact subset conditioning, the chain."""
    log = max(1, math.ceil(math.log2(max(2, k))))
    return {"rank": k, "prefix": k * k, "subset": nodes * k, "chain": steps * (k * log + redraws * k)}


def plan_counters(df: DataFrame) -> dict[str, int]:
    """Run ``df`` and count: files' rows scanned, rows and bytes written to shuffles, exchanges and scans (passes) in the plan that ran."""
    df._jdf.collectToPython()
    found = {"rows_scanned": 0, "scans": 0, "shuffle_rows": 0, "shuffle_bytes": 0, "exchanges": 0}

    def value(metrics, name: str) -> int:
        return int(metrics.apply(name).value()) if metrics.contains(name) else 0

    def walk(node) -> None:
        name, metrics = node.nodeName(), node.metrics()
        if name == "AdaptiveSparkPlan":
            return walk(node.executedPlan())
        if name.startswith(("ShuffleQueryStage", "BroadcastQueryStage", "ResultQueryStage", "TableCacheQueryStage")):
            return walk(node.plan())
        if name.startswith("ReusedExchange"):
            return None
        if name.startswith("Scan "):
            found["scans"] += 1
            found["rows_scanned"] += value(metrics, "numOutputRows")
        if name == "Exchange":
            found["exchanges"] += 1
            found["shuffle_rows"] += value(metrics, "shuffleRecordsWritten")
            found["shuffle_bytes"] += value(metrics, "shuffleBytesWritten")
        children = node.children()
        for i in range(children.size()):
            walk(children.apply(i))
        return None

    walk(df._jdf.queryExecution().executedPlan())
    return found
