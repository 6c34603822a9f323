"""Queries over adjusted weights, and estimate and bounds in one row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import adjusted, bounds, mle
from .sketch import Sketch


def _expr(predicate: Column | str) -> Column:
    return F.expr(predicate) if isinstance(predicate, str) else predicate


def attributes(rows: DataFrame) -> DataFrame:
    """Entries with the fields of ``attrs`` as columns of their own, for predicates."""
    return rows.select("*", "attrs.*")


def subpop_weight(adj: DataFrame, predicate: Column | str = "true") -> DataFrame:
    """Estimated weight of the items that satisfy a predicate, for each sketch; 0 if none is sampled."""
    return adj.groupBy("sketch_id").agg(F.coalesce(F.sum(F.when(_expr(predicate), F.col("adj_weight"))), F.lit(0.0)).alias("estimate"))


def weight_by(adj: DataFrame, by: list[str], mode: str = "group") -> DataFrame:
    """Estimated weight of many subpopulations at once: groups, rollup or cube."""
    grouped = {"group": adj.groupBy, "rollup": adj.rollup, "cube": adj.cube}[mode](*by)
    return grouped.agg(F.sum("adj_weight").alias("estimate"))


def selectivity(adj: DataFrame, predicate: Column | str, total: float | None = None) -> DataFrame:
    """Estimated share of the total weight; the total as known, or estimated too."""
    whole = F.sum("adj_weight") if total is None else F.lit(float(total))
    return adj.groupBy("sketch_id").agg((F.coalesce(F.sum(F.when(_expr(predicate), F.col("adj_weight"))), F.lit(0.0)) / whole).alias("estimate"))


def other_attribute(adj: DataFrame, value: Column | str, predicate: Column | str = "true") -> DataFrame:
    """Estimated sum of another attribute over a subpopulation: value times adjusted weight over weight."""
    v = F.col(value) if isinstance(value, str) else value
    return adj.groupBy("sketch_id").agg(F.coalesce(F.sum(F.when(_expr(predicate), v * F.col("adj_weight") / F.col("weight"))), F.lit(0.0)).alias("estimate"))


def moments(adj: DataFrame, predicate: Column | str = "true") -> DataFrame:
    """Estimated count, mean and variance of the weights of a subpopulation, from its estimated 0th, 1st and 2nd moment."""
    w, a, p = F.col("weight"), F.col("adj_weight"), _expr(predicate)
    part = lambda c: F.coalesce(F.sum(F.when(p, c)), F.lit(0.0))  # noqa: E731 an empty subpopulation has a count of 0, and no mean
    sums = adj.groupBy("sketch_id").agg(part(a / w).alias("count"), part(a).alias("sum"), part(a * w).alias("squares"))
    mean = F.col("sum") / F.nullif(F.col("count"), F.lit(0.0))
    return sums.select("sketch_id", "count", mean.alias("mean"), (F.col("squares") / F.nullif(F.col("count"), F.lit(0.0)) - mean * mean).alias("variance"))


def weight_ratio(adj: DataFrame, over: Column | str, under: Column | str) -> DataFrame:
    """Ratio of the estimated weights of two subpopulations."""
    part = lambda p: F.sum(F.when(_expr(p), F.col("adj_weight")))
    return adj.groupBy("sketch_id").agg((part(over) / part(under)).alias("estimate"))


def exact_weight(df: DataFrame, weight: Column | str, predicate: Column | str = "true", by: list[str] | None = None) -> DataFrame:
    """The true answer, by a scan of everything."""
    w = F.col(weight) if isinstance(weight, str) else weight
    return df.filter(_expr(predicate)).groupBy(*(by or [])).agg(F.sum(w).alias("exact"))


def choose_estimator(sketch: Sketch) -> str:
    """Subset conditioning for exponential ranks with the total known; else rank conditioning, of either family."""
    head = sketch.header.first()
    return "subset" if head["family"] == "exp" and head["total_weight"] is not None else "rank"


def adjust(sketch: Sketch, method: str = "auto") -> DataFrame:
    method = choose_estimator(sketch) if method == "auto" else method
    make = {"rank": adjusted.rank_conditioned, "prefix": adjusted.prefix_conditioned, "subset": adjusted.subset_conditioned, "ordered": adjusted.ordered_average, "chain": adjusted.subset_conditioned_chain}
    return make[method](sketch)


def estimate(sketch: Sketch, predicate: Column | str = "true", method: str = "auto", delta: float = 0.05, solver: str = "quantile") -> DataFrame:
    """(sketch_id, estimate, lower, upper, method) for a predicate over entries and their attributes."""
    opened = Sketch(attributes(sketch.entries), sketch.header, sketch.family)
    head = sketch.header.first()
    if method == "ml":
        value = mle.mle_subpop_with_total(opened, predicate) if head["total_weight"] is not None else mle.mle_subpop(opened, predicate)
    else:
        value = subpop_weight(attributes(adjust(sketch, method)), predicate)
    if head["family"] == "priority":
        limits = bounds.bounds_priority(opened, predicate, delta=delta)
    else:
        limits = bounds.bounds_subpop(opened, predicate, True if head["total_weight"] is not None else None, solver, delta)
    return value.join(limits.drop("width"), "sketch_id", "left")
