"""Maximum-likelihood estimates from exponential bottom-k sketches: roots of one decreasing function, as expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.ranks import hash_uniform, redrawn_rank
from ..functions.solve import bisect, inverse_sum
from .sketch import Sketch


def _expr(predicate: Column | str) -> Column:
    return F.expr(predicate) if isinstance(predicate, str) else predicate


def split_sums(sketch: Sketch, predicate: Column | str = "true") -> DataFrame:
    """One row a sketch: header, and in rank order the weight before each item of the subpopulation (ins, c of them, sum_in) and before each other one (outs, a, sum_out); last_in, last_out: their largest ranks."""
    inside = _expr(predicate)
    before = Window.partitionBy("sketch_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    rows = sketch.flat().withColumn("inside", F.coalesce(inside, F.lit(False)))
    mine, other = F.when(F.col("inside"), F.col("weight")).otherwise(0.0), F.when(F.col("inside"), 0.0).otherwise(F.col("weight"))
    rows = rows.withColumn("before_in", F.coalesce(F.sum(mine).over(before), F.lit(0.0))).withColumn("before_out", F.coalesce(F.sum(other).over(before), F.lit(0.0)))
    keep = lambda flag, c: F.transform(F.sort_array(F.collect_list(F.when(F.col("inside") == flag, F.struct("pos", F.col(c).alias("s"))))), lambda x: x["s"])
    return rows.groupBy("sketch_id").agg(
        *[F.first(c).alias(c) for c in ("family", "k", "n_seen", "total_weight", "tau", "exact")],
        keep(True, "before_in").alias("ins"),
        keep(False, "before_out").alias("outs"),
        F.coalesce(F.sum(mine), F.lit(0.0)).alias("sum_in"),
        F.coalesce(F.sum(other), F.lit(0.0)).alias("sum_out"),
        F.count_if("inside").alias("c"),
        F.count_if(~F.col("inside")).alias("a"),
        F.max("rank").alias("last"),
        F.coalesce(F.max(F.when(F.col("inside"), F.col("rank"))), F.lit(0.0)).alias("last_in"),
        F.coalesce(F.max(F.when(~F.col("inside"), F.col("rank"))), F.lit(0.0)).alias("last_out"),
    )


def _unknown(ins: Column, tau: Column) -> Column:
    """Root of: sum of 1 / (x - s) over ``ins`` equals tau."""
    last, n = F.element_at(ins, -1), F.size(ins)
    return bisect(lambda x: inverse_sum(x, ins) > tau, last + 1 / tau, last + n / tau)


def mle_total(sketch: Sketch, redraws: int = 0, seed: str = "ml") -> DataFrame:
    """Likeliest total weight; with ``redraws`` the mean over so many redraws of the ranks below tau."""
    if redraws:
        return _redrawn(sketch, None, redraws, seed, True)
    row = split_sums(sketch)
    sums = F.concat("ins", F.array("sum_in"))
    return row.select("sketch_id", F.when(F.col("exact"), F.col("sum_in")).otherwise(_unknown(sums, F.col("tau"))).alias("estimate"))


def mle_subpop(sketch: Sketch, predicate: Column | str, redraws: int = 0, clamp: bool = True, seed: str = "ml") -> DataFrame:
    """Likeliest weight of a subpopulation, total unknown; clamped to at least what was sampled of it."""
    if redraws:
        return _redrawn(sketch, predicate, redraws, seed, clamp)
    return _subpop(split_sums(sketch, predicate), clamp)


def _subpop(row: DataFrame, clamp: bool) -> DataFrame:
    root = F.when(F.col("c") == 0, F.lit(0.0)).otherwise(_unknown(F.col("ins"), F.col("tau")))
    value = F.when(F.col("exact"), F.col("sum_in")).otherwise(F.greatest(root, F.col("sum_in")) if clamp else root)
    return row.select("sketch_id", value.alias("estimate"))


def _redrawn(sketch: Sketch, predicate: Column | str | None, redraws: int, seed: str, clamp: bool) -> DataFrame:
    flat = sketch.flat().crossJoin(sketch.entries.sparkSession.range(1, redraws + 1).withColumnRenamed("id", "draw"))  # k rows times the draws
    extra = [c for c in sketch.entries.columns if c not in ("sketch_id", "pos", "item_id", "weight", "rank", "u", "attrs")]
    rank = F.when(F.col("exact"), F.col("rank")).otherwise(redrawn_rank(hash_uniform(seed, "draw", "item_id"), F.col("weight"), F.col("tau")))
    rows = flat.withColumn("rank", rank).withColumn("sketch_id", F.concat_ws("#", "sketch_id", "draw"))
    order = Window.partitionBy("sketch_id").orderBy("rank", "item_id")
    again = Sketch(rows.withColumn("pos", F.row_number().over(order)).select("sketch_id", "pos", "item_id", "weight", "rank", "u", "attrs", *extra), rows.select("sketch_id", "family", "seed", "k", "n_seen", "total_weight", "tau", "exact").distinct(), sketch.family)
    each = mle_total(again) if predicate is None else mle_subpop(again, predicate, clamp=clamp)
    return each.groupBy(F.substring_index("sketch_id", "#", 1).alias("sketch_id")).agg(F.avg("estimate").alias("estimate"))


def mle_subpop_with_total(sketch: Sketch, predicate: Column | str, total: float | None = None, clamp: bool = True) -> DataFrame:
    """Likeliest weight of a subpopulation with the total known: the sums of 1 / rate of both sides are equal; needs no tau."""
    row = split_sums(sketch, predicate)
    if total is not None:
        row = row.withColumn("total_weight", F.lit(float(total)))
    whole, low, high = F.col("total_weight"), F.element_at("ins", -1), F.col("total_weight") - F.element_at("outs", -1)
    root = bisect(lambda x: inverse_sum(x, F.col("ins")) > inverse_sum(whole - x, F.col("outs")), low, high)
    value = F.when(F.col("c") == 0, F.lit(0.0)).when(F.col("a") == 0, whole).otherwise(root)
    if clamp:
        value = F.least(F.greatest(value, F.col("sum_in")), whole - F.col("sum_out"))
    return row.select("sketch_id", F.when(F.col("exact"), F.col("sum_in")).otherwise(value).alias("estimate"))
