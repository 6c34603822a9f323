"""k-mins sketches (sampling with replacement), the baseline: k independent ranks for each item, the least of each kept."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.ranks import family_of, hash_uniform
from .sketch import WHOLE, checked_weight


@dataclass
class KMins:
    """rows: sketch_id, j (1 to k), min_rank, item_id, weight; header: sketch_id, k, n_seen, total_weight."""

    rows: DataFrame
    header: DataFrame


def kmins(df: DataFrame, item: str, weight: Column | str, k: int, family: str = "exp", seed: str = "s1", by: Column | None = None, on_negative: str = "error") -> KMins:
    """One scan: every rank's least row, combined before the shuffle."""
    base = df.select((by if by is not None else F.lit(WHOLE)).cast("string").alias("sketch_id"), F.col(item).alias("item_id"), checked_weight(weight, on_negative).alias("weight"))
    each = base.filter("weight IS NOT NULL").select("*", F.explode(F.sequence(F.lit(1), F.lit(k))).alias("j"))
    ranked = each.withColumn("rank", family_of(family).rank(hash_uniform(seed, "j", "item_id"), F.col("weight")))
    least = ranked.groupBy("sketch_id", "j").agg(F.min(F.struct("rank", "item_id", "weight")).alias("m"))
    rows = least.select("sketch_id", "j", F.col("m.rank").alias("min_rank"), F.col("m.item_id").alias("item_id"), F.col("m.weight").alias("weight"))
    header = base.groupBy("sketch_id").agg(F.lit(k).alias("k"), F.count("*").alias("n_seen"), F.sum("weight").alias("total_weight"))
    return KMins(rows, header)


def kmins_ranks(df: DataFrame, item: str, weight: Column | str, k: int, family: str = "exp", seed: str = "s1") -> DataFrame:
    """The least ranks alone, k aggregates in one row and no item kept: enough for total weights."""
    w = checked_weight(weight)
    ranks = df.select(F.col(item).alias("item_id"), w.alias("weight"))
    return ranks.agg(*[F.min(family_of(family).rank(hash_uniform(seed, F.lit(j), "item_id"), F.col("weight"))).alias(f"r{j}") for j in range(1, k + 1)]).select(F.array(*[f"r{j}" for j in range(1, k + 1)]).alias("min_ranks"))


def merge_kmins(*parts: KMins, sketch_id: str = WHOLE) -> KMins:
    """The k-mins sketch of the union; total weights are added (disjoint sets)."""
    rows, header = parts[0].rows, parts[0].header
    for p in parts[1:]:
        rows, header = rows.unionByName(p.rows), header.unionByName(p.header)
    least = rows.groupBy("j").agg(F.min(F.struct(F.col("min_rank"), "item_id", "weight")).alias("m"))
    merged = least.select(F.lit(sketch_id).alias("sketch_id"), "j", "m.min_rank", "m.item_id", "m.weight")
    return KMins(merged, header.agg(F.max("k").alias("k"), F.sum("n_seen").alias("n_seen"), F.sum("total_weight").alias("total_weight")).withColumn("sketch_id", F.lit(sketch_id)))


def _sums(sketch: KMins) -> DataFrame:
    return sketch.rows.groupBy("sketch_id").agg(F.count("*").alias("k"), F.sum("min_rank").alias("sum_rank"))


def kmins_weight(sketch: KMins) -> DataFrame:
    """Unbiased total weight: (k - 1) / sum of least ranks; standard deviation W / sqrt(k - 2)."""
    return _sums(sketch).select("sketch_id", ((F.col("k") - 1) / F.col("sum_rank")).alias("estimate"))


def kmins_weight_ml(sketch: KMins) -> DataFrame:
    """Maximum likelihood: k / sum of least ranks; bias W / (k - 1)."""
    return _sums(sketch).select("sketch_id", (F.col("k") / F.col("sum_rank")).alias("estimate"))


def kmins_inverse_weight(sketch: KMins) -> DataFrame:
    """Unbiased inverse of the total weight: the mean least rank."""
    return _sums(sketch).select("sketch_id", (F.col("sum_rank") / F.col("k")).alias("estimate"))


def kmins_ht(sketch: KMins, predicate: Column | str = "true", total: float | None = None) -> DataFrame:
    """Distinct sampled items, each over its chance to be drawn at least once in k; needs the total."""
    predicate = F.expr(predicate) if isinstance(predicate, str) else predicate
    rows = sketch.rows.join(sketch.header, "sketch_id").filter(predicate)
    whole = F.col("total_weight") if total is None else F.lit(float(total))
    once = rows.groupBy("sketch_id", "item_id").agg(F.max("weight").alias("weight"), F.max("k").alias("k"), F.max(whole).alias("total"))
    chance = F.when(F.col("weight") >= F.col("total"), F.lit(1.0)).otherwise(-F.expm1(F.col("k") * F.log1p(-F.col("weight") / F.col("total"))))
    return once.groupBy("sketch_id").agg(F.sum(F.col("weight") / chance).alias("estimate"))


def kmins_ratio(sketch: KMins, predicate: Column | str = "true", total: float | None = None) -> DataFrame:
    """The share of the k draws that satisfy the predicate, times the total; the whole set's estimate is the total itself."""
    predicate = F.expr(predicate) if isinstance(predicate, str) else predicate
    whole = F.col("total_weight") if total is None else F.lit(float(total))
    return sketch.rows.join(sketch.header, "sketch_id").groupBy("sketch_id").agg((F.max(whole) / F.max("k") * F.sum(F.when(predicate, 1).otherwise(0))).alias("estimate"))
