"""Tables of the input folder, weight policies, and sketches kept as Parquet."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.sketch import Sketch


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def whole_seconds(ts: str) -> Column:
    """The nearest whole second of a timestamp, of two the even one: what a cast of its epoch to an integer gives in SQL."""
    return F.timestamp_seconds(F.rint(F.unix_micros(F.col(ts).cast("timestamp")) / 1e6))


def save_sketch(sketch: Sketch, path: str, mode: str = "overwrite") -> None:
    """Entries and header side by side, entries in one file for each sketch-id prefix."""
    sketch.entries.withColumn("prefix", F.substring(F.md5(F.col("sketch_id")), 1, 1)).write.mode(mode).partitionBy("prefix").parquet(f"{path}/entries")
    sketch.header.write.mode(mode).parquet(f"{path}/header")


def load_sketch(spark: SparkSession, path: str) -> Sketch:
    return Sketch(spark.read.parquet(f"{path}/entries").drop("prefix"), spark.read.parquet(f"{path}/header"))


def pareto_weight(alpha: float, *key: Column | str, seed: str = "pareto") -> Column:
    """Heavy-tailed weights from the hash of a key: least weight 1, tail exponent alpha."""
    from ..functions.ranks import hash_uniform

    return F.pow(1 - hash_uniform(seed, *key), F.lit(-1.0 / alpha))
