"""The methods in SQL: functions that become part of the plan, sketches as views, and table functions over sketches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .adjusted import subset_weights
from .bounds import split_bounds
from .sketch import Sketch

#: Temporary SQL functions: name, parameters and result, body.
FUNCTIONS = (
    ("hash_uniform", "(seed STRING, id STRING) RETURNS DOUBLE", "(cast(conv(substring(md5(concat_ws('|', seed, id)), 1, 13), 16, 10) AS BIGINT) + 0.5D) / 4503599627370496D"),
    ("rank_exp", "(u DOUBLE, w DOUBLE) RETURNS DOUBLE", "-ln(u) / w"),
    ("rank_priority", "(u DOUBLE, w DOUBLE) RETURNS DOUBLE", "u / w"),
    ("adj_rc_exp", "(w DOUBLE, tau DOUBLE) RETURNS DOUBLE", "coalesce(w / -expm1(-w * tau), w)"),
    ("adj_rc_priority", "(w DOUBLE, tau DOUBLE) RETURNS DOUBLE", "coalesce(greatest(w, 1 / tau), w)"),
)


@udtf(returnType="sketch_id string, item_id long, weight double, adj_weight double")
class SubsetConditioned:
    """Subset-conditioned weights of one sketch: TABLE(sketch_id, item_id, weight, total_weight) PARTITION BY sketch_id ORDER BY pos.

    Executors get the numeric functions by value and need no copy of the package.
    """

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((row["sketch_id"], row["item_id"], row["weight"], row["total_weight"]))

    def terminate(self):
        if self.rows:
            w = np.array([r[2] for r in self.rows])
            if self.rows[0][3] is None:
                raise ValueError("subset conditioning needs the total weight")
            rest = self.rows[0][3] - w.sum()
            for (sketch, item, weight, _), a in zip(self.rows, subset_weights(w, rest) if rest > 0 else w, strict=True):
                yield sketch, item, weight, float(a)


@udtf(returnType="sketch_id string, lower double, upper double")
class SubpopBounds:
    """Bounds on a subpopulation's weight with the total known: TABLE(sketch_id, weight, rank, inside, total_weight) PARTITION BY sketch_id ORDER BY pos, then delta and the number of draws."""

    def __init__(self):
        self.rows, self.delta, self.draws = [], 0.05, 200

    def eval(self, row, delta: float = 0.05, draws: int = 200):
        self.rows.append((row["sketch_id"], row["weight"], row["rank"], bool(row["inside"]), row["total_weight"]))
        self.delta, self.draws = delta, draws

    def terminate(self):
        if self.rows:
            g = pd.DataFrame(self.rows, columns=["sketch_id", "weight", "rank", "inside", "total_weight"])
            low, high = split_bounds(g, None, self.delta, self.draws, "bs")
            yield self.rows[0][0], float(low), float(high)


def register(spark: SparkSession) -> None:
    for name, head, body in FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{head} RETURN {body}")
    spark.udtf.register("subset_conditioned", SubsetConditioned)
    spark.udtf.register("subpop_bounds", SubpopBounds)


def register_sketch(sketch: Sketch, name: str) -> None:
    """The sketch as a temporary view: entries beside their header, attributes as columns."""
    flat = sketch.flat()
    flat.select("*", "attrs.*").drop("attrs").createOrReplaceTempView(name)
