"""Roots and peaks as expressions: a fixed number of interval steps folded over an array, without any UDF."""

from __future__ import annotations

from collections.abc import Callable
from statistics import NormalDist

from pyspark.sql import Column
from pyspark.sql import functions as F

STEPS = 80


def bind(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with the value worked out once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def bisect(above: Callable[[Column], Column], low: Column, high: Column, steps: int = STEPS) -> Column:
    """The point at which ``above`` (is the root above this point?) turns from true to false."""
    start = F.struct(low.cast("double").alias("lo"), high.cast("double").alias("hi"))

    def step(acc: Column, _: Column) -> Column:
        def at(mid: Column) -> Column:
            return bind(above(mid), lambda up: F.struct(F.when(up, mid).otherwise(acc["lo"]).alias("lo"), F.when(up, acc["hi"]).otherwise(mid).alias("hi")))

        return bind((acc["lo"] + acc["hi"]) / 2, at)

    end = F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, step)
    return bind(end, lambda e: (e["lo"] + e["hi"]) / 2)


def peak(f: Callable[[Column], Column], low: Column, high: Column, steps: int = STEPS) -> Column:
    """Where a function with one peak is largest, by thirds."""
    start = F.struct(low.cast("double").alias("lo"), high.cast("double").alias("hi"))

    def step(acc: Column, _: Column) -> Column:
        a, b = (2 * acc["lo"] + acc["hi"]) / 3, (acc["lo"] + 2 * acc["hi"]) / 3
        return bind(f(a) < f(b), lambda up: F.struct(F.when(up, a).otherwise(acc["lo"]).alias("lo"), F.when(up, acc["hi"]).otherwise(b).alias("hi")))

    end = F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, step)
    return bind(end, lambda e: (e["lo"] + e["hi"]) / 2)


def sum_of(values: Column, f: Callable[[Column], Column]) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, s: acc + f(s))


def inverse_sum(x: Column, sums: Column) -> Column:
    """Sum of 1 / (x - s): the mean of a sum of exponentials with rates x - s."""
    return sum_of(sums, lambda s: 1.0 / (x - s))


def normal_quantile(p: float) -> float:
    return NormalDist().inv_cdf(p)
