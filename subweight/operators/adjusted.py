"""Adjusted weights: a weight for every sampled item whose expectation, 0 when not sampled, is the true one."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.ranks import family_of, hash_uniform, uniform_of
from .sketch import Sketch, family_in

OUT = "sketch_id string, pos int, adj_weight double"


def horvitz_thompson(df: DataFrame, weight: str = "weight", probability: str = "probability") -> DataFrame:
    """Weight over the known probability of being sampled."""
    return df.withColumn("adj_weight", F.col(weight) / F.col(probability))


def partitioned_ht(sketch: Sketch, probability: Column) -> DataFrame:
    """Weight over the probability of being sampled within the part of the outcomes that the sketch shows."""
    return sketch.flat().withColumn("adj_weight", F.when(F.col("exact"), F.col("weight")).otherwise(F.col("weight") / probability))


def rank_conditioned(sketch: Sketch, family: str | None = None) -> DataFrame:
    """Given the (k+1)-st rank: weight over the chance of a rank below it.  One division an item, all families."""
    family = family or family_in(sketch)
    flat = sketch.flat()
    w, tau = F.col("weight"), F.col("tau")
    value = F.greatest(w, 1 / tau) if family == "priority" else w / family_of(family).cdf(w, tau)
    return flat.withColumn("adj_weight", F.when(F.col("exact"), w).otherwise(value))


def _need_exp(sketch: Sketch, what: str) -> None:
    if family_in(sketch) != "exp":
        raise ValueError(f"{what} needs exponential ranks")


def _with_total(sketch: Sketch, total: float | None) -> DataFrame:
    flat = sketch.flat()
    return flat if total is None else flat.withColumn("total_weight", F.lit(float(total)))


def prefix_conditioned(sketch: Sketch, total: float | None = None) -> DataFrame:
    """Given the order of the other k-1 items, with the total weight known; exponential ranks.

    The chance to be sampled is one less the product, over how many of the others came first, of the
    chance not to be drawn next.
    """
    _need_exp(sketch, "prefix conditioning")
    flat = _with_total(sketch, total)
    whole = Window.partitionBy("sketch_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    before = F.coalesce(F.sum("weight").over(Window.partitionBy("sketch_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    rows = flat.withColumn("upto", before + F.col("weight")).withColumn("prefix", F.concat(F.array(F.lit(0.0)), F.collect_list("upto").over(whole)))
    w, n = F.col("weight"), F.size("prefix") - 1

    def term(m: Column) -> Column:
        others = F.when(m < F.col("pos") - 1, F.get("prefix", m)).otherwise(F.get("prefix", m + 1) - w)
        return F.log1p(-w / F.nullif(F.col("total_weight") - others, F.lit(0.0)))

    log = F.aggregate(F.sequence(F.lit(0), n - 1), F.lit(0.0), lambda acc, m: acc + term(m))
    return rows.withColumn("adj_weight", F.when(F.col("exact"), w).otherwise(w / -F.expm1(log))).drop("upto", "prefix")


def subset_weights(w: np.ndarray, rest: float, nodes: int = 200) -> np.ndarray:
    """Subset-conditioned weights: the mean of w / (1 - exp(-w y)) for y of density exp(-rest y) times the product of 1 - exp(-w y).

    Trapezoids in ln y over the window in which the log-density is within 45 of its peak.
    """
    w = np.asarray(w, float)
    if not len(w) or rest <= 1e-12 * (rest + w.sum()):
        return w.copy()

    def g(t: np.ndarray) -> np.ndarray:
        y = np.exp(t)
        return t - rest * y + np.log(-np.expm1(-np.outer(y, w))).sum(axis=1)

    def slope(t: float) -> float:
        y = np.exp(t)
        return 1 - rest * y + float((w * y / np.expm1(np.minimum(w * y, 700))).sum())

    low, high = -80 - np.log(w.sum() + rest), np.log((len(w) + 1) / rest) + 1
    for _ in range(100):
        mid = (low + high) / 2
        low, high = (mid, high) if slope(mid) > 0 else (low, mid)
    top = (low + high) / 2
    best = float(g(np.array([top]))[0])

    def edge(sign: int) -> float:
        step = 0.5
        while g(np.array([top + sign * step]))[0] > best - 45:
            step *= 2
        a, b = 0.0, step
        for _ in range(40):
            m = (a + b) / 2
            a, b = (m, b) if g(np.array([top + sign * m]))[0] > best - 45 else (a, m)
        return top + sign * b

    t = np.linspace(edge(-1), edge(1), nodes)
    density = np.exp(g(t) - best)
    return (density[:, None] * w / -np.expm1(-np.outer(np.exp(t), w))).sum(axis=0) / density.sum()


def chance_recurrence(w: tuple[float, ...], rest: float) -> float:
    """The chance that all of ``w`` come before the rest, by recursion (2^k steps; a check)."""
    if not w:
        return 1.0
    return chance_recurrence(w[1:], rest) - chance_recurrence(w[1:], rest + w[0]) * rest / (rest + w[0])


def chance_inclusion_exclusion(w: tuple[float, ...], rest: float) -> float:
    """The same by inclusion and exclusion."""
    total = 0.0
    for mask in range(1 << len(w)):
        part = sum(x for i, x in enumerate(w) if mask >> i & 1)
        total += (-1) ** mask.bit_count() * rest / (rest + part)
    return total


def _grouped(sketch: Sketch, total: float | None, work: Callable[[np.ndarray, float, str], np.ndarray]) -> DataFrame:
    """Adjusted weights by a function of one sketch's weights in order and the unsampled weight; groups hold k rows."""
    flat = _with_total(sketch, total)

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("pos")
        w = rows["weight"].to_numpy(float)
        rest = float(rows["total_weight"].iloc[0]) - w.sum()
        exact = bool(rows["exact"].iloc[0]) or rest <= 1e-12 * float(rows["total_weight"].iloc[0])
        return pd.DataFrame({"sketch_id": rows["sketch_id"], "pos": rows["pos"], "adj_weight": w if exact else work(w, rest, rows["sketch_id"].iloc[0])})

    out = flat.select("sketch_id", "pos", "weight", "total_weight", "exact").groupBy("sketch_id").applyInPandas(run, OUT)
    return flat.join(out, ["sketch_id", "pos"])


def subset_conditioned(sketch: Sketch, total: float | None = None, nodes: int = 200) -> DataFrame:
    """Given the set of the other k-1 items, with the total weight known; exponential ranks.  They add up to the total."""
    _need_exp(sketch, "subset conditioning")
    return _grouped(sketch, total, lambda w, rest, _: subset_weights(w, rest, nodes))


def ordered_average(sketch: Sketch, total: float | None = None, draws: int = 200, seed: str = "oa") -> DataFrame:
    """The rank-conditioned weight averaged over the (k+1)-st rank given the order: a sum of exponentials with the rates of what is left."""
    _need_exp(sketch, "the ordered average")
    flat = _with_total(sketch, total)
    whole = Window.partitionBy("sketch_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    run = Window.partitionBy("sketch_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    rows = flat.withColumn("upto", F.sum("weight").over(run)).withColumn("rates", F.transform(F.concat(F.array(F.lit(0.0)), F.collect_list("upto").over(whole)), lambda s: F.col("total_weight") - s))
    gaps = lambda d: F.aggregate(F.transform("rates", lambda r, j: -F.log(hash_uniform(seed, "sketch_id", d, j)) / F.nullif(r, F.lit(0.0))), F.lit(0.0), lambda a, x: a + x)
    taus = rows.filter("pos = 1").select("sketch_id", F.transform(F.sequence(F.lit(1), F.lit(draws)), gaps).alias("taus"))
    mean = F.aggregate("taus", F.lit(0.0), lambda a, t: a + F.col("weight") / -F.expm1(-F.col("weight") * t)) / draws
    return rows.join(taus, "sketch_id").withColumn("adj_weight", F.when(F.col("exact"), F.col("weight")).otherwise(mean)).drop("upto", "rates", "taus")


def chain_weights(w: np.ndarray, rest: float, redraws: int, steps: int, uniform: Callable[..., float]) -> np.ndarray:
    """A chain over orders of the sampled items: draw the (k+1)-st rank given the order ``redraws`` times, use one to redraw the ranks below it, sort, go on.

    ``uniform(step, draw, j)`` and ``uniform(step, "r", place)`` are the random numbers, places in the first order.
    """
    total = rest + w.sum()
    order = np.arange(len(w))
    out = np.zeros(len(w))
    for step in range(1, steps + 1):
        left = total - np.concatenate([[0], np.cumsum(w[order])])
        left[-1] = rest
        e = -np.log([[uniform(step, d, j) for j in range(len(left))] for d in range(1, redraws + 1)])
        tau = (e / left).sum(axis=1)
        out += (w / -np.expm1(-np.outer(tau, w))).sum(axis=0)
        if step < steps:
            ranks = -np.log1p(np.array([uniform(step, "r", i + 1) for i in range(len(w))]) * np.expm1(-w * tau[0])) / w
            order = np.argsort(ranks)
    return out / (redraws * steps)


def subset_conditioned_chain(sketch: Sketch, total: float | None = None, redraws: int = 20, steps: int = 20, seed: str = "ch") -> DataFrame:
    """Subset conditioning by the chain: ``steps`` orders, ``redraws`` draws in each; unbiased for any of both.  Draws are hashes of the sketch's id."""
    _need_exp(sketch, "the chain")
    return _grouped(sketch, total, lambda w, rest, name: chain_weights(w, rest, redraws, steps, lambda *at: uniform_of(seed, name, *at)))
