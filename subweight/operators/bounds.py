"""One-sided confidence bounds: each is wrong with probability delta.

With exponential ranks, tau given the order of the sampled items is a sum of exponentials whose rates
are x less the weights before; the bound is the x at which tau as observed would be too late (upper)
or too early (lower).  By ``normal`` that law is taken as normal; by ``quantile`` it is drawn, and x
solved for each draw.  With the total known both sides of the split are drawn together.  Priority
ranks have bounds from the number of light items.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.ranks import hash_uniform, uniform_of
from ..functions.solve import bind, bisect, inverse_sum, normal_quantile, peak, sum_of
from .kmins import KMins
from .mle import split_sums
from .sketch import Sketch, family_in

OUT = "sketch_id string, lower double, upper double"


def _need(sketch: Sketch, family: str) -> None:
    """Bounds of one family are not those of another; for others than these two there is no good upper bound, and none is given."""
    if family_in(sketch) != family:
        raise ValueError(f"these bounds need {family} ranks")


def _finish(df: DataFrame, delta: float, method: str) -> DataFrame:
    return df.select("sketch_id", "lower", "upper", (F.col("upper") - F.col("lower")).alias("width"), F.lit(delta).alias("delta"), F.lit(method).alias("method"))


def bounds_kmins(sketch: KMins, delta: float = 0.05) -> DataFrame:
    """Sampling with replacement: (1 -+ alpha / sqrt(k)) over the mean least rank."""
    alpha = normal_quantile(1 - delta)
    rows = sketch.rows.groupBy("sketch_id").agg(F.avg("min_rank").alias("m"), F.count("*").alias("n"))
    side = alpha / F.sqrt("n")
    return _finish(rows.select("sketch_id", ((1 - side) / F.col("m")).alias("lower"), ((1 + side) / F.col("m")).alias("upper")), delta, "with_replacement_normal")


# ---------------------------------------------------------------- sums of exponentials, as expressions


def _upper_normal(sums: Column, tau: Column, alpha: float) -> Column:
    """x with mean + alpha * deviation = tau."""
    last, n = F.element_at(sums, -1), F.size(sums)

    def over(x: Column) -> Column:
        return inverse_sum(x, sums) + alpha * F.sqrt(sum_of(sums, lambda s: 1 / ((x - s) * (x - s)))) > tau

    return bisect(over, last + (1 + alpha) / tau, last + (n + alpha * F.sqrt(n)) / tau)


def _lower_normal(sums: Column, tau: Column, alpha: float, floor: Column) -> Column:
    """The larger x with mean - alpha * deviation = tau; without one, ``floor``."""
    last, n = F.element_at(sums, -1), F.size(sums)

    def value(x: Column) -> Column:
        return inverse_sum(x, sums) - alpha * F.sqrt(sum_of(sums, lambda s: 1 / ((x - s) * (x - s))))

    high = last + n / tau
    low = last + 1e-9 / tau
    return bind(peak(value, low, high), lambda top: F.when(value(top) <= tau, floor).otherwise(F.greatest(floor, bisect(lambda x: value(x) > tau, top, high))))


def _draws(sums: Column, tau: Column, seed: str, draws: int) -> Column:
    """For each draw of unit exponentials, the x at which their sum over x - s is tau; sorted."""

    def solve(d: Column) -> Column:
        e = F.transform(sums, lambda s, j: F.struct(s.alias("s"), (-F.log(hash_uniform(seed, "sketch_id", d, j))).alias("e")))

        def at(e: Column) -> Column:
            last = F.element_at(e, -1)
            total = F.aggregate(e, F.lit(0.0), lambda a, y: a + y["e"])
            return bisect(lambda x: F.aggregate(e, F.lit(0.0), lambda a, y: a + y["e"] / (x - y["s"])) > tau, last["s"] + last["e"] / tau, last["s"] + total / tau, 60)

        return bind(e, at)

    return F.sort_array(F.transform(F.sequence(F.lit(1), F.lit(draws)), solve))


def _pick(sorted_values: Column, level: float, draws: int) -> Column:
    """The value at a quantile: of 200 draws at 0.95, the 190th."""
    return F.element_at(sorted_values, max(1, min(draws, math.ceil(level * draws))))


def bounds_total(sketch: Sketch, conditioning: str = "order", solver: str = "normal", delta: float = 0.05, draws: int = 200, seed: str = "bt") -> DataFrame:
    """Bounds on the total weight from an exponential sketch, given the order of its items or (``set``, tightest) only which they are."""
    _need(sketch, "exp")
    if conditioning == "set":
        return _finish(_numeric(sketch, "true", lambda g: set_bounds(g["weight"].to_numpy(float), float(g["tau"].iloc[0]), delta)), delta, "exp_total_set")
    row = split_sums(sketch).withColumn("sums", F.concat("ins", F.array("sum_in")))
    tau, seen = F.col("tau"), F.col("sum_in")
    if solver == "normal":
        alpha = normal_quantile(1 - delta)
        low, high = _lower_normal(F.col("sums"), tau, alpha, seen), _upper_normal(F.col("sums"), tau, alpha)
    else:
        row = row.withColumn("x", F.when(~F.col("exact"), _draws(F.col("sums"), tau, seed, draws)))
        low, high = F.greatest(seen, _pick(F.col("x"), delta, draws)), _pick(F.col("x"), 1 - delta, draws)
    exact = F.col("exact")
    return _finish(row.select("sketch_id", F.when(exact, seen).otherwise(low).alias("lower"), F.when(exact, seen).otherwise(high).alias("upper")), delta, f"exp_total_{solver}")


def bounds_subpop(sketch: Sketch, predicate: Column | str, total: float | bool | None = None, solver: str = "quantile", delta: float = 0.05, draws: int = 200, seed: str = "bs") -> DataFrame:
    """Bounds on a subpopulation's weight; with ``total`` (a number, or True: the header's) both sides are used.

    Without the total: the upper bound has one term more than sampled items and tau, the lower one
    as many terms and the largest sampled rank.
    """
    _need(sketch, "exp")
    if total is not None and total is not False:
        return _finish(_numeric(sketch, predicate, lambda g: split_bounds(g, None if total is True else float(total), delta, draws, seed)), delta, "exp_subpop_total")
    row = split_sums(sketch, predicate).withColumn("sums", F.concat("ins", F.array("sum_in")))
    tau, last, seen, c = F.col("tau"), F.col("last"), F.col("sum_in"), F.col("c")
    if solver == "normal":
        alpha = normal_quantile(1 - delta)
        high, low = _upper_normal(F.col("sums"), tau, alpha), _lower_normal(F.col("ins"), last, alpha, seen)
    else:
        row = row.withColumn("x", F.when(~F.col("exact") & (c > 0), _draws(F.col("sums"), tau, seed, draws))).withColumn("y", F.when(~F.col("exact") & (c > 0), _draws(F.col("ins"), last, seed, draws)))
        high, low = _pick(F.col("x"), 1 - delta, draws), F.greatest(seen, _pick(F.col("y"), delta, draws))
    none = -math.log(delta) / tau
    exact = F.col("exact")
    return _finish(row.select("sketch_id", F.when(exact, seen).when(c == 0, F.lit(0.0)).otherwise(low).alias("lower"), F.when(exact, seen).when(c == 0, none).otherwise(high).alias("upper")), delta, f"exp_subpop_{solver}")


def bounds_priority(sketch: Sketch, predicate: Column | str = "true", tail: str = "chernoff", delta: float = 0.05) -> DataFrame:
    """Priority ranks: items heavier than 1/tau are certain; the number of light ones bounds their expected number, by Chernoff's bound or the exact Poisson tail.

    ``simulated``: the light items that are sampled are drawn by their own chances, and only what is unseen is Poisson.
    """
    _need(sketch, "priority")
    if tail == "simulated":
        return _finish(_numeric(sketch, predicate, lambda g: simulated_bounds(g, delta)), delta, "priority_simulated")
    if tail == "poisson":
        return _finish(_numeric(sketch, predicate, lambda g: poisson_bounds(g, delta)), delta, "priority_poisson")
    predicate = F.expr(predicate) if isinstance(predicate, str) else predicate
    rows = sketch.flat().withColumn("inside", F.coalesce(predicate, F.lit(False)))
    heavy = F.col("inside") & (F.col("exact") | (F.col("weight") * F.col("tau") >= 1))
    row = rows.groupBy("sketch_id").agg(F.first("tau").alias("tau"), F.first("exact").alias("exact"), F.coalesce(F.sum(F.when(heavy, F.col("weight"))), F.lit(0.0)).alias("certain"), F.count_if(F.col("inside") & ~heavy).cast("double").alias("n"))
    n, log = F.col("n"), math.log(delta)
    gap = lambda x: n - x + n * F.log(x / n) - log
    high = F.when(n == 0, F.lit(-log)).otherwise(bisect(lambda x: gap(x) > 0, n, n - 2 * log + F.sqrt(F.greatest(4 * log * log - 8 * n * log, F.lit(0.0))) + 1))
    low = F.when(n == 0, F.lit(0.0)).otherwise(bisect(lambda x: gap(x) < 0, n * 1e-12, n))
    out = lambda x: F.when(F.col("exact"), F.col("certain")).otherwise(F.col("certain") + x / F.col("tau"))
    return _finish(row.select("sketch_id", out(low).alias("lower"), out(high).alias("upper")), delta, "priority_chernoff")


def bounds_priority_total(sketch: Sketch, delta: float = 0.05) -> DataFrame:
    """Bounds on the total weight from a priority sketch by the law of the (k+1)-st rank given which items are sampled."""
    _need(sketch, "priority")
    return _finish(_numeric(sketch, "true", lambda g: priority_total_bounds(g["weight"].to_numpy(float), float(g["tau"].iloc[0]), delta)), delta, "priority_total")


# ---------------------------------------------------------------- on the k rows of a sketch, in numpy


def _numeric(sketch: Sketch, predicate: Column | str, work) -> DataFrame:
    predicate = F.expr(predicate) if isinstance(predicate, str) else predicate
    rows = sketch.flat().withColumn("inside", F.coalesce(predicate, F.lit(False))).select("sketch_id", "pos", "weight", "rank", "inside", "tau", "total_weight", "exact")

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        if bool(g["exact"].iloc[0]):
            seen = float(g.loc[g["inside"], "weight"].sum())
            low, high = seen, seen
        else:
            low, high = work(g)
        return pd.DataFrame({"sketch_id": [g["sketch_id"].iloc[0]], "lower": [low], "upper": [high]})

    return rows.groupBy("sketch_id").applyInPandas(run, OUT)


def _share_below(log_density, tau: float, top: float) -> float:
    """Share of a density over ln y that lies below ln tau, by trapezoids."""
    t = np.linspace(math.log(tau) - 60, top, 4000)
    g = log_density(t)
    best = g.max()
    near = np.flatnonzero(g > best - 50)
    t = np.linspace(t[max(near[0] - 1, 0)], t[min(near[-1] + 1, len(t) - 1)], 8000)
    p = np.exp(log_density(t) - best)
    area = np.concatenate([[0], np.cumsum((p[1:] + p[:-1]) / 2 * np.diff(t))])
    return float(np.interp(math.log(tau), t, area) / area[-1])


@dataclass(frozen=True)
class BoundFamily:
    """What bounds on the unseen weight need of a family of ranks, as log densities over t, the logarithm of the least unseen rank.

    seen(w, t): all sampled ranks are below; most(rest, t) and least(rest, t): the least rank of an unseen
    set of that weight, in the cases that make it latest and earliest; ends(rest): where ``least`` ends.
    """

    name: str
    seen: Callable[[np.ndarray, np.ndarray], np.ndarray]
    most: Callable[[float, np.ndarray], np.ndarray]
    least: Callable[[float, np.ndarray], np.ndarray]
    ends: Callable[[float], float] | None = None


_exponential = lambda rest, t: t - rest * np.exp(t)  # noqa: E731 of many tiny items, whatever the family; of any, with exponential ranks
#: Exponential ranks: an unseen set's least rank is exponential with its weight, however that is split.
EXP_BOUNDS = BoundFamily("exp", lambda w, t: np.log(-np.expm1(-np.outer(np.exp(t), w))).sum(axis=1), _exponential, _exponential)
#: Priority ranks: latest if unseen items are many and tiny, earliest if there is one, whose rank is uniform up to 1 / rest.
PRIORITY_BOUNDS = BoundFamily("priority", lambda w, t: np.minimum(0, np.log(w)[None, :] + t[:, None]).sum(axis=1), _exponential, lambda rest, t: t, lambda rest: -math.log(rest))


def general_bounds(w: np.ndarray, tau: float, delta: float, family: BoundFamily) -> tuple[float, float]:
    """Total weight given which items (weights ``w``) were sampled and the next rank, for any family."""
    w = np.asarray(w, float)

    def share(rest: float, law, end: float | None) -> float:
        if end is not None and end <= math.log(tau):
            return 1.0
        top = max(math.log(tau), math.log((len(w) + 1) / rest)) + 6 if end is None else end
        return _share_below(lambda t: law(rest, t) + family.seen(w, t), tau, top)

    high = _solve_rest(lambda rest: share(rest, family.most, None), w.sum(), tau, delta)[1]
    low = _solve_rest(lambda rest: share(rest, family.least, family.ends(rest) if family.ends else None), w.sum(), tau, delta)[0]
    return low, high


def set_bounds(w: np.ndarray, tau: float, delta: float) -> tuple[float, float]:
    """Total weight given which items were sampled, by exponential ranks."""
    return general_bounds(w, tau, delta, EXP_BOUNDS)


def _solve_rest(share, seen: float, tau: float, delta: float) -> tuple[float, float]:
    """The unsampled weights at which tau is at its delta (lower) and 1 - delta (upper) quantile; the share grows with the weight."""

    def solve(level: float) -> float:
        low, high = 1e-9 / tau, 1 / tau
        if share(low) >= level:
            return 0.0
        while share(high) < level:
            high *= 2
        for _ in range(60):
            mid = math.sqrt(low * high) if high > 4 * low else (low + high) / 2
            low, high = (mid, high) if share(mid) < level else (low, mid)
        return (low + high) / 2

    return seen + solve(delta), seen + solve(1 - delta)


def priority_total_bounds(w: np.ndarray, tau: float, delta: float) -> tuple[float, float]:
    """Total weight given which items were sampled, by priority ranks."""
    return general_bounds(w, tau, delta, PRIORITY_BOUNDS)


def _root(f, low: np.ndarray, high: np.ndarray, steps: int = 60) -> np.ndarray:
    """Rows of roots of a function that rises, by halving."""
    low, high = low.astype(float).copy(), high.astype(float).copy()
    for _ in range(steps):
        mid = (low + high) / 2
        up = f(mid) < 0
        low, high = np.where(up, mid, low), np.where(up, high, mid)
    return (low + high) / 2


def split_solutions(ins: np.ndarray, outs: np.ndarray, total: float, gap: float, e: np.ndarray, f: np.ndarray) -> np.ndarray:
    """For each row of unit exponentials, the weight x of the subpopulation at which the ranks of both sides differ by ``gap``.

    ``ins``, ``outs``: weights in order.  A(m), B(m): the m-th rank of each side as a function of x,
    sums of e / (x - s) and of f / (W - x - s').
    """
    s, r = np.concatenate([[0], np.cumsum(ins)]), np.concatenate([[0], np.cumsum(outs)])
    i, j, n = len(ins), len(outs), len(e)

    def side_a(x: np.ndarray, m: int) -> np.ndarray:
        return (e[:, :m] / np.maximum(x[:, None] - s[:m], 1e-300)).sum(axis=1)

    def side_b(x: np.ndarray, m: int) -> np.ndarray:
        return (f[:, :m] / np.maximum(total - x[:, None] - r[:m], 1e-300)).sum(axis=1)

    bottom, top = np.full(n, s[i]), np.full(n, total - r[j])
    high = _root(lambda x: side_b(x, j) - side_a(x, i + 1), bottom, top) if j else np.full(n, total)
    low = _root(lambda x: side_b(x, j + 1) - side_a(x, i), bottom, top) if i else np.zeros(n)
    low, high = np.clip(low, bottom, top), np.clip(high, bottom, top)
    return np.clip(_root(lambda x: side_b(x, j) - side_a(x, i) - gap, np.minimum(low, high), np.maximum(low, high)), bottom, top)


def split_bounds(g: pd.DataFrame, total: float | None, delta: float, draws: int, seed: str) -> tuple[float, float]:
    w, inside, rank = g["weight"].to_numpy(float), g["inside"].to_numpy(bool), g["rank"].to_numpy(float)
    whole = float(g["total_weight"].iloc[0]) if total is None else total
    ins, outs = w[inside], w[~inside]
    gap = (rank[~inside].max() if len(outs) else 0.0) - (rank[inside].max() if len(ins) else 0.0)
    name = g["sketch_id"].iloc[0]
    e, f = (-np.log([[uniform_of(seed, name, d, side, j) for j in range(n + 1)] for d in range(1, draws + 1)]) for side, n in (("i", len(ins)), ("o", len(outs))))
    x = np.sort(split_solutions(ins, outs, whole, gap, e, f))
    at = lambda level: float(x[max(0, min(draws - 1, math.ceil(level * draws) - 1))])
    return at(delta), at(1 - delta)


def poisson_tail(n: int, x: float) -> float:
    """Pr(a Poisson number of mean x is at most n)."""
    if n < 0:
        return 0.0
    if x <= 0:
        return 1.0
    logs = -x + np.cumsum(np.concatenate([[0.0], np.log(x) - np.log(np.arange(1, n + 1))])) if n else np.array([-x])
    return float(np.exp(logs).sum())


def poisson_bounds(g: pd.DataFrame, delta: float) -> tuple[float, float]:
    tau = float(g["tau"].iloc[0])
    own = g.loc[g["inside"], "weight"].to_numpy(float)
    certain, n = float(own[own * tau >= 1].sum()), int((own * tau < 1).sum())

    def solve(f, low: float, high: float) -> float:
        for _ in range(80):
            mid = (low + high) / 2
            low, high = (mid, high) if f(mid) else (low, mid)
        return (low + high) / 2

    high = solve(lambda x: poisson_tail(n, x) > delta, 0.0, n + 10 * math.sqrt(n + 1) + 20)
    low = solve(lambda x: 1 - poisson_tail(n - 1, x) < delta, 0.0, float(n)) if n else 0.0
    return certain + low / tau, certain + high / tau


def simulated_bounds(g: pd.DataFrame, delta: float, draws: int = 50, seed: str = "light") -> tuple[float, float]:
    """The unseen weight at which so many light items as are seen are too few (upper) or too many (lower): theirs drawn by their chances, the unseen ones' number Poisson."""
    tau, name = float(g["tau"].iloc[0]), g["sketch_id"].iloc[0]
    rows = g[g["inside"]]
    w = rows["weight"].to_numpy(float)
    light = w * tau < 1
    n, seen = int(light.sum()), float(w.sum())
    chance, at = w[light] * tau, rows["pos"].to_numpy()[light]
    left = [n - sum(uniform_of(seed, name, d, p) < c for p, c in zip(at, chance, strict=True)) for d in range(1, draws + 1)]
    below = lambda x: float(np.mean([poisson_tail(m, x) for m in left]))  # noqa: E731 no more than are seen
    above = lambda x: float(np.mean([1 - poisson_tail(m - 1, x) if m > 0 else 1.0 for m in left]))  # noqa: E731 no fewer

    def solve(f, high: float) -> float:
        low = 0.0
        for _ in range(60):
            mid = (low + high) / 2
            low, high = (mid, high) if f(mid) else (low, mid)
        return (low + high) / 2

    most = n + 10 * math.sqrt(n + 1) + 20
    low = 0.0 if above(0.0) >= delta else solve(lambda x: above(x) < delta, most)
    return seen + low / tau, seen + solve(lambda x: below(x) > delta, most) / tau
