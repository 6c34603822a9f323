"""Set relations of coordinated sketches, distances, with-replacement mimicry and stream samplers."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.ranks import uniform_of
from .adjusted import rank_conditioned
from .kmins import KMins
from .sketch import Sketch, merge, ranked, top_by


def membership(a: Sketch, b: Sketch, k: int, family: str = "exp", seed: str = "s1") -> DataFrame:
    """The sketch of the union with an adjusted weight, and whether each item is of the first and of the second set.

    Ranks below the union's tau are in a set's own sketch if the item is in the set.
    """
    both = merge(a, b, k=k, family=family, seed=seed)
    one, two = a.entries.select("item_id", F.lit(True).alias("in_a")), b.entries.select("item_id", F.lit(True).alias("in_b"))
    rows = rank_conditioned(both, family).join(one, "item_id", "left").join(two, "item_id", "left")
    return rows.withColumn("in_a", F.coalesce("in_a", F.lit(False))).withColumn("in_b", F.coalesce("in_b", F.lit(False)))


def set_relations(a: Sketch, b: Sketch, k: int, family: str = "exp", seed: str = "s1") -> DataFrame:
    """Estimated weights of union, intersection and differences, and their ratio (weighted Jaccard)."""
    w, both = F.col("adj_weight"), F.col("in_a") & F.col("in_b")
    part = lambda p: F.coalesce(F.sum(F.when(p, w)), F.lit(0.0))
    out = membership(a, b, k, family, seed).agg(F.sum(w).alias("union_weight"), part(both).alias("intersection_weight"), part(F.col("in_a") & ~F.col("in_b")).alias("only_a"), part(F.col("in_b") & ~F.col("in_a")).alias("only_b"))
    return out.withColumn("jaccard", F.col("intersection_weight") / F.col("union_weight"))


def all_distances(df: DataFrame, item: Column | str, weight: Column | str, distance: Column | str, k: int, by: Column | str | None = None, family: str = "exp", seed: str = "s1", on_negative: str = "error") -> DataFrame:
    """(sketch_id, item_id, distance, weight, rank, u): items whose rank is among the k+1 smallest of those no farther than they.

    A first pass over every partition, with what it holds so far, drops most; what survives, about k times
    the logarithm of the number of items, meets first by groups of partitions, then in one pass a location.
    """
    base = ranked(df.withColumn("__d", F.col(distance) if isinstance(distance, str) else distance), item, weight, family, seed, ["__d"], on_negative, None if by is None else (F.col(by) if isinstance(by, str) else by))
    rows = base.filter("rank IS NOT NULL").select("sketch_id", "item_id", F.col("attrs.__d").cast("double").alias("distance"), "weight", "rank", "u")

    def survivors(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["distance", "rank", "item_id"])
        heap: list[float] = []
        keep = np.zeros(len(g), bool)
        for i, r in enumerate(g["rank"].to_numpy()):
            if len(heap) <= k:
                heapq.heappush(heap, -r)
                keep[i] = True
            elif r < -heap[0]:
                heapq.heapreplace(heap, -r)
                keep[i] = True
        return g[keep]

    def local(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict[str, pd.DataFrame] = {}
        for g in batches:
            for name, x in g.groupby("sketch_id", sort=False):
                held[name] = survivors(pd.concat([held[name], x]) if name in held else x)
        yield from held.values()

    near = rows.mapInPandas(local, rows.schema).withColumn("__level", F.floor(F.sqrt(F.spark_partition_id())))
    some = near.groupBy("sketch_id", "__level").applyInPandas(lambda g: survivors(g.drop(columns="__level")), rows.schema)
    return some.groupBy("sketch_id").applyInPandas(survivors, rows.schema)


def neighborhood(ads: DataFrame, d: float, k: int, family: str = "exp", seed: str = "s1") -> Sketch:
    """The ordinary bottom-k sketch of the items within a distance; their total weight is unknown."""
    rows = ads.filter(F.col("distance") <= d).withColumn("attrs", F.struct("distance"))
    stats = rows.groupBy("sketch_id").agg(F.lit(None).cast("long").alias("n_seen"), F.lit(None).cast("double").alias("total_weight"))
    return top_by(rows.select("sketch_id", "item_id", "weight", "rank", "u", "attrs"), k, family, seed, stats)


def decayed_weight(ads: DataFrame, k: int, decay, family: str = "exp") -> DataFrame:
    """Estimated sum of weight times decay(distance): every entry has the adjusted weight it has in the sketch of its own distance, given the ranks of the others there."""
    order = Window.partitionBy("sketch_id").orderBy("distance", "rank", "item_id").rowsBetween(Window.unboundedPreceding, -1)
    ranks = F.sort_array(F.collect_list("rank").over(order))
    rows = ads.withColumn("kth", F.get(ranks, F.lit(k - 1)))
    chance = {"exp": -F.expm1(-F.col("weight") * F.col("kth")), "priority": F.least(F.lit(1.0), F.col("weight") * F.col("kth"))}[family]
    adj = F.when(F.col("kth").isNull(), F.col("weight")).when(F.col("rank") < F.col("kth"), F.col("weight") / chance).otherwise(0.0)
    return rows.groupBy("sketch_id").agg(F.sum(adj * decay(F.col("distance"))).alias("estimate"))


def mimic_with_replacement(sketch: Sketch, draws: int, total: float | None = None, seed: str = "mimic") -> KMins:
    """A with-replacement sample made of a bottom-k one and the total: a draw is of the items seen so far by their share of the weight, else the sketch's next item.

    It ends when the sketch has no next item: fewer draws may come back.
    """
    flat = sketch.flat() if total is None else sketch.flat().withColumn("total_weight", F.lit(float(total)))
    schema = f"sketch_id string, j int, min_rank double, item_id {sketch.entries.schema['item_id'].dataType.simpleString()}, weight double"

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        w, whole, name = g["weight"].to_numpy(float), float(g["total_weight"].iloc[0]), g["sketch_id"].iloc[0]
        upto = np.cumsum(w)
        seen, at = 0, []
        for d in range(1, draws + 1):
            held = upto[seen - 1] if seen else 0.0
            if seen and uniform_of(seed, name, d, "old") * whole < held:
                at.append(min(int(np.searchsorted(upto[:seen], uniform_of(seed, name, d, "which") * held)), seen - 1))
            elif seen < len(w):
                at.append(seen)
                seen += 1
            else:
                break
        return pd.DataFrame({"sketch_id": name, "j": np.arange(1, len(at) + 1, dtype=np.int32), "min_rank": np.nan, "item_id": g["item_id"].to_numpy()[at], "weight": w[at]})

    rows = flat.select("sketch_id", "pos", "item_id", "weight", "total_weight").groupBy("sketch_id").applyInPandas(run, schema)
    header = rows.groupBy("sketch_id").agg(F.count("*").cast("int").alias("k")).join(flat.groupBy("sketch_id").agg(F.first("n_seen").alias("n_seen"), F.first("total_weight").alias("total_weight")), "sketch_id")
    return KMins(rows, header)


class HeapSampler:
    """Bottom-k of a stream: a heap of k+1 ranks; an item enters if its rank is smaller than the largest kept."""

    def __init__(self, k: int):
        self.k, self.heap, self.draws = k, [], 0

    def add(self, item, weight: float, rank: float) -> None:
        self.draws += 1
        entry = (-rank, item, weight)
        if len(self.heap) <= self.k:
            heapq.heappush(self.heap, entry)
        elif entry > self.heap[0]:
            heapq.heapreplace(self.heap, entry)

    def rows(self) -> list[tuple]:
        return sorted((-r, i, w) for r, i, w in self.heap)


class SkipSampler(HeapSampler):
    """The same law with one draw for every item that enters: the weight to pass over until then is exponential with the largest kept rank as rate."""

    def __init__(self, k: int, rng: np.random.Generator):
        super().__init__(k)
        self.rng, self.skip = rng, 0.0

    def _next_skip(self) -> None:
        self.skip = self.rng.exponential() / -self.heap[0][0]
        self.draws += 1

    def feed(self, items: np.ndarray, weights: np.ndarray) -> None:
        i, n = 0, len(items)
        while i < n and len(self.heap) <= self.k:
            self.add(items[i], float(weights[i]), float(self.rng.exponential() / weights[i]))
            i += 1
            if len(self.heap) > self.k:
                self._next_skip()
        upto = np.cumsum(weights)
        at = float(upto[i - 1]) if i else 0.0
        while i < n:
            j = int(np.searchsorted(upto, at + self.skip))
            if j >= n:
                self.skip -= float(upto[-1]) - at
                return
            t = -self.heap[0][0]
            w = float(weights[j])
            rank = float(-np.log1p(self.rng.random() * np.expm1(-w * t)) / w)
            heapq.heapreplace(self.heap, (-rank, items[j], w))
            i, at = j + 1, float(upto[j])
            self._next_skip()


def bottomk_skip(df: DataFrame, item: str, weight: str, k: int, seed: int = 5) -> Sketch:
    """Every partition samples its rows with weight skips; ranks are independent, so the merged k+1 smallest are a sketch of all."""
    rows = df.select(F.col(item).cast("long").alias("item_id"), F.col(weight).cast("double").alias("weight")).filter("weight > 0")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        sampler = SkipSampler(k, np.random.default_rng([seed, TaskContext.get().partitionId()]))
        n, total = 0, 0.0
        for batch in batches:
            items, weights = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            sampler.feed(items, weights)
            n, total = n + len(items), total + float(weights.sum())
        got = sampler.rows()
        first = [i == 0 for i in range(max(1, len(got)))]
        got = got or [(None, None, None)]
        yield pa.RecordBatch.from_arrays([pa.array([g[1] for g in got], pa.int64()), pa.array([g[2] for g in got], pa.float64()), pa.array([g[0] for g in got], pa.float64()), pa.array([n if f else 0 for f in first], pa.int64()), pa.array([total if f else 0.0 for f in first]), pa.array([sampler.draws if f else 0 for f in first], pa.int64())], names=["item_id", "weight", "rank", "n", "w", "draws"])

    parts = rows.mapInArrow(run, "item_id long, weight double, rank double, n long, w double, draws long").withColumn("sketch_id", F.lit("all"))
    stats = parts.groupBy("sketch_id").agg(F.sum("n").alias("n_seen"), F.sum("w").alias("total_weight"))
    entries = parts.select("sketch_id", "item_id", "weight", "rank", F.exp(-F.col("weight") * F.col("rank")).alias("u"), F.struct(F.lit(None).cast("string").alias("none")).alias("attrs"))
    return top_by(entries, k, "exp", str(seed), stats)


def sample_sequential(weights: np.ndarray, k: int, rng: np.random.Generator) -> list[int]:
    """Weighted sampling without replacement as it is defined: one draw after the other, by weight among what is left."""
    left, out = np.array(weights, float), []
    for _ in range(min(k, int((left > 0).sum()))):
        i = int(rng.choice(len(left), p=left / left.sum()))
        out.append(i)
        left[i] = 0
    return out
