"""Sketches of streams: whole-stream snapshots, windowed and session sketches, and elapsed-time state.

Ranks come from hashes of ids, so any batching, retry or order of arrival gives the same sketch, and
an event that comes twice changes nothing but the total, unless it is dropped first.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.sketch import least_distinct, ranked

KEPT = "item_id long, weight double, rank double"
OUT = "sketch_id string, pos int, item_id long, weight double, rank double, tau double, n_seen long, total_weight double"


def stream_bottomk(events: DataFrame, item: str, weight: str, k: int, store: str, checkpoint: str, family: str = "exp", seed: str = "s1", once: bool = True):
    """A query that keeps the k+1 smallest ranks, the count and the total weight of all events so far.

    Each batch writes a new version of the snapshot under ``store``, named by the batch, from the
    version of the batch before; a batch that is run again overwrites its own version.
    """

    def fold(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        rows = ranked(batch, item, weight, family, seed).select(F.col("item_id").cast("long").alias("item_id"), "weight", "rank")
        seen = rows.agg(F.count("*").alias("n"), F.coalesce(F.sum("weight"), F.lit(0.0)).alias("w"))
        best = rows.filter("rank IS NOT NULL")
        if number:
            best = best.unionByName(spark.read.parquet(f"{store}/entries/{number - 1}"))
            seen = seen.unionByName(spark.read.parquet(f"{store}/totals/{number - 1}")).agg(F.sum("n").alias("n"), F.sum("w").alias("w"))
        once = least_distinct(best, k).groupBy("item_id").agg(F.min(F.struct("rank", "weight")).alias("m")).select("item_id", "m.weight", "m.rank")
        once.orderBy("rank", "item_id").limit(k + 1).write.mode("overwrite").parquet(f"{store}/entries/{number}")
        seen.coalesce(1).write.mode("overwrite").parquet(f"{store}/totals/{number}")

    writer = events.writeStream.foreachBatch(fold).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer.trigger(processingTime="10 seconds")).start()


def latest_version(spark: SparkSession, store: str) -> int:
    """The last version whose entries and totals are both complete."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(f"{store}/totals")
    system = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    done = lambda name: system.exists(spark._jvm.org.apache.hadoop.fs.Path(folder, f"{name}/_SUCCESS"))
    return max(int(x.getPath().getName()) for x in system.listStatus(folder) if x.getPath().getName().isdigit() and done(x.getPath().getName()))


def read_snapshot(spark: SparkSession, store: str, number: int | None, k: int) -> DataFrame:
    """The entries of a version (none given: the latest) with tau, count and total weight."""
    number = latest_version(spark, store) if number is None else number
    best, seen = spark.read.parquet(f"{store}/entries/{number}"), spark.read.parquet(f"{store}/totals/{number}")
    rows = [(i + 1, *r) for i, r in enumerate(best.select("item_id", "weight", "rank").orderBy("rank", "item_id").collect())]  # k+1 rows
    tau = rows[k][3] if len(rows) > k else None
    head = spark.createDataFrame(rows[:k], f"pos int, {KEPT}").withColumn("tau", F.lit(tau).cast("double"))
    return head.crossJoin(seen.select(F.col("n").alias("n_seen"), F.col("w").alias("total_weight")))


def late_rows(query) -> int:
    """Rows that a query's operators have dropped as later than the watermark."""
    return sum(int(o.numRowsDroppedByWatermark) for p in query.recentProgress for o in p.stateOperators)


def _elapsed(k: int):
    """State of each key: an item stays while its rank is among the k+1 smallest of those that came after it and itself."""

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        kept = pd.DataFrame(dict(zip(("time", "item_id", "weight", "rank"), state.get, strict=True))) if state.exists else None
        for g in batches:
            own = g[["time", "item_id", "weight", "rank"]]
            kept = own if kept is None else pd.concat([kept, own])
            kept = kept.sort_values(["time", "rank", "item_id"], ascending=[False, True, True])
            heap: list[float] = []
            stay = []
            for r in kept["rank"]:
                stay.append(len(heap) <= k or r < -heap[0])
                if len(heap) <= k:
                    heapq.heappush(heap, -r)
                elif r < -heap[0]:
                    heapq.heapreplace(heap, -r)
            kept = kept[stay]
        state.update(tuple(kept[c].tolist() for c in ("time", "item_id", "weight", "rank")))
        yield pd.DataFrame({"sketch_id": str(key[0]), "upto": float(kept["time"].iloc[0]), "time": kept["time"], "item_id": kept["item_id"], "weight": kept["weight"], "rank": kept["rank"]})

    return run


def stream_elapsed(events: DataFrame, ts: str, item: str, weight: str, k: int, by: str, family: str = "exp", seed: str = "s1") -> DataFrame:
    """The all-distances state of each value of ``by``, backwards from its newest event: with every batch the whole state, marked by the time it goes up to.

    From the rows of one mark the bottom-k sketch of any last span of time is the k+1 smallest ranks in it.
    """
    rows = ranked(events, item, weight, family, seed, [ts, by]).filter("rank IS NOT NULL")
    rows = rows.select(F.col(f"attrs.{by}").cast("string").alias("part"), (F.unix_micros(F.col(f"attrs.{ts}").cast("timestamp")) / 1e6).alias("time"), F.col("item_id").cast("long").alias("item_id"), "weight", "rank")
    out = "sketch_id string, upto double, time double, item_id long, weight double, rank double"
    return rows.groupBy("part").applyInPandasWithState(_elapsed(k), out, "times array<double>, items array<long>, weights array<double>, ranks array<double>", "append", GroupStateTimeout.NoTimeout)


def _windowed(k: int):
    """Keep a heap of k+1 ranks, the count and the total of each key; give them out when the watermark passes."""

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        name = "|".join(str(x) for x in key[:-1])
        if state.hasTimedOut:
            items, weights, ranks, n, total = state.get
            state.remove()
            rows = sorted(zip(ranks, items, weights, strict=True))
            tau = rows[k][0] if len(rows) > k else None
            yield pd.DataFrame([(name, i + 1, it, w, r, tau, n, total) for i, (r, it, w) in enumerate(rows[:k])], columns=["sketch_id", "pos", "item_id", "weight", "rank", "tau", "n_seen", "total_weight"])
            return
        items, weights, ranks, n, total = state.get if state.exists else ([], [], [], 0, 0.0)
        heap = [(-r, -i, w) for r, i, w in zip(ranks, items, weights, strict=True)]
        heapq.heapify(heap)
        for g in batches:
            n, total = n + len(g), total + float(g["weight"].sum())
            for i, w, r in zip(g["item_id"], g["weight"], g["rank"], strict=True):
                if r == r:
                    (heapq.heappush if len(heap) <= k else heapq.heappushpop)(heap, (-r, -int(i), float(w)))
        state.update(([-i for _, i, _ in heap], [w for _, _, w in heap], [-r for r, _, _ in heap], n, total))
        # a timeout comes when the watermark is above it: of a window, when the watermark is at its end, as no event before that is taken any more
        state.setTimeoutTimestamp(max(int(pd.Timestamp(key[-1]).timestamp() * 1000) - 1, state.getCurrentWatermarkMs() + 1))

    return run


def stream_windowed_bottomk(events: DataFrame, ts: str, item: str, weight: str, k: int, size: str = "1 day", slide: str | None = None, watermark: str = "1 hour", by: str | None = None, family: str = "exp", seed: str = "s1", distinct: bool = False) -> DataFrame:
    """A sketch of each time window (and value of ``by``), given out when the watermark has passed its end; later events are dropped.

    ``distinct`` drops events whose id came within the watermark before.
    """
    timed = events.withColumn("__ts", F.col(ts).cast("timestamp")).withWatermark("__ts", watermark)
    if distinct:
        timed = timed.dropDuplicatesWithinWatermark([item])
    rows = ranked(timed, item, weight, family, seed, ["__ts", *([by] if by else [])])
    rows = rows.select(F.window("attrs.__ts", size, slide).alias("w"), *([F.col(f"attrs.{by}").alias("part")] if by else []), F.col("attrs.__ts").alias("__ts"), F.col("item_id").cast("long").alias("item_id"), "weight", F.col("rank"))
    rows = rows.select("*", F.unix_seconds("w.start").alias("start"), F.col("w.end").alias("end")).drop("w")
    keys = [*(["part"] if by else []), "start", "end"]
    state = "items array<long>, weights array<double>, ranks array<double>, n long, total double"
    return rows.groupBy(*keys).applyInPandasWithState(_windowed(k), OUT, state, "append", GroupStateTimeout.EventTimeTimeout)


def stream_sessions(events: DataFrame, ts: str, user: str, weight: str, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    """Count and total weight of the sessions of each user: events no farther apart than ``gap``."""
    timed = events.withColumn("__ts", F.col(ts).cast("timestamp")).withWatermark("__ts", watermark)
    return timed.groupBy(F.session_window("__ts", gap).alias("s"), user).agg(F.count("*").alias("n_seen"), F.sum(weight).alias("total_weight")).select(user, F.unix_seconds("s.start").alias("start"), "n_seen", "total_weight")


class ElapsedSketch:
    """All-distances state of a stream, from now backwards: an item stays while its rank is among the k+1 smallest of those that came after it and itself."""

    def __init__(self, k: int):
        self.k, self.kept = k, []

    def add(self, time: float, item: int, weight: float, rank: float) -> None:
        self.kept.append([time, item, weight, rank, 0])
        for e in self.kept[:-1]:
            e[4] += rank < e[3]
        self.kept = [e for e in self.kept if e[4] <= self.k]

    def within(self, since: float) -> list[tuple[float, int, float]]:
        """The k+1 smallest (rank, item, weight) of the items not before a time."""
        return sorted((e[3], e[1], e[2]) for e in self.kept if e[0] >= since)[: self.k + 1]
