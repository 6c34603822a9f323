"""Connected components of a graph of links, by alternating large and small stars of the DataFrame of edges."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from .common import durable, release


def _forest(edges: DataFrame) -> DataFrame:
    """Fewer links that connect the same nodes: of each batch of links, those that join two of its pieces."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parent: dict[int, int] = {}
            keep = []
            for i, (a, b) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
                for x in (a, b):
                    parent.setdefault(x, x)
                while parent[a] != a:
                    parent[a] = a = parent[parent[a]]
                while parent[b] != b:
                    parent[b] = b = parent[parent[b]]
                if a != b:
                    parent[max(a, b)] = min(a, b)
                    keep.append(i)
            yield batch.take(pa.array(keep, pa.int64()))

    return edges.mapInArrow(run, "a long, b long")


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """One step: hook each node's neighbours (large: those above it; small: those below it and itself) to its least neighbour."""
    if large:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy(F.col("a").alias("n")).agg(F.min("b").alias("m")).select("n", F.least("n", "m").alias("m"))
        hooked = both.filter("b > a").join(least, F.col("a") == F.col("n")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = down.groupBy(F.col("a").alias("n")).agg(F.min("b").alias("m"))
        hooked = down.join(least, F.col("a") == F.col("n")).select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select(F.col("n").alias("a"), F.col("m").alias("b")))
    return hooked.filter("a <> b").distinct()


def _kept(edges: DataFrame) -> tuple[DataFrame, tuple]:
    """The links, durable, and a mark of their set, worked out by the same job."""
    seen = Observation()
    marked = edges.observe(seen, F.count("*").alias("n"), F.bit_xor(F.xxhash64("a", "b")).alias("h"), F.sum(F.when(F.col("a") > F.col("b"), 1).otherwise(0)).alias("down"))
    out = durable(marked)
    return out, (seen.get["n"], seen.get["h"], seen.get["down"])


def components(edges: DataFrame) -> DataFrame:
    """(a, b) links, in any direction, to (node, component): the least node that each linked node reaches, itself included.

    Nulls and links to oneself are left out.  Each round is cut by a durable table; the number of
    rounds grows with the logarithm of the longest chain.
    """
    edges, mark = _kept(_forest(edges.filter("a <> b").select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).distinct()))
    last = None
    while mark != last and mark[0]:
        last = mark
        edges, mark = _kept(_stars(durable(_stars(edges, large=True)), large=False))
        release(edges)
    roots = edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots)
