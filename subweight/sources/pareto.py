"""A data source of heavy-tailed weights: spark.read.format("pareto_weights").option("rows", n).option("alpha", a).

Items are 0 to n - 1, or those of the option "ranges" ("first:last,..."); ``weights_of`` asks for the
ranges in which a table has ids and gives the weights to its rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


#: Ids of a block, of which the least and the largest in a table bound a range; most items of a partition and of a batch.
BLOCK, PART, BATCH = 1 << 16, 1 << 18, 1 << 16


class _Part(InputPartition):
    def __init__(self, ranges: list[tuple[int, int]]):
        self.ranges = ranges  # ends are not in


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.rows, self.alpha = int(options.get("rows", 1000)), float(options.get("alpha", 1.2))
        self.parts, self.seed = int(options.get("partitions", 4)), options.get("seed", "pareto")
        self.ranges, self.part = options.get("ranges"), PART

    def partitions(self) -> list[_Part]:
        if self.ranges is None:
            edges = [self.rows * i // self.parts for i in range(self.parts + 1)]
            return [_Part([(a, b)]) for a, b in zip(edges, edges[1:], strict=False)]
        out, held, size = [], [], 0
        for text in self.ranges.split(",") if self.ranges else []:
            at, last = (int(x) for x in text.split(":"))
            while at <= last:
                end = min(last + 1, at + self.part - size)
                held.append((at, end))
                size, at = size + end - at, end
                if size == self.part:
                    out.append(_Part(held))
                    held, size = [], 0
        return [*out, _Part(held)]

    def read(self, partition: _Part, most: int = BATCH) -> Iterator[pa.RecordBatch]:
        import hashlib

        for start, end in partition.ranges:
            for first in range(start, end, most):
                ids = range(first, min(end, first + most))
                u = [(int(hashlib.md5(f"{self.seed}|{i}".encode()).hexdigest()[:13], 16) + 0.5) / 2.0**52 for i in ids]
                yield pa.RecordBatch.from_arrays([pa.array(list(ids), pa.int64()), pa.array([(1 - x) ** (-1 / self.alpha) for x in u], pa.float64())], names=["item_id", "weight"])


class ParetoWeights(DataSource):
    @classmethod
    def name(cls) -> str:
        return "pareto_weights"

    def schema(self) -> str:
        return "item_id long, weight double"

    def reader(self, schema) -> _Reader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ParetoWeights)


def weights_of(rows: DataFrame, id_column: str, alpha: float) -> DataFrame:
    """(item_id, weight) of every row of a table, from the source; a null id has no weight.

    The ranges come to the driver, one for each run of blocks without a gap: few for ids that stand close together.
    """
    register(rows.sparkSession)
    ids = rows.select(F.col(id_column).cast("long").alias("item_id"))
    blocks = ids.filter("item_id IS NOT NULL").groupBy(F.floor(F.col("item_id") / BLOCK).alias("block")).agg(F.min("item_id").alias("first"), F.max("item_id").alias("last"))
    ranges: list[list[int]] = []
    for r in blocks.orderBy("first").collect():
        if ranges and r["first"] == ranges[-1][1] + 1:
            ranges[-1][1] = r["last"]
        else:
            ranges.append([r["first"], r["last"]])
    made = rows.sparkSession.read.format("pareto_weights").option("alpha", alpha).option("ranges", ",".join(f"{a}:{b}" for a, b in ranges)).load()
    return ids.join(made.select(F.col("item_id").alias("of"), "weight"), F.col("item_id") == F.col("of"), "left").select("item_id", "weight")
