"""Bottom-k sketches: the k items of smallest rank, and tau, the next smallest rank.

Columns of entries: sketch_id, pos (from 1, by rank), item_id, weight, rank, u, attrs (a struct).
Columns of a header: sketch_id, family, seed, k, n_seen, total_weight, tau, exact.  With no more
than k items a sketch holds them all: tau is null and exact is true.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.ranks import RankFamily, family_of, hash_uniform, piece_rank, rank_exp

WHOLE = "all"


@dataclass
class Sketch:
    entries: DataFrame
    header: DataFrame
    family: str | None = None  # if known without reading the header

    def flat(self) -> DataFrame:
        """Entries beside the header of their sketch."""
        return self.entries.join(self.header, "sketch_id")


def checked_weight(weight: Column | str, on_negative: str = "error") -> Column:
    """Weight as a double; null for what is never sampled (null, NaN, 0).

    Infinite weights raise; negative ones by policy: error, drop (as 0), clip (to 0) or abs.
    """
    w = (F.col(weight) if isinstance(weight, str) else weight).cast("double")
    if on_negative == "abs":
        w = F.abs(w)
    elif on_negative not in ("error", "drop", "clip"):
        raise ValueError(f"no policy {on_negative}")
    negative = F.raise_error(F.lit("negative weight")).cast("double") if on_negative == "error" else F.lit(None).cast("double")
    return F.when(F.isnan(w) | (w == 0), None).when(F.abs(w) == float("inf"), F.raise_error(F.lit("infinite weight")).cast("double")).when(w < 0, negative).otherwise(w)


def ranked(df: DataFrame, item: Column | str, weight: Column | str, family: str | RankFamily = "exp", seed: str = "s1", attrs: list[str] | None = None, on_negative: str = "error", sketch_id: Column | None = None, uniform=hash_uniform) -> DataFrame:
    """Rows (sketch_id, item_id, weight, rank, u, attrs); rank is null for what is never sampled."""
    item = F.col(item) if isinstance(item, str) else item
    struct = F.struct(*attrs) if attrs else F.struct(F.lit(None).cast("string").alias("none"))
    rows = df.select((sketch_id if sketch_id is not None else F.lit(WHOLE)).cast("string").alias("sketch_id"), item.alias("item_id"), checked_weight(weight, on_negative).alias("weight"), struct.alias("attrs"))
    rows = rows.withColumn("u", F.when(F.col("weight").isNotNull(), uniform(seed, "item_id")))
    return rows.withColumn("rank", family_of(family).rank(F.col("u"), F.col("weight"))).select("sketch_id", "item_id", "weight", "rank", "u", "attrs")


def _header(stats: DataFrame, k: int, family: str, seed: str) -> DataFrame:
    return stats.select("sketch_id", F.lit(family).alias("family"), F.lit(seed).alias("seed"), F.lit(k).alias("k"), F.col("n_seen").cast("long").alias("n_seen"), F.col("total_weight").cast("double").alias("total_weight"), F.col("tau").cast("double").alias("tau"), F.col("tau").isNull().alias("exact"))


def bottomk(df: DataFrame, item: Column | str, weight: Column | str, k: int, family: str | RankFamily = "exp", seed: str = "s1", attrs: list[str] | None = None, on_negative: str = "error", below: float | None = None, uniform=hash_uniform) -> Sketch:
    """One scan: a heap of k+1 rows in every partition, and weight and count as observed metrics.

    Runs at once; k+1 rows come to the driver.  ``below``, if known (say from an earlier total W:
    (k + 1 + 6 sqrt(k + 1)) / W), drops ranks at or over it before heaps are merged; if fewer than
    k+1 are left the scan is repeated without it.
    """
    name = family_of(family).name
    rows = ranked(df, item, weight, family, seed, attrs, on_negative, uniform=uniform)
    seen = Observation()
    counted = rows.observe(seen, F.count("*").alias("n"), F.sum("weight").alias("w")).filter("weight IS NOT NULL")
    if below is not None:
        counted = counted.filter(F.col("rank") < below)
    got = counted.orderBy("rank", "item_id").limit(k + 1).collect()
    if below is not None and len(got) <= k:
        return bottomk(df, item, weight, k, family, seed, attrs, on_negative, None, uniform)
    tau = got[k]["rank"] if len(got) > k else None
    spark = df.sparkSession
    schema = T.StructType([T.StructField("pos", T.IntegerType()), *rows.schema.fields])
    entries = spark.createDataFrame([(i + 1, *r) for i, r in enumerate(got[:k])], schema).select("sketch_id", "pos", "item_id", "weight", "rank", "u", "attrs")
    stats = spark.createDataFrame([(WHOLE, seen.get["n"], seen.get["w"] or 0.0, tau)], "sketch_id string, n_seen long, total_weight double, tau double")
    return Sketch(entries, _header(stats, k, name, seed), name)


#: Rows and totals of grouped sketches that are cached now.
_CACHED: list[DataFrame] = []


def release_cached() -> None:
    """Let go of what grouped sketches have cached; a sketch that is used again is worked out again."""
    while _CACHED:
        _CACHED.pop().unpersist()


def truncated(sketch: Sketch, k: int) -> Sketch:
    """The sketch of a smaller k that a larger one holds: bottom-k sketches are nested, and the next entry's rank is the smaller one's tau."""
    after = sketch.entries.filter(F.col("pos") == k + 1).select("sketch_id", F.col("rank").alias("after"))
    header = sketch.header.join(after, "sketch_id", "left").withColumn("tau", F.when(F.col("k") > k, F.col("after")).otherwise(F.col("tau")))
    header = header.withColumn("exact", F.col("tau").isNull()).withColumn("k", F.lit(k)).select(*sketch.header.columns)
    return Sketch(sketch.entries.filter(F.col("pos") <= k), header, sketch.family)


def top_by(rows: DataFrame, k: int, family: str, seed: str, stats: DataFrame | None = None) -> Sketch:
    """Sketches of ranked rows by sketch_id; a limit below the window keeps k+1 rows a sketch and partition before the shuffle.

    The k+1 rows and the totals of each sketch are cached when first used, so the rows below are
    read once for each of both, however often the sketch is; ``release_cached`` lets go of them.
    """
    order = Window.partitionBy("sketch_id").orderBy("rank", "item_id")
    top = rows.filter("weight IS NOT NULL").withColumn("pos", F.row_number().over(order)).filter(F.col("pos") <= k + 1)
    _CACHED.append(top.persist())
    if stats is None:
        stats = rows.groupBy("sketch_id").agg(F.count("*").alias("n_seen"), F.coalesce(F.sum("weight"), F.lit(0.0)).alias("total_weight"))
        _CACHED.append(stats.persist())
    tau = top.filter(F.col("pos") == k + 1).select("sketch_id", F.col("rank").alias("tau"))
    return Sketch(top.filter(F.col("pos") <= k).select("sketch_id", "pos", "item_id", "weight", "rank", "u", "attrs"), _header(stats.join(tau, "sketch_id", "left"), k, family, seed), family)


def bottomk_by(df: DataFrame, by: Column | str, item: Column | str, weight: Column | str, k: int, family: str | RankFamily = "exp", seed: str = "s1", attrs: list[str] | None = None, on_negative: str = "error") -> Sketch:
    """A sketch for each value of ``by``; an item has the same rank in all of them (coordinated)."""
    rows = ranked(df, item, weight, family, seed, attrs, on_negative, F.col(by) if isinstance(by, str) else by)
    return top_by(rows, k, family_of(family).name, seed)


def merge(*sketches: Sketch, k: int, family: str = "exp", seed: str = "s1", distinct: bool = True, sketch_id: str = WHOLE) -> Sketch:
    """The sketch of the union of the sketched sets, from their entries alone.

    Sketches must share k, family and seed.  Items in several sets count once (``distinct``), and
    then the total weight of the union is unknown; of disjoint sets totals and counts are added.
    An entry of a set whose tau is below another's entry stays correct: the k+1 smallest ranks of
    the union are among the k+1 smallest of each.
    """
    entries, header = sketches[0].entries, sketches[0].header
    for s in sketches[1:]:
        entries, header = entries.unionByName(s.entries), header.unionByName(s.header)
    wrong = header.filter((F.col("k") != k) | (F.col("family") != family) | (F.col("seed") != seed)).limit(1).count()
    if wrong:
        raise ValueError("sketches of another k, family or seed do not merge")
    rows = entries.withColumn("sketch_id", F.lit(sketch_id))
    if distinct:
        rows = rows.dropDuplicates(["item_id"])
    top = top_by(rows, k, family, seed, header.agg(F.sum("n_seen").alias("n_seen"), F.sum("total_weight").alias("total_weight")).withColumn("sketch_id", F.lit(sketch_id)))
    least = header.agg(F.min("tau").alias("least"))
    own = top.header.crossJoin(least)  # one row each
    total = F.lit(None).cast("double") if distinct else F.col("total_weight")
    tau = F.least("tau", "least")
    # with a k+1-st entry its rank is tau, unless a part has seen a smaller one that it does not hold
    return Sketch(top.entries.crossJoin(least).filter(F.col("least").isNull() | (F.col("rank") < F.col("least"))).drop("least"), own.select("sketch_id", "family", "seed", "k", "n_seen", total.alias("total_weight"), tau.alias("tau"), tau.isNull().alias("exact")), family)


def least_distinct(rows: DataFrame, k: int) -> DataFrame:
    """Of ranked rows, in each partition, one of each of the k+1 least (rank, item): copies never leave their partition.

    Copies of unlike weight have unlike ranks; the least of an item's ranks is kept by whoever merges.
    """
    order = [("rank", "ascending"), ("item_id", "ascending")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for batch in batches:
            part = pa.Table.from_batches([batch])
            if held is not None and held.num_rows > k:
                part = part.filter(pc.less_equal(part.column("rank"), held.column("rank")[k]))
            if not part.num_rows:
                continue
            part = (part if held is None else pa.concat_tables([held, part])).sort_by(order)
            item, rank = part.column("item_id").to_pylist(), part.column("rank").to_pylist()
            seen: set = set()
            keep = []
            for i, x in enumerate(item):
                if rank[i] is not None and x not in seen:
                    seen.add(x)
                    keep.append(i)
                    if len(keep) > k:
                        break
            held = part.take(pa.array(keep, pa.int64()))
        if held is not None:
            yield from held.to_batches()

    return rows.mapInArrow(run, rows.schema)


def bottomk_distinct(df: DataFrame, item: Column | str, k: int, weight: Column | str | None = None, seed: str = "s1", family: str = "exp") -> Sketch:
    """The sketch of the set of distinct ids: copies collapse and all but k+1 ids go in each partition, before anything is shuffled.

    The number of distinct ids and their total weight are not known from it (null) unless it holds all of them.
    """
    rows = ranked(df, item, F.lit(1.0) if weight is None else weight, family, seed)
    near = least_distinct(rows.select("item_id", "weight", "rank", "u"), k)
    once = near.groupBy("item_id").agg(F.min(F.struct("rank", "weight", "u")).alias("m")).select(F.lit(WHOLE).alias("sketch_id"), "item_id", "m.weight", "m.rank", "m.u", F.struct(F.lit(None).cast("string").alias("none")).alias("attrs"))
    few = F.count("*") <= k
    stats = once.groupBy("sketch_id").agg(F.when(few, F.count("*")).alias("n_seen"), F.when(few, F.sum("weight")).alias("total_weight"))
    return top_by(once, k, family, seed, stats)


def bottomk_unaggregated(pieces: DataFrame, item: str, piece: list[str], weight: Column | str, k: int, seed: str = "s1") -> Sketch:
    """Items in many pieces, two passes and no total for every item: exponential ranks only.

    Pass 1 finds the k+1 items whose least piece rank is smallest; pass 2 adds up the pieces of those.
    """
    w = checked_weight(weight)
    first = pieces.select(F.col(item).alias("item_id"), w.alias("weight"), piece_rank(seed, piece, w).alias("rank"))
    seen = Observation()
    least = first.observe(seen, F.sum("weight").alias("w")).groupBy("item_id").agg(F.min("rank").alias("rank"))
    count = Observation()
    got = least.observe(count, F.count("*").alias("n")).filter("rank IS NOT NULL").orderBy("rank", "item_id").limit(k + 1).collect()
    spark = pieces.sparkSession
    tau = got[k]["rank"] if len(got) > k else None
    kept = spark.createDataFrame([(i + 1, r["item_id"], r["rank"]) for i, r in enumerate(got[:k])], T.StructType([T.StructField("pos", T.IntegerType()), T.StructField("item_id", pieces.schema[item].dataType), T.StructField("rank", T.DoubleType())]))
    sums = first.select("item_id", "weight").join(F.broadcast(kept.select("item_id")), "item_id", "left_semi").groupBy("item_id").agg(F.sum("weight").alias("weight"))  # k ids
    entries = kept.join(sums, "item_id").select(F.lit(WHOLE).alias("sketch_id"), "pos", "item_id", "weight", "rank", F.exp(-F.col("weight") * F.col("rank")).alias("u"), F.struct(F.lit(None).cast("string").alias("none")).alias("attrs"))
    stats = spark.createDataFrame([(WHOLE, count.get["n"], seen.get["w"] or 0.0, tau)], "sketch_id string, n_seen long, total_weight double, tau double")
    return Sketch(entries, _header(stats, k, "exp", seed), "exp")


def bottomk_preagg(pieces: DataFrame, item: str, weight: Column | str, k: int, family: str = "exp", seed: str = "s1") -> Sketch:
    """The baseline for pieces: total every item, then sketch."""
    totals = pieces.select(F.col(item), checked_weight(weight).alias("__w")).groupBy(item).agg(F.sum("__w").alias("__w"))
    return bottomk(totals, item, "__w", k, family, seed)


def part_minima(parts: DataFrame, part: str, part_weight: str, seed: str) -> DataFrame:
    """The least rank in each part, drawn from the part's known weight alone."""
    return parts.withColumn("least", rank_exp(hash_uniform(seed + "|part", part), F.col(part_weight)))


def bottomk_partitioned(df: DataFrame, part: str, parts: DataFrame, part_weight: str, item: str, weight: Column | str, k: int, seed: str = "s1") -> Sketch:
    """Read at most k+1 parts: those whose drawn least ranks are smallest hold the k+1 smallest ranks.

    In a part the least rank belongs to an item picked by weight, and by the lack of memory every
    other item's rank is that least rank plus an exponential of its own.
    """
    spark = df.sparkSession
    chosen = part_minima(parts, part, part_weight, seed).orderBy("least", part).limit(k + 1).collect()
    kept = spark.createDataFrame([(r[part], r["least"], float(r[part_weight])) for r in chosen], T.StructType([T.StructField(part, parts.schema[part].dataType), T.StructField("least", T.DoubleType()), T.StructField("part_total", T.DoubleType())]))
    rows = df.filter(F.col(part).isin([r[part] for r in chosen])).join(F.broadcast(kept), part)  # k+1 rows
    rows = rows.select(F.lit(WHOLE).alias("sketch_id"), F.col(part).alias("part"), F.col(item).alias("item_id"), checked_weight(weight).alias("weight"), "least", "part_total").filter("weight IS NOT NULL")
    run = Window.partitionBy("part").orderBy("item_id").rowsBetween(Window.unboundedPreceding, 0)
    placed = rows.withColumn("upto", F.sum("weight").over(run)).withColumn("whole", F.sum("weight").over(Window.partitionBy("part"))).withColumn("point", hash_uniform(seed + "|owner", "part") * F.col("whole"))
    own = (F.col("point") <= F.col("upto")) & (F.col("point") > F.col("upto") - F.col("weight"))
    u = hash_uniform(seed, "item_id")
    out = placed.withColumn("rank", F.when(own, F.col("least")).otherwise(F.col("least") + rank_exp(u, F.col("weight")))).withColumn("u", F.exp(-F.col("weight") * F.col("rank"))).withColumn("attrs", F.struct("part"))
    stats = parts.agg(F.lit(None).cast("long").alias("n_seen"), F.sum(part_weight).alias("total_weight")).withColumn("sketch_id", F.lit(WHOLE))
    return top_by(out.select("sketch_id", "item_id", "weight", "rank", "u", "attrs"), k, "exp", seed, stats)


def family_in(sketch: Sketch) -> str:
    """The family of all sketches in a table of sketches; read from the header only if it is not known."""
    if sketch.family is not None:
        return sketch.family
    found = [r["family"] for r in sketch.header.select("family").distinct().limit(2).collect()]
    if len(found) > 1:
        raise ValueError("sketches of several families")
    return found[0] if found else "exp"


def redraw_ordered(sketch: Sketch, total: float | None = None, seed: str = "ro") -> Sketch:
    """Ranks and tau drawn anew given the order of the items and the total weight: gaps are exponential with the weight that is left; exponential ranks."""
    if family_in(sketch) != "exp":
        raise ValueError("drawing ranks given their order needs exponential ranks")
    flat = sketch.flat() if total is None else sketch.flat().withColumn("total_weight", F.lit(float(total)))
    run = Window.partitionBy("sketch_id").orderBy("pos")
    before = F.coalesce(F.sum("weight").over(run.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    gap = -F.log(hash_uniform(seed, "sketch_id", "pos")) / (F.col("total_weight") - before)
    rows = flat.withColumn("gap", gap).withColumn("rank", F.sum("gap").over(run.rowsBetween(Window.unboundedPreceding, 0)))
    last = rows.groupBy("sketch_id").agg(F.max("rank").alias("last"), F.sum("weight").alias("held"), F.max("total_weight").alias("whole"), F.max("k").alias("kk"))
    left = F.nullif(F.col("whole") - F.col("held"), F.lit(0.0))
    tau = F.when(~F.col("exact"), F.col("last") - F.log(hash_uniform(seed, "sketch_id", F.col("kk") + 1)) / left)
    header = sketch.header.join(last, "sketch_id").withColumn("tau", tau).select(*sketch.header.columns)
    return Sketch(rows.select("sketch_id", "pos", "item_id", "weight", "rank", F.exp(-F.col("weight") * F.col("rank")).alias("u"), "attrs"), header, "exp")
