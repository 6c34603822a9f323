"""The catalogue: one query for each method, variant and baseline on the given tables, and its DuckDB text."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.ranks import hash_uniform
from ..operators import adjusted, bounds, kmins, mle, query, sets
from ..operators import sketch as sk
from ..sources.io import table
from . import sql

K = 64
QUERIES, ORACLES = {}, {}


def add(name: str, oracle: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return keep


# ---------------------------------------------------------------- sketches


def orders_sketch(spark: SparkSession, sf_dir: str, family: str = "exp", k: int = K, seed: str = "s1") -> sk.Sketch:
    return sk.bottomk(table(spark, sf_dir, "orders"), "o_orderkey", "o_totalprice", k, family, seed, ["o_orderstatus", "o_orderpriority", "o_custkey"])


def orders_sql(family: str = "exp", k: int = K, seed: str = "s1") -> str:
    return sql.sketch("orders", "o_orderkey", "o_totalprice", k, family, seed, extra=", o_orderstatus, o_orderpriority, o_custkey")


def entries_of(s: sk.Sketch, digits: int = 9) -> DataFrame:
    flat = s.flat()
    scale = F.col("total_weight")
    return flat.select("sketch_id", F.col("pos").cast("long").alias("pos"), F.col("item_id").cast("long").alias("item_id"), F.round("weight", 2).alias("weight"), F.round(F.col("rank") * scale, digits).alias("scaled_rank"), F.round(F.col("tau") * scale, digits).alias("scaled_tau"), F.col("n_seen").cast("long").alias("n_seen"), F.round(scale, 2).alias("total_weight"))


ENTRIES = "SELECT sketch_id, pos, item_id::BIGINT AS item_id, round(weight, 2) AS weight, round(rank * total_weight, {d}) AS scaled_rank, round(tau * total_weight, {d}) AS scaled_tau, n_seen, round(total_weight, 2) AS total_weight FROM e"

for _f in ("exp", "priority"):
    add(f"sketch_{_f}_orders", orders_sql(_f) + ENTRIES.format(d=6))(lambda spark, d, f=_f: entries_of(orders_sketch(spark, d, f), 6))
add("sketch_uniform_orders", orders_sql("uniform") + ENTRIES.format(d=0))(lambda spark, d: entries_of(orders_sketch(spark, d, "uniform"), 0))


@add("sketch_fast_hash")
def _fast(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..functions.ranks import fast_uniform

    return entries_of(sk.bottomk(table(spark, sf_dir, "orders"), "o_orderkey", "o_totalprice", K, uniform=fast_uniform), 6)


@add("sketch_exp_by_status", sql.sketch("orders", "o_orderkey", "o_totalprice", 32, by="o_orderstatus") + ENTRIES.format(d=6))
def _by_status(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entries_of(sk.bottomk_by(table(spark, sf_dir, "orders"), "o_orderstatus", "o_orderkey", "o_totalprice", 32), 6)


@add("sketch_priority_by_nation", sql.sketch("(SELECT * FROM customer WHERE c_acctbal > 0)", "c_custkey", "c_acctbal", 16, "priority", by="c_nationkey") + ENTRIES.format(d=6))
def _by_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entries_of(sk.bottomk_by(table(spark, sf_dir, "customer").filter("c_acctbal > 0"), "c_nationkey", "c_custkey", "c_acctbal", 16, "priority"), 6)


@add("sketch_negative_policies", "SELECT 'drop' AS policy, count(*) FILTER (c_acctbal > 0) AS n, round(sum(c_acctbal) FILTER (c_acctbal > 0), 2) AS total FROM customer UNION ALL SELECT 'abs', count(*) FILTER (c_acctbal <> 0), round(sum(abs(c_acctbal)), 2) FROM customer")
def _policies(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "customer")
    one = lambda p: rows.select(sk.checked_weight("c_acctbal", p).alias("w")).agg(F.count("w").alias("n"), F.round(F.sum("w"), 2).alias("total")).select(F.lit(p).alias("policy"), "n", "total")
    return one("drop").unionByName(one("abs"))


KM = f"""WITH y AS (SELECT j, o_orderkey AS item_id, o_totalprice::DOUBLE AS weight, o_orderstatus AS o_orderstatus, -ln({sql.uniform("s1", "j", "o_orderkey")}) / o_totalprice AS rank FROM orders, range(1, 33) AS t(j) WHERE o_totalprice > 0),
    m AS (SELECT j, min(struct_pack(rank := rank, item_id := item_id, weight := weight)) AS m FROM y GROUP BY j),
    km AS (SELECT j, m.rank AS min_rank, m.item_id AS item_id, m.weight AS weight FROM m),
    t AS (SELECT sum(o_totalprice) AS w FROM orders)"""


def orders_kmins(spark: SparkSession, sf_dir: str) -> kmins.KMins:
    return kmins.kmins(table(spark, sf_dir, "orders"), "o_orderkey", "o_totalprice", 32)


KM_ROWS = KM + " SELECT j::BIGINT AS j, item_id::BIGINT AS item_id, round(weight, 2) AS weight, round(min_rank * w, 6) AS scaled_rank FROM km, t"


def _km_rows(s: kmins.KMins) -> DataFrame:
    return s.rows.join(s.header, "sketch_id").select(F.col("j").cast("long").alias("j"), F.col("item_id").cast("long").alias("item_id"), F.round("weight", 2).alias("weight"), F.round(F.col("min_rank") * F.col("total_weight"), 6).alias("scaled_rank"))


add("sketch_kmins_orders", KM_ROWS)(lambda spark, d: _km_rows(orders_kmins(spark, d)))


for _f, _rank in (("priority", "u / weight"), ("uniform", "u")):
    add(
        f"sketch_kmins_{_f}",
        f"""WITH y AS (SELECT j, item_id, weight, {_rank} AS rank FROM (SELECT j, c_custkey AS item_id, c_acctbal AS weight, {sql.uniform("s1", "j", "c_custkey")} AS u FROM customer, range(1, 17) AS t(j) WHERE c_acctbal > 0)),
        m AS (SELECT j, min(struct_pack(rank := rank, item_id := item_id, weight := weight)) AS m FROM y GROUP BY j)
        SELECT j::BIGINT AS j, m.item_id::BIGINT AS item_id, round(m.weight, 2) AS weight, round(m.rank * 1e6, 9) AS scaled_rank FROM m""",
    )(
        lambda spark, d, f=_f: kmins.kmins(table(spark, d, "customer").filter("c_acctbal > 0"), "c_custkey", "c_acctbal", 16, f).rows.select(F.col("j").cast("long").alias("j"), F.col("item_id").cast("long").alias("item_id"), F.round("weight", 2).alias("weight"), F.round(F.col("min_rank") * 1e6, 9).alias("scaled_rank"))
    )


@add("sketch_kmins_merge", KM_ROWS)
def _km_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders")
    parts = [kmins.kmins(o.filter(F.col("o_orderstatus") == s), "o_orderkey", "o_totalprice", 32) for s in ("F", "O", "P")]
    return _km_rows(kmins.merge_kmins(*parts))


@add("sketch_kmins_ranks", KM + " SELECT j::BIGINT AS j, round(min_rank * w, 6) AS scaled_rank FROM km, t")
def _km_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders")
    total = o.agg(F.sum("o_totalprice").alias("w"))
    return kmins.kmins_ranks(o, "o_orderkey", "o_totalprice", 32).select(F.posexplode("min_ranks").alias("j", "r")).crossJoin(total).select((F.col("j") + 1).cast("long").alias("j"), F.round(F.col("r") * F.col("w"), 6).alias("scaled_rank"))


@add("sketch_merge_months", orders_sql() + ENTRIES.format(d=6))
def _merge_months(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").withColumn("m", F.month("o_orderdate") % 3)
    parts = [sk.bottomk(o.filter(F.col("m") == i), "o_orderkey", "o_totalprice", K) for i in range(3)]
    return entries_of(sk.merge(*parts, k=K, distinct=False), 6)


PIECES = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice", "l_shipdate"]
PIECE_IDS = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "price_text", "date_text"]


def _pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prices in cents and dates in seconds, so that ids read alike in every engine."""
    li = table(spark, sf_dir, "lineitem")
    return li.withColumn("price_text", F.round(F.col("l_extendedprice") * 100).cast("long")).withColumn("date_text", F.unix_seconds(F.col("l_shipdate").cast("timestamp")))


PIECE_SQL = f"(SELECT l_partkey, l_extendedprice, {sql.uniform('s1', 'l_orderkey', 'l_partkey', 'l_suppkey', 'l_linenumber', 'round(l_extendedprice * 100)::BIGINT', 'epoch(l_shipdate)::BIGINT')} AS pu FROM lineitem)"


@add(
    "sketch_two_pass_parts",
    f"""WITH p AS (SELECT l_partkey AS item_id, sum(l_extendedprice) AS weight, min(-ln(pu) / l_extendedprice) AS rank FROM {PIECE_SQL} GROUP BY 1),
    q AS (SELECT *, row_number() OVER (ORDER BY rank, item_id) AS pos FROM p), t AS (SELECT sum(weight) AS w, (SELECT rank FROM q WHERE pos = {K + 1}) AS tau FROM p)
    SELECT pos, item_id::BIGINT AS item_id, round(weight, 2) AS weight, round(rank * w, 6) AS scaled_rank, round(tau * w, 6) AS scaled_tau FROM q, t WHERE pos <= {K}""",
)
def _two_pass(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = sk.bottomk_unaggregated(_pieces(spark, sf_dir), "l_partkey", PIECE_IDS, "l_extendedprice", K)
    return entries_of(s, 6).select("pos", "item_id", "weight", "scaled_rank", "scaled_tau")


@add("sketch_preagg_parts", sql.sketch("(SELECT l_partkey, sum(l_extendedprice) AS w FROM lineitem GROUP BY 1)", "l_partkey", "w", K) + ENTRIES.format(d=4))
def _preagg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entries_of(sk.bottomk_preagg(table(spark, sf_dir, "lineitem"), "l_partkey", "l_extendedprice", K), 4)


def monthly_orders(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, str, DataFrame, str]:
    """Orders kept by month, with the stored catalogue of months and their weights: a sketch of it reads the folders of a few months."""
    from .catalog_streams import scratch

    folder = scratch(spark)
    o = table(spark, sf_dir, "orders").withColumn("part", F.date_format("o_orderdate", "yyyy-MM"))
    o.groupBy("part").agg(F.sum("o_totalprice").alias("pw")).coalesce(1).write.parquet(f"{folder}/catalogue")
    o.repartition("part").write.partitionBy("part").parquet(f"{folder}/orders")
    return spark.read.schema(o.schema).parquet(f"{folder}/orders"), "part", spark.read.parquet(f"{folder}/catalogue"), "pw"


@add(
    "sketch_parts_eliminated",
    f"""WITH o AS (SELECT *, strftime(o_orderdate, '%Y-%m') AS part FROM orders), c AS (SELECT part, sum(o_totalprice) AS pw FROM o GROUP BY 1),
    l AS (SELECT *, -ln({sql.uniform("s1|part", "part")}) / pw AS least FROM c), z AS (SELECT * FROM l ORDER BY least, part LIMIT 13),
    y AS (SELECT o.part, o_orderkey AS item_id, o_totalprice AS weight, least, sum(o_totalprice) OVER (PARTITION BY o.part ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS upto, sum(o_totalprice) OVER (PARTITION BY o.part) AS whole FROM o JOIN z USING (part)),
    v AS (SELECT *, {sql.uniform("s1|owner", "part")} * whole AS point FROM y),
    r AS (SELECT *, CASE WHEN point <= upto AND point > upto - weight THEN least ELSE least - ln({sql.uniform("s1", "item_id")}) / weight END AS rank FROM v),
    q AS (SELECT *, row_number() OVER (ORDER BY rank, item_id) AS pos FROM r), t AS (SELECT sum(pw) AS w FROM c)
    SELECT pos, item_id::BIGINT AS item_id, part, round(weight, 2) AS weight, round(rank * w, 6) AS scaled_rank FROM q, t WHERE pos <= 12""",
)
def _eliminated(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = sk.bottomk_partitioned(*monthly_orders(spark, sf_dir), "o_orderkey", "o_totalprice", 12)
    return s.flat().select(F.col("pos").cast("long").alias("pos"), F.col("item_id").cast("long").alias("item_id"), "attrs.part", F.round("weight", 2).alias("weight"), F.round(F.col("rank") * F.col("total_weight"), 6).alias("scaled_rank"))


@add("sketch_skip_stream")
def _skip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entries_of(sets.bottomk_skip(table(spark, sf_dir, "events"), "event_id", "value", K), 6)


@add("sketch_distinct_users", sql.sketch("(SELECT DISTINCT user_id FROM events)", "user_id", "1", 32, extra="") + " SELECT sketch_id, pos, item_id::BIGINT AS item_id, round(rank, 9) AS rank, round(tau, 9) AS tau FROM e")
def _distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    flat = sk.bottomk_distinct(table(spark, sf_dir, "events"), "user_id", 32).flat()
    return flat.select("sketch_id", F.col("pos").cast("long").alias("pos"), F.col("item_id").cast("long").alias("item_id"), F.round("rank", 9).alias("rank"), F.round("tau", 9).alias("tau"))


_OLD, _WHICH = sql.uniform("mimic", "sketch_id", "d", "'old'"), sql.uniform("mimic", "sketch_id", "d", "'which'")


@add(
    "mimic_with_replacement",
    orders_sql()
    + f""", u AS (SELECT sketch_id, any_value(total_weight) AS w, list(upto ORDER BY pos) AS upto FROM (SELECT *, sum(weight) OVER (PARTITION BY sketch_id ORDER BY pos) AS upto FROM e) GROUP BY 1),
    m AS (SELECT sketch_id, w, upto, 0 AS seen, 0 AS pick, 1 AS d FROM u
        UNION ALL SELECT sketch_id, w, upto, CASE WHEN old THEN seen ELSE seen + 1 END, CASE WHEN old THEN least(seen, 1 + len([x FOR x IN upto[1:seen] IF x < {_WHICH} * upto[seen]])) ELSE seen + 1 END, d + 1
        FROM (SELECT *, seen > 0 AND {_OLD} * w < coalesce(upto[seen], 0) AS old FROM m WHERE d <= 32) WHERE old OR seen < len(upto))
    SELECT (d - 1)::BIGINT AS j, item_id::BIGINT AS item_id, round(weight, 2) AS weight FROM m JOIN e ON e.sketch_id = m.sketch_id AND e.pos = m.pick""",
)
def _mimic(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = sets.mimic_with_replacement(orders_sketch(spark, sf_dir), 32)
    return s.rows.select(F.col("j").cast("long").alias("j"), F.col("item_id").cast("long").alias("item_id"), F.round("weight", 2).alias("weight"))


@add("rank_redraws", orders_sql() + f" SELECT item_id::BIGINT AS item_id, round(-ln(1 - v * (1 - exp(-weight * tau))) / weight * total_weight, 6) AS scaled_rank, round((1 - exp(-weight * rank)) / weight * total_weight, 6) AS as_priority FROM (SELECT *, {sql.uniform('redraw', 'item_id')} AS v FROM e)")
def _redraws(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..functions.ranks import redrawn_rank, remap_rank

    f = orders_sketch(spark, sf_dir).flat()
    again = redrawn_rank(hash_uniform("redraw", "item_id"), F.col("weight"), F.col("tau"))
    return f.select(F.col("item_id").cast("long").alias("item_id"), F.round(again * F.col("total_weight"), 6).alias("scaled_rank"), F.round(remap_rank(F.col("rank"), F.col("weight"), "exp", "priority") * F.col("total_weight"), 6).alias("as_priority"))


@add(
    "rank_redraw_ordered",
    orders_sql()
    + f""", b AS (SELECT *, -ln({sql.uniform("ro", "sketch_id", "pos")}) / (total_weight - coalesce(sum(weight) OVER (ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS gap FROM e)
    SELECT pos, item_id::BIGINT AS item_id, round(sum(gap) OVER (ORDER BY pos) * total_weight, 6) AS scaled_rank, round(((SELECT sum(gap) FROM b) - ln({sql.uniform("ro", "'all'", str(K + 1))}) / (total_weight - (SELECT sum(weight) FROM b))) * total_weight, 6) AS scaled_tau FROM b""",
)
def _redraw_ordered(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entries_of(sk.redraw_ordered(orders_sketch(spark, sf_dir)), 6).select("pos", "item_id", "scaled_rank", "scaled_tau")


# ---------------------------------------------------------------- sets and distances

#: Baskets of the lines of more than 45 pieces: without a condition on lines nearly every part has some of each flag.
_FLAGS = {f: f"(SELECT DISTINCT l_partkey FROM lineitem WHERE l_returnflag = '{f}' AND l_quantity > 45)" for f in "ANR"}


def _union_sql(select: str, first: str = "A", second: str = "R") -> str:
    def one(tag: str) -> str:
        text = sql.sketch(f"part JOIN {_FLAGS[tag]} ON l_partkey = p_partkey", "p_partkey", "p_retailprice", K)
        return text.replace("WITH RECURSIVE ", f"e{tag} AS (WITH ", 1) + f" SELECT * FROM e), h{tag} AS (" + text.replace("WITH RECURSIVE", "WITH", 1) + " SELECT * FROM h)"

    return f"""WITH {one(first)}, {one(second)},
    u0 AS (SELECT item_id, weight, rank FROM e{first} UNION SELECT item_id, weight, rank FROM e{second}),
    u1 AS (SELECT *, row_number() OVER (ORDER BY rank, item_id) AS pos FROM u0),
    tt AS (SELECT least((SELECT rank FROM u1 WHERE pos = {K + 1}), (SELECT tau FROM h{first}), (SELECT tau FROM h{second})) AS tau),
    u AS (SELECT u1.*, weight / (1 - exp(-weight * tau)) AS adj, item_id IN (SELECT item_id FROM e{first}) AS a, item_id IN (SELECT item_id FROM e{second}) AS b FROM u1, tt WHERE pos <= {K}) {select}"""


def _relations(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts, li = table(spark, sf_dir, "part"), table(spark, sf_dir, "lineitem").filter("l_quantity > 45")
    one = lambda f: sk.bottomk(parts.join(li.filter(F.col("l_returnflag") == f), F.col("l_partkey") == F.col("p_partkey"), "left_semi"), "p_partkey", "p_retailprice", K)
    return sets.set_relations(one("A"), one("R"), K)


add("set_union_weight", _union_sql("SELECT round(sum(adj), 4) AS union_weight FROM u"))(lambda s, d: _relations(s, d).select(F.round("union_weight", 4).alias("union_weight")))
add("set_intersection_weight", _union_sql("SELECT round(coalesce(sum(adj) FILTER (a AND b), 0), 4) AS intersection_weight, round(coalesce(sum(adj) FILTER (a AND NOT b), 0), 4) AS only_a FROM u"))(lambda s, d: _relations(s, d).select(F.round("intersection_weight", 4).alias("intersection_weight"), F.round("only_a", 4).alias("only_a")))
add("set_jaccard", _union_sql("SELECT round(coalesce(sum(adj) FILTER (a AND b), 0) / sum(adj), 9) AS jaccard FROM u"))(lambda s, d: _relations(s, d).select(F.round("jaccard", 9).alias("jaccard")))

_DIST = "(epoch((SELECT max(ts) FROM events)) - epoch(ts))"


def _ads(spark: SparkSession, sf_dir: str, k: int = 16) -> DataFrame:
    ev = table(spark, sf_dir, "events")
    last = ev.agg(F.max("ts").alias("last"))
    return sets.all_distances(ev.crossJoin(last), "event_id", "value", F.unix_micros(F.col("last").cast("timestamp")) / 1e6 - F.unix_micros(F.col("ts").cast("timestamp")) / 1e6, k, "event_type")


_ADS_SQL = f"""WITH x AS (SELECT event_type AS sketch_id, event_id AS item_id, value AS weight, {_DIST} AS distance, -ln({sql.uniform("s1", "event_id")}) / value AS rank FROM events WHERE value > 0),
    a AS (SELECT *, (SELECT count(*) FROM x y WHERE y.sketch_id = x.sketch_id AND (y.distance < x.distance OR (y.distance = x.distance AND (y.rank, y.item_id) < (x.rank, x.item_id))) AND y.rank < x.rank) AS smaller FROM x)"""


add("all_distances_events", _ADS_SQL + " SELECT sketch_id, item_id::BIGINT AS item_id, round(weight, 4) AS weight, round(rank * 1000, 9) AS scaled_rank FROM a WHERE smaller <= 16")(
    lambda s, d: _ads(s, d).select("sketch_id", F.col("item_id").cast("long").alias("item_id"), F.round("weight", 4).alias("weight"), F.round(F.col("rank") * 1000, 9).alias("scaled_rank"))
)


@add("neighborhood_weight", sql.sketch(f"(SELECT * FROM events WHERE {_DIST} <= 864000)", "event_id", "value", 16, by="event_type") + f" SELECT sketch_id, count(*) AS n, round(sum({sql.ADJ['exp']}), 4) AS estimate FROM e GROUP BY 1")
def _near(spark: SparkSession, sf_dir: str) -> DataFrame:
    adj = adjusted.rank_conditioned(sets.neighborhood(_ads(spark, sf_dir), 864000.0, 16))
    return adj.groupBy("sketch_id").agg(F.count("*").alias("n"), F.round(F.sum("adj_weight"), 4).alias("estimate"))


@add(
    "decayed_sum",
    _ADS_SQL
    + """, z AS (SELECT * FROM a WHERE smaller <= 16), k AS (SELECT *, list_sort(list(rank) OVER (PARTITION BY sketch_id ORDER BY distance, rank, item_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))[16] AS kth FROM z)
    SELECT sketch_id, round(sum(CASE WHEN kth IS NULL THEN weight WHEN rank < kth THEN weight / (1 - exp(-weight * kth)) ELSE 0 END * exp(-distance / 864000)), 4) AS estimate FROM k GROUP BY 1""",
)
def _decayed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sets.decayed_weight(_ads(spark, sf_dir), 16, lambda x: F.exp(-x / 864000)).withColumn("estimate", F.round("estimate", 4))


# ---------------------------------------------------------------- with-replacement estimators

add("kmins_unbiased", KM + " SELECT round(31 / sum(min_rank), 4) AS estimate FROM km")(lambda s, d: kmins.kmins_weight(orders_kmins(s, d)).select(F.round("estimate", 4).alias("estimate")))
add("kmins_ml", KM + " SELECT round(32 / sum(min_rank), 4) AS estimate FROM km")(lambda s, d: kmins.kmins_weight_ml(orders_kmins(s, d)).select(F.round("estimate", 4).alias("estimate")))
add("kmins_inverse", KM + " SELECT round(sum(min_rank) / 32 * 1e9, 9) AS estimate FROM km")(lambda s, d: kmins.kmins_inverse_weight(orders_kmins(s, d)).select(F.round(F.col("estimate") * 1e9, 9).alias("estimate")))
add("kmins_ht", KM + " SELECT round(sum(weight / (1 - pow(1 - weight / w, 32))) / any_value(w), 6) AS share FROM (SELECT DISTINCT item_id, weight FROM km), t WHERE item_id % 2 = 0")(
    lambda s, d: kmins.kmins_ht(orders_kmins(s, d), "item_id % 2 = 0").crossJoin(table(s, d, "orders").agg(F.sum("o_totalprice").alias("w"))).select(F.round(F.col("estimate") / F.col("w"), 6).alias("share"))
)
add("kmins_ratio", KM + " SELECT round(w / 32 * (SELECT count(*) FROM km WHERE item_id % 2 = 0), 4) AS estimate FROM t")(lambda s, d: kmins.kmins_ratio(orders_kmins(s, d), "item_id % 2 = 0").select(F.round("estimate", 4).alias("estimate")))

# ---------------------------------------------------------------- maximum likelihood

_S = "list_concat(ins, [sum_in])"
_J = "o_orderstatus = 'F'"


def opened(s: sk.Sketch) -> sk.Sketch:
    return sk.Sketch(query.attributes(s.entries), s.header, s.family)


def _est(df: DataFrame, digits: int = 2) -> DataFrame:
    return df.select(F.round("estimate", digits).alias("estimate"))


add("ml_total", orders_sql() + sql.splits("true") + sql.bisect("b", f"{sql.inv('mid', _S)} > tau", "sum_in + 1 / tau", f"sum_in + {K + 1} / tau") + " SELECT round(root, 2) AS estimate FROM b")(lambda s, d: _est(mle.mle_total(orders_sketch(s, d))))
add("ml_subpop", orders_sql() + sql.splits(_J) + sql.bisect("b", f"{sql.inv('mid', 'ins')} > tau", "ins[-1] + 1 / tau", "ins[-1] + len(ins) / tau") + " SELECT round(greatest(root, sum_in), 2) AS estimate FROM b JOIN g USING (sketch_id)")(
    lambda s, d: _est(mle.mle_subpop(opened(orders_sketch(s, d)), _J))
)
add("ml_subpop_total", orders_sql() + sql.splits(_J) + sql.bisect("b", f"{sql.inv('mid', 'ins')} > {sql.inv('(w - mid)', 'outs')}", "ins[-1]", "w - outs[-1]") + " SELECT round(least(greatest(root, sum_in), w - sum_out), 2) AS estimate FROM b JOIN g USING (sketch_id)")(
    lambda s, d: _est(mle.mle_subpop_with_total(opened(orders_sketch(s, d)), _J))
)
_ALL = sql.bisect("b", f"{sql.inv('mid', _S)} > tau", "sum_in + 1 / tau", "sum_in + len(ins) / tau + 1 / tau")
add("ml_total_redraw", orders_sql() + sql.redrawn(20) + sql.splits("true", "er") + _ALL + " SELECT round(avg(root), 2) AS estimate FROM b")(lambda s, d: _est(mle.mle_total(orders_sketch(s, d), redraws=20)))
add("ml_subpop_redraw", orders_sql() + sql.redrawn(20) + sql.splits(_J, "er") + sql.bisect("b", f"{sql.inv('mid', 'ins')} > tau", "ins[-1] + 1 / tau", "ins[-1] + len(ins) / tau") + " SELECT round(avg(greatest(root, sum_in)), 2) AS estimate FROM b JOIN g USING (sketch_id)")(lambda s, d: _est(mle.mle_subpop(opened(orders_sketch(s, d)), _J, redraws=20)))

# ---------------------------------------------------------------- adjusted weights


def _shares(adj: DataFrame, digits: int = 8) -> DataFrame:
    return adj.select("sketch_id", F.col("item_id").cast("long").alias("item_id"), F.round(F.col("adj_weight") / F.col("total_weight"), digits).alias("share"))


for _f in ("exp", "priority", "uniform"):
    add(f"rc_{_f}_items", orders_sql(_f) + f" SELECT sketch_id, item_id::BIGINT AS item_id, round({sql.ADJ[_f]} / total_weight, 8) AS share FROM e")(lambda s, d, f=_f: _shares(adjusted.rank_conditioned(orders_sketch(s, d, f))))

_REGION_JOIN = "JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey"


def with_region(spark: SparkSession, sf_dir: str, rows: DataFrame) -> DataFrame:
    """Rows with a customer key beside their region: dimensions join to the few rows of a sketch."""
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    return rows.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))


for _f in ("exp", "priority"):

    @add(f"rc_{_f}_by_region", orders_sql(_f, 256) + f" SELECT r_name, round(sum({sql.ADJ[_f]}), 2) AS estimate, count(*) AS n FROM e {_REGION_JOIN} GROUP BY 1")
    def _by_region(spark: SparkSession, sf_dir: str, f: str = _f) -> DataFrame:
        adj = query.attributes(adjusted.rank_conditioned(orders_sketch(spark, sf_dir, f, 256)))
        return with_region(spark, sf_dir, adj).groupBy("r_name").agg(F.round(F.sum("adj_weight"), 2).alias("estimate"), F.count("*").alias("n"))


add(
    "prefix_conditioned_items",
    orders_sql()
    + f""", pr AS (SELECT a.sketch_id, a.item_id, a.weight, a.total_weight, b.pos AS m, CASE WHEN b.pos < a.pos THEN 0 ELSE 0 END AS z,
        (SELECT coalesce(sum(c.weight), 0) FROM e c WHERE c.item_id <> a.item_id AND (CASE WHEN c.pos > a.pos THEN c.pos - 1 ELSE c.pos END) < b.pos) AS s FROM e a, e b)
    SELECT sketch_id, item_id::BIGINT AS item_id, round(weight / (1 - exp(sum(ln(1 - weight / (total_weight - s))))) / any_value(total_weight), 8) AS share FROM pr GROUP BY sketch_id, item_id, weight""",
)(lambda s, d: _shares(adjusted.prefix_conditioned(orders_sketch(s, d))))

_NATIONS = f"(SELECT c_nationkey, sum(o_totalprice) AS w FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1)"
_MASK = "list_sum([CASE WHEN (m >> (i - 1)) & 1 = 1 THEN ws[i] ELSE 0 END FOR i IN range(1, len(ws) + 1)])"


def _f_sql(ws: str, rest: str) -> str:
    """Inclusion and exclusion over the subsets of a list."""
    return f"list_sum([(CASE WHEN bit_count(m) % 2 = 0 THEN 1 ELSE -1 END) * ({rest}) / (({rest}) + list_sum([CASE WHEN (m >> (i - 1)) & 1 = 1 THEN ({ws})[i] ELSE 0.0 END FOR i IN range(1, len({ws}) + 1)])) FOR m IN range(0, (1 << len({ws}))::BIGINT)])"


def nation_sketch(spark: SparkSession, sf_dir: str) -> sk.Sketch:
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    return sk.bottomk(o.join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_nationkey").agg(F.sum("o_totalprice").alias("w")), "c_nationkey", "w", 6)


add(
    "subset_conditioned_small",
    sql.sketch(_NATIONS, "c_nationkey", "w", 6)
    + f""", ll AS (SELECT list(weight / total_weight ORDER BY pos) AS ws, 1 - sum(weight / total_weight) AS rest FROM e),
    o AS (SELECT sketch_id, item_id, weight / total_weight AS w, ws, rest, list_concat(ws[1 : pos - 1], ws[pos + 1 :]) AS others FROM e, ll)
    SELECT sketch_id, item_id::BIGINT AS item_id, round(w * {_f_sql("others", "rest")} / {_f_sql("ws", "rest")}, 6) AS share FROM o""",
)(lambda s, d: _shares(adjusted.subset_conditioned(nation_sketch(s, d)), 6))

add(
    "subset_conditioned_orders",
    orders_sql()
    + """, ll AS (SELECT list(weight / total_weight ORDER BY pos) AS ws, 1 - sum(weight / total_weight) AS rest FROM e),
    t AS (SELECT i * 0.002 - 12.0 AS t FROM range(0, 12001) AS r(i)),
    d0 AS (SELECT t, t - rest * exp(t) + list_sum([ln(1 - exp(-x * exp(t))) FOR x IN ws]) AS g FROM t, ll WHERE t < 12),
    d AS (SELECT t, exp(g - (SELECT max(g) FROM d0)) AS p FROM d0 WHERE g > (SELECT max(g) FROM d0) - 60)
    SELECT sketch_id, item_id::BIGINT AS item_id, round(sum(p * (weight / total_weight) / (1 - exp(-(weight / total_weight) * exp(t)))) / sum(p), 8) AS share FROM e, d GROUP BY 1, 2""",
)(lambda s, d: _shares(adjusted.subset_conditioned(orders_sketch(s, d))))

add(
    "ordered_average_items",
    orders_sql()
    + f""", pp AS (SELECT sketch_id, total_weight AS w, sum(weight) OVER (PARTITION BY sketch_id ORDER BY pos) AS s, pos AS j FROM e UNION ALL SELECT sketch_id, total_weight, 0, 0 FROM h),
    tt AS (SELECT sketch_id, d, sum(-ln({sql.uniform("oa", "sketch_id", "d", "j")}) / (w - s)) AS t FROM pp, range(1, 101) AS r(d) GROUP BY 1, 2)
    SELECT e.sketch_id, item_id::BIGINT AS item_id, round(avg(weight / (1 - exp(-weight * t))) / any_value(total_weight), 8) AS share FROM e JOIN tt USING (sketch_id) GROUP BY 1, 2""",
)(lambda s, d: _shares(adjusted.ordered_average(orders_sketch(s, d), draws=100)))

for _r, _p in ((5, 2), (20, 20), (400, 1), (1, 400)):
    add(f"chain_{_r}_{_p}", orders_sql() + sql.chain(_r, _p) + " SELECT sketch_id, item_id::BIGINT AS item_id, round(acc[pos] / total_weight, 8) AS share FROM e JOIN ch USING (sketch_id)")(lambda s, d, r=_r, p=_p: _shares(adjusted.subset_conditioned_chain(orders_sketch(s, d), redraws=r, steps=p)))

add("partitioned_ht_items", orders_sql() + f" SELECT sketch_id, item_id::BIGINT AS item_id, round({sql.ADJ['exp']} / total_weight, 8) AS share FROM e")(lambda s, d: _shares(adjusted.partitioned_ht(orders_sketch(s, d), -F.expm1(-F.col("weight") * F.col("tau")))))
add("horvitz_thompson", f"SELECT round(sum(o_totalprice / least(1, o_totalprice * 1e-6)), 2) AS estimate, count(*) AS n FROM orders WHERE {sql.uniform('poisson', 'o_orderkey')} < o_totalprice * 1e-6")(
    lambda s, d: adjusted.horvitz_thompson(table(s, d, "orders").withColumn("p", F.least(F.lit(1.0), F.col("o_totalprice") * 1e-6)).filter(hash_uniform("poisson", "o_orderkey") < F.col("p")), "o_totalprice", "p").agg(F.round(F.sum("adj_weight"), 2).alias("estimate"), F.count("*").alias("n"))
)

# ---------------------------------------------------------------- queries over adjusted weights


def _adj(spark: SparkSession, sf_dir: str, k: int = 256) -> DataFrame:
    return query.attributes(adjusted.rank_conditioned(orders_sketch(spark, sf_dir, k=k)))


_A = orders_sql(k=256) + f", a AS (SELECT *, {sql.ADJ['exp']} AS adj FROM e)"
add("subpop_weight", _A + f" SELECT round(coalesce(sum(adj) FILTER ({_J}), 0), 2) AS estimate FROM a")(lambda s, d: _est(query.subpop_weight(_adj(s, d), _J)))
add("selectivity", _A + f" SELECT round(sum(adj) FILTER ({_J}) / sum(adj), 9) AS estimate FROM a")(lambda s, d: _est(query.selectivity(_adj(s, d), _J), 9))
add("moments", _A + f", s AS (SELECT sum(adj / weight) AS c, sum(adj) AS m, sum(adj * weight) AS q FROM a WHERE {_J}) SELECT round(c, 4) AS count, round(m / c, 4) AS mean, round((q / c - (m / c) * (m / c)) / 1e9, 6) AS variance FROM s")(
    lambda s, d: query.moments(_adj(s, d), _J).select(F.round("count", 4).alias("count"), F.round("mean", 4).alias("mean"), F.round(F.col("variance") / 1e9, 6).alias("variance"))
)
add("other_attribute", _A + " SELECT round(sum(o_custkey * adj / weight), 2) AS estimate FROM a")(lambda s, d: _est(query.other_attribute(_adj(s, d), "o_custkey")))
add("weight_ratio", _A + " SELECT round(sum(adj) FILTER (o_orderstatus = 'F') / sum(adj) FILTER (o_orderstatus = 'O'), 9) AS estimate FROM a")(lambda s, d: _est(query.weight_ratio(_adj(s, d), _J, "o_orderstatus = 'O'"), 9))
for _m in ("rollup", "cube"):
    add(f"{_m}_estimates", _A + f" SELECT o_orderstatus, o_orderpriority, round(sum(adj), 2) AS estimate FROM a GROUP BY {_m}(o_orderstatus, o_orderpriority)")(
        lambda s, d, m=_m: query.weight_by(_adj(s, d), ["o_orderstatus", "o_orderpriority"], m).withColumn("estimate", F.round("estimate", 2))
    )
add("exact_weight", "SELECT o_orderstatus, round(sum(o_totalprice), 2) AS exact FROM orders GROUP BY 1")(lambda s, d: query.exact_weight(table(s, d, "orders"), "o_totalprice", by=["o_orderstatus"]).withColumn("exact", F.round("exact", 2)))

# ---------------------------------------------------------------- bounds


def _b(df: DataFrame, digits: int = 2) -> DataFrame:
    return df.select(F.round("lower", digits).alias("lower"), F.round("upper", digits).alias("upper"))


_ALPHA = sql.normal_quantile(0.95)
add("bounds_kmins", KM + f" SELECT round((1 - {_ALPHA!r} / sqrt(32)) / avg(min_rank), 2) AS lower, round((1 + {_ALPHA!r} / sqrt(32)) / avg(min_rank), 2) AS upper FROM km")(lambda s, d: _b(bounds.bounds_kmins(orders_kmins(s, d))))
_G = ", g2 AS (SELECT *, list_concat(ins, [sum_in]) AS sums FROM g)"
add("bounds_exp_total_normal", orders_sql() + sql.splits("true") + _G + sql.upper_normal("up", "sums", "tau", 0.05, "g2") + sql.lower_normal("dn", "sums", "tau", 0.05, "g2") + " SELECT round(greatest(coalesce(dn.root, sum_in), sum_in), 2) AS lower, round(up.root, 2) AS upper FROM g2 JOIN up USING (sketch_id) JOIN dn USING (sketch_id)")(
    lambda s, d: _b(bounds.bounds_total(orders_sketch(s, d)))
)
_D = 50
add("bounds_exp_total_quantile", orders_sql(k=24) + sql.splits("true") + _G + sql.draw_roots("dr", "sums", "tau", "bt", _D, "g2") + f" SELECT round(greatest(sum_in, {sql.pick('xs', 0.05, _D)}), 2) AS lower, round({sql.pick('xs', 0.95, _D)}, 2) AS upper FROM g2 JOIN dr USING (sketch_id)")(
    lambda s, d: _b(bounds.bounds_total(orders_sketch(s, d, k=24), solver="quantile", draws=_D))
)
add("bounds_exp_total_set", orders_sql() + sql.set_limits("sl", 0.05) + " SELECT round(lower / w, 3) AS lower, round(upper / w, 3) AS upper FROM sl")(
    lambda s, d: bounds.bounds_total(orders_sketch(s, d), conditioning="set").crossJoin(table(s, d, "orders").agg(F.sum("o_totalprice").alias("w"))).select(F.round(F.col("lower") / F.col("w"), 3).alias("lower"), F.round(F.col("upper") / F.col("w"), 3).alias("upper"))
)
add("bounds_subpop_normal", orders_sql() + sql.splits(_J) + _G + sql.upper_normal("up", "sums", "tau", 0.05, "g2") + sql.lower_normal("dn", "ins", "last", 0.05, "g2") + " SELECT round(greatest(coalesce(dn.root, sum_in), sum_in), 2) AS lower, round(up.root, 2) AS upper FROM g2 JOIN up USING (sketch_id) JOIN dn USING (sketch_id)")(
    lambda s, d: _b(bounds.bounds_subpop(opened(orders_sketch(s, d)), _J, solver="normal"))
)
add("bounds_subpop_quantile", orders_sql() + sql.splits(_J) + _G + sql.draw_roots("dr", "sums", "tau", "bs", _D, "g2") + sql.draw_roots("dl", "ins", "last", "bs", _D, "g2") + f" SELECT round(greatest(sum_in, {sql.pick('dl.xs', 0.05, _D)}), 2) AS lower, round({sql.pick('dr.xs', 0.95, _D)}, 2) AS upper FROM g2 JOIN dr USING (sketch_id) JOIN dl USING (sketch_id)")(
    lambda s, d: _b(bounds.bounds_subpop(opened(orders_sketch(s, d)), _J, draws=_D))
)
SPLIT_SQL = orders_sql() + sql.splits(_J) + sql.split_roots("sr", _D) + f", split_limits AS (SELECT sketch_id, round({sql.pick('xs', 0.05, _D)}, 2) AS lower, round({sql.pick('xs', 0.95, _D)}, 2) AS upper FROM sr)"
add("bounds_subpop_total", SPLIT_SQL + " SELECT lower, upper FROM split_limits")(lambda s, d: _b(bounds.bounds_subpop(opened(orders_sketch(s, d)), _J, total=True, draws=_D)))
_LOG = math.log(0.05)
add(
    "bounds_priority_chernoff",
    orders_sql("priority")
    + f""", c AS (SELECT any_value(sketch_id) AS sketch_id, any_value(tau) AS tau, coalesce(sum(weight) FILTER ({_J} AND weight * tau >= 1), 0) AS certain, (count(*) FILTER ({_J} AND weight * tau < 1))::DOUBLE AS n FROM e)"""
    + sql.bisect("up", f"n - mid + n * ln(mid / n) - ({_LOG!r}) > 0", "n", f"n - 2 * ({_LOG!r}) + sqrt(greatest(4 * {_LOG * _LOG!r} - 8 * n * ({_LOG!r}), 0)) + 1", "c")
    + sql.bisect("dn", f"n - mid + n * ln(mid / n) - ({_LOG!r}) < 0", "n * 1e-12", "n", "c")
    + " SELECT round(certain + dn.root / tau, 2) AS lower, round(certain + up.root / tau, 2) AS upper FROM c JOIN up USING (sketch_id) JOIN dn USING (sketch_id)",
)(lambda s, d: _b(bounds.bounds_priority(opened(orders_sketch(s, d, "priority")), _J)))
add("bounds_priority_poisson", orders_sql("priority") + sql.poisson("pp", "e", _J) + " SELECT round(lower, 2) AS lower, round(upper, 2) AS upper FROM pp")(lambda s, d: _b(bounds.bounds_priority(opened(orders_sketch(s, d, "priority")), _J, "poisson")))
add("bounds_priority_simulated", orders_sql("priority") + sql.simulated("ps", "e", _J) + " SELECT round(lower, 2) AS lower, round(upper, 2) AS upper FROM ps")(lambda s, d: _b(bounds.bounds_priority(opened(orders_sketch(s, d, "priority")), _J, "simulated")))
add("bounds_priority_total")(lambda s, d: _b(bounds.bounds_priority_total(orders_sketch(s, d, "priority"))))
SUBSET_SQL = orders_sql() + sql.subset() + " SELECT sketch_id, item_id::BIGINT AS item_id, share FROM e JOIN sc USING (sketch_id, pos)"
add(
    "estimate_and_bounds",
    SPLIT_SQL.replace(f"range(1, {_D + 1})", "range(1, 201)").replace(sql.pick("xs", 0.05, _D), sql.pick("xs", 0.05, 200)).replace(sql.pick("xs", 0.95, _D), sql.pick("xs", 0.95, 200))
    + sql.subset(12)
    + f" SELECT sketch_id, (SELECT round(sum(share * total_weight), 1) FROM e JOIN sc USING (sketch_id, pos) WHERE {_J}) AS estimate, lower, upper FROM split_limits",
)(lambda s, d: query.estimate(orders_sketch(s, d), _J).select("sketch_id", F.round("estimate", 1).alias("estimate"), F.round("lower", 2).alias("lower"), F.round("upper", 2).alias("upper")))
