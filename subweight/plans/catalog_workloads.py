"""Catalogue entries of the experiments, at few repetitions; the workload functions take as many as wanted."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..operators import sketch as sk
from . import sql, workloads
from .catalog import _FLAGS, PIECE_IDS, PIECE_SQL, K, _pieces, _union_sql, add, orders_sql

REPS = 10


def _round(df, digits: int = 6):
    """The rows of an experiment, a few, as a table of their own, so that what its sketches cached can go."""
    rows = df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c).cast("long").alias(c) if t in ("int", "bigint") else F.col(c) for c, t in df.dtypes])
    out = df.sparkSession.createDataFrame(rows.collect(), rows.schema)
    sk.release_cached()
    return out


def base_sql(alphas=(1.0, 1.2, 2.0), uniform: bool = True, n: int | None = 1000) -> str:
    u = sql.uniform("pareto", "o_orderkey")
    rows = "orders" if n is None else f"orders WHERE o_orderkey < {n}"
    parts = [f"SELECT 'pareto{a:g}' AS wt, o_orderkey AS item_id, pow(1 - {u}, {-1.0 / a!r}) AS weight FROM {rows}" for a in alphas]
    if uniform:
        parts.append(f"SELECT 'uniform', o_orderkey, {u} FROM {rows}")
    return "(" + " UNION ALL ".join(parts) + ")"


NATURAL = "(SELECT 'n_chars' AS wt, doc_id AS item_id, n_chars::DOUBLE AS weight FROM documents UNION ALL SELECT 'value', event_id, value FROM events UNION ALL SELECT 'totalprice', o_orderkey, o_totalprice FROM orders)"


def reps_sql(base: str, k: int, family: str, reps: int = REPS) -> str:
    return sql.sketch(f"{base} b, range({reps}) AS rr(rep)", "item_id", "weight", k, family, "w", by="wt || '#' || rep", extra=", rep, wt", key="rep,item_id")


def _cte(text: str, select: str) -> str:
    return f"({text} {select})"


def _least(base: str, k: int, reps: int) -> str:
    """The least ranks of sketches with replacement."""
    return f"(SELECT wt || '#' || rep AS sketch_id, j, min(-ln({sql.uniform('w', 'rep', 'j', 'item_id')}) / weight) AS r FROM {base} b, range({reps}) AS rr(rep), range(1, {k + 1}) AS jj(j) GROUP BY ALL)"


def _error_sql(k: int, reps: int = REPS, base: str | None = None) -> str:
    base = base or base_sql()
    exp, pri = reps_sql(base, k, "exp", reps), reps_sql(base, k, "priority", reps)
    ml = exp + sql.splits("true") + sql.bisect("b", f"{sql.inv('mid', 'list_concat(ins, [sum_in])')} > tau", "sum_in + 1 / tau", f"sum_in + {k + 1} / tau")
    parts = [
        f"SELECT *, 'exp_rc' AS method FROM {_cte(exp, f'SELECT sketch_id, sum({sql.ADJ["exp"]}) AS estimate FROM e GROUP BY 1')}",
        f"SELECT *, 'priority_rc' FROM {_cte(pri, f'SELECT sketch_id, sum({sql.ADJ["priority"]}) AS estimate FROM e GROUP BY 1')}",
        f"SELECT *, 'exp_ml' FROM {_cte(ml, 'SELECT sketch_id, root AS estimate FROM b')}",
        f"SELECT sketch_id, {k - 1} / sum(r) AS estimate, 'with_replacement' FROM {_least(base, k, reps)} GROUP BY 1",
    ]
    return f"""SELECT wt, {k}::BIGINT AS k, method, round(avg(abs(estimate / truth - 1)), 6) AS mean_abs_rel_error, round(avg(estimate / truth - 1), 6) AS bias, round(sqrt(avg(pow(estimate / truth - 1, 2))), 6) AS rmse, count(*) AS reps
        FROM ({" UNION ALL ".join(parts)}) e JOIN (SELECT wt, sum(weight) AS truth FROM {base} GROUP BY 1) t ON t.wt = split_part(e.sketch_id, '#', 1) GROUP BY wt, method"""


def _limits_sql(k: int, reps: int, base: str) -> str:
    """(sketch_id, lower, upper, method, k) of the three bounds on the total."""
    alpha = sql.normal_quantile(0.95)
    both = reps_sql(base, k, "exp", reps) + sql.splits("true") + ", g2 AS (SELECT *, list_concat(ins, [sum_in]) AS sums FROM g)"
    both += sql.upper_normal("up", "sums", "tau", 0.05, "g2") + sql.lower_normal("dn", "sums", "tau", 0.05, "g2")
    return " UNION ALL ".join(
        [
            f"SELECT *, 'exp_order_normal' AS method, {k} AS k FROM {_cte(both, 'SELECT sketch_id, greatest(coalesce(dn.root, sum_in), sum_in) AS lower, up.root AS upper FROM g2 JOIN up USING (sketch_id) JOIN dn USING (sketch_id)')}",
            f"SELECT sketch_id, (1 - {alpha!r} / sqrt({k})) / avg(r), (1 + {alpha!r} / sqrt({k})) / avg(r), 'with_replacement_normal', {k} FROM {_least(base, k, reps)} GROUP BY 1",
            f"SELECT *, 'priority_chernoff', {k} FROM {_cte(reps_sql(base, k, 'priority', reps) + sql.chernoff('pc', 'e', 'true'), 'SELECT * FROM pc')}",
        ]
    )


def _bounds_sql(ks: tuple[int, ...], reps: int, base: str) -> str:
    rows = " UNION ALL ".join(_limits_sql(k, reps, base) for k in ks)
    return f"SELECT wt, k::BIGINT AS k, method, {sql.QUALITY} FROM ({rows}) x JOIN (SELECT wt, sum(weight) AS truth FROM {base} GROUP BY 1) t ON t.wt = split_part(x.sketch_id, '#', 1) GROUP BY wt, k, method"


def _partition_sql(ks: tuple[int, ...], gs: tuple[int, ...], reps: int, n: int | None = None) -> str:
    base = base_sql((1.2, 2.0), False, n)
    one = lambda k, m, f: f"SELECT '{m}' AS method, {k} AS k, * FROM {_cte(reps_sql(base, k, f, reps), f'SELECT wt, rep, item_id, {sql.ADJ[f]} AS adj FROM e')}"
    adj = " UNION ALL ".join(one(k, m, f) for k in ks for m, f in (("exp_rc", "exp"), ("priority_rc", "priority")))
    return f"""WITH a AS ({adj}), i AS (SELECT *, row_number() OVER (PARTITION BY wt ORDER BY weight, item_id) - 1 AS rn FROM {base}),
    gg AS (SELECT unnest({list(gs)}) AS g), t AS (SELECT wt, g, rn // g AS grp, sum(weight) AS truth FROM i, gg GROUP BY ALL),
    e AS (SELECT a.method, a.k, a.wt, a.rep, g, rn // g AS grp, sum(adj) AS est FROM a JOIN i USING (wt, item_id), gg GROUP BY ALL),
    q AS (SELECT wt, g, sum(truth * truth) AS squares FROM t GROUP BY ALL),
    s AS (SELECT method, k, wt, g, rep, sum(est * est - 2 * est * truth) AS gain FROM e JOIN t USING (wt, g, grp) GROUP BY ALL)
    SELECT wt, k::BIGINT AS k, g::BIGINT AS g, method, round(avg(squares + gain) / any_value(w * w), 6) AS rel_sse FROM s JOIN q USING (wt, g) JOIN (SELECT wt, sum(weight) AS w FROM {base} GROUP BY 1) USING (wt) GROUP BY wt, k, g, method"""


def _subpop_sql(ks: tuple[int, ...], g: int, reps: int, draws: int, n: int | None = 1000, alphas=(1.0, 1.2, 2.0)) -> str:
    base = base_sql(alphas, False, n)
    items = f"(SELECT *, (row_number() OVER (PARTITION BY wt ORDER BY weight, item_id) - 1) // {g} AS grp FROM {base})"

    def grouped(k: int, family: str) -> str:
        return reps_sql(base, k, family, reps) + f", it AS (SELECT * FROM {items}), e2 AS (SELECT e.* REPLACE (e.sketch_id || '#' || x.grp AS sketch_id), it.grp = x.grp AS chosen FROM e JOIN it ON it.wt = e.wt AND it.item_id = e.item_id JOIN (SELECT DISTINCT wt, grp FROM it) x ON x.wt = e.wt)"

    rows = []
    for k in ks:
        cut = grouped(k, "exp") + sql.splits("chosen", "e2")
        known = cut + sql.split_roots("sr", draws)
        open_ = cut + ", g2 AS (SELECT *, list_concat(ins, [sum_in]) AS sums FROM g)" + sql.draw_roots("dr", "sums", "tau", "bs", draws, "g2") + sql.draw_roots("dl", "ins", "last", "bs", draws, "g2")
        low = f"CASE WHEN c = 0 THEN 0 ELSE greatest(sum_in, {sql.pick('dl.xs', 0.05, draws)}) END"
        high = f"CASE WHEN c = 0 THEN {-math.log(0.05)!r} / tau ELSE {sql.pick('dr.xs', 0.95, draws)} END"
        rows += [
            f"SELECT *, 'exp_total_known' AS method, {k} AS k FROM {_cte(known, f'SELECT sketch_id, {sql.pick("xs", 0.05, draws)} AS lower, {sql.pick("xs", 0.95, draws)} AS upper FROM sr')}",
            f"SELECT *, 'exp_total_unknown', {k} FROM {_cte(open_, f'SELECT g2.sketch_id, {low}, {high} FROM g2 LEFT JOIN dr USING (sketch_id) LEFT JOIN dl USING (sketch_id)')}",
            f"SELECT *, 'priority_chernoff', {k} FROM {_cte(grouped(k, 'priority') + sql.chernoff('pc', 'e2', 'chosen'), 'SELECT * FROM pc')}",
        ]
    return f"""SELECT wt, k::BIGINT AS k, method, {sql.QUALITY} FROM ({" UNION ALL ".join(rows)}) x
        JOIN (SELECT wt, grp, sum(weight) AS truth FROM {items} GROUP BY ALL) t ON t.wt = split_part(x.sketch_id, '#', 1) AND t.grp = split_part(x.sketch_id, '#', 3)::BIGINT GROUP BY wt, k, method"""


def _variance_sql(k: int, reps: int) -> str:
    base = base_sql(uniform=False)
    adj = " UNION ALL ".join(f"SELECT '{m}' AS method, * FROM {_cte(reps_sql(base, k, f, reps), f'SELECT wt, rep, item_id, weight, {sql.ADJ[f]} AS adj FROM e')}" for m, f in (("exp_rc", "exp"), ("priority_rc", "priority")))
    return f"""WITH a AS ({adj}), w AS (SELECT wt, sum(weight) AS truth, sum(weight * weight) AS squares FROM {base} GROUP BY 1),
    v AS (SELECT method, wt, sum(adj * adj - 2 * weight * adj) / {reps} AS gain FROM a GROUP BY ALL),
    t AS (SELECT method, wt, avg(pow(est - truth, 2)) AS total_variance, avg(n) AS adjusted_items FROM (SELECT method, wt, rep, sum(adj) AS est, count(*) AS n FROM a GROUP BY ALL) JOIN w USING (wt) GROUP BY ALL),
    o AS (SELECT *, row_number() OVER z - 1 AS certain, sum(weight) OVER (z ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest FROM {base} WINDOW z AS (PARTITION BY wt ORDER BY weight DESC, item_id)),
    c AS (SELECT wt, min(struct_pack(certain := certain, threshold := rest / ({k - 1} - certain))) AS c FROM o WHERE certain < {k - 1} AND weight <= rest / ({k - 1} - certain) GROUP BY 1),
    b AS (SELECT wt, sum(weight * (c.threshold - weight)) AS best FROM o JOIN c USING (wt) WHERE certain >= c.certain GROUP BY 1)
    SELECT wt, method, round(total_variance / (truth * truth), 6) AS total_variance, round((squares + gain) / (truth * truth), 6) AS sum_variances, round((total_variance - squares - gain) / (truth * truth), 6) AS sum_covariances,
        round(best / (truth * truth), 6) AS best, round(adjusted_items, 6) AS adjusted_items, {k + 1}::BIGINT AS ranks_used FROM v JOIN t USING (method, wt) JOIN w USING (wt) JOIN b USING (wt)"""


# W1: error of the total; the reference defines these, and W2, W3 and W7, on 1,000 items
add("exp_total_error", _error_sql(16))(lambda s, d: _round(workloads.run_total_error(s, d, REPS, (16,))))
add("exp_total_error_by_k", " UNION ALL ".join(f"({_error_sql(k, 5)})" for k in (4, 16, 64)))(lambda s, d: _round(workloads.run_total_error(s, d, 5, (4, 16, 64))))
add("exp_total_error_natural", _error_sql(32, 3, NATURAL))(lambda s, d: _round(workloads.run_total_error(s, d, 3, (32,), workloads.natural_weights(s, d))))
# W2, W3: bounds on the total, and the rate inside
add("exp_total_bounds", _bounds_sql((4, 16), REPS, base_sql()))(lambda s, d: _round(workloads.run_total_bounds(s, d, REPS, (4, 16))))
add("exp_total_bounds_variants")(lambda s, d: _round(workloads.run_total_bounds(s, d, REPS, (16,), more=True)))
_RATES = _limits_sql(16, REPS, base_sql(uniform=False)) + " UNION ALL " + _limits_sql(64, REPS, base_sql(uniform=False))
add(
    "exp_inbounds",
    f"""SELECT wt, method, round(avg(i), 6) AS in_bounds, round(max(greatest(o, u)), 6) AS worst_side FROM (SELECT wt, method, k, avg(CASE WHEN lower <= truth AND truth <= upper THEN 1.0::DOUBLE ELSE 0 END) AS i, avg(CASE WHEN truth > upper THEN 1.0::DOUBLE ELSE 0 END) AS o, avg(CASE WHEN truth < lower THEN 1.0::DOUBLE ELSE 0 END) AS u
    FROM ({_RATES}) x JOIN (SELECT wt, sum(weight) AS truth FROM {base_sql(uniform=False)} GROUP BY 1) t ON t.wt = split_part(x.sketch_id, '#', 1) GROUP BY ALL) GROUP BY ALL""",
)(lambda s, d: _round(workloads.run_in_bounds(s, d, REPS)))
# W4 to W6: squared error over partitions of all orders
add("exp_partition_sse_g", _partition_sql((40,), (1, 10, 100, 1000, 5000), 5))(lambda s, d: _round(workloads.run_partition_error(s, d, 5, (40,), (1, 10, 100, 1000, 5000), ("exp_rc", "priority_rc"))))
add("exp_partition_sse_k", _partition_sql((4, 40, 500), (1, 5000), 3))(lambda s, d: _round(workloads.run_partition_error(s, d, 3, (4, 40, 500), (1, 5000), ("exp_rc", "priority_rc"))))
add("exp_partition_sse_conditioned")(lambda s, d: _round(workloads.run_partition_error(s, d, 3, (4, 40, 500), (1, 5000), ("subset", "subset_chain"))))
add("exp_partition_sse_baselines")(lambda s, d: _round(workloads.run_partition_error(s, d, 2, (40,), (1, 5000), ("subset", "prefix"), baselines=True)))
add("exp_chain_settings")(lambda s, d: _round(workloads.run_chain_settings(s, d, 2)))
# W7, W8: bounds on all groups
add("exp_subpop_bounds", _subpop_sql((16,), 200, 2, 200))(lambda s, d: _round(workloads.run_subpop_bounds(s, d, 2, (16,), 200)))
add("exp_subpop_bounds_500", _subpop_sql((16,), 500, 3, 200))(lambda s, d: _round(workloads.run_subpop_bounds(s, d, 3, (16,), 500)))
add("exp_subpop_bounds_4000", _subpop_sql((16,), 4000, 2, 200, None, (1.2, 2.0)))(lambda s, d: _round(workloads.run_subpop_bounds(s, d, 2, (16,), 4000, None, (1.2, 2.0))))
add("exp_subpop_bounds_by_k")(lambda s, d: _round(workloads.run_subpop_bounds(s, d, 3, (10, 40, 100), 200)))
add("exp_item_variance", _variance_sql(40, 20))(lambda s, d: _round(workloads.run_item_variance(s, d)))
add("exp_item_variance_conditioned")(lambda s, d: _round(workloads.run_item_variance(s, d, 10, 40, ("exp_rc", "subset", "subset_chain"))))
_EVENTS = "(SELECT *, hour(ts)::VARCHAR AS hour_of_day, CASE WHEN (props->>'$.k')::INT < 10 THEN 'true' ELSE 'false' END AS small_key FROM events)"
add(
    "exp_event_shares",
    sql.sketch(_EVENTS, "event_id", "value", 256, extra=", event_type, hour_of_day, small_key")
    + f", a AS (SELECT *, {sql.ADJ['exp']} AS adj FROM e) "
    + " UNION ALL ".join(f"SELECT '{c}' AS attribute, x.{c} AS part, round(x.exact, 4) AS exact, round(coalesce(y.est, 0), 4) AS estimate FROM (SELECT {c}, sum(value) AS exact FROM {_EVENTS} GROUP BY 1) x LEFT JOIN (SELECT {c}, sum(adj) AS est FROM a GROUP BY 1) y ON x.{c} = y.{c}" for c in ("event_type", "hour_of_day", "small_key")),
)(lambda s, d: _round(workloads.run_event_shares(s, d), 4))
_DIMS = "(SELECT c_custkey, r_name FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey)"
add(
    "exp_region_totals",
    orders_sql(k=256)
    + sql.subset(15)
    + f", dm AS (SELECT * FROM {_DIMS}), e2 AS (SELECT e.* REPLACE (region.r_name AS sketch_id), dm.r_name = region.r_name AS chosen FROM e JOIN dm ON c_custkey = o_custkey, region)"
    + sql.splits("chosen", "e2")
    + sql.split_roots("sr", 200)
    + f""" SELECT r_name, round(exact, 0) AS exact, round(estimate, 0) AS estimate, round({sql.pick("xs", 0.05, 200)}, 0) AS lower, round({sql.pick("xs", 0.95, 200)}, 0) AS upper FROM (SELECT r_name, sum(o_totalprice) AS exact FROM orders JOIN dm ON c_custkey = o_custkey GROUP BY 1)
    LEFT JOIN (SELECT r_name, sum(share * total_weight) AS estimate FROM e JOIN sc USING (sketch_id, pos) JOIN dm ON c_custkey = o_custkey GROUP BY 1) USING (r_name) LEFT JOIN sr ON sr.sketch_id = r_name""",
)(lambda s, d: _round(workloads.run_region_totals(s, d), 0))


add(
    "exp_unaggregated",
    f"""WITH p AS (SELECT l_partkey AS item_id, sum(l_extendedprice) AS weight, min(-ln(pu) / l_extendedprice) AS r2 FROM {PIECE_SQL} GROUP BY 1),
    q AS (SELECT *, -ln({sql.uniform("s1", "item_id")}) / weight AS r1 FROM p),
    o AS (SELECT weight, r1, r2, row_number() OVER (ORDER BY r1, item_id) AS p1, row_number() OVER (ORDER BY r2, item_id) AS p2 FROM q),
    t AS (SELECT max(r1) FILTER (p1 = {K + 1}) AS t1, max(r2) FILTER (p2 = {K + 1}) AS t2, sum(weight) AS w FROM o)
    SELECT 'two_pass' AS method, round(sum(weight / (1 - exp(-weight * t2))), 2) AS estimate, round(any_value(w), 2) AS exact FROM o, t WHERE p2 <= {K}
    UNION ALL SELECT 'pre_aggregated', round(sum(weight / (1 - exp(-weight * t1))), 2), round(any_value(w), 2) FROM o, t WHERE p1 <= {K}""",
)(lambda s, d: _round(workloads.run_unaggregated(s, d, PIECE_IDS, _pieces(s, d), K), 2))
_EXACT = "(SELECT round(sum(p_retailprice), 4) FROM part WHERE p_partkey IN (SELECT * FROM {a}) {how} p_partkey IN (SELECT * FROM {b})) AS exact_{name}"
add(
    "exp_baskets",
    " UNION ALL ".join(
        "("
        + _union_sql(
            f"SELECT '{a + b}' AS pair, round(sum(adj), 4) AS union_weight, round(coalesce(sum(adj) FILTER (a AND b), 0), 4) AS intersection_weight, round(coalesce(sum(adj) FILTER (a AND NOT b), 0), 4) AS only_a, round(coalesce(sum(adj) FILTER (b AND NOT a), 0), 4) AS only_b, round(coalesce(sum(adj) FILTER (a AND b), 0) / sum(adj), 4) AS jaccard, "
            + ", ".join(_EXACT.format(a=_FLAGS[a], b=_FLAGS[b], how=how, name=name) for how, name in (("OR", "union"), ("AND", "intersection")))
            + " FROM u",
            a,
            b,
        )
        + ")"
        for a, b in (("A", "N"), ("A", "R"), ("N", "R"))
    ),
)(lambda s, d: _round(workloads.run_baskets(s, d), 4))
add("sampling_baseline")(lambda s, d: workloads.sampling_baseline(workloads.table(s, d, "orders"), "o_totalprice", 0.05))

