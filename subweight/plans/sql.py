"""DuckDB text of sketches and estimators: the independent answers that queries are held against."""

from __future__ import annotations

import math

from ..functions.solve import normal_quantile


def uniform(seed: str, *ids: str) -> str:
    text = " || '|' || ".join([f"'{seed}'", *[f"({i})::VARCHAR" for i in ids]])
    return f"((('0x' || substr(md5({text}), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0)"


RANK = {"exp": "-ln(u) / weight", "priority": "u / weight", "uniform": "u"}


def sketch(rel: str, item: str, weight: str, k: int, family: str = "exp", seed: str = "s1", by: str = "'all'", extra: str = "", key: str = "") -> str:
    """CTEs: e (entries, with tau, total_weight, n_seen) and h (one row a sketch); starts WITH RECURSIVE."""
    return f"""WITH RECURSIVE x AS (SELECT ({by})::VARCHAR AS sketch_id, {item} AS item_id, ({weight})::DOUBLE AS weight{extra} FROM {rel}),
    r0 AS (SELECT *, {uniform(seed, *(key.split(",") if key else ["item_id"]))} AS u FROM x WHERE weight > 0),
    r AS (SELECT *, {RANK[family]} AS rank FROM r0),
    q AS (SELECT *, row_number() OVER (PARTITION BY sketch_id ORDER BY rank, item_id) AS pos FROM r),
    n AS (SELECT sketch_id, count(*) AS n_seen, coalesce(sum(weight), 0) AS total_weight FROM x GROUP BY 1),
    h AS (SELECT n.*, (SELECT q.rank FROM q WHERE q.sketch_id = n.sketch_id AND q.pos = {k + 1}) AS tau FROM n),
    e AS (SELECT q.*, h.tau, h.total_weight, h.n_seen FROM q JOIN h USING (sketch_id) WHERE pos <= {k})"""


ADJ = {
    "exp": "CASE WHEN tau IS NULL THEN weight ELSE weight / (1 - exp(-weight * tau)) END",
    "priority": "CASE WHEN tau IS NULL THEN weight ELSE greatest(weight, 1 / tau) END",
    "uniform": "CASE WHEN tau IS NULL THEN weight ELSE weight / least(1.0, tau) END",
}


def splits(predicate: str, source: str = "e") -> str:
    """CTE g: lists of the weights before each item inside and outside, their sums and largest ranks."""
    return f""", sp AS (SELECT *, coalesce({predicate}, false) AS inside FROM {source}),
    pf AS (SELECT *, coalesce(sum(CASE WHEN inside THEN weight ELSE 0 END) OVER w, 0) AS before_in, coalesce(sum(CASE WHEN inside THEN 0 ELSE weight END) OVER w, 0) AS before_out
        FROM sp WINDOW w AS (PARTITION BY sketch_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
    g AS (SELECT sketch_id, any_value(tau) AS tau, any_value(total_weight) AS w, max(rank) AS last,
        list(before_in ORDER BY pos) FILTER (inside) AS ins, list(before_out ORDER BY pos) FILTER (NOT inside) AS outs,
        coalesce(sum(weight) FILTER (inside), 0) AS sum_in, coalesce(sum(weight) FILTER (NOT inside), 0) AS sum_out,
        coalesce(max(rank) FILTER (inside), 0) AS last_in, coalesce(max(rank) FILTER (NOT inside), 0) AS last_out, count(*) FILTER (inside) AS c, count(*) FILTER (NOT inside) AS a FROM pf GROUP BY sketch_id)"""


def inv(x: str, sums: str) -> str:
    return f"list_sum([1.0 / ({x} - s) FOR s IN {sums}])"


def bisect(name: str, above: str, low: str, high: str, source: str = "g", key: str = "sketch_id", keep: str = "*", steps: int = 80) -> str:
    """CTE ``name`` (key, root) of rows of ``source``; ``above`` speaks of mid and of the columns of the source."""
    return f""", {name}_i AS (SELECT {keep}, ({low})::DOUBLE AS lo, ({high})::DOUBLE AS hi, (({low}) + ({high}))::DOUBLE / 2 AS mid, 0 AS step FROM {source}
    UNION ALL SELECT * EXCLUDE (up) REPLACE (CASE WHEN up THEN mid ELSE lo END AS lo, CASE WHEN up THEN hi ELSE mid END AS hi, ((CASE WHEN up THEN mid ELSE lo END) + (CASE WHEN up THEN hi ELSE mid END)) / 2 AS mid, step + 1 AS step)
    FROM (SELECT *, {above} AS up FROM {name}_i WHERE step < {steps})),
    {name} AS (SELECT {key}, mid AS root FROM {name}_i WHERE step = {steps})"""


def sq(x: str, sums: str) -> str:
    return f"sqrt(list_sum([1.0 / (({x} - s) * ({x} - s)) FOR s IN {sums}]))"


def upper_normal(name: str, sums: str, tau: str, delta: float, source: str) -> str:
    a = normal_quantile(1 - delta)
    return bisect(name, f"{inv('mid', sums)} + {a!r} * {sq('mid', sums)} > {tau}", f"{sums}[-1] + (1 + {a!r}) / {tau}", f"{sums}[-1] + (len({sums}) + {a!r} * sqrt(len({sums}))) / {tau}", source)


def lower_normal(name: str, sums: str, tau: str, delta: float, source: str) -> str:
    """CTE ``name`` (sketch_id, root): null where there is no root."""
    a = normal_quantile(1 - delta)
    value = lambda x: f"({inv(x, sums)} - {a!r} * {sq(x, sums)})"
    low, high = f"({sums}[-1] + 1e-9 / {tau})", f"({sums}[-1] + len({sums}) / {tau})"
    one, two = "((2 * lo + hi) / 3)", "((lo + 2 * hi) / 3)"
    thirds = f""", {name}_p AS (SELECT *, {low}::DOUBLE AS lo, {high}::DOUBLE AS hi, 0 AS step FROM {source}
    UNION ALL SELECT * EXCLUDE (up) REPLACE (CASE WHEN up THEN {one} ELSE lo END AS lo, CASE WHEN up THEN hi ELSE {two} END AS hi, step + 1 AS step) FROM (SELECT *, {value(one)} < {value(two)} AS up FROM {name}_p WHERE step < 80)),
    {name}_t AS (SELECT * EXCLUDE (lo, hi, step), (lo + hi) / 2 AS top FROM {name}_p WHERE step = 80)"""
    return thirds + bisect(f"{name}_b", f"{value('mid')} > {tau}", "top", high, f"{name}_t") + f""",
    {name} AS (SELECT t.sketch_id, CASE WHEN {value("t.top")} > {tau} THEN b.root END AS root FROM {name}_t t JOIN {name}_b b USING (sketch_id))"""


def draw_roots(name: str, sums: str, tau: str, seed: str, draws: int, source: str) -> str:
    """CTE ``name`` (sketch_id, xs): sorted solutions of all draws."""
    prepared = f""", {name}_d AS (SELECT {source}.*, d, [-ln({uniform(seed, "sketch_id", "d", "j")}) FOR s, j0 IN {sums}] AS es FROM {source}, range(1, {draws + 1}) AS t(d) WHERE len({sums}) > 0)"""
    prepared = prepared.replace("(j)::VARCHAR", "(j0 - 1)::VARCHAR")
    total = f"list_sum([es[i] / (mid - {sums}[i]) FOR i IN range(1, len({sums}) + 1)])"
    return prepared + bisect(f"{name}_r", f"{total} > {tau}", f"{sums}[-1] + es[-1] / {tau}", f"{sums}[-1] + list_sum(es) / {tau}", f"{name}_d", "sketch_id, d", steps=60) + f""",
    {name} AS (SELECT sketch_id, list(root ORDER BY root) AS xs FROM {name}_r GROUP BY sketch_id)"""


def pick(xs: str, level: float, draws: int) -> str:
    return f"{xs}[{max(1, min(draws, math.ceil(level * draws)))}]"


def split_roots(name: str, draws: int, seed: str = "bs") -> str:
    """After ``splits``: CTE ``name`` (sketch_id, xs), the sorted weights at which the drawn ranks of both sides are as far apart as the seen ones; the total is known."""

    def drawn(side: str, sums: str) -> str:
        return f"[-ln({uniform(seed, 'sketch_id', 'd', repr(side), 'j')}) FOR j IN range(0, len({sums}))]"

    def inside(m: str) -> str:
        return f"coalesce(list_sum([es[i] / greatest(mid - s[i], 1e-300) FOR i IN range(1, {m} + 1)]), 0)"

    def outside(m: str) -> str:
        return f"coalesce(list_sum([fs[i] / greatest(w - mid - r[i], 1e-300) FOR i IN range(1, {m} + 1)]), 0)"

    text = f""", {name}_g AS (SELECT *, coalesce(ins, []) || [sum_in] AS s, coalesce(outs, []) || [sum_out] AS r FROM g),
    {name}_d AS (SELECT {name}_g.*, d, {drawn("i", "s")} AS es, {drawn("o", "r")} AS fs, sum_in AS bottom, w - sum_out AS top FROM {name}_g, range(1, {draws + 1}) AS t(d))"""
    text += bisect(f"{name}_hi", f"{outside('a')} - {inside('c + 1')} < 0", "bottom", "top", f"{name}_d", "sketch_id, d", steps=60)
    text += bisect(f"{name}_lo", f"{outside('a + 1')} - {inside('c')} < 0", "bottom", "top", f"{name}_d", "sketch_id, d", steps=60)
    text += f""", {name}_b AS (SELECT x.*, least(greatest(CASE WHEN c = 0 THEN 0 ELSE l.root END, bottom), top) AS low, least(greatest(CASE WHEN a = 0 THEN w ELSE h.root END, bottom), top) AS high
        FROM {name}_d x JOIN {name}_hi h USING (sketch_id, d) JOIN {name}_lo l USING (sketch_id, d))"""
    text += bisect(f"{name}_r", f"{outside('a')} - {inside('c')} - (last_out - last_in) < 0", "least(low, high)", "greatest(low, high)", f"{name}_b", "sketch_id, d", steps=60)
    return text + f", {name} AS (SELECT sketch_id, list(least(greatest(root, bottom), top) ORDER BY least(greatest(root, bottom), top)) AS xs FROM {name}_r JOIN {name}_d USING (sketch_id, d) GROUP BY sketch_id)"


def subset(digits: int = 8) -> str:
    """After ``sketch``: the subset-conditioned share of each entry, by a fine grid over the logarithm of y."""
    return f""", ll AS (SELECT sketch_id, list(weight / total_weight ORDER BY pos) AS ws, 1 - sum(weight / total_weight) AS rest FROM e GROUP BY 1),
    t AS (SELECT i * 0.002 - 12.0 AS t FROM range(0, 12001) AS r(i)),
    d0 AS (SELECT sketch_id, t, t - rest * exp(t) + list_sum([ln(1 - exp(-x * exp(t))) FOR x IN ws]) AS g FROM t, ll WHERE t < 12),
    d AS (SELECT sketch_id, t, exp(g - top) AS p FROM d0 JOIN (SELECT sketch_id, max(g) AS top FROM d0 GROUP BY 1) USING (sketch_id) WHERE g > top - 60),
    sc AS (SELECT e.sketch_id, pos, round(sum(p * (weight / total_weight) / (1 - exp(-(weight / total_weight) * exp(t)))) / sum(p), {digits}) AS share FROM e JOIN d USING (sketch_id) GROUP BY 1, 2)"""


def chain(redraws: int, steps: int, seed: str = "ch") -> str:
    """After ``sketch``: CTE ch (sketch_id, acc), the chain's adjusted weights by place."""
    tau = f"[list_sum([-ln({uniform(seed, 'sketch_id', 'step', 'd', 'j')}) / lefts[j + 1] FOR j IN range(0, len(ws) + 1)]) FOR d IN range(1, {redraws + 1})]"
    return f""", c0 AS (SELECT sketch_id, any_value(total_weight) AS w, any_value(total_weight) - sum(weight) AS rest, list(weight ORDER BY pos) AS ws, list(weight ORDER BY pos) AS ord, [0.0::DOUBLE FOR x IN list(weight)] AS acc, 1 AS step FROM e GROUP BY 1
    UNION ALL SELECT sketch_id, w, rest, ws,
        [x.w FOR x IN list_sort([{{'r': -ln(1 + {uniform(seed, 'sketch_id', 'step', "'r'", 'i')} * (exp(-ws[i] * taus[1]) - 1)) / ws[i], 'w': ws[i]}} FOR i IN range(1, len(ws) + 1)])],
        [acc[i] + list_sum([ws[i] / (1 - exp(-ws[i] * x)) FOR x IN taus]) FOR i IN range(1, len(ws) + 1)], step + 1
        FROM (SELECT *, {tau} AS taus FROM (SELECT *, [CASE WHEN i = len(ws) THEN rest ELSE w - coalesce(list_sum(ord[1:i]), 0) END FOR i IN range(0, len(ws) + 1)] AS lefts FROM c0 WHERE step <= {steps}))),
    ch AS (SELECT sketch_id, [x / {redraws * steps} FOR x IN acc] AS acc FROM c0 WHERE step = {steps + 1})"""


def redrawn(draws: int, seed: str = "ml") -> str:
    """After ``sketch``: CTE er, entries of so many redraws of the ranks below tau, each a sketch all#draw."""
    return f""", er0 AS (SELECT e.* EXCLUDE (sketch_id, pos, rank), sketch_id || '#' || draw AS sketch_id, -ln(1 + {uniform(seed, 'draw', 'item_id')} * (exp(-weight * tau) - 1)) / weight AS rank FROM e, range(1, {draws + 1}) AS t(draw)),
    er AS (SELECT *, row_number() OVER (PARTITION BY sketch_id ORDER BY rank, item_id) AS pos FROM er0)"""


def chernoff(name: str, source: str, predicate: str, delta: float = 0.05) -> str:
    """CTE ``name`` (sketch_id, lower, upper): priority bounds from the number of light items."""
    log = math.log(delta)
    gap = f"n - mid + n * ln(mid / n) - ({log!r})"
    text = f""", {name}_c AS (SELECT sketch_id, any_value(tau) AS tau, coalesce(sum(weight) FILTER (({predicate}) AND weight * tau >= 1), 0) AS certain, (count(*) FILTER (({predicate}) AND weight * tau < 1))::DOUBLE AS n FROM {source} GROUP BY 1),
    {name}_n AS (SELECT * FROM {name}_c WHERE n > 0)"""
    text += bisect(f"{name}_u", f"{gap} > 0", "n", f"n - 2 * ({log!r}) + sqrt(greatest({4 * log * log!r} - 8 * n * ({log!r}), 0)) + 1", f"{name}_n")
    text += bisect(f"{name}_l", f"{gap} < 0", "n * 1e-12", "n", f"{name}_n")
    return text + f", {name} AS (SELECT c.sketch_id, certain + coalesce(l.root, 0) / tau AS lower, certain + coalesce(u.root, {-log!r}) / tau AS upper FROM {name}_c c LEFT JOIN {name}_u u USING (sketch_id) LEFT JOIN {name}_l l USING (sketch_id))"


def poisson(name: str, source: str, predicate: str, delta: float = 0.05) -> str:
    """CTE ``name`` (sketch_id, lower, upper): priority bounds from the exact Poisson tail."""
    text = f", {name}_c AS (SELECT sketch_id, any_value(tau) AS tau, coalesce(sum(weight) FILTER (({predicate}) AND weight * tau >= 1), 0) AS certain, count(*) FILTER (({predicate}) AND weight * tau < 1) AS n FROM {source} GROUP BY 1)"
    tail = lambda upto: f"list_sum([exp(-mid + i * ln(mid) - lgamma(i + 1)) FOR i IN range(0, {upto} + 1)])"
    text += bisect(f"{name}_u", f"{tail('n')} > {delta!r}", "0.0", "n + 10 * sqrt(n + 1) + 20", f"{name}_c")
    text += bisect(f"{name}_l", f"1 - {tail('(n - 1)')} < {delta!r}", "0.0", "n::DOUBLE", f"(SELECT * FROM {name}_c WHERE n > 0)")
    return text + f", {name} AS (SELECT c.sketch_id, certain + coalesce(l.root, 0) / tau AS lower, certain + u.root / tau AS upper FROM {name}_c c JOIN {name}_u u USING (sketch_id) LEFT JOIN {name}_l l USING (sketch_id))"


QUALITY = """round(avg(lower / truth), 6) AS lower, round(avg(upper / truth), 6) AS upper, round(avg((upper - lower) / truth), 6) AS width, round(avg(pow(upper / truth - 1, 2)), 6) AS upper_sq_error, round(avg(pow(lower / truth - 1, 2)), 6) AS lower_sq_error,
    round(avg(CASE WHEN lower <= truth AND truth <= upper THEN 1.0::DOUBLE ELSE 0 END), 6) AS in_bounds, round(avg(CASE WHEN truth > upper THEN 1.0::DOUBLE ELSE 0 END), 6) AS over_upper, round(avg(CASE WHEN truth < lower THEN 1.0::DOUBLE ELSE 0 END), 6) AS under_lower"""


def simulated(name: str, source: str, predicate: str, delta: float = 0.05, draws: int = 50, seed: str = "light") -> str:
    """CTE ``name`` (sketch_id, lower, upper): priority bounds with the seen light items drawn by their chances and the unseen ones Poisson."""
    tail = lambda upto: f"coalesce(list_sum([exp(-mid + i * ln(mid) - lgamma(i + 1)) FOR i IN range(0, {upto})]), 0)"
    text = f""", {name}_l AS (SELECT * FROM {source} WHERE ({predicate}) AND weight * tau < 1),
    {name}_n AS (SELECT sketch_id, any_value(tau) AS tau, sum(weight) FILTER ({predicate}) AS seen, count(*) FILTER (({predicate}) AND weight * tau < 1) AS n FROM {source} GROUP BY 1),
    {name}_d AS (SELECT sketch_id, d, count(*) FILTER ({uniform(seed, "sketch_id", "d", "pos")} < weight * tau) AS hit FROM {name}_l, range(1, {draws + 1}) AS t(d) GROUP BY 1, 2),
    {name}_c AS (SELECT x.*, ls FROM {name}_n x JOIN (SELECT sketch_id, list(n - hit) AS ls FROM {name}_d JOIN {name}_n USING (sketch_id) GROUP BY 1) USING (sketch_id))"""
    most = "n + 10 * sqrt(n + 1) + 20"
    text += bisect(f"{name}_u", f"list_avg([{tail('m + 1')} FOR m IN ls]) > {delta!r}", "0.0", most, f"{name}_c", steps=60)
    text += bisect(f"{name}_b", f"list_avg([CASE WHEN m > 0 THEN 1 - {tail('m')} ELSE 1 END FOR m IN ls]) < {delta!r}", "0.0", most, f"{name}_c", steps=60)
    none = f"list_avg([CASE WHEN m > 0 THEN 0.0 ELSE 1.0 END FOR m IN ls]) >= {delta!r}"
    return text + f", {name} AS (SELECT c.sketch_id, seen + CASE WHEN {none} THEN 0 ELSE b.root END / tau AS lower, seen + u.root / tau AS upper FROM {name}_c c JOIN {name}_u u USING (sketch_id) JOIN {name}_b b USING (sketch_id))"


def set_limits(name: str, delta: float, step: float = 0.004, points: int = 4000) -> str:
    """CTE ``name`` (sketch_id, lower, upper, w): bounds on the total given which items were sampled, by a grid that has ln tau as a point."""
    text = f""", {name}_w AS (SELECT sketch_id, any_value(tau) AS tau, any_value(total_weight) AS w, sum(weight) AS seen, list(weight) AS ws FROM e GROUP BY 1),
    {name}_p AS (SELECT sketch_id, i, exp(ln(tau) + i * {step}) AS y, ln(tau) + i * {step} + list_sum([ln(1 - exp(-x * exp(ln(tau) + i * {step}))) FOR x IN ws]) AS g FROM {name}_w, range({-points}, {points // 2}) AS t(i)),
    {name}_g AS (SELECT x.*, ys, gs, tops FROM {name}_w x JOIN (SELECT sketch_id, list(y ORDER BY i) AS ys, list(g ORDER BY i) AS gs, max(g) AS tops FROM {name}_p GROUP BY 1) USING (sketch_id))"""
    mass = lambda a, b: f"list_sum([exp(gs[i] - tops - mid * ys[i]) FOR i IN range({a}, {b})])"
    share = f"({mass(1, points + 1)} + exp(gs[{points + 1}] - tops - mid * tau) / 2) / {mass(1, points + points // 2 + 1)}"
    for side, level in (("lo", delta), ("hi", 1 - delta)):
        text += bisect(f"{name}_{side}", f"{share} < {level!r}", "0.0", "200 * len(ws) / tau / 64", f"{name}_g", steps=50)
    return text + f", {name} AS (SELECT x.sketch_id, w, seen + a.root AS lower, seen + b.root AS upper FROM {name}_w x JOIN {name}_lo a USING (sketch_id) JOIN {name}_hi b USING (sketch_id))"
