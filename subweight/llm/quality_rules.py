"""Quality rules with adaptive thresholds, by DataFrame functions only.

Every row gets integer features.  For each language and source, the features of rows that pass the
base rules are summarised in mergeable quantile sketches: counts of values rounded down to seven
significant bits, so that sketches of parts add up to the sketch of the whole, in any order and
with the same result, and a quantile is off by under 1/64 of its value.  Thresholds are Tukey
fences from the quartiles plus a slack; groups of few rows take those of the merged sketches of
their language, or of all rows.  The thresholds are then joined to the rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SEPARATORS, durable, word_array

#: Words in a window that must not repeat, fewest words, highest share of repeated words (percent).
WINDOW, LEAST_WORDS, MOST_REPEATED = 5, 10, 20
SYMBOLS = "#*$%&|<>"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Feature, slack over the upper fence, slack under the lower fence (None: no lower threshold).
FEATURES = (("symbols", 50, None), ("dup_lines", 500, None), ("repeats", 200, None), ("length", 20, 20), ("upper", 300, None), ("marks", 50, None))
#: Fewest rows of a group with thresholds of its own; interquartile ranges to the fences.
LEAST_ROWS, FENCE = 40, 3
#: Groups up to which thresholds are broadcast (about 100 bytes each); above, they are joined with salt.
MOST_BROADCAST, SALTS = 50_000, 32

BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def _count_of(text: Column, characters: str) -> Column:
    return (F.length(text) - F.length(F.translate(text, characters, ""))).cast("long")


def _repeat_words(hashes: Column, n: Column) -> Column:
    """Words in windows found twice or more: sort (hash, place), keep those with an equal neighbour, add up what each place newly covers."""
    window = F.when(n >= WINDOW, F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*[F.get(hashes, i + k) for k in range(WINDOW)]))).otherwise(F.array().cast("array<bigint>"))
    ordered = F.sort_array(F.transform(window, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def twice(s: Column) -> Column:
        return F.filter(s, lambda x, i: ((i > 0) & (F.get(s, i - 1)["h"] == x["h"])) | F.coalesce(F.get(s, i + 1)["h"] == x["h"], F.lit(False)))

    def covered(places: Column) -> Column:
        return F.aggregate(places, F.struct(F.lit(0).alias("sum"), F.lit(-WINDOW).alias("last")), lambda a, p: F.struct((a["sum"] + F.least(F.lit(WINDOW), p - a["last"])).alias("sum"), p.alias("last")))["sum"]

    places = F.sort_array(F.transform(F.get(F.transform(F.array(ordered), twice), F.lit(0)), lambda x: x["i"]))
    return F.when(F.size(F.array_distinct(window)) == F.size(window), F.lit(0)).otherwise(covered(places)).cast("long")


def _once(docs: DataFrame, name: str, value: Column) -> DataFrame:
    """``docs`` with a column that is worked out once: a generator of one row, which the optimizer does not merge with what reads it."""
    return docs.select("*", F.explode(F.array(value)).alias(name))


def with_stats(docs: DataFrame, text_column: str = "text") -> DataFrame:
    """``docs`` with one more column ``__q``: a struct of the counts and features of each row.

    For frames of own columns (see ``packed``); those of callers may have any names.
    """
    text = F.coalesce(F.col(text_column), F.lit(""))
    staged = _once(docs, "__h", F.transform(word_array(text_column), lambda w: F.xxhash64(w)))
    staged = _once(staged, "__l", F.filter(F.split(text, "\n", -1), lambda x: F.translate(x, SEPARATORS, "") != ""))
    n = F.size("__h")
    counts = _once(
        staged,
        "__q",
        F.struct(
            n.cast("long").alias("n_words"),
            F.length(F.translate(text, SEPARATORS, "")).cast("long").alias("word_chars"),
            _count_of(text, SYMBOLS).alias("n_symbols"),
            (F.size("__l") - F.size(F.array_distinct("__l"))).cast("long").alias("n_dup_lines"),
            _repeat_words(F.col("__h"), n).alias("n_repeat_words"),
            F.size("__l").cast("long").alias("n_lines"),
            _count_of(text, UPPER).alias("n_upper"),
            _count_of(text, "!?").alias("n_marks"),
        ),
    ).drop("__h", "__l")

    def share(a: str, b: str, by: int = 1000) -> Column:
        return F.floor(F.col(f"__c.{a}") * by / F.greatest(F.col(f"__c.{b}"), F.lit(1)))

    words, repeated = F.col("__c.n_words"), F.col("__c.n_repeat_words")
    return _once(
        counts.withColumnRenamed("__q", "__c"),
        "__q",
        F.struct(
            "__c.*",
            ((words < LEAST_WORDS) | (100 * repeated > MOST_REPEATED * words)).alias("base_failed"),
            F.array(share("n_symbols", "word_chars"), share("n_dup_lines", "n_lines"), share("n_repeat_words", "n_words"), share("word_chars", "n_words", 10), share("n_upper", "word_chars"), share("n_marks", "word_chars")).alias("features"),
        ),
    ).drop("__c")


def sketch(stats: DataFrame) -> DataFrame:
    """Quantile sketches of (lang, source, feature): how many rows have each rounded value.  Sketches merge by adding counts."""
    value = F.col("value")
    shift = F.greatest(F.length(F.bin(value)) - 7, F.lit(0))
    each = stats.filter("NOT __q.base_failed").select("lang", "source", F.posexplode("__q.features").alias("feature", "value"))
    return each.select("lang", "source", "feature", (value - F.pmod(value, F.pow(F.lit(2.0), shift).cast("long"))).alias("bucket")).groupBy("lang", "source", "feature", "bucket").agg(F.count("*").alias("n"))


def _fences(sketches: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, feature, n, low, high) of sketches merged to ``keys``."""
    from pyspark.sql import Window

    by = [*keys, "feature"]
    merged = sketches.groupBy(*by, "bucket").agg(F.sum("n").alias("n"))
    run = Window.partitionBy(*by).orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
    ranked = merged.withColumn("upto", F.sum("n").over(run)).withColumn("total", F.sum("n").over(Window.partitionBy(*by)))
    quartiles = ranked.groupBy(*by).agg(F.max("total").alias("n"), F.min(F.when(4 * F.col("upto") >= F.col("total"), F.col("bucket"))).alias("q1"), F.min(F.when(4 * F.col("upto") >= 3 * F.col("total"), F.col("bucket"))).alias("q3"))
    up = F.element_at(F.array(*[F.lit(x[1]) for x in FEATURES]), F.col("feature") + 1)
    down = F.element_at(F.array(*[F.lit(x[2]).cast("int") for x in FEATURES]), F.col("feature") + 1)
    span = FENCE * (F.col("q3") - F.col("q1"))
    return quartiles.select(*by, "n", (F.col("q1") - span - down).alias("low"), (F.col("q3") + span + up).alias("high"))


def thresholds(sketches: DataFrame) -> DataFrame:
    """One row for each (lang, source) with arrays low and high, one entry a feature; durable."""
    sketches = durable(sketches)
    own, wide, whole = _fences(sketches, ["lang", "source"]), _fences(sketches, ["lang"]), _fences(sketches, [])
    rename = lambda df, tag: df.select(*[F.col(c).alias(f"{tag}_{c}") for c in df.columns])
    wide, whole = rename(wide, "w"), rename(whole, "a")
    joined = own.join(wide, own["lang"].eqNullSafe(wide["w_lang"]) & (own["feature"] == wide["w_feature"]), "left").join(F.broadcast(whole), F.col("feature") == F.col("a_feature"), "left")  # one row a feature

    def pick(c: str) -> Column:
        return F.when(F.col("n") >= LEAST_ROWS, F.col(c)).when(F.col("w_n") >= LEAST_ROWS, F.col(f"w_{c}")).otherwise(F.col(f"a_{c}"))

    rows = joined.select("lang", "source", F.struct("feature", pick("low").alias("low"), pick("high").alias("high")).alias("t")).groupBy("lang", "source").agg(F.sort_array(F.collect_list("t")).alias("t"))
    return durable(rows.select(F.col("lang").alias("t_lang"), F.col("source").alias("t_source"), "t"))


def judge(stats: DataFrame, limits: DataFrame) -> DataFrame:
    """``stats`` with __kept: not base_failed, and every feature within the thresholds of the row's language and source."""
    match = F.col("lang").eqNullSafe(F.col("t_lang")) & F.col("source").eqNullSafe(F.col("t_source"))
    if limits.count() <= MOST_BROADCAST:
        joined = stats.join(F.broadcast(limits), match, "left")
    else:  # a source with a third of all rows is dealt to SALTS tasks
        salted = limits.withColumn("t_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = stats.withColumn("__salt", F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int")).join(salted, match & (F.col("__salt") == F.col("t_salt")), "left").drop("__salt", "t_salt")
    inside = F.forall(F.coalesce("t", F.array().cast("array<struct<feature:int,low:bigint,high:bigint>>")), lambda t: (F.get("__q.features", t["feature"]) <= t["high"]) & (F.get("__q.features", t["feature"]) >= F.coalesce(t["low"], F.lit(0))))
    return joined.withColumn("__kept", ~F.col("__q.base_failed") & inside).drop("t", "t_lang", "t_source")


def packed(docs: DataFrame, text_column: str, *columns: str) -> DataFrame:
    """(row, lang, source): the named columns of ``docs`` in one struct, so that no name of theirs meets one of the rules'."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("row"), F.col("lang"), F.col("source"), F.col(f"`{text_column}`").cast("string").alias("text"))


def verdicts(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """Counts, base_failed and kept of every row.

    A null or empty text has no words and fails the base rules; null languages and sources are
    groups of their own; repeated rows count and are returned as often as they come; a group none
    of whose rows passes the base rules has no thresholds; no rows give no rows; other columns of
    any name are ignored.
    """
    stats = durable(with_stats(packed(docs, text_column, id_column)).drop("text"))
    out = judge(stats, thresholds(sketch(stats)))
    return out.select(F.col(f"row.`{id_column}`").alias("id"), *[F.col(f"__q.{c}") for c in BASE], F.col("__q.base_failed"), F.col("__kept").alias("kept"))


def keep_by_rules(docs: DataFrame, text_column: str = "text") -> DataFrame:
    """The rows of ``docs`` that the rules keep, with all their columns, whatever their names; the same cases as in ``verdicts``.

    Counts are worked out once: rows that pass the base rules are kept with them until the
    thresholds, which need all of them, are there.
    """
    stats = durable(with_stats(packed(docs, text_column, *docs.columns)).drop("text").filter("NOT __q.base_failed"))
    limits = thresholds(sketch(stats))
    return judge(stats, limits).filter("__kept").select(*[F.col(f"row.`{c}`").alias(c) for c in docs.columns])


def oracle() -> str:
    """The same for DuckDB."""
    words = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
    bare = r"regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', '', 'g')"
    out = rf"""
    WITH d AS (SELECT doc_id, lang, source, coalesce(text, '') AS text, {words} AS w FROM documents),
    p AS (SELECT doc_id, unnest(range(1, greatest(len(w) - {WINDOW - 2}, 1))) AS i, w FROM d),
    v AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, array_to_string(w[i : i + {WINDOW - 1}], ' ')) AS c FROM p),
    r AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM v, range({WINDOW}) AS t(k) WHERE c > 1 GROUP BY doc_id),
    l AS (SELECT doc_id, [x FOR x IN string_split(text, chr(10)) IF regexp_matches(x, '[^\x20\x09-\x0D]')] AS l FROM d),
    b AS (SELECT d.doc_id, lang, source, len(w)::BIGINT AS n_words, length({bare})::BIGINT AS word_chars,
        (length(text) - length(translate(text, '{SYMBOLS}', '')))::BIGINT AS n_symbols,
        (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(r.n, 0)::BIGINT AS n_repeat_words, len(l) AS n_lines,
        length(text) - length(translate(text, '{UPPER}', '')) AS n_upper, length(text) - length(translate(text, '!?', '')) AS n_marks
        FROM d JOIN l USING (doc_id) LEFT JOIN r USING (doc_id)),
    f AS (SELECT *, n_words < {LEAST_WORDS} OR 100 * n_repeat_words > {MOST_REPEATED} * n_words AS base_failed,
        [n_symbols * 1000 // greatest(word_chars, 1), n_dup_lines * 1000 // greatest(n_lines, 1), n_repeat_words * 1000 // greatest(n_words, 1),
         word_chars * 10 // greatest(n_words, 1), n_upper * 1000 // greatest(word_chars, 1), n_marks * 1000 // greatest(word_chars, 1)] AS x FROM b),
    e AS (SELECT lang, source, k, x[k] AS v FROM f, range(1, {len(FEATURES) + 1}) AS t(k) WHERE NOT base_failed),
    s AS (SELECT lang, source, k, v - v % (2 ** greatest(length(bin(v)) - 7, 0))::BIGINT AS v FROM e),
    """

    def fences(name: str, keys: str) -> str:
        by = f"{keys}k"
        up = "[" + ", ".join(str(x[1]) for x in FEATURES) + "]"
        down = "[" + ", ".join("NULL" if x[2] is None else str(x[2]) for x in FEATURES) + "]"
        return f"""{name}1 AS (SELECT *, row_number() OVER (PARTITION BY {by} ORDER BY v) AS i, count(*) OVER (PARTITION BY {by}) AS n FROM s),
        {name}2 AS (SELECT {by}, max(n) AS n, min(v) FILTER (4 * i >= n) AS q1, min(v) FILTER (4 * i >= 3 * n) AS q3 FROM {name}1 GROUP BY ALL),
        {name} AS (SELECT {by}, n, q1 - {FENCE} * (q3 - q1) - {down}[k] AS lo, q3 + {FENCE} * (q3 - q1) + {up}[k] AS hi FROM {name}2),
        """

    out += fences("own", "lang, source, ") + fences("wide", "lang, ") + fences("whole", "")
    pick = lambda c: f"CASE WHEN own.n >= {LEAST_ROWS} THEN own.{c} WHEN wide.n >= {LEAST_ROWS} THEN wide.{c} ELSE whole.{c} END"
    return (
        out
        + f"""t AS (SELECT own.lang, own.source, own.k, {pick("lo")} AS lo, {pick("hi")} AS hi FROM own JOIN wide ON own.k = wide.k AND own.lang IS NOT DISTINCT FROM wide.lang JOIN whole ON own.k = whole.k),
    bad AS (SELECT DISTINCT doc_id FROM f JOIN t ON f.lang IS NOT DISTINCT FROM t.lang AND f.source IS NOT DISTINCT FROM t.source WHERE x[k] > hi OR x[k] < coalesce(lo, 0))
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND doc_id NOT IN (SELECT doc_id FROM bad) AS kept FROM f"""
    )
