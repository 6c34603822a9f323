"""Chat formatting with cumulative-snapshot collapse, by DataFrame functions only.

A logged conversation is often a snapshot that a later log continues.  Each turn gets two 64-bit
hashes of its place, role and text; their running exclusive-or is a hash of the conversation up to
that turn.  A conversation whose whole hash is that of an earlier turn of another one is a prefix of
it and goes, by an anti-join; of equal conversations the smallest id stays.  What stays is rendered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import durable

#: What stands before a turn's role, between role and text, and after the text.
OPEN, MIDDLE, CLOSE = "<|", "|>\n", "<|end|>\n"


def _escaped(text: Column) -> Column:
    """Marks inside a text cannot be read as marks."""
    return F.replace(F.coalesce(text, F.lit("")), F.lit("<|"), F.lit("< |"))


def prefix_hashes(turns: DataFrame, id_column: str = "conv_id", turn_column: str = "turn", role_column: str = "role", text_column: str = "text") -> DataFrame:
    """(id, role, text, place, a, b): place from 1 by turn, then role, then text; a and b hash all up to that place."""
    rows = turns.select(F.col(id_column).alias("id"), F.col(turn_column).alias("turn"), F.coalesce(F.col(role_column), F.lit("")).alias("role"), F.coalesce(F.col(text_column), F.lit("")).alias("text")).filter("id IS NOT NULL")
    by = Window.partitionBy("id").orderBy("turn", "role", "text")
    placed = rows.withColumn("place", F.row_number().over(by))
    upto = by.rowsBetween(Window.unboundedPreceding, 0)
    return placed.select("id", "role", "text", "place", F.bit_xor(F.xxhash64("place", "role", "text")).over(upto).alias("a"), F.bit_xor(F.xxhash64("text", F.lit("\0"), "role", "place")).over(upto).alias("b"))


def collapse(prefixes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(id, place, copies) of the maximal conversations, the smallest id of equal ones; and all (place, a, b) that were someone's proper prefix.

    One key's rows are counted before they are shuffled, so that a first turn or a conversation
    that is logged many times makes one row a task.
    """
    last = prefixes.groupBy("id").agg(F.max(F.struct("place", "a", "b")).alias("l"))
    whole = last.groupBy("l").agg(F.min("id").alias("id"), F.count("*").alias("copies")).select("id", "copies", "l.*")
    ends = last.select("id", F.col("l.place").alias("end"))
    inner = prefixes.select("id", "place", "a", "b").join(ends, "id").filter("place < end").select("place", "a", "b").distinct()
    return whole.join(inner, ["place", "a", "b"], "left_anti").select("id", "place", "copies"), inner


def render(turns: DataFrame, id_column: str = "conv_id", turn_column: str = "turn", role_column: str = "role", text_column: str = "text") -> DataFrame:
    """(id, n_turns, copies, chat) of each maximal conversation.

    A null role or text is an empty one; turns without a conversation id are left out; a null turn
    comes first; repeated turns are turns; no rows give no rows; other columns are ignored.
    """
    prefixes = durable(prefix_hashes(turns, id_column, turn_column, role_column, text_column))
    kept, _ = collapse(prefixes)
    rows = prefixes.select("id", "place", "role", "text").join(kept.select("id", "copies"), "id")
    line = F.concat(F.lit(OPEN), _escaped(F.col("role")), F.lit(MIDDLE), _escaped(F.col("text")), F.lit(CLOSE))
    chats = rows.groupBy("id", "copies").agg(F.sort_array(F.collect_list(F.struct("place", line.alias("line")))).alias("lines"))
    return chats.select("id", F.size("lines").cast("long").alias("n_turns"), "copies", F.array_join(F.transform("lines", lambda x: x["line"]), "").alias("chat"))


ORACLE = f"""
    WITH t AS (SELECT conv_id, row_number() OVER w AS place, turn, coalesce(role, '') AS role, coalesce(text, '') AS text
        FROM conversations WHERE conv_id IS NOT NULL WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, coalesce(role, ''), coalesce(text, ''))),
    p AS (SELECT conv_id, place, max(place) OVER (PARTITION BY conv_id) AS n,
        list((role, text)) OVER (PARTITION BY conv_id ORDER BY place ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS l FROM t),
    w AS (SELECT min(conv_id) AS conv_id, count(*) AS copies, l, n FROM p WHERE place = n GROUP BY l, n),
    k AS (SELECT conv_id, copies, n FROM w WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.l = w.l AND p.place < p.n))
    SELECT conv_id, n::BIGINT AS n_turns, copies, string_agg('{OPEN}' || replace(role, '<|', '< |') || '|>' || chr(10) || replace(text, '<|', '< |') || '<|end|>' || chr(10), '' ORDER BY place) AS chat
    FROM k JOIN t USING (conv_id) GROUP BY conv_id, n, copies"""
