"""Chat formatting: logged snapshots of one growing conversation collapse to the longest, then render.

Only DataFrame functions. A turn's fingerprint is two 64-bit hashes of (place, role, text) with
different seeds; the prefix hash after turn t is the running XOR of the fingerprints of the places
1..t, an order-bound 128-bit name as each fingerprint holds its place. The hash of a whole
conversation is its last prefix hash, so a conversation is a snapshot of a longer one exactly if
its hash is among the proper prefixes' hashes (all but the last of a conversation).

Defined results: turns are ordered by turn, role, text (nulls first); repeated rows are turns of
their own; a null role or text counts as empty; rows with a null conv_id belong to no conversation
and are left out. Of equal conversations the one with the smallest conv_id stays. Columns beyond
conv_id, turn, role and text are ignored. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def prefix_hashes(turns: DataFrame) -> DataFrame:
    """conv_id, place, a, b (the prefix hash), role, text, last (whether it is the last turn)."""
    rows = turns.where("conv_id IS NOT NULL").select(
        "conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")
    )
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    upto = order.rowsBetween(Window.unboundedPreceding, 0)
    return (
        rows.withColumns({"place": F.row_number().over(order), "last": F.lead(F.lit(1)).over(order).isNull()})
        .withColumns({"a": F.xxhash64("place", "role", "text"), "b": F.xxhash64(F.lit(-7), "text", "role", "place")})
        .withColumns({"a": F.bit_xor("a").over(upto), "b": F.bit_xor("b").over(upto)})
        .select("conv_id", "place", "a", "b", "last", "role", "text")
    )


def maximal(turns: DataFrame) -> DataFrame:
    """conv_id, n_turns of the conversations that prefix no other one.

    Proper prefixes and whole conversations are made distinct before they meet, so a first turn
    that a third of all conversations share is one row of the anti-join.
    """
    h = prefix_hashes(turns).select("conv_id", "place", "a", "b", "last")
    whole = h.where("last").groupBy("place", "a", "b").agg(F.min("conv_id").alias("conv_id"))
    inner = h.where("NOT last").select("place", "a", "b").distinct()
    return whole.join(inner, ["place", "a", "b"], "left_anti").select("conv_id", F.col("place").cast("long").alias("n_turns"))


def render(turns: DataFrame, kept: DataFrame, opens: str = "<|im_start|>", closes: str = "<|im_end|>") -> DataFrame:
    """conv_id, n_turns, rendered: each turn as ``{opens}{role}\\n{text}{closes}\\n``. One rendered string is one row by need."""
    said = turns.where("conv_id IS NOT NULL").select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    line = lambda x: F.concat(F.lit(opens), x["role"], F.lit("\n"), x["text"], F.lit(closes + "\n"))
    return (
        said.join(kept, "conv_id")
        .groupBy("conv_id", "n_turns")
        .agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("t"))
        .select("conv_id", "n_turns", F.array_join(F.transform("t", line), "").alias("rendered"))
    )


def collapse_and_render(turns: DataFrame, **template: str) -> DataFrame:
    return render(turns, maximal(turns), **template)


ORACLE = """
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text,
         row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, coalesce(role, ''), coalesce(text, '')) AS place
  FROM conversations WHERE conv_id IS NOT NULL),
p AS (
  SELECT conv_id, place,
         md5(string_agg(place || chr(1) || role || chr(2) || text, chr(3)) OVER (PARTITION BY conv_id ORDER BY place)) AS h,
         max(place) OVER (PARTITION BY conv_id) AS n
  FROM t),
whole AS (SELECT h, n, min(conv_id) AS conv_id FROM p WHERE place = n GROUP BY h, n),
kept AS (SELECT conv_id, n FROM whole WHERE h NOT IN (SELECT h FROM p WHERE place < n))
SELECT k.conv_id, k.n::BIGINT AS n_turns,
       string_agg('<|im_start|>' || role || chr(10) || text || '<|im_end|>' || chr(10), '' ORDER BY place) AS rendered
FROM kept k JOIN t USING (conv_id) GROUP BY k.conv_id, k.n
"""
