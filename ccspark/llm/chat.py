"""Chat formatting after the collapse of cumulative snapshots. DataFrame functions only.

Logged conversations often repeat: each snapshot holds the turns so far. A conversation
whose whole turn sequence (role and text, in order) starts a longer one is dropped, and
of equal conversations the one of lowest id stays. Rolling hashes name every prefix;
full hashes are made unique before an anti-join against the distinct proper prefixes, so
a first turn that a third of all conversations share is one row on either side.

Turns are ordered by (turn, role, text digest); repeated rows are turns of their own.
Null role or text counts as empty; a null turn comes first; rows with a null conv_id
belong to no conversation and are left out. An empty table gives no rows. Only a
conversation's own turns are gathered into one row, as its rendered text must be.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ccspark.llm.common import scan_array

#: Fixed values of the template.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


def _turns(conversations: DataFrame) -> DataFrame:
    return conversations.where("conv_id is not null").select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")
    )


def prefix_hashes(conversations: DataFrame) -> DataFrame:
    """``conv_id, n_turns, prefixes``: prefixes[i] is the hash of the first i + 1 turns."""
    turns = _turns(conversations).select("conv_id", "turn", "role", F.md5(F.concat(F.md5("role"), F.md5("text"))).alias("h"))
    rows = turns.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "h"))).alias("t"))
    roll = lambda last, t: F.md5(F.concat(last, t["h"]))
    return rows.select("conv_id", F.size("t").alias("n_turns"), scan_array(F.col("t"), F.lit(""), roll, roll, "string").alias("prefixes"))


def maximal(conversations: DataFrame) -> DataFrame:
    """``conv_id, n_turns``: conversations that start no longer one, one of each set of equals."""
    p = prefix_hashes(conversations)
    whole = p.groupBy(F.element_at("prefixes", -1).alias("h")).agg(F.min("conv_id").alias("conv_id"), F.min("n_turns").alias("n_turns"))
    proper = p.where("n_turns > 1").select(F.explode(F.slice("prefixes", F.lit(1), F.col("n_turns") - 1)).alias("h")).distinct()
    return whole.join(proper, "h", "left_anti").select("conv_id", "n_turns")


def _escape(text: Column) -> Column:
    """The template's own marks inside a text lose their first character's meaning by a space after it."""
    return F.replace(F.replace(text, F.lit(OPEN), F.lit("< |im_start|>")), F.lit(CLOSE), F.lit("< |im_end|>"))


def format_chats(conversations: DataFrame) -> DataFrame:
    """``conv_id, n_turns, rendered``: each maximal conversation in the chat template."""
    kept = maximal(conversations)
    turns = _turns(conversations).withColumn("h", F.md5("text"))
    piece = F.concat(F.lit(OPEN), _escape(F.col("role")), F.lit("\n"), _escape(F.col("text")), F.lit(CLOSE + "\n"))
    rows = turns.join(kept, "conv_id").select("conv_id", "n_turns", F.struct("turn", "role", F.md5(F.concat(F.md5("role"), F.md5("text"))).alias("h"), piece.alias("piece")).alias("t"))
    out = rows.groupBy("conv_id").agg(F.max("n_turns").cast("long").alias("n_turns"), F.sort_array(F.collect_list("t")).alias("t"))
    return out.select("conv_id", "n_turns", F.array_join("t.piece", "").alias("rendered"))


#: The same rows in DuckDB.
ORACLE_SQL = r"""
WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text, md5(md5(coalesce(role, '')) || md5(coalesce(text, ''))) AS h
           FROM conversations WHERE conv_id IS NOT NULL),
c AS (SELECT conv_id, count(*) AS n, string_agg(h, '' ORDER BY turn NULLS FIRST, role, h) AS seq FROM t GROUP BY conv_id),
w AS (SELECT seq, min(conv_id) AS conv_id, min(n) AS n FROM c GROUP BY seq),
p AS (SELECT DISTINCT left(seq, (32 * i)::BIGINT) AS pre FROM c, range(1, n) AS r(i)),
k AS (SELECT w.conv_id, w.n FROM w WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.pre = w.seq))
SELECT t.conv_id::BIGINT AS conv_id, max(k.n)::BIGINT AS n_turns,
       string_agg('<|im_start|>' || replace(replace(t.role, '<|im_start|>', '< |im_start|>'), '<|im_end|>', '< |im_end|>') || chr(10)
                  || replace(replace(t.text, '<|im_start|>', '< |im_start|>'), '<|im_end|>', '< |im_end|>') || '<|im_end|>' || chr(10), '' ORDER BY t.turn NULLS FIRST, t.role, t.h) AS rendered
FROM t JOIN k ON t.conv_id = k.conv_id GROUP BY t.conv_id
"""
