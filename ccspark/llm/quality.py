"""Quality rules: a table of thresholds compiled into one projection. DataFrame functions only.

Measures of a text: words are runs outside the six white-space characters, lines are
parts between ``\\n``. Null or empty text has no words and no line with a word. Repeated
rows give repeated rows, extra columns are left behind, an empty table gives none.

A text's repeated 8-word windows are found by sorting their hashes as primitive longs;
only a text that has some goes on to place them, so that clean text pays for one sort.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ccspark.llm.common import LOWER, UPPER, WHITE, ascii_lower, text_of, words_of

WINDOW = 8
SYMBOLS = "#*$%&|<>"
#: Frequent words of the four languages, and the marks stripped before they are looked up.
STOP_WORDS = (
    "the and of to in is that it for on with was as are be by this at from or an have not but they you we which "
    "de la le les des et en un une du que qui dans pour par sur der die das und ist nicht ein eine mit von zu den auf für el los las y con se no es"
).split()
MARKS = ".,;:!?\"'()"


@dataclass(frozen=True)
class Threshold:
    """One row of the rule table: text passes if ``low <= numerator / denominator <= high``; a ratio over nothing passes."""

    name: str
    numerator: str
    denominator: str
    low: float | None = None
    high: float | None = None


#: The rule table. Measures are columns of :func:`measures`.
RULES = (
    Threshold("mean_word_length", "word_chars", "n_words", 2.0, 15.0),
    Threshold("symbols_per_word", "n_symbols", "n_words", None, 0.25),
    Threshold("exclaims_per_word", "n_exclaims", "n_words", None, 0.5),
    Threshold("capital_share", "n_capitals", "word_chars", None, 0.35),
    Threshold("words_with_letters", "n_letter_words", "n_words", 0.75, None),
    Threshold("stop_words", "n_stop_words", "n_words", 0.03, None),
    Threshold("duplicate_lines", "n_dup_lines", "n_lines", None, 0.4),
    Threshold("cut_lines", "n_cut_lines", "n_lines", None, 0.5),
)


def _length_without(text: Column, chars: str) -> Column:
    return F.char_length(F.translate(text, chars, ""))


def measures(docs: DataFrame, *carry: str) -> DataFrame:
    """``doc_id``, the carried columns and every measure as a long."""
    t = docs.select("doc_id", *carry, text_of().alias("_t"))
    t = t.select("*", words_of(F.col("_t")).alias("_w"), F.filter(F.split("_t", "\n"), lambda x: F.btrim(x, F.lit(WHITE)) != "").alias("_l"))
    t = t.select("*", F.size("_w").cast("long").alias("n_words"), F.transform("_w", lambda x: F.xxhash64(x)).alias("_h"))
    window = lambda i: F.xxhash64(*[F.get("_h", i + k) for k in range(WINDOW)])
    none = F.array().cast("array<bigint>")
    t = t.select("*", F.when(F.col("n_words") >= WINDOW, F.transform(F.sequence(F.lit(0), (F.col("n_words") - WINDOW).cast("int")), window)).otherwise(none).alias("_g"))
    t = t.select("*", F.sort_array("_g").alias("_s"))
    some = F.exists(F.zip_with("_s", F.slice("_s", 2, F.greatest(F.size("_s"), F.lit(1))), lambda a, b: F.coalesce(a == b, F.lit(False))), lambda x: x)
    pairs = F.sort_array(F.transform("_g", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    t = t.select("*", F.when(some, pairs).otherwise(F.array().cast("array<struct<h:bigint,i:int>>")).alias("_p"))
    again = lambda x, j: (F.coalesce(F.get("_p", j - 1)["h"] == x["h"], F.lit(False))) | F.coalesce(F.get("_p", j + 1)["h"] == x["h"], F.lit(False))
    t = t.select("*", F.sort_array(F.transform(F.filter("_p", again), lambda x: x["i"])).alias("_q"))
    covered = F.aggregate(
        "_q",
        F.struct(F.lit(-WINDOW).alias("last"), F.lit(0).cast("long").alias("n")),
        lambda a, i: F.struct(i.alias("last"), (a["n"] + F.least(F.lit(WINDOW), i - a["last"])).alias("n")),
    )["n"]
    length = F.char_length("_t")
    count = lambda c: F.size(c).cast("long")
    return t.select(
        "doc_id",
        *carry,
        "n_words",
        _length_without(F.col("_t"), WHITE).cast("long").alias("word_chars"),
        (length - _length_without(F.col("_t"), SYMBOLS)).cast("long").alias("n_symbols"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        covered.alias("n_repeat_words"),
        count("_l").alias("n_lines"),
        (length - _length_without(F.col("_t"), "!?")).cast("long").alias("n_exclaims"),
        (length - _length_without(F.col("_t"), UPPER)).cast("long").alias("n_capitals"),
        count(F.filter("_w", lambda x: x.rlike(r"\p{L}"))).alias("n_letter_words"),
        count(F.filter("_w", lambda x: F.translate(F.btrim(x, F.lit(MARKS)), UPPER, LOWER).isin(STOP_WORDS))).alias("n_stop_words"),
        count(F.filter("_l", lambda x: x.endswith("...") | x.endswith("…"))).alias("n_cut_lines"),
    )


def compile_rules(rules: Sequence[Threshold] = RULES) -> Column:
    """One boolean over the measures: all rules hold."""
    out = F.lit(True)
    for r in rules:
        for bound, sign in ((r.low, ">="), (r.high, "<=")):
            if bound is not None:
                a, b = F.col(r.numerator), F.col(r.denominator) * F.lit(bound)
                out = out & ((F.col(r.denominator) == 0) | (a >= b if sign == ">=" else a <= b))
    return out


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


def judge(docs: DataFrame, rules: Sequence[Threshold] = RULES) -> DataFrame:
    """``doc_id``, the measures, ``base_failed`` and ``kept`` for each row."""
    return measures(docs).withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & compile_rules(rules))


def filter_documents(docs: DataFrame, rules: Sequence[Threshold] = RULES) -> DataFrame:
    """The rows that are kept, with their own columns: the verdict stands on the row itself, no join.

    Rows are let go by exploding an array that is null for them. As a filter the verdict would be pushed
    below the projections that share its measures, and each measure would be computed anew for each element.
    """
    names = list(docs.columns)
    renamed = docs.select("doc_id", "text", F.struct(*[F.col(f"`{c}`") for c in names]).alias("_row"))
    kept = measures(renamed, "_row").select(F.explode(F.when(~base_failed() & compile_rules(rules), F.array("_row"))).alias("_row"))
    return kept.select(*[F.col("_row").getField(c).alias(c) for c in names])


def oracle_sql(rules: Sequence[Threshold] = RULES, table: str = "documents", columns: str = "") -> str:
    """The same rows in DuckDB."""
    white = r"[^\x20\x09-\x0D]+"
    tests = []
    for r in rules:
        for bound, sign in ((r.low, ">="), (r.high, "<=")):
            if bound is not None:
                tests.append(f"({r.denominator} = 0 OR {r.numerator} {sign} {r.denominator} * {bound}::DOUBLE)")
    stop = ", ".join(f"'{w}'" for w in STOP_WORDS)
    marks = MARKS.replace("'", "''")
    return rf"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS t FROM {table}),
w AS (SELECT doc_id, t, regexp_extract_all(t, '{white}') AS w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM t),
g AS (SELECT doc_id, i, array_to_string(w[i : i + {WINDOW - 1}], ' ') AS g FROM w, range(1, len(w) - {WINDOW - 2}) AS r(i) WHERE len(w) >= {WINDOW}),
p AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM g) WHERE c > 1),
q AS (SELECT doc_id, sum(least({WINDOW}, i - coalesce(b, i - {WINDOW}))) AS n FROM (SELECT doc_id, i, lag(i) OVER (PARTITION BY doc_id ORDER BY i) AS b FROM p) GROUP BY doc_id),
m AS (SELECT doc_id, len(w)::BIGINT AS n_words, length(translate(t, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13), ''))::BIGINT AS word_chars,
  (length(t) - length(translate(t, '{SYMBOLS}', '')))::BIGINT AS n_symbols, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(q.n, 0)::BIGINT AS n_repeat_words,
  len(l)::BIGINT AS n_lines, (length(t) - length(translate(t, '!?', '')))::BIGINT AS n_exclaims, (length(t) - length(translate(t, '{UPPER}', '')))::BIGINT AS n_capitals,
  len(list_filter(w, lambda x: regexp_matches(x, '\p{{L}}')))::BIGINT AS n_letter_words,
  len(list_filter(w, lambda x: translate(trim(x, '{marks}'), '{UPPER}', '{LOWER}') IN ({stop})))::BIGINT AS n_stop_words,
  len(list_filter(l, lambda x: x LIKE '%...' OR x LIKE '%…'))::BIGINT AS n_cut_lines
  FROM w LEFT JOIN q USING (doc_id)),
b AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM m)
SELECT *, NOT base_failed AND {" AND ".join(tests)} AS kept FROM b
"""


def lower_words(text: Column) -> Column:
    return words_of(ascii_lower(text))
