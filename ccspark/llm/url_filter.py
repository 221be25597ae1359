"""URL filters: rules by host and path, then a cascade of Bloom filters. DataFrame functions only.

The cascade answers membership in a list exactly for every key of the corpus: level 0
encodes the listed keys, level 1 the unlisted keys of the corpus that level 0 lets pass,
level 2 the listed keys that level 1 lets pass, and so on until a level lets none pass by
mistake. A key is listed if the first level that misses it has an odd number, or if all
levels hit and the last has an even number.

A level is an array of 64-bit words, each key sets four bits of one word, built by a
``bit_or`` per word before any exchange. The arrays reach the tasks as scalar subqueries,
without a join. Their size follows the list, so it is checked: beyond ``max_words`` the
keys are dealt to shards by hash, each with a cascade of its own; the rows are written by
shard once, and each shard's are judged in a pass of their own.

The list is a table of hosts and paths, or a rule that marks keys. Only the cascade's
construction joins it, with the corpus's distinct keys.

Null url or one without ``://``: empty host, path and key, judged like any other key.
Repeated rows give repeated rows. Empty tables give no rows.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ccspark.llm.common import split_hosts
from ccspark.plans.store import Scratch

BITS = 4
MAX_WORDS = 1 << 22


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path


#: The rules of the query.
RULES = (Rule("allow", "com", "/"), Rule("block", "example.com", "/en/"), Rule("allow", "www.example.com", "/en/"), Rule("block", "net", "/es/"), Rule("block", "net", "/fr/"))


def rule_of(host: Column, path: Column, rules: Sequence[Rule]) -> Column:
    """The longest rule that fits, as a struct ``rule, verdict``, or null."""
    out = None
    for r in sorted(rules, key=lambda r: (-len(r.text), r.text)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        value = F.struct(F.lit(r.text).alias("rule"), F.lit(r.verdict).alias("verdict"))
        out = F.when(fits, value) if out is None else out.when(fits, value)
    return F.lit(None).cast("struct<rule:string,verdict:string>") if out is None else out


def listed_stand_in(host: Column, key: Column) -> Column:
    """The list of the query, as no list is among the tables: hosts with a label that starts with ``ads``, and a
    sixteenth of all other keys, by digest."""
    return host.rlike(r"(^|\.)ads") | F.md5(key).startswith("0")


def _slot(level: int, words: int) -> tuple[Column, Column]:
    h = F.xxhash64("k1", "k2", F.lit(level))
    at = F.pmod(F.shiftrightunsigned(h, 6 * BITS), F.lit(words)).cast("int")
    mask = reduce(lambda a, b: a.bitwiseOR(b), (_bit(F.shiftrightunsigned(h, 6 * j).bitwiseAND(F.lit(63)).cast("int")) for j in range(BITS)))
    return at, mask


def _bit(n: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("bigint"), n)


def _hit(level: int, words: int, bits: Column) -> Column:
    at, mask = _slot(level, words)
    return F.get(bits, at).bitwiseAND(mask) == mask


class Cascade:
    """Levels for one shard of the keys: number of words and the one-row table of each."""

    def __init__(self, scratch: Scratch, tag: str):
        self.scratch, self.tag, self.levels = scratch, tag, []

    def build(self, inside: DataFrame, n_in: int, outside: DataFrame, bits_per_key: int = 12) -> Cascade:
        """inside, outside: ``k1, k2``, distinct and disjoint."""
        encoded, n, others = inside, n_in, outside
        while n:
            level = len(self.levels)
            words = max(1, math.ceil(n * (bits_per_key if level == 0 else 8) / 64))
            at, mask = _slot(level, words)
            made = encoded.select(at.alias("i"), mask.alias("m")).groupBy("i").agg(F.bit_or("m").alias("m"))
            row = F.transform(F.sort_array(F.collect_list(F.struct("i", "m"))), lambda x: x["m"])
            spark = encoded.sparkSession
            every = spark.range(words).select(F.col("id").cast("int").alias("i"), F.lit(0).cast("long").alias("m"))
            full = made.unionByName(every).groupBy("i").agg(F.bit_or("m").alias("m")).agg(row.alias("bits"))
            self.levels.append((words, self.scratch.write(full, f"{self.tag}-bits-{level}")))
            passed, n = self.scratch.counted(others.where(_hit(level, words, self.bits(level))), f"{self.tag}-passed-{level}")
            encoded, others = passed, encoded
        return self

    def bits(self, level: int) -> Column:
        return self.levels[level][1].select("bits").scalar()

    def member(self) -> Column:
        """Whether the key ``k1, k2`` of a row is listed."""
        if not self.levels:
            return F.lit(False)
        out = F.lit(len(self.levels) % 2 == 1)
        for level in reversed(range(len(self.levels))):
            out = F.when(_hit(level, self.levels[level][0], self.bits(level)), out).otherwise(F.lit(level % 2 == 1))
        return out


def judge(pages: DataFrame, rules: Sequence[Rule] = RULES, listed: DataFrame | Callable[[Column, Column], Column] = listed_stand_in, max_words: int = MAX_WORDS, bits_per_key: int = 12, scratch: Scratch | None = None) -> DataFrame:
    """``page_id, host, path, rule, verdict, listed`` for every page: the rule's verdict, else ``block`` for a listed key.

    listed: a table of ``host, path`` (null: empty; repeated rows count once), or from (host, key) a boolean column that
    marks the listed keys; the key is host and path together.
    """
    scratch = scratch or Scratch(pages.sparkSession, "url-filter")
    host, path = split_hosts(F.col("url"))
    rows = pages.select(F.col("page_id"), host.alias("host"), path.alias("path"))
    hashes = {"k1": F.xxhash64("host", "path"), "k2": F.xxhash64(F.lit(1), F.col("path"), F.col("host"))}
    rows = rows.withColumns(hashes)
    if isinstance(listed, DataFrame):
        own = listed.select(*[F.coalesce(F.col(c), F.lit("")).alias(c) for c in ("host", "path")]).withColumns(hashes)
        own = own.select("k1", "k2", F.lit(True).alias("inside")).distinct()
        keys = rows.select("k1", "k2").distinct().join(own, ["k1", "k2"], "left").select("k1", "k2", F.coalesce("inside", F.lit(False)).alias("inside"))
    else:
        keys = rows.groupBy("k1", "k2").agg(F.bool_or(listed(F.col("host"), F.concat("host", "path"))).alias("inside"))
    keys = scratch.write(keys, "keys")
    n = keys.where("inside").count()
    shards = max(1, math.ceil(n * bits_per_key / 64 / max_words))
    out, shard = [], F.pmod("k2", F.lit(shards)).cast("int")
    if shards > 1:
        rows = scratch.write(rows.withColumn("shard", shard), "rows", partition_by=["shard"])
    for s in range(shards):
        own = F.col("shard") == s if shards > 1 else F.lit(True)
        part = keys.where(shard == s) if shards > 1 else keys
        cascade = Cascade(scratch, f"shard-{s}").build(part.where("inside").select("k1", "k2"), n if shards == 1 else part.where("inside").count(), part.where("not inside").select("k1", "k2"), bits_per_key)
        out.append(rows.where(own).withColumn("listed", cascade.member()))
    judged = reduce(DataFrame.unionByName, out).withColumn("r", rule_of(F.col("host"), F.col("path"), rules))
    verdict = F.coalesce(F.col("r.verdict"), F.when(F.col("listed"), "block").otherwise("allow"))
    return judged.select("page_id", "host", "path", F.col("r.rule").alias("rule"), verdict.alias("verdict"), "listed")


def oracle_sql(rules: Sequence[Rule] = RULES) -> str:
    """The same rows in DuckDB, by plain membership."""
    fits = sorted(rules, key=lambda r: (-len(r.text), r.text))
    case = " ".join(f"WHEN (host = '{r.host}' OR host LIKE '%.{r.host}') AND starts_with(path, '{r.path}') THEN '{{{i}}}'" for i, r in enumerate(fits))
    rule, verdict = (case.format(*[getattr(r, k) for r in fits]) for k in ("text", "verdict"))
    return rf"""
WITH u AS (SELECT page_id, coalesce(url, '') AS url FROM pages),
s AS (SELECT page_id, translate(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
             regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path FROM u),
m AS (SELECT *, regexp_matches(host, '(^|\.)ads') OR starts_with(md5(host || path), '0') AS listed FROM s)
SELECT page_id, host, path, CASE {rule} ELSE NULL END AS rule, CASE {verdict} WHEN listed THEN 'block' ELSE 'allow' END AS verdict, listed FROM m
"""
