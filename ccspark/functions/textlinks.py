"""Keys inside text: lines, hosts, links, word runs, digests."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def lines(text: Column, min_chars: int = 20) -> Column:
    """Distinct trimmed lines of at least ``min_chars`` characters, as an array."""
    return F.array_distinct(F.filter(F.transform(F.split(text, "\n"), F.trim), lambda x: F.char_length(x) >= min_chars))


def host(url: Column) -> Column:
    found = F.regexp_extract(url, "://([^/:?]+)", 1)
    return F.when(found != "", found)


def links(html: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(html, F.lit('href="([^"]+)"'), F.lit(1)))


def shingles(text: Column, k: int) -> Column:
    words = F.split(F.trim(text), r"\s+")
    last = F.greatest(F.size(words) - k, F.lit(0))
    return F.array_distinct(F.transform(F.sequence(F.lit(1), last + 1), lambda i: F.array_join(F.slice(words, i, F.lit(k)), " ")))


def digest(text: Column) -> Column:
    return F.md5(text)
