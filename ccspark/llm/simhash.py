"""SimHash near-duplicates by anchor points of a covering code.

A fingerprint is a row of 32-bit words. The first 31 bits of a word are covered by the
perfect Hamming code of length 31: each value lies within one bit (the covering radius)
of exactly one codeword, its home anchor. A fingerprint is copied to every anchor within
covering radius plus one of each word: 1 or 16 anchors. Two fingerprints that differ by
at most ``2w - 1`` bits over ``w`` words differ by at most one bit in some word, and then
meet at the first one's home anchor. So two words find all pairs within two bits.

Equal fingerprints are one vertex from the start. Of an anchor, homes are compared with
guests; a crowded anchor is split first by parts of the other word, one more than bits may
differ, of which one must agree, so that no crowded list is compared with itself. Words
that are so frequent that their anchors would burden one task (``hot`` fingerprints) are
known beforehand: such anchors are dealt by these parts already. Links leave the task as a
spanning forest of each part, never as all pairs of a group.

Null or empty text has fingerprint zero and is linked like any other. Text of fewer words
than a shingle is one shingle. Repeated rows share a component. An empty table gives none.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.llm.common import lean
from ccspark.plans.runner import connected_components
from ccspark.plans.store import Scratch

SEED = 42
CODE_LENGTH = 31
CROWD = 512
#: Fingerprints of one word value above which its anchors are dealt by parts; a thousandth of all, if that is more.
HOT = 100_000
PAIRS_AT_ONCE = 1 << 21


def shingle_hashes(text: str, shingle: int) -> np.ndarray:
    """XXH64 of each run of words, A-Z in lower case, one space between the words; repeats stay."""
    import xxhash

    words = text.encode().lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    runs = list(map(b" ".join, zip(*[words[i:] for i in range(shingle)], strict=False))) if len(words) >= shingle else [b" ".join(words)]
    return np.fromiter(map(xxhash.xxh64_intdigest, runs, repeat(SEED)), np.uint64, len(runs))


def fingerprint(hashes: np.ndarray) -> int:
    """Bit i is 1 if set in over half of the hashes."""
    n, total = len(hashes), np.zeros(64, np.int64)
    for i in range(0, n, 1 << 16):
        part = hashes[i : i + (1 << 16)].astype("<u8")
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * total > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """``doc_id, fp`` (64 bits as a long) for each row."""

    def work(batches):
        import pyarrow as pa

        for b in batches:
            fps = np.array([fingerprint(shingle_hashes(t or "", shingle)) for t in b.column("text").to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fps.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(lean(work, 512), "doc_id long, fp long")


def _syndrome(x: np.ndarray) -> np.ndarray:
    """Sum (by exclusive or) of the places 1..31 of the set bits: zero for a codeword."""
    s = np.zeros(len(x), np.uint32)
    for place in range(1, CODE_LENGTH + 1):
        s ^= ((x >> np.uint32(place - 1)) & np.uint32(1)) * np.uint32(place)
    return s


def anchors(word: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, bool]]:
    """For 32-bit words: (rows, codewords, whether they are home) of all anchors within two bits."""
    x = word.astype(np.uint32) & np.uint32((1 << CODE_LENGTH) - 1)
    s = _syndrome(x)
    flip = lambda places: np.where(places > 0, np.uint32(1) << (np.maximum(places, 1) - 1).astype(np.uint32), np.uint32(0))
    yield np.arange(len(x)), x ^ flip(s), True
    odd = np.flatnonzero(s)
    for i in range(1, CODE_LENGTH + 1):
        j = s[odd] ^ np.uint32(i)
        take = odd[(j > i) & (j <= CODE_LENGTH)]
        yield take, x[take] ^ flip(np.full(len(take), i, np.uint32)) ^ flip(s[take] ^ np.uint32(i)), False


def hot_anchors(values: DataFrame, n: int, hot: int) -> np.ndarray:
    """Anchors, in order, of the word values (``value, n``: the word's number above 32 bits of it) that over ``hot`` fingerprints share.

    The bound follows the fingerprints, so that some thousand values at most are told to the tasks.
    """
    got = values.groupBy("value").agg(F.sum("n").alias("n")).where(F.col("n") > max(hot, n // 1000)).select("value").toArrow()
    value = got.column("value").to_numpy()
    found = [np.zeros(0, np.int64)]
    for rows, code, _ in anchors((value & 0xFFFFFFFF).astype(np.uint32)):
        found.append(code.astype(np.int64) | value[rows] >> 32 << 32)
    return np.unique(np.concatenate(found))


def is_hot(hot: np.ndarray, anchor: np.ndarray) -> np.ndarray:
    if not len(hot):
        return np.zeros(len(anchor), bool)
    return hot[np.minimum(np.searchsorted(hot, anchor), len(hot) - 1)] == anchor


def _parts(anchor: np.ndarray, fp: np.ndarray, max_bits: int) -> Iterator[np.ndarray]:
    """Parts of the word that the anchor is not of, one more than bits may differ: equal in one of them if within ``max_bits``."""
    half = (anchor >> 32).astype(np.uint64)
    other = (fp >> (np.uint64(32) * (np.uint64(1) - half))) & np.uint64(0xFFFFFFFF)
    edges = [32 * i // (max_bits + 1) for i in range(max_bits + 2)]
    for low, high in zip(edges, edges[1:], strict=False):
        yield ((other >> np.uint64(low)) & np.uint64((1 << (high - low)) - 1)).astype(np.int64)


def replicate(distinct: DataFrame, max_bits: int = 2, hot: int = HOT) -> DataFrame:
    """``anchor, part, fp, rep, home``: each distinct fingerprint (``fp, rep``) at all its anchors of both words.

    part: zero, or for a hot anchor the number and value of a part of the other word.
    """
    word = F.explode(F.array(F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF)), F.shiftrightunsigned("fp", 32).bitwiseOR(F.lit(1 << 32)))).alias("value")
    sent = distinct.sparkSession.sparkContext.broadcast(hot_anchors(distinct.select(word, F.lit(1).alias("n")), distinct.count(), hot))
    names = ["anchor", "part", "fp", "rep", "home"]

    def work(batches):
        import pyarrow as pa

        def rows_of(at, part, fp, rep, rows, home):
            return pa.RecordBatch.from_arrays([pa.array(at), pa.array(part), pa.array(fp[rows].view(np.int64)), rep.take(pa.array(rows)), pa.array(np.full(len(rows), home))], names=names)

        for b in batches:
            fp, rep = b.column("fp").to_numpy().view(np.uint64), b.column("rep")
            for half in (0, 1):
                word = (fp >> np.uint64(32 * half)).astype(np.uint32)
                for rows, code, home in anchors(word):
                    at = code.astype(np.int64) | np.int64(half << 32)
                    many = is_hot(sent.value, at)
                    few = ~many
                    if few.any():
                        yield rows_of(at[few], np.zeros(few.sum(), np.int64), fp, rep, rows[few], home)
                    if many.any():
                        for i, part in enumerate(_parts(at[many], fp[rows[many]], max_bits)):
                            yield rows_of(at[many], part | (i + 1) << 33, fp, rep, rows[many], home)

    return distinct.select("fp", "rep").mapInArrow(lean(work), "anchor long, part long, fp long, rep long, home boolean")


def _expand(group: np.ndarray, home: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (home row, row) of equal group, rows sorted by group; some millions at a time."""
    starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    ends = np.r_[starts[1:], len(group)]
    run = np.repeat(np.arange(len(starts)), ends - starts)
    homes = np.flatnonzero(home & ((ends - starts)[run] > 1))
    count = (ends - starts)[run[homes]]
    done = 0
    bounds = np.cumsum(count)
    while done < len(homes):
        upto = max(done + 1, int(np.searchsorted(bounds, (bounds[done - 1] if done else 0) + PAIRS_AT_ONCE, side="right")))
        h, c = homes[done:upto], count[done:upto]
        a = np.repeat(h, c)
        b = np.arange(int(c.sum())) - np.repeat(np.cumsum(c) - c, c) + np.repeat(starts[run[h]], c)
        yield a, b
        done = upto


def near_pairs(anchor: np.ndarray, part: np.ndarray, fp: np.ndarray, home: np.ndarray, max_bits: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Rows (sorted by anchor and part) that meet there within ``max_bits``; a pair may come more than once."""

    def near(a, b):
        keep = (fp[a] != fp[b]) & (np.bitwise_count(fp[a] ^ fp[b]) <= max_bits)
        return a[keep], b[keep]

    starts = np.flatnonzero(np.r_[True, (anchor[1:] != anchor[:-1]) | (part[1:] != part[:-1])])
    sizes = np.diff(np.r_[starts, len(anchor)])
    group_ = np.repeat(np.arange(len(starts)), sizes)
    big = np.repeat(sizes > CROWD, sizes)
    small = np.flatnonzero(~big & np.repeat(sizes > 1, sizes))
    if len(small):
        for a, b in _expand(group_[small], home[small]):
            yield near(small[a], small[b])
    crowd = np.flatnonzero(big)
    if len(crowd):
        for part in _parts(anchor[crowd], fp[crowd], max_bits):
            order = np.lexsort((part, group_[crowd]))
            rows = crowd[order]
            group = np.cumsum(np.r_[True, (np.diff(group_[rows]) != 0) | (np.diff(part[order]) != 0)])
            for a, b in _expand(group, home[rows]):
                yield near(rows[a], rows[b])


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of vertex pairs, as (vertex, lowest vertex of its part)."""
    ids, flat = np.unique(np.r_[a, b], return_inverse=True)
    x, y = flat[: len(a)], flat[len(a) :]
    low = np.arange(len(ids))
    while True:
        before = low.copy()
        np.minimum.at(low, x, before[y])
        np.minimum.at(low, y, low[x])
        low = low[low]
        if (low == before).all():
            break
    keep = low != np.arange(len(ids))
    return ids[keep], ids[low[keep]]


def _runs(batches, columns: int, rows: int = 200_000) -> Iterator[list[np.ndarray]]:
    """Arrays of whole anchors from batches sorted by anchor (the first column): some 200,000 rows at a time.

    Batches are kept as they come and joined once, so a long run is copied once.
    """
    held: list[list[np.ndarray]] = []
    n = 0

    def joined():
        return [np.concatenate(x) for x in zip(*held, strict=True)]

    for b in batches:
        if not b.num_rows:
            continue
        got = [b.column(i).to_numpy(zero_copy_only=False) for i in range(columns)]
        if n > rows and held[-1][0][-1] != got[0][0]:
            yield joined()
            held, n = [], 0
        elif n > rows and got[0][0] != got[0][-1]:
            cut = int(np.searchsorted(got[0], got[0][0], side="right"))
            held.append([g[:cut] for g in got])
            yield joined()
            held, n, got = [], 0, [g[cut:] for g in got]
        held.append(got)
        n += len(got[0])
    if n:
        yield joined()


def links(distinct: DataFrame, max_bits: int = 2, hot: int = HOT) -> DataFrame:
    """``src, dst``: a spanning forest of the links of each task's anchors, over the representatives."""
    if not 0 <= max_bits <= 3:
        raise ValueError("two words cover at most three differing bits")
    # three bits over two words leave at most one in some word
    dealt = replicate(distinct, max_bits, hot).repartition("anchor", "part").sortWithinPartitions("anchor", "part")

    def work(batches):
        import pyarrow as pa

        for anchor, part, fp, rep, home in _runs(batches, 5):
            a, b = [], []
            for x, y in near_pairs(anchor, part, fp.view(np.uint64), home.astype(bool), max_bits):
                if len(x):
                    u, v = forest(rep[x], rep[y])
                    a.append(u)
                    b.append(v)
            if a:
                u, v = forest(np.concatenate(a), np.concatenate(b))
                yield pa.RecordBatch.from_arrays([pa.array(v), pa.array(u)], names=["src", "dst"])

    return dealt.select("anchor", "part", "fp", "rep", "home").mapInArrow(lean(work), "src long, dst long")


def components(docs: DataFrame, shingle: int = 3, max_bits: int = 2, scratch: Scratch | None = None) -> DataFrame:
    """``doc_id, fp, component_id`` for each row; the component is the least doc_id that links reach."""
    scratch = scratch or Scratch(docs.sparkSession, "simhash")
    fps = scratch.write(fingerprints(docs, shingle), "fingerprints")
    distinct = scratch.write(fps.groupBy("fp").agg(F.min("doc_id").alias("rep")), "distinct")
    edges = scratch.write(links(distinct.where("rep is not null"), max_bits), "links")
    found = connected_components(edges, finish_edges=200_000, scratch=Scratch(docs.sparkSession, "simhash-cc")).assignment
    named = distinct.join(found.withColumnRenamed("vertex", "rep"), "rep", "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return fps.join(named, "fp").select("doc_id", "fp", "component_id")


def hex_fingerprint(fp):
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
