"""Repeated-substring removal by column-wise construction over aligned contexts.

Each byte covered by a string of ``length`` bytes that also starts earlier (smaller
doc_id, or same document and earlier start) is removed; overlaps count, matches stay
inside documents, and all strings are judged on the input.

Where two equal strings may stand is found by content-defined anchors: of the ``GRAM``-byte
grams that start in a string, the leftmost of least hash. Equal strings have equal
anchors at equal distance, so an anchor that stands once in the corpus rules out all
strings that own it. Around each other anchor the bytes of its strings form a context;
contexts aligned at the anchor are a collection of short documents, and the construction
inserts one symbol of each per round, from the last column to the first: a stable sort by
the new symbol turns the order of the suffixes of one round into that of the next (its
symbols in this order are the collection's Burrows-Wheeler column), and the common
prefixes of neighbours follow by range minima. Where ``length`` symbols are shared,
strings are equal. As anchors align the collection, a round meets only its own column, so
columns stream by and none is read again.

Equal contexts are one from the start: their first keeps its strings for judgement, and
all strings of the others are repeats; counts and firsts are taken in each task before the
exchange. (A context is told by 64 bits among those of its anchor, a hash of its own.) Only
contexts of anchors that have several are cut from the texts, and whether their strings
repeat is read off the construction alone: how contexts are dealt to blocks decides
nothing, as long as equal strings meet. An anchor with more than ``crowd`` different contexts
(the ends of a passage that stands in a large share of the documents) is constructed twice:
first in blocks of its documents, which leaves each string once for each block, then by the
bytes that all strings within a few places of each other share. :func:`column_files` gives
the construction's own output, round by round.

Null or empty text, or text under ``length`` bytes: nothing is removed. Repeated rows are
one document and have equal results; rows of equal doc_id and different text are documents
of their own, in the order of their digests. Null doc_ids come first. Extra columns are
left behind. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.llm.common import dense_ids, lean, text_of
from ccspark.plans.store import Scratch

LENGTH, GRAM = 100, 32
BLOCK_ROWS = 8192
#: Different contexts of an anchor above which it is constructed in two steps; its rows of a block in the first; ranges of places in the second.
CROWD, FIRST_ROWS, RANGES = 4096, 2048, 8
#: Texts that a task takes at once.
ROWS = 512
CHUNK = 1 << 22
_P = np.uint64(0x9E3779B97F4A7C15)


def gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    """A mixed hash of each gram (a power of two of bytes), by doubling."""
    h = (data.astype(np.uint64) + np.uint64(1)) * np.uint64(0xBF58476D1CE4E5B9)
    base, width = _P, 1
    with np.errstate(over="ignore"):
        while width < gram:
            h = h[:-width] * base + h[width:]
            base, width = base * base, 2 * width
        h ^= h >> np.uint64(31)
        h *= np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(29)
    return h


def least_places(h: np.ndarray, window: int) -> np.ndarray:
    """For each window of hashes the place of its leftmost least one."""
    place = np.arange(len(h), dtype=np.int32)
    value, span = h, 1
    while span < window:
        step = min(span, window - span)
        a, b = value[:-step], value[step:]
        right = b < a
        value = np.where(right, b, a)
        place = np.where(right, place[step:], place[:-step])
        span += step
    return place


def anchors_of(data: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """Anchors of one text: place, hash, and the first and last start of the strings that own it."""
    place = least_places(h := gram_hashes(data, gram), length - gram + 1)
    first = np.flatnonzero(np.r_[True, place[1:] != place[:-1]])
    last = np.r_[first[1:], len(place)] - 1
    at = place[first]
    return at, h[at], first, last


def _pieces(data: np.ndarray, length: int) -> Iterator[tuple[int, np.ndarray]]:
    """A long text in parts that share ``2 * length`` bytes, each with its offset."""
    for i in range(0, max(1, len(data) - length + 1), CHUNK):
        yield i, data[i : i + CHUNK + length - 1]


def text_anchors(text: str | None, length: int, gram: int):
    data = np.frombuffer((text or "").encode(), np.uint8)
    if len(data) < length:
        return data, None
    parts = [(i, anchors_of(d, length, gram)) for i, d in _pieces(data, length)]
    # an anchor at the seam may appear in both parts, each with its own strings: two rows, each right
    return data, tuple(np.concatenate([x[k] + (i if k != 1 else 0) for i, x in parts]) for k in (0, 1, 2, 3))


def _context_hashes(data: bytes, at: np.ndarray, first: np.ndarray, last: np.ndarray, length: int) -> np.ndarray:
    import xxhash

    digest = xxhash.xxh3_64_intdigest
    return np.fromiter((digest(data[a : b + length], p - a) for p, a, b in zip(at.tolist(), first.tolist(), last.tolist(), strict=True)), np.uint64, len(at))


def anchor_rows(docs: DataFrame, length: int, gram: int, contexts: bool) -> DataFrame:
    """``h`` alone, made distinct within the document's batch with its count, or all of ``h, c, d, at, own``.

    own: distance from the anchor back to the last and to the first start, in one number.
    """

    def count(batches):
        import pyarrow as pa

        for b in batches:
            got = [text_anchors(t, length, gram)[1] for t in b.column("text").to_pylist()]
            h, n = np.unique(np.concatenate([x[1] for x in got if x] or [np.zeros(0, np.uint64)]), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(n.astype(np.int64))], names=["h", "n"])

    def rows(batches):
        import pyarrow as pa

        for b in batches:
            for d, t in zip(b.column("d").to_pylist(), b.column("text").to_pylist(), strict=True):
                data, got = text_anchors(t, length, gram)
                if got:
                    at, h, first, last = got
                    c = _context_hashes(data.tobytes(), at, first, last, length)
                    own = ((at - last) << 16) | (at - first)
                    yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(c.view(np.int64)), pa.array(np.full(len(at), d, np.int64)), pa.array(at.astype(np.int32)), pa.array(own.astype(np.int32))], names=["h", "c", "d", "at", "own"])

    def gathered(batches):
        """Small batches of one document each are joined to batches worth sending."""
        import pyarrow as pa

        held, n = [], 0
        for b in rows(batches):
            held.append(b)
            n += b.num_rows
            if n > 50_000:
                yield from pa.Table.from_batches(held).combine_chunks().to_batches()
                held, n = [], 0
        if held:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()

    return docs.mapInArrow(lean(gathered, ROWS), "h long, c long, d long, at int, own int") if contexts else docs.mapInArrow(lean(count, ROWS), "h long, n long")


def columns(symbols: np.ndarray, cap: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """Round by round, from the last column: (column, order of the suffixes that start there, their symbols, common prefix with the one before, at most ``cap``)."""
    n, width = symbols.shape
    order, lcp = np.arange(n), np.zeros(n, np.int16)
    turned = np.ascontiguousarray(symbols.T)
    for c in range(width - 1, -1, -1):
        symbol = turned[c][order]
        perm = np.argsort(symbol, kind="stable")
        low = perm[:-1] + 1
        span = perm[1:] - low + 1
        same = symbol[perm[1:]] == symbol[perm[:-1]]
        new = np.zeros(n, np.int16)
        one = same & (span == 1)
        new[1:][one] = lcp[low[one]] + 1
        far = np.flatnonzero(same & (span > 1))
        if len(far):
            level = np.log2(span[far]).astype(np.int64)
            table = [lcp]
            for k in range(int(level.max())):
                t, s = table[-1], 1 << k
                table.append(np.minimum(t, np.r_[t[s:], np.full(s, cap, np.int16)]))
            stack = np.stack(table)
            new[1:][far] = np.minimum(stack[level, low[far]], stack[level, low[far] + span[far] - (1 << level)]) + 1
        order, lcp = order[perm], np.minimum(new, np.int16(cap))
        yield c, order, symbol[perm], lcp


def repeats(symbols: np.ndarray, nearest: np.ndarray, farthest: np.ndarray, rank: np.ndarray, length: int, reach: int) -> np.ndarray:
    """For aligned contexts (anchor at column ``reach``): marks [row, column] of strings that equal one of lower rank."""
    out = np.zeros((len(symbols), reach + 1), bool)
    for c, order, _, lcp in columns(symbols, length):
        if c > reach:
            continue
        back = reach - c
        own = ((nearest <= back) & (back <= farthest))[order]
        run = np.cumsum(lcp < length) - (lcp[0] < length)
        starts = np.flatnonzero(np.r_[True, lcp[1:] < length])
        held = np.where(own, rank[order], np.iinfo(np.int64).max)
        least = np.minimum.reduceat(held, starts)
        out[order, c] = own & (held > least[run])
    return out


def _mark_runs(flags: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows, first and last column of each run of marks."""
    edge = np.diff(np.pad(flags, ((0, 0), (1, 1))).astype(np.int8), axis=1)
    row, first = np.nonzero(edge == 1)
    _, past = np.nonzero(edge == -1)
    return row, first, past - 1


def _blocks(batches, rows: int = BLOCK_ROWS) -> Iterator[list[tuple]]:
    """Rows (``g, d, at, own, ctx``, sorted by g) in blocks of whole groups, some ``rows`` at a time."""
    held: list[tuple] = []
    for b in batches:
        held.extend(zip(*[b.column(i).to_pylist() for i in range(5)], strict=True))
        if len(held) >= rows and held[0][0] != held[-1][0]:
            cut = next(i for i in range(len(held) - 1, -1, -1) if held[i][0] != held[-1][0]) + 1
            yield held[:cut]
            held = held[cut:]
    if held:
        yield held


def _aligned(rows: list[tuple], length: int, reach: int) -> tuple[np.ndarray, ...]:
    """Symbols of the contexts with their anchors in one column, their places, and the nearest and farthest starts."""
    symbols = np.zeros((len(rows), reach + length), np.uint8)
    d, at, own = (np.array([r[k] for r in rows], np.int64) for k in (1, 2, 3))
    nearest, farthest = own >> 16, own & 0xFFFF
    for i, r in enumerate(rows):
        left = reach - int(farthest[i])
        symbols[i, left : left + len(r[4])] = np.frombuffer(r[4], np.uint8)
    return symbols, d, at, nearest, farthest


CONSTRUCTED = "d long, lo long, hi long, at int, own int, ctx binary"


def _construct(dealt: DataFrame, length: int, gram: int, rest: bool = False) -> DataFrame:
    """Bytes ``lo .. hi`` of ``d`` covered by strings that repeat an earlier one of their group.

    dealt: contexts ``g, d, at, own, ctx``, dealt and sorted by the group g. rest: also the strings that are the first
    of their kind in their block, as contexts (``at, own, ctx``; null for the others).
    """
    reach = length - gram

    def work(batches):
        import pyarrow as pa

        for rows in _blocks(batches):
            symbols, d, at, nearest, farthest = _aligned(rows, length, reach)
            sorted_ = np.lexsort((at, d))
            rank = np.zeros(len(rows), np.int64)
            rank[sorted_[1:]] = np.cumsum((np.diff(d[sorted_]) != 0) | (np.diff(at[sorted_]) != 0))
            flags = repeats(symbols, nearest, farthest, rank, length, reach)
            row, first, last = _mark_runs(flags)
            start = at[row] - reach + first
            none = pa.nulls(len(row), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(d[row]), pa.array(start), pa.array(start + (last - first) + length), none, none, pa.nulls(len(row), pa.binary())], names=names)
            if rest:
                back = reach - np.arange(reach + 1)[None, :]
                row, first, last = _mark_runs((nearest[:, None] <= back) & (back <= farthest[:, None]) & ~flags)
                kept = [symbols[i, a : b + length].tobytes() for i, a, b in zip(row.tolist(), first.tolist(), last.tolist(), strict=True)]
                none = pa.nulls(len(row), pa.int64())
                own = (reach - last) << 16 | (reach - first)
                yield pa.RecordBatch.from_arrays([pa.array(d[row]), none, none, pa.array(at[row].astype(np.int32)), pa.array(own.astype(np.int32)), pa.array(kept, pa.binary())], names=names)

    names = [x.split()[0] for x in CONSTRUCTED.split(", ")]
    return dealt.select("g", "d", "at", "own", "ctx").mapInArrow(lean(work), CONSTRUCTED)


def _by_shared_bytes(contexts: DataFrame, length: int, gram: int) -> DataFrame:
    """Contexts cut to ranges of places and dealt by the bytes that all strings of a range have in common: ``g, d, at, own, ctx``."""
    step = -(-(length - gram + 1) // RANGES)

    def work(batches):
        import pyarrow as pa
        import xxhash

        for b in batches:
            out: list[list] = [[] for _ in range(5)]
            for d, at, own, ctx in zip(*[b.column(i).to_pylist() for i in range(4)], strict=True):
                near, far = own >> 16, own & 0xFFFF
                for p in range(near // step, far // step + 1):
                    low, high = max(near, p * step), min(far, (p + 1) * step - 1)
                    shared = ctx[far - p * step : far - (p + 1) * step + 1 + length]
                    key = xxhash.xxh3_64_intdigest(shared, p) - (1 << 63)
                    for k, v in enumerate((key, d, at, low << 16 | high, ctx[far - high : far - low + length])):
                        out[k].append(v)
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(out, kinds, strict=True)], names=["g", "d", "at", "own", "ctx"])

    return contexts.select("d", "at", "own", "ctx").mapInArrow(lean(work), "g long, d long, at int, own int, ctx binary")


def _dealt(contexts: DataFrame) -> DataFrame:
    return contexts.repartition("g").sortWithinPartitions("g")


def column_files(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, scratch: Scratch | None = None) -> DataFrame:
    """The construction's own output: ``block, round, symbols, lcp``, one row for each block and round (last column first).

    symbols: of the suffixes that start in the round's column, in their order, so each round's piece of the collection's
    transform; lcp: two bytes each, the common prefix with the suffix before, at most ``length``. The rows are written in the order in which they come,
    so they are the sequential files of the construction; nothing of an earlier round is read again.
    """
    scratch = scratch or Scratch(docs.sparkSession, "substrings")
    contexts = _contexts(_numbered(docs, scratch), scratch, length, gram)[0]
    reach = length - gram

    def work(batches):
        import pyarrow as pa

        for rows in _blocks(batches):
            symbols, *_ = _aligned(rows, length, reach)
            for c, _, column, lcp in columns(symbols, length):
                yield pa.RecordBatch.from_arrays([pa.array([rows[0][0]], pa.int64()), pa.array([reach + length - 1 - c], pa.int32()), pa.array([column.tobytes()], pa.binary()), pa.array([lcp.astype("<i2").tobytes()], pa.binary())], names=["block", "round", "symbols", "lcp"])

    return _dealt(contexts.withColumnRenamed("h", "g")).select("g", "d", "at", "own", "ctx").mapInArrow(lean(work), "block long, round int, symbols binary, lcp binary")


def _numbered(docs: DataFrame, scratch: Scratch) -> DataFrame:
    """``d, doc_id, text``: d is the doc_id, or where some doc_id has several texts or is null, the rank of (doc_id, digest)."""
    t = docs.select(F.col("doc_id"), text_of().alias("text"))
    ids = t.select("doc_id", F.xxhash64("text").alias("k1"), F.xxhash64(F.lit(1), F.col("text")).alias("k2"))
    odd = ids.groupBy("doc_id").agg((F.min("k1") != F.max("k1")).alias("several")).where("several or doc_id is null").limit(1).count()
    if not odd:
        return t.select(F.col("doc_id").cast("long").alias("d"), "doc_id", "text")
    ranked = scratch.write(dense_ids(ids.distinct(), ["doc_id", "k1", "k2"], scratch).withColumnRenamed("id", "d"), "ranks")
    named = t.withColumns({"k1": F.xxhash64("text"), "k2": F.xxhash64(F.lit(1), F.col("text"))})
    r = ranked.select(F.col("doc_id").alias("r"), F.col("k1").alias("r1"), F.col("k2").alias("r2"), "d")
    return named.join(r, named["doc_id"].eqNullSafe(r["r"]) & (named["k1"] == r["r1"]) & (named["k2"] == r["r2"])).select("d", "doc_id", "text")


def _contexts(numbered: DataFrame, scratch: Scratch, length: int, gram: int) -> tuple[DataFrame, DataFrame]:
    """Different contexts of anchors that have several (``h, m, d, at, own, ctx``, m of them), and ``d, lo, hi`` of those that equal an earlier one."""
    texts = numbered.select("d", "text")
    # written, so that both sides of the join come straight from an exchange and a hot anchor can be split
    shared = scratch.write(anchor_rows(texts, length, gram, contexts=False).groupBy("h").agg(F.sum("n").alias("n")).where("n > 1").select("h"), "shared")
    own = scratch.write(anchor_rows(texts, length, gram, contexts=True).join(shared, "h"), "anchors")
    groups = own.groupBy("h", "c").agg(F.min(F.struct("d", "at", "own")).alias("first"), F.count(F.lit(1)).alias("n"))
    groups = scratch.write(groups, "groups")
    # all strings of a context that is not the first of its kind
    later = own.join(groups.where("n > 1").select("h", "c", "first"), ["h", "c"]).where(F.struct("d", "at", "own") > F.col("first"))
    whole = later.select("d", (F.col("at") - F.col("own").bitwiseAND(F.lit(0xFFFF))).cast("long").alias("lo"), (F.col("at") - F.shiftright("own", 16) + length).cast("long").alias("hi"))
    several = scratch.write(groups.groupBy("h").agg(F.count(F.lit(1)).alias("m")).where("m > 1"), "several")
    firsts = groups.join(several, "h").select("h", "m", "first.d", "first.at", "first.own")
    cut = texts.join(firsts.groupBy("d").agg(F.collect_list(F.struct("h", "m", "at", "own")).alias("a")), "d")

    def cutter(batches):
        import pyarrow as pa

        for b in batches:
            out: list[list] = [[] for _ in range(6)]
            for d, text, found in zip(*[b.column(c).to_pylist() for c in ("d", "text", "a")], strict=True):
                data = text.encode()
                for x in found:
                    near, far = x["own"] >> 16, x["own"] & 0xFFFF
                    for k, v in enumerate((x["h"], x["m"], d, x["at"], x["own"], data[x["at"] - far : x["at"] - near + length])):
                        out[k].append(v)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(out, kinds, strict=True)], names=["h", "m", "d", "at", "own", "ctx"])

    return scratch.write(cut.mapInArrow(lean(cutter, ROWS), "h long, m long, d long, at int, own int, ctx binary"), "contexts"), whole


def covered(numbered: DataFrame, scratch: Scratch, length: int = LENGTH, gram: int = GRAM, crowd: int = CROWD) -> DataFrame:
    """``d, lo, hi``: byte ranges of the strings that repeat an earlier one; ranges may overlap."""
    contexts, whole = _contexts(numbered, scratch, length, gram)
    few = _construct(_dealt(contexts.where(F.col("m") <= crowd).withColumnRenamed("h", "g")), length, gram).select("d", "lo", "hi")
    part = F.pmod(F.xxhash64("d"), F.ceil(F.col("m") / min(FIRST_ROWS, crowd)))
    crowded = contexts.where(F.col("m") > crowd).withColumn("g", F.xxhash64("h", part))
    first = scratch.write(_construct(_dealt(crowded), length, gram, rest=True), "crowded")
    second = _construct(_dealt(_by_shared_bytes(first.where("ctx is not null"), length, gram)), length, gram).select("d", "lo", "hi")
    return whole.unionByName(few).unionByName(first.where("ctx is null").select("d", "lo", "hi")).unionByName(second)


def remove(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, crowd: int = CROWD, digest: bool = False, scratch: Scratch | None = None) -> DataFrame:
    """``doc_id, n_bytes, n_removed, n_spans`` and ``kept`` (bytes) or ``kept_sha256`` for each row."""
    if gram & (gram - 1) or gram > length or length > 30_000:
        raise ValueError("gram must be a power of two, at most length")
    scratch = scratch or Scratch(docs.sparkSession, "substrings")
    numbered = _numbered(docs, scratch)
    spans = covered(numbered, scratch, length, gram, crowd).distinct().groupBy("d").agg(F.sort_array(F.collect_list(F.struct("lo", "hi"))).alias("spans"))
    joined = numbered.join(spans.withColumnRenamed("d", "sd"), F.col("d") == F.col("sd"), "left").select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("spans.lo").alias("lo"), F.col("spans.hi").alias("hi"))
    last = "kept_sha256 string" if digest else "kept binary"

    def work(batches):
        import pyarrow as pa

        for b in batches:
            size, gone, runs, kept = [], [], [], []
            for text, lo, hi in zip(*[b.column(c).to_pylist() for c in ("text", "lo", "hi")], strict=True):
                data = text.encode()
                parts, at, cut, n = [], 0, 0, 0
                for x, y in zip(lo or (), hi or (), strict=True):
                    if x > at or (x == at == 0 and n == 0):
                        parts.append(data[at:x])
                        n += 1
                    if y > at:
                        cut += y - max(x, at)
                        at = y
                parts.append(data[at:])
                rest = b"".join(parts)
                size.append(len(data))
                gone.append(cut)
                runs.append(n)
                kept.append(hashlib.sha256(rest).hexdigest() if digest else rest)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(size, pa.int64()), pa.array(gone, pa.int64()), pa.array(runs, pa.int64()), pa.array(kept, pa.string() if digest else pa.binary())], names=["doc_id", "n_bytes", "n_removed", "n_spans", last.split()[0]])

    return joined.mapInArrow(lean(work, ROWS), f"doc_id long, n_bytes long, n_removed long, n_spans long, {last}")
