"""Near-duplicate groups of documents: wide SimHash fingerprints at anchor points, settled by exact similarity.

Two documents are linked if their sets of ``shingle``-word runs have a Jaccard similarity
of ``min_similarity`` or more; groups are the components of the links.

Most links are found cheaply by a fingerprint of ``WORDS`` words of 32 bits over the document's words, long
words weighing more (they tell texts apart, short ones hardly do). Each word is dealt to
the anchors of the covering code as in :mod:`ccspark.llm.simhash`, so two documents meet
if some word of theirs differs by one bit or less. Documents with the same
word sequence are one from the start.

Where documents meet, each that is at home is first paired with the member nearest to the anchor's
majority fingerprint and, unless the anchor is crowded, with its two nearest members;
these pairs are linear in the members and are settled by exact similarity. The components found so far then leave
only pairs between different components within ``max_bits``, which are settled in
a second round: of anchors with many members where they meet, so that only links leave
the tasks, of others as pairs. Both rounds save work and need not find all: an anchor that a
large share of the documents has is split by a hash.

Fingerprints miss edits of whole blocks, and splits lose pairs, so a third round finds every link that is left between
different components. Two sets with Jaccard similarity ``t`` share ``k`` of the first ``n - ceil(t n) + k`` of
their ``n`` runs in any one order, here the rarer ones of a sample first. Where such runs meet, a pair is passed over only if
it shares fewer, or if
its sizes, its places in the order or the differing bits of its parities (each run flips one bit, so at most
as many bits differ as runs do) exclude the similarity. Nothing is capped.

Null or empty text: equal to other empty texts only. Texts shorter than a shingle are
their own shingle. Repeated rows are in one group; rows of equal doc_id and different text are documents
of their own, each in its group. An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.llm.common import dense_ids, lean, text_of
from ccspark.llm.simhash import HOT, _expand, _runs, anchors, hot_anchors, is_hot
from ccspark.plans.runner import connected_components
from ccspark.plans.store import Scratch

WORDS = 8
#: Texts that a task takes at once.
ROWS = 512
#: Parts of an anchor that would burden one task.
PARTS = 256
NEAREST = 2
#: Members of an anchor above which the first round pairs them with the middle one alone; the second round takes the rest.
CROWD = 1024
#: Members of an anchor above which the second round settles pairs where they meet, and below which it sends them.
SMALL = 32
MAX_BITS = 40
#: Bits of the parity of a set of word runs.
PARITY = 1024
#: Documents read to tell frequent word runs from rare ones, and how many of these are told to the tasks.
SAMPLE, FREQUENT = 8192, 1 << 17


def _spread(digests: bytes, n: int) -> np.ndarray:
    """From 128-bit digests ``WORDS * 32`` bits each, as bytes: the two halves, mixed on."""
    half = np.frombuffer(digests, "<u8").reshape(n, 2)
    out = np.empty((n, WORDS // 2), np.uint64)
    x, y = half[:, 0].copy(), half[:, 1].copy()
    with np.errstate(over="ignore"):
        for i in range(0, WORDS // 2, 2):
            out[:, i], out[:, i + 1] = x, y
            x, y = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) + y, (y ^ (y >> np.uint64(32))) * np.uint64(0x94D049BB133111EB) + x
    return out.view(np.uint8).reshape(n, WORDS * 4)


def _digests(words: list[bytes]) -> bytes:
    import xxhash

    return b"".join(map(xxhash.xxh3_128_digest, words))


def wide_fingerprint(words: list[bytes], digests: bytes | None = None) -> bytes:
    bits = np.unpackbits(_spread(_digests(words) if digests is None else digests, len(words)), axis=1, bitorder="little")
    weight = np.maximum(np.fromiter(map(len, words), np.float32, len(words)) - 3, 0)
    if not weight.any():
        weight += 1
    return np.packbits(2 * (weight @ bits.astype(np.float32)) > weight.sum(), bitorder="little").tobytes()


def run_hashes(digests: bytes, shingle: int) -> np.ndarray:
    """The distinct word runs of a text from its words' digests, as sorted hashes; a text shorter than a run is one."""
    word = np.frombuffer(digests, "<u8")[::2]
    span = min(shingle, len(word))
    out = np.zeros(len(word) - span + 1, np.uint64)
    with np.errstate(over="ignore"):
        for i in range(span):
            out = (out ^ (out >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15) + word[i : len(word) - span + 1 + i]
        out = (out ^ (out >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return np.unique(out ^ (out >> np.uint64(32)))


def parity(runs: np.ndarray) -> bytes:
    return np.packbits(np.bincount((runs >> np.uint64(16)) % np.uint64(PARITY), minlength=PARITY) & 1).tobytes()


def least_shared(size, min_similarity: float):
    """First runs that a set of this size shares with any similar one: one in forty of its runs and one more, if so many are alike."""
    return np.minimum(1 + size // 40, np.ceil(min_similarity * size - 1e-9).astype(np.int64))


def prefix(runs: np.ndarray, frequent: np.ndarray, times: np.ndarray, min_similarity: float) -> np.ndarray:
    """The first runs in the common order (rarer ones first), of which two similar sets share the lesser of their ``least_shared``."""
    at = np.minimum(np.searchsorted(frequent, runs), len(frequent) - 1)
    count = np.where(frequent[at] == runs, times[at], 0)
    n = len(runs)
    return runs[np.lexsort((runs, count))][: n - int(np.ceil(min_similarity * n - 1e-9)) + int(least_shared(n, min_similarity))]


def frequent_runs(docs: DataFrame, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Word runs that come more than once in a sample of the documents, sorted, and how often. They only set an order."""

    def work(batches):
        import pyarrow as pa

        for b in batches:
            runs = [run_hashes(_digests(w), shingle) for w in (t.encode().lower().split() for t in b.column("text").to_pylist()) if w]
            if runs:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(runs).view(np.int64))], names=["run"])

    every = max(1, docs.count() // SAMPLE)
    some = docs.select(text_of().alias("text")).where(F.pmod(F.xxhash64("text"), F.lit(every)) == 0).mapInArrow(lean(work, ROWS), "run long")
    got = some.groupBy("run").agg(F.count("*").alias("n")).where("n > 1").orderBy(F.desc("n"), "run").limit(FREQUENT).toArrow()
    runs, times = got.column("run").to_numpy().view(np.uint64), got.column("n").to_numpy()
    order = np.argsort(runs)
    return np.r_[runs[order], np.uint64(0xFFFFFFFFFFFFFFFF)], np.r_[times[order], 0]


def sketches(docs: DataFrame, shingle: int = 5, min_similarity: float = 0.8) -> DataFrame:
    """``doc_id, h, k1, k2, fp, runs, size, parity``: hash of the text, digest of its word sequence, the wide fingerprint,
    the first word runs in the common order, their whole number and parity (null without words)."""
    sent = docs.sparkSession.sparkContext.broadcast(frequent_runs(docs, shingle))

    def work(batches):
        import pyarrow as pa
        import xxhash

        for b in batches:
            k1, k2, rest = [], [], []
            for text in b.column("text").to_pylist():
                words = text.encode().lower().split()
                k = xxhash.xxh3_128_intdigest(b" ".join(words))
                k1.append((k >> 64) - (1 << 63))
                k2.append((k & ((1 << 64) - 1)) - (1 << 63))
                if words:
                    digests = _digests(words)
                    runs = run_hashes(digests, shingle)
                    rest.append((wide_fingerprint(words, digests), prefix(runs, *sent.value, min_similarity).view(np.int64), len(runs), parity(runs)))
                else:
                    rest.append((None,) * 4)
            columns = [pa.array([r[i] for r in rest], t) for i, t in enumerate((pa.binary(), pa.list_(pa.int64()), pa.int32(), pa.binary()))]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("h"), pa.array(k1, pa.int64()), pa.array(k2, pa.int64()), *columns], names=["doc_id", "h", "k1", "k2", "fp", "runs", "size", "parity"])

    schema = "doc_id long, h long, k1 long, k2 long, fp binary, runs array<long>, size int, parity binary"
    return _named(docs).mapInArrow(lean(work, ROWS), schema)


def _named(docs: DataFrame) -> DataFrame:
    """``doc_id, text, h``: h tells rows of equal doc_id apart."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"), F.xxhash64(text_of()).alias("h"))


def _words_of(batch) -> np.ndarray:
    return np.frombuffer(b"".join(batch.column("fp").to_pylist()), "<u4").reshape(-1, WORDS)


def _word_values(reps: DataFrame) -> DataFrame:
    """``value, n``: each word's values with its number above them, counted in each batch."""

    def work(batches):
        import pyarrow as pa

        for b in batches:
            if b.num_rows:
                value, n = np.unique(_words_of(b).astype(np.int64) | np.arange(WORDS)[None, :] << 32, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(value), pa.array(n)], names=["value", "n"])

    return reps.select("fp").mapInArrow(lean(work), "value long, n long")


def meetings(reps: DataFrame, hot: int = HOT) -> DataFrame:
    """``anchor, rep, home`` for anchors where several documents meet, one of them at home.

    Anchors of values that over ``hot`` documents share are split by a hash of the document, into as many as ``PARTS``.
    """
    sent = reps.sparkSession.sparkContext.broadcast(hot_anchors(_word_values(reps), reps.count(), hot))

    def deal(batches):
        import pyarrow as pa

        for b in batches:
            if not b.num_rows:
                continue
            fp = _words_of(b)
            rep = b.column("rep")
            mixed = rep.to_numpy().astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)
            for w in range(WORDS):
                part = ((mixed >> np.uint64(w)) % np.uint64(PARTS)).astype(np.int64) + 1 << 40
                for rows, code, home in anchors(np.ascontiguousarray(fp[:, w])):
                    if len(rows):
                        at = code.astype(np.int64) | np.int64(w << 32)
                        at = np.where(is_hot(sent.value, at), at | part[rows], at)
                        yield pa.RecordBatch.from_arrays([pa.array(at), rep.take(pa.array(rows)), pa.array(np.full(len(rows), home))], names=["anchor", "rep", "home"])

    def meet(batches):
        import pyarrow as pa

        for anchor, rep, home in _runs(batches, 3):
            begin = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
            size = np.diff(np.r_[begin, len(anchor)])
            some = (size > 1) & np.logical_or.reduceat(home.astype(bool), begin)
            keep = np.repeat(some, size)
            if keep.any():
                yield pa.RecordBatch.from_arrays([pa.array(anchor[keep]), pa.array(rep[keep]), pa.array(home.astype(bool)[keep])], names=["anchor", "rep", "home"])

    schema = "anchor long, rep long, home boolean"
    dealt = reps.select("rep", "fp").mapInArrow(lean(deal), schema)
    return dealt.repartition("anchor").sortWithinPartitions("anchor").select("anchor", "rep", "home").mapInArrow(lean(meet), schema)


def _bits_between(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x ^ y).sum(1)


def _dealt(met: DataFrame, *columns: str) -> DataFrame:
    return met.repartition("anchor").sortWithinPartitions("anchor").select("anchor", *columns)


def first_pairs(met: DataFrame, max_bits: int) -> DataFrame:
    """``a, b`` (a < b) from meetings with fingerprints (``anchor, rep, home, fp``): a few for each document at home."""

    def work(batches):
        import pyarrow as pa

        for anchor, rep, home, fp in _runs(batches, 4, 100_000):
            home = home.astype(bool)
            words = np.frombuffer(b"".join(fp), "<u8").reshape(-1, WORDS // 2)
            begin = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
            size = np.diff(np.r_[begin, len(anchor)])
            left, right = [], []
            for s, n in zip(begin[size > 2].tolist(), size[size > 2].tolist(), strict=True):
                bits = np.unpackbits(words[s : s + n].view(np.uint8), axis=1)
                middle = np.packbits(2 * bits.sum(0, dtype=np.int64) > n).view("<u8")
                pivot = s + int(np.bitwise_count(words[s : s + n] ^ middle).sum(1).argmin())
                x = s + np.flatnonzero(home[s : s + n])  # each document is at home once for each word
                x = x[_bits_between(words[x], words[pivot][None, :]) <= max_bits]
                left.append(x)
                right.append(np.full(len(x), pivot))
            rows = np.flatnonzero(np.repeat(size <= CROWD, size))
            for x, y in _expand(anchor[rows], home[rows]) if len(rows) else ():
                x, y = rows[x], rows[y]
                d = _bits_between(words[x], words[y])
                keep = (x != y) & (d <= max_bits)
                x, y, d = x[keep], y[keep], d[keep]
                order = np.lexsort((d, x))
                x, y = x[order], y[order]
                start = np.flatnonzero(np.r_[True, x[1:] != x[:-1]]) if len(x) else np.zeros(0, np.int64)
                nth = np.arange(len(x)) - np.repeat(start, np.diff(np.r_[start, len(x)]))
                left.append(x[nth < NEAREST])
                right.append(y[nth < NEAREST])
            if left:
                x, y = rep[np.concatenate(left)], rep[np.concatenate(right)]
                both = np.unique(np.stack([np.minimum(x, y), np.maximum(x, y)], 1)[x != y], axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(both[:, 0].copy()), pa.array(both[:, 1].copy())], names=["a", "b"])

    return _dealt(met, "rep", "home", "fp").mapInArrow(lean(work), "a long, b long").distinct()


def second_round(met: DataFrame, max_bits: int) -> DataFrame:
    """Pairs of different components (``kind`` 0: a, b), or for anchors of over ``SMALL`` members those members that are
    in such a pair (``kind`` 1: a the anchor, b the document, ``home``): as many rows as members, not as pairs."""

    def work(batches):
        import pyarrow as pa

        for anchor, rep, home, fp, comp in _runs(batches, 5, 100_000):
            home = home.astype(bool)
            words = np.frombuffer(b"".join(fp), "<u8").reshape(-1, WORDS // 2)
            begin = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
            size = np.repeat(np.diff(np.r_[begin, len(anchor)]), np.diff(np.r_[begin, len(anchor)]))
            part = np.zeros(len(anchor), bool)
            pairs = []
            for x, y in _expand(anchor, home):
                keep = comp[x] != comp[y]
                x, y = x[keep], y[keep]
                keep = _bits_between(words[x], words[y]) <= max_bits
                x, y = x[keep], y[keep]
                crowd = size[x] > SMALL
                part[x[crowd]] = part[y[crowd]] = True
                pairs.append(np.stack([np.minimum(rep[x], rep[y]), np.maximum(rep[x], rep[y])], 1)[~crowd])
            both = np.unique(np.concatenate(pairs), axis=0) if pairs else np.zeros((0, 2), np.int64)
            at = np.flatnonzero(part)
            kind = np.r_[np.zeros(len(both), np.int32), np.ones(len(at), np.int32)]
            if len(kind):
                yield pa.RecordBatch.from_arrays([pa.array(kind), pa.array(np.r_[both[:, 0], anchor[at]]), pa.array(np.r_[both[:, 1], rep[at]]), pa.array(np.r_[np.zeros(len(both), bool), home[at]])], names=["kind", "a", "b", "home"])

    return _dealt(met, "rep", "home", "fp", "comp").mapInArrow(lean(work), "kind int, a long, b long, home boolean")


def gram_rows(texts: DataFrame, shingle: int) -> DataFrame:
    """``rep, grams``: hashes of the distinct word runs of each text."""

    def work(batches):
        import pyarrow as pa

        for b in batches:
            grams = [[hash_ - (1 << 63) for hash_ in _gram_hashes(t, shingle)] for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("rep"), pa.array(grams, pa.list_(pa.int64()))], names=["rep", "grams"])

    return texts.select("rep", "text").mapInArrow(lean(work, ROWS), "rep long, grams array<long>")


def _gram_hashes(text: str, shingle: int) -> set[int]:
    import xxhash

    return {xxhash.xxh3_64_intdigest(b" ".join(g)) for g in shingle_set(text, shingle)}


def links_between(met: DataFrame, max_bits: int, min_similarity: float) -> DataFrame:
    """``src, dst``: links between different components, from meetings with ``comp`` and ``grams`` besides.

    All pairs of different components are settled where they meet, by the exact similarity of their word runs; only
    links leave the task, at most one less than the components of an anchor.
    """

    def settle(words, home, comp, grams) -> Iterator[tuple[int, int]]:
        up: dict[int, int] = {}

        def root(x):
            while up.setdefault(x, x) != x:
                x = up[x]
            return x

        sets = [set(g.tolist()) for g in grams]
        size = np.array([len(g) for g in sets])
        for x in np.flatnonzero(home).tolist():
            near = np.flatnonzero((comp != comp[x]) & (size >= min_similarity * size[x]) & (min_similarity * size <= size[x]))
            near = near[_bits_between(words[near], words[x][None, :]) <= max_bits]
            for y in near.tolist():
                a, b = root(comp[x]), root(comp[y])
                if a != b:
                    common = len(sets[x] & sets[y])
                    if common >= min_similarity * (len(sets[x]) + len(sets[y]) - common):
                        up[b] = a
                        yield x, y

    def work(batches):
        import pyarrow as pa

        for anchor, rep, home, fp, comp, grams in _runs(batches, 6, 20_000):
            words = np.frombuffer(b"".join(fp), "<u8").reshape(-1, WORDS // 2)
            begin = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
            out = []
            for s, e in zip(begin.tolist(), np.r_[begin[1:], len(anchor)].tolist(), strict=True):
                out += [(int(rep[s + x]), int(rep[s + y])) for x, y in settle(words[s:e], home[s:e].astype(bool), comp[s:e], grams[s:e])]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], pa.int64()) for i in (0, 1)], names=["src", "dst"])

    return _dealt(met, "rep", "home", "fp", "comp", "grams").mapInArrow(lean(work), "src long, dst long")


def _may_link(x, y, comp: np.ndarray, place: np.ndarray, size: np.ndarray, min_similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Of pairs of rows that share a run, those of different components that sizes and places in the order allow."""
    keep = (x < y) & (comp[x] != comp[y])
    x, y = x[keep], y[keep]
    most = np.minimum(np.minimum(place[x], place[y]) + np.minimum(size[x] - place[x], size[y] - place[y]), np.minimum(size[x], size[y]))
    keep = most * (1 + min_similarity) >= min_similarity * (size[x] + size[y]) - 1e-6
    return x[keep], y[keep]


def shared_runs(reps: DataFrame, min_similarity: float) -> DataFrame:
    """``anchor, rep, comp, at, size``: where first runs of different components (``rep, comp, runs, size``) meet.

    Of a run with up to ``SMALL`` documents only those in a pair that may be a link.
    """

    def deal(batches):
        import pyarrow as pa

        for b in batches:
            runs = b.column("runs")
            n = np.diff(runs.offsets.to_numpy())
            rows = np.repeat(np.arange(len(n)), n)
            at = np.arange(len(rows)) - np.repeat(np.cumsum(n) - n, n)
            held = at.astype(np.int64) << 32 | b.column("size").to_numpy()[rows]
            yield pa.RecordBatch.from_arrays([runs.flatten(), b.column("rep").take(pa.array(rows)), b.column("comp").take(pa.array(rows)), pa.array(held)], names=["anchor", "rep", "comp", "held"])

    def meet(batches):
        import pyarrow as pa

        for anchor, rep, comp, held in _runs(batches, 4):
            begin = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
            n = np.diff(np.r_[begin, len(anchor)])
            open_ = np.minimum.reduceat(comp, begin) != np.maximum.reduceat(comp, begin)
            keep = np.repeat(open_ & (n > SMALL), n)
            few = np.flatnonzero(np.repeat(open_ & (n <= SMALL), n))
            for x, y in _expand(anchor[few], np.ones(len(few), bool)) if len(few) else ():
                x, y = _may_link(few[x], few[y], comp, held >> 32, held & 0xFFFFFFFF, min_similarity)
                keep[x] = keep[y] = True
            if keep.any():
                yield pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in (anchor, rep, comp, held >> 32, held & 0xFFFFFFFF)], names=["anchor", "rep", "comp", "at", "size"])

    dealt = reps.select("rep", "comp", "runs", "size").mapInArrow(lean(deal), "anchor long, rep long, comp long, held long")
    dealt = dealt.repartition("anchor").sortWithinPartitions("anchor").select("anchor", "rep", "comp", "held")
    return dealt.mapInArrow(lean(meet), "anchor long, rep long, comp long, at long, size long")


def third_round(shared: DataFrame, min_similarity: float) -> DataFrame:
    """``a, b`` (a < b): all pairs of different components that share enough first runs and may be links. shared: with ``parity``."""

    def work(batches):
        import pyarrow as pa

        for anchor, rep, comp, at, size, bits in _runs(batches, 6, 100_000):
            bits = np.frombuffer(b"".join(bits), "<u8").reshape(-1, PARITY // 64)
            found = [np.zeros((0, 3), np.int64)]
            for x, y in _expand(anchor, np.ones(len(anchor), bool)):
                x, y = _may_link(x, y, comp, at, size, min_similarity)
                for i in range(0, len(x), 1 << 18):
                    u, v = x[i : i + (1 << 18)], y[i : i + (1 << 18)]
                    keep = _bits_between(bits[u], bits[v]) * (1 + min_similarity) <= (1 - min_similarity) * (size[u] + size[v]) + 1e-6
                    u, v = u[keep], v[keep]
                    need = least_shared(np.minimum(size[u], size[v]), min_similarity)
                    found.append(np.stack([np.minimum(rep[u], rep[v]), np.maximum(rep[u], rep[v]), need], 1))
            both, n = np.unique(np.concatenate(found), axis=0, return_counts=True)
            if len(both):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (both[:, 0].copy(), both[:, 1].copy(), both[:, 2].copy(), n)], names=["a", "b", "need", "n"])

    met = _dealt(shared, "rep", "comp", "at", "size", "parity").mapInArrow(lean(work), "a long, b long, need long, n long")
    return met.groupBy("a", "b", "need").agg(F.sum("n").alias("n")).where("n >= need").select("a", "b")


def shingle_set(text: str, shingle: int) -> set:
    words = text.encode().lower().split()
    return set(zip(*[words[i:] for i in range(shingle)], strict=False)) if len(words) >= shingle else {tuple(words)}


def settled(pairs: DataFrame, texts: DataFrame, shingle: int, min_similarity: float) -> DataFrame:
    """``src, dst`` of the pairs whose exact similarity suffices. texts: ``rep, text``."""
    a = texts.select(F.col("rep").alias("a"), F.col("text").alias("text_a"))
    b = texts.select(F.col("rep").alias("b"), F.col("text").alias("text_b"))
    both = pairs.join(a, "a").join(b, "b")

    def work(batches):
        import pyarrow as pa

        for batch in batches:
            keep, last, own = [], None, None
            for x, y in zip(batch.column("text_a").to_pylist(), batch.column("text_b").to_pylist(), strict=True):
                if x != last:
                    last, own = x, shingle_set(x, shingle)
                other = shingle_set(y, shingle)
                common = len(own & other)
                keep.append(common >= min_similarity * (len(own) + len(other) - common))
            mask = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(mask), batch.column("b").filter(mask)], names=["src", "dst"])

    return both.select("a", "b", "text_a", "text_b").mapInArrow(lean(work, ROWS), "src long, dst long")


def _kinds(marks: DataFrame, scratch: Scratch) -> DataFrame:
    """One row for each word sequence: ``rep`` (its number), ``first`` (its first row: doc_id and h) and the sketch.

    The number is the least doc_id, or where some doc_id has several texts, the rank of (doc_id, digest).
    """
    sketch = [F.first(c).alias(c) for c in ("fp", "runs", "size", "parity")]
    kinds = scratch.write(marks.groupBy("k1", "k2").agg(F.min(F.struct("doc_id", "h")).alias("first"), *sketch), "kinds")
    if kinds.groupBy("first.doc_id").count().where("count > 1").limit(1).count():
        ranked = dense_ids(kinds.select(F.col("first.doc_id").alias("low"), "k1", "k2"), ["low", "k1", "k2"], scratch, "ranks")
        return scratch.write(kinds.join(ranked.select("k1", "k2", F.col("id").alias("rep")), ["k1", "k2"]), "numbered")
    return kinds.withColumn("rep", F.col("first.doc_id"))


def _components(known: DataFrame, shingle: int, min_similarity: float, max_bits: int, scratch: Scratch, hot: int) -> tuple[DataFrame, DataFrame]:
    """The sketches, and for each word sequence the first row of its group: ``k1, k2, first``."""
    spark = known.sparkSession
    marks = scratch.write(sketches(known, shingle, min_similarity), "sketches")
    kinds = _kinds(marks, scratch)
    some = kinds.where("fp is not null")
    reps = some.select("rep", "fp")
    links: list[DataFrame] = []

    def texts_of(wanted: DataFrame, table: str) -> DataFrame:
        """``rep, text`` of the wanted representatives (``rep``)."""
        own = kinds.join(wanted, "rep", "left_semi").select("rep", F.col("first.doc_id").alias("d"), F.col("first.h").alias("g"))
        rows = _named(known).join(own, (F.col("doc_id") == F.col("d")) & (F.col("h") == F.col("g")))
        return scratch.write(rows.select("rep", "text").dropDuplicates(["rep"]), table)

    def linked(found: DataFrame, table: str) -> DataFrame:
        """Adds links; ``rep, c`` for all documents that have some by now."""
        links.append(scratch.write(found, table))
        run = connected_components(reduce(DataFrame.unionByName, links), finish_edges=200_000, scratch=Scratch(spark, "near-dups-cc"))
        out = scratch.write(run.assignment.select(F.col("vertex").alias("rep"), F.col("component").alias("c")), f"components-{len(links)}")
        run.scratch.drop()
        return out

    met = scratch.write(meetings(reps, hot), "meetings")
    texts = texts_of(met.select("rep").distinct(), "texts")
    held = met.join(reps, "rep")
    pairs = scratch.write(first_pairs(held, max_bits), "pairs")
    named = linked(settled(pairs, texts, shingle, min_similarity), "links-1")
    again = scratch.write(held.join(named, "rep", "left").select("anchor", "rep", "home", "fp", F.coalesce("c", "rep").alias("comp")), "again")
    scratch.drop("meetings")
    open_ = again.groupBy("anchor").agg((F.min("comp") != F.max("comp")).alias("open")).where("open").select("anchor")
    rest = scratch.write(second_round(again.join(open_, "anchor", "left_semi"), max_bits), "rest")
    scratch.drop("again")
    few = rest.where("kind = 0").select("a", "b").distinct().join(pairs, ["a", "b"], "left_anti")
    many = rest.where("kind = 1").select(F.col("a").alias("anchor"), F.col("b").alias("rep"), "home")
    grams = gram_rows(texts.join(many.select("rep").distinct(), "rep", "left_semi"), shingle)
    known_ = reps.join(named, "rep", "left").select("rep", "fp", F.coalesce("c", "rep").alias("comp"))
    named = linked(settled(few, texts, shingle, min_similarity).unionByName(links_between(many.join(known_, "rep").join(grams, "rep"), max_bits, min_similarity)), "links-2")
    for table in ("rest", "pairs", "texts"):
        scratch.drop(table)
    comps = some.join(named, "rep", "left").withColumn("comp", F.coalesce("c", "rep"))
    shared = scratch.write(shared_runs(comps, min_similarity), "shared")
    pairs = scratch.write(third_round(shared.join(kinds.select("rep", "parity"), "rep"), min_similarity), "pairs-3")
    scratch.drop("shared")
    texts = texts_of(pairs.select(F.explode(F.array("a", "b")).alias("rep")).distinct(), "texts-3")
    named = linked(settled(pairs, texts, shingle, min_similarity), "links-3")
    scratch.drop("texts-3")
    grouped = kinds.join(named, "rep", "left").select("k1", "k2", "first", F.coalesce("c", "rep").alias("c"))
    firsts = grouped.groupBy("c").agg(F.min("first").alias("of"))
    return marks, grouped.join(firsts, "c").select("k1", "k2", F.col("of").alias("first"))


def groups(docs: DataFrame, shingle: int = 5, min_similarity: float = 0.8, max_bits: int = MAX_BITS, scratch: Scratch | None = None, hot: int = HOT) -> DataFrame:
    """``doc_id, component_id`` for each row: the least doc_id of its group. Rows with a null doc_id have none."""
    scratch = scratch or Scratch(docs.sparkSession, "near-dups")
    marks, firsts = _components(docs.where("doc_id is not null"), shingle, min_similarity, max_bits, scratch, hot)
    return marks.join(firsts, ["k1", "k2"]).select("doc_id", F.col("first.doc_id").alias("component_id"))


def keep_one(docs: DataFrame, shingle: int = 5, min_similarity: float = 0.8, max_bits: int = MAX_BITS, scratch: Scratch | None = None, hot: int = HOT) -> DataFrame:
    """The documents that are the first of their group, with all their columns; rows with a null doc_id stay.

    Of repeated rows (equal doc_id and text) one stays.
    """
    scratch = scratch or Scratch(docs.sparkSession, "near-dups")
    known = docs.where("doc_id is not null")
    _, firsts = _components(known, shingle, min_similarity, max_bits, scratch, hot)
    kept = firsts.select(F.col("first.doc_id").alias("_kept"), F.col("first.h").alias("_kept_h")).distinct()
    own = known.withColumn("_own_h", F.xxhash64(text_of()))
    first = own.join(kept, (own["doc_id"] == F.col("_kept")) & (F.col("_own_h") == F.col("_kept_h")), "left_semi").dropDuplicates(["doc_id", "_own_h"])
    return first.drop("_own_h").unionByName(docs.where("doc_id is null"))
