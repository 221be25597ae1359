"""LM scoring by partial matching over bytes, pretrained or adaptive, beside a word-count base.

The context trie is a table: a node is a context of up to ``order`` bytes, its children
are the symbols counted after it; the parent of a context is its own end. Texts are
lower-cased (A-Z), preceded by ``order`` zero bytes and followed by one end symbol, so
that a score is the probability of the whole text. A context with n counts of d symbols
gives a symbol counted c times (2c - 1) / 2n and the escape d / 2n. After an escape the
symbols of the longer context are excluded: weights and kinds of the shorter one are taken
without them. As every symbol of a context also stands in its parent, the excluded counts
depend on the two contexts alone and are tabled; below order zero the symbols that never
came are equally likely.

Counting: each task counts its n-grams with numpy and sends partial counts; shorter
orders are sums of the longest. Longer contexts fall into ``BUCKETS`` buckets by a mix of
their last two bytes (three, where a bucket of two would be too large), so that all longer
orders of a position lie in one bucket; the shorter orders are bounded by the alphabet.
Scoring sends as many buckets to the tasks as ``broadcast_bytes`` allow. Each such set is
one pass over the texts, whose partial sums are written and added. The counts of a pass
come to the driver in jobs of ``COLLECT`` rows. Word counts go with the first passes. A single bucket of three bytes over the
bound is refused, with the size that it needs.

Null or empty text: only the end. A null doc_id is never held out. Repeated rows are
scored each and learnt from as often. An empty table gives no rows; with nothing to learn
from, all symbols are equally likely.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ccspark.llm.common import lean, release, text_of
from ccspark.plans.store import Scratch

END, SYMBOLS = 255, 256
ORDER = 5
#: Buckets of the longer contexts and of the word counts; those that fit are sent at once.
BUCKETS = 4096
BROADCAST_BYTES = 160 << 20
#: What a counted n-gram and a word take in a task; rows that one job brings to the driver; texts that a task takes at once.
GRAM_BYTES, WORD_BYTES, COLLECT, ROWS = 64, 24, 1 << 20, 512
#: Multiplier of the buckets' mix, whose product with three bytes fits a long, and the shift that takes its middle.
_MIX, _SHIFT = 2654435761, 20
_MULT = np.uint64(0x9E3779B97F4A7C15)


#: The model that a worker process holds, by the broadcast that it was built from.
_models: dict[int, tuple] = {}


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 7 == 2, F.lit(False))


def _bytes_of(texts: list, order: int) -> tuple[np.ndarray, np.ndarray]:
    """One buffer of all texts, each after ``order`` zero bytes and before the end symbol; and where each begins."""
    pad, end = b"\0" * order, bytes([END])
    parts = [(t or "").encode().lower() for t in texts]
    buffer = np.frombuffer(b"".join(pad + p + end for p in parts), np.uint8)
    size = np.array([len(p) + 1 for p in parts], np.int64)
    return buffer, np.cumsum(size + order) - size


def _positions(first: np.ndarray, total: int, order: int) -> np.ndarray:
    """Marks the bytes that are scored (not the padding)."""
    keep = np.ones(total, bool)
    for i in range(order):
        keep[first - 1 - i] = False
    return keep


def _grams(buffer: np.ndarray, order: int) -> np.ndarray:
    """For each place: its byte and the ``order`` bytes before it, as one integer."""
    key = np.zeros(len(buffer), np.uint64)
    for back in range(order, -1, -1):
        key <<= np.uint64(8)
        if back:
            key[back:] |= buffer[:-back].astype(np.uint64)
        else:
            key |= buffer.astype(np.uint64)
    return key


def _add(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, np.int64)
    return keys[first], np.add.reduceat(counts, first) if len(first) else counts


def _word_hashes(text: str | None) -> np.ndarray:
    import xxhash

    words = (text or "").encode().lower().split()
    return np.maximum(np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words)), np.uint64(1))


#: The hash of the end token: its name holds a space, as no word can.
def _end_hash() -> np.uint64:
    import xxhash

    return np.uint64(xxhash.xxh64_intdigest(b"end of text"))


def count_corpus(docs: DataFrame, order: int = ORDER, flush: int = 1 << 22) -> DataFrame:
    """``kind, key, n``: counts of n-grams (kind 0) and of word hashes (kind 1) over the rows. Partial counts leave each task."""

    def work(batches):
        import pyarrow as pa

        _models.clear()  # a worker that scored before makes room
        held = [(np.zeros(0, np.uint64), np.zeros(0, np.int64)) for _ in (0, 1)]
        waiting: list[list[np.ndarray]] = [[], []]
        size = 0

        def settle():
            nonlocal size
            for kind in (0, 1):
                if waiting[kind]:
                    k, c = np.unique(np.concatenate(waiting[kind]), return_counts=True)
                    held[kind] = _add(np.r_[held[kind][0], k], np.r_[held[kind][1], c])
                    waiting[kind].clear()
            size = 0

        def out():
            settle()
            for kind in (0, 1):
                k, c = held[kind]
                for i in range(0, len(k), 1 << 17):
                    part = slice(i, i + (1 << 17))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(k[part]), kind, np.int32)), pa.array(k[part].view(np.int64)), pa.array(c[part])], names=["kind", "key", "n"])
                held[kind] = (np.zeros(0, np.uint64), np.zeros(0, np.int64))

        for b in batches:
            texts = b.column(0).to_pylist()
            at = 0
            while at < len(texts):
                upto, chars = at, 0
                while upto < len(texts) and (upto == at or chars < flush // 4):
                    chars += len(texts[upto] or "")
                    upto += 1
                buffer, first = _bytes_of(texts[at:upto], order)
                waiting[0].append(_grams(buffer, order)[_positions(first, len(buffer), order)])
                waiting[1].append(np.concatenate([_word_hashes(t) for t in texts[at:upto]]))
                waiting[1].append(np.full(upto - at, _end_hash(), np.uint64))
                size += len(buffer)
                if size > flush:
                    settle()
                if len(held[0][0]) + len(held[1][0]) > 3_000_000:
                    yield from out()
                at = upto
        yield from out()

    partial = docs.select(text_of().alias("text")).mapInArrow(lean(work, ROWS), "kind int, key long, n long")
    return partial.groupBy("kind", "key").agg(F.sum("n").alias("n"))


class HashTable:
    """Open addressing over numpy arrays: unsigned 64-bit keys (never zero) to values of four bytes, three fifths full."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.size = max(16, int(len(keys) / 0.6))
        self.keys, self.values = np.zeros(self.size, np.uint64), np.zeros(self.size, values.dtype)
        for i in range(0, len(keys), 1 << 20):
            self._insert(keys[i : i + (1 << 20)], values[i : i + (1 << 20)])

    def _insert(self, keys: np.ndarray, values: np.ndarray) -> None:
        todo, slot = np.arange(len(keys)), self._slot(keys)
        while len(todo):
            free = self.keys[slot] == 0
            self.keys[slot[free]] = keys[todo[free]]
            won = self.keys[slot] == keys[todo]
            self.values[slot[won]] = values[todo[won]]
            todo, slot = todo[~won], slot[~won] + 1
            slot[slot == self.size] = 0

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((((keys * _MULT) >> np.uint64(32)) * np.uint64(self.size)) >> np.uint64(32)).astype(np.int64)

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each key is there, and its value."""
        slot = self._slot(keys)
        seen = self.keys[slot]
        found, value = seen == keys, self.values[slot]
        todo = np.flatnonzero(~found & (seen != 0))
        slot = slot[todo]
        while len(todo):
            slot += 1
            slot[slot == self.size] = 0
            seen = self.keys[slot]
            hit = seen == keys[todo]
            found[todo[hit]], value[todo[hit]] = True, self.values[slot[hit]]
            go = ~hit & (seen != 0)
            todo, slot = todo[go], slot[go]
        return found, value


def _key(ctx: np.ndarray, order: int) -> np.ndarray:
    """A key that is never zero and differs between orders."""
    return ctx | (np.uint64(order + 1) << np.uint64(56))


class Level:
    """All contexts of one order: for each (context, symbol) its log10 weight, for each context the log10 of its
    denominator and escape numerator, alone and of its parent without its own symbols."""

    def __init__(self, order: int, grams: np.ndarray, counts: np.ndarray, parent: Level | None):
        self.order, counts = order, 2 * counts - 1
        ctx = grams >> np.uint64(8)
        starts = np.flatnonzero(np.r_[True, ctx[1:] != ctx[:-1]]) if len(ctx) else np.zeros(0, np.int64)
        self.ctx, self.grams, self.counts = ctx[starts], grams, counts
        self.n = np.add.reduceat(counts, starts) if len(starts) else counts[:0]
        self.d = np.diff(np.r_[starts, len(ctx)])
        if parent is None:
            above_n, above_d, excluded = np.zeros(len(starts)), np.full(len(starts), SYMBOLS), np.zeros(len(starts))
        else:
            mask = np.uint64((1 << (8 * parent.order)) - 1)
            up = np.searchsorted(parent.ctx, self.ctx & mask) if parent.order else np.zeros(len(self.ctx), np.int64)
            above_n, above_d = parent.n[up], parent.d[up]
            own = np.searchsorted(parent.grams, grams & np.uint64((1 << (8 * (parent.order + 1))) - 1))
            excluded = np.add.reduceat(parent.counts[own], starts) if len(starts) else np.zeros(0)
        self.more = (above_d - self.d).astype(np.int64)
        rest = (above_n - excluded).astype(np.float64)
        with np.errstate(divide="ignore"):
            # four bytes each: a text's score keeps six digits
            self.log_self = np.log10((self.n + self.d).astype(np.float32))
            self.log_escape = np.log10(self.d.astype(np.float32)) - self.log_self
            self.log_above = np.log10(np.maximum(rest + self.more, 1)).astype(np.float32)
            self.log_above_escape = np.where(self.more > 0, np.log10(np.maximum(self.more, 1).astype(np.float32)) - self.log_above, np.float32(0))
        # below order zero: the symbols that never came, equally likely
        self.log_base = np.log10(np.maximum(SYMBOLS - self.d, 1).astype(np.float64)) if parent is None else None

    def index(self) -> None:
        """Builds the tables that scoring needs, and lets go of the rest."""
        if hasattr(self, "pairs"):
            return
        self.pairs = HashTable(_key(self.grams, 8 + self.order), np.log10(self.counts.astype(np.float32)))
        self.contexts = HashTable(_key(self.ctx, self.order), np.arange(len(self.ctx), dtype=np.int32))
        del self.grams, self.ctx, self.counts, self.n, self.d, self.more


def levels_of(longest: list[np.ndarray], order: int, least: int, parent: Level | None) -> list[Level]:
    """Levels ``least .. order`` from the longest n-grams and their counts; parent: the level below ``least``."""
    out = []
    grams, counts = longest
    longest.clear()
    for j in range(least, order + 1):
        sums = _add(grams & np.uint64((1 << (8 * (j + 1))) - 1), counts)
        if j == order:
            del grams, counts
        level = Level(j, *sums, parent)
        del sums
        if parent is not None and parent.order > 1:
            parent.index()
        out.append(parent := level)
    return out


def bucket_of(gram: np.ndarray, suffix: int) -> np.ndarray:
    """From the ``suffix`` bytes before the symbol; :func:`_bucket_column` is its like."""
    end = (gram >> np.uint64(8)) & np.uint64((1 << (8 * suffix)) - 1)
    return ((end * np.uint64(_MIX) >> np.uint64(_SHIFT)) & np.uint64(BUCKETS - 1)).astype(np.int64)


class Model:
    """The orders below ``suffix`` and those of the longer contexts whose buckets are held."""

    def __init__(self, order: int, suffix: int, low: tuple[np.ndarray, np.ndarray], held: np.ndarray, grams: list[np.ndarray]):
        """grams: n-grams and counts; the list is emptied, so that they go when the tables are built."""
        self.order, self.suffix, self.held = order, suffix, held
        self.low = levels_of(list(low), min(suffix - 1, order), 0, None)
        high = []
        if order >= suffix:
            high = levels_of(grams, order, suffix, self.low[-1])
            high[-1].index()
        for x in self.low:
            x.index()
        self.levels = self.low + high

    def log10(self, grams: np.ndarray) -> np.ndarray:
        """log10 probability of each n-gram's last byte after the rest; zero where another pass holds its bucket."""
        out = np.zeros(len(grams))
        rem = np.arange(len(grams))
        if not self.held.all():
            rem = np.flatnonzero(self.held[bucket_of(grams, self.suffix)])
        above = np.full(len(rem), -1, np.int64)
        longer: Level | None = None
        for level in reversed(self.levels):
            mask = np.uint64((1 << (8 * (level.order + 1))) - 1)
            g = grams[rem] & mask
            hit, weight = level.pairs.find(_key(g, 8 + level.order))
            known, ctx = level.contexts.find(_key(g >> np.uint64(8), level.order))
            fresh = above < 0
            bottom, gone = np.zeros(len(rem)), np.zeros(len(rem))
            a, b = known & fresh, known & ~fresh
            bottom[a], gone[a] = level.log_self[ctx[a]], level.log_escape[ctx[a]]
            if longer is not None:
                bottom[b], gone[b] = longer.log_above[above[b]], longer.log_above_escape[above[b]]
            out[rem[hit]] += weight[hit] - bottom[hit]
            miss = ~hit
            out[rem[miss]] += gone[miss]
            above = np.where(known, ctx, -1)[miss]
            rem, longer = rem[miss], level
        if len(rem):
            last = np.where(above >= 0, longer.log_base[np.maximum(above, 0)] if len(longer.log_base) else 0.0, math.log10(SYMBOLS))
            out[rem] -= last
        return out


def _bucket_column(suffix: int) -> Column:
    """The bucket of a counted key: of n-grams as :func:`bucket_of` has it, of words by their hash."""
    end = F.shiftrightunsigned("key", 8).bitwiseAND(F.lit((1 << (8 * suffix)) - 1))
    mixed = F.shiftrightunsigned(end * F.lit(_MIX), _SHIFT).bitwiseAND(F.lit(BUCKETS - 1))
    return F.when(F.col("kind") == 0, mixed).otherwise(F.pmod(F.shiftrightunsigned("key", 3), F.lit(BUCKETS))).cast("int")


class Trained:
    """Counts of a corpus, written once: ``kind, key, n``; and the bounded sums that every pass needs."""

    def __init__(self, docs: DataFrame, order: int = ORDER, scratch: Scratch | None = None):
        self.order = order
        self.scratch = scratch or Scratch(docs.sparkSession, "ppm")
        self.counts = self.scratch.write(count_corpus(docs, order), "counts")
        sums = self.counts.where("kind = 1").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("types")).first()
        self.tokens, self.types = sums["n"] or 0, sums["types"]

    def _sizes(self, suffix: int) -> np.ndarray:
        """Rows of each kind and bucket."""
        got = self.counts.groupBy("kind", _bucket_column(suffix).alias("b")).agg(F.count(F.lit(1)).alias("rows")).collect()
        out = np.zeros((2, BUCKETS), np.int64)
        for r in got:
            out[r["kind"], r["b"]] = r["rows"]
        return out

    def passes(self, broadcast_bytes: int) -> tuple[int, list[list[tuple[int, list[int]]]]]:
        """Bytes of context that tell buckets apart, and for each pass its slices (kind, buckets), one job each. Words come first."""
        for suffix in (2, 3):
            rows = self._sizes(suffix)
            need = np.stack([GRAM_BYTES * rows[0], WORD_BYTES * rows[1]])
            if need.max() <= broadcast_bytes:
                break
        else:
            raise ValueError(f"a bucket of contexts needs {need.max()} bytes in a task, over broadcast_bytes={broadcast_bytes}")
        out: list[list[tuple[int, list[int]]]] = [[]]
        room = broadcast_bytes
        for kind in (1, 0):
            left = 0
            for b in range(BUCKETS):
                if need[kind, b] > room:
                    out.append([])
                    room, left = broadcast_bytes, 0
                if not out[-1] or out[-1][-1][0] != kind or rows[kind, b] > left:
                    out[-1].append((kind, []))
                    left = COLLECT
                out[-1][-1][1].append(b)
                room -= need[kind, b]
                left -= rows[kind, b]
        return suffix, out

    def low(self, suffix: int) -> tuple[np.ndarray, np.ndarray]:
        """Counts of the shorter orders: their n-grams are ``suffix`` bytes, so the alphabet bounds them."""
        width = min(suffix, self.order + 1)
        got = self.counts.where("kind = 0").groupBy(F.col("key").bitwiseAND(F.lit((1 << (8 * width)) - 1)).alias("key")).agg(F.sum("n").alias("n")).toArrow()
        return got.column("key").to_numpy().view(np.uint64), got.column("n").to_numpy()

    def load(self, suffix: int, slices: list[tuple[int, list[int]]], low: tuple[np.ndarray, np.ndarray]) -> dict:
        """What a pass sends."""
        held = np.zeros(BUCKETS, bool)
        got: list[list[tuple[np.ndarray, np.ndarray]]] = [[(np.zeros(0, np.uint64), np.zeros(0, t))] for t in (np.int64, np.float64)]
        for kind, x in slices:
            if not kind:
                held[x] = True
            value = F.log10(F.col("n") + F.lit(1.0)) if kind else F.col("n")
            rows = self.counts.where((F.col("kind") == kind) & _bucket_column(suffix).between(x[0], x[-1])).select("key", value.alias("v")).toArrow()
            got[kind].append((rows.column(0).to_numpy().view(np.uint64), rows.column(1).to_numpy()))
        grams, (key, gain) = ([np.concatenate([x[i] for x in got[kind]]) for i in (0, 1)] for kind in (0, 1))
        order = np.argsort(key)
        return {"order": self.order, "suffix": suffix, "low": low, "held": held, "grams": grams, "words": (key[order], gain[order]), "first": slices[0][0] == 1}


def _model(sent) -> tuple[Model, dict]:
    """Built once in each worker process for each set of buckets; holds the broadcast, so that its id stays its own."""
    if id(sent) not in _models:
        _models.clear()
        v = sent.value
        _models[id(sent)] = (sent, Model(v["order"], v["suffix"], v["low"], v["held"], v.pop("grams")), {"words": v["words"] if len(v["words"][0]) or v["first"] else None, "order": v["order"]})
        # the counts are in the tables now; a worker that needs them again reads them from its disk
        del v
        sent.__dict__.pop("_value", None)
        release()
    return _models[id(sent)][1:]


def score_batch(model: Model, words: tuple[np.ndarray, np.ndarray] | None, texts: list, order: int) -> tuple[np.ndarray, ...]:
    """Per text: tokens, known tokens, their log10(count + 1), and the log10 probability that this pass adds.

    words: hashes and gains that this pass holds; None if it holds none and another counts the tokens.
    """
    buffer, first = _bytes_of(texts, order)
    keep = _positions(first, len(buffer), order)
    logs = np.zeros(len(buffer))
    at = np.flatnonzero(keep)
    grams = _grams(buffer, order)
    for i in range(0, len(at), 1 << 19):
        part = at[i : i + (1 << 19)]
        logs[part] = model.log10(grams[part])
    score = np.add.reduceat(logs, first)
    if words is None:
        return *(np.zeros(len(texts), t) for t in (np.int64, np.int64, np.float64)), score
    hashes = [_word_hashes(t) for t in texts]
    size = np.array([len(h) + 1 for h in hashes], np.int64)
    flat = np.concatenate([x for h in hashes for x in (h, np.array([_end_hash()], np.uint64))])
    values, back = np.unique(flat, return_inverse=True)
    spot = np.minimum(np.searchsorted(words[0], values), max(len(words[0]) - 1, 0))
    known = words[0][spot] == values if len(words[0]) else np.zeros(len(values), bool)
    gain = np.where(known, words[1][spot], 0.0) if len(words[0]) else np.zeros(len(values))
    begin = np.cumsum(size) - size
    return size, np.add.reduceat(known[back].astype(np.int64), begin), np.add.reduceat(gain[back], begin), score


def _slices(texts: list, chars: int = 1 << 21):
    at = 0
    while at < len(texts):
        upto, n = at, 0
        while upto < len(texts) and (upto == at or n < chars):
            n += len(texts[upto] or "")
            upto += 1
        yield at, upto
        at = upto


def score(docs: DataFrame, trained: Trained, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score`` for each row."""
    spark = docs.sparkSession
    suffix, passes = trained.passes(broadcast_bytes)
    low = trained.low(suffix)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"), F.xxhash64(text_of()).alias("h"))
    schema = "doc_id long, h long, n_tokens long, n_known long, gain double, score double"
    parts: list[DataFrame] = []
    for i, slices in enumerate(passes):
        sent = spark.sparkContext.broadcast(trained.load(suffix, slices, low))

        def work(batches, sent=sent):
            import pyarrow as pa

            model, rest = _model(sent)
            for b in batches:
                texts = b.column("text").to_pylist()
                got = [score_batch(model, rest["words"], texts[x:y], rest["order"]) for x, y in _slices(texts)]
                size, known, gain, logs = (np.concatenate(x) for x in zip(*got, strict=True)) if got else (np.zeros(0),) * 4
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id"), b.column("h"), pa.array(size.astype(np.int64)), pa.array(known.astype(np.int64)), pa.array(gain), pa.array(logs)],
                    names=["doc_id", "h", "n_tokens", "n_known", "gain", "score"],
                )

        part = rows.mapInArrow(lean(work, ROWS), schema)
        if len(passes) > 1:
            part = trained.scratch.write(part.withColumn("pass", F.lit(i)), f"pass-{i}")
            sent.unpersist()
        parts.append(part)
    if len(parts) == 1:
        out = parts[0]
    else:
        # repeated rows score alike, so one of them stands for all
        one = reduce(DataFrame.unionByName, parts).dropDuplicates(["pass", "doc_id", "h"])
        sums = one.groupBy(F.col("doc_id").alias("d"), F.col("h").alias("g")).agg(F.max("n_tokens").alias("n_tokens"), *[F.sum(c).alias(c) for c in ("n_known", "gain", "score")])
        keys = rows.select("doc_id", "h")
        out = keys.join(sums, keys["doc_id"].eqNullSafe(sums["d"]) & (keys["h"] == sums["g"]))
    bottom = math.log10(trained.tokens + trained.types + 1)
    base = F.col("gain") - F.col("n_tokens") * F.lit(bottom)
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "n_tokens", "n_known", F.lit(trained.tokens).cast("long").alias("train_tokens"), base.alias("base_score"), "score")


def score_corpus(docs: DataFrame, order: int = ORDER, scratch: Scratch | None = None, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Learn from the rows that aren't held out, score all."""
    train = docs.where(~held_out(F.col("doc_id")))
    return score(docs, Trained(train, order, scratch=scratch), broadcast_bytes)


class Trie:
    """The same model as a plain trie that can grow while it scores: for one text, or as the check of the tables."""

    def __init__(self, order: int = ORDER):
        self.order, self.nodes = order, {}

    def log10(self, context: bytes, symbol: int) -> float:
        excluded: frozenset = frozenset()
        total = 0.0
        for j in range(self.order, -1, -1):
            node = self.nodes.get(context[len(context) - j :])
            if not node:
                continue
            left = {s: c for s, c in node.items() if s not in excluded}
            if left:
                bottom = 2 * sum(left.values())
                if symbol in left:
                    return total + math.log10((2 * left[symbol] - 1) / bottom)
                total += math.log10(len(left) / bottom)
            excluded = excluded | node.keys()
        return total - math.log10(SYMBOLS - len(excluded))

    def learn(self, context: bytes, symbol: int) -> None:
        for j in range(self.order + 1):
            node = self.nodes.setdefault(context[len(context) - j :], {})
            node[symbol] = node.get(symbol, 0) + 1

    def run(self, text: str | None, learn: bool, score: bool = True) -> float:
        data = b"\0" * self.order + (text or "").encode().lower() + bytes([END])
        out = 0.0
        for i in range(self.order, len(data)):
            context = data[i - self.order : i]
            if score:
                out += self.log10(context, data[i])
            if learn:
                self.learn(context, data[i])
        return out


def score_adaptive(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """``doc_id, score``: code length of each text by a trie that starts empty and learns as it goes."""

    def work(batches):
        import pyarrow as pa

        for b in batches:
            logs = [Trie(order).run(t, learn=True) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(logs, pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).mapInArrow(lean(work, ROWS), "doc_id long, score double")
