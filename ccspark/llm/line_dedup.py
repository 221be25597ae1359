"""Line dedup: sharded cuckoo filters backed by exact reference-count tables, reversible.

A line's key is the line stripped of white space at both ends, with A-Z in lower case.
Keys of ``min_chars`` code points or more that stand in ``min_docs`` documents or more
lose all their lines.

The state (:class:`LineState`) is a list of signed reference-count tables (key hash of 128
bits, number of documents), one for each change, merged when they become many; and, for
each shard of the key space, a cuckoo filter of the keys at or above the threshold. A
change looks up the counts of its own keys alone. Keys that cross the threshold enter or
leave their shard's filter; other shards stay as they are, a shard that overflows is
rebuilt from the exact counts, and the number of shards follows the number of keys.

A filter lets a few rarer keys pass. Which ones is read off the count tables: these keys,
a few in some thousand millions, are the shard's exceptions. A line is dropped if the filter
holds its key and the exceptions don't, which is exact for all counted keys. So texts are
never exchanged: filters and exceptions are sent to the tasks, as many shards at once as
``broadcast_bytes`` allow, and each set of shards takes its lines out in one pass.

Null or empty text is one empty line, which is never dropped. Each row is a document;
repeated rows count as many. An empty table gives no rows; extra columns are left behind
by :func:`dedup`, and kept by :func:`apply_state` with ``columns``.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator, Sequence
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from ccspark.llm.common import WHITE, ascii_lower, lean, text_of
from ccspark.plans.store import Scratch

SLOTS, KICKS = 4, 500
#: Bits of a fingerprint: a filter lets one key in some thousand millions pass by mistake.
MARK_BITS = 32
BROADCAST_BYTES = 64 << 20
#: Frequent keys of a shard, about; and count tables that are kept apart.
SHARD_KEYS, LEVELS = 1 << 17, 8
KEYS = "k1 long, k2 long"
#: Texts that a task takes at once.
ROWS = 512


class CuckooFilter:
    """Buckets of four fingerprints of up to 32 bits; a key is a pair of 64-bit hashes. Supports deletion."""

    def __init__(self, buckets: int, bits: int = MARK_BITS, table: np.ndarray | None = None):
        self.buckets, self.bits = buckets, bits
        self.table = np.zeros((buckets, SLOTS), np.uint32) if table is None else table

    @classmethod
    def sized(cls, keys: int, bits: int = MARK_BITS) -> CuckooFilter:
        return cls(1 << max(3, math.ceil(math.log2(max(1, keys) / (SLOTS * 0.8)))), bits)

    @classmethod
    def loads(cls, data: bytes, bits: int = MARK_BITS) -> CuckooFilter:
        table = np.frombuffer(data, np.uint32).reshape(-1, SLOTS).copy()
        return cls(len(table), bits, table)

    @classmethod
    def of(cls, k1: np.ndarray, k2: np.ndarray, bits: int = MARK_BITS) -> CuckooFilter:
        n = len(k1)
        while not (f := cls.sized(n, bits)).insert(k1, k2):
            n = 2 * max(n, 8)
        return f

    def dumps(self) -> bytes:
        return self.table.tobytes()

    def _places(self, k1, k2):
        """Fingerprint (never zero) and the two buckets; the second is reached from the first by the fingerprint alone."""
        k1, k2 = np.asarray(k1).astype(np.int64).view(np.uint64), np.asarray(k2).astype(np.int64).view(np.uint64)
        mark = np.maximum((k2 >> np.uint64(64 - self.bits)).astype(np.uint32), np.uint32(1))
        first = (k1 & np.uint64(self.buckets - 1)).astype(np.int64)
        return mark, first, self._other(first, mark)

    def _other(self, bucket, mark):
        step = (mark.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(20)
        return bucket ^ (step & np.uint64(self.buckets - 1)).astype(np.int64)

    def contains(self, k1, k2) -> np.ndarray:
        mark, a, b = self._places(k1, k2)
        return (self.table[a] == mark[:, None]).any(1) | (self.table[b] == mark[:, None]).any(1)

    def _settle(self, at: np.ndarray, mark: np.ndarray) -> np.ndarray:
        """Puts marks into free slots of their buckets, the n-th of a bucket into its n-th free slot; which found one."""
        order = np.argsort(at, kind="stable")
        b = at[order]
        start = np.flatnonzero(np.r_[True, b[1:] != b[:-1]])
        nth = np.arange(len(b)) - np.repeat(start, np.diff(np.r_[start, len(b)]))
        free = self.table[b] == 0
        hit = free & (np.cumsum(free, axis=1) == nth[:, None] + 1)
        done = hit.any(1)
        self.table[b[done], hit[done].argmax(1)] = mark[order[done]]
        out = np.zeros(len(at), bool)
        out[order] = done
        return out

    def insert(self, k1, k2) -> bool:
        """False if some key found no room: the caller rebuilds a larger filter from the exact table."""
        mark, a, b = self._places(k1, k2)
        for second in (False, True):
            left = ~self._settle(b if second else a, mark)
            mark, a, b = mark[left], a[left], b[left]
        for m, at in zip(mark, b.tolist(), strict=True):
            for kick in range(KICKS):
                slot = kick % SLOTS
                m, self.table[at, slot] = self.table[at, slot].copy(), m
                at = int(self._other(np.array([at]), np.array([m], np.uint32))[0])
                free = np.flatnonzero(self.table[at] == 0)
                if len(free):
                    self.table[at, free[0]] = m
                    break
            else:
                return False
        return True

    def delete(self, k1, k2) -> None:
        """Removes keys that were inserted before."""
        mark, a, b = self._places(k1, k2)
        while len(mark):
            # one of each (bucket, fingerprint) at a time, as several keys may have left the same
            _, one = np.unique(np.minimum(a, b) << 32 | mark, return_index=True)
            m, x, y = mark[one], a[one], b[one]
            here = (self.table[x] == m[:, None]).any(1)
            at = np.where(here, x, y)
            hit = self.table[at] == m[:, None]
            some = hit.any(1)
            self.table[at[some], hit[some].argmax(1)] = 0
            rest = np.ones(len(mark), bool)
            rest[one] = False
            mark, a, b = mark[rest], a[rest], b[rest]


def line_key(line: Column) -> Column:
    """The rule of :func:`keys_of`, as a column."""
    return ascii_lower(F.btrim(line, F.lit(WHITE)))


def keys_of(text: bytes) -> list[bytes]:
    """Keys of a text's lines."""
    white = WHITE.encode()
    return [x.strip(white) for x in text.lower().split(b"\n")]


def _hashed(keys: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    import xxhash

    both = np.frombuffer(b"".join(map(xxhash.xxh3_128_digest, keys)), "<i8").reshape(-1, 2)
    return both[:, 0], both[:, 1]


def _counted(key: bytes, least: int) -> bool:
    return len(key) >= least and (least <= 1 or len(key.decode()) >= least)


def _shard_of(k2: np.ndarray, shards: int) -> np.ndarray:
    return ((k2.astype(np.int64).view(np.uint64) >> np.uint64(8)) % np.uint64(shards)).astype(np.int32)


def _shard(shards: int) -> Column:
    return F.pmod(F.shiftrightunsigned("k2", 8), F.lit(shards)).cast("int").alias("shard")


def line_counts(docs: DataFrame, min_chars: int = 1) -> DataFrame:
    """``k1, k2, n``: documents of each key. A document's own lines are made distinct within its row."""

    def work(batches):
        import pyarrow as pa

        for b in batches:
            found: list[bytes] = []
            for text in b.column("text").cast(pa.binary()):
                found.extend(k for k in set(keys_of(text.as_py())) if _counted(k, min_chars))
            k1, k2 = _hashed(found)
            yield pa.RecordBatch.from_arrays([pa.array(k1), pa.array(k2)], names=["k1", "k2"])

    rows = docs.select(text_of().alias("text")).mapInArrow(lean(work, ROWS), KEYS)
    return rows.groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("n"))


class LineState:
    """The state of an incremental line dedup. Tables live in the run's shared folder, a version for each change."""

    def __init__(self, spark, min_docs: int = 10, min_chars: int = 1, shard_keys: int = SHARD_KEYS, mark_bits: int = MARK_BITS, scratch: Scratch | None = None):
        self.spark, self.min_docs, self.min_chars, self.shard_keys, self.mark_bits = spark, min_docs, min_chars, shard_keys, mark_bits
        self.scratch = scratch or Scratch(spark, "line-dedup")
        self.version, self.shards, self.frequent = 0, 1, 0
        self.levels: list[DataFrame] = []
        self.filters: DataFrame = spark.createDataFrame([], "shard int, data binary")

    def insert(self, docs: DataFrame) -> LineState:
        return self._change(docs, 1)

    def delete(self, docs: DataFrame) -> LineState:
        """Takes documents back that were inserted before (same rows)."""
        return self._change(docs, -1)

    @property
    def counts(self) -> DataFrame:
        """``k1, k2, n`` of all keys that are left."""
        if len(self.levels) == 1:
            return self.levels[0].where("n > 0")
        rows = reduce(DataFrame.unionByName, self.levels)
        return rows.groupBy("k1", "k2").agg(F.sum("n").alias("n")).where("n > 0")

    def frequent_keys(self) -> DataFrame:
        return self.counts.where(F.col("n") >= self.min_docs).select("k1", "k2")

    def _change(self, docs: DataFrame, sign: int) -> LineState:
        self.version += 1
        delta = self.scratch.write(line_counts(docs, self.min_chars).select("k1", "k2", (F.col("n") * sign).alias("n")), f"delta-{self.version}")
        at = F.lit(self.min_docs)
        if self.levels:
            own = delta.select("k1", "k2")
            before = reduce(DataFrame.unionByName, [x.join(own, ["k1", "k2"], "left_semi") for x in self.levels])
            both = before.select("k1", "k2", F.lit(0).cast("long").alias("n"), F.col("n").alias("was")).unionByName(delta.select("k1", "k2", "n", F.lit(0).cast("long").alias("was")))
            now = both.groupBy("k1", "k2").agg((F.sum("n") + F.sum("was")).alias("n"), F.sum("was").alias("was"))
        else:
            now = delta.withColumn("was", F.lit(0).cast("long"))
        up = F.col("n") >= at
        crossed, seen = self.scratch.observed(now.where(up != (F.col("was") >= at)).select("k1", "k2", up.alias("up")), f"crossed-{self.version}", up=F.sum(F.col("up").cast("long")), n=F.count(F.lit(1)))
        self.levels.append(delta)
        self.frequent += 2 * (seen["up"] or 0) - seen["n"]
        if len(self.levels) > LEVELS:
            self.levels = [self.scratch.write(self.counts, f"counts-{self.version}")]
        need = max(1, math.ceil(self.frequent / self.shard_keys))
        if need > 2 * self.shards or self.version == 1:
            self.shards = need
            self.filters = self.scratch.write(self._built(self.frequent_keys()), f"filters-{self.version}")
        elif seen["n"]:
            self.filters = self._merged(crossed)
        return self

    def _built(self, keys: DataFrame) -> DataFrame:
        """``shard, data``: filters of the keys from anew."""
        bits = self.mark_bits

        def build(key, table):
            import pyarrow as pa

            f = CuckooFilter.of(*(table.column(c).to_numpy() for c in ("k1", "k2")), bits)
            return pa.table({"shard": pa.array([key[0].as_py()], pa.int32()), "data": pa.array([f.dumps()], pa.binary())})

        return keys.select(_shard(self.shards), "k1", "k2").groupBy("shard").applyInArrow(build, "shard int, data binary")

    def _merged(self, crossed: DataFrame) -> DataFrame:
        """The filters with the crossing keys applied. Only their shards change; those without room are rebuilt."""
        keys, bits = crossed.select(_shard(self.shards), "k1", "k2", "up"), self.mark_bits

        def merge(key, held, table):
            import pyarrow as pa

            if not table.num_rows:
                return held
            up = np.asarray(table.column("up"))
            k1, k2 = (table.column(c).to_numpy() for c in ("k1", "k2"))
            if held.num_rows:
                f = CuckooFilter.loads(held.column("data")[0].as_py(), bits)
                f.delete(k1[~up], k2[~up])
                data = f.dumps() if f.insert(k1[up], k2[up]) else None
            else:
                data = CuckooFilter.of(k1[up], k2[up], bits).dumps()
            return pa.table({"shard": pa.array([key[0].as_py()], pa.int32()), "data": pa.array([data], pa.binary())})

        out = self.filters.groupBy("shard").cogroup(keys.groupBy("shard")).applyInArrow(merge, "shard int, data binary")
        out, seen = self.scratch.observed(out, f"merged-{self.version}", full=F.sum(F.isnull("data").cast("long")))
        if not seen["full"]:
            return out
        full = out.where("data is null").select(F.col("shard").alias("full"))
        own = self.frequent_keys().join(full, _shard(self.shards) == F.col("full"), "left_semi")
        return self.scratch.write(out.where("data is not null").unionByName(self._built(own)), f"filters-{self.version}")

    def _sets(self, broadcast_bytes: int) -> Iterator[dict[int, bytes]]:
        """The filters in sets of shards that may be sent at once."""
        held, room = {}, broadcast_bytes
        for r in self.filters.orderBy("shard").toLocalIterator():
            if held and len(r["data"]) > room:
                yield held
                held, room = {}, broadcast_bytes
            held[r["shard"]] = bytes(r["data"])
            room -= len(r["data"])
        if held:
            yield held

    def passes(self, broadcast_bytes: int = BROADCAST_BYTES) -> Iterator[tuple[dict[int, bytes], dict[int, np.ndarray]]]:
        """Sets of filters, each with its exceptions: keys below the threshold that a filter lets pass."""
        shards, spark, bits = self.shards, self.spark, self.mark_bits
        for held in self._sets(broadcast_bytes // 2):
            sent = spark.sparkContext.broadcast(held)

            def probe(batches, sent=sent):
                import pyarrow as pa

                filters = {s: CuckooFilter.loads(d, bits) for s, d in sent.value.items()}
                for b in batches:
                    hit = _passing(filters, b.column("k1").to_numpy(), b.column("k2").to_numpy(), shards)
                    yield b.filter(pa.array(hit))

            rows = reduce(DataFrame.unionByName, [x.select("k1", "k2", "n") for x in self.levels]).mapInArrow(lean(probe), f"{KEYS}, n long")
            rare = rows.groupBy("k1", "k2").agg(F.sum("n").alias("n")).where((F.col("n") > 0) & (F.col("n") < self.min_docs))
            rare = rare.select("k1", "k2").toArrow()
            k1, k2 = (rare.column(c).to_numpy() for c in ("k1", "k2"))
            of = _shard_of(k2, shards) if len(k2) else np.zeros(0, np.int32)
            sent.unpersist()
            yield held, {int(s): np.sort(_wide(k1[of == s], k2[of == s])) for s in np.unique(of)}


def _wide(k1: np.ndarray, k2: np.ndarray) -> np.ndarray:
    """Pairs as one value that sorts and compares."""
    out = np.empty(len(k1), [("a", "<i8"), ("b", "<i8")])
    out["a"], out["b"] = k1, k2
    return out


def _passing(filters: dict[int, CuckooFilter], k1: np.ndarray, k2: np.ndarray, shards: int) -> np.ndarray:
    hit = np.zeros(len(k1), bool)
    if not len(k1):
        return hit
    if shards == 1:
        return filters[0].contains(k1, k2) if 0 in filters else hit
    of = _shard_of(k2, shards)
    order = np.argsort(of, kind="stable")
    some, start = np.unique(of[order], return_index=True)
    for s, rows in zip(some.tolist(), np.split(order, start[1:]), strict=True):
        if s in filters:
            hit[rows] = filters[s].contains(k1[rows], k2[rows])
    return hit


def _member(sorted_: np.ndarray | None, keys: np.ndarray) -> np.ndarray:
    if sorted_ is None or not len(sorted_):
        return np.zeros(len(keys), bool)
    at = np.minimum(np.searchsorted(sorted_, keys), len(sorted_) - 1)
    return sorted_[at] == keys


def apply_state(docs: DataFrame, state: LineState, columns: Sequence[str] = (), digest: bool = False, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Each document's text without its frequent lines: ``doc_id``, the columns, ``n_lines, n_dropped`` and ``text`` (or ``kept_sha256``).

    The documents' lines must have been counted: for a line that never was, a filter may err.
    """
    carry = [c for c in columns if c not in ("doc_id", "text")]
    frame = docs.select("doc_id", F.struct(F.lit(0).alias("_"), *[F.col(c) for c in carry]).alias("carry"), F.lit(-1).cast("long").alias("n_lines"), F.lit(0).cast("long").alias("n_dropped"), text_of().alias("text"))
    shards, least, bits = state.shards, state.min_chars, state.mark_bits
    sets = state.passes(broadcast_bytes)
    following, i, last = next(sets, ({}, {})), 0, False
    while not last:
        (held, rare), following = following, next(sets, None)
        last = following is None
        sent = docs.sparkSession.sparkContext.broadcast((held, rare))
        hashed = digest and last

        def work(batches, sent=sent, hashed=hashed):
            import pyarrow as pa

            filters, rare = {s: CuckooFilter.loads(d, bits) for s, d in sent.value[0].items()}, sent.value[1]
            for b in batches:
                texts = b.column("text").cast(pa.binary())
                keys: list[bytes] = []
                known, ends = [], []
                for t in texts:
                    own = keys_of(t.as_py())
                    known.extend(_counted(k, least) for k in own)
                    keys.extend(own)
                    ends.append(len(keys))
                k1, k2 = _hashed(keys)
                del keys
                gone = _passing(filters, k1, k2, shards) & np.array(known, bool)
                at = np.flatnonzero(gone)
                of = _shard_of(k2[at], shards)
                for s in np.unique(of):
                    rows = at[of == s]
                    gone[rows[_member(rare.get(int(s)), _wide(k1[rows], k2[rows]))]] = False
                ends = np.array(ends, np.int64)
                begin = np.r_[np.zeros(1, np.int64), ends[:-1]]
                dropped = np.r_[0, np.cumsum(gone)]
                n_gone = (dropped[ends] - dropped[begin]).astype(np.int64) if len(ends) else np.zeros(0, np.int64)
                out = []
                for r, t in enumerate(texts):
                    kept = t.as_py()
                    if n_gone[r]:
                        kept = b"\n".join(x for x, g in zip(kept.split(b"\n"), gone[begin[r] : ends[r]].tolist(), strict=True) if not g)
                    out.append(hashlib.sha256(kept).hexdigest() if hashed else kept)
                total = b.column("n_lines").to_numpy()
                total = np.where(total < 0, ends - begin, total) if len(ends) else np.zeros(0, np.int64)
                text = pa.array(out, pa.string()) if hashed else pa.array(out, pa.binary()).cast(pa.string())
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("carry"), pa.array(total, pa.int64()), pa.array(b.column("n_dropped").to_numpy() + n_gone), text], names=["doc_id", "carry", "n_lines", "n_dropped", "text"])

        schema = StructType([docs.schema["doc_id"], StructField("carry", frame.schema["carry"].dataType)]).add("n_lines", "long").add("n_dropped", "long").add("text", "string")
        frame = frame.mapInArrow(lean(work, ROWS), schema)
        if not last:
            frame = state.scratch.write(frame, f"pass-{state.version}-{i}")
        i += 1
    return frame.select("doc_id", *[F.col("carry").getField(c).alias(c) for c in carry], "n_lines", "n_dropped", F.col("text").alias("kept_sha256" if digest else "text"))


def dedup(docs: DataFrame, min_docs: int = 10, min_chars: int = 1, digest: bool = False, scratch: Scratch | None = None) -> DataFrame:
    """One insertion of all documents, then their texts without the frequent lines."""
    return apply_state(docs, LineState(docs.sparkSession, min_docs, min_chars, scratch=scratch).insert(docs), digest=digest)


#: The rows of the query in DuckDB.
ORACLE_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents),
e AS (SELECT rid, doc_id, unnest(l) AS line, generate_subscripts(l, 1) AS i FROM d),
k AS (SELECT *, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM e),
f AS (SELECT key FROM (SELECT DISTINCT rid, key FROM k WHERE length(key) >= 1) GROUP BY key HAVING count(*) >= 10)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (f.key IS NOT NULL)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (f.key IS NULL), '')) AS kept_sha256
FROM k LEFT JOIN f USING (key) GROUP BY rid, doc_id
"""
