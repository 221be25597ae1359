"""Byte-level BPE encoding and decoding with tiktoken.

The rank file is read once on the driver and sent to the tasks (a file of fixed size,
about one megabyte). Texts over ``block`` characters are cut where the pre-tokenising
pattern has a match boundary in any case: between a character that is not white space
and a white-space character that follows. Nothing before such a cut can match across it,
and no look-ahead there sees past it, so the ids are those of the whole text.

Null or empty text: no ids, the digest of nothing. Text of one unbroken run has no safe
cut and is encoded whole. Repeated rows give repeated rows; an empty table gives none.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import re
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame

from ccspark.llm.common import keep_columns, lean

SCHEMA = "doc_id long, n_tokens long, ids array<int>, decoded string"
DIGEST_SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
#: Before white space of both engines: U+001C to U+001F are such to this one only, so no cut is made beside them.
_CUT = re.compile(r"(?<=[^\s\x1c-\x1f])(?=[ \t\n\r])")
#: Texts that a task takes at once.
ROWS = 512


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


@functools.lru_cache(maxsize=4)
def _encoding(ranks_file: bytes, pattern: str):
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in (x.split() for x in ranks_file.splitlines() if x.strip())}
    return tiktoken.Encoding("file", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


def blocks(text: str, block: int) -> Iterator[str]:
    """The text cut at safe boundaries, each part at least ``block`` characters but the last."""
    at = 0
    while len(text) - at > block:
        m = _CUT.search(text, at + block)
        if not m:
            break
        yield text[at : m.start()]
        at = m.start()
    yield text[at:]


def encode_text(encoding, text: str, block: int = 65536) -> list[int]:
    if len(text) <= block:
        return encoding.encode_ordinary(text)
    return [i for part in blocks(text, block) for i in encoding.encode_ordinary(part)]


def _run(docs: DataFrame, path: str, pattern: str, block: int, digest: bool, keep_text: bool = True) -> DataFrame:
    with open(path, "rb") as f:
        sent = docs.sparkSession.sparkContext.broadcast(f.read())

    def work(batches):
        import pyarrow as pa

        encoding = _encoding(sent.value, pattern)
        for b in batches:
            ids_of, n, ids, back = b.column(0), [], [], []
            for text in b.column(1).to_pylist():
                got = encode_text(encoding, text or "", block)
                raw = encoding.decode_bytes(got)
                n.append(len(got))
                if digest:
                    ids.append(hashlib.sha256(",".join(map(str, got)).encode()).hexdigest())
                    back.append(hashlib.sha256(raw).hexdigest())
                else:
                    ids.append(np.array(got, np.int32))
                    back.append(raw.decode("utf-8", "replace") if keep_text else None)
            kind = pa.string() if digest else pa.list_(pa.int32())
            names = ["doc_id", "n_tokens", "ids_sha256" if digest else "ids", "decoded_sha256" if digest else "decoded"]
            yield pa.RecordBatch.from_arrays([ids_of, pa.array(n, pa.int64()), pa.array(ids, kind), pa.array(back, pa.string())], names=names)

    rows = keep_columns(docs, "doc_id", "text")
    return rows.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(lean(work, ROWS), DIGEST_SCHEMA if digest else SCHEMA)


def encode(docs: DataFrame, path: str, pattern: str, block: int = 65536) -> DataFrame:
    """``doc_id, n_tokens, ids, decoded``: ids of each text and the text that they decode to."""
    return _run(docs, path, pattern, block, digest=False)


def encode_digests(docs: DataFrame, path: str, pattern: str, block: int = 65536) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` of each text, digested where it is encoded."""
    return _run(docs, path, pattern, block, digest=True)


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """``doc_id, bytes``: raw bytes of id lists (``doc_id, ids``); null ids give empty bytes. An unknown id raises."""
    with open(path, "rb") as f:
        sent = encoded.sparkSession.sparkContext.broadcast(f.read())

    def work(batches):
        import pyarrow as pa

        encoding = _encoding(sent.value, pattern)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([encoding.decode_bytes(x or []) for x in b.column(1).to_pylist()], pa.binary())], names=["doc_id", "bytes"])

    return encoded.selectExpr("cast(doc_id as long) doc_id", "ids").mapInArrow(lean(work, ROWS), "doc_id long, bytes binary")
