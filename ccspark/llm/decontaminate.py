"""Benchmark decontamination by latent semantic retrieval.

Benchmark items are cut into passages of ``PASSAGE`` words. Words are weighed by their
inverse document frequency over all documents; the TF-IDF matrix of the passages is
reduced by a randomised SVD whose products are summed over the tasks that hold the rows.
Documents are read at a spot every ``STEP`` words, whose ``PASSAGE`` words are folded into the
latent space. Spots whose cosine with a passage is ``min_cosine`` or more are candidates of its
item. Around a candidate an item leaks if ``full`` of its words are there in order (longest
common subsequence), or ``part`` of them together with its answer (its last sentence). What a
document or a spot cannot meet with all its words, in whatever order, is not searched for in it;
that loses nothing.

The benchmark is a stated query set: it is taken in blocks of ``block`` items, each with
its own vocabulary and space, and each block reads all documents. What is sent to the
tasks is bounded by the block.

Words are runs of letters and digits in lower case. Null or empty texts and items match
nothing; items of fewer than ``min_words`` words are too short to tell and are left out.
Repeated rows give repeated results; an empty table gives no rows.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.llm.common import lean, text_of

PASSAGE, STEP = 32, 16
RANK, POWER = 192, 2
#: Least cosine in the latent space of a spot with a passage that makes it a candidate.
MIN_COSINE = 0.4
SCHEMA = "doc_id long, item_id long, lcs_share double, answer_found boolean, cosine double"
BLOCK = 2048
#: Texts that a task takes at once.
ROWS = 512
_OTHER = bytes(b if b >= 128 or chr(b).isalnum() else 32 for b in range(256))


def tokens(text: str | None) -> list[bytes]:
    return (text or "").lower().encode().translate(_OTHER).split()


def answer_of(text: str) -> list[bytes]:
    """Words of the last sentence or line that has three or more, else the last three words."""
    parts = [tokens(p) for p in text.replace("\n", ".").replace("?", ".").replace("!", ".").split(".")]
    long = [p for p in parts if len(p) >= 3]
    return long[-1] if long else tokens(text)[-3:]


def starts(n: int, size: int, step: int) -> np.ndarray:
    """Starts of windows that cover n words; the last ends with them."""
    return np.unique(np.r_[np.arange(0, max(1, n - size + 1), step), max(0, n - size)])


def common_length(a: list, b: list) -> int:
    """Length of the longest common subsequence, by bit rows over ``a``."""
    place: dict = {}
    for i, w in enumerate(a):
        place[w] = place.get(w, 0) | 1 << i
    full = (1 << len(a)) - 1
    row = full
    for w in b:
        hit = row & place.get(w, 0)
        row = ((row + hit) | (row - hit)) & full
    return len(a) - row.bit_count()


def inverse_frequencies(docs: DataFrame, vocabulary: dict[bytes, int]) -> np.ndarray:
    """For each word of the vocabulary ln((N + 1) / (df + 0.5)) over all documents."""
    sent = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def work(batches):
        import pyarrow as pa

        number = sent.value
        df, n = np.zeros(len(number) + 1, np.int64), 0
        for b in batches:
            for text in b.column("text").to_pylist():
                words = tokens(text)
                seen = np.zeros(len(number) + 1, bool)
                seen[np.fromiter(map(number.get, words, _missing(len(number))), np.int32, len(words))] = True
                df += seen
                n += 1
        df[-1] = n
        at = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(df[at])], names=["w", "n"])

    got = docs.select("text").mapInArrow(lean(work, ROWS), "w int, n long").groupBy("w").agg(F.sum("n").alias("n")).toArrow()
    df = np.zeros(len(vocabulary) + 1)
    df[got.column("w").to_numpy()] = got.column("n").to_numpy()
    return np.log((df[-1] + 1) / (df[:-1] + 0.5))


def _missing(value: int):
    from itertools import repeat

    return repeat(value)


def _product(rows: DataFrame, right: np.ndarray) -> np.ndarray:
    """A'(A right) for the sparse rows (``ids, weights``): each task adds its own rows, then words are summed."""
    spark, width = rows.sparkSession, right.shape[1]
    sent = spark.sparkContext.broadcast(right)

    def work(batches):
        import pyarrow as pa

        out = np.zeros_like(sent.value)
        for b in batches:
            for ids, weights in zip(b.column("ids").to_pylist(), b.column("weights").to_pylist(), strict=True):
                w = np.array(weights)
                out[ids] += np.outer(w, w @ sent.value[ids])
        at = np.flatnonzero(out.any(1))
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array([out[i].tobytes() for i in at], pa.binary())], names=["w", "y"])

    def add(key, table):
        import pyarrow as pa

        y = np.sum([np.frombuffer(v) for v in table.column("y").to_pylist()], axis=0)
        return pa.table({"w": pa.array([key[0].as_py()], pa.int32()), "y": pa.array([y.tobytes()], pa.binary())})

    got = rows.mapInArrow(lean(work), "w int, y binary").groupBy("w").applyInArrow(add, "w int, y binary").toArrow()
    out = np.zeros((len(right), width))
    for w, y in zip(got.column("w").to_pylist(), got.column("y").to_pylist(), strict=True):
        out[w] = np.frombuffer(y)
    return out


def latent_basis(rows: DataFrame, words: int, rank: int = RANK, power: int = POWER, seed: int = 7) -> np.ndarray:
    """An orthonormal basis (words by rank) of the leading right singular vectors, by a randomised range finder.

    Cosines in the space do not depend on the rotation of the basis, so it is not turned further.
    """
    y = np.random.default_rng(seed).standard_normal((words, min(rank, words)))
    for _ in range(power + 1):
        y, _ = np.linalg.qr(_product(rows, y))
    return y


def _weighed(ids: np.ndarray, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A passage's distinct words with their TF-IDF weights, of length one: each passage counts alike in the space."""
    at, count = np.unique(ids, return_counts=True)
    weights = count * idf[at]
    return at, weights / np.linalg.norm(weights)


def _counted(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct words of each list with their counts, one list after another, and where each begins."""
    each = [np.unique(ids, return_counts=True) for ids in lists]
    begin = np.cumsum([0] + [len(w) for w, _ in each])
    return np.concatenate([w for w, _ in each]), np.concatenate([c for _, c in each]), begin


def _regions(ids: np.ndarray, spots: np.ndarray, word: np.ndarray, count: np.ndarray, told: np.ndarray, reach: int) -> tuple[np.ndarray, ...]:
    """The item's words in a text, and for each spot where they begin and end around it and how many of the item's and of
    its answer's words they can be at most: as many as each word comes, in any order.

    word, count: the item's distinct words in order, with their counts; told: the counts in its answer.
    """
    at = np.minimum(np.searchsorted(word, ids), len(word) - 1)
    place = np.flatnonzero(word[at] == ids)
    low, high = np.searchsorted(place, spots - reach), np.searchsorted(place, spots + PASSAGE + reach)
    most, answer = np.zeros(len(spots), np.int64), np.zeros(len(spots), np.int64)
    for i in range(0, len(spots), 1024):
        part, start, end = slice(i, i + 1024), low[i], high[min(i + 1024, len(spots)) - 1]
        sums = np.zeros((end - start + 1, len(word)), np.int32)
        sums[np.arange(1, end - start + 1), at[place[start:end]]] = 1
        np.cumsum(sums, axis=0, out=sums)
        here = sums[high[part] - start] - sums[low[part] - start]
        most[part], answer[part] = np.minimum(here, count).sum(1), np.minimum(here, told).sum(1)
    return place, low, high, most, answer


def _spot_vectors(ids: np.ndarray, table: np.ndarray) -> np.ndarray:
    """The words of each spot folded into the latent space, of length one."""
    spots = np.arange(max(1, -(-len(ids) // STEP) - 1)) * STEP
    out = np.zeros((len(spots), table.shape[1]), np.float32)
    for i in range(0, len(spots), 512):
        start, end = spots[i], min(len(ids), spots[min(i + 512, len(spots)) - 1] + PASSAGE)
        steps = np.add.reduceat(table[ids[start:end]], np.arange(0, end - start, STEP))
        part = out[i : i + 512]
        n = len(part)
        part += steps[:n]
        more = steps[1 : n + 1]
        part[: len(more)] += more
    return out / np.maximum(np.linalg.norm(out, axis=1), 1e-9)[:, None]


def _search_block(docs: DataFrame, items: list[tuple[int, str]], full: float, part: float, rank: int, min_cosine: float) -> DataFrame:
    spark = docs.sparkSession
    words = [tokens(t) for _, t in items]
    vocabulary = {w: i for i, w in enumerate(sorted({w for x in words for w in x}))}
    idf = inverse_frequencies(docs, vocabulary)
    cut = [(k, int(s), np.array([vocabulary[w] for w in x[s : s + PASSAGE]])) for k, x in enumerate(words) for s in starts(len(x), PASSAGE, STEP)]
    weighed = [_weighed(ids, idf) for _, _, ids in cut]
    rows = spark.createDataFrame([(ids.tolist(), w.tolist()) for ids, w in weighed], "ids array<int>, weights array<double>")
    basis = latent_basis(rows, len(vocabulary), rank)
    table = np.vstack([basis * idf[:, None], np.zeros((1, basis.shape[1]))]).astype(np.float32)
    passages = np.stack([w @ basis[ids] for ids, w in weighed]).astype(np.float32)
    norms = np.linalg.norm(passages, axis=1)
    passages /= np.maximum(norms, 1e-9)[:, None]
    of = np.array([k for k, _, _ in cut])
    numbered = [np.array([vocabulary[w] for w in x]) for x in words]
    answers = [np.array([vocabulary[w] for w in answer_of(t)]) for _, t in items]
    sent = spark.sparkContext.broadcast(
        {"number": vocabulary, "table": table, "of": [passages[of == k] for k in range(len(items))], "ids": [i for i, _ in items], "items": numbered, "answers": answers, "words": _counted(numbered), "told": _counted(answers)}
    )

    def settle(ids: np.ndarray, vectors: np.ndarray, k: int, v: dict) -> tuple[float, bool, float]:
        """The best common subsequence around the candidate spots: share of the item, whether the answer is there, cosine.

        Candidates are the spots whose cosine with a passage of the item suffices, the nearest first. Of these one is
        passed over if its words, in whatever order, cannot meet the rule or be better than what was found.
        """
        item, answer = v["items"][k].tolist(), v["answers"][k].tolist()
        words, counts, begin = v["words"]
        word, count = words[begin[k] : begin[k + 1]], counts[begin[k] : begin[k + 1]]
        told = np.bincount(np.searchsorted(word, v["answers"][k]), minlength=len(word))
        near = (vectors @ v["of"][k].T).max(1)
        at = np.flatnonzero(near >= min_cosine)
        best = (False, 0.0, False, 0.0)
        if not len(at):
            return best[1:]
        place, low, high, most, share_of_answer = _regions(ids, at * STEP, word, count, told, len(item) + len(item) // 2)
        most, can = most / len(item), share_of_answer >= 0.8 * len(answer)
        for i in np.argsort(-near[at], kind="stable").tolist():
            if most[i] >= full or (most[i] >= part and can[i]):
                # alike in what may be met, so no better: leaks first, then by share
                if best[0] and (most[i], bool(can[i])) <= best[1:3]:
                    continue
                around = ids[place[low[i] : high[i]]].tolist()
                share, answered = common_length(item, around) / len(item), common_length(answer, around) >= 0.8 * len(answer)
                leak = share >= full or (share >= part and answered)
                if (leak, share, answered) > best[:3]:
                    best = (leak, share, answered, float(near[at[i]]))
        return best[1:]

    def work(batches):
        import pyarrow as pa

        v, names = sent.value, [x.split()[0] for x in SCHEMA.split(", ")]
        number, (words, counts, begin), (told, times, start) = v["number"], v["words"], v["told"]
        size, size_of_answer = np.array([len(x) for x in v["items"]]), np.array([len(x) for x in v["answers"]])
        for b in batches:
            out = [[], [], [], [], []]
            for doc, text in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist(), strict=True):
                found = tokens(text)
                if not found:
                    continue
                ids = np.fromiter(map(number.get, found, _missing(len(number))), np.int32, len(found))
                here = np.bincount(ids, minlength=len(number) + 1)
                most = np.add.reduceat(np.minimum(here[words], counts), begin[:-1]) / size
                can = np.add.reduceat(np.minimum(here[told], times), start[:-1]) >= 0.8 * size_of_answer
                possible = np.flatnonzero((most >= full) | ((most >= part) & can)).tolist()
                vectors = _spot_vectors(ids, v["table"]) if possible else None
                for k in possible:
                    share, answered, cosine = settle(ids, vectors, k, v)
                    if share >= full or (share >= part and answered):
                        for column, value in zip(out, (doc, v["ids"][k], share, answered, cosine), strict=True):
                            column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, (pa.int64(), pa.int64(), pa.float64(), pa.bool_(), pa.float64()), strict=True)], names=names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).mapInArrow(lean(work, ROWS), SCHEMA)


def leaks(docs: DataFrame, benchmark: DataFrame, full: float = 0.8, part: float = 0.5, min_words: int = 8, rank: int = RANK, block: int = BLOCK, min_cosine: float = MIN_COSINE) -> DataFrame:
    """``doc_id, item_id, lcs_share, answer_found, cosine``: documents that hold a benchmark item, with the share of its words there in order and the cosine of that spot."""
    texts = docs.select("doc_id", text_of().alias("text"))
    out: list[DataFrame] = []
    held: list[tuple[int, str]] = []

    def flush():
        if held:
            out.append(_search_block(texts, list(held), full, part, rank, min_cosine))
            held.clear()

    for r in benchmark.where("text is not null and item_id is not null").select("item_id", "text").dropDuplicates().toLocalIterator():
        if len(tokens(r["text"])) >= max(1, min_words):
            held.append((r["item_id"], r["text"]))
        if len(held) >= block:
            flush()
    flush()
    if not out:
        return docs.sparkSession.createDataFrame([], SCHEMA)
    return reduce(DataFrame.unionByName, out)


def clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The documents that hold no item, with all their columns; a null doc_id is kept."""
    found = leaks(docs, benchmark, **options).select(F.col("doc_id").alias("_leaking")).distinct()
    return docs.join(found, docs["doc_id"] == F.col("_leaking"), "left_anti")
