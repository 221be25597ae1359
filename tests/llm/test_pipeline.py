"""The pipeline against plain versions of its stages, one after another, on tables of some hundred awkward rows."""

import random

import brute
import duckdb
import pytest

from ccspark.llm import byte_bpe, decontaminate, near_dups, quality

P = pytest.importorskip("public_tokenizers")


def tables(spark, folder):
    rng = random.Random(12)
    common = "the of and to in a is that for it as was with be by on not he i this are or his from at which but have an had they you were their one all we can her has there been if more when will would who so no".split()
    rare = ["".join(rng.choice("abcdefghijklmnoprstuvw") for _ in range(rng.randrange(4, 11))) for _ in range(4000)]
    words = lambda n: [rng.choice(common) if rng.random() < 0.5 else rng.choice(rare) for _ in range(n)]
    sentences = lambda n: ". ".join(" ".join(words(rng.randrange(8, 16))).capitalize() for _ in range(n)) + "."
    items = [(i, sentences(3)) for i in range(25)]
    footer = "All rights of this page are kept by its owner and its editors"
    docs = []
    for i in range(120):
        lines = [sentences(3) for _ in range(rng.randrange(2, 6))]
        if i % 4 == 0:
            lines.insert(rng.randrange(len(lines)), "  " + footer + "\t")
        docs.append((i, "\n".join(lines)))
    for i in range(20):
        w = docs[i][1].split(" ")
        for k in rng.sample(range(len(w)), max(1, len(w) // 60)):
            w[k] = rng.choice(rare)
        docs.append((200 + i, " ".join(w)))
        docs.append((300 + i, docs[40 + i][1]))
    for i in range(10):
        w = items[i][1].split(" ")
        for k in rng.sample(range(len(w) - 12), i):
            w[k] = rng.choice(rare)
        docs.append((400 + i, sentences(6) + "\n" + " ".join(w) + "\n" + sentences(6)))
    docs += [(500, None), (501, ""), (502, "### $$$ %%%"), (503, "one two " * 300), (504, "x" * 5000), (3, docs[3][1]), (7, sentences(12)), (None, sentences(12))]
    frame = spark.createDataFrame([(d, t, "en", None, None if t is None else len(t)) for d, t in docs], "doc_id long, text string, lang string, source string, n_chars long")
    frame.coalesce(3).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(items + [(99, None)], "item_id long, text string").coalesce(1).write.parquet(f"{folder}/benchmark.parquet")
    return [(d, t) for d, t in docs], items


def plain_near(rows):
    """Rows (doc_id, text) that are the first of their group by all pairs of distinct texts; null ids stay."""
    known = sorted({r for r in rows if r[0] is not None})
    sets = [near_dups.shingle_set(t, 5) for _, t in known]
    empty = [not t.encode().split() for _, t in known]
    up = list(range(len(known)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(known)):
        for b in range(a + 1, len(known)):
            common = len(sets[a] & sets[b])
            if empty[a] == empty[b] and common >= 0.8 * (len(sets[a]) + len(sets[b]) - common):
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    # of equal ids the order is that of a hash, so a group may keep any of its texts with the least id
    return [[known[i] for i in range(len(known)) if root(i) == g] for g in sorted({root(i) for i in range(len(known))})], [r for r in rows if r[0] is None]


def leaks(text, items):
    found = decontaminate.tokens(text)
    for _, item in items:
        words, answer = decontaminate.tokens(item), decontaminate.answer_of(item)
        reach = len(words) * 3 // 2
        for s in range(0, max(1, len(found) - 16), 16):
            around = found[max(0, s - reach) : s + 32 + reach]
            share = decontaminate.common_length(words, around) / len(words)
            if share >= 0.8 or (share >= 0.5 and decontaminate.common_length(answer, around) >= 0.8 * len(answer)):
                return True
    return False


def test_pipeline_equals_plain_stages(spark, tmp_path):
    import corpus_pipeline

    folder = str(tmp_path)
    docs, items = tables(spark, folder)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "line_dedup", "near_duplicates", "decontamination", "byte_bpe"]
    own = spark.read.parquet(f"{folder}/documents.parquet")
    steps = []
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, own, folder)
        if i < 4:
            assert out.dtypes == spark.read.parquet(f"{folder}/documents.parquet").dtypes
        out.write.parquet(f"{folder}/{name}")
        own = spark.read.parquet(f"{folder}/{name}")
        steps.append([(r[0], r[1]) if i < 4 else r for r in own.collect()])
    key = lambda r: (r[0] is not None, r[0] or 0, r[1] or "")

    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT row_number() OVER () AS doc_id, text FROM '{folder}/documents.parquet/*.parquet'")
    verdicts = con.execute(f"SELECT text, kept FROM documents JOIN ({quality.oracle_sql()}) USING (doc_id)").fetchall()
    keep = {t for t, k in verdicts if k}
    assert sorted(steps[0], key=key) == sorted([r for r in docs if r[1] in keep], key=key) and 500 not in {r[0] for r in steps[0]}

    numbered = list(enumerate(t for _, t in steps[0]))
    dropped = brute.line_dedup(numbered, 10)
    want = sorted((d, dropped[i][2]) for i, (d, _) in enumerate(steps[0]) if d is not None)
    assert sorted((d, brute.sha(t)) for d, t in steps[1] if d is not None) == want and any(n for _, n, _ in dropped.values())

    groups, lone = plain_near(steps[1])
    assert len(steps[2]) == len(groups) + len(lone) and all(r in steps[2] for r in lone)
    for g in groups:
        kept = [r for r in g if r in steps[2]]
        assert len(kept) == 1 and kept[0][0] == min(d for d, _ in g)
    assert not {r[0] for r in steps[2]} & {*range(200, 220), *range(300, 320)}

    assert sorted(steps[3], key=key) == sorted([r for r in steps[2] if not leaks(r[1], items)], key=key)
    assert not {r[0] for r in steps[3]} & set(range(400, 410)) and len(steps[3]) > 80

    encoding = byte_bpe._encoding(open(P.path("byte_bpe_multi_50k.tiktoken"), "rb").read(), P.PATTERN)
    assert sorted((r.doc_id or 0, list(r.ids), r.decoded) for r in steps[4]) == sorted((d or 0, encoding.encode_ordinary(t), t) for d, t in steps[3])
    whole = corpus_pipeline.run(spark, folder)
    assert sorted((r.doc_id or 0, list(r.ids)) for r in whole.collect()) == sorted((r.doc_id or 0, list(r.ids)) for r in steps[4])


def test_stages_bound_the_bytes_of_a_batch(spark):
    """15 MB of texts in one partition reach Python in parts, none lost; a bound that is lower stays."""
    import corpus_pipeline

    from ccspark.llm import common

    def sizes(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], names=["n", "bytes"])

    docs = spark.range(3000).coalesce(1).selectExpr("id as doc_id", "repeat('some words ', 460) as text")
    key = common._BATCH_CONF
    spark.conf.unset(key)
    try:
        corpus_pipeline.encode(spark, docs, "")
        got = docs.mapInArrow(sizes, "n long, bytes long").collect()
        assert sum(r.n for r in got) == 3000 and max(r.bytes for r in got) < 2 * common.BATCH_BYTES
        spark.conf.set(key, "1m")
        corpus_pipeline.encode(spark, docs, "")
        assert spark.conf.get(key) == "1m"
    finally:
        spark.conf.unset(key)
