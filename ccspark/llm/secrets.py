"""Secret scans: three patterns, then a battery of randomness tests with false-discovery control. DataFrame functions only.

Positions are code points. They come from the lengths of the parts between the matches
(one split by the same pattern), as the engine's regular expressions report no offsets.

The battery takes each long run of key-like characters, infers the smallest alphabet that
holds it, and tests uniformity (chi-squared), runs about the middle of the alphabet and
serial correlation. The three share one string and are rough on short ones, so their weighed sum
of logarithms is not read off a formula: random strings of each alphabet and length class
go through the same columns (``SIMS`` of each), and a run's rank among them is its
p-value under randomness, uniform if the run is random, near zero if it is structured.

Reported are the runs of the highest ranks, as many as the false-discovery control of
their length class allows: the runs of the uppermost quarter, nearly all random, tell how
many random runs the class holds; what stands above a rank beyond their share is false.
Short runs carry little evidence, so their rate is higher. A class whose uppermost quarter
is empty reports none. Ranks are counted over all runs of the table that no base span
overlaps, in a hundred bins, so the rule needs one bounded aggregate and no sort; its
thresholds reach the rows as one scalar array. Such runs are of kind ``random``.

Null or empty text has no spans. Repeated rows give repeated rows (and count as often in
the ranks). An empty table gives none. Extra columns are left behind.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ccspark.llm.common import scan_array, text_of
from ccspark.plans.store import Scratch

#: The base patterns in order of kind.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}+"
HEX = r"(?<![0-9a-f])[0-9a-f]{32,}+"
BASE = (("assign", ASSIGN), ("access", ACCESS), ("hex", HEX))
RUN = r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{20,}+={0,2}"
#: Lower ends of the length classes, the length that stands for each, and the rate of false ones among its reported runs.
CLASSES = ((20, 24, 0.25), (32, 40, 0.15), (48, 56, 0.10), (64, 80, 0.10))
#: Weight of uniformity among the tests: letters of words are uneven, but hardly correlated.
UNIFORMITY = 4
#: Ranks, those of the uppermost quarter, and random strings of each alphabet and class.
BINS, TOP, SIMS = 100, 75, 1000
#: Alphabets from small to large; the first that holds a run is its encoding.
ALPHABETS = (
    ("digits", "0123456789"),
    ("hex", "0123456789abcdef"),
    ("HEX", "0123456789ABCDEF"),
    ("lower letters", "abcdefghijklmnopqrstuvwxyz"),
    ("upper letters", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    ("base32", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"),
    ("lower", "0123456789abcdefghijklmnopqrstuvwxyz"),
    ("upper", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    ("letters", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"),
    ("alnum", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"),
    ("base64", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"),
    ("base64url", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-_"),
)
SPAN = "struct<start:int,kind:int,end:int,value:string>"


def spans(text: Column, pattern: str, kind: int) -> Column:
    """All leftmost matches as ``start, kind, end, value``."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    between = F.split(text, pattern, -1)
    pairs = F.zip_with(found, F.slice(between, F.lit(1), F.size(found)), lambda v, g: F.struct(v.alias("value"), F.char_length(g).alias("gap"), F.char_length(v).alias("n")))
    after = lambda at, x: at + x["gap"] + x["n"]
    span = lambda at, x: F.struct((at + x["gap"]).alias("start"), F.lit(kind).alias("kind"), after(at, x).alias("end"), x["value"].alias("value"))
    return F.when(text.rlike(pattern), scan_array(pairs, F.lit(0), after, span, SPAN)).otherwise(F.array().cast(f"array<{SPAN}>"))


def _tail(z: Column) -> Column:
    """Two-sided normal tail, by the rational approximation with five terms."""
    x = F.abs(z) / math.sqrt(2)
    t = 1 / (1 + 0.3275911 * x)
    poly = t * (0.254829592 + t * (-0.284496736 + t * (1.421413741 + t * (-1.453152027 + t * 1.061405429))))
    return F.greatest(poly * F.exp(-x * x), F.lit(1e-30))


def _upper(z: Column) -> Column:
    """One-sided tail above z."""
    return F.when(z > 0, _tail(z) / 2).otherwise(1 - _tail(z) / 2)


def battery(value: Column) -> Column:
    """``encoding`` (the alphabet's place, null if none holds it), ``size, letters, body`` of one run."""
    body = F.rtrim(value, F.lit("="))
    place, letters = F.lit(None).cast("int"), F.lit("")
    for i, (_, a) in reversed(list(enumerate(ALPHABETS))):
        held = F.char_length(F.translate(body, a, "")) == 0
        place, letters = F.when(held, F.lit(i)).otherwise(place), F.when(held, F.lit(a)).otherwise(letters)
    return F.struct(place.alias("encoding"), F.char_length(letters).alias("size"), letters.alias("letters"), body.alias("body"))


def _tests(c: Column) -> Column:
    """From ``size, letters, body``: what the three tests need."""
    n, size = F.char_length(c["body"]).cast("double"), c["size"].cast("double")
    chars = F.split(c["body"], "")
    index = F.transform(chars, lambda x: (F.call_function("locate", x, c["letters"]) - 1).cast("double"))
    squares = F.aggregate(F.array_distinct(chars), F.lit(0.0), lambda a, x: a + F.pow(n - F.char_length(F.replace(c["body"], x, F.lit(""))), F.lit(2.0)))
    chi = size / n * squares - n
    df = size - 1
    z_chi = (F.pow(chi / df, F.lit(1 / 3)) - (1 - 2 / (9 * df))) / F.sqrt(2 / (9 * df))
    seen = F.aggregate(
        index,
        F.struct(F.lit(None).cast("double").alias("last"), F.lit(0.0).alias("high"), F.lit(0.0).alias("runs"), F.lit(0.0).alias("s"), F.lit(0.0).alias("ss"), F.lit(0.0).alias("sx")),
        lambda a, x: F.struct(
            x.alias("last"),
            (a["high"] + (x >= size / 2).cast("double")).alias("high"),
            (a["runs"] + F.when(a["last"].isNull(), 1.0).otherwise(((x >= size / 2) != (a["last"] >= size / 2)).cast("double"))).alias("runs"),
            (a["s"] + x).alias("s"),
            (a["ss"] + x * x).alias("ss"),
            (a["sx"] + F.coalesce(a["last"] * x, F.lit(0.0))).alias("sx"),
        ),
    )
    return F.struct(n.alias("n"), z_chi.alias("z_chi"), seen.alias("seen"))


def _combined(x: Column) -> Column:
    """Minus the weighed sum of the logarithms of the three tails: small for random strings."""
    n, seen = x["n"], x["seen"]
    hi, lo = seen["high"], x["n"] - seen["high"]
    twice = 2 * hi * lo
    z_runs = (seen["runs"] - (1 + twice / n)) / F.sqrt(F.greatest(twice * (twice - n) / (n * n * (n - 1)), F.lit(1e-9)))
    mean = seen["s"] / n
    var = seen["ss"] / n - mean * mean
    z_serial = ((seen["sx"] / (n - 1) - mean * mean) / F.greatest(var, F.lit(1e-9))) * F.sqrt(n)
    return -(UNIFORMITY * F.log(_upper(x["z_chi"])) + F.log(_tail(z_runs)) + F.log(_tail(z_serial)))


def statistic(c: Column) -> Column:
    """The battery's statistic of ``size, letters, body``; the tests' sums are taken once."""
    return F.element_at(F.transform(F.transform(F.array(c), _tests), _combined), 1)


def random_ranks(spark, sims: int = SIMS) -> DataFrame:
    """One row, ``ranks``: for each alphabet and length class (in this order) the percentiles 1 to 99 of the statistic of random strings."""
    cells = F.array(*[F.struct(F.lit(i).alias("a"), F.lit(k).alias("cls"), F.lit(n).alias("n"), F.lit(len(letters)).alias("size"), F.lit(letters).alias("letters")) for i, (_, letters) in enumerate(ALPHABETS) for k, (_, n, _) in enumerate(CLASSES)])
    rows = spark.range(sims).select("id", F.explode(cells).alias("c"))
    drawn = F.transform(F.sequence(F.lit(1), F.col("c.n")), lambda i: F.call_function("substring", F.col("c.letters"), F.pmod(F.xxhash64("id", "c.a", i), F.col("c.size")).cast("int") + 1, F.lit(1)))
    text = rows.select("c.a", "c.cls", F.struct("c.size", "c.letters", F.array_join(drawn, "").alias("body")).alias("c"))
    per = text.select("a", "cls", statistic(F.col("c")).alias("s")).groupBy("a", "cls").agg(F.percentile("s", F.array(*[F.lit(i / BINS) for i in range(1, BINS)])).alias("q"))
    return per.agg(F.transform(F.sort_array(F.collect_list(F.struct("a", "cls", "q"))), lambda x: x["q"]).alias("ranks"))


def length_class(n: Column) -> Column:
    out = F.lit(0)
    for i, (low, _, _) in enumerate(CLASSES):
        out = F.when(n >= low, F.lit(i)).otherwise(out)
    return out


def _rows(docs: DataFrame, ranks: Column) -> DataFrame:
    """Per document: base spans that hold, and the runs that none overlaps, with class and rank."""
    t = docs.select("doc_id", text_of().alias("_t"))
    t = t.select("doc_id", *[spans(F.col("_t"), p, i).alias(k) for i, (k, p) in enumerate(BASE)], spans(F.col("_t"), RUN, len(BASE)).alias("runs"))
    t = t.withColumn("assign", F.filter("assign", lambda s: F.char_length(F.regexp_extract(s["value"], ASSIGN, 2)) >= 8))
    t = t.withColumn("access", F.filter("access", lambda s: s["end"] - s["start"] >= 16))
    t = t.withColumn("base", F.sort_array(F.concat("assign", "access", "hex")))
    t = t.withColumn("runs", F.filter("runs", lambda r: ~F.exists("base", lambda b: (b["start"] < r["end"]) & (r["start"] < b["end"]))))
    t = t.withColumn("runs", F.transform("runs", lambda r: F.struct(r["start"].alias("start"), r["end"].alias("end"), battery(r["value"]).alias("c"))))
    t = t.withColumn("runs", F.transform(F.filter("runs", lambda r: r["c"]["encoding"].isNotNull()), lambda r: F.struct(r["start"].alias("start"), r["end"].alias("end"), r["c"]["encoding"].alias("encoding"), length_class(F.char_length(r["c"]["body"])).alias("cls"), statistic(r["c"]).alias("s"))))
    t = t.withColumn("ranks", F.when(F.size("runs") > 0, ranks))
    rank = lambda r: F.size(F.filter(F.element_at("ranks", r["encoding"] * len(CLASSES) + r["cls"] + 1), lambda q: q > r["s"]))
    t = t.withColumn("runs", F.transform("runs", lambda r: F.struct(r["start"].alias("start"), r["end"].alias("end"), r["encoding"].alias("encoding"), r["cls"].alias("cls"), rank(r).alias("bin"))))
    return t.select("doc_id", "assign", "access", "hex", "base", "runs")


def thresholds(rows: DataFrame) -> DataFrame:
    """One row, ``least``: per length class the least rank that is reported (past all ranks if none is)."""
    counts = rows.select(F.explode("runs").alias("r")).groupBy(F.col("r.cls").alias("cls"), F.col("r.bin").alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    grid = rows.sparkSession.range(len(CLASSES) * BINS).select(F.floor(F.col("id") / BINS).cast("int").alias("cls"), (F.col("id") % BINS).cast("int").alias("bin"))
    all_ = grid.join(counts, ["cls", "bin"], "left").select("cls", "bin", F.coalesce("n", F.lit(0)).alias("n"))
    above = Window.partitionBy("cls").orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, 0)
    top = F.sum(F.when(F.col("bin") >= TOP, F.col("n")).otherwise(0)).over(Window.partitionBy("cls"))
    rate = F.element_at(F.array(*[F.lit(q) for _, _, q in CLASSES]), F.col("cls") + 1)
    seen = all_.select("cls", "bin", F.sum("n").over(above).alias("reported"), (top * (BINS - F.col("bin")) / (BINS - TOP)).alias("random"), rate.alias("rate"))
    allowed = (F.col("reported") > 0) & (F.col("reported") - F.col("random") <= F.col("rate") * F.col("reported"))
    least = seen.groupBy("cls").agg(F.coalesce(F.min(F.when(allowed, F.col("bin"))), F.lit(BINS)).alias("least"))
    return least.agg(F.transform(F.sort_array(F.collect_list(F.struct("cls", "least"))), lambda x: x["least"]).alias("least"))


def _joined(spans_: Column) -> Column:
    names = F.array(*[F.lit(k) for k in (*[k for k, _ in BASE], "random")])
    return F.array_join(F.transform(spans_, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan(docs: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """``doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_random`` for each row."""
    scratch = scratch or Scratch(docs.sparkSession, "secrets")
    ranks = scratch.write(random_ranks(docs.sparkSession), "ranks").select("ranks").scalar()
    rows = scratch.write(_rows(docs, ranks), "rows")
    least = scratch.write(thresholds(rows), "thresholds").select("least").scalar()
    found = rows.withColumn("least", least)
    kept = F.filter("runs", lambda r: r["bin"] >= F.element_at("least", r["cls"] + 1))
    added = F.transform(kept, lambda r: F.struct(r["start"].alias("start"), F.lit(len(BASE)).alias("kind"), r["end"].alias("end")))
    base = F.transform("base", lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end")))
    count = lambda c: F.size(c).cast("long")
    return found.select("doc_id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"), F.sha2(_joined(base), 256).alias("base_sha256"), _joined(F.sort_array(F.concat(base, added))).alias("spans"), count(kept).alias("n_random"))
