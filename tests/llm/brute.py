"""Plain Python versions of the operators, for small inputs."""

import hashlib
import math
import re
import string
import struct

import xxhash

WHITE = " \t\n\x0b\x0c\r"
LOWER = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def sha(data):
    return hashlib.sha256(data if isinstance(data, bytes) else data.encode()).hexdigest()


def line_dedup(docs, min_docs):
    count = {}
    split = {i: (t or "").split("\n") for i, t in docs}
    key = lambda x: x.strip(WHITE).translate(LOWER)
    for lines in split.values():
        for k in {key(x) for x in lines}:
            count[k] = count.get(k, 0) + 1
    out = {}
    for i, lines in split.items():
        kept = [x for x in lines if not (key(x) and count[key(x)] >= min_docs)]
        out[i] = (len(lines), len(lines) - len(kept), sha("\n".join(kept)))
    return out


def substrings(docs, length):
    seen, out = set(), {}
    for i, t in sorted(docs):
        data = (t or "").encode()
        gone = bytearray(len(data))
        for p in range(len(data) - length + 1):
            s = data[p : p + length]
            if s in seen:
                gone[p : p + length] = b"\1" * length
            seen.add(s)
        spans = len(re.findall(rb"\x01+", bytes(gone)))
        out[i] = (len(data), sum(gone), spans, sha(bytes(b for b, g in zip(data, gone, strict=True) if not g)))
    return out


def fingerprint(text, k=3):
    w = (text or "").translate(LOWER)
    w = words(w)
    if not w:
        return 0
    runs = [" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] or [" ".join(w)]
    hs = [xxhash.xxh64_intdigest(r.encode(), 42) for r in runs]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def components(fps, bits=2):
    """fps: {id: fingerprint} -> {id: lowest id reached}."""
    ids = sorted(fps)
    up = {i: i for i in ids}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    first = {}
    for i in ids:
        j = first.setdefault(fps[i], i)
        up[root(i)] = root(j)
    distinct = sorted(first)
    for a, f in enumerate(distinct):
        for g in distinct[a + 1 :]:
            if (f ^ g).bit_count() <= bits:
                x, y = root(first[f]), root(first[g])
                up[max(x, y)] = min(x, y)
    low = {}
    for i in ids:
        low.setdefault(root(i), i)
    return {i: low[root(i)] for i in ids}


SECRETS = {
    "assign": re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""),
    "access": re.compile(r"AKIA[A-Z0-9]+"),
    "hex": re.compile(r"[0-9a-f]+"),
}


def secret_spans(text):
    t = text or ""
    out = [(m.start(), 0, m.end()) for m in SECRETS["assign"].finditer(t) if len(m[2]) >= 8]
    out += [(m.start(), 1, m.end()) for m in SECRETS["access"].finditer(t) if len(m[0]) >= 16]
    out += [(m.start(), 2, m.end()) for m in SECRETS["hex"].finditer(t) if len(m[0]) >= 32]
    return sorted(out)


def statistic(body, letters):
    """Minus the weighed sum of the logarithms of three tails: uniformity (four times), runs about the middle, correlation of neighbours."""
    n, k = len(body), len(letters)
    x = [letters.index(c) for c in body]
    chi = k / n * sum(body.count(c) ** 2 for c in set(body)) - n
    df = k - 1
    z_chi = ((chi / df) ** (1 / 3) - (1 - 2 / (9 * df))) / math.sqrt(2 / (9 * df))
    high = [v >= k / 2 for v in x]
    hi = sum(high)
    runs = 1 + sum(a != b for a, b in zip(high, high[1:]))
    twice = 2 * hi * (n - hi)
    z_runs = (runs - (1 + twice / n)) / math.sqrt(max(twice * (twice - n) / (n * n * (n - 1)), 1e-9))
    mean = sum(x) / n
    var = sum(v * v for v in x) / n - mean * mean
    z_serial = (sum(a * b for a, b in zip(x, x[1:])) / (n - 1) - mean * mean) / max(var, 1e-9) * math.sqrt(n)
    tail = lambda z: max(math.erfc(abs(z) / math.sqrt(2)), 1e-30)
    upper = tail(z_chi) / 2 if z_chi > 0 else 1 - tail(z_chi) / 2
    return -(4 * math.log(upper) + math.log(tail(z_runs)) + math.log(tail(z_serial)))


def random_string(i, a, n, letters):
    """Spark's hash of (long, int, int) chains XXH64 from seed 42; its remainder draws each letter."""
    h = xxhash.xxh64_intdigest(struct.pack("<i", a), xxhash.xxh64_intdigest(struct.pack("<q", i), 42))
    signed = lambda u: u - (1 << 64) if u >> 63 else u
    return "".join(letters[signed(xxhash.xxh64_intdigest(struct.pack("<i", j), h)) % len(letters)] for j in range(1, n + 1))


def random_spans(texts, alphabets, classes, ranks, pattern):
    """Spans of kind ``random`` of each text: runs that no base span overlaps, at or above the rank that their class allows."""
    runs = []
    for i, t in enumerate(texts):
        base = secret_spans(t)
        for m in re.finditer(pattern, t or ""):
            body = m[0].rstrip("=")
            held = next((k for k, (_, a) in enumerate(alphabets) if not set(body) - set(a)), None)
            if held is not None and not any(a < m.end() and m.start() < b for a, _, b in base):
                cls = max(k for k, (low, _, _) in enumerate(classes) if len(body) >= low)
                s = statistic(body, alphabets[held][1])
                runs.append((i, m.start(), m.end(), cls, sum(q > s for q in ranks[held * len(classes) + cls])))
    out = {i: [] for i in range(len(texts))}
    for k, (_, _, rate) in enumerate(classes):
        own = [r for r in runs if r[3] == k]
        top = sum(r[4] >= 75 for r in own)
        for least in range(100):
            reported = [r for r in own if r[4] >= least]
            if reported and len(reported) - top * (100 - least) / 25 <= rate * len(reported):
                for r in reported:
                    out[r[0]].append((r[1], 3, r[2]))
                break
    return out
