"""Secret scanning with a battery of randomness tests.

Three base patterns (assignments, access key ids, long hexadecimal runs) are always reported.
Beside them every run of encoding characters of 20 or more is a candidate; runs are split at each
``=`` but padding at their end, so a name and its value are judged apart.  A candidate's encoding is
inferred from its characters (decimal, hexadecimal, base32, base64); under the hypothesis that it
was drawn at random from that alphabet, three tests each give a p-value: chi-squared uniformity of
the alphabet (cells pooled to the length), runs above and below the alphabet's middle, and serial
correlation of neighbours.  Fisher's method combines them.

Ordinary text rejects randomness, but short runs reject it less often, so candidates are judged
within classes of length: over all documents, Benjamini-Hochberg finds in each class the p-values
at which structure is a discovery at the false-discovery rate given, and of the others those that
also pass a length-aware floor and mix kinds of characters are reported as random.  Counts of
p-values on a fixed grid are all that leaves the executors for that.

Edge cases: a null text is empty; offsets are code points, ends exclusive; matches of one kind do
not overlap; repeated rows each get the result; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .packed import FOLD, chunks, runs
from .scratch import stored, table

# The base patterns.
ASSIGN = re.compile(rb"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
NAMED = (b"passw", b"secret", b"token", b"api")  # every assignment has one of these, folded
LEAST = {"assign": 6, "access": 20, "hex": 24}
KINDS = ("assign", "access", "hex", "random")
MIN_RUN = 20
GRID = 400  # p-values are counted by floor(-log10(p) * 20), up to this

HEX = np.zeros(256, bool)
HEX[[*range(0x30, 0x3A), *range(0x61, 0x67)]] = True
CODE = np.zeros(256, bool)
CODE[[*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *b"+/_=-"]] = True


def _alphabet(chars: str) -> np.ndarray:
    out = np.full(256, -1, np.int16)
    out[np.frombuffer(chars.encode(), np.uint8)] = np.arange(len(chars))
    return out


_UP, _LOW, _DIG = (bytes(range(a, b)).decode() for a, b in ((0x41, 0x5B), (0x61, 0x7B), (0x30, 0x3A)))
_B64 = _alphabet(_UP + _LOW + _DIG + "+/")
_B64[ord("-")], _B64[ord("_")] = 62, 63
_HEXL = _alphabet(_DIG + "abcdef")
_HEXU = _alphabet(_DIG + "ABCDEF")
ENCODINGS = [("decimal", _alphabet(_DIG), 10), ("hex", _HEXL, 16), ("hex", _HEXU, 16), ("base32", _alphabet(_UP + "234567"), 32), ("base64", _B64, 64)]


def chi2_tail(x: float, k: int) -> float:
    """P(chi-squared with k degrees >= x), by the Wilson-Hilferty approximation."""
    if x <= 0:
        return 1.0
    z = ((x / k) ** (1 / 3) - (1 - 2 / (9 * k))) / math.sqrt(2 / (9 * k))
    return 0.5 * math.erfc(z / math.sqrt(2))


def battery(codes: np.ndarray, size: int) -> float:
    """Combined p-value of the three tests for a run of alphabet positions."""
    n = len(codes)
    cells = max(2, min(size, n // 5))
    seen = np.bincount(codes.astype(np.int64) * cells // size, minlength=cells)
    share = np.bincount(np.arange(size) * cells // size, minlength=cells) / size
    p_uniform = chi2_tail(float(((seen - n * share) ** 2 / (n * share)).sum()), cells - 1)
    high = codes >= size / 2
    turns, a = int((high[1:] != high[:-1]).sum()) + 1, int(high.sum())
    b = n - a
    if a and b:
        mean = 2 * a * b / n + 1
        var = max(1e-9, (mean - 1) * (mean - 2) / (n - 1))
        p_runs = math.erfc(abs(turns - mean) / math.sqrt(2 * var))
    else:
        p_runs = 2.0 ** (1 - n)
    x = codes - codes.mean()
    ss = float((x * x).sum())
    r = float((x[1:] * x[:-1]).sum()) / ss if ss else 1.0
    p_serial = math.erfc(abs(r + 1 / n) * math.sqrt(n) / math.sqrt(2))
    stat = -2 * sum(math.log(max(p, 1e-300)) for p in (p_uniform, p_runs, p_serial))
    # Chi-squared tail with six degrees of freedom in closed form.
    half = stat / 2
    return min(1.0, math.exp(-half) * (1 + half + half * half / 2)) if half < 700 else 0.0


def encoding_of(raw: np.ndarray) -> tuple[np.ndarray, int] | None:
    for _, alphabet, size in ENCODINGS:
        codes = alphabet[raw]
        if (codes >= 0).all():
            return codes, size
    return None


def length_class(n: int) -> int:
    """Classes of length: powers of the square root of two from 20 on, at most 16."""
    return min(16, int(2 * math.log2(max(n, MIN_RUN) / MIN_RUN)))


def candidate(text: bytes, a: int, b: int) -> float | None:
    """p-value of a run, or None if its characters are of one kind or of no encoding."""
    raw = np.frombuffer(text[a:b].rstrip(b"="), np.uint8)
    if len(raw) < MIN_RUN:
        return None
    ranges = ((0x30, 0x39), (0x41, 0x5A), (0x61, 0x7A))
    digit, upper, lower = (bool(((raw >= a) & (raw <= b)).any()) for a, b in ranges)
    if not digit or not (upper or lower):
        return None
    found = encoding_of(raw)
    return battery(*found) if found else None


def parts(text: bytes, a: int, b: int) -> Iterator[tuple[int, int]]:
    """A run split at every "=" that is not padding at its end; the last part keeps the padding."""
    end = a + len(text[a:b].rstrip(b"="))
    while (cut := text.find(b"=", a, end)) >= 0:
        yield a, cut
        a = cut + 1
    yield a, b


def base_spans(text: bytes, hexes: list[tuple[int, int]], keyword: bool, akia: bool) -> list[tuple[int, int, int]]:
    """(start, end, kind number) in bytes."""
    out = [(a, b, 2) for a, b in hexes]
    if keyword:
        out += [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if m.end(1) - m.start(1) >= LEAST["assign"]]
    if akia:
        out += [(m.start(), m.end(), 1) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST["access"]]
    return out


def places(data: bytes, words: tuple[bytes, ...]) -> np.ndarray:
    """Starts of all occurrences of the words, overlapping ones too, in order.

    Texts lie end to end in ``data``; an occurrence across a border must not hide one behind it.
    It makes only its document be searched in vain."""
    out = []
    for w in words:
        at = data.find(w)
        while at >= 0:
            out.append(at)
            at = data.find(w, at + 1)
    return np.sort(np.array(out, np.int64))


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """doc_id, text -> doc_id, base spans and candidates (code points)."""
    for batch in batches:
        base, cand = [], []
        for _, _, buf, offs in chunks(batch.column(1)):
            hs, he = runs(HEX[buf], offs)
            long = he - hs >= LEAST["hex"]
            hs, he = hs[long], he[long]
            cs, ce = runs(CODE[buf], offs)
            long = ce - cs >= MIN_RUN
            cs, ce = cs[long], ce[long]
            hi, ci = np.searchsorted(hs, offs), np.searchsorted(cs, offs)
            data = buf.tobytes()
            keys, aks = places(FOLD[buf].tobytes(), NAMED), places(data, (b"AKIA",))
            ki, ai = np.searchsorted(keys, offs), np.searchsorted(aks, offs)
            for k, (a, b) in enumerate(zip(offs[:-1].tolist(), offs[1:].tolist())):
                has = ki[k] < ki[k + 1], ai[k] < ai[k + 1]
                if hi[k] == hi[k + 1] and ci[k] == ci[k + 1] and not any(has):
                    base.append([]), cand.append([])
                    continue
                text = data[a:b]
                spans = base_spans(text, [(int(x) - a, int(y) - a) for x, y in zip(hs[hi[k] : hi[k + 1]], he[hi[k] : hi[k + 1]])], *has)
                runs_ = zip(cs[ci[k] : ci[k + 1]].tolist(), ce[ci[k] : ci[k + 1]].tolist())
                tests = [(x - a, y - a, p) for run in runs_ for x, y in parts(data, *run) if (p := candidate(data, x, y)) is not None]
                at = None
                if not text.isascii():
                    at = np.concatenate([[0], np.cumsum((buf[a:b] & 0xC0) != 0x80)])
                to = (lambda x: int(at[x])) if at is not None else int
                base.append([{"start": to(x), "end": to(y), "kind": z} for x, y, z in spans])
                cand.append([{"start": to(x), "end": to(y), "len": y - x, "p": p} for x, y, p in tests])
        s = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.int32())]))
        c = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("len", pa.int32()), ("p", pa.float64())]))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(base, s), pa.array(cand, c)], ["doc_id", "base", "cand"])


def thresholds(counts: list[tuple[int, int, int]], rate: float, floor: float) -> dict[int, float]:
    """(length class, grid place of -log10 p, count) -> by class, the least p that counts as random.

    Benjamini-Hochberg on the grid: the largest p up to which structure is a discovery.  The
    floor tightens with the number of candidates of the class and loosens with length, as long
    runs that are not random are nearly always found out.
    """
    out = {}
    for k in {c for c, _, _ in counts}:
        own = sorted(((g, n) for c, g, n in counts if c == k), reverse=True)
        total, below, cut = sum(n for _, n in own), 0, 0.0
        for g, n in own:
            below += n
            p = 10 ** (-g / 20)
            if p <= rate * below / total:
                cut = p
        out[k] = max(cut, floor * 2.0 ** (-k / 2))
    return out


def scan(docs: DataFrame, rate: float = 0.05, floor: float = 0.01) -> DataFrame:
    """doc_id, text -> doc_id, spans array<struct<start, end, kind>>: base spans first, then random ones."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    found = stored(docs.select("doc_id", "text").mapInArrow(_scan, f"doc_id {kind}, base array<struct<start: int, end: int, kind: int>>, cand array<struct<start: int, end: int, len: int, p: double>>"))
    one = found.select(F.explode("cand").alias("c"))
    cls = lambda n: F.least(F.lit(16), F.floor(2 * F.log2(F.greatest(n, F.lit(MIN_RUN)) / float(MIN_RUN)))).cast("int")
    place = F.least(F.lit(GRID), F.floor(-20 * F.log10(F.greatest(F.col("c.p"), F.lit(1e-30))))).cast("int")
    counts = one.groupBy(cls(F.col("c.len")).alias("k"), place.alias("g")).count().collect()  # 17 classes x the grid at most
    limit = thresholds([(r["k"], r["g"], r["count"]) for r in counts], rate, floor)
    def random_enough(c):
        out = F.lit(False)
        for k, p in sorted(limit.items()):
            out = out | ((cls(c["len"]) == k) & (c["p"] > p))
        return out

    extra = F.transform(F.filter("cand", random_enough), lambda c: F.struct(c["start"].alias("start"), c["end"].alias("end"), F.lit(3).alias("kind")))
    spans = F.array_sort(F.concat("base", extra), lambda x, y: F.when(x["start"] != y["start"], x["start"] - y["start"]).otherwise(x["kind"] - y["kind"]))
    return found.select("doc_id", spans.alias("spans"))


def op7_secrets(spark, sf_dir: str) -> DataFrame:
    got = scan(table(spark, sf_dir, "documents", "doc_id", "text"))
    name = F.array(*[F.lit(k) for k in KINDS])
    joined = lambda s: F.array_join(F.transform(s, lambda x: F.concat_ws(":", F.element_at(name, x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("spans", lambda x: x["kind"] == k)).cast("long")
    base = F.filter("spans", lambda x: x["kind"] < 3)
    return got.select("doc_id", count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"), F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))


def plain_base(text: str | None) -> list[tuple[int, int, str]]:
    """Base spans by the patterns alone, for tests: (start, end, kind) in code points."""
    text = text or ""
    out = [(m.start(), m.end(), "assign") for m in re.finditer("""(?ai:(password|passwd|secret|token|api_?key))["']?\\x20*[:=]\\x20*["']?([A-Za-z0-9+/_.=-]+)""", text) if len(m[2]) >= 6]
    out += [(m.start(), m.end(), "access") for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    out += [(m.start(), m.end(), "hex") for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return sorted(out, key=lambda x: (x[0], KINDS.index(x[2])))


def digest(spans: list[tuple[int, int, str]]) -> str:
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, b, k in spans).encode()).hexdigest()
