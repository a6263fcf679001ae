"""Toxic spans by a linear-chain conditional random field over words.

A token's features are forms: hashes of the word, of its beginnings and endings and of the word with
the one before it.  A likelihood-ratio test over a bounded sample of labelled documents chooses the
forms that toxic documents have much more often; every one has a weight of its own in the field,
beside the weight of a bare token and those of the transitions between the two tags.

Labels are given by document.  They label all tokens of a clean document 0.  In a toxic document
tokens with a form of ``sure_odds`` or more are labelled 1 and the others are summed out; without
such a token some token is 1, and which one is summed out.  As the path without any 1 weighs one, a
document with partition Z is clean with probability 1 / Z, so the likelihood and its gradient come
from forward-backward passes (expected transitions and marginals, free and with the labelled tokens
held), and are climbed by L-BFGS.  Marginals of
a document's tokens give its offending offsets, and a logistic curve over their largest, their sum
and the log odds of any, fitted on the same documents, gives its score.

Stretches of tokens without any form share one transition matrix, so its powers (by its
eigenvalues) carry messages and their derivatives across them exactly, whatever their length.

Edge cases: null and empty texts score as a document without any marked token; without training
rows of both labels every score is the share of label 1 (0 without rows); repeated label rows of
a document count once, as toxic if one of them is.  Near copies within the sample count once.  The
fit does not depend on how rows are dealt to tasks: the sample is chosen and ordered by hashes.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .language import letters
from .packed import chunks, mixed, owners, runs, span_hashes
from .samples import bounded, id_mod
from .scratch import Shared, stored, table

PREFIXES = (4, 5, 6, 7)
SUFFIXES = (4, 5, 6)
BITMAP = 1 << 20


def form_hashes(low: np.ndarray, starts: np.ndarray, ends: np.ndarray, first: np.ndarray) -> list[np.ndarray]:
    """Hashes of each word, of its beginnings and endings and of the pair with the word before it;
    0 where there is none (a part as long as the word, the first word of a document)."""
    word = span_hashes(low, starts, ends)
    out = [word]
    for k in PREFIXES:
        h = span_hashes(low, starts, np.minimum(starts + k, ends)) ^ np.uint64(k)
        h[ends - starts <= k] = 0
        out.append(h)
    for k in SUFFIXES:
        h = span_hashes(low, np.maximum(ends - k, starts), ends) ^ np.uint64(k << 8)
        h[ends - starts <= k] = 0
        out.append(h)
    pair = mixed(np.append(np.zeros(1, np.uint64), word[:-1]) * np.uint64(0x9E3779B97F4A7C15) + word) if len(word) else word.copy()
    pair[first[:-1][first[:-1] < len(pair)]] = 0
    out.append(pair)
    return out


class Chains:
    """Marked tokens of several documents: ``count`` of each, the unmarked ones before each token
    (``gap``) and after the last of each document (``after``)."""

    def __init__(self, count: np.ndarray, gap: np.ndarray, after: np.ndarray):
        self.count, self.gap, self.after = count, gap, after
        self.first = np.append(0, np.cumsum(count))
        self.doc = np.repeat(np.arange(len(count)), count)
        # Documents by falling length: those that have a k-th token come first.
        self.order = np.argsort(-count, kind="stable")
        self.reach = np.searchsorted(-count[self.order], -np.arange(1, (count.max() if len(count) else 0) + 1), "right")

    def steps(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for k, n in enumerate(self.reach):
            docs = self.order[:n]
            yield docs, self.first[docs] + k


class Field:
    """Weights of the two-tag chain, and exact inference.  ``turn[before, after]``, ``bias`` of tag 1."""

    def __init__(self, bias: float, turn: np.ndarray):
        self.bias, self.turn = bias, turn
        g = self.g = np.exp(turn) * np.array([1.0, np.exp(bias)])
        tr, det = g[0, 0] + g[1, 1], g[0, 0] * g[1, 1] - g[0, 1] * g[1, 0]
        root = np.sqrt(max(tr * tr / 4 - det, 1e-300))
        self.big, self.low = tr / 2 + root, tr / 2 - root
        self.p = (g - self.low * np.eye(2)) / (self.big - self.low)  # projects on the larger eigenvalue

    def powers(self, gap: np.ndarray) -> np.ndarray:
        """The matrix of gap unmarked tokens, scaled by the larger eigenvalue's power."""
        decay = (self.low / self.big) ** gap.astype(np.float64)
        return self.p + decay[..., None, None] * (np.eye(2) - self.p)

    def tokens(self, extra: np.ndarray) -> np.ndarray:
        """Matrices of marked tokens whose forms add ``extra`` to the weight of tag 1."""
        e = np.stack([np.ones(len(extra)), np.exp(self.bias + extra)], -1)
        return np.exp(self.turn) * e[:, None, :]

    def run(self, c: Chains, extra: np.ndarray, gradient: bool = False, held: np.ndarray | None = None):
        """(log Z of each document, P(tag 1) of each marked token), and with ``gradient`` the sums over
        a document's places of d log Z by (bias, turn01, turn10, turn11); the tag of ``held`` tokens is 1."""
        n = len(c.count)
        over, tok, last = self.powers(c.gap), self.tokens(extra), self.powers(c.after)
        if held is not None:
            tok[held, :, 0] = 0.0
        m = over @ tok
        ahead, before = np.zeros((len(c.gap), 2)), np.zeros((len(c.gap), 2))
        a, log = np.tile([1.0, 0.0], (n, 1)), np.log(self.big) * (np.bincount(c.doc, c.gap, n) + c.after)
        for docs, at in c.steps():
            before[at] = a[docs]
            x = np.einsum("di,dij->dj", a[docs], m[at])
            s = x.sum(1)
            log[docs] += np.log(s)
            a[docs] = ahead[at] = x / s[:, None]
        b = last.sum(2)
        log += np.log((a * b).sum(1))
        behind = np.zeros((len(c.gap), 2))
        ends = b.copy()
        b = b / b.sum(1, keepdims=True)
        for docs, at in reversed(list(c.steps())):
            behind[at] = b[docs]
            x = np.einsum("dij,dj->di", m[at], b[docs])
            b[docs] = x / x.sum(1, keepdims=True)
        both = ahead * behind
        hot = both[:, 1] / both.sum(1) if len(both) else np.zeros(0)
        if not gradient:
            return log, hot
        # Marked tokens: expected transitions into them.
        into = np.einsum("ki,kij->kj", before, over)[:, :, None] * tok * behind[:, None, :]
        into /= into.sum((1, 2), keepdims=True)
        out = np.stack([np.bincount(c.doc, x, n) for x in (hot, into[:, 0, 1], into[:, 1, 0], into[:, 1, 1])], -1).astype(float)
        # Unmarked stretches: u' dG^gap v / u' G^gap v, before each marked token and at the end.
        u = np.concatenate([before, a])
        v = np.concatenate([np.einsum("kij,kj->ki", tok, behind), np.ones((n, 2))])
        size, owner = np.concatenate([c.gap, c.after]).astype(np.float64), np.concatenate([c.doc, np.arange(n)])
        total = np.concatenate([np.einsum("ki,kij,kj->k", before, over, v[: len(c.gap)]), (a * ends).sum(1)])
        ratio = self.low / self.big
        cross = (1 - ratio**size) / (self.big - self.low)
        weight = {(0, 0): size / self.big, (1, 1): np.where(size > 0, size * ratio ** np.maximum(size - 1, 0), 0.0) / self.big, (0, 1): cross, (1, 0): cross}
        side = (self.p, np.eye(2) - self.p)
        for j, cells in enumerate((((0, 1), (1, 1)), ((0, 1),), ((1, 0),), ((1, 1),))):
            d = np.zeros((2, 2))
            for cell in cells:
                d[cell] = self.g[cell]
            got = sum(w * np.einsum("ki,ij,kj->k", u, side[i] @ d @ side[k], v) for (i, k), w in weight.items())
            out[:, j] += np.bincount(owner, got / total, n)
        return log, hot, out


class ToxicModel:
    def __init__(self, forms: np.ndarray, weight: np.ndarray, field: Field, curve: np.ndarray):
        order = np.argsort(forms)
        self.forms, self.weight, self.field, self.curve = forms[order], weight[order], field, curve
        self.bits = np.zeros(BITMAP, bool)
        self.bits[(self.forms & np.uint64(BITMAP - 1)).astype(np.int64)] = True

    def matches(self, low: np.ndarray, starts: np.ndarray, ends: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(token, number of a form that it has), by token."""
        tok, form = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        if len(self.forms) and len(starts):
            for h in form_hashes(low, starts, ends, first):
                at = np.flatnonzero(self.bits[(h & np.uint64(BITMAP - 1)).astype(np.int64)])
                k = np.minimum(np.searchsorted(self.forms, h[at]), len(self.forms) - 1)
                ok = self.forms[k] == h[at]
                tok.append(at[ok])
                form.append(k[ok])
        tok, form = np.concatenate(tok), np.concatenate(form)
        order = np.lexsort((form, tok))
        return tok[order], form[order]

    def chains(self, buf: np.ndarray, offs: np.ndarray):
        """(chains, token of each match counted over marked ones, form of each match, starts, ends of marked tokens)"""
        low = letters(buf)
        starts, ends = runs(low != 0x20, offs)
        first = np.searchsorted(starts, offs)
        tok, form = self.matches(low, starts, ends, first)
        hit, nth = np.unique(tok, return_inverse=True)
        cut = np.searchsorted(hit, first)
        head = cut[:-1][cut[:-1] < cut[1:]]  # the first marked token of each document that has one
        prior = np.append(-1, hit[:-1]) if len(hit) else hit
        owner = owners(starts[hit], offs) if len(hit) else hit
        prior[head] = first[owner[head]] - 1
        last = np.where(cut[:-1] < cut[1:], hit[np.maximum(cut[1:] - 1, 0)] if len(hit) else 0, first[:-1] - 1)
        return Chains(np.diff(cut), hit - prior - 1, first[1:] - 1 - last), nth, form, starts[hit], ends[hit]

    def evidence(self, c: Chains, log: np.ndarray, hot: np.ndarray) -> np.ndarray:
        """Per document: 1, the largest marginal, log of 1 + their sum, log odds of any token of tag 1."""
        top = np.zeros(len(c.count))
        np.maximum.at(top, c.doc, hot)
        odds = np.log(np.expm1(np.clip(log, 1e-6, 30)))
        return np.stack([np.ones(len(top)), top, np.log1p(np.bincount(c.doc, hot, len(top))), np.clip(odds, -8, 8)], -1)

    def scores(self, buf: np.ndarray, offs: np.ndarray):
        """(score of each document, chains, marginals, starts, ends of marked tokens)"""
        c, nth, form, starts, ends = self.chains(buf, offs)
        log, hot = self.field.run(c, np.bincount(nth, self.weight[form], len(starts)))
        return 1 / (1 + np.exp(-np.clip(self.evidence(c, log, hot) @ self.curve, -30, 30))), c, hot, starts, ends


def climb(f: Callable[[np.ndarray], tuple[float, np.ndarray]], x: np.ndarray, rounds: int, memory: int = 8) -> np.ndarray:
    """Maximum of f (value, gradient) by L-BFGS with backtracking."""
    value, g = f(x)
    past: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(rounds):
        d, alphas = g.copy(), []
        for s, y in reversed(past):
            alphas.append((s @ d) / (s @ y))
            d -= alphas[-1] * y
        d *= (past[-1][0] @ past[-1][1]) / (past[-1][1] @ past[-1][1]) if past else 1 / max(1.0, np.linalg.norm(g))
        for (s, y), alpha in zip(past, reversed(alphas)):
            d += s * (alpha - (y @ d) / (s @ y))
        step, slope = 1.0, g @ d
        while step > 1e-6:
            new, g2 = f(x + step * d)
            if np.isfinite(new) and new >= value + 1e-4 * step * slope:
                break
            step /= 2
        else:
            return x
        s, y = step * d, g - g2
        if s @ y > 1e-10:
            past = [*past, (s, y)][-memory:]
        x, gain, value, g = x + s, new - value, new, g2
        if gain < 1e-7 * max(1.0, abs(value)):
            break
    return x


def fit_field(c: Chains, nth: np.ndarray, form: np.ndarray, toxic: np.ndarray, start: np.ndarray, sure: np.ndarray, rounds: int = 60, ridge: float = 0.1) -> tuple[Field, np.ndarray]:
    """Field and form weights of greatest penalised likelihood; ``start``: first weights; ``sure``: forms
    that label their tokens in toxic documents."""
    size = len(c.gap)
    held = toxic[c.doc] & (np.bincount(nth, sure[form], size) > 0)
    told = np.bincount(c.doc, held, len(c.count)) > 0

    def unpack(x: np.ndarray) -> tuple[Field, np.ndarray]:
        return Field(float(x[0]), np.array([[0.0, x[1]], [x[2], x[3]]])), x[4:]

    centre = np.concatenate([[-6.0, 0.0, 0.0, 1.0], np.zeros(len(start))])

    def value(x: np.ndarray) -> tuple[float, np.ndarray]:
        if np.abs(x).max() > 50:
            return -np.inf, x
        field, w = unpack(x)
        extra = np.bincount(nth, w[form], size)
        log, hot, chain = field.run(c, extra, gradient=True)
        log1, hot1, chain1 = field.run(c, extra, gradient=True, held=held)
        log = np.maximum(log, 1e-9)
        # Clean: log 1/Z.  Toxic: log (1 - 1/Z), whose slope in log Z is 1 / (Z - 1); with labelled
        # tokens the share of the paths that have them.
        slope = np.where(told, -1.0, np.where(toxic, 1 / np.expm1(np.minimum(log, 500)), -1.0))
        like = np.where(told, log1 - log, np.where(toxic, np.log(-np.expm1(-log)), -log)).sum()
        g = slope @ chain + told @ chain1
        g = np.concatenate([g, np.bincount(form, (slope[c.doc] * hot + told[c.doc] * hot1)[nth], len(w))])
        off = x - centre
        return float(like - ridge * (off @ off) / 2), g - ridge * off

    return unpack(climb(value, np.concatenate([centre[:4], start]), rounds))


def logistic(xs: np.ndarray, ys: np.ndarray, ridge: float = 0.05, rounds: int = 40) -> np.ndarray:
    w = np.zeros(xs.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(xs @ w, -30, 30)))
        g = xs.T @ (ys - p) - ridge * w
        hess = (xs * (p * (1 - p))[:, None]).T @ xs + ridge * np.eye(len(w))
        w = w + np.linalg.solve(hess, g)
    return w


def _marks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """toxic, text -> toxic, text and two least hashes of five words in a row: copies share them."""
    for batch in batches:
        out = [np.zeros(batch.num_rows, np.uint64) for _ in range(2)]
        for i, j, buf, offs in chunks(batch.column(1)):
            low = letters(buf)
            starts, ends = runs(low != 0x20, offs)
            first = np.searchsorted(starts, offs)
            h = span_hashes(low, starts, ends)
            five = mixed(sum((np.roll(h, -k) * np.uint64(2 * k + 3) for k in range(5)), np.zeros(len(h), np.uint64))) if len(h) else h
            for k in range(j - i):
                own = five[first[k] : max(first[k] + 1, first[k + 1] - 4)] if first[k + 1] > first[k] else np.zeros(1, np.uint64)
                out[0][i + k], out[1][i + k] = own.min(), mixed(own).min()
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(x.view(np.int64)) for x in out)], ["toxic", "text", "m0", "m1"])


def _forms_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Partial counts of the toxic and clean documents that have each form (toxic, text -> form, t, c)."""
    for batch in batches:
        toxic = np.array(batch.column(0).to_pylist(), np.int64)
        forms, bad = [], []
        for i, j, buf, offs in chunks(batch.column(1)):
            low = letters(buf)
            starts, ends = runs(low != 0x20, offs)
            if not len(starts):
                continue
            doc = owners(starts, offs)
            for h in form_hashes(low, starts, ends, np.searchsorted(starts, offs)):
                keep = h != 0
                order = np.lexsort((doc[keep], h[keep]))
                hs, ds = h[keep][order], doc[keep][order]
                new = np.ones(len(hs), bool)
                new[1:] = (hs[1:] != hs[:-1]) | (ds[1:] != ds[:-1])
                forms.append(hs[new])
                bad.append(toxic[i + ds[new]])
        if not forms:
            continue
        f, inv = np.unique(np.concatenate(forms), return_inverse=True)
        t = np.bincount(inv, np.concatenate(bad), len(f)).astype(np.int64)
        n = np.bincount(inv, minlength=len(f)).astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(f.view(np.int64)), pa.array(t), pa.array(n - t)], ["form", "t", "c"])


def fit(docs: DataFrame, labels: DataFrame, per_label: int = 2500, max_forms: int = 4096, least_odds: float = 1.5, least_stat: float = 30.0, sure_odds: float = 3.5, tasks: int = 8) -> ToxicModel | float:
    """docs (doc_id, text) and labels (doc_id, toxic).

    The sample has about ``per_label`` documents of each label at most; its ids are what is broadcast,
    and its marked tokens what the driver fits the field on.  A form is used if its log odds ratio
    and likelihood-ratio statistic reach ``least_odds`` and ``least_stat``; of more than
    ``max_forms`` the most significant.
    """
    one = labels.filter(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = bounded(one, "toxic", per_label)
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("toxic", "text").repartition(tasks)
    # Copies of one text would lend its words a significance they do not have.
    sample = sample.mapInArrow(_marks, "toxic int, text string, m0 long, m1 long")
    for mark in ("m0", "m1"):
        sample = sample.groupBy("toxic", mark).agg(F.min_by(F.struct("text", "m1"), F.struct(F.xxhash64("text"), "text")).alias("r")).select("toxic", "r.*")
    sample = stored(sample.select("toxic", "text"))
    n = {int(r["toxic"]): r["count"] for r in sample.groupBy("toxic").count().collect()}
    nt, nc = n.get(1, 0), n.get(0, 0)
    if not nt or not nc:
        return float(nt > 0) if nt + nc else 0.0
    counts = sample.mapInArrow(_forms_of, "form long, t long, c long").groupBy("form").agg(F.sum("t").alias("t"), F.sum("c").alias("c"))
    odds = F.log((F.col("t") + 0.5) / (nt + 1)) - F.log((F.col("c") + 0.5) / (nc + 1))
    # Likelihood-ratio statistic of the two shares against one common share.
    both = (F.col("t") + F.col("c")) / float(nt + nc)
    part = lambda x, e: F.when(x > 0, x * F.log(x / e)).otherwise(0.0)
    stat = 2 * (part(F.col("t"), nt * both) + part(F.col("c"), nc * both) + part(nt - F.col("t"), nt * (1 - both)) + part(nc - F.col("c"), nc * (1 - both)))
    strong = counts.withColumn("odds", odds).withColumn("stat", F.round(stat, 6)).filter((F.col("odds") > least_odds) & (F.col("stat") > least_stat) & (F.col("t") >= 4))
    forms = strong.orderBy(F.desc("stat"), "form").limit(max_forms).collect()
    hashes = np.array([r["form"] for r in forms], np.int64).view(np.uint64)
    shell = ToxicModel(hashes, np.array([r["odds"] for r in forms]), Field(0.0, np.zeros((2, 2))), np.zeros(4))
    shared = Shared(docs.sparkSession, shell)

    def marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            rows = []
            for _, _, buf, offs in chunks(batch.column(1)):
                c, nth, form, _, _ = m.chains(buf, offs)
                cut = np.searchsorted(nth, c.first)
                for k in range(len(offs) - 1):
                    own = slice(c.first[k], c.first[k + 1])
                    rows.append((c.gap[own].tolist(), int(c.after[k]), (nth[cut[k] : cut[k + 1]] - c.first[k]).tolist(), form[cut[k] : cut[k + 1]].tolist()))
            ints = pa.list_(pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[i] for r in rows], pa.int32() if i == 1 else ints) for i in range(4))], ["toxic", "gap", "after", "nth", "form"])

    seen = sample.mapInArrow(marked, "toxic int, gap array<int>, after int, nth array<int>, form array<int>").collect()
    seen.sort(key=lambda r: (r["toxic"], len(r["gap"]), r["after"], r["gap"], r["form"], r["nth"]))
    count = np.array([len(r["gap"]) for r in seen])
    flat = lambda name: np.array([x for r in seen for x in r[name]], np.int64)
    c = Chains(count, flat("gap"), np.array([r["after"] for r in seen]))
    nth = flat("nth") + np.repeat(c.first[:-1], [len(r["nth"]) for r in seen])
    form, toxic = flat("form"), np.array([r["toxic"] for r in seen]) == 1
    field, weight = fit_field(c, nth, form, toxic, 0.5 * shell.weight, shell.weight >= sure_odds)
    model = ToxicModel(shell.forms, weight, field, np.zeros(4))
    log, hot = field.run(c, np.bincount(nth, weight[form], len(c.gap)))
    model.curve = logistic(model.evidence(c, log, hot), toxic.astype(float))
    return model


def score(docs: DataFrame, model: ToxicModel | float, spans: bool = False) -> DataFrame:
    """doc_id, text -> doc_id, score; with ``spans`` also each marked token's place (code points)
    and marginal."""
    if isinstance(model, float):
        out = docs.select("doc_id", F.lit(model).alias("score"))
        return out.withColumn("spans", F.array().cast("array<struct<start: int, end: int, p: double>>")) if spans else out
    shared = Shared(docs.sparkSession, model)
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            scores, found = [np.zeros(0)], []
            for _, _, buf, offs in chunks(batch.column(1)):
                got, c, hot, starts, ends = m.scores(buf, offs)
                scores.append(got)
                if spans:
                    point = np.append(0, np.cumsum((buf & 0xC0) != 0x80))
                    for k in range(len(offs) - 1):
                        own = slice(c.first[k], c.first[k + 1])
                        found.append([{"start": int(point[x] - point[offs[k]]), "end": int(point[y] - point[offs[k]]), "p": float(p)} for x, y, p in zip(starts[own], ends[own], hot[own])])
            cols, names = [batch.column(0), pa.array(np.concatenate(scores), pa.float64())], ["doc_id", "score"]
            if spans:
                cols.append(pa.array(found, pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("p", pa.float64())]))))
                names.append("spans")
            yield pa.RecordBatch.from_arrays(cols, names)

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, score double" + ", spans array<struct<start: int, end: int, p: double>>" * spans)


def keep_below(docs: DataFrame, model: ToxicModel | float, least: float = 0.7) -> DataFrame:
    """The rows of ``docs`` (any columns beside text) that score below ``least``, in one pass."""
    if isinstance(model, float):
        return docs if model < least else docs.limit(0)
    shared = Shared(docs.sparkSession, model)
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            keep = [m.scores(buf, offs)[0] < least for _, _, buf, offs in chunks(batch.column(at))]
            yield batch.filter(pa.array(np.concatenate(keep) if keep else np.zeros(0, bool), pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op6_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    labels = table(spark, sf_dir, "labels", "doc_id", "toxic").filter(id_mod(3) != 1)
    model = fit(docs, labels)
    got = score(docs, model)
    return got.select("doc_id", (id_mod(3) == 1).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
