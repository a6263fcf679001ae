"""Language identification of mixed text.

Words are runs of letters.  A word's script, read from code point ranges, narrows its candidate
languages to those seen in that script; byte trigrams give a log probability per word and
candidate.  Viterbi with a penalty for switching labels every word, neighbours with one label make
a span, and the language with most words is the document's.  A document whose best single language
no stretch of words contradicts by more than one penalty needs no search: no path with a switch
can be better.

Edge cases: null texts and texts without letters are `und` with score 0; without any labelled row
every text is `und`; equal word counts go to the higher total score, then to the first name.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .packed import FOLD, chunks, owners, runs
from .samples import bounded, id_mod
from .scratch import Shared

# First and last code point of the main blocks of each script.
SCRIPT_RANGES = [
    ("Latin", 0x0041, 0x024F), ("Greek", 0x0370, 0x03FF), ("Cyrillic", 0x0400, 0x052F), ("Armenian", 0x0530, 0x058F),
    ("Hebrew", 0x0590, 0x05FF), ("Arabic", 0x0600, 0x06FF), ("Devanagari", 0x0900, 0x097F), ("Bengali", 0x0980, 0x09FF),
    ("Tamil", 0x0B80, 0x0BFF), ("Thai", 0x0E00, 0x0E7F), ("Georgian", 0x10A0, 0x10FF), ("Kana", 0x3040, 0x30FF),
    ("Han", 0x3400, 0x9FFF), ("Hangul", 0xAC00, 0xD7AF),
]
BUCKETS = 1 << 17
OTHER = len(SCRIPT_RANGES)


def _script_table() -> np.ndarray:
    """Script by the first two bytes of a code point's UTF-8 form (Latin where undecided)."""
    out = np.zeros(1 << 16, np.uint8)
    for cp in range(0x80, 0xFFFF, 0x20):
        if not 0xD800 <= cp <= 0xDFFF:
            b = chr(cp).encode()
            if (k := next((i for i, (_, a, z) in enumerate(SCRIPT_RANGES) if a <= cp <= z), OTHER)) != OTHER:
                out[b[0] << 8 | b[1]] = k
    return out


SCRIPT = _script_table()


def letters(buf: np.ndarray) -> np.ndarray:
    """Folded bytes; what is no letter is a space (bytes of other alphabets count as letters)."""
    out = FOLD[buf].copy()
    if len(out) > 1:
        accent = (buf[:-1] == 0xC3) & (buf[1:] >= 0x80) & (buf[1:] <= 0x9E) & (buf[1:] != 0x97)
        out[1:][accent] += 0x20
    out[~(((out >= 0x61) & (out <= 0x7A)) | (out >= 0x80))] = 0x20
    return out


def trigram_slots(low: np.ndarray) -> np.ndarray:
    """Table slot of the trigram around each byte; the text's ends count as spaces."""
    pad = np.full(len(low) + 2, 0x20, np.uint32)
    pad[1:-1] = low
    tri = pad[:-2] << np.uint32(16) | pad[1:-1] << np.uint32(8) | pad[2:]
    return (tri * np.uint32(0x9E3779B1)) >> np.uint32(32 - 17)


def word_scripts(low: np.ndarray, starts: np.ndarray) -> np.ndarray:
    if not len(starts):
        return np.zeros(0, np.uint8)
    nxt = np.append(low[1:], 0x20).astype(np.uint16)
    return np.maximum.reduceat(SCRIPT[low.astype(np.uint16) << np.uint16(8) | nxt] * (low >= 0xC0), starts)


class LanguageModel:
    """Trigram log probabilities and the languages of each script."""

    def __init__(self, langs: list[str], counts: np.ndarray, scripts: np.ndarray, penalty: float = 12.0, min_share: float = 0.01):
        self.langs, self.penalty = langs, penalty
        total = counts.sum(1, keepdims=True)
        self.logp = np.log((counts + 0.5) / (total + 0.5 * BUCKETS)).T.astype(np.float32).copy()
        seen = scripts.sum(1, keepdims=True)
        allowed = scripts >= np.maximum(1, min_share * seen)
        allowed |= ~allowed.any(1, keepdims=True)
        self.bar = np.where(allowed, 0.0, -40.0)

    def word_scores(self, buf: np.ndarray, offs: np.ndarray):
        """starts, ends and documents of the words, and their scores by language."""
        low = letters(buf)
        starts, ends = runs(low != 0x20, offs)
        if not len(starts):
            return starts, ends, starts, np.zeros((0, len(self.langs)))
        slots = trigram_slots(low)
        total = np.zeros((len(low) + 1, len(self.langs)))
        np.cumsum(self.logp[slots], axis=0, dtype=np.float64, out=total[1:])
        scores = total[ends] - total[starts] + self.bar[word_scripts(low, starts)]
        return starts, ends, owners(starts, offs), scores

    def label(self, scores: np.ndarray, first: np.ndarray, docs: int) -> np.ndarray:
        """Language number of every word; first: where each document's words begin (docs + 1)."""
        labels = np.zeros(len(scores), np.int16)
        filled = np.flatnonzero(first[1:] > first[:-1])
        if not len(filled):
            return labels
        heads = first[:-1][filled]
        best = np.argmax(np.add.reduceat(scores, heads, axis=0), axis=1)
        which = np.repeat(np.arange(len(filled)), (first[1:] - first[:-1])[filled])
        labels[:] = best[which]
        own = scores[np.arange(len(scores)), labels]
        rest = scores.copy()
        rest[np.arange(len(scores)), labels] = -np.inf
        gain = rest.max(1) - own if len(self.langs) > 1 else np.full(len(scores), -1.0)
        # Largest sum of consecutive gains by document; the offset makes the running minimum start anew.
        run = np.cumsum(gain)
        before = run - gain
        lift = (np.abs(gain).sum() + 1.0) * which
        peak = np.maximum.reduceat(run - lift - np.minimum.accumulate(before - lift), heads)
        for k in np.flatnonzero(peak > self.penalty):
            a, b = heads[k], first[1:][filled[k]]
            labels[a:b] = self.viterbi(scores[a:b])
        return labels

    def viterbi(self, scores: np.ndarray) -> np.ndarray:
        n, m = scores.shape
        value = scores[0].tolist()
        back = []
        pen = self.penalty
        for row in scores[1:].tolist():
            top = max(range(m), key=value.__getitem__)
            turn = value[top] - pen
            back.append([top if turn > x else j for j, x in enumerate(value)])
            value = [(turn if turn > x else x) + s for x, s in zip(value, row)]
        at = max(range(m), key=value.__getitem__)
        out = [at]
        for step in reversed(back):
            at = step[at]
            out.append(at)
        return np.array(out[::-1], np.int16)


def fit(docs: DataFrame, per_language: int = 1500, tasks: int = 8) -> LanguageModel | None:
    """doc_id, text, lang -> model.  The sample has about ``per_language`` documents a language at
    most; its trigrams are counted on the executors."""
    sample = bounded(docs.select("doc_id", "text", "lang"), "lang", per_language).select("lang", "text").repartition(tasks)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tri: dict[str, np.ndarray] = {}
        script: dict[str, np.ndarray] = {}
        for batch in batches:
            langs = batch.column(0).to_pylist()
            for i, j, buf, offs in chunks(batch.column(1)):
                for k in range(j - i):
                    lang, low = langs[i + k], letters(buf[offs[k] : offs[k + 1]])
                    starts, _ = runs(low != 0x20, np.array([0, len(low)]))
                    slots = trigram_slots(low)[low != 0x20]
                    tri.setdefault(lang, np.zeros(BUCKETS, np.int64))[:] += np.bincount(slots, minlength=BUCKETS)
                    script.setdefault(lang, np.zeros(OTHER + 1, np.int64))[:] += np.bincount(word_scripts(low, starts), minlength=OTHER + 1)
        rows = [(lang, (at := np.flatnonzero(c)).astype(np.int32).tobytes(), c[at].tobytes(), script[lang].tobytes()) for lang, c in tri.items()]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), *(pa.array([r[j] for r in rows], pa.binary()) for j in (1, 2, 3))], ["lang", "at", "n", "scripts"])

    parts = sample.mapInArrow(count, "lang string, at binary, n binary, scripts binary").collect()
    langs = sorted({r["lang"] for r in parts})
    if not langs:
        return None
    counts, scripts = np.zeros((len(langs), BUCKETS)), np.zeros((OTHER + 1, len(langs)))
    for r in parts:
        k = langs.index(r["lang"])
        counts[k, np.frombuffer(r["at"], np.int32)] += np.frombuffer(r["n"], np.int64)
        scripts[:, k] += np.frombuffer(r["scripts"], np.int64)
    return LanguageModel(langs, counts, scripts)


def has_letter(buf: np.ndarray) -> bool:
    return any(map(str.isalpha, buf.tobytes().decode("utf-8", "ignore")))


def predict(docs: DataFrame, model: LanguageModel | None, spans: bool = False) -> DataFrame:
    """doc_id, text -> doc_id, lang_pred, score; with ``spans`` also the labelled stretches
    (start, end in code points, lang)."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, lang_pred string, score double" + ", spans array<struct<start: int, end: int, lang: string>>" * spans
    if model is None:
        out = docs.select("doc_id", F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"))
        return out.withColumn("spans", F.array().cast("array<struct<start: int, end: int, lang: string>>")) if spans else out
    shared = Shared(docs.sparkSession, model)

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        names = np.array(m.langs)
        for batch in batches:
            preds, scores, found = [], [], []
            for i, j, buf, offs in chunks(batch.column(1)):
                starts, ends, doc, ws = m.word_scores(buf, offs)
                first = np.searchsorted(doc, np.arange(j - i + 1))
                labels = m.label(ws, first, j - i)
                ascii_words = buf[starts] < 0x80
                for k in range(j - i):
                    a, b = first[k], first[k + 1]
                    if a == b or not (ascii_words[a:b].any() or has_letter(buf[offs[k] : offs[k + 1]])):
                        preds.append("und"), scores.append(0.0), found.append([])
                        continue
                    votes = np.bincount(labels[a:b], minlength=len(names))
                    top = votes.max()
                    tied = np.flatnonzero(votes == top)
                    win = tied[0] if len(tied) == 1 else tied[np.argmax(ws[a:b, tied].sum(0))]
                    preds.append(names[win]), scores.append(float(top / (b - a)))
                    if spans:
                        heads = np.flatnonzero(np.diff(labels[a:b], prepend=-1))
                        tails = np.append(heads[1:], b - a) - 1
                        text = buf[offs[k] : offs[k + 1]]
                        at = np.concatenate([[0], np.cumsum((text & 0xC0) != 0x80)])
                        found.append([{"start": int(at[starts[a + h] - offs[k]]), "end": int(at[ends[a + t] - offs[k]]), "lang": str(names[labels[a + h]])} for h, t in zip(heads, tails)])
            cols = [batch.column(0), pa.array(preds, pa.string()), pa.array(scores, pa.float64())]
            names_out = ["doc_id", "lang_pred", "score"]
            if spans:
                cols.append(pa.array(found, pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("lang", pa.string())]))))
                names_out.append("spans")
            yield pa.RecordBatch.from_arrays(cols, names_out)

    return docs.select("doc_id", "text").mapInArrow(label, schema)


def op2_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    model = fit(docs.filter(id_mod(4) != 2))
    return predict(docs, model).select("doc_id", (id_mod(4) == 2).alias("held_out"), "lang_pred", "score")
