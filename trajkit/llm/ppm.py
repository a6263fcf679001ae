"""Language-model scores by prediction by partial matching over bytes.

The model is a trie of byte contexts up to five bytes long.  A symbol (a byte or the end of the
text) is predicted from the longest context seen in training; a context predicts the symbols seen
after it by their counts and escapes to the next shorter one with the number of different symbols
as the escape's count.  Symbols seen in the longer context are excluded in the shorter one.  A
text's score is the log10 probability of its bytes (A-Z folded) and its end.

Every symbol seen after a context was also seen after each shorter one, so an exclusion set is the
set of the next longer context; what it leaves of the shorter one is stored with the longer one.
The six-symbol grams of all documents are counted exactly, by whether they are training ones, and
the trie is a table for each order, one row a context (``Contexts``).  The log probability of every
distinct gram is worked out once, by joins with these tables; nothing is cut at any size.  A text's
score adds up its grams: the ``cached`` most frequent are looked up in a broadcast table, the others
in a join by gram.  The cache decides how a gram is looked up, not its value.  ``Adaptive`` is the
model that starts empty with each document.

The base score is a unigram model over words with one end token each: the words of highest count
are looked up in a broadcast table of at most ``max_words``, the others in the same join by hash.

Edge cases: a null text is empty (one end token); without training rows all counts are 0 and every
symbol has probability 1/257; repeated rows each get the result.
"""

from __future__ import annotations

import math
import os
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .packed import FOLD, SPACE, chunks, mixed, runs, span_hashes
from .samples import id_mod
from .scratch import Shared, stored, table

ORDER = 5
BITS = 9
SYMBOLS = 257
LOG10 = math.log(10)
SYMBOL_MASK = (1 << BITS) - 1
CHUNK = 1 << 19  # bytes of text that a worker has in wide arrays at once


def symbols(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Symbols (byte + 1; 0 before, after and between texts) and the places to predict; each text
    is followed by its end."""
    n = len(offs) - 1
    s = np.zeros(len(buf) + ORDER * (n + 1), np.uint64)
    doc = np.repeat(np.arange(n), np.diff(offs))
    s[np.arange(len(buf)) + ORDER * (doc + 1)] = FOLD[buf].astype(np.uint64) + np.uint64(1)
    size = np.diff(offs) + 1
    at = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size) + np.repeat(offs[:-1] + ORDER * (np.arange(n) + 1), size)
    return s, at


def grams(buf: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """The six-symbol gram that ends at each predicted symbol, text after text."""
    s, at = symbols(buf, offs)
    key = s.copy()
    for k in range(1, ORDER + 1):
        key[k:] |= s[:-k] << np.uint64(BITS * k)
    return key[at]


class Slots:
    """Open-addressing table from 64-bit keys to floats, filled and read in whole arrays."""

    EMPTY = np.uint64(2**64 - 1)

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        bits = max(8, int(2 * len(keys)).bit_length())
        self.mask = (1 << bits) - 1
        self.keys = np.full(1 << bits, self.EMPTY)
        self.values = np.zeros(1 << bits)
        left, at = np.arange(len(keys)), self._home(keys)
        self.probes = 0
        while len(left):
            self.probes += 1
            free = self.keys[at] == self.EMPTY
            self.keys[at[free]] = keys[left[free]]  # the last of those that want one slot has it
            won = self.keys[at] == keys[left]
            self.values[at[won]] = values[left[won]]
            left, at = left[~won], (at[~won] + 1) & self.mask

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return (mixed(keys) & np.uint64(self.mask)).astype(np.int64)

    def get(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(values, whether the key is there)"""
        at = self._home(keys)
        held = self.keys[at]
        found = held == keys
        out = np.where(found, self.values[at], 0.0)
        left = np.flatnonzero(~found & (held != self.EMPTY))
        while len(left):
            at[left] = (at[left] + 1) & self.mask
            held = self.keys[at[left]]
            hit = held == keys[left]
            out[left[hit]] = self.values[at[left[hit]]]
            found[left[hit]] = True
            left = left[~hit & (held != self.EMPTY)]
        return out, found


class Contexts:
    """The trie as tables.  ``order[o]``: one row for each context of ``o`` symbols seen in training,
    with the total and the number of the symbols after it, their counts, and what they leave of the
    next shorter context's total and number.  Every group here has at most 257 rows."""

    def __init__(self, grams: DataFrame):
        """grams: key, c (six-symbol grams with their training counts)."""
        self.order = {}
        low = lambda c, symbols_: c.bitwiseAND(F.lit((1 << BITS * symbols_) - 1))
        after = F.shiftright("key", BITS).alias("ctx")
        last = low(F.col("key"), 1).cast("int")
        for o in range(ORDER, -1, -1):
            own = grams.withColumn("short", low(F.col("key"), o))
            shorter = stored(own.groupBy(F.col("short").alias("key")).agg(F.sum("c").alias("c"))) if o else grams
            own = own.withColumn("below", F.sum("c").over(W.partitionBy("short")) if o else F.lit(0))
            # A gram of the highest order is found by its own row; shorter ones through their context.
            then = F.map_from_entries(F.collect_list(F.struct(last.alias("s"), F.col("c")))) if o < ORDER else F.lit(None).cast("map<int, bigint>")
            rows = own.groupBy(after).agg(F.sum("c").alias("n"), F.count("*").alias("t"), F.sum("below").alias("gone"), then.alias("next"))
            if o:
                less = shorter.groupBy(after).agg(F.sum("c").alias("n1"), F.count("*").alias("t1")).withColumnRenamed("ctx", "ctx1")
                less = F.broadcast(less) if o <= 2 else less  # at most 257 contexts of one symbol
                rows = rows.join(less, low(F.col("ctx"), o - 1) == F.col("ctx1"))
                rows = rows.select("ctx", "n", "t", "next", (F.col("n1") - F.col("gone")).alias("left_n"), (F.col("t1") - F.col("t")).alias("left_t"))
            else:
                rows = rows.select("ctx", "n", "t", "next", F.lit(0).cast("long").alias("left_n"), F.lit(0).cast("long").alias("left_t"))
            self.order[o] = stored(rows)
            grams = shorter
        start = self.order[0].select("t").first()
        self.new = SYMBOLS - (start["t"] if start else 0)  # symbols never seen

    def log_p(self, grams: DataFrame) -> DataFrame:
        """key, n (training count), m -> key, m, value: the log10 probability of each gram."""
        own = W.partitionBy(F.shiftright("key", BITS))
        total, kinds = F.sum("n").over(own), F.sum((F.col("n") > 0).cast("int")).over(own)
        rows = grams.withColumns({"total": total, "kinds": kinds})
        done = rows.filter("n > 0").select("key", "m", (F.log10(F.col("n") / (F.col("total") + F.col("kinds")))).alias("value"))
        left = rows.filter("n = 0").join(self.order[ORDER].select("ctx", "left_n", "left_t"), F.shiftright("key", BITS) == F.col("ctx"), "left")
        escape = F.when(F.col("kinds") > 0, F.log10(F.col("kinds") / (F.col("total") + F.col("kinds")))).otherwise(0.0)
        left = left.select("key", "m", escape.alias("value"), "left_n", "left_t")
        for o in range(ORDER - 1, -1, -1):
            ctx = F.shiftright("key", BITS).bitwiseAND(F.lit((1 << BITS * o) - 1))
            here = self.order[o].select("ctx", "n", "t", "next", F.col("left_n").alias("then_n"), F.col("left_t").alias("then_t"))
            here = F.broadcast(here) if o <= 1 else here  # at most 257 contexts
            both = left.join(here, ctx == F.col("ctx"), "left")
            both = both.withColumns({
                "c": F.try_element_at("next", F.col("key").bitwiseAND(F.lit(SYMBOL_MASK)).cast("int")),
                "n": F.coalesce("left_n", "n"), "t": F.coalesce("left_t", "t"), "seen": F.col("t").isNotNull(),
            })
            some = F.col("n") + F.col("t")
            step = F.when(F.col("c").isNotNull(), F.log10(F.col("c") / some)).when(F.col("seen") & (some > 0), F.log10(F.col("t") / some)).otherwise(0.0)
            both = stored(both.select("key", "m", (F.col("value") + step).alias("value"), F.col("c").isNotNull().alias("hit"), F.col("then_n").alias("left_n"), F.col("then_t").alias("left_t")))
            done = done.unionByName(both.filter("hit").select("key", "m", "value"))
            left = both.filter("NOT hit").drop("hit")
        return done.unionByName(left.select("key", "m", (F.col("value") - math.log10(max(self.new, 1))).alias("value")))


class Adaptive:
    """The same model kept in dictionaries, which learns as it reads (or only when told)."""

    def __init__(self, order: int = ORDER):
        self.order = order
        self.after: dict[tuple, dict[int, int]] = defaultdict(dict)

    def learn(self, ctx: tuple, s: int) -> None:
        for o in range(self.order + 1):
            d = self.after[ctx[len(ctx) - o :]]
            d[s] = d.get(s, 0) + 1

    def log_p(self, ctx: tuple, s: int) -> float:
        gone: set[int] = set()
        out = 0.0
        for o in range(self.order, -1, -1):
            d = self.after.get(ctx[len(ctx) - o :])
            if not d:
                continue
            n = sum(c for x, c in d.items() if x not in gone)
            t = sum(x not in gone for x in d)
            if s in d and s not in gone:
                return out + math.log(d[s] / (n + t))
            if n + t:
                out += math.log(t / (n + t))
            gone |= d.keys()
        return out - math.log(SYMBOLS - len(gone))

    def score(self, text: str | None, learn: bool = True) -> float:
        """log10 probability of a text and its end."""
        ctx, total = (0,) * self.order, 0.0
        for s in [*(b + 1 for b in (text or "").encode().translate(FOLD.tobytes())), 0]:
            total += self.log_p(ctx, s)
            if learn:
                self.learn(ctx, s)
            ctx = (*ctx, s)[-self.order :] if self.order else ()
        return total / LOG10


def tokens(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words, and where each document's begin (documents + 1)."""
    starts, ends = runs(~SPACE[buf], offs)
    return (span_hashes(FOLD[buf], starts, ends) if len(starts) else np.zeros(0, np.uint64)), np.searchsorted(starts, offs)


class _Tally:
    """Counts of keys, merged now and then; ``drain`` gives them up."""

    def __init__(self, most: int = 1 << 20):
        self.most, self.parts, self.size = most, [], 0

    def add(self, keys: np.ndarray) -> None:
        k, n = np.unique(keys, return_counts=True)
        self.parts.append((k, n))
        self.size += len(k)
        if self.size > 2 * self.most:
            self.merge()

    def merge(self) -> None:
        k = np.concatenate([p[0] for p in self.parts])
        n = np.concatenate([p[1] for p in self.parts])
        order = np.argsort(k, kind="stable")
        k, n = k[order], n[order]
        head = np.flatnonzero(np.append(True, k[1:] != k[:-1])) if len(k) else np.zeros(0, np.int64)
        self.parts = [(k[head], np.add.reduceat(n, head) if len(head) else n)]
        self.size = len(head)

    def drain(self) -> tuple[np.ndarray, np.ndarray]:
        if not self.parts:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self.merge()
        out, self.parts, self.size = self.parts[0], [], 0
        return out


def count_tables(docs: DataFrame) -> DataFrame:
    """text, train -> kind (0: training words, 1: training grams, 2: training documents, 3: other grams),
    key, n over all rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tallies, n_docs = {0: _Tally(), 1: _Tally(), 3: _Tally()}, 0

        def rows(kind: int, k: np.ndarray, n: np.ndarray) -> Iterator[pa.RecordBatch]:
            for i in range(0, len(k), 1 << 17):
                kk = k[i : i + (1 << 17)]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(kk), kind, np.int32)), pa.array(kk.view(np.int64)), pa.array(n[i : i + (1 << 17)].astype(np.int64))], ["kind", "key", "n"])

        for whole in batches:
            for train in (True, False):
                batch = whole.filter(whole.column(1) if train else pc.invert(whole.column(1)))
                n_docs += batch.num_rows if train else 0
                for _, _, buf, offs in chunks(batch.column(0), CHUNK):
                    if train:
                        tallies[0].add(tokens(buf, offs)[0])
                    tallies[1 if train else 3].add(grams(buf, offs))
                    for kind, tally in tallies.items():
                        if tally.size > tally.most:
                            tally.merge()
                            if tally.size > tally.most:
                                yield from rows(kind, *tally.drain())
        for kind, tally in tallies.items():
            yield from rows(kind, *tally.drain())
        yield from rows(2, np.zeros(1, np.uint64), np.array([n_docs]))

    parts = docs.select("text", "train").mapInArrow(run, "kind int, key long, n long")
    return parts.groupBy("kind", "key").agg(F.sum("n").alias("n"))


def cut_count(counts: DataFrame, most: int) -> int:
    """The least count at which at most ``most`` rows remain (counts in about 1,000 classes)."""
    bins = counts.groupBy(F.floor(F.log2("n") * 16).alias("b")).agg(F.count("*").alias("rows"), F.min("n").alias("least")).collect()
    total, cut = 0, None
    for b in sorted(bins, key=lambda r: -r["b"]):
        total += b["rows"]
        if total > most:
            break
        cut = b["least"]
    return cut if cut is not None else 1 + max((b["least"] for b in bins), default=0)


def _arrays(df: DataFrame, value: str) -> tuple[np.ndarray, np.ndarray]:
    t = df.select("key", value).toArrow()
    return t.column("key").to_numpy().view(np.uint64), t.column(value).to_numpy()


class Cache:
    """Log probabilities of the most frequent grams and words."""

    def __init__(self, grams_: tuple[np.ndarray, np.ndarray], words: tuple[np.ndarray, np.ndarray], ends: int, total: int, distinct: int):
        self.base = total + distinct + 1
        self.grams, self.words = Slots(*grams_), Slots(words[0], np.log10((words[1] + 1) / self.base))
        self.ends, self.total = ends, total


class Model:
    """``cache`` is broadcast; ``rest`` (kind, key, value, known) holds the grams (kind 1) and words
    (kind 0) that are not in it; a word in neither was not seen in training."""

    def __init__(self, cache: Cache, rest: DataFrame):
        self.cache, self.rest = cache, rest


def fit(docs: DataFrame, cached: int = 600_000, max_words: int = 131_072) -> Model:
    """text, train (boolean) -> the model of the training rows, with the values of all rows' grams."""
    tables = stored(count_tables(docs.select("text", F.coalesce("train", F.lit(False)).alias("train"))))
    words = tables.filter("kind = 0").select("key", "n")
    five = tables.filter("kind IN (1, 3)").groupBy("key").agg(F.sum(F.when(F.col("kind") == 1, F.col("n")).otherwise(0)).alias("n"), F.sum("n").alias("m"))
    five = stored(five)
    ends = tables.filter("kind = 2").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    n, v = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    values = stored(Contexts(five.filter("n > 0").select("key", F.col("n").alias("c"))).log_p(five))
    often = F.col("m") >= cut_count(five.select("key", F.col("m").alias("n")), cached)
    common = F.col("n") >= cut_count(words, max_words)
    cache = Cache(_arrays(values.filter(often), "value"), _arrays(words.filter(common), "n"), ends, n + ends, v + (ends > 0))
    rare = words.filter(~common).select(F.lit(0).alias("kind"), "key", F.log10((F.col("n") + 1) / F.lit(float(cache.base))).alias("value"), F.lit(1).alias("known"))
    return Model(cache, rare.unionByName(values.filter(~often).select(F.lit(1).alias("kind"), "key", "value", F.lit(0).alias("known"))))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, text of rows that the model was fitted with -> doc_id, n_tokens, n_known, base_score, score."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    shared = Shared(docs.sparkSession, model.cache)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        end = math.log10((m.ends + 1) / m.base)

        def sums(table_: Slots, keys: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            """Per document the sum of the values known and their number; and the keys not known."""
            value, known = table_.get(keys)
            total, some = np.append(0.0, np.cumsum(value)), np.append(0, np.cumsum(known))
            return total[first[1:]] - total[first[:-1]], some[first[1:]] - some[first[:-1]], keys[~known]

        for batch in batches:
            cols: list[list[np.ndarray]] = [[] for _ in range(4)]
            lost: list[list[np.ndarray]] = [[], []]  # words, grams
            size: list[list[np.ndarray]] = [[np.zeros(1, np.int64)], [np.zeros(1, np.int64)]]
            for i, j, buf, offs in chunks(batch.column(1), CHUNK):
                h, first = tokens(buf, offs)
                b, k, w = sums(m.words, h, first)
                at = offs + np.arange(len(offs))  # each text has one end
                s, found, g = sums(m.grams, grams(buf, offs), at)
                for c, x in zip(cols, (s, np.diff(first) + 1, k + (m.ends > 0), b + end)):
                    c.append(x)
                for q, keys, miss in ((0, w, np.diff(first) - k), (1, g, np.diff(at) - found)):
                    lost[q].append(keys)
                    size[q].append(miss)
            s, n, k, b = (np.concatenate(c) if c else np.zeros(0) for c in cols)
            lists = [pa.LargeListArray.from_arrays(pa.array(np.cumsum(np.concatenate(z))), pa.array(np.concatenate(x).view(np.int64) if x else np.zeros(0, np.int64))) for x, z in zip(lost, size)]
            row = np.frombuffer(os.urandom(8 * batch.num_rows), np.int64)  # names the row from here on
            lists = [x.cast(pa.list_(pa.int64())) for x in lists]
            yield pa.RecordBatch.from_arrays([pa.array(row), batch.column(0), pa.array(s), pa.array(n, pa.int64()), pa.array(k, pa.int64()), pa.array(b), *lists], ["row", "doc_id", "score", "n_tokens", "k", "b", "w", "g"])

    got = stored(docs.select("doc_id", "text").mapInArrow(run, f"row long, doc_id {kind}, score double, n_tokens long, k long, b double, w array<long>, g array<long>"))
    each = lambda number, name: got.select("row", F.lit(number).alias("kind"), F.explode(name).alias("key"))
    rest = each(0, "w").unionByName(each(1, "g")).join(model.rest, ["kind", "key"], "left")
    is_word = F.col("kind") == 0
    value: Column = F.coalesce("value", F.when(is_word, -math.log10(model.cache.base)))
    rest = rest.groupBy("row").agg(F.sum(F.when(is_word, value)).alias("b2"), F.sum("known").alias("k2"), F.sum(F.when(~is_word, value)).alias("s2"))
    zero = F.lit(0.0)
    return got.drop("w", "g").join(rest, "row", "left").select(
        "doc_id", "n_tokens", (F.col("k") + F.coalesce("k2", F.lit(0))).cast("long").alias("n_known"),
        (F.col("b") + F.coalesce("b2", zero)).alias("base_score"), (F.col("score") + F.coalesce("s2", zero)).alias("score"),
    )


def op4_ppm_score(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    model = fit(docs.withColumn("train", id_mod(7) != 2))
    got = score(docs, model)
    return got.select("doc_id", (id_mod(7) == 2).alias("held_out"), "n_tokens", "n_known", F.lit(model.cache.total).cast("long").alias("train_tokens"), "base_score", "score")
