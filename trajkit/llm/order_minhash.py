"""Near duplicates by order MinHash.

Words are runs of digits, letters and bytes beyond ASCII, folded for A-Z; k-mers are five words
in a row (all words of a shorter text), labelled with their occurrence number, so a document has
each at most once.  A sketch keeps, for each of several hash functions, the few k-mers of least
hash in their text order; texts that share one ordered tuple are candidates.  A candidate is
verified by aligning the two k-mer sequences inside the band that the similarity allows: with
L k-mers aligned in order out of a and b, the similarity is L / (a + b - L).  Links of 0.8 or more
join documents into classes; a class is named by its smallest doc_id.

Most pairs of a bucket need no test.  In each round every bucket compares its members with a hub
of another class; classes are merged along the links found, and further rounds draw other hubs for
the buckets that still hold several classes and in which something changed within the last
``patience`` rounds, as long as a round finds a link for every ``worth`` rows that it carries (100):
later ones would carry large buckets again and again for a few links each.  Then all buckets that still hold several classes
are finished: every pair of members of different classes is tested that passes two bounds (sizes,
and counts of k-mers by hash) which no similar pair fails.  The rounds decide how much is left to
the finish, not which links are found.

Edge cases: texts without words (null, empty, punctuation) are alone in their class; rows without
doc_id take no part and get a null class; repeated rows share a class; an empty table gives an
empty result.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .packed import FOLD, chunks, flat, mixed, runs, span_hashes
from .scratch import stored, table

K = 5
BINS = 256  # k-mers are counted by hash in so many bins, for a bound on what two texts share
TILE = 256  # members of a bucket that one step of the finish compares with as many others
SALTS = 16  # tasks that the rows of one label are dealt over
_rng = np.random.default_rng(20240301)
MULT = _rng.integers(0, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
MASK = _rng.integers(0, 2**63, 64, dtype=np.uint64)
WORD_BYTE = np.zeros(256, bool)
WORD_BYTE[[*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)]] = True
TOP = np.uint64(2**64 - 1)


def word_hashes(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """32-bit word hashes in order, and where each document's begin (documents + 1)."""
    low = FOLD[buf]
    starts, ends = runs(WORD_BYTE[low], offs)
    h = (span_hashes(low, starts, ends) >> np.uint64(32)).astype(np.uint32) if len(starts) else np.zeros(0, np.uint32)
    return h, np.searchsorted(starts, offs)


def labelled_kmers(words: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Occurrence-labelled k-mers of all documents in order, and where each document's begin."""
    n = first[1:] - first[:-1]
    count = np.where(n >= K, n - K + 1, np.minimum(n, 1))
    begin = np.concatenate([[0], np.cumsum(count)])
    if not begin[-1]:
        return np.zeros(0, np.uint64), begin
    doc = np.repeat(np.arange(len(n)), count)
    at = np.arange(begin[-1]) - begin[doc] + first[:-1][doc]
    w = words.astype(np.uint64) + np.uint64(1)
    kmer = np.zeros(len(at), np.uint64)
    for j in range(K):
        inside = at + j < first[1:][doc]
        kmer = kmer * np.uint64(0x9E3779B97F4A7C15) + np.where(inside, w[np.minimum(at + j, len(w) - 1)], np.uint64(0))
    kmer = mixed(kmer)
    own = kmer ^ (doc.astype(np.uint64) * np.uint64(0xD1342543DE82EF95))
    order = np.argsort(own, kind="stable")
    s = own[order]
    new = np.ones(len(s), bool)
    new[1:] = s[1:] != s[:-1]
    if not new.all():
        heads = np.flatnonzero(new)
        occ = np.arange(len(s)) - np.repeat(heads, np.diff(np.append(heads, len(s))))
        rep = occ > 0
        kmer[order[rep]] = mixed(kmer[order[rep]] + occ[rep].astype(np.uint64))
    return kmer, begin


def sketches(kmers: np.ndarray, begin: np.ndarray, functions: int, length: int) -> np.ndarray:
    """documents x functions keys; rows of documents without k-mers are 0."""
    docs = len(begin) - 1
    out = np.zeros((docs, functions), np.uint64)
    full = np.flatnonzero(begin[1:] > begin[:-1])
    if not len(full):
        return out
    heads = begin[:-1][full]
    size = np.diff(np.append(heads, len(kmers)))
    for f in range(functions):
        v = (kmers ^ MASK[f]) * MULT[f]
        vals, pos = np.zeros((length, len(full)), np.uint64), np.full((length, len(full)), len(kmers), np.int64)
        for k in range(length):
            least = np.minimum.reduceat(v, heads)
            at = np.flatnonzero(v == np.repeat(least, size))
            d = np.searchsorted(heads, at, "right") - 1
            keep = least[d] != TOP  # fewer k-mers than asked for
            vals[k] = least
            pos[k, d[keep]] = at[keep]
            v[at] = TOP
        order = np.argsort(pos, axis=0, kind="stable")
        key = np.full(len(full), np.uint64(f + 1))
        for k in range(length):
            key = mixed(key * np.uint64(0x9E3779B97F4A7C15) + np.take_along_axis(vals, order[k : k + 1], 0)[0])
        out[full, f] = key
    return out


def increasing(values: list[int]) -> int:
    """Length of the longest increasing subsequence."""
    tails: list[int] = []
    for x in values:
        k = bisect_left(tails, x)
        if k == len(tails):
            tails.append(x)
        else:
            tails[k] = x
    return len(tails)


def similarity(a: np.ndarray, b: np.ndarray, least: float) -> float:
    """Ordered similarity of two labelled k-mer sequences; 0 as soon as it must be below ``least``.
    Each k-mer occurs once in either, so their best alignment is the longest chain of matches that
    increases in both, here within the band of shifts that ``least`` leaves possible."""
    na, nb = len(a), len(b)
    if not na or not nb or min(na, nb) < least * max(na, nb):
        return 0.0
    ia, ib = np.argsort(a, kind="stable"), np.argsort(b, kind="stable")
    sa, sb = a[ia], b[ib]
    k = np.minimum(np.searchsorted(sb, sa), nb - 1)
    hit = sb[k] == sa
    pa_, pb = ia[hit], ib[k[hit]]
    band = (1 - least) / (1 + least) * (na + nb)
    near = np.abs(pa_ - pb) <= band + 1e-9
    pa_, pb = pa_[near], pb[near]
    common = len(pa_)
    if common < least * (na + nb - common):
        return 0.0
    pb = pb[np.argsort(pa_)]
    chain = common if (np.diff(pb) > 0).all() else increasing(pb.tolist())
    sim = chain / (na + nb - chain)
    return sim if sim >= least else 0.0


def sketch_table(texts: DataFrame, functions: int, length: int) -> DataFrame:
    """tid, m, text -> tid, m, size (k-mers), keys; texts without words are left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, buf, offs in chunks(batch.column(2)):
                kmers, begin = labelled_kmers(*word_hashes(buf, offs))
                keys = sketches(kmers, begin, functions, length)
                full = np.flatnonzero(begin[1:] > begin[:-1])
                flat = pa.array(keys[full].reshape(-1).view(np.int64))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (len(full) + 1) * functions, functions, dtype=np.int32)), flat)
                take = pa.array(full + i)
                size = pa.array(np.diff(begin)[full])
                yield pa.RecordBatch.from_arrays([batch.column(0).take(take), batch.column(1).take(take), size, lists], ["tid", "m", "size", "keys"])

    return texts.select("tid", "m", "text").mapInArrow(run, "tid long, m long, size long, keys array<long>")


def word_sequences(texts: DataFrame) -> DataFrame:
    """tid, text -> tid, seq (packed 32-bit word hashes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, buf, offs in chunks(batch.column(1)):
                words, first = word_hashes(buf, offs)
                seqs = [words[first[k] : first[k + 1]].tobytes() for k in range(j - i)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(seqs, pa.binary())], ["tid", "seq"])

    return texts.select("tid", "text").mapInArrow(run, "tid long, seq binary")


def bin_counts(seqs: DataFrame) -> DataFrame:
    """tid, seq -> tid, bins: k-mers counted by hash, one byte a bin (255: that many or more)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, buf, offs in chunks(batch.column(1)):
                kmers, begin = labelled_kmers(np.frombuffer(buf.tobytes(), np.uint32), offs // 4)
                at = np.repeat(np.arange(j - i), np.diff(begin)) * BINS + (kmers >> np.uint64(56)).astype(np.int64)
                bins = np.minimum(np.bincount(at, minlength=(j - i) * BINS), 255).astype(np.uint8).reshape(-1, BINS)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array([b.tobytes() for b in bins], pa.binary())], ["tid", "bins"])

    return seqs.select("tid", "seq").mapInArrow(run, "tid long, bins binary")


STEP = ["key", "c", "kind", "lo", "hi"]


def steps(held: DataFrame, least: float, tile: int = TILE) -> DataFrame:
    """key, tid, ... -> the same rows once for each step of the finish they take part in.

    A bucket of up to ``tile`` members is one step (kind 0).  Larger ones are cut into classes of
    size, of which only equal and neighbouring ones can hold similar texts, and these by hash into
    tiles; kind 1 compares tiles lo and hi of class c, kind 2 tile lo of c with hi of c - 1.
    """
    held = held.withColumn("c", F.floor(F.log(F.col("size") + 0.5) / F.log(F.lit(1 / least))).cast("int"))
    n = held.groupBy("key", "c").agg(F.count("*").alias("n"))
    n = n.groupBy("key").agg(F.sum("n").alias("n"), F.map_from_entries(F.collect_list(F.struct("c", F.ceil(F.col("n") / tile).cast("int").alias("g")))).alias("tiles"))
    held = held.join(n, "key")
    of = lambda c: F.coalesce(F.try_element_at("tiles", c), F.lit(0))
    own = F.pmod(F.xxhash64(F.lit(17), "tid"), of(F.col("c"))).cast("int")
    step = lambda c, kind, lo, hi, side: F.struct(c.alias("c"), F.lit(kind).alias("kind"), lo.alias("lo"), hi.alias("hi"), side.alias("side"))
    each = lambda c, f: F.when(of(c) > 0, F.transform(F.sequence(F.lit(0), of(c) - 1), f)).otherwise(F.array())
    c, zero, one = F.col("c"), F.lit(0), F.lit(1)
    large = F.concat(
        each(c, lambda j: step(c, 1, F.least(F.col("own"), j), F.greatest(F.col("own"), j), F.when(j < F.col("own"), one).otherwise(zero))),
        each(c - 1, lambda j: step(c, 2, F.col("own"), j, zero)),
        each(c + 1, lambda j: step(c + 1, 2, j, F.col("own"), one)),
    )
    small = F.array(step(zero, 0, zero, zero, zero))
    held = held.withColumn("own", own).withColumn("step", F.explode(F.when(F.col("n") <= tile, small).otherwise(large)))
    return held.drop("c", "n", "tiles", "own").select("*", "step.*").drop("step")


def possible(held: DataFrame, sk: DataFrame, seqs: DataFrame, least: float, tile: int = TILE) -> DataFrame:
    """key, tid, size, label -> a, b, la, lb: all pairs of a bucket's members with different labels
    that can be similar enough, each from the first bucket that the two share.

    With L k-mers in common the bins of texts of a and b k-mers differ by a + b - 2 L at least, and
    similar texts have L >= least * (a + b) / (1 + least)."""
    more = sk.select("tid", "keys").join(bin_counts(seqs), "tid")
    rows = steps(held.select("key", "tid", "size", "label"), least, tile).join(more.hint("merge"), "tid")
    rows = rows.select(*STEP, "side", "tid", "size", "label", "keys", "bins").repartition(*STEP).sortWithinPartitions(*STEP)
    apart = (1 - least) / (1 + least)

    def pairs(t: pa.Table) -> pa.RecordBatch:
        col = {x: t.column(x).to_numpy() for x in (*STEP, "side", "tid", "size", "label")}
        keys = t.column("keys").combine_chunks().flatten().to_numpy().reshape(t.num_rows, -1)
        bins = flat(t.column("bins").combine_chunks())[0].reshape(-1, BINS).astype(np.int16)
        new = np.zeros(t.num_rows, bool)
        new[0] = True
        for x in STEP:
            new[1:] |= col[x][1:] != col[x][:-1]
        heads = np.append(np.flatnonzero(new), t.num_rows)
        tid, size, label, side = col["tid"], col["size"], col["label"], col["side"]
        out = [np.zeros((2, 0), np.int64)]
        for i, j in zip(heads[:-1].tolist(), heads[1:].tolist()):
            same = col["kind"][i] == 0 or (col["kind"][i] == 1 and col["lo"][i] == col["hi"][i])
            one = np.arange(i, j) if same else i + np.flatnonzero(side[i:j] == 0)
            two = one if same else i + np.flatnonzero(side[i:j] == 1)
            for k, x in enumerate(one.tolist()):
                ys = two[k + 1 :] if same else two
                ys = ys[(label[ys] != label[x]) & (np.minimum(size[ys], size[x]) >= least * np.maximum(size[ys], size[x]))]
                if len(ys):
                    ys = ys[np.abs(bins[ys] - bins[x]).sum(1) <= apart * (size[ys] + size[x]) + 1e-6]
                if len(ys):
                    ys = ys[keys[x][(keys[ys] == keys[x]).argmax(1)] == col["key"][i]]
                    out.append(np.stack([np.full(len(ys), x), ys]))
        x, y = np.concatenate(out, 1)
        x, y = np.where(tid[x] < tid[y], x, y), np.where(tid[x] < tid[y], y, x)
        return pa.RecordBatch.from_arrays([pa.array(v) for v in (tid[x], tid[y], label[x], label[y])], ["a", "b", "la", "lb"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[pa.RecordBatch] = []  # the step that the next batch may go on with
        for batch in batches:
            t = pa.Table.from_batches([*kept, batch])
            at, last = t.num_rows, t.slice(t.num_rows - 1, 1).select(STEP).to_pylist()[0]
            open_ = np.ones(at, bool)
            for x in STEP:
                open_ &= t.column(x).to_numpy() == last[x]
            at = int(open_.argmax()) if at else 0
            kept = t.slice(at).to_batches()
            if at:
                yield pairs(t.slice(0, at))
            del t, batch
            pa.default_memory_pool().release_unused()
        if kept:
            yield pairs(pa.Table.from_batches(kept))

    return rows.mapInArrow(run, "a long, b long, la long, lb long")


def verified(pairs: DataFrame, seqs: DataFrame, least: float) -> DataFrame:
    """a, b, la, lb -> those of the pairs that are similar enough."""
    one = seqs.select(F.col("tid").alias("a"), F.col("seq").alias("sa"))
    two = seqs.select(F.col("tid").alias("b"), F.col("seq").alias("sb"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def kmers(x: bytes) -> np.ndarray:
            w = np.frombuffer(x, np.uint32)
            return labelled_kmers(w, np.array([0, len(w)]))[0]

        for batch in batches:
            last, left = None, None
            keep = []
            for r in range(batch.num_rows):
                a = batch.column(0)[r].as_py()
                if a != last:
                    last, left = a, kmers(batch.column(4)[r].as_py())
                if similarity(left, kmers(batch.column(5)[r].as_py()), least):
                    keep.append(r)
            take = pa.array(keep, pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(i).take(take) for i in range(4)], ["a", "b", "la", "lb"])
            del batch
            pa.default_memory_pool().release_unused()

    both = pairs.join(one, "a").join(two, "b").select("a", "b", "la", "lb", "sa", "sb")
    return both.mapInArrow(run, "a long, b long, la long, lb long")


def components(links: DataFrame) -> DataFrame:
    """Links la, lb between ids -> m, label: the least id of each id's component.

    Labels travel along the links and then jump to their own label's label, so rounds grow with
    the logarithm of a component's diameter.
    """
    both = stored(links.select("la", "lb").unionByName(links.select(F.col("lb").alias("la"), F.col("la").alias("lb"))).filter("la <> lb").distinct())
    now = both.select(F.col("la").alias("m")).distinct().withColumn("label", F.col("m"))
    while True:
        sent = both.join(now.select(F.col("m").alias("lb"), "label"), "lb").groupBy("la").agg(F.min("label").alias("got"))
        step = now.join(sent.withColumnRenamed("la", "m"), "m").select("m", "label", F.least("label", "got").alias("new"))
        top = step.select(F.col("m").alias("__m"), F.col("new").alias("__new"))
        step = stored(step.join(top, F.col("new") == F.col("__m")).select("m", "label", F.least("new", "__new").alias("new")))
        now = step.select("m", F.col("new").alias("label"))
        if not step.filter("new < label").limit(1).count():
            return now


def relabelled(buckets: DataFrame, found: DataFrame) -> DataFrame:
    """One hop of each label along the links found: enough to leave most linked texts with one
    label.  What it leaves apart costs repeated tests, not links; ``components`` settles it."""
    to = found.select(F.col("la").alias("label"), F.col("lb").alias("to")).unionByName(found.select(F.col("lb").alias("label"), F.col("la").alias("to")))
    to = to.groupBy("label").agg(F.min("to").alias("to")).filter("to < label")
    # One label may hold a third of all rows, so each is dealt over several tasks.
    to = to.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    rows = buckets.withColumn("salt", F.pmod(F.xxhash64("tid", "key"), F.lit(SALTS)).cast("int"))
    return rows.join(to, ["label", "salt"], "left").withColumn("label", F.coalesce("to", "label")).drop("to", "salt")


def joined(state: DataFrame, links: DataFrame | None) -> DataFrame:
    """tid, m, label -> the same with the labels that ``links`` between labels lead to."""
    if links is None:
        return state
    to = components(links.select("la", "lb")).select(F.col("m").alias("label"), F.col("label").alias("to"))
    return stored(state.join(to, "label", "left").select("tid", "m", F.coalesce("to", "label").alias("label")))


def classes(docs: DataFrame, least: float = 0.8, functions: int = 16, length: int = 3, patience: int = 2, hubs_a_round: int = 1, worth: int = 100) -> DataFrame:
    """doc_id, text -> doc_id, class_id (the class's smallest doc_id), class_size."""
    ids = docs.select("doc_id", "text").withColumn("tid", F.xxhash64("text"))
    texts = ids.filter(F.col("doc_id").isNotNull() & F.col("text").isNotNull())
    who = stored(ids.select("doc_id", F.when(F.col("text").isNotNull(), F.col("tid")).alias("tid")))
    sk = sketch_table(texts.select("tid", F.col("doc_id").cast("long").alias("m"), "text"), functions, length)
    sk = stored(sk.groupBy("tid").agg(F.min("m").alias("m"), F.first("size").alias("size"), F.first("keys").alias("keys")))
    rows = sk.select("tid", "m", "size", F.explode("keys").alias("key"))
    shared = rows.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1").select("key")
    buckets = stored(rows.join(shared, "key"))
    wanted = stored(buckets.groupBy("tid").agg(F.min("m").alias("m")))
    chosen = wanted.select("tid", F.col("m").alias("doc_id"))
    # Word sequences only of texts in some bucket, from one row each.  The texts of a bucket grow
    # with the input, so this join is a shuffled one at any size.
    seqs = stored(word_sequences(texts.join(chosen.hint("merge"), ["tid", "doc_id"], "left_semi")).groupBy("tid").agg(F.first("seq").alias("seq")))
    held = buckets.select("key", "tid", "size", F.col("m").alias("label"), F.lit(None).cast("long").alias("mark"), F.lit(0).alias("idle"))
    links, turn, heard = None, 0, None
    while True:
        # The first hub of a bucket is its first text; later rounds draw several by hash.
        draws = 1 if turn == 0 else hubs_a_round
        order = lambda i: F.col("label") if turn == 0 else F.xxhash64(F.lit(100 * turn + i), "key", "tid")  # noqa: B023, E731
        hubs = held.groupBy("key").agg(
            *[F.min_by(F.struct("tid", "label", "size"), order(i)).alias(f"h{i}") for i in range(draws)], F.min("label").alias("lo"), F.max("label").alias("hi"),
            F.bit_xor(F.xxhash64("tid", "label")).alias("now"), F.first("mark").alias("was"), F.first("idle").alias("since"),
        )
        # A bucket rests once all its texts have one label, or after rounds that changed none; the
        # mark is that of the texts which stay when the hubs have met all others and go.
        idle = F.when(F.col("now") == F.col("was"), F.col("since") + 1).otherwise(0)
        drawn = F.array_distinct(F.array(*[f"h{i}" for i in range(draws)]))
        gone = F.aggregate(drawn, F.col("now"), lambda x, h: x.bitwiseXOR(F.xxhash64(h["tid"], h["label"])))
        hubs = hubs.filter("lo <> hi").select("key", drawn.alias("hubs"), gone.alias("mark"), idle.alias("idle")).filter(F.col("idle") < patience)
        held = stored(held.drop("mark", "idle").join(hubs, "key"))
        # A hub meets all members of its bucket in its round, so the finish can leave it out.
        met = held.filter(F.exists("hubs", lambda h: h["tid"] == F.col("tid"))).select("key", "tid")
        heard = met if heard is None else heard.unionByName(met)
        near = held.select("tid", "label", "size", F.explode("hubs").alias("hub"))
        near = near.filter((F.col("label") != F.col("hub.label")) & (F.least("size", "hub.size") >= least * F.greatest("size", "hub.size")))
        swap = F.col("tid") < F.col("hub.tid")
        end = lambda x, y: F.when(swap, F.col(x)).otherwise(F.col(y))  # noqa: B023, E731
        pairs = near.select(end("tid", "hub.tid").alias("a"), end("hub.tid", "tid").alias("b"), end("label", "hub.label").alias("la"), end("hub.label", "label").alias("lb")).distinct()
        found = stored(verified(pairs, seqs, least))
        some = found.count()
        if some:
            links = found if links is None else links.unionByName(found)
        # The finish takes every bucket from here, so where the rounds stop decides no link.
        if turn and some * worth <= held.count():
            break
        held = held.filter(~F.exists("hubs", lambda h: h["tid"] == F.col("tid"))).drop("hubs")
        if some:
            held = stored(relabelled(held, found))
        turn += 1
    # A text's label on a link was reached from its own id along labels of earlier links.
    state = joined(wanted.select("tid", "m", F.col("m").alias("label")), links)
    left = buckets.select("key", "tid", "size").join(heard, ["key", "tid"], "left_anti").join(state.select("tid", "label"), "tid")
    several = left.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo <> hi").select("key")
    left = stored(left.join(several, "key"))
    found = stored(verified(possible(left, sk, seqs, least), seqs, least))
    if found.limit(1).count():
        state = joined(state, found)
    # The label is the smallest id over all rows with the same text, and over the linked texts.
    texts_of = who.filter("tid IS NOT NULL AND doc_id IS NOT NULL").groupBy("tid").agg(F.min("doc_id").alias("first"))
    with_words = sk.select(F.col("tid"), F.lit(True).alias("has_words"))
    label = texts_of.join(with_words, "tid", "left").join(state.select("tid", "label"), "tid", "left")
    label = label.select("tid", "has_words", F.coalesce("label", "first").alias("label"))
    got = who.join(label, "tid", "left").select("doc_id", F.when(F.col("has_words"), F.col("label")).otherwise(F.col("doc_id")).cast("long").alias("class_id"))
    sizes = got.groupBy(F.col("class_id").alias("__class")).agg(F.count("*").alias("class_size"))
    return got.join(sizes, F.col("class_id").eqNullSafe(F.col("__class"))).select("doc_id", "class_id", "class_size")


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """The documents whose id names their class, and those without an id; one row each."""
    named = classes(docs, **options).filter("doc_id = class_id").select("doc_id").distinct()
    kept = docs.join(named, "doc_id", "left_semi").select(docs.columns)
    kept = kept.unionByName(docs.filter("doc_id IS NULL"))
    repeated = docs.filter("doc_id IS NOT NULL").groupBy("doc_id").count().filter("count > 1").limit(1).count()
    return kept.dropDuplicates(["doc_id", "text"]).dropDuplicates(["doc_id"]) if repeated else kept


def op10_order_minhash(spark, sf_dir: str) -> DataFrame:
    got = classes(table(spark, sf_dir, "documents", "doc_id", "text"))
    return got.select("doc_id", "class_id", "class_size", (F.col("doc_id") == F.col("class_id")).alias("kept"))
