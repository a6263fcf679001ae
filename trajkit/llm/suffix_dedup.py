"""Removal of long repeated byte strings with suffix arrays.

Every byte covered by a string of ``span`` bytes that also starts earlier (smaller doc_id, or
earlier in the same document) goes.  Only places that can repeat get into suffix arrays:

1. Anchors: in every window of ``span`` bytes the substring of ``GRAM`` bytes with the least hash.
   Equal windows have equal anchors at equal offsets.  An anchor's context is all that windows
   around it can reach.
2. Anchors meet by hash.  Of equal contexts all but the first are removed whole; the first ones of
   different contexts around one anchor may share some windows and go on.
3. Their bytes are gathered in shards by anchor.  Each block of a shard gets a suffix array
   (Larsson-Sadakane refinement of ranks: 7, 14, 28, 56, 112 bytes, only groups still tied are
   sorted again) and Kasai's common prefixes; neighbours that share ``span`` bytes are one string.
   Blocks of one shard are merged by binary search of one's sorted strings among the other's.
4. The windows found, and the contexts of step 2, are cut out of their documents.

Texts travel compressed; anchors and places travel packed, some thousands to a row.  The number of
buckets follows spark.sql.shuffle.partitions, which is to be set by input size.

Edge cases: a null text is empty; rows that repeat an id and its text count as one document;
different texts under one id are ordered by their hash; a null id comes first; an empty table
gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .packed import BYTE_CODE, chunks, flat, mixed, powers
from .scratch import shuffle_parts, stored, table

SPAN = 100
GRAM = 64
REACH = SPAN - GRAM  # bytes of context on either side
BLOCK = 8192  # contexts of one suffix array
ANCHOR = np.dtype([("h", "<u8"), ("c", "<u8"), ("doc", "<i8"), ("pos", "<i4")])
PLACE = np.dtype([("doc", "<i8"), ("pos", "<i4")])


def _pack(a: np.ndarray) -> bytes:
    """Fields one after the other, so that like values lie together."""
    return b"".join(np.ascontiguousarray(a[f]).tobytes() for f in a.dtype.names)


def _unpack(x: bytes, kind: np.dtype) -> np.ndarray:
    n = len(x) // kind.itemsize
    out, at = np.empty(n, kind), 0
    for f in kind.names:
        size = kind[f].itemsize * n
        out[f] = np.frombuffer(x[at : at + size], kind[f])
        at += size
    return out


def _split(a: np.ndarray, key: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    order = np.argsort(key, kind="stable")
    key, a = key[order], a[order]
    cuts = np.flatnonzero(np.diff(key)) + 1
    for part, k in zip(np.split(a, cuts), key[np.concatenate([[0], cuts])] if len(key) else []):
        yield int(k), part


def bucket_of(h: np.ndarray, n: int) -> np.ndarray:
    return (mixed(h.astype(np.uint64)) % np.uint64(n)).astype(np.int32)


def _slide(a: np.ndarray, width: int, pick) -> np.ndarray:
    """pick over a[i : i + width] for every i (as far as the array goes)."""
    out, have = a, 1
    while have < width:
        step = min(have, width - have)
        nxt = out.copy()
        pick(out[:-step], out[step:], out=nxt[:-step])
        out, have = nxt, have + step
    return out


def anchors(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """h, c (context hash), document number and byte position of all anchors."""
    n = len(buf)
    none = np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    if n < SPAN:
        return none
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(BYTE_CODE[buf] * powers(n), out=total[1:])
    back = powers(n + 1, True)
    h = np.full(n, np.uint64(2**64 - 1))
    h[: n - GRAM + 1] = mixed((total[GRAM:] - total[: n - GRAM + 1]) * back[: n - GRAM + 1]) >> np.uint64(1)
    least = _slide(h, REACH + 1, np.minimum)
    ok = np.zeros(n + 1, np.int8)  # starts of windows that lie inside their document
    size = offs[1:] - offs[:-1]
    long = size >= SPAN
    ok[offs[:-1][long]] += 1
    ok[offs[1:][long] - SPAN + 1] -= 1
    least[np.cumsum(ok[:n]) == 0] = 0
    most = _slide(least[::-1].copy(), REACH + 1, np.maximum)[::-1]
    at = np.flatnonzero((most == h) & (most > 0))
    if not len(at):
        return none
    doc = np.searchsorted(offs, at, "right") - 1
    a, b = np.maximum(at - REACH, offs[doc]), np.minimum(at + GRAM + REACH, offs[doc + 1])
    c = mixed((total[b] - total[a]) * back[a] + (at - a).astype(np.uint64) * np.uint64(1000003) + (b - a).astype(np.uint64))
    return h[at], c, doc, at - offs[doc]


def _anchor_rows(buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for i, _, buf, offs in chunks(batch.column(1)):
                h, c, doc, pos = anchors(buf, offs)
                if not len(h):
                    continue
                a = np.empty(len(h), ANCHOR)
                a["h"], a["c"], a["doc"], a["pos"] = h, c, ids[i + doc], pos
                # Of equal contexts in this chunk only the first is sent in full.
                order = np.lexsort((a["pos"], a["doc"], mixed(a["h"] + mixed(a["c"]))))
                a = a[order]
                new = np.ones(len(a), bool)
                new[1:] = (a["h"][1:] != a["h"][:-1]) | (a["c"][1:] != a["c"][:-1])
                known, a = a[~new], a[new]
                a = a[np.lexsort((a["pos"], a["doc"]))]
                rows = [(k, _pack(part), b"") for k, part in _split(a, bucket_of(a["h"], buckets))]
                if len(known):
                    p = np.empty(len(known), PLACE)
                    p["doc"], p["pos"] = known["doc"], known["pos"]
                    rows += [(k, b"", _pack(part)) for k, part in _split(p, bucket_of(p["doc"], buckets))]
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.binary())], ["bucket", "anchors", "known"])

    return run


def _place_rows(full: np.ndarray, need: np.ndarray, buckets: int) -> pa.Table:
    rows = [(k, 0, _pack(part)) for k, part in _split(full, bucket_of(full["doc"], buckets))] if len(full) else []
    rows += [(k, 1, _pack(part)) for k, part in _split(need, bucket_of(need["doc"], buckets))] if len(need) else []
    return pa.table({"bucket": pa.array([r[0] for r in rows], pa.int32()), "kind": pa.array([r[1] for r in rows], pa.int32()), "places": pa.array([r[2] for r in rows], pa.binary())})


def _meet(buckets: int):
    """Anchors of one bucket -> places removed whole (kind 0), contexts to compare (kind 1)."""

    def run(group: pa.Table) -> pa.Table:
        pa.default_memory_pool().release_unused()  # of the group before
        packs = [x for x in group.column("anchors").to_pylist() if x]
        full = [_unpack(x, PLACE) for x in group.column("known").to_pylist() if x]
        need = np.zeros(0, np.dtype([*PLACE.descr, ("h", "<u8")]))
        if packs:
            hs = np.concatenate([np.frombuffer(x[: len(x) // ANCHOR.itemsize * 8], np.uint64) for x in packs])
            s = np.sort(hs)
            twice = np.unique(s[1:][s[1:] == s[:-1]])
            if len(twice):
                k = np.minimum(np.searchsorted(twice, hs), len(twice) - 1)
                keep, at, parts = twice[k] == hs, 0, []
                for x in packs:
                    n = len(x) // ANCHOR.itemsize
                    parts.append(_unpack(x, ANCHOR)[keep[at : at + n]])
                    at += n
                a = np.concatenate(parts)
                a = a[np.lexsort((a["pos"], a["doc"], a["c"], a["h"]))]
                new_h, new_c = np.ones(len(a), bool), np.ones(len(a), bool)
                new_h[1:] = a["h"][1:] != a["h"][:-1]
                new_c[1:] = new_h[1:] | (a["c"][1:] != a["c"][:-1])
                group_of = np.cumsum(new_h) - 1
                several = np.bincount(group_of, new_c)[group_of] > 1
                rest = a[~new_c]
                p = np.empty(len(rest), PLACE)
                p["doc"], p["pos"] = rest["doc"], rest["pos"]
                full.append(p)
                more = a[new_c & several]
                need = np.empty(len(more), need.dtype)
                for f in need.dtype.names:
                    need[f] = more[f]
        return _place_rows(np.concatenate(full) if full else np.zeros(0, PLACE), need, buckets)

    return run


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """bucket, doc, doc_id, text -> the same with compressed text and its size."""
    codec = pa.Codec("zstd", compression_level=1)
    for batch in batches:
        buf, offs = flat(batch.column(2))
        raw = memoryview(buf)
        z = [codec.compress(raw[a:b], asbytes=True) if b > a else b"" for a, b in zip(offs[:-1].tolist(), offs[1:].tolist())]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.diff(offs)), pa.array(z, pa.binary())], ["bucket", "doc", "n", "z"])


def _doc_places(packs: list[bytes], kind: np.dtype) -> tuple[np.ndarray, dict[int, tuple[int, int]]]:
    p = np.concatenate([_unpack(x, kind) for x in packs]) if packs else np.zeros(0, kind)
    p = p[np.lexsort((p["pos"], p["doc"]))]
    docs, first = np.unique(p["doc"], return_index=True)
    return p, {int(d): (int(a), int(b)) for d, a, b in zip(docs, first, [*first[1:], len(p)])}


def _contexts(buckets: int):
    """Documents and the places to compare of one bucket -> their contexts, by shard."""
    kind = np.dtype([*PLACE.descr, ("h", "<u8")])

    def run(docs: pa.Table, places: pa.Table) -> pa.Table:
        pa.default_memory_pool().release_unused()
        p, where = _doc_places(places.column("places").to_pylist(), kind)
        codec = pa.Codec("zstd")
        out: dict[int, list] = {}
        done = set()
        for d, n, z in zip(*(docs.column(c).to_pylist() for c in ("doc", "n", "z"))):
            if d not in where or d in done:
                continue
            done.add(d)
            text = codec.decompress(z, n, asbytes=True)
            own = p[slice(*where[d])]
            a, b = np.maximum(own["pos"] - REACH, 0), np.minimum(own["pos"] + GRAM + REACH, n)
            for x, y, q, k in zip(a.tolist(), b.tolist(), own["pos"].tolist(), bucket_of(own["h"], buckets).tolist()):
                out.setdefault(k, []).append((d, x, q - x, text[x:y]))
        rows = []
        for k, c in out.items():
            meta = np.array([(d, x, o, len(t)) for d, x, o, t in c], np.int64)
            rows.append((k, meta.tobytes(), b"".join(t for *_, t in c)))
        return pa.table({"bucket": pa.array([r[0] for r in rows], pa.int32()), "meta": pa.array([r[1] for r in rows], pa.binary()), "bytes": pa.array([r[2] for r in rows], pa.binary())})

    return run


def suffix_array(sym: np.ndarray, depth: int = 2 * SPAN) -> tuple[np.ndarray, np.ndarray]:
    """Order of all suffixes and their ranks (equal if equal to ``depth`` symbols).  sym: byte + 1,
    0 after each text; nothing is compared beyond a 0."""
    n = len(sym)
    width, bits = 7, 9
    pad = np.concatenate([sym.astype(np.int64), np.zeros(width, np.int64)])
    key = np.zeros(n, np.int64)
    open_ = np.ones(n, bool)
    for k in range(width):
        part = np.where(open_, pad[k : k + n], 0)
        open_ &= part > 0
        key = key << bits | part
    order = np.argsort(key, kind="stable")
    s = key[order]
    new = np.ones(n, bool)
    new[1:] = s[1:] != s[:-1]
    heads = np.flatnonzero(new)
    rank = np.empty(n, np.int64)
    rank[order] = np.repeat(heads, np.diff(np.append(heads, n)))
    ends = np.flatnonzero(sym == 0)
    left = ends[np.searchsorted(ends, np.arange(n))] - np.arange(n) if len(ends) else np.full(n, n)  # symbols before the end
    have = width
    while have < depth:
        tied = np.repeat(np.diff(np.append(heads, n)) > 1, np.diff(np.append(heads, n)))
        pos = np.flatnonzero(tied & (left[order] >= have))
        if not len(pos):
            break
        at = order[pos]
        # A suffix that ends inside the next stretch takes the rank of what is left of it.
        second = np.where(left[at] > have, rank[np.minimum(at + have, n - 1)] + 1, 0)
        again = np.lexsort((second, rank[at]))
        at, second = at[again], second[again]
        first = rank[at]
        # Suffixes that ended early keep the front of their group; the others follow in order.
        order[pos] = at
        split = np.ones(len(at), bool)
        split[1:] = (first[1:] != first[:-1]) | (second[1:] != second[:-1])
        head = np.flatnonzero(split)
        rank_new = pos[np.repeat(head, np.diff(np.append(head, len(at))))]
        rank[at] = rank_new
        new = np.zeros(n, bool)
        new[heads] = True
        new[pos[head]] = True
        heads = np.flatnonzero(new)
        have *= 2
    return order, rank


def kasai(sym: np.ndarray, order: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Common prefix of each suffix in ``order`` with the one before it.  Kasai's walk goes along
    each text and loses one symbol a step at most; all texts walk side by side."""
    n = len(sym)
    place = np.empty(n, np.int64)
    place[order] = np.arange(n)
    prev = np.where(place > 0, order[np.maximum(place - 1, 0)], -1)
    out = np.zeros(n, np.int64)
    h = np.zeros(len(starts), np.int64)
    for t in range(int(sizes.max()) if len(sizes) else 0):
        live = np.flatnonzero(sizes > t)
        i = starts[live] + t
        j = prev[i]
        m = np.where(j >= 0, np.maximum(h[live] - 1, 0), 0)
        run = np.flatnonzero(j >= 0)
        while len(run):
            a, b = i[run] + m[run], j[run] + m[run]
            same = (a < n) & (b < n)
            same[same] = (sym[a[same]] == sym[b[same]]) & (sym[a[same]] > 0)
            run = run[same]
            m[run] += 1
        h[live] = m
        out[place[i]] = m
    return out


class Block:
    """Distinct windows of some contexts in sorted order, each with its first place."""

    def __init__(self, meta: np.ndarray, raw: np.ndarray, starts: np.ndarray):
        self.removed: list[np.ndarray] = []
        n = int(meta[:, 3].sum()) + len(meta)
        sym = np.zeros(n, np.int16)
        begin = np.concatenate([[0], np.cumsum(meta[:, 3] + 1)])[:-1]
        inside = np.repeat(begin - np.concatenate([[0], np.cumsum(meta[:, 3])])[:-1], meta[:, 3]) + np.arange(int(meta[:, 3].sum()))
        src = np.repeat(starts - np.concatenate([[0], np.cumsum(meta[:, 3])])[:-1], meta[:, 3]) + np.arange(int(meta[:, 3].sum()))
        sym[inside] = raw[src].astype(np.int16) + 1
        order, _ = suffix_array(sym)
        lcp = kasai(sym, order, begin, meta[:, 3])
        ctx = np.searchsorted(begin, order, "right") - 1
        off = order - begin[ctx]
        whole = off + SPAN <= meta[ctx, 3]
        # Fewest common symbols between one whole window and the whole window before it.
        idx = np.flatnonzero(whole)
        if not len(idx):
            self.keys, self.doc, self.pos = np.zeros(0, f"S{SPAN}"), np.zeros(0, np.int64), np.zeros(0, np.int64)
            return
        low = np.minimum.reduceat(lcp[: idx[-1] + 1], np.concatenate([[0], idx[:-1] + 1]))
        new = low < SPAN
        new[0] = True
        group = np.cumsum(new) - 1
        doc, pos = meta[ctx[idx], 0], meta[ctx[idx], 1] + off[idx]
        by = np.lexsort((pos, doc, group))
        g = group[by]
        first = np.ones(len(g), bool)
        first[1:] = g[1:] != g[:-1]
        fd, fp = doc[by][first], pos[by][first]
        later = ~first & ~((doc[by] == fd[g]) & (pos[by] == fp[g]))  # one place can lie in two contexts
        self.removed.append(np.stack([doc[by][later], pos[by][later]], 1))
        rep = order[idx[np.flatnonzero(new)]]
        bytes_ = (sym[rep[:, None] + np.arange(SPAN)] - 1).astype(np.uint8)
        self.keys, self.doc, self.pos = np.ascontiguousarray(bytes_).view(f"S{SPAN}").ravel(), fd, fp

    def merge(self, other: Block) -> None:
        """Binary search of the other block's windows among these; of equal ones the later goes."""
        if not len(self.keys) or not len(other.keys):
            return
        k = np.minimum(np.searchsorted(self.keys, other.keys), len(self.keys) - 1)
        hit = np.flatnonzero(self.keys[k] == other.keys)
        k = k[hit]
        mine = (self.doc[k] < other.doc[hit]) | ((self.doc[k] == other.doc[hit]) & (self.pos[k] < other.pos[hit]))
        same = (self.doc[k] == other.doc[hit]) & (self.pos[k] == other.pos[hit])
        other.removed.append(np.stack([other.doc[hit][mine], other.pos[hit][mine]], 1))
        self.removed.append(np.stack([self.doc[k][~mine & ~same], self.pos[k][~mine & ~same]], 1))


def _partners(meta: np.ndarray, raw: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Contexts that can share a window with another: half of a window's reach lies on one side of
    the anchor, so one of two strings around the anchor is shared."""
    total = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum(BYTE_CODE[raw] * powers(len(raw)), out=total[1:])
    back = powers(len(raw) + 1, True)
    keep = np.zeros(len(meta), bool)
    half = REACH // 2
    for a, b, ok in (
        (starts + meta[:, 2] - half, starts + meta[:, 2] + GRAM, meta[:, 2] >= half),
        (starts + meta[:, 2], starts + meta[:, 2] + GRAM + half, meta[:, 2] + GRAM + half <= meta[:, 3]),
    ):
        at = np.flatnonzero(ok)
        h = mixed((total[b[at]] - total[a[at]]) * back[a[at]])
        _, inv, n = np.unique(h, return_inverse=True, return_counts=True)
        keep[at[n[inv] > 1]] = True
    return keep


def _repeated(buckets: int):
    """Contexts of one shard -> starts of windows that also start earlier."""

    def run(group: pa.Table) -> pa.Table:
        meta = np.concatenate([np.frombuffer(x, np.int64).reshape(-1, 4) for x in group.column("meta").to_pylist()])
        raw = np.frombuffer(b"".join(group.column("bytes").to_pylist()), np.uint8)
        starts = np.concatenate([[0], np.cumsum(meta[:, 3])])[:-1]
        keep = np.flatnonzero(_partners(meta, raw, starts))
        blocks = [Block(meta[keep[i : i + BLOCK]], raw, starts[keep[i : i + BLOCK]]) for i in range(0, len(keep), BLOCK)]
        for i, one in enumerate(blocks):
            for two in blocks[i + 1 :]:
                one.merge(two)
        gone = [x for b in blocks for x in b.removed if len(x)]
        p = np.zeros(0, PLACE)
        if gone:
            both = np.unique(np.concatenate(gone), axis=0)
            p = np.empty(len(both), PLACE)
            p["doc"], p["pos"] = both[:, 0], both[:, 1]
        rows = [(k, 2, _pack(part)) for k, part in _split(p, bucket_of(p["doc"], buckets))] if len(p) else []
        return pa.table({"bucket": pa.array([r[0] for r in rows], pa.int32()), "kind": pa.array([r[1] for r in rows], pa.int32()), "places": pa.array([r[2] for r in rows], pa.binary())})

    return run


def _cut(keep_text: bool):
    """Documents and all removed places of one bucket -> results."""

    def run(docs: pa.Table, places: pa.Table) -> pa.Table:
        pa.default_memory_pool().release_unused()
        kinds = places.column("kind").to_pylist()
        packs = places.column("places").to_pylist()
        whole, at_whole = _doc_places([x for x, k in zip(packs, kinds) if k == 0], PLACE)
        start, at_start = _doc_places([x for x, k in zip(packs, kinds) if k == 2], PLACE)
        codec = pa.Codec("zstd")
        out = []
        for d, n, z in zip(*(docs.column(c).to_pylist() for c in ("doc", "n", "z"))):
            text = codec.decompress(z, n, asbytes=True) if n else b""
            lo, hi = [], []
            if d in at_whole:
                p = whole["pos"][slice(*at_whole[d])].astype(np.int64)
                lo.append(np.maximum(p - REACH, 0)), hi.append(np.minimum(p, n - SPAN) + SPAN)
            if d in at_start:
                p = start["pos"][slice(*at_start[d])].astype(np.int64)
                lo.append(p), hi.append(p + SPAN)
            removed = spans = 0
            if lo:
                depth = np.zeros(n + 1, np.int64)
                np.add.at(depth, np.concatenate(lo), 1)
                np.add.at(depth, np.concatenate(hi), -1)
                gone = np.cumsum(depth[:n]) > 0
                removed = int(gone.sum())
                spans = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum())
                text = np.frombuffer(text, np.uint8)[~gone].tobytes()
            out.append((d, n, removed, spans, hashlib.sha256(text).hexdigest(), text if keep_text else None))
        cols = {"doc": pa.int64(), "n_bytes": pa.int64(), "n_removed": pa.int64(), "n_spans": pa.int64(), "kept_sha256": pa.string(), "kept": pa.binary()}
        return pa.table({c: pa.array([r[i] for r in out], t) for i, (c, t) in enumerate(cols.items()) if keep_text or c != "kept"})

    return run


def dedup(docs: DataFrame, keep_text: bool = False, buckets: int | None = None) -> DataFrame:
    """doc_id, text -> doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept, the bytes left)."""
    spark = docs.sparkSession
    buckets = buckets or shuffle_parts(spark)
    base = docs.select("doc_id", "text")
    marks = base.select("doc_id", F.xxhash64("text").alias("mark"))
    n = marks.groupBy("doc_id").agg(F.count("*").alias("n"), F.min("mark").alias("a"), F.max("mark").alias("b"))
    odd = n.filter("n > 1 AND a <> b OR doc_id IS NULL").limit(1).count()
    if odd:  # ids that are null or stand for several texts: number the texts
        order = stored(marks.distinct().withColumn("doc", F.row_number().over(W.partitionBy().orderBy(F.col("doc_id").asc_nulls_first(), "mark")).cast("long")))
        base = base.withColumn("mark", F.xxhash64("text")).alias("t").join(order.alias("o"), F.col("t.doc_id").eqNullSafe(F.col("o.doc_id")) & (F.col("t.mark") == F.col("o.mark"))).select("t.doc_id", "doc", "text")
        base = stored(base)
    else:
        base = base.withColumn("doc", F.col("doc_id").cast("long"))
    found = base.select("doc", "text").mapInArrow(_anchor_rows(buckets), "bucket int, anchors binary, known binary")
    places = stored(found.groupBy("bucket").applyInArrow(_meet(buckets), "bucket int, kind int, places binary"))

    def numbered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            k = bucket_of(batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64), buckets)
            yield from _texts([pa.RecordBatch.from_arrays([pa.array(k), batch.column(0), batch.column(1)], ["bucket", "doc", "text"])])

    packed = base.select("doc", "text").mapInArrow(numbered, "bucket int, doc long, n long, z binary")
    need = places.filter("kind = 1").select("bucket", "places")
    contexts = packed.groupBy("bucket").cogroup(need.groupBy("bucket")).applyInArrow(_contexts(buckets), "bucket int, meta binary, bytes binary")
    windows = contexts.groupBy("bucket").applyInArrow(_repeated(buckets), "bucket int, kind int, places binary")
    gone = places.filter("kind = 0").unionByName(windows)
    schema = "doc long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * keep_text
    got = packed.groupBy("bucket").cogroup(gone.groupBy("bucket")).applyInArrow(_cut(keep_text), schema)
    if odd:
        names = order.select("doc", "doc_id")
        return got.join(names, "doc").select("doc_id", *[c for c in got.columns if c != "doc"])
    return got.withColumnRenamed("doc", "doc_id")


def op3_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    return dedup(table(spark, sf_dir, "documents", "doc_id", "text"))
