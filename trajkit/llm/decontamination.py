"""Benchmark decontamination by a prefix-filtered set join (DataFrame functions only).

Items are cut into windows of ``window`` words (an item of fewer words is one window).  A window
occurs in a document only if all of its word shingles do, so its necessary prefix is one shingle:
the one that is rarest among the items' shingles, ties by hash.  Documents are scanned once; the
shingles at all word positions are looked up in the table of prefixes, candidates pass the length
and position bounds and are then compared word by word.

Edge cases: a null or wordless text has no words and is never hit; a wordless item has no window;
repeated item rows count once per item_id; repeated document rows each get the result.  Case is
folded for A-Z only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .scratch import stored, table

SPLIT = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words(text: Column) -> Column:
    """Words with their letters as they are; folding waits until words are compared."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPLIT), "")


def folded(ws: Column) -> Column:
    return F.transform(ws, lambda w: F.translate(w, UPPER, LOWER))


def shingle_hashes(low: Column, k: int) -> Column:
    """A hash of the k words from each position on; the last k - 1 entries are of no use."""
    pair = lambda a, b: F.xxhash64(a, b)
    n = F.size(low)
    rest = lambda x, s: F.slice(x, F.lit(s + 1), F.greatest(n - s, F.lit(0)))
    if k == 1:
        return F.transform(low, lambda w: F.xxhash64(w))
    two = F.zip_with(low, rest(low, 1), pair)
    if k == 2:
        return two
    if k == 3:
        return F.zip_with(two, rest(low, 2), pair)
    four = F.zip_with(two, rest(two, 2), pair)
    return four if k == 4 else F.zip_with(four, rest(low, 4), pair)


def prefixes(items: DataFrame, window: int = 13, shingle: int = 5) -> DataFrame:
    """One row per window: item_id, win (words), len, k, off (of the prefix shingle), h (its hash)."""
    it = items.select("item_id", words(F.col("text")).alias("ws")).filter(F.size("ws") > 0)
    it = it.withColumn("len", F.least(F.size("ws"), F.lit(window)))
    win = it.select("item_id", "len", F.explode(F.transform(F.sequence(F.lit(1), F.size("ws") - F.col("len") + 1), lambda s: F.slice("ws", s, F.col("len")))).alias("raw"))
    win = win.select("item_id", "len", folded(F.col("raw")).alias("win"), F.transform("raw", lambda w: F.lower(w)).alias("low")).dropDuplicates(["item_id", "win"])
    win = win.withColumn("k", F.least("len", F.lit(shingle)))
    hashes = F.when(F.col("k") == shingle, shingle_hashes(F.col("low"), shingle))
    for k in range(1, shingle):
        hashes = hashes.when(F.col("k") == k, shingle_hashes(F.col("low"), k))
    win = win.select("item_id", "win", "len", "k", F.slice(hashes, F.lit(1), F.col("len") - F.col("k") + 1).alias("hs"))
    each = win.select("*", F.posexplode("hs").alias("off", "h")).drop("hs")
    rarity = each.groupBy("k", "h").agg(F.count("*").alias("seen"))
    rank = W.partitionBy("item_id", "win").orderBy("seen", "h", "off")
    return each.join(rarity, ["k", "h"]).withColumn("nth", F.row_number().over(rank)).filter("nth = 1").drop("nth", "seen")


def _listed(base: DataFrame, ks: list[int], window: int) -> DataFrame:
    """The positions listed in ``at`` with their hash and the words around, and a last entry for the row itself."""
    seg = lambda i: F.floor(i / F.col("n")).cast("int")
    place = lambda i: (i - seg(i) * F.col("n")).cast("int")
    left = lambda i: F.greatest(place(i) + 1 - window, F.lit(0))
    about = lambda i: F.struct(
        F.element_at("hs", i + 1).alias("h"), F.element_at(F.array(*[F.lit(k) for k in ks]), seg(i) + 1).alias("dk"),
        place(i).alias("p"), left(i).alias("from"), F.slice("ws", left(i) + 1, F.lit(2 * window)).alias("around"),
    )
    whole = F.array(F.lit(None).cast("struct<h: bigint, dk: int, p: int, from: int, around: array<string>>"))
    at = base.select("doc_id", "mark", "n", F.explode_outer(F.concat(F.transform("at", about), whole)).alias("x"))
    return at.select("doc_id", "mark", "n", F.col("x").isNull().alias("is_row"), "x.*")


def scan(docs: DataFrame, items: DataFrame, window: int = 13, shingle: int = 5, listed_hashes: int = 50_000) -> DataFrame:
    """doc_id, text -> per row: doc_id, n_words, n_hit, hit_items (sorted ids as strings).

    If the prefix shingles have ``listed_hashes`` different hashes at most, the scan keeps only
    the positions whose hash is one of them, with the words around each, and the prefix table is
    broadcast.  Beyond that positions are joined with the prefix table, shuffled by hash; they carry
    no words: those are fetched for the candidates that pass the bounds.  Both ways find the same.
    """
    pre = stored(prefixes(items, window, shingle))
    ks = sorted({r["k"] for r in pre.select("k").distinct().collect()} | {shingle})
    hashes = [r["h"] for r in pre.select("h").distinct().limit(listed_hashes + 1).collect()]
    small = len(hashes) <= listed_hashes and pre.count() <= 8 * listed_hashes
    base = docs.select("doc_id", F.xxhash64("text").alias("mark"), words(F.col("text")).alias("ws"))
    base = base.withColumn("n", F.size("ws")).withColumn("low", F.transform("ws", lambda w: F.lower(w)))
    base = base.select("doc_id", "mark", "ws", "n", F.concat(*[shingle_hashes(F.col("low"), k) for k in ks]).alias("hs"))
    if small:
        wanted = (lambda h: h.isin(hashes)) if hashes else (lambda h: F.lit(False))
        base = base.withColumn("at", F.array_compact(F.transform("hs", lambda h, i: F.when(wanted(h), i))))
    start = F.col("p") - F.col("off")
    # Bounds come first: words are taken only where the window lies inside the document.
    fits = (start >= 0) & (start + F.col("len") <= F.col("n"))
    on = (F.col("h") == F.col("__h")) & (F.col("dk") == F.col("k"))
    right = pre.withColumnRenamed("h", "__h")
    if small:
        same = F.when(fits, folded(F.slice("around", F.greatest(start - F.col("from") + 1, F.lit(1)), F.coalesce("len", F.lit(1)))) == F.col("win")).otherwise(False)
        hit = _listed(base, ks, window).join(F.broadcast(right), on, "left").filter(F.col("is_row") | (F.col("win").isNotNull() & same))
        hit = hit.select("doc_id", "mark", "n", "is_row", "item_id", start.alias("start"), "len")
    else:
        each = base.select("doc_id", "mark", "n", F.posexplode("hs").alias("i", "h"))
        seg = F.floor(F.col("i") / F.col("n")).cast("int")
        each = each.select("doc_id", "mark", "n", "h", F.element_at(F.array(*[F.lit(k) for k in ks]), seg + 1).alias("dk"), (F.col("i") - seg * F.col("n")).cast("int").alias("p"))
        cand = each.join(right, on).filter(fits).select("doc_id", "mark", F.struct("item_id", start.alias("start"), "len", "win").alias("c"))
        cand = cand.groupBy(F.col("doc_id").alias("__id"), F.col("mark").alias("__mark")).agg(F.collect_set("c").alias("cs"))
        whole = F.array(F.lit(None).cast("struct<item_id: string, start: int, len: int>"))
        true = F.transform(F.filter("cs", lambda c: folded(F.slice("ws", c["start"] + 1, c["len"])) == c["win"]), lambda c: F.struct(c["item_id"].cast("string").alias("item_id"), c["start"].alias("start"), c["len"].alias("len")))
        hit = base.join(cand, (F.col("mark") == F.col("__mark")) & F.col("doc_id").eqNullSafe(F.col("__id")), "left")
        hit = hit.select("doc_id", "mark", "n", F.explode(F.concat(F.coalesce(true, F.array()), whole)).alias("x"))
        hit = hit.select("doc_id", "mark", "n", F.col("x").isNull().alias("is_row"), "x.*")
    start = F.col("start")
    found = F.when(~F.col("is_row"), F.struct(start.cast("long").alias("a"), (start + F.col("len")).cast("long").alias("b")))
    got = hit.groupBy("doc_id", "mark").agg(
        F.max("n").cast("long").alias("n_words"),
        F.sum(F.col("is_row").cast("int")).alias("rows"),
        F.collect_set(found).alias("runs"),
        F.collect_set(F.when(~F.col("is_row"), F.col("item_id").cast("string"))).alias("hit_items"),
    )
    zero = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("to"))
    covered = F.aggregate(
        F.array_sort("runs"), zero,
        lambda s, r: F.struct((s["n"] + F.greatest(F.lit(0).cast("long"), r["b"] - F.greatest(r["a"], s["to"]))).alias("n"), F.greatest(s["to"], r["b"]).alias("to")),
    )["n"]
    return got.select("doc_id", "mark", "n_words", covered.alias("n_hit"), F.array_sort("hit_items").alias("hit_items"), "rows")


def contaminated() -> Column:
    return (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))


def clean(docs: DataFrame, items: DataFrame, **options) -> DataFrame:
    """The documents that are not contaminated, with their columns."""
    bad = scan(docs, items, **options).filter(contaminated()).select(F.col("doc_id").alias("__id"), F.col("mark").alias("__mark"))
    same = F.col("__id").eqNullSafe(F.col("doc_id")) & (F.col("__mark") == F.xxhash64("text"))
    return docs.join(bad, same, "left_anti")


def op8_decontaminate(spark, sf_dir: str) -> DataFrame:
    got = scan(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))
    return got.select(
        "doc_id", "n_words", "n_hit", F.size("hit_items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "hit_items"), 256).alias("items_sha256"), contaminated().alias("contaminated"),
        F.explode(F.sequence(F.lit(1), F.col("rows"))).alias("__copy"),
    ).drop("__copy")


ORACLE = r"""
WITH d AS (SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS ws FROM documents),
i AS (SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
w AS (SELECT DISTINCT item_id, least(len(ws), 13) AS n, array_to_string(ws[s:s + least(len(ws), 13) - 1], ' ') AS win
      FROM (SELECT item_id, ws, unnest(range(1, len(ws) - least(len(ws), 13) + 2)) AS s FROM i WHERE len(ws) > 0)),
g AS (SELECT doc_id, n, s, array_to_string(ws[s:s + n - 1], ' ') AS win
      FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS s FROM d, (SELECT DISTINCT n FROM w) AS lens WHERE len(ws) >= n)),
h AS (SELECT g.doc_id, g.s, g.n, w.item_id FROM g JOIN w ON g.n = w.n AND g.win = w.win),
c AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM h) GROUP BY 1),
x AS (SELECT doc_id, count(*) AS n_items, string_agg(id, ',' ORDER BY id) AS ids FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS id FROM h) GROUP BY 1)
SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN x USING (doc_id)
"""
