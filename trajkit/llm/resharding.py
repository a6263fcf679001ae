"""Resharding by minimum-cost flow.

Old shards hold documents.  Given the old shards' bytes and the new shards' capacities, a
minimum-cost flow (successive cheapest paths over a graph with one node per shard) says how many
bytes each old shard sends to each new one; staying costs nothing, so the fewest bytes move.
Documents with equal texts are one group and stay together.  A group lies in the old shard that
holds most of it.  Groups of more than 1/``GRAIN`` of a shard are put first, largest first, where
the flow sends most of their old shard's bytes and they still fit; only a group that no shard has
room for is divided, row by row.  A second flow serves the rest: blocks of groups are laid end to
end inside their old shard and the flow cuts that line, so whole blocks move with one decision and
only the block at a cut is divided, between groups.

Slots follow a hash of the row, or with ``order="stored"`` the order in which the rows lie in the
files they were read from, so that a corpus sorted for training stays sorted in every shard.

Edge cases: a null text has no bytes (size 1, checksum 0) and is grouped with empty ones; null ids
are placed like any other; repeated rows are separate rows of one group; an empty table gives an
empty result.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .scratch import stored

HASH_PARTS = 1024  # rows of a shard are numbered in so many parts, or so many rows of a file at a time
STORED_ROWS = 20_000
GRAIN = 400  # shards of equal size differ by about a part in so many


def min_cost_flow(supply: Sequence[int], capacity: Sequence[int], cost: np.ndarray) -> np.ndarray:
    """flow[i, j] of least total cost that ships every supply within the capacities.

    Successive shortest augmenting paths (Bellman-Ford over the residual bipartite graph); sizes
    are numbers of shards, not of documents.
    """
    n, m = len(supply), len(capacity)
    if sum(supply) > sum(capacity):
        raise ValueError("the capacities are smaller than the supply")
    flow = np.zeros((n, m), dtype=object)
    left, room = [int(x) for x in supply], [int(x) for x in capacity]
    inf = float("inf")
    while any(left):
        dist = [0 if x else inf for x in left] + [inf] * m
        back: list[int | None] = [None] * (n + m)
        for _ in range(n + m):
            moved = False
            for i in range(n):
                for j in range(m):
                    if dist[i] + cost[i][j] < dist[n + j]:
                        dist[n + j], back[n + j], moved = dist[i] + cost[i][j], i, True
                    if flow[i, j] and dist[n + j] - cost[i][j] < dist[i]:
                        dist[i], back[i], moved = dist[n + j] - cost[i][j], n + j, True
            if not moved:
                break
        end = min((j for j in range(m) if room[j]), key=lambda j: (dist[n + j], j))
        path, at = [], n + end
        while back[at] is not None:
            path.append((back[at], at))
            at = back[at]
        push = min(left[at], room[end])
        for a, b in path:
            if a >= n:  # a step back over an arc that carries flow
                push = min(push, flow[b, a - n])
        for a, b in path:
            if a < n:
                flow[a, b - n] += push
            else:
                flow[b, a - n] -= push
        left[at] -= push
        room[end] -= push
    return flow


def fair_capacities(total: int, shards: int) -> list[int]:
    return [total // shards + (j < total % shards) for j in range(shards)]


def transfers(old_sizes: Sequence[int], capacities: Sequence[int]) -> np.ndarray:
    """Bytes that go from each old to each new shard; only bytes that change shard cost."""
    cost = np.array([[0 if i == j else 1 for j in range(len(capacities))] for i in range(len(old_sizes))])
    return min_cost_flow(old_sizes, capacities, cost)


def size_of(text: Column) -> Column:
    return (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long")


def by_source(count: int = 8) -> Column:
    """Where the query's documents lie before: one old shard for each group of sources."""
    return F.pmod(F.crc32(F.coalesce(F.col("source"), F.lit("")).cast("binary")), F.lit(count)).cast("int")


def levelled(loads: Sequence[int], supply: int) -> list[int]:
    """Room for ``supply`` more bytes that leaves the shards as even as can be."""
    order = sorted(range(len(loads)), key=lambda j: (loads[j], j))
    for k in range(len(order), 0, -1):  # the k emptiest shards take part
        level, over = divmod(supply + sum(loads[j] for j in order[:k]), k)
        if loads[order[k - 1]] <= level:
            break
    room = [0] * len(loads)
    for i, j in enumerate(order[:k]):
        room[j] = level - loads[j] + (i < over)
    return room


def pack(large: Sequence[tuple[int, int, int, int]], homes: Sequence[int], shards: int) -> tuple[dict[int, int], set[int], list[int]]:
    """(group, bytes, rows, home) of large groups -> their shards, the groups to divide, and the
    bytes put into each shard."""
    room = fair_capacities(sum(homes), shards)
    bins, loads = transfers(homes, room), [0] * shards
    placed, divided = {}, set()
    for group, size, rows, home in sorted(large, key=lambda g: (-g[1], g[0])):
        fits = [j for j in range(shards) if room[j] >= size]
        if not fits and rows > 1:
            divided.add(group)
            continue
        j = max(fits, key=lambda j: (bins[home, j], room[j], -j)) if fits else max(range(shards), key=lambda j: (room[j], -j))
        placed[group] = j
        room[j] -= size
        bins[home, j] -= size
        loads[j] += size
    return placed, divided, loads


def _keyed(docs: DataFrame, old: Column, order: str) -> DataFrame:
    crc = F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary"))
    out = docs.withColumns({"__size": size_of(F.col("text")), "__crc": crc, "__old": old, "__group": F.xxhash64(F.coalesce("text", F.lit("")))})
    out = out.withColumn("__row", F.xxhash64("doc_id", "__group", "__size"))
    if order == "stored":
        number = F.lpad(F.regexp_extract(F.col("_metadata.file_name"), r"^part-(\d+)", 1), 12, "0")
        file = F.concat(number, F.col("_metadata.file_path"))
        at = F.col("_metadata.row_index")
        return out.withColumns({"__at": at, "__part": F.struct(file.alias("file"), F.floor(at / STORED_ROWS).alias("chunk"))})
    return out.withColumns({"__at": F.col("__row"), "__part": F.pmod("__row", F.lit(HASH_PARTS)).cast("int")})


def with_shards(docs: DataFrame, shards: int = 8, old: Column | None = None, old_count: int = 8, blocks: int = 1024, order: str = "hash") -> DataFrame:
    """docs (doc_id, text, what ``old`` reads, any others) plus size, text_crc32, old_shard, shard, slot,
    which replace columns of those names.

    ``blocks`` per old shard are fixed and so are the large groups (``GRAIN`` * shards at most), so
    the driver reads old_count * blocks sums, those groups and a few cuts.  Decisions are broadcast
    and made row by row; texts are shuffled to look up where their group lies, if any group lies in
    several old shards, and to number the rows of each shard.
    """
    spark = docs.sparkSession
    old = by_source(old_count) if old is None else old
    base = stored(_keyed(docs, old, order).select("__size", "__old", "__group", "__row", "__part"))
    per = base.groupBy("__group", "__old").agg(F.sum("__size").alias("s"), F.count("*").alias("c"))
    groups = stored(per.groupBy("__group").agg(
        F.sum("s").alias("bytes"), F.sum("c").alias("rows"), F.max_by("__old", F.struct("s", -F.col("__old"))).alias("home"), F.count("*").alias("olds"),
    ))
    homes = [0] * old_count
    for r in groups.groupBy("home").agg(F.sum("bytes").alias("s")).collect():
        homes[r["home"]] = r["s"]
    grain = sum(homes) // (shards * GRAIN)
    large = [tuple(r) for r in groups.filter(F.col("bytes") > grain).select("__group", "bytes", "rows", "home").collect()]
    placed, divided, loads = pack(large, homes, shards)
    fixed = spark.createDataFrame([(g, placed.get(g)) for g, *_ in large], "__group long, __fixed int").withColumn("__large", F.lit(True))

    # What is left: units of the line are small groups, and rows of divided groups.
    unit = F.xxhash64(F.lit(23), "__group")
    block = F.pmod("__unit", F.lit(blocks)).cast("int")
    units = groups.filter(F.col("bytes") <= grain).select("home", unit.alias("__unit"), F.col("bytes").alias("size"))
    if divided:
        some = F.broadcast(spark.createDataFrame([(g,) for g in divided], "__group long"))
        units = units.unionByName(base.join(some, "__group").select(F.col("__old").alias("home"), F.col("__row").alias("__unit"), F.col("__size").alias("size")))
    units = units.withColumn("__block", block)
    sums = sorted((r["home"], r["__block"], r["s"]) for r in units.groupBy("home", "__block").agg(F.sum("size").alias("s")).collect())
    sizes, lines = [0] * old_count, []
    for i, k, s in sums:
        lines.append((i, k, sizes[i], s))
        sizes[i] += s
    flow = transfers(sizes, levelled(loads, sum(sizes)))
    targets = [[j for j in sorted(range(shards), key=lambda j: (j != i, j)) if flow[i, j]] for i in range(old_count)]
    ends = [np.cumsum([int(flow[i, j]) for j in targets[i]]).tolist()[:-1] for i in range(old_count)]
    cut = [(i, k, offset, [e for e in ends[i] if offset < e < offset + s]) for i, k, offset, s in lines]
    cut = [c for c in cut if c[3]]
    found: dict[tuple, list[int]] = {}
    if cut:  # only these blocks are divided; at most old_count * shards of them
        inside = W.partitionBy("home", "__block").orderBy("__unit").rowsBetween(W.unboundedPreceding, 0)
        some = spark.createDataFrame(cut, "home int, __block int, offset long, ends array<long>")
        rows = units.join(F.broadcast(some), ["home", "__block"])
        rows = rows.withColumn("middle", F.col("offset") + F.sum("size").over(inside) - F.col("size") / 2)
        each = rows.select("home", "__block", "__unit", "middle", F.posexplode("ends").alias("k", "end")).filter("middle >= end")
        for r in each.groupBy("home", "__block", "k").agg(F.min("__unit").alias("unit")).collect():
            found[r["home"], r["__block"], r["k"]] = r["unit"]
    inner = {(i, b): [found.get((i, b, k), 2**63 - 1) for k in range(len(e))] for i, b, _, e in cut}
    plan = [(i, b, targets[i], sum(e <= o for e in ends[i]), inner.get((i, b), [])) for i, b, o, _ in lines]
    plan = spark.createDataFrame(plan, "__home int, __block int, __targets array<int>, __from int, __cuts array<long>")
    apart = groups.filter((F.col("olds") > 1) & (F.col("bytes") <= grain)).select("__group", F.col("home").alias("__home"))
    scattered = apart.limit(1).count() > 0

    def sharded(df: DataFrame) -> DataFrame:
        df = df.join(F.broadcast(fixed), "__group", "left")
        if scattered:
            df = df.join(apart, "__group", "left").withColumn("__home", F.coalesce("__home", "__old"))
        else:
            df = df.withColumn("__home", F.col("__old"))
        df = df.withColumn("__unit", F.when(F.col("__large").isNull(), unit).otherwise(F.col("__row"))).withColumn("__block", block)
        nth = F.col("__from") + F.size(F.filter("__cuts", lambda c: c <= F.col("__unit")))
        to = F.element_at("__targets", F.least(F.size("__targets"), nth + 1))
        return df.join(F.broadcast(plan), ["__home", "__block"], "left").withColumn("__shard", F.coalesce("__fixed", to))

    counts = sharded(base).groupBy("__shard", "__part").agg(F.count("*").alias("__c"))
    before = F.sum("__c").over(W.partitionBy("__shard").orderBy("__part")) - F.col("__c")
    begin = counts.withColumn("__first", before).drop("__c")
    begin = F.broadcast(begin) if order == "hash" else begin  # shards * HASH_PARTS rows at most
    number = F.row_number().over(W.partitionBy("__shard", "__part").orderBy("__at"))
    out = sharded(_keyed(docs, old, order)).withColumn("__nth", number).join(begin, ["__shard", "__part"])
    new = {
        "size": F.col("__size"), "text_crc32": F.col("__crc"), "old_shard": F.col("__old"), "shard": F.col("__shard"),
        "slot": (F.col("__first") + F.col("__nth") - 1).cast("long"),
    }
    return out.select(*[F.col(f"`{c}`") for c in docs.columns if c not in new], *[v.alias(k) for k, v in new.items()])


def rewrite(docs: DataFrame, path: str, **options) -> list[int]:
    """Write below ``path`` the files of the shards that gain or lose a document; files of the
    other shards stay as they are.  Returns the numbers of the shards written."""
    rows = stored(with_shards(docs, **options))
    touched = sorted(r[0] for r in rows.filter("shard <> old_shard").select(F.explode(F.array("shard", "old_shard"))).distinct().collect())
    some = rows.filter(F.col("shard").isin(touched))
    some.repartitionByRange("shard", "slot").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("shard").parquet(path)
    return touched


def op5_reshard(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    return with_shards(docs).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "old_shard"
    )
