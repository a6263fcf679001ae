"""The credibility-guided ensemble: k-means rounds, cluster graph, normalised cut, consensus.

A round clusters the items that no earlier round has captured and captures those within ``eps`` of
their centre.  When all rounds are done one scan takes every item's distances to all centres:
it yields the labels of all rounds, what each round captures and the populations of the balls at
the midpoints of centres, since |x-m|^2 = |x-a|^2 / 2 + |x-b|^2 / 2 - |a-b|^2 / 4.  Items never
reach the driver; centres, edges and groups do (their number does not depend on the data's size).
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trajkit.operators import blocks as B, lloyd as L
from trajkit.operators.graphcut import components, normalized_cut


@dataclass(frozen=True)
class RoundOptions:
    k: int | tuple[int, ...] = 12
    eps: float = 2.0
    t_max: int = 10
    max_iter: int = 10
    stop: str = "captured"  # captured, remaining, both: fewer than k squared
    scope: str = "final_center"  # final_center, initial_center, trimmed
    seed: str = "0"

    def k_of(self, h: int) -> int:
        return self.k if isinstance(self.k, int) else self.k[min(h, len(self.k) - 1)]


@dataclass
class Rounds:
    centers: list[np.ndarray] = field(default_factory=list)
    balls: list[np.ndarray] = field(default_factory=list)  # centres of the capturing balls
    sizes: list[tuple[int, int]] = field(default_factory=list)  # pool, captured


def run_rounds(z: DataFrame | B.Blocks, cols: list[str], o: RoundOptions = RoundOptions()) -> Rounds:
    out, pool = Rounds(), z
    left = pool.count()
    for h in range(o.t_max):
        k = min(o.k_of(h), left)
        if stops(o, h, k, left):
            break
        if left * len(cols) <= L.ONE_TASK:
            return rounds_in_one_task(pool, cols, o, h, out)
        pool = B.packed(pool, cols)
        start = L.seeds(pool, cols, k, f"{o.seed}|{h}")
        centers = L.lloyd(pool, cols, k, start, o.max_iter, seed=f"{o.seed}|{h}")
        if o.scope == "trimmed":
            centers = L.step(pool, cols, centers, near=o.eps)
        balls = start if o.scope == "initial_center" else centers
        pool = L.outside(pool, cols, balls, o.eps)  # one pass writes what stays
        captured = left - pool.count()
        out.centers.append(centers)
        out.balls.append(balls)
        out.sizes.append((left, captured))
        left -= captured
        if few_captured(o, k, captured):
            break
    return out


def stops(o: RoundOptions, h: int, k: int, left: int) -> bool:
    """The rule on what is left speaks of what earlier rounds have left: one round always runs."""
    return not left or (h > 0 and o.stop in ("remaining", "both") and left < k * k)


def few_captured(o: RoundOptions, k: int, captured: int) -> bool:
    return o.stop in ("captured", "both") and captured < k * k


def local_rounds(ids: list, x: np.ndarray, o: RoundOptions, h: int) -> Rounds:
    """Round ``h`` and those after it over a pool that fits one task."""
    out = Rounds()
    for h in range(h, o.t_max):
        left = len(x)
        k = min(o.k_of(h), left)
        if stops(o, h, k, left):
            break
        seed = f"{o.seed}|{h}|"
        start = L.first_vectors([md5(f"{seed}{i}".encode()).digest() for i in ids], x, k)
        centers = L.iterate(start, o.max_iter, 1e-6, lambda c: L.moved_centers(x, L.closest(x, c)[0], c))  # noqa: B023
        if o.scope == "trimmed":
            label, d2 = L.closest(x, centers)
            near = d2 <= o.eps**2
            centers = L.moved_centers(x[near], label[near], centers)
        balls = start if o.scope == "initial_center" else centers
        stay = np.flatnonzero(L.closest(x, balls)[1] > o.eps**2)
        captured = left - len(stay)
        ids, x = [ids[i] for i in stay], x[stay]
        out.centers.append(centers)
        out.balls.append(balls)
        out.sizes.append((left, captured))
        if few_captured(o, k, captured):
            break
    return out


def rounds_in_one_task(pool: DataFrame | B.Blocks, cols: list[str], o: RoundOptions, h: int, before: Rounds) -> Rounds:
    """The rounds that are left, in one task: the same centres as by a job an iteration."""
    table, chunks = B.source(pool, cols)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, parts = [], [np.zeros((0, len(cols)))]
        for names, x in chunks(batches):
            ids += names.to_pylist()
            parts.append(x.T)
        r = local_rounds(ids, np.concatenate(parts), o, h)
        body = {"centers": [c.tolist() for c in r.centers], "balls": [c.tolist() for c in r.balls], "sizes": r.sizes}
        yield pa.RecordBatch.from_arrays([pa.array([json.dumps(body)])], ["body"])

    x = json.loads(table.coalesce(1).mapInArrow(run, "body string").first()[0])
    back = lambda c: np.array(c, float).reshape(-1, len(cols))
    return Rounds(before.centers + [back(c) for c in x["centers"]], before.balls + [back(c) for c in x["balls"]], before.sizes + [tuple(s) for s in x["sizes"]])


def scan(z: DataFrame, cols: list[str], r: Rounds, eps: float) -> DataFrame:
    """item_id, labels (one per round), dists, captured_at (null if never)."""
    names = z.columns
    sizes = [len(c) for c in r.centers]
    cuts = np.cumsum([0, *sizes])
    every = np.concatenate(r.centers) if sizes else np.zeros((0, len(cols)))
    balls = np.concatenate(r.balls) if sizes else every

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.column_stack([b.column(names.index(c)).to_numpy(zero_copy_only=False) for c in cols])
            labels, dists = np.zeros((len(x), len(sizes)), np.int32), np.zeros((len(x), len(sizes)))
            captured = np.full(len(x), -1)
            for h, (a, e) in enumerate(zip(cuts[:-1], cuts[1:])):
                d = np.round(((x[:, None, :] - every[None, a:e]) ** 2).sum(2), L.DIGITS)
                labels[:, h] = d.argmin(1)
                dists[:, h] = np.sqrt(d.min(1))
                near = np.round(((x[:, None, :] - balls[None, a:e]) ** 2).sum(2), L.DIGITS).min(1)
                captured[(captured < 0) & (near <= eps**2)] = h
            lists = lambda m, t: pa.ListArray.from_arrays(pa.array(np.arange(0, m.size + 1, max(1, m.shape[1]), dtype=np.int32)[: len(m) + 1]), pa.array(m.ravel(), t))
            yield pa.RecordBatch.from_arrays([b.column(names.index("item_id")), lists(labels, pa.int32()), lists(dists, pa.float64()), pa.array(captured, pa.int32(), mask=captured < 0)], ["item_id", "labels", "dists", "captured_at"])

    return z.mapInArrow(run, f"item_id {z.schema['item_id'].dataType.simpleString()}, labels array<int>, dists array<double>, captured_at int")


def classes(z: DataFrame | B.Blocks, cols: list[str], r: Rounds, eps: float, groups: np.ndarray, credible: bool) -> DataFrame:
    """item_id, captured_at, class in one pass, without the labels and distances on the way: the group of the
    round that captured the item, else the group of most rounds, the first of equals."""
    table, chunks = B.source(z, cols)
    cuts = np.cumsum([0, *(len(c) for c in r.centers)])
    named = [np.asarray(groups[a:e], np.int32) for a, e in zip(cuts[:-1], cuts[1:])]
    centers, balls, k = r.centers, r.balls, int(max(groups)) + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, x in chunks(batches):
            n = x.shape[1]
            votes, own, captured = np.zeros((k, n), np.int32), np.full(n, -1, np.int32), np.full(n, -1, np.int32)
            for h, (c, ball, name) in enumerate(zip(centers, balls, named)):
                g = name[B.labels(x, c, L.closest)]
                votes[g, np.arange(n)] += 1
                new = (captured < 0) & B.within(x, ball, eps, L.closest)
                captured[new], own[new] = h, g[new]
            most = votes.argmax(0).astype(np.int32)
            kind = np.where(captured >= 0, own, most) if credible else most
            yield pa.RecordBatch.from_arrays([ids, pa.array(captured, mask=captured < 0), pa.array(kind)], ["item_id", "captured_at", "class"])

    id_type = z.id_type if isinstance(z, B.Blocks) else z.schema["item_id"].dataType.simpleString()
    return table.mapInArrow(run, f"item_id {id_type}, captured_at int, class int")


def labels_long(scanned: DataFrame, eps: float) -> DataFrame:
    """item_id, h, label, dist, credible."""
    x = F.arrays_zip("labels", "dists")
    return scanned.select("item_id", F.posexplode(x).alias("h", "x")).select(
        "item_id", "h", F.col("x.labels").alias("label"), F.col("x.dists").alias("dist"), (F.col("x.dists") <= eps).alias("credible")
    )


def gated_pairs(centers: np.ndarray, eps: float, gate: float = 4.0, own: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs a < b (``own``: a = b too) of centres at most gate * eps apart, and their distances."""
    d = np.sqrt(((centers[:, None] - centers[None]) ** 2).sum(2))
    a, b = np.nonzero(np.triu(d <= gate * eps, 0 if own else 1))
    return a, b, d[a, b]


def affinity(z: DataFrame | B.Blocks, cols: list[str], centers: np.ndarray, eps: float, gate: float = 4.0, own: bool = False) -> DataFrame:
    """a, b, dist, pop, w: population of the ball at the midpoint over the distance.  Tasks send
    partial counts of pairs that have any; w is null for centres in one place.  With ``own`` the
    rows a = b give the population of each centre's own ball."""
    a, b, dist = gated_pairs(centers, eps, gate, own)
    table, chunks = B.source(z, cols, ids=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(a), np.int64)
        for _, x in chunks(batches):
            half, error = B.shifted(x, centers)
            half += np.einsum("ij,ij->j", x, x)
            half /= 2
            slack = 1e-8 + 4 * error
            near = (half <= (3 * eps) ** 2 / 2 + 1e-6 + slack).any(1)  # a ball at a midpoint lies within 3 eps of both
            near |= ~np.isfinite(half).all(1)
            for i in np.flatnonzero(near[a] & near[b]):
                m2 = half[a[i]] + half[b[i]]
                m2 -= dist[i] ** 2 / 4 + eps**2
                sure, may = np.count_nonzero(m2 < -slack), np.count_nonzero(m2 <= slack)
                if not slack < np.inf or sure != may:  # rounding may decide: the plain way for these rows
                    y = x[:, ~(np.abs(m2) > slack)].T
                    d2 = [((y - c) ** 2).sum(1) for c in (centers[a[i]], centers[b[i]])]
                    exact = np.round(d2[0] / 2 + d2[1] / 2 - dist[i] ** 2 / 4, L.DIGITS) <= eps**2
                    sure = np.count_nonzero((m2 < 0) & (np.abs(m2) > slack)) + np.count_nonzero(exact)
                total[i] += sure
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], ["pair", "pop"])

    counts = table.mapInArrow(run, "pair int, pop long").groupBy("pair").agg(F.sum("pop").alias("pop"))
    pairs = table.sparkSession.createDataFrame([(i, int(x), int(y), float(d)) for i, (x, y, d) in enumerate(zip(a, b, dist))], "pair int, a int, b int, dist double")
    w = F.when(F.col("dist") > 0, F.col("pop") / F.col("dist"))
    return pairs.join(counts, "pair", "left").select("a", "b", "dist", F.coalesce("pop", F.lit(0)).cast("long").alias("pop")).withColumn("w", w)


def weight_matrix(edges: list, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Symmetric weights and, for each node, the node it is merged into (same place)."""
    w, same = np.zeros((n, n)), np.arange(n)
    for a, b, dist, _, x in edges:
        if a == b:
            continue
        if dist == 0:
            same[same == same[b]] = same[a]
        elif x:
            w[a, b] = w[b, a] = x
    for node, head in enumerate(same):
        if node != head:
            w[head] += w[node]
            w[:, head] += w[:, node]
            w[node] = w[:, node] = 0
    np.fill_diagonal(w, 0)
    return w, same


def group_nodes(centers: np.ndarray, w: np.ndarray, same: np.ndarray, k: int | None, method: str = "spectral", mass: np.ndarray | None = None, least_mass: float = 0.02) -> np.ndarray:
    """A group for each node.  Connected parts whose balls hold less than ``least_mass`` of all
    (late rounds cluster outliers) join the nearest grouped centre, so that they do not use up a
    group; a part of one node that holds enough is a group of its own.  Without masses the nodes'
    edge weights stand for them."""
    mass = w.sum(1) if mass is None else mass
    part = components(w)
    held = np.bincount(part, mass)
    tied = np.flatnonzero((held > least_mass * held.sum())[part] & (np.arange(len(w)) == same))
    groups = np.full(len(centers), -1)
    if not len(tied):
        groups[:] = np.arange(len(centers)) % max(1, k or 1)
        return groups
    own = w[np.ix_(tied, tied)].copy()
    alone = np.flatnonzero(own.sum(1) == 0)
    own[alone, alone] = 1.0  # a loop makes it a part of its own in the spectrum
    groups[tied] = normalized_cut(own, k, method)
    for node in np.flatnonzero(groups < 0):
        if groups[same[node]] >= 0:
            groups[node] = groups[same[node]]
        else:
            groups[node] = groups[tied[np.argmin(((centers[tied] - centers[node]) ** 2).sum(1))]]
    return groups


def relabel(long: DataFrame, offsets: list[int], groups: np.ndarray) -> DataFrame:
    """Every base label's group; the map has one row per base cluster."""
    spark = long.sparkSession
    rows = [(h, i, int(groups[o + i])) for h, (o, e) in enumerate(zip(offsets[:-1], offsets[1:])) for i in range(e - o)]
    return long.join(F.broadcast(spark.createDataFrame(rows, "h int, label int, grp int")), ["h", "label"])


def consensus(relabelled: DataFrame, captured: DataFrame, how: str = "credible") -> DataFrame:
    """item_id, class.  credible: the group of the round that captured the item, the majority's for
    those never captured; majority; distance_weighted."""
    weight = F.count("*").cast("double") if how != "distance_weighted" else F.round(F.sum(1 / (F.col("dist") + 1e-6)), 6)
    votes = relabelled.groupBy("item_id", "grp").agg(weight.alias("v"))
    most = votes.groupBy("item_id").agg(F.max_by("grp", F.struct("v", -F.col("grp"))).alias("class"))
    if how != "credible":
        return most
    own = relabelled.join(captured.select("item_id", "captured_at"), "item_id").filter(F.col("h") == F.col("captured_at")).select("item_id", F.col("grp").alias("own"))
    return most.join(own, "item_id", "left").select("item_id", F.coalesce("own", "class").alias("class"))


def eps_from_quantile(z: DataFrame, cols: list[str], q: float = 0.02, sample: int = 500, seed: str = "0") -> float:
    """Quantile of the distances within a hash sample of bounded size."""
    order = F.md5(F.concat(F.lit(f"{seed}|"), F.col("item_id").cast("string")).cast("binary"))
    x = np.array([list(r) for r in z.orderBy(order).limit(sample).select(*cols).collect()], float)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))[np.triu_indices(len(x), 1)]
    return float(np.quantile(d, q)) if len(d) else 1.0


@dataclass
class EnsembleModel:
    """Scaler, centres, radius and groups: all that labelling needs."""

    cols: list[str]
    options: RoundOptions
    rounds: Rounds
    groups: np.ndarray
    edges: list

    @classmethod
    def fit(cls, z: DataFrame | B.Blocks, cols: list[str], o: RoundOptions = RoundOptions(), classes: int | None = None, gate: float = 4.0, method: str = "spectral") -> EnsembleModel:
        z = B.packed(z, cols)
        rounds = run_rounds(z, cols, o)
        centers = np.concatenate(rounds.centers)
        edges = [tuple(r) for r in affinity(z, cols, centers, o.eps, gate, own=True).orderBy("a", "b").collect()]
        w, same = weight_matrix(edges, len(centers))
        mass = np.zeros(len(centers))
        for a, b, _, pop, _ in edges:
            if a == b:
                mass[a] = pop
        return cls(cols, o, rounds, group_nodes(centers, w, same, classes, method, mass), edges)

    @property
    def offsets(self) -> list[int]:
        return [0, *np.cumsum([len(c) for c in self.rounds.centers]).tolist()]

    def transform(self, z: DataFrame | B.Blocks, how: str = "credible") -> DataFrame:
        """item_id, captured_at, class: a projection over the items, no shuffle."""
        if how != "distance_weighted" and len(self.groups):
            return classes(z, self.cols, self.rounds, self.options.eps, self.groups, how == "credible")
        groups, cuts = [int(g) for g in self.groups], self.offsets
        s = scan(z, self.cols, self.rounds, self.options.eps)
        table = F.array(*[F.array(*[F.lit(g) for g in groups[a:b]]) for a, b in zip(cuts[:-1], cuts[1:])])
        named = F.transform("labels", lambda x, h: F.element_at(F.element_at(table, h + 1), x + 1))
        k = max(groups) + 1
        weight = (lambda i: F.lit(1.0)) if how != "distance_weighted" else (lambda i: 1 / (F.element_at("dists", i + 1) + 1e-6))

        def vote(c: int):
            own = F.aggregate(F.transform("g", lambda x, i: F.when(x == c, weight(i)).otherwise(0.0)), F.lit(0.0), lambda a, x: a + x)
            return F.struct(F.round(own, 6).alias("v"), F.lit(-c).alias("c"))

        votes = F.array(*[vote(c) for c in range(k)])
        most = -F.array_max(votes)["c"]
        out = s.withColumn("g", named)
        cls_ = F.coalesce(F.element_at("g", F.col("captured_at") + 1), most) if how == "credible" else most
        return out.select("item_id", "captured_at", cls_.alias("class"))

    def save(self, spark: SparkSession, path: str) -> None:
        body = {"cols": self.cols, "options": asdict(self.options), "centers": [c.tolist() for c in self.rounds.centers], "balls": [c.tolist() for c in self.rounds.balls], "sizes": self.rounds.sizes, "groups": self.groups.tolist(), "edges": self.edges}
        spark.createDataFrame([(json.dumps(body),)], "model string").coalesce(1).write.mode("overwrite").text(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> EnsembleModel:
        x = json.loads("".join(r[0] for r in spark.read.text(path).collect()))
        o = x["options"] | ({"k": tuple(x["options"]["k"])} if isinstance(x["options"]["k"], list) else {})
        rounds = Rounds([np.array(c) for c in x["centers"]], [np.array(c) for c in x["balls"]], [tuple(s) for s in x["sizes"]])
        return cls(x["cols"], RoundOptions(**o), rounds, np.array(x["groups"]), [tuple(e) for e in x["edges"]])
