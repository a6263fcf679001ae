"""Plain k-means on feature columns.

An iteration is one scan that sends k rows a task; labelling is a projection with the centres as
one broadcast row.  Distances are rounded before the least is taken; sums are exact on the grid of ``DIGITS`` digits and
centres are rounded after each mean, so neither the order of summation nor the partitioning shows.
A table of at most ``ONE_TASK`` values iterates inside one task instead: a job an iteration costs more
than its work there.  Both ways use the same kernel and give the same centres.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from trajkit.operators import blocks as B

DIGITS = 9
LITERALS = 400  # k times columns up to which distances are unrolled
ONE_TASK = 4_000_000  # rows times columns, 32 MB


def matrix(batch: pa.RecordBatch, cols: list[str]) -> np.ndarray:
    return np.column_stack([batch.column(c).to_numpy(zero_copy_only=False) for c in cols]).astype(float)


def closest(x: np.ndarray, centers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Label and rounded squared distance of each row's nearest centre, the first of equals."""
    label, d2 = np.zeros(len(x), np.int32), np.zeros(len(x))
    for i in range(0, len(x), 8192):
        y = x[i : i + 8192]
        d = np.zeros((len(y), len(centers)))
        for j in range(x.shape[1]):
            d += (y[:, j, None] - centers[None, :, j]) ** 2
        d = np.round(d, DIGITS)
        at = d.argmin(1)
        label[i : i + 8192], d2[i : i + 8192] = at, d[np.arange(len(y)), at]
    return label, d2


def grid_sums(x: np.ndarray, label: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows, whole units of the last digit and what is left beside the grid, by label: the first two are
    exact in any order, the third is 0 for values that have ``DIGITS`` digits."""
    n, whole, rest = np.bincount(label, minlength=k), np.zeros((k, x.shape[1]), np.int64), np.zeros((k, x.shape[1]))
    order = np.argsort(label, kind="stable")
    some = np.flatnonzero(n)
    starts = np.concatenate([[0], np.cumsum(n[some])[:-1]]).astype(int)
    for j in range(x.shape[1] if len(x) else 0):
        v = x[order, j] * 10.0**DIGITS
        unit = np.rint(v)
        left = v - unit
        left[np.abs(left) <= np.abs(v) * 2.0**-51] = 0.0
        whole[some, j] = np.add.reduceat(unit.astype(np.int64), starts)
        rest[some, j] = np.add.reduceat(left, starts)
    return n, whole, rest


def grid_mean(n: int, whole: int, rest: float) -> float:
    """Mean of the exact sum, rounded half away from zero to ``DIGITS`` digits."""
    total = Fraction(int(whole)) + Fraction(float(rest))
    units = (2 * abs(total) + n) // (2 * n)
    return float(units if total >= 0 else -units) / 10.0**DIGITS


def moved_centers(x: np.ndarray, label: np.ndarray, centers: np.ndarray) -> np.ndarray:
    out, (n, whole, rest) = centers.copy(), grid_sums(x, label, len(centers))
    for i in np.flatnonzero(n):
        out[i] = [grid_mean(int(n[i]), w, r) for w, r in zip(whole[i], rest[i])]
    return out


def iterate(centers: np.ndarray, max_iter: int, tol: float, move) -> np.ndarray:
    for _ in range(max_iter):
        new = move(centers)
        moved = float(np.abs(new - centers).max()) if len(centers) else 0.0
        centers = new
        if moved <= tol:
            break
    return centers


def first_vectors(hashes: list, x: np.ndarray, k: int) -> np.ndarray:
    """The k different rows that come first by hash."""
    out: dict[tuple, None] = {}
    for i in sorted(range(len(hashes)), key=hashes.__getitem__):
        out.setdefault(tuple(x[i].tolist()))
        if len(out) == k:
            break
    return np.array(list(out), float).reshape(-1, x.shape[1])


def sq_dist(cols: list[str], center) -> Column:
    out = F.lit(0.0)
    for c, v in zip(cols, center):
        out = out + (F.col(c) - F.lit(float(v))) * (F.col(c) - F.lit(float(v)))
    return out


def nearest(cols: list[str], centers: np.ndarray) -> Column:
    """struct(d2, label) of the nearest centre, the first of equals."""
    each = [F.struct(F.round(sq_dist(cols, c), DIGITS).alias("d2"), F.lit(i).alias("label")) for i, c in enumerate(centers)]
    return F.least(*each) if len(each) > 1 else each[0]


def seeds(pool: DataFrame | B.Blocks, cols: list[str], k: int, seed: str) -> np.ndarray:
    """The k different vectors whose items come first by hash; the same on any partitioning."""
    if isinstance(pool, B.Blocks):
        return B.first_by_hash(pool, k, seed, first_vectors)
    order = F.md5(F.concat(F.lit(f"{seed}|"), F.col("item_id").cast("string")).cast("binary"))
    hashed = pool.select(order.alias("h"), *cols)
    # Rows in hash order are enough unless most of the first ones are copies.
    rows = hashed.filter("h IS NOT NULL").orderBy("h").limit(16 * k).collect()
    found = first_vectors([r["h"] for r in rows], np.array([tuple(r[c] for c in cols) for r in rows], float).reshape(-1, len(cols)), k)
    if len(found) == k or len(rows) < 16 * k:
        return found
    first = hashed.groupBy(*cols).agg(F.min("h").alias("h"))
    rows = first.orderBy("h").limit(k).collect()
    return np.array([tuple(r[c] for c in cols) for r in rows], float).reshape(-1, len(cols))


def assign(df: DataFrame, cols: list[str], centers: np.ndarray) -> DataFrame:
    """Adds label and d2.  The centres come as one broadcast row, so the generated code is the same
    in every iteration and is compiled once."""
    if len(centers) * len(cols) > LITERALS:
        return _assign_arrow(df, cols, centers)
    names = [f"__c{i}" for i in range(len(centers))]
    row = df.sparkSession.createDataFrame([tuple([float(v) for v in c] for c in centers)], T.StructType([T.StructField(n, T.ArrayType(T.DoubleType(), False), False) for n in names]))
    each = []
    for i, c in enumerate(names):
        d2 = F.lit(0.0)
        for j, a in enumerate(cols):
            d2 = d2 + (F.col(a) - F.get(c, F.lit(j))) * (F.col(a) - F.get(c, F.lit(j)))
        each.append(F.struct(F.round(d2, DIGITS).alias("d2"), F.lit(i).alias("label")))
    least = F.least(*each) if len(each) > 1 else each[0]
    out = df.crossJoin(F.broadcast(row)).withColumn("__n", least)
    return out.select(*df.columns, F.col("__n.label").alias("label"), F.col("__n.d2").alias("d2"))


def _assign_arrow(df: DataFrame, cols: list[str], centers: np.ndarray) -> DataFrame:
    names = df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.column_stack([b.column(names.index(c)).to_numpy(zero_copy_only=False) for c in cols])
            d = np.round(((x[:, None, :] - centers[None]) ** 2).sum(2), DIGITS) if len(x) else np.zeros((0, len(centers)))
            label = d.argmin(1).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(label), pa.array(d[np.arange(len(x)), label])], [*names, "label", "d2"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
    return df.mapInArrow(run, f"{fields}, label int, d2 double")


def update(assigned: DataFrame, cols: list[str], centers: np.ndarray) -> np.ndarray:
    """New centres; a centre without items stays."""
    rows = assigned.groupBy("label").agg(*[F.round(F.avg(c), DIGITS).alias(c) for c in cols]).collect()
    out = centers.copy()
    for r in rows:
        out[r["label"]] = [r[c] for c in cols]
    return out


def step(df: DataFrame | B.Blocks, cols: list[str], centers: np.ndarray, near: float | None = None) -> np.ndarray:
    """One iteration in one pass: tasks send k rows of counts and sums, no row comes back labelled.
    Measured against the unrolled column form it takes about half the time, as rounding a double
    costs the JVM a big decimal for every distance.  ``near``: only items that close to their centre count."""
    k = len(centers)
    table, chunks = B.source(df, cols, ids=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, whole, rest = np.zeros(k, np.int64), np.zeros((k, len(cols)), np.int64), np.zeros((k, len(cols)))
        for _, x in chunks(batches):
            if near is not None:
                x = x[:, B.within(x, centers, near, closest)]
            for total, part in zip((n, whole, rest), B.exact_sums(x, B.labels(x, centers, closest), k, DIGITS, grid_sums)):
                total += part
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(n[at]), *(pa.array(v[at, j]) for v in (whole, rest) for j in range(len(cols)))], ["label", "n", *(f"{v}{j}" for v in "wr" for j in range(len(cols)))])

    fields = [T.StructField("label", T.IntegerType()), T.StructField("n", T.LongType()), *(T.StructField(f"w{j}", T.LongType()) for j in range(len(cols))), *(T.StructField(f"r{j}", T.DoubleType()) for j in range(len(cols)))]
    parts = table.mapInArrow(run, T.StructType(fields))
    sums = [F.sum(F.col(f"w{j}").cast("decimal(28,0)")).alias(f"w{j}") for j in range(len(cols))] + [F.sum(f"r{j}").alias(f"r{j}") for j in range(len(cols))]
    rows = parts.groupBy("label").agg(F.sum("n").alias("n"), *sums).collect()  # k rows
    out = centers.copy()
    for r in rows:
        out[r["label"]] = [grid_mean(r["n"], r[f"w{j}"], r[f"r{j}"]) for j in range(len(cols))]
    return out


def outside(df: DataFrame | B.Blocks, cols: list[str], balls: np.ndarray, eps: float) -> B.Blocks:
    """Items farther than ``eps`` from every centre, stored."""

    def far(ids: pa.Array, x: np.ndarray) -> B.Chunk:
        stay = ~B.within(x, balls, eps, closest)
        return ids.filter(pa.array(stay)), x[:, stay]

    return B.packed(df, cols, far)


def lloyd_in_one_task(df: DataFrame | B.Blocks, cols: list[str], centers: np.ndarray, max_iter: int, tol: float) -> np.ndarray:
    table, chunks = B.source(df, cols, ids=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x = np.concatenate([np.zeros((0, len(cols))), *(x.T for _, x in chunks(batches))])
        done = iterate(centers, max_iter, tol, lambda c: moved_centers(x, closest(x, c)[0], c))
        yield pa.RecordBatch.from_arrays([pa.array(done.tolist(), pa.list_(pa.float64()))], ["center"])

    rows = table.coalesce(1).mapInArrow(run, "center array<double>").collect()
    return np.array([r["center"] for r in rows], float).reshape(-1, len(cols)) if rows else centers


def lloyd(df: DataFrame | B.Blocks, cols: list[str], k: int, init: str | np.ndarray = "hash_sample", max_iter: int = 10, tol: float = 1e-6, seed: str = "0") -> np.ndarray:
    """Centres.  ``init``: hash_sample, an array of centres, or kmeans|| (scalable seeding)."""
    if isinstance(init, np.ndarray):
        centers = init.astype(float)
    elif init == "kmeans||":
        centers = parallel_seeds(df, cols, k, seed)
    else:
        centers = seeds(df, cols, k, seed)
    if len(centers) and max_iter and df.count() * len(cols) <= ONE_TASK:
        return lloyd_in_one_task(df, cols, centers, max_iter, tol)
    return iterate(centers, max_iter, tol, lambda c: step(df, cols, c))


def parallel_seeds(df: DataFrame, cols: list[str], k: int, seed: str) -> np.ndarray:
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    x = VectorAssembler(inputCols=cols, outputCol="v").transform(df)
    model = KMeans(k=k, featuresCol="v", initMode="k-means||", maxIter=1, seed=crc32(seed.encode()) % 2**31).fit(x)
    return np.array(model.clusterCenters())


def objective(assigned: DataFrame) -> DataFrame:
    return assigned.agg(F.round(F.sum("d2"), 6).alias("objective"), F.count("*").alias("items"))
