"""Exact top-k search by inner product with vector-approximation files.

Vectors are dealt into blocks by hash.  A block keeps, beside the exact integer vectors, a file
of cells: each component's place among 2**bits equal steps between the block's least and largest
value of that dimension.  For a query the cells alone bound every score from both sides.  Vectors
whose upper bound is below the kth largest lower bound are out; the others are read exactly, from
the largest upper bound down, until the kth score found is above every bound that is left.
Blocks of queries meet blocks of vectors on an equi-join key; each pair yields k rows a query.

Edge cases: null vectors, empty ones and those with null or non-finite components take no part;
vectors of different lengths never meet; equal scores go to the smaller id; a query with fewer
candidates than k gets them all; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .scratch import table


class CellFile:
    """The approximation of one block of integer vectors."""

    def __init__(self, exact: np.ndarray, bits: int = 6):
        self.low = exact.min(0)
        span = exact.max(0) - self.low
        self.step = span // (1 << bits) + 1
        self.cells = ((exact - self.low) // self.step).astype(np.uint8 if bits <= 8 else np.uint16)

    def bounds(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Lower and upper bounds of the scores, queries x vectors."""
        q = queries.astype(np.float64)
        base = (q * self.step) @ self.cells.T.astype(np.float64) + (q @ self.low.astype(np.float64))[:, None]
        width = (self.step - 1).astype(np.float64)
        slack = 1e-9 * (np.abs(q) @ (np.abs(self.low).astype(np.float64) + self.step * 256.0))[:, None]
        return base + (np.minimum(q, 0) @ width)[:, None] - slack, base + (np.maximum(q, 0) @ width)[:, None] + slack


def search_block(qid: np.ndarray, q: np.ndarray, vid: np.ndarray, v: np.ndarray, k: int, bits: int = 6, step: int = 128):
    """The k best of one block for each query: (query_id, vec_id, score) and how many exact
    vectors were read."""
    out, read = [], 0
    file = CellFile(v, bits)
    for i in range(0, len(qid), step):
        lows, highs = file.bounds(q[i : i + step])
        for r, one in enumerate(qid[i : i + step]):
            low, high = lows[r], highs[r]
            own = vid == one
            low[own], high[own] = -np.inf, -np.inf
            n = len(vid) - int(own.sum())
            if not n:
                continue
            kk = min(k, n)
            floor = np.partition(low, len(low) - kk)[len(low) - kk]
            left = np.flatnonzero((high >= floor) & ~own)
            left = left[np.argsort(-high[left], kind="stable")]
            scores, ids, at, size = np.zeros(0, np.int64), np.zeros(0, np.int64), 0, max(32, 2 * k)
            while at < len(left):
                if len(scores) >= kk and high[left[at]] < np.partition(scores, len(scores) - kk)[len(scores) - kk]:
                    break
                now = left[at : at + size]
                scores = np.concatenate([scores, v[now] @ q[i + r]])
                ids = np.concatenate([ids, vid[now]])
                best = np.lexsort((ids, -scores))[:kk]
                scores, ids = scores[best], ids[best]
                at, size = at + len(now), size * 2
            read += at
            out.append((np.full(len(ids), one), ids, scores))
    return out, read


def top_k(vectors: DataFrame, is_query: Column, k: int = 10, block_rows: int = 8192, query_rows: int = 4096, bits: int = 6) -> DataFrame:
    """vec_id long, v array<long> -> query_id, rank, vec_id, score.

    ``is_query`` picks the queries.  Every pair of a query block and a vector block is one task's
    group of at most about query_rows + block_rows rows.
    """
    n, nq = vectors.agg(F.count("*"), F.count(F.when(is_query, 1))).first()
    blocks, qblocks = max(1, -(-n // block_rows)), max(1, -(-nq // query_rows))
    salt = F.xxhash64("vec_id", "v")
    side = vectors.withColumn("dim", F.size("v"))
    data = side.select("dim", F.pmod(salt, F.lit(blocks)).alias("b"), F.explode(F.sequence(F.lit(0), F.lit(qblocks - 1))).alias("qb"), "vec_id", "v")
    asked = side.filter(is_query).select("dim", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("b"), F.pmod(salt, F.lit(qblocks)).cast("int").alias("qb"), "vec_id", "v")

    def pair(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype("int64")
        stack = lambda x: np.array(x.tolist(), np.int64)
        right = right.drop_duplicates("vec_id")
        got, _ = search_block(right["vec_id"].to_numpy(), stack(right["v"]), left["vec_id"].to_numpy(), stack(left["v"]), k, bits)
        if not got:
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype("int64")
        return pd.DataFrame(dict(zip(("query_id", "vec_id", "score"), map(np.concatenate, zip(*got)))))

    key = ["dim", "b", "qb"]
    found = data.groupBy(*key).cogroup(asked.groupBy(*key)).applyInPandas(pair, "query_id long, vec_id long, score long")
    best = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def integer_vectors(df: DataFrame) -> DataFrame:
    """vec_id, v: floor(1024 * component), for vectors all of whose components are finite."""
    x = F.transform("embedding", lambda e: e.cast("double"))
    fine = F.forall(x, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < float("inf")))
    kept = df.filter(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0) & fine)
    return kept.select("vec_id", F.transform(x, lambda e: F.floor(e * 1024)).alias("v"))


def op1_exact_top_k(spark, sf_dir: str) -> DataFrame:
    vectors = integer_vectors(table(spark, sf_dir, "embeddings", "vec_id", "embedding"))
    return top_k(vectors, F.col("vec_id") % 100 == 0)


ORACLE = r"""
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)::BIGINT) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2]))::BIGINT AS score
      FROM v AS q JOIN v AS c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v) WHERE q.vec_id % 100 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""
