"""Vectors as columns: cosine, and exact nearest neighbours in blocks."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


#: Vectors of a block at most; candidates whose fast similarity is so close to the k-th are compared again; pairs compared again at once.
BLOCK, CLOSE, AGAIN = 4096, 1e-9, 1 << 15


def _best(k: int):
    """Task: of a block of vectors and a block of queries, each query's k most similar others, by similarities to the twelfth digit."""

    def unit(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        lists = t.column("embedding").combine_chunks()
        v = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(t.num_rows, -1)
        with np.errstate(invalid="ignore", divide="ignore"):
            return t.column("id").to_numpy(), v / np.sqrt((v * v).sum(axis=1, keepdims=True))

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        src, dst, far = [], [], []
        if left.num_rows and right.num_rows:
            (mine, queries), (ids, members) = unit(left), unit(right)
            for at in range(0, len(mine), 256):
                some = mine[at : at + 256]
                fast = queries[at : at + 256] @ members.T
                fast[some[:, None] == ids[None, :]] = -np.inf
                least = np.partition(fast, max(0, len(ids) - k), axis=1)[:, max(0, len(ids) - k)]
                i, j = np.nonzero((fast >= least[:, None] - CLOSE) & (fast > -np.inf))
                # the product of blocks rounds as it likes; equal vectors must be equally far
                exact = np.concatenate([np.round((queries[at + i[c : c + AGAIN]] * members[j[c : c + AGAIN]]).sum(axis=1), 12) for c in range(0, len(i), AGAIN)] or [np.zeros(0)])
                order = np.lexsort((ids[j], -exact, i))
                i, j, exact = i[order], j[order], exact[order]
                first = np.searchsorted(i, np.arange(len(some)))
                keep = np.arange(len(i)) - first[i] < k
                src.append(some[i[keep]])
                dst.append(ids[j[keep]])
                far.append(exact[keep])
        join = lambda parts, kind: np.concatenate(parts) if parts else np.zeros(0, kind)
        return pa.table({"src": join(src, np.int64), "dst": join(dst, np.int64), "similarity": join(far, np.float64)})

    return kernel


def nearest(vectors: DataFrame, k: int, block_rows: int = 500) -> DataFrame:
    """src, dst, similarity, place: each vector's k most similar others, exactly; ties go to the smaller id.

    Exact neighbours cost V^2 comparisons whatever the plan. Vectors are dealt into blocks of ``block_rows`` or more by a hash of their id; each
    block meets each other one as a product of matrices, of which a query keeps k, so what is shuffled is every vector
    once a block and k rows per query and block. Rows without a vector have no neighbours.
    """
    ship(vectors.sparkSession)
    rows = vectors.where("vec_id IS NOT NULL AND embedding IS NOT NULL").select(F.col("vec_id").cast("long").alias("id"), "embedding")
    n = rows.count()
    blocks = max(-(-n // BLOCK), min(8, -(-n // block_rows)), 1)
    rows = rows.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    queries = rows.select("id", "embedding", F.col("own").alias("q"), other.alias("m"))
    members = rows.select("id", "embedding", F.col("own").alias("m"), other.alias("q"))
    found = queries.groupBy("q", "m").cogroup(members.groupBy("q", "m")).applyInArrow(_best(k), "src bigint, dst bigint, similarity double")
    return found.withColumn("place", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("similarity"), "dst"))).where(F.col("place") <= k)


def pairs_above(vectors: DataFrame, least: float, block_rows: int = 500) -> DataFrame:
    """a, b, where a < b and their cosine is above ``least``, exactly: every vector meets each block of vectors once."""
    unit = vectors.select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    unit = unit.withColumn("v", F.transform("v", lambda x: x / F.sqrt(dot(F.col("v"), F.col("v")))))
    blocks = unit.groupBy(F.floor(F.col("id") / block_rows).alias("block")).agg(F.collect_list(F.struct("id", "v")).alias("members"))
    first = F.floor(F.col("id") / block_rows)
    queries = unit.withColumn("block", F.explode(F.sequence(first, F.lit(_last_block(vectors, block_rows)))))
    near = F.transform(F.filter("members", lambda m: (m["id"] > F.col("id")) & (F.round(dot(m["v"], F.col("v")), 9) > least)), lambda m: m["id"])
    return queries.join(blocks, "block").select(F.col("id").alias("a"), F.explode(near).alias("b"))


def _last_block(vectors: DataFrame, block_rows: int) -> int:
    top = vectors.agg(F.max("vec_id")).first()[0]
    return int(top or 0) // block_rows
