"""A uniform shuffle into shards of exact sizes.

A communication matrix says how many rows each input block sends to each shard.
Its rows are multivariate hypergeometric draws from what the shards still lack,
so a block's counts are those of a uniform shuffle while every shard ends at its
exact size. Rows are permuted within their block, exchanged by the matrix, and
permuted again within their shard. Only DataFrame and SQL functions are used on rows;
the driver draws the matrix, whose size is bounded by ``max_blocks``.
"""

from __future__ import annotations

import math
import random

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored, texts_of

MAX_BLOCKS = 1 << 14


#: Standard deviations on either side of the mode that are looked at; beyond them lies less than floating point can tell.
REACH = 12


def hypergeometric(rng: random.Random, good: int, bad: int, draws: int) -> int:
    """How many of ``draws`` draws without replacement hit one of ``good`` among ``good + bad``.

    Exact inversion: probabilities relative to the mode's are products of ratios of neighbours, on either side of it. The
    work grows with the standard deviation, the root of the rows.
    """
    low, high = max(0, draws - bad), min(good, draws)
    if low == high:
        return low
    n = good + bad
    mode = min(high, max(low, (draws + 1) * (good + 1) // (n + 2)))
    reach = 64 + int(REACH * math.sqrt(draws * (good / n) * (bad / n) * ((n - draws) / max(1, n - 1))))
    first, last = max(low, mode - reach), min(high, mode + reach)
    up, down = np.arange(mode, last, dtype=float), np.arange(mode, first, -1, dtype=float)
    above = np.cumprod((good - up) / (up + 1) * ((draws - up) / (bad - draws + up + 1)))
    below = np.cumprod(down / (good - down + 1) * ((bad - draws + down) / (draws - down + 1)))
    total = np.cumsum(np.concatenate([below[::-1], [1.0], above]))
    return first + min(last - first, int(np.searchsorted(total, rng.random() * total[-1], side="right")))


def communication_matrix(block_rows: list[int], shard_rows: list[int], seed: int) -> list[list[int]]:
    """Rows: blocks; columns: shards. Row and column sums are exactly those asked for."""
    rng, left, out = random.Random(seed), list(shard_rows), []
    for n in block_rows:
        row, pool, todo = [], sum(left), n
        for k, room in enumerate(left):
            got = hypergeometric(rng, room, pool - room, todo)
            row.append(got)
            pool -= room
            todo -= got
            left[k] -= got
        out.append(row)
    return out


def shard_sizes(n: int, shards: int) -> list[int]:
    return [n // shards + (k < n % shards) for k in range(shards)]



def shuffled_shards(docs: DataFrame, shards: int = 16, seed: int = 42, rows_per_block: int = 2_000, max_blocks: int = MAX_BLOCKS) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot: every row gets a uniform place in a shard; shard sizes differ by one at most.

    Null text has size 1 (no bytes plus 1) and the checksum of the empty text.
    Rows are told apart by doc_id; where some share one or have none, all rows are told apart by a written number instead, so
    that these, too, go anywhere. An empty table gives an empty result. Other columns are ignored.
    """
    spark = docs.sparkSession
    slim = texts_of(docs).select("doc_id", (F.octet_length("text").cast("long") + 1).alias("size"), F.crc32(F.col("text").cast("binary")).alias("text_crc32"), F.monotonically_increasing_id().alias("row"))
    slim = stored(slim, "shard-rows")  # written once, so that a row keeps its number
    total = slim.count()
    key = "doc_id" if slim.groupBy("doc_id").count().where("doc_id IS NULL OR count > 1").isEmpty() else "row"
    blocks = max(1, min(max_blocks, -(-total // rows_per_block)))
    inner = max(1, min(max_blocks // shards, -(-total // (shards * rows_per_block))))

    def dealt(rows: DataFrame) -> DataFrame:
        """First permutation and the matrix: block, then shard."""
        rows = rows.withColumn("block", F.pmod(F.xxhash64(F.lit(seed), "key"), F.lit(blocks)).cast("int"))
        place = F.row_number().over(Window.partitionBy("block").orderBy(F.xxhash64(F.lit(seed + 1), "key"), "key"))
        rows = rows.withColumn("place", place).join(F.broadcast(bounds), "block")
        rows = rows.withColumn("shard", F.size(F.filter("ends", lambda e: e < F.col("place"))))
        return rows.withColumn("cell", F.shiftrightunsigned(F.xxhash64(F.lit(seed + 2), "key"), 33) % inner)

    slim = slim.withColumn("key", F.col(key))
    ids = slim.select("key")
    counted = {r["block"]: r["n"] for r in ids.groupBy(F.pmod(F.xxhash64(F.lit(seed), "key"), F.lit(blocks)).cast("int").alias("block")).agg(F.count(F.lit(1)).alias("n")).collect()}
    matrix = communication_matrix([counted.get(b, 0) for b in range(blocks)], shard_sizes(sum(counted.values()), shards), seed)
    ends = []
    for row in matrix:
        run = 0
        ends.append([run := run + x for x in row])
    bounds = spark.createDataFrame([(b, e) for b, e in enumerate(ends)], "block int, ends array<bigint>")
    cells = {(r["shard"], r["cell"]): r["n"] for r in dealt(ids).groupBy("shard", "cell").agg(F.count(F.lit(1)).alias("n")).collect()}
    starts = []
    for s in range(shards):
        run = 0
        for c in range(inner):
            starts.append((s, c, run))
            run += cells.get((s, c), 0)
    offsets = spark.createDataFrame(starts, "shard int, cell bigint, first bigint")
    # Second permutation: a random cell of the shard, then a random order within the cell.
    order = Window.partitionBy("shard", "cell").orderBy(F.xxhash64(F.lit(seed + 3), "key"), "key")
    return dealt(slim).join(F.broadcast(offsets), ["shard", "cell"]).select("doc_id", "size", "text_crc32", "shard", (F.col("first") + F.row_number().over(order) - 1).alias("slot"))
