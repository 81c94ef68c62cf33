"""Importance resampling towards a target text.

Hashed word n-grams have two generative models, one of the target texts and one of
all raw texts. The log ratio of the two likelihoods is a text's importance
weight; adding Gumbel noise and taking the largest k draws k texts without
replacement with probabilities proportional to the weights.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column_bytes, mix64, steps, stored, texts_of, unit_floats, word_hashes

BUCKETS = 1 << 14
#: The target is fitted on at most so many labelled rows, those with the smallest hash of doc_id.
MAX_TARGET = 50_000


def ngram_buckets(offsets: np.ndarray, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all words, signs included, and of all pairs of neighbours, with the text of each."""
    hashes, owner, _ = word_hashes(offsets, data, signs=True)
    with np.errstate(over="ignore"):
        pairs = mix64(hashes[:-1] * np.uint64(0xD6E8FEB86659FD93) + hashes[1:])
    same = owner[:-1] == owner[1:]
    both = np.concatenate([hashes, pairs[same]]) & np.uint64(BUCKETS - 1)
    return both.astype(np.int64), np.concatenate([owner, owner[:-1][same]])


def bucket_counts(texts: DataFrame) -> np.ndarray:
    """N-grams by bucket over all texts; each task sends one row per bucket at most."""

    def kernel(batches):
        totals = np.zeros(BUCKETS, np.int64)
        for batch in steps(batches):
            totals += np.bincount(ngram_buckets(*column_bytes(batch.column(0)))[0], minlength=BUCKETS)
        some = np.flatnonzero(totals)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(totals[some])], ["bucket", "n"])

    out = np.zeros(BUCKETS)
    for r in texts.select("text").mapInArrow(kernel, "bucket int, n bigint").groupBy("bucket").agg(F.sum("n").alias("n")).toArrow().to_pylist():
        out[r["bucket"]] = r["n"]
    return out


def log_ratio(target: np.ndarray, raw: np.ndarray) -> np.ndarray:
    """Per bucket, how much likelier it is in the target; one count is added to every bucket of both."""
    return np.log((target + 1) / (target.sum() + len(target))) - np.log((raw + 1) / (raw.sum() + len(raw)))


def gumbel_noise(ids: np.ndarray, seed: int) -> np.ndarray:
    """Noise that the identifier determines, so a repeated or restarted run draws the same texts."""
    return -np.log(-np.log(unit_floats(mix64(mix64(ids.astype(np.uint64)) + np.uint64(seed)))))


def weigh(docs: DataFrame, ratio: np.ndarray, seed: int) -> DataFrame:
    """doc_id, n_grams, log_weight, draw: the log weight plus Gumbel noise."""

    def kernel(batches):
        for batch in steps(batches):
            buckets, owner = ngram_buckets(*column_bytes(batch.column(1)))
            weight = np.bincount(owner, weights=ratio[buckets], minlength=batch.num_rows).astype(np.float64)
            ids = batch.column(0).fill_null(-1).to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.bincount(owner, minlength=batch.num_rows)), pa.array(weight), pa.array(weight + gumbel_noise(ids, seed))], ["doc_id", "n_grams", "log_weight", "draw"])

    return texts_of(docs).mapInArrow(kernel, "doc_id bigint, n_grams bigint, log_weight double, draw double")


def kth_largest(drawn: DataFrame, k: int, bins: int = 4096, few: int = 4096) -> tuple[float, int] | None:
    """The draw and doc_id of the k-th row by descending draw, then ascending doc_id.

    Histograms of an ever narrower range find it; the driver sees ``bins`` counts at a time, and at
    the end a few rows, or one row per doc_id where more than a few rows share one draw.
    """
    low, high, total = drawn.agg(F.min("draw"), F.max("draw"), F.count(F.lit(1))).first()
    if not total or k <= 0:
        return None
    k = min(k, total)
    while True:
        inside = drawn.where(F.col("draw").between(low, high))
        n = inside.count()
        width = (high - low) / bins
        if n <= few or low + width <= low or not width:
            row = inside.select("draw", F.coalesce("doc_id", F.lit(-1)).alias("doc_id")).orderBy(F.desc("draw"), "doc_id").limit(k).orderBy("draw", F.desc("doc_id")).first()
            return row["draw"], row["doc_id"]
        bin_ = F.least(F.lit(bins - 1), F.greatest(F.lit(0), F.floor((F.col("draw") - low) / width)))
        edges = inside.groupBy(bin_.alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.min("draw").alias("low"), F.max("draw").alias("high")).orderBy(F.desc("bin")).collect()
        for e in edges:
            if e["n"] >= k:
                low, high = e["low"], e["high"]
                break
            k -= e["n"]


def importance_resample(docs: DataFrame, labels: DataFrame, share: float | None = None, seed: int = 7, most: int = MAX_TARGET) -> DataFrame:
    """One row per document: doc_id, n_grams, log_weight, draw, kept.

    The target is the labelled rows of quality 1; the raw model counts every document. ``share`` of all rows
    are kept; by default as large a share as quality 1 has among the labels. Null text counts as empty: weight 0.
    Repeated rows draw alike and are kept or left together, so that ties at the limit may keep a few more.
    Without labels every text weighs 0 and all are kept.
    """
    known = labels.where("quality IN (0, 1) AND doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), "quality")
    if share is None:
        share = known.agg(F.avg("quality")).first()[0]
        share = 1.0 if share is None else share
    chosen = known.where("quality = 1").select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    texts = texts_of(docs)
    target = bucket_counts(texts.join(F.broadcast(chosen), "doc_id"))
    ratio = log_ratio(target, bucket_counts(texts)) if target.any() else np.zeros(BUCKETS)
    drawn = stored(weigh(docs, ratio, seed), "draws")
    limit = kth_largest(drawn, round(share * drawn.count()))
    kept = F.lit(False) if limit is None else (F.col("draw") > limit[0]) | (F.col("draw") == limit[0]) & (F.coalesce("doc_id", F.lit(-1)) <= limit[1])
    return drawn.withColumn("kept", kept)
