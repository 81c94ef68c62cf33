"""Toxic passages as maximum-scoring segments.

Words get log-odds between toxic and clean labelled texts, under a Dirichlet
prior from all of them; a cautious bound of the log-odds, less a small drift, is
the word's score. One linear scan finds every maximal-scoring segment of a text.
Extreme-value statistics of such segments in clean text turn a segment's score
and the text's length into evidence, and a logistic curve fitted on labelled
texts kept apart turns a text's evidence into a score between 0 and 1.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import _POWERS, LOWER, WORD_CLASS, column_bytes, mix64, ship, steps, stored, texts_of, word_hashes

#: Bits of the table that tells most words without log-odds at once; the others' hashes are looked up.
TELLS = 1 << 20
#: Besides whole words, their beginnings of these many bytes carry log-odds: words inflect.
PREFIXES = (5, 6)
#: At most so many labelled rows are used to fit, those with the smallest hash of doc_id.
MAX_LABELLED = 30_000
#: How many standard errors log-odds lose, what they must still reach to count, what each word costs, and the prior's least count.
CAUTION, LEAST_ODDS, DRIFT, PRIOR = 2.33, 1.0, 0.1, 0.5
#: Evidence is measured from one to the other: beyond these, a text counts as clean, or as toxic, as any can be.
LEAST, MOST = -12.0, 24.0


def features(offsets: np.ndarray, data: np.ndarray) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray, np.ndarray]:
    """(word, hash) of all words, then of their beginnings, where words are long enough; with the words' texts and first bytes."""
    hashes, owner, starts = word_hashes(offsets, data)
    kinds = [(np.arange(len(hashes)), hashes)]
    lengths = word_lengths(offsets, data, starts)
    for k in PREFIXES:
        long = np.flatnonzero(lengths >= k)
        with np.errstate(over="ignore"):
            total = np.full(len(long), k, np.uint64)
            for j in range(k):
                total += (LOWER[data[starts[long] + j]].astype(np.uint64) + np.uint64(1)) * _POWERS[j]
        kinds.append((long, mix64(total ^ np.uint64(0x5BF03635 * k))))
    return kinds, owner, starts


def word_lengths(offsets: np.ndarray, data: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Bytes from each word's start to the next byte that is no word byte, or to the text's end."""
    stops = np.union1d(np.flatnonzero(WORD_CLASS[data] != 1), offsets[1:])
    return stops[np.searchsorted(stops, starts, side="right")] - starts if len(stops) else np.zeros(0, np.int64)


@dataclass
class ToxicityModel:
    """Log-odds of words and beginnings by hash, in order, and the two calibrations. Its size is that of the bounded labelled sample's vocabulary."""

    hashes: np.ndarray
    odds: np.ndarray
    decay: float = 1.0
    scale: float = 1.0
    slope: float = 1.0
    intercept: float = 0.0

    def evidence(self, segment: float, words: int) -> float:
        """Minus the logarithm of how many segments as good a clean text of so many words would have by chance."""
        if segment <= 0:
            return LEAST
        return min(MOST, max(LEAST, self.decay * segment - math.log(self.scale * max(words, 1))))

    def probability(self, evidence: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * evidence + self.intercept, -500, 500)))


@lru_cache(maxsize=4)
def _tells(hashes: bytes) -> np.ndarray:
    held = np.zeros(TELLS, bool)
    held[(np.frombuffer(hashes, np.uint64) & np.uint64(TELLS - 1)).astype(np.int64)] = True
    return held


def word_scores(model: ToxicityModel, kinds: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """The log-odds furthest up among a word and its beginnings, or the word's own, less the drift."""
    best = np.zeros(len(kinds[0][0]))
    tells = _tells(model.hashes.tobytes())
    for k, (words, hashes) in enumerate(kinds):
        some = np.flatnonzero(tells[(hashes & np.uint64(TELLS - 1)).astype(np.int64)])
        at = np.searchsorted(model.hashes, hashes[some])
        hit = at < len(model.hashes)
        hit[hit] = model.hashes[at[hit]] == hashes[some][hit]
        some, got = some[hit], model.odds[at[hit]]
        if k == 0:
            best[words[some]] = got
        else:
            up = got > 0
            at = words[some[up]]
            best[at] = np.maximum(best[at], got[up])
    return best - DRIFT


def maximal_segments(sums: np.ndarray, gains: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal-scoring segments: (first, last, score), by position, in time linear in ``gains``.

    ``sums`` has the sum of scores before each word and in all; ``gains`` are the
    positions of words with a positive score. Each candidate is joined with the
    nearest one before it that starts lower and ends lower, until there is none. A candidate
    knows the nearest one before it that starts lower, so that those between are never looked at again; where none starts lower, all
    before are final and leave the list.
    """
    final: list[tuple[int, int, float]] = []
    before, after, first, last, lower = [], [], [], [], []
    for k, low, high in zip(gains.tolist(), sums[gains].tolist(), sums[gains + 1].tolist(), strict=True):
        start, j = k, len(before) - 1
        while True:
            while j >= 0 and before[j] >= low:
                j = lower[j]
            if j < 0:
                final += zip(first, last, map(float.__sub__, after, before), strict=True)
                before, after, first, last, lower = [low], [high], [start], [k], [-1]
                break
            if after[j] >= high:
                for held, x in zip((before, after, first, last, lower), (low, high, start, k, j), strict=True):
                    held.append(x)
                break
            low, start, link = before[j], first[j], lower[j]
            for held in (before, after, first, last, lower):
                del held[j:]
            j = link
    return [*final, *zip(first, last, map(float.__sub__, after, before), strict=True)]


def best_segments(offsets: np.ndarray, data: np.ndarray, model: ToxicityModel):
    """For each text with a positive word: (text, words, segments, first bytes of its words)."""
    kinds, owner, starts = features(offsets, data)
    each = word_scores(model, kinds)
    words = np.bincount(owner, minlength=len(offsets) - 1)
    firsts = np.concatenate([[0], np.cumsum(words)])
    gains = np.flatnonzero(each > 0)
    cuts = np.searchsorted(gains, firsts)
    found = []
    for t in np.flatnonzero(np.diff(cuts)).tolist():
        a, b = firsts[t], firsts[t + 1]
        sums = np.concatenate([[0.0], np.cumsum(each[a:b])])
        found.append((t, int(b - a), maximal_segments(sums, gains[cuts[t] : cuts[t + 1]] - a), starts[a:b] - offsets[t]))
    return words, found


def evidence_of(model: ToxicityModel, offsets: np.ndarray, data: np.ndarray) -> np.ndarray:
    """A text's evidence: its significant segments' evidence in all, or the best segment's where none is significant."""
    words, found = best_segments(offsets, data, model)
    out = np.full(len(words), LEAST)
    for t, n, segments, _ in found:
        each = [model.evidence(s, n) for _, _, s in segments]
        strong = sum(e for e in each if e > 0)
        out[t] = min(MOST, strong) if strong else max(each)
    return out


MARKS = 3


def shingle_marks(batches):
    """The least hashes of a text's runs of five words under a few permutations: near copies share most of them.

    A text of fewer words has the hash of all of them.
    """
    for batch in steps(batches):
        hashes, owner, _ = word_hashes(*column_bytes(batch.column(1)))
        firsts = np.searchsorted(owner, np.arange(batch.num_rows + 1))
        runs = hashes.copy()
        with np.errstate(over="ignore"):
            for j in range(1, min(5, len(runs))):
                runs[: len(runs) - j] += hashes[j:] * _POWERS[2 * j]
        whole = np.append(owner[4:], np.full(min(4, len(owner)), -1)) == owner if len(owner) else np.zeros(0, bool)
        marks = np.zeros((MARKS, batch.num_rows), np.uint64)
        for t in range(batch.num_rows):
            a, b = firsts[t], firsts[t + 1]
            own = runs[a:b][whole[a:b]]
            if not len(own):
                with np.errstate(over="ignore"):
                    own = np.array([(hashes[a:b] * _POWERS[: b - a]).sum() + np.uint64(b - a)], np.uint64)
            for k in range(MARKS):
                marks[k, t] = mix64(own ^ np.uint64(0x9E3779B9 * (k + 1))).min()
        yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(m.view(np.int64)) for m in marks)], [*batch.schema.names, *(f"mark{k}" for k in range(MARKS))])


def labelled_sample(docs: DataFrame, labels: DataFrame, allowed, most: int) -> DataFrame:
    """doc_id, text, toxic, fold of labelled rows that may be learnt from; bounded, hence the broadcast."""
    key = F.col("doc_id").cast("long").alias("doc_id")
    chosen = labels.where("toxic IN (0, 1) AND doc_id IS NOT NULL").select(key, F.col("toxic").cast("int").alias("toxic")).where(allowed(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    sample = texts_of(docs).join(F.broadcast(chosen), "doc_id").withColumn("fold", F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5)
    kept = stored(sample.mapInArrow(shingle_marks, "doc_id bigint, text string, toxic int, fold bigint, mark0 bigint, mark1 bigint, mark2 bigint"), "labelled-all")
    # A word that only one text and its many copies have is no evidence: of texts with a mark in common, one is learnt from.
    for k in range(MARKS):
        first = kept.groupBy(f"mark{k}").agg(F.min("doc_id").alias("doc_id")).select("doc_id")
        kept = kept.join(first, "doc_id", "left_semi")
    return kept.select("doc_id", "text", "toxic", "fold")


def fit(docs: DataFrame, labels: DataFrame, allowed, most: int = MAX_LABELLED) -> ToxicityModel:
    """Learn from labelled rows that ``allowed`` admits. Folds 1 to 3 give log-odds, fold 4 the calibration.

    The driver gets the bounded table of log-odds, a histogram, and one evidence and label per calibration row.
    Without labelled rows of both classes every text scores below one half.
    """
    sample = stored(labelled_sample(docs, labels, allowed, most), "labelled")

    def count(batches):
        """How many texts of each class have a word or beginning."""
        for batch in steps(batches):
            label = np.array(batch.column(1).to_pylist(), np.int64)
            kinds, owner, _ = features(*column_bytes(batch.column(0)))
            texts, hashes = np.concatenate([owner[w] for w, _ in kinds]), np.concatenate([h for _, h in kinds])
            order = np.lexsort((texts, hashes))
            texts, hashes = texts[order], hashes[order]
            new = np.ones(len(hashes), bool)
            new[1:] = (hashes[1:] != hashes[:-1]) | (texts[1:] != texts[:-1])
            texts, hashes = texts[new], hashes[new]
            first = np.flatnonzero(np.append(True, hashes[1:] != hashes[:-1])) if len(hashes) else np.zeros(0, int)
            toxic = np.add.reduceat(label[texts], first) if len(first) else first
            all_ = np.diff(np.append(first, len(hashes)))
            yield pa.RecordBatch.from_arrays([pa.array(hashes[first].view(np.int64)), pa.array(toxic), pa.array(all_ - toxic)], ["hash", "toxic", "clean"])

    learn = sample.where("fold < 4").select("text", "toxic")
    n_toxic, n_all = learn.agg(F.coalesce(F.sum("toxic"), F.lit(0)), F.count(F.lit(1))).first()
    n_clean = n_all - n_toxic
    if not n_toxic or not n_clean:
        return ToxicityModel(np.zeros(0, np.uint64), np.zeros(0))
    prior = F.lit(PRIOR) + (F.col("toxic") + F.col("clean")) / n_all
    odds = F.ln((F.col("toxic") + prior) / (n_toxic + 1 - F.col("toxic"))) - F.ln((F.col("clean") + prior) / (n_clean + 1 - F.col("clean")))
    error = F.lit(CAUTION) * F.sqrt(1 / (F.col("toxic") + prior) + 1 / (F.col("clean") + prior))
    cautious = F.signum("odds") * F.greatest(F.abs("odds") - error, F.lit(0.0))
    counted = learn.mapInArrow(count, "hash bigint, toxic bigint, clean bigint").groupBy("hash").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))
    table = counted.withColumn("odds", odds).withColumn("odds", cautious).where(F.abs("odds") >= LEAST_ODDS).select("hash", "odds").toPandas()
    hashes = table["hash"].to_numpy(np.int64).view(np.uint64)
    order = np.argsort(hashes)
    model = ToxicityModel(hashes[order], table["odds"].to_numpy(float)[order])

    def background(batches):
        """Scores of the words of clean texts, in steps of 1/4."""
        hist = np.zeros(512, np.int64)
        for batch in steps(batches):
            kinds, _, _ = features(*column_bytes(batch.column(0)))
            hist += np.bincount(np.clip(np.round(word_scores(model, kinds) * 4).astype(int) + 256, 0, 511), minlength=512)
        some = np.flatnonzero(hist)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(hist[some])], ["bin", "n"])

    hist = np.zeros(512)
    for r in sample.where("toxic = 0").select("text").mapInArrow(background, "bin int, n bigint").groupBy("bin").agg(F.sum("n").alias("n")).collect():
        hist[r["bin"]] = r["n"]
    values = (np.arange(512) - 256) / 4
    values[256] = -DRIFT  # the many words without log-odds
    hist[256 + int(round(float(model.odds.max(initial=1.0)) * 4))] += 1  # clean text may have any word
    model.decay = segment_decay(values, hist / hist.sum())
    model.scale = float((hist * (values > 0)).sum() / hist.sum())

    def weigh(batches):
        for batch in steps(batches):
            offsets, data = column_bytes(batch.column(0))
            yield pa.RecordBatch.from_arrays([pa.array(evidence_of(model, offsets, data)), batch.column(1)], ["evidence", "toxic"])

    held = sample.where("fold = 4").select("text", "toxic").mapInArrow(weigh, "evidence double, toxic int").toPandas()
    model.slope, model.intercept = logistic(held.evidence.to_numpy(), held.toxic.to_numpy())
    return model


def segment_decay(values: np.ndarray, p: np.ndarray) -> float:
    """The positive root x of sum p exp(x value) = 1: how fast chance segments get rarer with their score."""
    low, high = 0.0, 1.0
    excess = lambda x: float((p * np.exp(np.minimum(x * values, 700))).sum() - 1)
    if float((p * values).sum()) >= 0 or not (p * (values > 0)).any():
        return 1.0
    while excess(high) < 0 and high < 64:
        high *= 2
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if excess(mid) < 0 else (low, mid)
    return max(high, 1e-3)


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2) -> tuple[float, float]:
    """Slope and intercept of a logistic curve by Newton steps; the slope stays positive."""
    if len(x) == 0 or y.min() == y.max():
        return 1.0, 0.0
    centre, width = x.mean(), x.std() or 1.0
    z = np.stack([(x - centre) / width, np.ones_like(x)], 1)
    w = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        h = z.T @ (z * (p * (1 - p) + 1e-6)[:, None]) + ridge * np.eye(2)
        step = np.linalg.solve(h, z.T @ (y - p) - ridge * w)
        w += np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-8:
            break
    slope = max(w[0], 1e-6) / width
    return float(slope), float(w[1] - slope * centre)


def may_learn(doc_id):
    """Rows whose checksum is a multiple of 5 are held out."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 != 0


def score_texts(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """doc_id, score, evidence. Empty and null texts have no segment and score as any text without one."""

    def kernel(batches):
        for batch in steps(batches):
            evidence = evidence_of(model, *column_bytes(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.probability(evidence)), pa.array(evidence)], ["doc_id", "score", "evidence"])

    return texts_of(docs).mapInArrow(kernel, "doc_id bigint, score double, evidence double")


def toxic_passages(docs: DataFrame, model: ToxicityModel, least_evidence: float = 0.0) -> DataFrame:
    """doc_id, start, words, score, evidence of every significant passage; start is the passage's first byte."""
    names = ["doc_id", "start", "words", "score", "evidence"]

    def kernel(batches):
        for batch in steps(batches):
            ids, rows = batch.column(0).to_pylist(), []
            for t, n, segments, starts in best_segments(*column_bytes(batch.column(1)), model)[1]:
                rows += [(ids[t], int(starts[a]), b - a + 1, s, e) for a, b, s in segments if (e := model.evidence(s, n)) > least_evidence]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64()), strict=True)], names)

    return texts_of(docs).mapInArrow(kernel, "doc_id bigint, start bigint, words bigint, score double, evidence double")


def score_documents(docs: DataFrame, labels: DataFrame, most: int = MAX_LABELLED) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of ``docs``; labels of held-out rows are never used.

    A null doc_id counts as held out. Repeated rows score alike; an empty table gives an empty result; other columns are ignored.
    """
    scored = score_texts(docs, fit(docs, labels, may_learn, most))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(True))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def keep_clean(docs: DataFrame, model: ToxicityModel, text_col: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns as they are, whose texts score below one half; null text counts as empty."""
    ship(docs.sparkSession)
    at = docs.columns.index(text_col)

    def kernel(batches):
        for batch in batches:
            text = batch.column(at).fill_null("")
            parts = [model.probability(evidence_of(model, *column_bytes(part.column(0)))) for part in steps([pa.RecordBatch.from_arrays([text], ["text"])])]
            if parts:
                yield batch.filter(pa.array(np.concatenate(parts) < 0.5))

    return docs.mapInArrow(kernel, docs.schema)
