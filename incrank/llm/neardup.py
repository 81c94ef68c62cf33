"""Near-duplicate documents by consistent weighted sampling.

A document is the multiset of its runs of five words, weighted by TF-IDF. Improved
consistent weighted sampling draws from it so that two documents draw alike with
the probability of their weighted Jaccard similarity. Bands of draws nominate
pairs, the draws they have in common estimate their similarity, and the exact
weights decide. What bands miss, within large groups above all, an exact join on
rare runs finds among documents that are still apart. Documents with equal
multisets are one from the start, so large groups of copies cost no pairs.

Document frequencies are counted over all documents. Draws take them by hash bucket, of which there is a fixed
number; what decides are the frequencies of the runs themselves, by 64-bit hash, whatever the corpus.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import release_shuffles
from .common import _POWERS, column_bytes, join_per_key, mix64, partitions_for, steps, stored, texts_of, word_hashes
from .components import connected_components
from .suffix import NO_ID, home, joined, multikey_order, packed, unpacked

WORDS, SIMILARITY = 5, 0.8
#: Draws of a band, bands: at similarity 0.8 a pair shares no band once in 200,000 pairs.
ROWS, BANDS = 2, 12
DRAWS = ROWS * BANDS
#: A pair is looked at if it has so many draws in common; at similarity 0.8 fewer happen once in a million pairs.
LEAST_ALIKE = 9
DF_BUCKETS, DF_PARTS = 1 << 20, 16
STEP = 1 << 18
#: Records of runs that a task holds before it sends them, records of a bucket aimed at, bytes of text for a record.
FLUSH, BUCKET_RECORDS, RUN_BYTES = 1 << 20, 2_000_000, 6
RUN, TOTAL = 0, 1
#: A run that fewer than one document in so many have is rare, and all rare ones weigh the same. Else, the more documents there were, the
#: more would the few runs that an edit makes weigh against those that a group of copies has in common.
RARE = 256
#: Slack of bounds on sums of weights, far above their rounding.
SLACK = 1e-9
#: Hash buckets that a document's shared weight is summed by; two documents have at most the lesser sum of each bucket in common.
MARKS = 64
U = np.uint64


def shingles(offsets: np.ndarray, data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Different runs of five words of each text, sorted by text and hash: (text, hash, times).

    A text of fewer words is one run of all its words; a text without words has one run that is its bytes.
    """
    n = len(offsets) - 1
    hashes, owner, _ = word_hashes(offsets, data)
    words = np.bincount(owner, minlength=n)
    with np.errstate(over="ignore"):
        runs = hashes.copy()
        for j in range(1, min(WORDS, len(runs))):
            runs[: len(runs) - j] += hashes[j:] * _POWERS[2 * j]
        runs = mix64(runs)
        ends = np.cumsum(words)
        full = np.arange(len(hashes)) + WORDS <= ends[owner]
        texts, got = [owner[full]], [runs[full]]
        for t in np.flatnonzero(words < WORDS).tolist():
            if words[t]:
                own = hashes[ends[t] - words[t] : ends[t]]
                value = (own * _POWERS[2 * np.arange(len(own))]).sum() + U(len(own))
            else:
                own = data[offsets[t] : offsets[t + 1]].astype(U) + U(1)
                value = (own * mix64(np.arange(len(own), dtype=U))).sum() + U(0xABCDEF)
            texts.append(np.array([t]))
            got.append(mix64(np.array([value], U)))
    texts, got = np.concatenate(texts), np.concatenate(got)
    order = np.lexsort((got, texts))
    texts, got = texts[order], got[order]
    new = np.flatnonzero(np.append(True, (texts[1:] != texts[:-1]) | (got[1:] != got[:-1]))) if len(texts) else np.zeros(0, np.int64)
    return texts[new], got[new], np.diff(np.append(new, len(texts)))


def document_frequencies(texts: DataFrame) -> tuple[np.ndarray, int]:
    """Documents by bucket of the runs they have, and documents in all. Tasks send compressed blocks of counts."""

    def count(batches):
        totals, n = np.zeros(DF_BUCKETS, np.int64), 0
        for batch in steps(batches, "text", 4 * STEP):
            _, got, _ = shingles(*column_bytes(batch.column(0)))
            totals += np.bincount((got & U(DF_BUCKETS - 1)).astype(np.int64), minlength=DF_BUCKETS)
            n += batch.num_rows
        blocks = np.split(totals, DF_PARTS)
        pack = zstandard.ZstdCompressor(level=1).compress
        yield pa.RecordBatch.from_arrays([pa.array(range(DF_PARTS), pa.int32()), pa.array([pack(b.tobytes()) for b in blocks], pa.binary()), pa.array([n] * DF_PARTS, pa.int64())], ["part", "block", "n"])

    def add(batches):
        sums: dict[int, list] = {}
        open_ = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            for part, block, n in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                had = sums.setdefault(part, [np.zeros(DF_BUCKETS // DF_PARTS, np.int64), 0])
                had[0] += np.frombuffer(open_(block), np.int64)
                had[1] += n
        for part, (total, n) in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([zstandard.compress(total.tobytes(), 3)], pa.binary()), pa.array([n], pa.int64())], ["part", "block", "n"])

    schema = "part int, block binary, n bigint"
    rows = sorted(texts.select("text").mapInArrow(count, schema).repartitionById(DF_PARTS, F.col("part")).mapInArrow(add, schema).collect(), key=lambda r: r["part"])
    if not rows:
        return np.zeros(DF_BUCKETS, np.int64), 0
    return np.concatenate([np.frombuffer(zstandard.decompress(r["block"]), np.int64) for r in rows]), rows[0]["n"]


def idf(frequencies: np.ndarray, documents: int) -> np.ndarray:
    """Weight of a run by the number of documents that have it; rare ones weigh the same, however rare."""
    return np.log1p(np.minimum(max(documents, 1) / np.maximum(frequencies, 1), RARE))


def idf_weights(frequencies: np.ndarray, documents: int) -> np.ndarray:
    return idf(frequencies, documents).astype(np.float32)


@lru_cache(maxsize=1)
def gamma_table() -> tuple[np.ndarray, np.ndarray]:
    """Quantiles of the Gamma(2, 1) distribution, and their logarithms, at 65,536 even steps."""
    p = (np.arange(1 << 16) + 0.5) / (1 << 16)
    low, high = np.zeros(len(p)), np.full(len(p), 40.0)
    for _ in range(60):
        mid = (low + high) / 2
        below = 1 - np.exp(-mid) * (1 + mid) < p
        low, high = np.where(below, mid, low), np.where(below, high, mid)
    return high.astype(np.float32), np.log(high).astype(np.float32)


def weighted_draws(texts: np.ndarray, got: np.ndarray, weights: np.ndarray, n: int) -> np.ndarray:
    """n x DRAWS hashes of (run, level) drawn from each text's weighted runs; every text has one run at least."""
    gamma, log_gamma = gamma_table()
    log_weight = np.log(weights)
    starts = np.searchsorted(texts, np.arange(n))
    counts = np.diff(np.append(starts, len(texts)))
    out = np.zeros((n, DRAWS), U)
    low = U(0xFFFF)
    for k in range(DRAWS):
        with np.errstate(over="ignore"):
            x = mix64(got + U((k + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1))
        r = gamma[(x & low).astype(np.int64)]
        beta = ((x >> U(16)) & low).astype(np.float32) * np.float32(1 / 65536)
        level = np.floor(log_weight / r + beta)
        a = log_gamma[((x >> U(32)) & low).astype(np.int64)] - r * (level + 1 - beta)
        least = np.minimum.reduceat(a, starts)
        hit = np.flatnonzero(a == np.repeat(least, counts))
        hit = hit[np.append(True, texts[hit[1:]] != texts[hit[:-1]])]
        with np.errstate(over="ignore"):
            out[:, k] = mix64(got[hit] + level[hit].astype(np.int64).view(U) * U(0xD6E8FEB86659FD93))
    return out


SIGNED = "doc_id bigint, print_a bigint, print_b bigint, draws array<int>, bands array<bigint>"


def sign(weights: np.ndarray):
    """Task: fingerprint of each text's multiset of runs, its draws (32 bits of each) and the keys of its bands."""

    def kernel(batches):
        for batch in steps(batches, "text", STEP):
            n = batch.num_rows
            texts, got, times = shingles(*column_bytes(batch.column(1)))
            starts = np.searchsorted(texts, np.arange(n))
            with np.errstate(over="ignore"):
                prints = [np.add.reduceat(mix64(got ^ U(s)) * (times.astype(U) * U(2) + U(1)), starts).view(np.int64) for s in (0x51ED270B, 0x2545F491)]
            draws = weighted_draws(texts, got, weights[(got & U(DF_BUCKETS - 1)).astype(np.int64)] * times.astype(np.float32), n)
            with np.errstate(over="ignore"):
                bands = np.stack([mix64(draws[:, b * ROWS] * U(3) + mix64(draws[:, b * ROWS + 1]) + U(b)) for b in range(BANDS)], 1)
            short = (draws >> U(32)).astype(np.uint32).view(np.int32)
            lists = [pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * w), pa.array(v.reshape(-1))) for v, w in ((short, DRAWS), (bands.view(np.int64), BANDS))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints[0]), pa.array(prints[1]), *lists], ["doc_id", "print_a", "print_b", "draws", "bands"])

    return kernel


def band_pairs(reps: DataFrame, parts: int) -> DataFrame:
    """Pairs (a, b) of neighbours within bands, where a < b.

    Members of a band that share its key are put in the order of their next bands' keys, so that the alike stand together
    however large the group; each is paired with the two before it and with its group's first. Range
    splitters from a sample cut even one large group between tasks, and the pairs across a cut are added.
    """
    spark = reps.sparkSession
    sample = reps.orderBy(F.xxhash64("doc_id")).limit(20_000).select("bands").toArrow().column(0).combine_chunks()
    keys = sample.values.to_numpy().view(U).reshape(-1, BANDS) if len(sample) else np.zeros((0, BANDS), U)
    first = keys.reshape(-1) >> U(16)
    second = np.roll(keys, -1, axis=1).reshape(-1) >> U(32)
    order = np.lexsort((second, first))
    at = (np.arange(1, parts) * len(order)) // parts
    cut1, cut2 = (first[order][at], second[order][at]) if len(order) else (np.zeros(0, U), np.zeros(0, U))

    def send(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            docs = batch.column(0).to_numpy()
            got = batch.column(1).values.to_numpy().view(U).reshape(-1, BANDS)
            got = got[: batch.num_rows] if batch.column(1).offset == 0 else got[batch.column(1).offset : batch.column(1).offset + batch.num_rows]
            key, then = got.reshape(-1) >> U(16), np.roll(got, -1, axis=1).reshape(-1) >> U(32)
            doc = np.repeat(docs, BANDS)
            part = np.searchsorted(cut1, key, side="left")
            hit = np.flatnonzero(np.isin(key, cut1))
            for value in np.unique(key[hit]):
                mine = hit[key[hit] == value]
                low, high = np.searchsorted(cut1, value, side="left"), np.searchsorted(cut1, value, side="right")
                part[mine] = low + np.searchsorted(cut2[low:high], then[mine], side="left")
            order = np.argsort(part, kind="stable")
            cuts = np.searchsorted(part[order], np.arange(parts + 1))
            rows = [(p, packed((key[i], 6), (then[i], 4), (doc[i], 8))) for p in range(parts) if len(i := order[cuts[p] : cuts[p + 1]])]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], ["part", "block"])

    def pair(batches):
        """Pairs; and, as rows of their own, the first two and last two members with their keys."""
        held, part = [], None
        for batch in batches:
            for part, block in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                held.append(unpacked(block, 6, 4, 8)[0])
        if not held:
            return
        key, then, doc = (np.concatenate(c) for c in zip(*held, strict=True))
        doc = doc.view(np.int64)
        order = multikey_order(key, then, doc)
        key, then, doc = key[order], then[order], doc[order]
        head = np.maximum.accumulate(np.where(np.append(True, key[1:] != key[:-1]), np.arange(len(key)), 0))
        me = np.arange(len(key))
        a, b = [], []
        for other in (np.maximum(me - 1, head), np.maximum(me - 2, head), head):
            some = doc[other] != doc
            a.append(np.minimum(doc[other], doc)[some])
            b.append(np.maximum(doc[other], doc)[some])
        a, b = np.concatenate(a), np.concatenate(b)
        order = multikey_order(a, b)
        a, b = a[order], b[order]
        new = np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])) if len(a) else np.zeros(0, bool)
        a, b = a[new], b[new]
        none = np.zeros(len(a), np.int64)
        edge = np.unique([0, min(1, len(key) - 1), max(0, len(key) - 2), len(key) - 1])
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([a, doc[edge]])), pa.array(np.concatenate([b, key[edge].view(np.int64)])), pa.array(np.concatenate([none - 1, np.full(len(edge), part)])), pa.array(np.concatenate([none, edge]))], ["a", "b", "part", "at"])

    sent = reps.select("doc_id", "bands").mapInArrow(send, "part int, block binary").repartitionById(parts, F.col("part"))
    found = stored(sent.mapInArrow(pair, "a bigint, b bigint, part bigint, at bigint"), "band-pairs")
    edges = sorted((r["part"], r["at"], r["b"], r["a"]) for r in found.where("part >= 0").collect())
    across = [(x[3], y[3]) for n, x in enumerate(edges) for y in edges[n + 1 : n + 4] if x[0] != y[0] and x[2] == y[2] and x[3] != y[3]]
    pairs = found.where("part < 0").select("a", "b")
    if across:
        pairs = pairs.unionByName(spark.createDataFrame([(min(p), max(p)) for p in across], "a bigint, b bigint"))
    return pairs.distinct()


def similarities(offsets: np.ndarray, data: np.ndarray, weights: np.ndarray, pairs: list[tuple[int, int]]) -> list[float]:
    """Weighted Jaccard similarities of pairs of texts of a block."""
    texts, got, times = shingles(offsets, data)
    weight = weights[(got & U(DF_BUCKETS - 1)).astype(np.int64)].astype(np.float64) * times
    starts = np.searchsorted(texts, np.arange(len(offsets)))
    out = []
    for i, j in pairs:
        a, b = slice(starts[i], starts[i + 1]), slice(starts[j], starts[j + 1])
        x, y = got[a], got[b]
        at = np.minimum(np.searchsorted(y, x), len(y) - 1)
        same = np.flatnonzero(y[at] == x)
        both = np.minimum(weight[a][same], weight[b][at[same]]).sum()
        out.append(float(both / (weight[a].sum() + weight[b].sum() - both)))
    return out


def marks(owner: np.ndarray, got: np.ndarray, weight: np.ndarray, n: int) -> np.ndarray:
    """n x MARKS sums of the weights of each document's runs by hash bucket, rounded up to half precision so that bounds from them hold."""
    sums = np.bincount(owner * MARKS + (got % U(MARKS)).astype(np.int64), weight, n * MARKS).reshape(n, MARKS)
    with np.errstate(over="ignore"):
        half = sums.astype(np.float16)
    return np.where(half < sums, np.nextafter(half, np.float16(np.inf)), half).astype(np.float32)


def can_be_alike(both, weight_a, weight_b, least: float):
    """Whether documents of such weights that have ``both`` in common are at least so similar."""
    return both * (1 + least) >= least * (weight_a + weight_b) * (1 - SLACK)


def run_counts(texts: DataFrame, documents: int, least: float) -> DataFrame:
    """doc_id, weight, runs, marks of each document that can be so similar to another one.

    ``runs`` has its runs that other documents have too: hash, document frequency and times, in the order of hashes. Runs meet
    in the bucket of their hash, where they are counted, and go back to their documents. ``weight`` is that of all
    the document's runs, ``marks`` those of the runs it shares, summed by hash bucket. A document of which less than the
    share ``least`` is in other documents is like none.
    """
    spark = texts.sparkSession
    size = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(partitions_for(spark), size // (RUN_BYTES * BUCKET_RECORDS) + 1)
    bounds = (np.arange(1, parts, dtype=np.float64) / parts * 2.0**64).astype(U)

    def row(kind, part, block):
        return pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([part], pa.int32()), pa.array([block], pa.binary())], ["kind", "part", "block"])

    def by_part(part, order):
        cuts = np.searchsorted(part[order], np.arange(parts + 1))
        return ((p, order[cuts[p] : cuts[p + 1]]) for p in range(parts) if cuts[p] < cuts[p + 1])

    def send(batches):
        held, totals, n = [], [], 0

        def flush():
            got, docs, times = joined(held)
            order = np.argsort(got)
            for p, at in by_part(np.searchsorted(bounds, got, side="right"), order):
                yield row(RUN, p, packed((got[at], 8), (docs[at], 8), (times[at], 5)))
            docs, total = joined(totals)
            part = home(docs, parts)
            for p, at in by_part(part, np.argsort(part, kind="stable")):
                yield row(TOTAL, p, packed((docs[at], 8), (total[at], 5)))

        for batch in steps(batches, "text", 4 * STEP):
            ids = batch.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False)
            owner, got, times = shingles(*column_bytes(batch.column(1)))
            held.append([got, ids[owner], times])
            totals.append([ids, np.bincount(owner, times, len(ids)).astype(np.int64)])
            n += len(got)
            if n >= FLUSH:
                yield from flush()
                held, totals, n = [], [], 0
        if held:
            yield from flush()

    def count(batches):
        held = []
        for batch in batches:
            for kind, part, block in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if kind == RUN:
                    held.append(unpacked(block, 8, 8, 5)[0])
                else:
                    yield row(kind, part, block)
        if not held:
            return
        got, docs, times = joined(held)
        held.clear()
        order = np.argsort(got)
        got, docs, times = got[order], docs[order].view(np.int64), times[order]
        starts = np.flatnonzero(np.append(True, got[1:] != got[:-1]))
        having = np.diff(np.append(starts, len(got)))
        having = np.repeat(having, having)
        some = np.flatnonzero((having > 1) & (docs != NO_ID))
        got, docs, times, having = got[some], docs[some], times[some], having[some]
        part = home(docs, parts)
        for p, at in by_part(part, np.argsort(part, kind="stable")):
            yield row(RUN, p, packed((docs[at], 8), (got[at], 8), (having[at], 5), (times[at], 5)))

    def gather(batches):
        runs, totals = [], []
        for batch in batches:
            for kind, _, block in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if kind == RUN:
                    runs.append(unpacked(block, 8, 8, 5, 5)[0])
                else:
                    totals.append(unpacked(block, 8, 5)[0])
        if not runs:
            return
        docs, got, having, times = joined(runs)
        runs.clear()
        order = multikey_order(docs, got)
        docs, got, having, times = docs[order], got[order], having[order].astype(np.int64), times[order].astype(np.int64)
        once = np.append(True, (docs[1:] != docs[:-1]) | (got[1:] != got[:-1]))
        docs, got, having, times = docs[once], got[once], having[once], times[once]
        starts = np.flatnonzero(np.append(True, docs[1:] != docs[:-1]))
        ends = np.append(starts[1:], len(docs))
        known, total = joined(totals)
        order = multikey_order(known, total)
        total = total[order][np.searchsorted(known[order], docs[starts])].astype(np.int64)
        each = times * idf(having, documents)
        shared = np.add.reduceat(each, starts)
        weight = shared + np.maximum(0, total - np.add.reduceat(times, starts)) * idf(1, documents)
        some = np.flatnonzero(shared >= least * weight * (1 - SLACK))
        for k in range(0, len(some), 512):
            at = some[k : k + 512]
            blocks = [packed((got[a:b], 8), (having[a:b], 5), (times[a:b], 5)) for a, b in zip(starts[at].tolist(), ends[at].tolist(), strict=True)]
            own = np.concatenate([np.arange(a, b) for a, b in zip(starts[at].tolist(), ends[at].tolist(), strict=True)])
            sums = marks(np.repeat(np.arange(len(at)), (ends - starts)[at]), got[own], each[own], len(at))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(at) + 1, dtype=np.int32) * MARKS), pa.array(sums.reshape(-1)))
            yield pa.RecordBatch.from_arrays([pa.array(docs[starts[at]].view(np.int64)), pa.array(weight[at]), pa.array(blocks, pa.binary()), lists], ["doc_id", "weight", "runs", "marks"])

    schema = "kind int, part int, block binary"
    sent = texts.mapInArrow(send, schema).repartitionById(parts, F.col("part"))
    return sent.mapInArrow(count, schema).repartitionById(parts, F.col("part")).mapInArrow(gather, "doc_id bigint, weight double, runs binary, marks array<float>")


def verified(pairs: DataFrame, counts: DataFrame, documents: int, least: float) -> DataFrame:
    """Of pairs (a, b), those that are at least so similar by the exact weights. What two documents share is in the counts of both."""

    def kernel(batches):
        for batch in batches:
            sim = []
            for weight_a, weight_b, runs_a, runs_b in zip(*(c.to_pylist() for c in batch.columns[2:]), strict=True):
                (x, having, n), (y, _, m) = unpacked(runs_a, 8, 5, 5)[0], unpacked(runs_b, 8, 5, 5)[0]
                at = np.minimum(np.searchsorted(y, x), len(y) - 1)
                same = np.flatnonzero(y[at] == x)
                both = (np.minimum(n[same], m[at[same]]) * idf(having[same], documents)).sum()
                sim.append(float(both / (weight_a + weight_b - both)))
            keep = pa.array([s >= least - 1e-9 for s in sim], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep), pa.array(sim, pa.float64()).filter(keep)], ["a", "b", "similarity"])

    of = lambda c: counts.select(F.col("doc_id").alias(c), F.col("weight").alias(f"weight_{c}"), F.col("runs").alias(f"runs_{c}"))
    both = pairs.select("a", "b").join(of("a"), "a").join(of("b"), "b")
    return both.select("a", "b", "weight_a", "weight_b", "runs_a", "runs_b").mapInArrow(kernel, "a bigint, b bigint, similarity double")


def prefix_pairs(counts: DataFrame, documents: int, least: float, parts: int, nearest: bool = False) -> DataFrame:
    """All pairs (a, b) of different components that can be so similar, by their rarest common run.

    With runs in one order, rare ones first, a pair shares at most what either has from its first common run on. For weights
    v and w it must share least / (1 + least) * (v + w), so a run is of use to a document only as long as the rest from it on
    is the share ``least``, and only for partners whose weight the rest allows. Of these, pairs go whose marks tell that they
    share less. With ``nearest``, a document gets of a bucket's partners only the one that its marks are most like: so there are no
    more pairs than documents in buckets, whatever their groups. Columns: doc_id, weight, runs, marks, component.
    """
    factor = (1 + least) / least

    def send(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            doc, weight, component = (batch.column(k).to_numpy() for k in (0, 1, 4))
            sums = np.stack(batch.column(3).to_numpy(zero_copy_only=False)).astype(np.float16)
            held = []
            for k, block in enumerate(batch.column(2).to_pylist()):
                got, having, times = unpacked(block, 8, 5, 5)[0]
                order = np.lexsort((got, having))
                rest = np.cumsum((times * idf(having, documents))[order][::-1])[::-1]
                n = int((rest >= least * weight[k] * (1 - SLACK)).sum())
                held.append([got[order][:n], rest[:n], np.full(n, k)])
            got, rest, of = joined(held)
            part = (got % U(parts)).astype(np.int64)
            order = np.argsort(part, kind="stable")
            cuts = np.searchsorted(part[order], np.arange(parts + 1))
            rows = []
            for p in np.flatnonzero(cuts[1:] > cuts[:-1]).tolist():
                at = order[cuts[p] : cuts[p + 1]]
                own, place = np.unique(of[at], return_inverse=True)
                rows.append((p, packed((got[at], 8), (rest[at].view(U), 8), (place, 4)), packed((doc[own], 8), (weight[own].view(U), 8), (component[own], 8)), sums[own].tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), *(pa.array([r[k] for r in rows], pa.binary()) for k in (1, 2, 3))], ["part", "block", "docs", "marks"])

    def pair(batches):
        held, about, sums, known = [], [], [], 0
        for batch in batches:
            for block, docs, own in zip(*(c.to_pylist() for c in batch.columns[1:]), strict=True):
                got, rest, place = unpacked(block, 8, 8, 4)[0]
                held.append([got, rest, place.astype(np.int64) + known])
                about.append(unpacked(docs, 8, 8, 8)[0])
                sums.append(np.frombuffer(own, np.float16).reshape(-1, MARKS))
                known += len(sums[-1])
        if not held:
            return
        got, rest, of = joined(held)
        ids, weights, components = joined(about)
        sums = np.concatenate(sums).astype(np.float32)
        held.clear()
        ids, weights, components, rest = ids.view(np.int64), weights.view(np.float64), components.view(np.int64), rest.view(np.float64)
        order = np.lexsort((components[of], got))
        got, rest, of = got[order], rest[order], of[order]
        component = components[of]
        run = np.cumsum(np.append(True, got[1:] != got[:-1])) - 1
        # Of each run's components the largest needs no pairs of its own: the others' members look for theirs.
        new = np.flatnonzero(np.append(True, (run[1:] != run[:-1]) | (component[1:] != component[:-1])))
        size = np.diff(np.append(new, len(run)))
        by_size = np.lexsort((-size, run[new]))
        largest = by_size[np.append(True, run[new][by_size][1:] != run[new][by_size][:-1])]
        seeks = np.ones(len(new), bool)
        seeks[largest] = False
        seeks = np.repeat(seeks, size)
        several = np.zeros(run[-1] + 1, bool)
        several[run[seeks]] = True
        use = several[run]
        run, rest, of, seeks = (c[use] for c in (run, rest, of, seeks))
        if not len(run):
            return
        order = np.lexsort((weights[of], run))
        run, rest, of, seeks = (c[order] for c in (run, rest, of, seeks))
        weight, component = weights[of], components[of]
        limit = (rest * factor - weight) * (1 + SLACK) + SLACK
        values = np.unique(weight)
        place = run * (len(values) + 1) + np.searchsorted(values, weight)
        me = np.flatnonzero(seeks)
        low = np.searchsorted(place, run[me] * (len(values) + 1) + np.searchsorted(values, least * weight[me] * (1 - SLACK)))
        high = np.searchsorted(place, run[me] * (len(values) + 1) + np.searchsorted(values, limit[me], side="right"))
        many = np.maximum(0, high - low)
        ends = np.cumsum(many)
        at = 0
        while at < len(me):
            to = max(at + 1, int(np.searchsorted(ends, ends[at] - many[at] + (1 << 21), side="right")))
            n = many[at:to]
            i = np.repeat(me[at:to], n)
            j = np.arange(len(i)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(low[at:to], n)
            keep = (component[i] != component[j]) & (limit[j] >= weight[i])
            once = np.unique(of[i[keep]] * known + of[j[keep]])
            seeker, other = once // known, once % known
            both = np.concatenate([np.zeros(0), *(np.minimum(sums[seeker[k : k + STEP]], sums[other[k : k + STEP]]).sum(1, dtype=np.float64) for k in range(0, len(once), STEP))])
            keep = can_be_alike(both, weights[seeker], weights[other], least)
            seeker, other, share = seeker[keep], other[keep], (both / (weights[seeker] + weights[other]))[keep]
            if nearest:
                best = np.lexsort((-share, seeker))
                best = best[np.flatnonzero(np.append(True, seeker[best][1:] != seeker[best][:-1]))] if len(best) else best
                seeker, other = seeker[best], other[best]
            a, b = np.minimum(ids[seeker], ids[other]), np.maximum(ids[seeker], ids[other])
            order = multikey_order(a, b)
            a, b = a[order], b[order]
            new = np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])) if len(a) else np.zeros(0, bool)
            yield pa.RecordBatch.from_arrays([pa.array(a[new]), pa.array(b[new])], ["a", "b"])
            at = to

    sent = counts.select("doc_id", "weight", "runs", "marks", "component").mapInArrow(send, "part int, block binary, docs binary, marks binary").repartitionById(parts, F.col("part"))
    return sent.mapInArrow(pair, "a bigint, b bigint").distinct()


def between(pairs: DataFrame, label: DataFrame) -> DataFrame:
    """Pairs (a, b) whose documents are in different components; a document without a label is one of its own."""
    of = lambda c: label.select(F.col("node").alias(c), F.col("component").alias(f"in_{c}"))
    both = pairs.select("a", "b").join(of("a"), "a", "left").join(of("b"), "b", "left")
    return both.where(F.coalesce("in_a", "a") != F.coalesce("in_b", "b")).select("a", "b")


def linked(label: DataFrame, links: DataFrame) -> DataFrame:
    """Components as they are once ``links`` (a, b) have been added."""
    more = stored(links.select("a", "b"), "more-links")
    if more.isEmpty():
        return label
    return connected_components(label.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(more))


def near_duplicates(docs: DataFrame, least: float = SIMILARITY) -> DataFrame:
    """One row per document: doc_id, class_id (the class's smallest doc_id), rep_id (of those with the same runs of words), kept.

    Classes are the connected components of links of at least ``least`` weighted Jaccard similarity. Null text
    counts as empty; texts without words are alike only if their bytes are. Rows without doc_id are in no class and stay;
    repeated rows are in one class, and all rows with the class's doc_id carry kept, so a caller who wants one of them drops
    duplicates by doc_id. An empty table gives an empty result. Other columns are ignored.
    """
    spark = docs.sparkSession
    texts = texts_of(docs)
    frequencies, documents = document_frequencies(texts)
    weights = idf_weights(frequencies, documents)
    signed = stored(texts.where("doc_id IS NOT NULL").mapInArrow(sign(weights), SIGNED), "signatures")
    release_shuffles(spark)
    prints = stored(signed.groupBy("print_a", "print_b").agg(F.min("doc_id").alias("rep_id"), F.count(F.lit(1)).alias("copies")), "prints")
    members = join_per_key(signed.select("doc_id", "print_a", "print_b"), prints, ["print_a", "print_b"], "copies", documents).select("doc_id", "rep_id")
    members = stored(members, "members")
    heads = members.where("doc_id = rep_id").select("doc_id").distinct()
    counts = stored(run_counts(texts, documents, least).join(heads.hint("shuffle_hash"), "doc_id", "left_semi"), "run-counts")
    release_shuffles(spark)
    # Documents that can be like no other need no neighbours.
    reps = stored(signed.join(counts.select("doc_id", "weight", "marks"), "doc_id").dropDuplicates(["doc_id"]).select("doc_id", "draws", "bands", "weight", "marks"), "reps")
    pairs = band_pairs(reps, partitions_for(spark))
    of = lambda c: reps.select(F.col("doc_id").alias(c), *(F.col(x).alias(f"{x}_{c}") for x in ("draws", "weight", "marks")))
    alike = F.aggregate(F.zip_with("draws_a", "draws_b", lambda x, y: (x == y).cast("int")), F.lit(0), lambda x, y: x + y)
    both = F.aggregate(F.zip_with("marks_a", "marks_b", lambda x, y: F.least(x, y).cast("double")), F.lit(0.0), lambda x, y: x + y)
    near = pairs.join(of("a"), "a").join(of("b"), "b").where(can_be_alike(both, F.col("weight_a"), F.col("weight_b"), least))
    near = stored(near.select("a", "b", alike.alias("alike")).where(F.col("alike") >= LEAST_ALIKE), "near-pairs")
    release_shuffles(spark)

    # Each document with the earlier one most like it first; then the other neighbours, then for each document and bucket the one that it can be
    # most like, and then all pairs that can be alike, as far as they are still apart.
    parents = near.groupBy("b").agg(F.max(F.struct("alike", (-F.col("a")).alias("a"))).alias("best")).select((-F.col("best.a")).alias("a"), "b")
    label = connected_components(stored(verified(parents, counts, documents, least).select("a", "b"), "links"))
    release_shuffles(spark)
    label = linked(label, verified(stored(between(near, label), "pairs-between"), counts, documents, least))
    for nearest in (True, False):
        known = counts.join(label.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
        apart = stored(prefix_pairs(known, documents, least, partitions_for(spark), nearest), "pairs-apart")
        if apart.isEmpty():
            break
        label = linked(label, verified(apart, counts, documents, least))
    classes = members.join(label.withColumnRenamed("node", "rep_id"), "rep_id", "left").select("doc_id", F.coalesce("component", "rep_id").alias("class_id"), "rep_id")
    alone = texts.where("doc_id IS NULL").select("doc_id", F.lit(None).cast("long").alias("class_id"), F.lit(None).cast("long").alias("rep_id"))
    return classes.unionByName(alone).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("class_id")))


def keep_class_heads(docs: DataFrame, least: float = SIMILARITY) -> DataFrame:
    """The rows of ``docs``, all columns as they are, of which each class of near-duplicates keeps one; rows without doc_id stay."""
    result = stored(near_duplicates(docs, least), "near")
    heads = result.where("kept AND doc_id IS NOT NULL").select("doc_id")
    out = docs.where("doc_id IS NOT NULL").join(heads.distinct().hint("shuffle_hash"), "doc_id", "left_semi").select(*docs.columns)
    if not heads.groupBy("doc_id").count().where("count > 1").isEmpty():
        out = out.dropDuplicates(["doc_id"])
    if not result.where("doc_id IS NULL").isEmpty():
        out = out.unionByName(docs.where("doc_id IS NULL"))
    return out
