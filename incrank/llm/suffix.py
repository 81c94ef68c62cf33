"""Removal of passages that an earlier document also has, by a distributed suffix sort.

A byte goes when a string of ``length`` bytes covers it that also starts in a
document with a smaller doc_id (rows that share one or have none: in an earlier row). Not all suffixes need sorting: every string of
that length has a least hashed token (a window of ``token`` bytes), and neighbouring
strings mostly share it. So one suffix is kept for each run of strings with one
least token: it is known by that leading token, by a fingerprint of the whole
run, by document and place.

1. Sampled splitters range-partition the suffixes by leading token. A splitter never
   cuts through one token, so equal strings meet in one bucket and no comparison
   across a boundary is left to do; tokens that the sample finds hot skip this step.
2. Buckets sort by multikey quicksort. A run that an earlier document has whole is
   removed; a token no earlier document has is settled; what is left are the
   edges of repeated passages, and hot tokens.
3. Edges send their few bytes to the bucket of their token again, where all their
   strings are compared one by one. Hot tokens send fingerprints of their strings, of each task's equal
   strings only the first document's.

Records travel as compressed blocks, a few rows for each task and bucket.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import release_shuffles
from .common import STEP_BYTES, column_bytes, give_back, mix64, partitions_for, steps, stored, texts_of

LENGTH, TOKEN = 50, 24
#: Records that a task holds before it sends them; strings of one run at most (more would not share its first and last string's bytes).
FLUSH, LONGEST_RUN = 1 << 20, LENGTH + 1
#: Records of a bucket aimed at, documents of the sample for splitters, records of it that the driver sees.
BUCKET_RECORDS, SAMPLE_DOCS, SAMPLE_RECORDS = 2_000_000, 2_000, 200_000
#: Columns of rows' own keys and written numbers.
KEY, NUMBER = "suffix_row_key", "suffix_row_number"
NO_ID = (1 << 63) - 1
REMOVED, EDGE, HOT = 0, 1, 2

U = np.uint64


def _wider(h: np.ndarray, step: int, factor: int) -> np.ndarray:
    """Hashes of strings twice as long as ``step`` from those of ``step`` bytes."""
    with np.errstate(over="ignore"):
        out = h[:-step] * U(factor)
        out += h[step:]
        out ^= out >> U(29)
    return out


class Strings:
    """Hashes of all tokens and strings of a block of bytes."""

    def __init__(self, data: np.ndarray) -> None:
        with np.errstate(over="ignore"):
            one = (data.astype(U) + U(1)) * U(0x9E3779B97F4A7C15)
        self.two = _wider(one, 1, 0xBF58476D1CE4E5B9)
        self.eight = _wider(_wider(self.two, 2, 0x94D049BB133111EB), 4, 0xD6E8FEB86659FD93)
        self.sixteen = _wider(self.eight, 8, 0xA0761D6478BD642F)

    def least_tokens(self) -> np.ndarray:
        """Of each string, the least hash of its tokens."""
        with np.errstate(over="ignore"):
            h = self.sixteen[: len(self.sixteen) - 8] * U(0xE7037ED1A0B428DB)
            h += self.eight[16:]
            h ^= h >> U(32)
            h *= U(0x9FB21C651E98DF25)
            h ^= h >> U(28)
        for step in (1, 2, 4, 8):
            h = np.minimum(h[:-step], h[step:])
        rest = LENGTH - TOKEN + 1 - 16
        return np.minimum(h[:-rest], h[rest:])

    def strings(self, at: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            h = self.sixteen[at] * U(0x8EBC6AF09C88C6E3) + self.sixteen[at + 16]
            h ^= h >> U(31)
            h = h * U(0x589965CC75374CC3) + self.sixteen[at + 32]
            h ^= h >> U(31)
            return mix64(h * U(0x1D8E4E27C47D124F) + self.two[at + 48])


def string_places(offsets: np.ndarray) -> np.ndarray:
    """Of each byte, whether a whole string of its own text starts there."""
    size = int(offsets[-1])
    lengths = np.diff(offsets)
    fits = lengths >= LENGTH
    steps_ = np.zeros(size + 1, np.int32)
    np.add.at(steps_, offsets[:-1][fits], 1)
    np.add.at(steps_, offsets[1:][fits] - LENGTH + 1, -1)
    return np.cumsum(steps_[:size]) > 0


def runs_of(offsets: np.ndarray, data: np.ndarray):
    """Runs of strings with one least token: (token, fingerprint, first string, strings), 48 bits of each hash."""
    empty = np.zeros(0, U), np.zeros(0, U), np.zeros(0, np.int64), np.zeros(0, np.int64)
    if len(data) < LENGTH:
        return empty
    h = Strings(data)
    least = h.least_tokens()
    here = string_places(offsets)[: len(least)]
    first = here.copy()
    first[1:] &= (least[1:] != least[:-1]) | ~here[:-1]
    heads = offsets[:-1][offsets[:-1] < len(here)]
    first[heads] = here[heads]
    starts = np.flatnonzero(first)
    if not len(starts):
        return empty
    ends = np.minimum(np.append(starts[1:], len(here)), _last_places(here, starts))
    counts = ends - starts
    if counts.max() > LONGEST_RUN:
        parts = -(-counts // LONGEST_RUN)
        again = np.repeat(np.arange(len(starts)), parts)
        nth = np.arange(len(again)) - np.repeat(np.cumsum(parts) - parts, parts)
        counts = np.minimum(LONGEST_RUN, counts[again] - nth * LONGEST_RUN)
        starts = starts[again] + nth * LONGEST_RUN
    with np.errstate(over="ignore"):
        print_ = mix64(h.strings(starts) * U(3) + h.strings(starts + counts - 1) * U(0x9E3779B97F4A7C15) + counts.astype(U))
    return least[starts] >> U(16), print_ >> U(16), starts, counts


def _last_places(here: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Of each start, the first place after it where no string starts."""
    gaps = np.append(np.flatnonzero(~here), len(here))
    return gaps[np.searchsorted(gaps, starts)]


def blocks_of(batches: Iterator[pa.RecordBatch]):
    """(doc_ids, offsets, bytes, base, row): texts in slices of about a megabyte; a longer text in overlapping pieces."""
    for batch in steps(batches):
        ids = batch.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False)
        offsets, data = column_bytes(batch.column(1))
        if batch.num_rows > 1 or len(data) <= 4 * STEP_BYTES:
            yield batch, ids, offsets, data, 0
        else:
            for at in range(0, len(data) - LENGTH + 1, STEP_BYTES):
                piece = data[at : at + STEP_BYTES + LENGTH - 1]
                yield batch, ids, np.array([0, len(piece)]), piece, at


def multikey_order(*words: np.ndarray) -> np.ndarray:
    """Order by the first word; where it ties, by the next; and so on: only ties are sorted again."""
    order = np.argsort(words[0], kind="stable")
    same = np.zeros(len(order), bool)
    same[1:] = words[0][order][1:] == words[0][order][:-1]
    for word in words[1:]:
        tied = same.copy()
        tied[:-1] |= same[1:]
        at = np.flatnonzero(tied)
        if not len(at):
            break
        group = np.cumsum(~same)[at]
        by = word[order[at]]
        inner = np.lexsort((by, group))
        order[at] = order[at][inner]
        by = by[inner]
        equal = np.zeros(len(at), bool)
        equal[1:] = (by[1:] == by[:-1]) & (group[1:] == group[:-1])
        same = np.zeros(len(order), bool)
        same[at] = equal
    return order


def packed(*arrays: tuple[np.ndarray, int]) -> bytes:
    """Columns of whole numbers, the low bytes of each, plane by plane, compressed."""
    parts = [a.astype(np.int64 if a.dtype.kind == "i" else U).view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes() for a, width in arrays]
    return zstandard.ZstdCompressor(level=1).compress(len(arrays[0][0]).to_bytes(8, "little") + b"".join(parts))


def unpacked(blob: bytes, *widths: int) -> tuple[list[np.ndarray], bytes]:
    data = zstandard.ZstdDecompressor().decompress(blob)
    n, at, out = int.from_bytes(data[:8], "little"), 8, []
    for width in widths:
        wide = np.zeros((n, 8), np.uint8)
        wide[:, :width] = np.frombuffer(data, np.uint8, n * width, at).reshape(width, n).T
        out.append(wide.view(U).reshape(-1))
        at += n * width
    return out, data[at:]


def joined(lists: list[list[np.ndarray]]) -> list[np.ndarray]:
    return [np.concatenate(c) for c in zip(*lists, strict=True)]


SENT = "kind int, part int, block binary"
_SENT = pa.schema([("kind", pa.int32()), ("part", pa.int32()), ("block", pa.binary())])


def _rows(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), _SENT.types, strict=True)], schema=_SENT)


def home(docs: np.ndarray, parts: int) -> np.ndarray:
    return (mix64(docs.view(U)) % U(parts)).astype(np.int64)


def by_home(docs: np.ndarray, first: np.ndarray, count: np.ndarray, flag: np.ndarray, parts: int) -> Iterator[tuple[int, int, bytes]]:
    """Verdicts on runs, on their way back to the documents."""
    part = home(docs, parts)
    order = multikey_order(part, docs, first)
    cuts = np.searchsorted(part[order], np.arange(parts + 1))
    for p in range(parts):
        at = order[cuts[p] : cuts[p + 1]]
        if len(at):
            yield REMOVED, p, packed((docs[at], 8), (first[at], 5), (count[at], 1), (flag[at], 1))


def least_by_group(new: np.ndarray, values: np.ndarray) -> np.ndarray:
    starts = np.flatnonzero(new)
    return np.repeat(np.minimum.reduceat(values, starts), np.diff(np.append(starts, len(values))))


def send_runs(splitters: np.ndarray, hot: np.ndarray, parts: int):
    """Task of step 1: runs to the bucket of their token; runs of hot tokens back to their documents."""

    def kernel(batches):
        held, n = [], 0

        def flush():
            token, print_, docs, first, count = joined(held)
            warm = np.isin(token, hot)
            if warm.any():
                yield from by_home(docs[warm], first[warm], count[warm], np.full(int(warm.sum()), HOT), parts)
                token, print_, docs, first, count = (a[~warm] for a in (token, print_, docs, first, count))
            order = np.argsort(token)
            cuts = np.concatenate([[0], np.searchsorted(token[order], splitters), [len(order)]])
            for p in range(parts):
                at = order[cuts[p] : cuts[p + 1]]
                if len(at):
                    yield EDGE, p, packed((token[at], 6), (print_[at], 6), (docs[at], 8), (first[at], 5), (count[at], 1))

        for _, ids, offsets, data, base in blocks_of(batches):
            token, print_, first, count = runs_of(offsets, data)
            owner = np.searchsorted(offsets, first, side="right") - 1
            held.append([token, print_, ids[owner], first - offsets[owner] + base, count])
            n += len(token)
            if n >= FLUSH:
                yield from (_rows([r]) for r in flush())
                held, n = [], 0
        if n:
            yield from (_rows([r]) for r in flush())

    return kernel


def judge_runs(parts: int):
    """Task of step 2: sort a bucket; send back runs that go, and edges."""

    def kernel(batches):
        held = []
        for batch in batches:
            for kind, part, block in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if kind == EDGE:
                    held.append(unpacked(block, 6, 6, 8, 5, 1)[0])
                else:
                    yield _rows([(kind, part, block)])
        if not held:
            return
        token, print_, docs, first, count = joined(held)
        held.clear()
        docs = docs.view(np.int64)
        order = multikey_order(token, print_, docs)
        token, print_, docs, first, count = (a[order] for a in (token, print_, docs, first, count))
        new_token = np.append(True, token[1:] != token[:-1])
        new_print = new_token | np.append(True, print_[1:] != print_[:-1])
        removed = docs > least_by_group(new_print, docs)
        prints = np.add.reduceat(new_print.astype(np.int64), np.flatnonzero(new_token))
        many = np.repeat(prints, np.diff(np.append(np.flatnonzero(new_token), len(token)))) > 1
        several = many & (least_by_group(new_token, -docs) != -least_by_group(new_token, docs))
        # An edge is compared string by string: of equal runs, the first document's stands for all.
        edge = several & ~removed
        keep = removed | edge
        yield from (_rows([r]) for r in by_home(docs[keep], first[keep].astype(np.int64), count[keep].astype(np.int64), np.where(edge[keep], EDGE, REMOVED), parts))
        del token, print_, docs, first, count, order
        give_back()

    return kernel


def by_document(batches):
    """One row per document: its verdicts in one block."""
    held = [unpacked(b, 8, 5, 1, 1)[0] for batch in batches for k, b in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), strict=True) if k == REMOVED]
    if not held:
        return
    docs, first, count, flag = joined(held)
    order = np.lexsort((first, docs))
    docs, first, count, flag = docs[order].view(np.int64), first[order], count[order], flag[order]
    starts = np.flatnonzero(np.append(True, docs[1:] != docs[:-1]))
    ends = np.append(starts[1:], len(docs))
    for k in range(0, len(starts), 4096):
        some = list(zip(starts[k : k + 4096].tolist(), ends[k : k + 4096].tolist(), strict=True))
        pending = [bool((flag[a:b] != REMOVED).any()) for a, b in some]
        yield pa.RecordBatch.from_arrays([pa.array(docs[starts[k : k + 4096]]), pa.array(pending), pa.array([packed((first[a:b], 5), (count[a:b], 1), (flag[a:b], 1)) for a, b in some], pa.binary())], ["doc_id", "pending", "verdicts"])


VERDICTS = "doc_id bigint, pending boolean, verdicts binary"


def send_edges(parts: int):
    """Task of step 3: the bytes of edges to the bucket of their token, fingerprints of hot tokens' strings to buckets of their own."""

    def kernel(batches):
        edges: list[list[np.ndarray]] = []
        texts: list[np.ndarray] = []
        hot: list[list[np.ndarray]] = []
        size = 0

        def flush():
            if edges:
                token, docs, first, count = joined(edges)
                data = np.concatenate(texts)
                starts = np.cumsum(count + LENGTH - 1) - (count + LENGTH - 1)
                part = (mix64(token) % U(parts)).astype(np.int64)
                order = multikey_order(part, token, docs)
                cuts = np.searchsorted(part[order], np.arange(parts + 1))
                for p in range(parts):
                    at = order[cuts[p] : cuts[p + 1]]
                    if len(at):
                        lengths = count[at] + LENGTH - 1
                        index = np.repeat(starts[at] - (np.cumsum(lengths) - lengths), lengths) + np.arange(lengths.sum())
                        yield EDGE, p, packed_with(data[index].tobytes(), (token[at], 6), (docs[at], 8), (first[at], 5), (count[at], 1))
            if hot:
                token, string, docs, first = joined(hot)
                order = multikey_order(string, token, docs)
                token, string, docs, first = (a[order] for a in (token, string, docs, first))
                new = np.append(True, (string[1:] != string[:-1]) | (token[1:] != token[:-1]))
                later = docs > least_by_group(new, docs)
                if later.any():
                    yield from by_home(docs[later], first[later], np.ones(int(later.sum()), np.int64), np.full(int(later.sum()), REMOVED), parts)
                token, string, docs, first = (a[~later] for a in (token, string, docs, first))
                part = (string % U(parts)).astype(np.int64)
                order = multikey_order(part, string, token)
                cuts = np.searchsorted(part[order], np.arange(parts + 1))
                for p in range(parts):
                    at = order[cuts[p] : cuts[p + 1]]
                    if len(at):
                        yield HOT, p, packed((token[at], 6), (string[at], 8), (docs[at], 8), (first[at], 5))

        for batch in steps(batches):
            for key, text, block in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), batch.column(2).to_pylist(), strict=True):
                (first, count, flag), _ = unpacked(block, 5, 1, 1)
                first, count = first.astype(np.int64), count.astype(np.int64)
                data = np.frombuffer(text, np.uint8)
                todo = (flag != REMOVED) & (first + count + LENGTH - 1 <= len(data))
                first, count, flag = first[todo], count[todo], flag[todo]
                if not len(first):
                    continue
                lengths = count + LENGTH - 1
                offsets = np.concatenate([[0], np.cumsum(lengths)])
                index = np.repeat(first - offsets[:-1], lengths) + np.arange(offsets[-1])
                own = data[index]
                h = Strings(own)
                least = h.least_tokens() >> U(16)
                token = least[offsets[:-1]]
                for kind, into in ((EDGE, edges), (HOT, hot)):
                    mine = np.flatnonzero(flag == kind)
                    if not len(mine):
                        continue
                    if kind == EDGE:
                        into.append([token[mine], np.full(len(mine), key), first[mine], count[mine]])
                        texts.append(own[np.repeat(flag == EDGE, lengths)])
                        size += len(texts[-1])
                    else:
                        n = count[mine]
                        each = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                        at = np.repeat(offsets[:-1][mine], n) + each
                        into.append([np.repeat(token[mine], n), h.strings(at), np.full(len(at), key), np.repeat(first[mine], n) + each])
                        size += 32 * len(at)
            if size > 32 * STEP_BYTES:
                yield from (_rows([r]) for r in flush())
                edges, texts, hot, size = [], [], [], 0
        yield from (_rows([r]) for r in flush())

    return kernel


def packed_with(tail: bytes, *arrays: tuple[np.ndarray, int]) -> bytes:
    parts = [a.astype(np.int64 if a.dtype.kind == "i" else U).view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes() for a, width in arrays]
    return zstandard.ZstdCompressor(level=3).compress(len(arrays[0][0]).to_bytes(8, "little") + b"".join(parts) + tail)


def judge_edges(parts: int):
    """Task of step 3: every string of the edges and hot tokens of a bucket against the same strings of earlier documents."""

    def kernel(batches):
        edges, texts, hot = [], [], []
        for batch in batches:
            for kind, part, block in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if kind == EDGE:
                    columns, tail = unpacked(block, 6, 8, 5, 1)
                    edges.append(columns)
                    texts.append(np.frombuffer(tail, np.uint8))
                elif kind == HOT:
                    hot.append(unpacked(block, 6, 8, 8, 5)[0])
                else:
                    yield _rows([(kind, part, block)])
        found = []
        if edges:
            token, docs, first, count = joined(edges)
            data = np.concatenate(texts)
            first, count = first.astype(np.int64), count.astype(np.int64)
            lengths = count + LENGTH - 1
            offsets = np.cumsum(lengths) - lengths
            each = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
            found.append([np.repeat(token, count), Strings(data).strings(np.repeat(offsets, count) + each), np.repeat(docs, count), (np.repeat(first, count) + each).astype(U)])
            edges.clear()
            texts.clear()
        if hot:
            found.append(joined(hot))
            hot.clear()
        if not found:
            return
        token, string, docs, first = joined(found)
        found.clear()
        docs = docs.view(np.int64)
        order = multikey_order(string, token, docs)
        token, string, docs, first = (a[order] for a in (token, string, docs, first))
        new = np.append(True, (string[1:] != string[:-1]) | (token[1:] != token[:-1]))
        later = docs > least_by_group(new, docs)
        docs, first = docs[later], first[later].astype(np.int64)
        # neighbouring strings become runs again
        order = np.lexsort((first, docs))
        docs, first = docs[order], first[order]
        if not len(docs):
            return
        nth = np.arange(len(docs))
        breaks = np.append(True, (docs[1:] != docs[:-1]) | (first[1:] != first[:-1] + 1))
        start = np.maximum.accumulate(np.where(breaks, nth, 0))
        breaks |= (nth - start) % 255 == 0
        starts = np.flatnonzero(breaks)
        count = np.diff(np.append(starts, len(docs)))
        yield from (_rows([r]) for r in by_home(docs[starts], first[starts], count, np.full(len(starts), REMOVED), parts))

    return kernel


def splitters_of(texts: DataFrame, total: int, size: int, partitions: int) -> tuple[np.ndarray, np.ndarray, int]:
    """(splitters, hot tokens, buckets) from a bounded sample of documents; the driver sees at most SAMPLE_RECORDS tokens.

    Buckets are as many as the records of all ``size`` bytes need, at the rate of records that the whole sample has.
    """
    every = max(1, total // SAMPLE_DOCS)
    seen = texts.where(F.pmod(F.xxhash64("doc_id"), F.lit(every)) == 0).limit(4 * SAMPLE_DOCS)

    def kernel(batches):
        for _, _, offsets, data, _ in blocks_of(batches):
            token = runs_of(offsets, data)[0]
            weight = np.zeros(len(token) + 1, np.int64)
            weight[-1] = len(data)
            yield pa.RecordBatch.from_arrays([pa.array(np.append(token, U(0)).view(np.int64)), pa.array(weight)], ["token", "bytes"])

    # one row more for each block says how many bytes it has
    found = stored(seen.mapInArrow(kernel, "token bigint, bytes bigint"), "suffix-sample")
    runs, looked_at = found.agg(F.count_if(F.col("bytes") == 0), F.coalesce(F.sum("bytes"), F.lit(0))).first()
    tokens = found.where("bytes = 0").select("token")
    if runs > SAMPLE_RECORDS:
        tokens = tokens.orderBy(F.xxhash64("token", F.monotonically_increasing_id())).limit(SAMPLE_RECORDS)
    sample = np.sort(tokens.toArrow().column(0).to_numpy().view(U))
    parts = max(partitions, int(runs / max(1, looked_at) * size / BUCKET_RECORDS) + 1)
    if not len(sample):
        return np.zeros(parts - 1, U), np.zeros(0, U), parts
    values, counts = np.unique(sample, return_counts=True)
    hot = values[counts > max(16, len(sample) / (4 * parts))]
    cold = sample[~np.isin(sample, hot)]
    if len(cold) < parts:
        return np.linspace(0, 1 << 48, parts + 1)[1:-1].astype(U), hot, parts
    return cold[np.arange(1, parts) * len(cold) // parts], hot, parts


def keyed(docs: DataFrame) -> DataFrame:
    """``docs`` with a key of its own for every row, in the order of doc_id; rows that share one, or have none and come last, by a written number.

    Where all have a doc_id of their own, that is the key.
    """
    number = F.col("doc_id").cast("long")
    ids = docs.select(number.alias("doc_id"))
    if ids.groupBy("doc_id").count().where("doc_id IS NULL OR count > 1").isEmpty():
        return docs.withColumn(KEY, number)
    parts = partitions_for(docs.sparkSession)
    rows = stored(docs.withColumn(NUMBER, F.monotonically_increasing_id()), "suffix-rows")
    order = [F.col("doc_id").asc_nulls_last(), F.col(NUMBER).asc()]
    dealt = stored(rows.select(number.alias("doc_id"), NUMBER).repartitionByRange(parts, *order).withColumn("part", F.spark_partition_id()), "suffix-order")
    counts = sorted((r["part"], r["count"]) for r in dealt.groupBy("part").count().collect())
    before = [(p, sum(n for _, n in counts[:k])) for k, (p, _) in enumerate(counts)]
    place = F.row_number().over(Window.partitionBy("part").orderBy(*order))
    keys = dealt.withColumn("place", place).join(F.broadcast(docs.sparkSession.createDataFrame(before, "part int, before bigint")), "part")
    return rows.join(stored(keys.select(NUMBER, (F.col("before") + F.col("place")).alias(KEY)), "suffix-keys"), NUMBER).drop(NUMBER)


def verdicts(rows: DataFrame) -> DataFrame:
    """doc_id, blocks: the runs of strings to remove, for rows that have any; doc_id is the key that :func:`keyed` gave the row."""
    spark = rows.sparkSession
    texts = texts_of(rows, KEY)
    total, size = texts.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    splitters, hot, parts = splitters_of(texts, total, size, partitions_for(spark))
    sent = texts.mapInArrow(send_runs(splitters, hot, parts), SENT).repartitionById(parts, F.col("part"))
    back = sent.mapInArrow(judge_runs(parts), SENT).repartitionById(parts, F.col("part"))
    first = stored(back.mapInArrow(by_document, VERDICTS), "suffix-runs")
    release_shuffles(spark)
    pending = first.where("pending").select("doc_id", "verdicts").hint("shuffle_hash")
    edges = texts.join(pending, "doc_id").select("doc_id", "text", "verdicts")
    sent = edges.mapInArrow(send_edges(parts), SENT).repartitionById(parts, F.col("part"))
    back = sent.mapInArrow(judge_edges(parts), SENT).repartitionById(parts, F.col("part"))
    second = stored(back.mapInArrow(by_document, VERDICTS), "suffix-edges")
    release_shuffles(spark)
    return first.unionByName(second).groupBy("doc_id").agg(F.collect_list("verdicts").alias("blocks"))


def removed_spans(blocks: list[bytes] | None, size: int) -> list[tuple[int, int]]:
    """Maximal removed runs of bytes, from the verdicts of a document."""
    if not blocks:
        return []
    columns = joined([unpacked(b, 5, 1, 1)[0] for b in blocks])
    first, count = (c[columns[2] == REMOVED].astype(np.int64) for c in columns[:2])
    if not len(first):
        return []
    order = np.argsort(first, kind="stable")
    first, ends = first[order], np.minimum((first + count + LENGTH - 1)[order], size)
    reach = np.maximum.accumulate(ends)
    new = np.flatnonzero(np.append(True, first[1:] > reach[:-1]))
    return [(a, b) for a, b in zip(first[new].tolist(), reach[np.append(new[1:] - 1, len(first) - 1)].tolist(), strict=True) if a < b]


def without(data: bytes, spans: list[tuple[int, int]]) -> bytes:
    out, at = [], 0
    for a, b in spans:
        out.append(data[at:a])
        at = b
    return b"".join([*out, data[at:]])


def whole_characters(data: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans shrunk to whole characters of UTF-8, so that what is left is text."""
    out = []
    for a, b in spans:
        while a < b and data[a] & 0xC0 == 0x80:
            a += 1
        while b > a and b < len(data) and data[b] & 0xC0 == 0x80:
            b -= 1
        if a < b:
            out.append((a, b))
    return out


def _with_verdicts(docs: DataFrame) -> DataFrame:
    rows = keyed(docs)
    known = verdicts(rows).withColumnRenamed("doc_id", KEY).hint("shuffle_hash")
    texts = rows.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), KEY)
    return texts.join(known, KEY, "left").select("doc_id", "text", "blocks")


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, text, n_removed: the texts without repeated passages. Characters that would be cut in two stay whole.

    Null text counts as empty. Every row is a document of its own: rows that share a doc_id come one after the other, rows
    without one after all others, in the order in which they are read. Texts under 50 bytes stay. Other columns are ignored.
    """

    def kernel(batches):
        for batch in steps(batches):
            texts, gone = [], []
            for text, blocks in zip(batch.column(1).cast(pa.binary()).to_pylist(), batch.column(2).to_pylist(), strict=True):
                spans = whole_characters(text, removed_spans(blocks, len(text)))
                texts.append(without(text, spans).decode())
                gone.append(sum(b - a for a, b in spans))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string()), pa.array(gone, pa.int64())], ["doc_id", "text", "n_removed"])

    return _with_verdicts(docs).mapInArrow(kernel, "doc_id bigint, text string, n_removed bigint")


def repeat_digests(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document; nulls and shared doc_ids as in :func:`remove_repeats`."""

    def kernel(batches):
        for batch in steps(batches):
            rows = []
            for text, blocks in zip(batch.column(1).cast(pa.binary()).to_pylist(), batch.column(2).to_pylist(), strict=True):
                spans = removed_spans(blocks, len(text))
                rows.append((len(text), sum(b - a for a, b in spans), len(spans), hashlib.sha256(without(text, spans)).hexdigest()))
            types = [pa.int64(), pa.int64(), pa.int64(), pa.string()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True))], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return _with_verdicts(docs).mapInArrow(kernel, "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string")


def strip_repeats(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` with repeated passages removed from their texts and n_chars, where there is such a column, set anew.

    All other columns stay as they are, and so do null texts. See :func:`remove_repeats`.
    """
    rows = keyed(docs)
    known = verdicts(rows).select(F.col("doc_id").alias(KEY), F.col("blocks").alias("repeat_blocks")).hint("shuffle_hash")
    columns = docs.columns
    at, chars = columns.index("text"), columns.index("n_chars") if "n_chars" in columns else None
    both = rows.join(known, KEY, "left").select(*columns, "repeat_blocks")

    def kernel(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            texts = []
            for text, blocks in zip(batch.column(at).to_pylist(), batch.column(len(columns)).to_pylist(), strict=True):
                if text is not None and blocks:
                    raw = text.encode()
                    text = without(raw, whole_characters(raw, removed_spans(blocks, len(raw)))).decode()
                texts.append(text)
            arrays = list(batch.columns[:-1])
            arrays[at] = pa.array(texts, arrays[at].type)
            if chars is not None:
                arrays[chars] = pa.array([None if t is None else len(t) for t in texts], arrays[chars].type)
            yield pa.RecordBatch.from_arrays(arrays, columns)

    return both.mapInArrow(kernel, docs.schema)
