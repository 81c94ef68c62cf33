"""Best-fit packing of tokenized documents into sequences of fixed capacity.

All decisions are taken on the histogram of piece lengths, which has at most
``capacity`` entries whatever the corpus: large lengths are rounded up within
groups of equal cardinality, the few sizes that remain are packed by an
optimised mix of configurations, actual lengths take the places of rounded ones,
and what is left, down to the smallest, goes where it fits best. The plan says
which ranks of each length go to which range of sequences; pieces look their
places up with one small broadcast table.
"""

from __future__ import annotations

import bisect
import os
import re
import zlib
from dataclasses import dataclass, field
from functools import lru_cache
from itertools import filterfalse, pairwise

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import PieceEncoder
from .common import STEP_BYTES, steps, stored, texts_of

CAPACITY = 2048
#: Texts with any of these take the library's whole path: beyond Latin, white space and separators beyond ASCII's six, special tokens' spelling.
_UNUSUAL = re.compile("[\x1c-\x1f\x85\xa0\u0250-\U0010ffff]|<\\|")
_SEPARATORS = "\x1c\x1d\x1e\x1f"


def unusual(text: str) -> bool:
    if text.isascii():
        return "<|" in text or any(c in text for c in _SEPARATORS)
    return _UNUSUAL.search(text) is not None


#: Signs that, after a word, are a piece of their own.
_SIGNS = ".,;:!?"


class WordEncoder(PieceEncoder):
    """Ids of a lower-casing word BPE whose pieces never cross white space.

    So what stands between white space can be encoded, and remembered, by itself. A word is one piece and its last id
    says that it ends, so many new words go through the library as one text; a
    sign after a word is another piece. Texts with unusual characters are handed to the library whole.
    """

    limit = 1 << 19, 1 << 23

    def __init__(self, tokenizer, split) -> None:
        super().__init__(tokenizer, split)
        vocab = tokenizer.get_vocab()
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self.signs = {c: np.array(tokenizer.encode(c, add_special_tokens=False).ids, "<u4").tobytes() for c in _SIGNS}

    def encode_texts(self, texts: list[str]) -> list[bytes]:
        return self.encode_column(pa.array(texts, pa.string()))

    def encode_column(self, column: pa.Array) -> list[bytes]:
        """Ids of each text. Arrow splits them and tells their different pieces; only those are looked up."""
        texts = column.to_pylist()
        odd = list(map(unusual, texts))
        lists = pc.ascii_split_whitespace(pc.if_else(pa.array(odd, pa.bool_()), pa.scalar("", column.type), column))
        encoded = lists.flatten().dictionary_encode()
        joined = pa.array(self.lookup(encoded.dictionary.to_pylist(), len(encoded)), pa.binary()).take(encoded.indices)
        ends = np.frombuffer(joined.buffers()[1], np.int32, len(joined) + 1, joined.offset * 4)
        cuts = ends[np.asarray(lists.offsets) - lists.offsets[0].as_py()].tolist()
        data = joined.buffers()[2].to_pybytes() if joined.buffers()[2] is not None else b""
        out = [data[a:b] for a, b in pairwise(cuts)]
        for k in np.flatnonzero(odd).tolist():
            out[k] = np.array(self.tokenizer.encode(texts[k], add_special_tokens=False).ids, "<u4").tobytes()
        return out

    def lookup(self, pieces: list[str], times: int) -> list[bytes]:
        """Ids of different pieces, which come so many times in all."""
        ids = list(map(self.seen.get, pieces))
        gaps = [k for k, x in enumerate(ids) if x is None]
        if gaps:
            new = self.learn([pieces[k] for k in gaps])
            for k in gaps:
                ids[k] = new[pieces[k]]
            self.keep(new, len(gaps), times)
        return ids

    def learn(self, pieces: list[str]) -> dict[str, bytes]:
        seen, signs = self.seen, self.signs
        words = dict.fromkeys(filter(str.isalpha, pieces))
        others = [p for p in filterfalse(str.isalpha, pieces) if p]
        signed = [(p, p[:-1]) for p in others if p[-1] in _SIGNS and p[:-1].isalpha()]
        got = super().learn([p for p in others if not (p[-1] in _SIGNS and p[:-1].isalpha())]) if len(signed) < len(others) else {}
        words |= dict.fromkeys([w for _, w in signed if w not in seen])
        if words:
            ids = np.array(self.tokenizer.encode_batch_fast([" ".join(words)], add_special_tokens=False)[0].ids, "<u4")
            cuts = [0, *(4 * (np.flatnonzero(self.ends[ids]) + 1)).tolist()]
            block = ids.tobytes()
            got |= zip(words, [block[a:b] for a, b in pairwise(cuts)], strict=True)
        got[""] = b""  # white space at a text's ends
        for piece, word in signed:
            got[piece] = (got.get(word) or seen[word]) + signs[piece[-1]]
        return got


@lru_cache(maxsize=2)
def word_encoder(path: str) -> WordEncoder:
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.encode_special_tokens = True
    return WordEncoder(tokenizer, str.split)


def token_pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: each document's ids and the end id, cut only where longer than the capacity."""

    def kernel(batches):
        enc, end = word_encoder(tokenizer_path), np.array([end_id], "<u4").tobytes()
        for batch in steps(batches, step=4 * STEP_BYTES):
            rows = []
            for key, ids in zip(batch.column(0).to_pylist(), enc.encode_column(batch.column(1)), strict=True):
                ids += end
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    rows.append((key, k, at // 4, len(part) // 4, zlib.crc32(part)))
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return texts_of(docs).mapInArrow(kernel, "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint")


@dataclass
class Plan:
    """Where ranks of a length go: (first rank, ranks, first sequence, offset), and ranges of sequences by the room they have left."""

    capacity: int
    places: dict[int, list[tuple[int, int, int, int]]] = field(default_factory=dict)
    taken: dict[int, int] = field(default_factory=dict)
    room: dict[int, list[tuple[int, int]]] = field(default_factory=dict)
    rooms: list[int] = field(default_factory=list)
    sequences: int = 0

    def put(self, length: int, n: int, first: int, offset: int) -> None:
        rank = self.taken.get(length, 0)
        self.places.setdefault(length, []).append((rank, n, first, offset))
        self.taken[length] = rank + n

    def free(self, left: int, first: int, n: int) -> None:
        if left and n:
            if left not in self.room:
                bisect.insort(self.rooms, left)
                self.room[left] = []
            self.room[left].append((first, n))

    def open(self, n: int) -> int:
        self.sequences += n
        return self.sequences - n

    def best_fit(self, length: int, n: int) -> None:
        """Put ``n`` pieces of one length where they fit best, one after the other; new sequences when nothing has room."""
        while n:
            k = bisect.bisect_left(self.rooms, length)
            if k == len(self.rooms):
                per = self.capacity // length
                full, rest = divmod(n, per)
                for count, each in ((full, per), (1, rest)):
                    if count and each:
                        first = self.open(count)
                        for j in range(each):
                            self.put(length, count, first, j * length)
                        self.free(self.capacity - each * length, first, count)
                return
            left = self.rooms[k]
            first, count = self.room[left].pop()
            if not self.room[left]:
                del self.room[left]
                self.rooms.pop(k)
            per = left // length
            full = min(count, n // per)
            for j in range(per if full else 0):
                self.put(length, full, first, self.capacity - left + j * length)
            self.free(left - per * length, first, full)
            n -= full * per
            first, count = first + full, count - full
            if count and n:  # fewer pieces than this sequence could hold
                for j in range(n):
                    self.put(length, 1, first, self.capacity - left + j * length)
                self.free(left - n * length, first, 1)
                first, count, n = first + 1, count - 1, 0
            self.free(left, first, count)


def linear_groups(lengths: list[tuple[int, int]], groups: int) -> list[tuple[int, list[list[int]]]]:
    """(length, count), longest first, to groups of equal cardinality: (rounded length, [[length, count], ...])."""
    total = sum(n for _, n in lengths)
    size, out, held = max(1, -(-total // groups)), [], 0
    for length, n in lengths:
        while n:
            if not out or held == size:
                out.append((length, []))
                held = 0
            part = min(n, size - held)
            out[-1][1].append([length, part])
            held += part
            n -= part
    return out


def configurations(sizes: list[int], demand: list[int], capacity: int, rounds: int = 400) -> list[tuple[np.ndarray, int]]:
    """Configurations of few sizes and how often each is used, rounded down, from the linear programme of the sizes.

    Columns are generated by a knapsack over the duals; the basis starts with one size per sequence.
    """
    m = len(sizes)
    basis = np.diag([float(capacity // s) for s in sizes])
    demand_ = np.array(demand, float)
    inverse = np.linalg.inv(basis)
    for _ in range(rounds):
        duals = np.ones(m) @ inverse
        best, came = np.zeros(capacity + 1), np.full(capacity + 1, -1)
        for k in sorted(range(m), key=lambda k: -duals[k] / sizes[k]):
            if duals[k] <= 0:
                continue
            s = sizes[k]
            for _ in range(capacity // s):  # each pass allows one more piece of this size
                better = best[:-s] + duals[k] > best[s:] + 1e-12
                if not better.any():
                    break
                at = np.flatnonzero(better) + s
                new = best[at - s] + duals[k]
                best[at] = new
                came[at] = k
        if best[capacity] <= 1 + 1e-9:
            break
        column, left = np.zeros(m), capacity
        while left > 0 and came[left] >= 0 or left > 0 and best[left] > 0:
            if came[left] < 0:
                left -= 1
                continue
            column[came[left]] += 1
            left -= sizes[came[left]]
        if duals @ column <= 1 + 1e-9:
            break
        use, direction = inverse @ demand_, inverse @ column
        ratios = np.where(direction > 1e-9, use / np.where(direction > 1e-9, direction, 1), np.inf)
        leaves = int(ratios.argmin())
        if not np.isfinite(ratios[leaves]):
            break
        basis[:, leaves] = column
        inverse = np.linalg.inv(basis)
    use = np.floor(np.maximum(inverse @ demand_, 0) + 1e-9).astype(int)
    return [(basis[:, k].astype(int), int(use[k])) for k in range(m) if use[k] > 0]


def make_plan(counts: dict[int, int], capacity: int, groups: int, small: int) -> Plan:
    """One packing of the histogram, with this many groups and everything up to ``small`` left for best fit."""
    plan = Plan(capacity)
    todo = {k: n for k, n in counts.items() if n}
    if full := todo.pop(capacity, 0):
        plan.put(capacity, full, plan.open(full), 0)
    large = sorted(((k, n) for k, n in todo.items() if k > small), reverse=True)
    if large:
        grouped = linear_groups(large, groups)
        left = [g for _, g in grouped]
        for column, times in configurations([s for s, _ in grouped], [sum(n for _, n in g) for _, g in grouped], capacity):
            have = [sum(n for _, n in g) for g in left]
            times = min([times, *(have[k] // int(c) for k, c in enumerate(column) if c)])
            if not times:
                continue
            ranges = [(plan.open(times), times, 0)]
            for k in np.repeat(np.arange(len(column)), column).tolist():
                new = []
                for first, n, used in ranges:
                    while n:
                        length, there = left[k][0]
                        part = min(n, there)
                        plan.put(length, part, first, used)
                        new.append((first, part, used + length))
                        first, n = first + part, n - part
                        left[k][0][1] -= part
                        if not left[k][0][1]:
                            left[k].pop(0)
                ranges = new
            for first, n, used in ranges:
                plan.free(capacity - used, first, n)
        rest: dict[int, int] = {}
        for g in left:
            for length, n in g:
                rest[length] = rest.get(length, 0) + n
        for length in sorted(rest, reverse=True):
            plan.best_fit(length, rest[length])
    for length in sorted((k for k in todo if k <= small), reverse=True):
        plan.best_fit(length, todo[length])
    return plan


def pack_histogram(counts: dict[int, int], capacity: int = CAPACITY) -> Plan:
    """The packing with the fewest sequences among several group counts and limits of smallness."""
    bound = -(-sum(k * n for k, n in counts.items()) // capacity)
    best = None
    for groups, share in ((24, 2), (48, 2), (96, 2), (48, 3), (48, 4), (24, 8), (96, 4), (96, 8)):
        plan = make_plan(counts, capacity, groups, capacity // share)
        if best is None or plan.sequences < best.sequences:
            best = plan
        if best.sequences == bound:
            break
    return best


def best_fit_packing(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, rows_per_cell: int = 50_000, max_cells: int = 512) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null text counts as empty: such a document is its end id alone. Repeated rows are packed as often as they come;
    an empty table gives an empty result. Other columns are ignored.
    """
    spark = docs.sparkSession
    pieces = stored(token_pieces(docs, tokenizer_path, capacity), "pieces")
    total = pieces.count()
    cells = max(1, min(max_cells, -(-total // rows_per_cell)))
    pieces = pieces.withColumn("cell", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(cells)).cast("int"))
    # Ranks within a length without gathering a length in one task: counts by (length, cell), at most capacity x cells of them.
    counted = pieces.groupBy("length", "cell").agg(F.count(F.lit(1)).alias("n")).toArrow().sort_by([("length", "ascending"), ("cell", "ascending")])
    lengths, n = (counted.column(c).to_numpy() for c in ("length", "n"))
    starts = np.flatnonzero(np.append(True, lengths[1:] != lengths[:-1])) if len(lengths) else np.zeros(0, np.int64)
    running = np.cumsum(n) - n
    before = running - np.repeat(running[starts], np.diff(np.append(starts, len(n))))
    histogram = {int(k): int(x) for k, x in zip(lengths[starts], np.add.reduceat(n, starts), strict=True)} if len(n) else {}
    plan = pack_histogram(histogram, capacity)
    rows = [(length, [p[0] for p in ps], [p[2] for p in ps], [p[3] for p in ps]) for length, ps in plan.places.items()]
    first = spark.createDataFrame(pa.table({"length": counted.column("length"), "cell": counted.column("cell"), "first": pa.array(before)}))
    places = spark.createDataFrame(rows, "length bigint, ranks array<bigint>, firsts array<bigint>, offsets array<bigint>")
    rank = F.row_number().over(Window.partitionBy("length", "cell").orderBy("doc_id", "piece")) - 1
    ranked = pieces.join(F.broadcast(first), ["length", "cell"]).withColumn("rank", F.col("first") + rank).join(F.broadcast(places), "length")
    found = ranked.withColumn("k", F.size(F.filter("ranks", lambda r: r <= F.col("rank"))))
    pick = lambda c: F.element_at(c, F.col("k"))
    return found.select("doc_id", "piece", "start", "length", "ids_crc32", (pick("firsts") + F.col("rank") - pick("ranks")).alias("sequence_id"), pick("offsets").alias("offset"))
