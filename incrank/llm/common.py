"""Helpers that the document operators share."""

from __future__ import annotations

import ctypes
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import drop_path, scratch, shared_dir, ship, stored  # noqa: F401


#: Text bytes that one step of a Python kernel works on; bounds a worker's memory whatever the Arrow batch holds.
STEP_BYTES = 1 << 20


def texts_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the identifier (as long) and the text, where null counts as empty; other columns never get in."""
    ship(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))


def partitions_for(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


#: A key with more rows than this, and than the share 1 / MOST_HOT of all rows, is hot: so at most MOST_HOT keys are.
HOT_ROWS, MOST_HOT = 256, 10_000


def join_per_key(rows: DataFrame, per_key: DataFrame, keys: list[str], size: str, total: int) -> DataFrame:
    """``rows`` joined with a table of one row per key, whose column ``size`` says how many of the ``total`` rows have the key.

    Rows of hot keys stay where they are and get their keys' rows sent, of which there are ``MOST_HOT`` at most; all others are joined by key.
    """
    limit = max(HOT_ROWS, total // MOST_HOT)
    hot = F.broadcast(per_key.where(F.col(size) > limit))
    cold = rows.join(hot.select(*keys), keys, "left_anti").join(per_key.where(F.col(size) <= limit), keys)
    return rows.join(hot, keys).unionByName(cold)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def column_bytes(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets and bytes of a string or binary Arrow array without nulls, as numpy views."""
    wide = pa.types.is_large_string(array.type) or pa.types.is_large_binary(array.type)
    kind, width = (np.int64, 8) if wide else (np.int32, 4)
    if len(array) == 0:
        return np.zeros(1, np.int64), np.zeros(0, np.uint8)
    offsets = np.frombuffer(array.buffers()[1], kind, len(array) + 1, array.offset * width).astype(np.int64)
    data = np.frombuffer(array.buffers()[2], np.uint8) if array.buffers()[2] is not None and array.buffers()[2].size else np.zeros(0, np.uint8)
    return offsets - offsets[0], data[offsets[0] : offsets[-1]]


def steps(batches: Iterator[pa.RecordBatch], column: str = "text", step: int = STEP_BYTES) -> Iterator[pa.RecordBatch]:
    """Slice Arrow batches so that each slice holds about ``step`` bytes of ``column``, or one longer row."""
    for batch in batches:
        if batch.num_rows == 0:
            continue
        offsets, _ = column_bytes(batch.column(batch.schema.get_field_index(column)))
        start = 0
        while start < batch.num_rows:
            end = max(start + 1, int(np.searchsorted(offsets, offsets[start] + step, side="right")) - 1)
            yield batch.slice(start, min(end, batch.num_rows) - start)
            start = end
    give_back()


def give_back() -> None:
    """Return freed memory to the system: idle workers of earlier stages stay, and an executor's memory is one pool."""
    pa.default_memory_pool().release_unused()
    if (trim := getattr(ctypes.CDLL(None), "malloc_trim", None)) is not None:
        trim(0)


def mix64(x: np.ndarray) -> np.ndarray:
    """A fixed bijective scrambling of 64-bit integers (the finaliser of the public splitmix64 generator)."""
    x = x.astype(np.uint64, copy=True)
    with np.errstate(over="ignore"):
        x ^= x >> np.uint64(30)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(31)
    return x


def unit_floats(x: np.ndarray) -> np.ndarray:
    """Hashes as uniform numbers strictly inside (0, 1)."""
    return ((x >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)


#: Class of each byte: 0 separates words, 1 belongs to a word (letters, digits, apostrophes and all of UTF-8 beyond ASCII), 2 is a sign.
WORD_CLASS = np.full(256, 2, np.uint8)
WORD_CLASS[[9, 10, 11, 12, 13, 32]] = 0
WORD_CLASS[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = 1
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def _powers(n: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return np.multiply.accumulate(np.full(n, 0x9E3779B97F4A7C15, np.uint64))


_POWERS = _powers(256)


def word_hashes(offsets: np.ndarray, data: np.ndarray, signs: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash every word of every text of a batch, ASCII letters lower-cased, with no Python loop.

    Words are maximal runs of word bytes; with ``signs``, runs of other printable
    bytes count as words too. Returns the hashes, each word's text (an index
    into the batch) and its first byte.
    """
    if len(data) == 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    kind = WORD_CLASS[data]
    first = np.empty(len(data), bool)
    first[0] = True
    np.not_equal(kind[1:], kind[:-1], out=first[1:])
    first[offsets[:-1][offsets[:-1] < len(data)]] = True
    starts = np.flatnonzero(first)
    keep = kind[starts] > 0 if signs else kind[starts] == 1
    ends = np.append(starts[1:], len(data))
    with np.errstate(over="ignore"):
        place = np.arange(len(data), dtype=np.int64) - np.repeat(starts, ends - starts)
        terms = (LOWER[data].astype(np.uint64) + np.uint64(1)) * _POWERS[place & 255]
        long = place > 255
        if long.any():
            terms[long] = mix64(terms[long] + place[long].astype(np.uint64))
        sums = np.add.reduceat(terms, starts)
        hashes = mix64(sums + (ends - starts).astype(np.uint64))
    starts, hashes = starts[keep], hashes[keep]
    return hashes, np.searchsorted(offsets, starts, side="right") - 1, starts


def ceil_div(a: int, b: int) -> int:
    return math.ceil(a / b) if b else 0
