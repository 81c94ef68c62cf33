"""Byte-level BPE encoding and decoding with the tokenizers library, over Arrow batches.

A byte-level tokenizer spells every byte as one printable character. Encoding
maps text to those characters, splits it by the pattern and merges by rank;
decoding reverses the byte table, and characters whose bytes are split between
tokens come back whole because bytes are joined before they are read as UTF-8.
"""

from __future__ import annotations

import base64
import codecs
import hashlib
import json
import os
import struct
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import steps, texts_of

#: What a worker remembers of pieces it has met: pieces, and characters in all.
CACHE_PIECES, CACHE_CHARS = 1 << 18, 1 << 22


def byte_chars() -> list[str]:
    """The character that stands for each byte: itself where it is printable, else the next free one from U+0100 on."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = iter(range(256, 512))
    return [chr(b) if b in set(shown) else chr(next(hidden)) for b in range(256)]


def char_bytes() -> dict[str, int]:
    return {c: b for b, c in enumerate(byte_chars())}


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def tokenizer_json(ranks: dict[bytes, int]) -> str:
    """A byte-level BPE of the tokenizers library that merges as the ranks say.

    A rank file only orders tokens; any two neighbours whose bytes together are a token may
    merge. So every split of a token into two tokens becomes a merge, in order of the token's rank.
    """
    table = byte_chars()
    name = {t: "".join(map(table.__getitem__, t)) for t in ranks}
    merges = [[name[t[:k]], name[t[k:]]] for t in sorted(ranks, key=ranks.__getitem__) for k in range(1, len(t)) if t[:k] in ranks and t[k:] in ranks]
    model = {"type": "BPE", "dropout": None, "unk_token": None, "continuing_subword_prefix": None, "end_of_word_suffix": None, "fuse_unk": False, "byte_fallback": False, "ignore_merges": True, "vocab": {name[t]: r for t, r in ranks.items()}, "merges": merges}
    level = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": False, "use_regex": False}
    return json.dumps({"version": "1.0", "truncation": None, "padding": None, "added_tokens": [], "normalizer": None, "pre_tokenizer": level, "post_processor": None, "decoder": level, "model": model})


class PieceEncoder:
    """Encodes pieces of text one by one, and remembers those that come again.

    What is remembered is bounded: when full it stays as it is, until so many pieces of a block are new
    that the text must have changed; then it starts anew.
    """

    limit = CACHE_PIECES, CACHE_CHARS

    def __init__(self, tokenizer, split) -> None:
        self.tokenizer, self.split, self.seen, self.chars = tokenizer, split, {}, 0

    def learn(self, pieces: list[str]) -> dict[str, bytes]:
        """Ids of pieces not met before."""
        got = self.tokenizer.encode_batch_fast(pieces, add_special_tokens=False)
        return {p: struct.pack(f"<{len(g.ids)}I", *g.ids) for p, g in zip(pieces, got, strict=True)}

    def keep(self, new: dict[str, bytes], gaps: int, pieces: int) -> None:
        """Remember what was learnt while there is room; start anew when a fifth of what comes is new."""
        if len(self.seen) < self.limit[0] and self.chars < self.limit[1]:
            self.seen |= new
            self.chars += sum(map(len, new))
        elif 5 * gaps > pieces:
            self.seen, self.chars = {}, 0

    def encode_pieces(self, texts: list[list[str]]) -> list[bytes]:
        """Ids of split texts. What the texts of a block have new is learnt together."""
        known, found, gaps = self.seen.get, [], []
        for pieces in texts:
            ids = list(map(known, pieces))
            k = -1
            try:
                while True:
                    k = ids.index(None, k + 1)
                    gaps.append((ids, k, pieces[k]))
            except ValueError:
                found.append(ids)
        if gaps:
            new = self.learn(list({g[2] for g in gaps}))
            for ids, k, piece in gaps:
                ids[k] = new[piece]
            self.keep(new, len(gaps), sum(map(len, texts)))
        return list(map(b"".join, found))

    def encode_texts(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers."""
        return self.encode_pieces(list(map(self.split, texts)))


@lru_cache(maxsize=2)
def encoder(spec: str, pattern: str) -> PieceEncoder:
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    return PieceEncoder(Tokenizer.from_str(spec), regex.compile(pattern).findall)


@lru_cache(maxsize=2)
def id_bytes(spec: str) -> tuple[bytes, ...]:
    """The bytes of each id, read back through the byte table."""
    back, vocab = char_bytes(), json.loads(spec)["model"]["vocab"]
    out = [b""] * (max(vocab.values()) + 1)
    for token, i in vocab.items():
        out[i] = bytes(map(back.__getitem__, token))
    return tuple(out)


def decode_bytes(spec: str, ids: bytes) -> bytes:
    return b"".join(map(id_bytes(spec).__getitem__, np.frombuffer(ids, "<u4").tolist()))


def decode_pieces(spec: str, parts: Iterable[Iterable[int]]) -> Iterator[str]:
    """Text of successive runs of ids; a character whose bytes are split over runs comes with the run that ends it."""
    table, reader = id_bytes(spec), codecs.getincrementaldecoder("utf-8")("replace")
    for ids in parts:
        yield reader.decode(b"".join(table[i] for i in ids))
    if rest := reader.decode(b"", final=True):
        yield rest


def encode_documents(docs: DataFrame, spec: str, pattern: str) -> DataFrame:
    """doc_id, ids array<int>, starts array<int>, ends array<int>: each token with the characters of the text it covers.

    A character whose bytes fall into several tokens is covered by each of them. Null text counts as empty and has no tokens.
    """

    def kernel(batches):
        enc = encoder(spec, pattern)
        for batch in steps(batches):
            ids, starts, ends = [], [], []
            for text in batch.column(1).to_pylist():
                at, spans, found = 0, [], []
                pieces = enc.split(text)
                for piece, got in zip(pieces, enc.tokenizer.encode_batch(pieces, add_special_tokens=False), strict=True):
                    found += got.ids
                    spans += [(at + a, at + b) for a, b in got.offsets]
                    at += len(piece)
                ids.append(found)
                starts.append([a for a, _ in spans])
                ends.append([b for _, b in spans])
            ints = pa.list_(pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, ints), pa.array(starts, ints), pa.array(ends, ints)], ["doc_id", "ids", "starts", "ends"])

    return texts_of(docs).mapInArrow(kernel, "doc_id bigint, ids array<int>, starts array<int>, ends array<int>")


def decode_documents(encoded: DataFrame, spec: str) -> DataFrame:
    """doc_id, text of a table with doc_id and ids; null ids give the empty text, bytes that are no UTF-8 the replacement character."""

    def kernel(batches):
        for batch in batches:
            texts = ["".join(decode_pieces(spec, [ids or []])) for ids in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(kernel, "doc_id bigint, text string")


def round_trip(docs: DataFrame, spec: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: digests of the ids, and of the bytes they decode to. Null text counts as empty."""

    def kernel(batches):
        enc = encoder(spec, pattern)
        for batch in steps(batches):
            ids = enc.encode_texts(batch.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in ids]), pa.array([hashlib.sha256(decode_bytes(spec, x)).hexdigest() for x in ids])],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    return texts_of(docs).mapInArrow(kernel, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
