"""TIFF columns: walk the image directories of stored files and emit one row per page.

Reads classic TIFF of either byte order (no BigTIFF, no other depths): strips and tiles, chunky and planar
samples of 8, 16 or 32 bits, raw, PackBits, LZW or deflate, with horizontal or
floating-point predictors. The writer makes the same kinds of files.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import STEP_BYTES, steps, texts_of

# Fixed values of the TIFF format: tags, field types, compressions, predictors.
WIDTH, LENGTH, BITS, COMPRESSION, PHOTOMETRIC, STRIP_OFFSETS, SAMPLES, STRIP_ROWS, STRIP_BYTES = 256, 257, 258, 259, 262, 273, 277, 278, 279
PLANAR, PREDICTOR, TILE_WIDTH, TILE_LENGTH, TILE_OFFSETS, TILE_BYTES, SAMPLE_FORMAT = 284, 317, 322, 323, 324, 325, 339
FIELD = {1: "B", 2: "B", 3: "H", 4: "I", 6: "b", 8: "h", 9: "i", 16: "Q"}
RAW, LZW, DEFLATE, OLD_DEFLATE, PACKBITS = 1, 5, 8, 32946, 32773
NO_PREDICTOR, HORIZONTAL, FLOATING = 1, 2, 3

#: The payload of a text is padded with byte 255 up to a multiple of this many bytes, which is the width of its pages.
PAYLOAD_UNIT = 576
PAGE_ROWS = 512


#: How many bytes a byte of stored data can stand for at most, by compression: more than that is not allocated for a page.
EXPANSION = {RAW: 1, PACKBITS: 64, LZW: 2560, DEFLATE: 1032, OLD_DEFLATE: 1032}
#: What a broken file can raise, whatever its headers say.
BROKEN = (ValueError, LookupError, ArithmeticError, MemoryError, TypeError, struct.error, zlib.error)


class BadTiff(ValueError):
    pass


def unpack_bits(data: bytes, size: int = 1 << 62) -> bytes:
    out, i, n = [], 0, len(data)
    while i < n:
        head = data[i]
        if head < 128:
            out.append(data[i + 1 : i + 2 + head])
            i += 2 + head
        elif head > 128:
            out.append(data[i + 1 : i + 2] * (257 - head))
            i += 2
        else:
            i += 1
    return b"".join(out)


def pack_bits(data: bytes) -> bytes:
    a = np.frombuffer(data, np.uint8)
    if not len(a):
        return b""
    cuts = np.flatnonzero(np.append(True, a[1:] != a[:-1]))
    lengths = np.diff(np.append(cuts, len(a)))
    out, at = [], 0

    def literal(start: int, end: int) -> None:
        for k in range(start, end, 128):
            part = data[k : min(k + 128, end)]
            out.append(bytes([len(part) - 1]) + part)

    for k in np.flatnonzero(lengths >= 3).tolist():
        start, left = int(cuts[k]), int(lengths[k])
        literal(at, start)
        at, value = start + left, data[start : start + 1]
        while left > 1:
            run = min(left, 128)
            out.append(bytes([257 - run]) + value)
            left -= run
        if left:
            out.append(b"\0" + value)
    literal(at, len(data))
    return b"".join(out)


LZW_CLEAR, LZW_END, LZW_TOP = 256, 257, 4094
_BYTES = [bytes([k]) for k in range(256)]


def lzw_encode(data: bytes) -> bytes:
    """Most significant bit first; the code width grows one code early, as TIFF has it."""
    acc, bits, width = LZW_CLEAR, 9, 9
    out, table, free, prefix = bytearray(), {}, 258, -1
    for byte in data:
        if prefix < 0:
            prefix = byte
            continue
        key = prefix << 8 | byte
        code = table.get(key)
        if code is not None:
            prefix = code
            continue
        acc, bits = acc << width | prefix, bits + width
        table[key] = free
        free += 1
        prefix = byte
        if free > LZW_TOP:
            acc, bits = acc << 12 | LZW_CLEAR, bits + 12
            table, free, width = {}, 258, 9
        elif free + 1 > 1 << width:
            width += 1
        if bits >= 512:
            spare = bits & 7
            out += (acc >> spare).to_bytes(bits >> 3, "big")
            acc, bits = acc & (1 << spare) - 1, spare
    if prefix >= 0:
        acc, bits = acc << width | prefix, bits + width
        free += 1
        if free <= LZW_TOP and free + 1 > 1 << width:
            width += 1
        elif free > LZW_TOP:
            width = 12
    acc, bits = acc << width | LZW_END, bits + width
    pad = -bits % 8
    return bytes(out) + (acc << pad).to_bytes((bits + pad) >> 3, "big")


def lzw_decode(data: bytes, size: int = 1 << 62) -> bytes:
    """The first ``size`` bytes at least, or all there are."""
    out, table = [], [*_BYTES, b"", b""]
    acc = bits = at = 0
    width, last, n = 9, b"", len(data)
    while True:
        if bits < width:
            part = data[at : at + 32]
            if not part:
                break
            acc, bits, at = (acc & (1 << bits) - 1) << 8 * len(part) | int.from_bytes(part, "big"), bits + 8 * len(part), at + len(part)
            if bits < width:
                break
        bits -= width
        code = acc >> bits & (1 << width) - 1
        if code < 256 or code > 257:
            if not last:
                entry = table[code]
            else:
                if code < len(table):
                    entry = table[code]
                elif code == len(table):
                    entry = last + last[:1]
                else:
                    raise BadTiff("LZW code beyond its table")
                table.append(last + entry[:1])
                if len(table) + 1 >= 1 << width and width < 12:
                    width += 1
            out.append(entry)
            last = entry
            size -= len(entry)
            if size <= 0:
                break
        elif code == LZW_CLEAR:
            table, width, last = [*_BYTES, b"", b""], 9, b""
        else:
            break
    return b"".join(out)


ENCODERS = {RAW: bytes, PACKBITS: pack_bits, LZW: lzw_encode, DEFLATE: lambda b: zlib.compress(b, 1)}
def inflate(data: bytes, size: int) -> bytes:
    return zlib.decompressobj().decompress(data, max(1, size))


DECODERS = {RAW: lambda data, size: data, PACKBITS: unpack_bits, LZW: lzw_decode, DEFLATE: inflate, OLD_DEFLATE: inflate}


def predict(rows: np.ndarray, predictor: int) -> np.ndarray:
    """Rows x columns x samples to what is stored."""
    if predictor == HORIZONTAL:
        out = rows.copy()
        out[:, 1:] -= rows[:, :-1]
        return out
    if predictor == FLOATING:
        h, w, s = rows.shape
        planes = rows.astype(">f4").view(np.uint8).reshape(h, w * s, 4).transpose(0, 2, 1).reshape(h, -1)
        out = planes.copy()
        out[:, s:] -= planes[:, :-s]
        return out
    return rows


def restore(data: bytes, shape: tuple[int, int, int], dtype: np.dtype, predictor: int) -> np.ndarray:
    """Undo a predictor: decoded bytes to rows x columns x samples."""
    h, w, s = shape
    size = h * w * s * dtype.itemsize
    if len(data) < size:
        raise BadTiff(f"a strip or tile has {len(data)} bytes of {size}")
    if predictor == FLOATING:
        planes = np.frombuffer(data[:size], np.uint8).reshape(h, -1, s)
        planes = np.cumsum(planes, axis=1, dtype=np.uint8).reshape(h, 4, w * s)
        return np.ascontiguousarray(planes.transpose(0, 2, 1)).view(">f4").reshape(shape).astype(np.float32)
    rows = np.frombuffer(data[:size], dtype).reshape(shape)
    if predictor == HORIZONTAL:
        return np.cumsum(rows, axis=1, dtype=dtype.newbyteorder("="))
    return rows


@dataclass
class Page:
    """One image directory, decoded."""

    index: int
    width: int
    height: int
    samples: int
    bits: int
    compression: int
    predictor: int
    tiled: bool
    pixels: np.ndarray


def directories(data: bytes) -> Iterator[tuple[str, dict[int, tuple[int, ...]]]]:
    """The image directories of a file in their order; a chain that turns back on itself is an error."""
    order = {b"II": "<", b"MM": ">"}.get(data[:2])
    if order is None or len(data) < 8 or struct.unpack(order + "H", data[2:4]) != (42,):
        raise BadTiff("no TIFF header")
    (at,), seen = struct.unpack(order + "I", data[4:8]), set()
    while at:
        if at in seen or at + 2 > len(data):
            raise BadTiff("a directory offset leads nowhere new")
        seen.add(at)
        (n,), tags = struct.unpack_from(order + "H", data, at), {}
        for k in range(n):
            tag, kind, count = struct.unpack_from(order + "HHI", data, at + 2 + 12 * k)
            if kind not in FIELD:
                continue
            form = f"{order}{count}{FIELD[kind]}"
            place = at + 10 + 12 * k
            if struct.calcsize(form) > 4:
                (place,) = struct.unpack_from(order + "I", data, place)
            if place + struct.calcsize(form) > len(data):
                raise BadTiff(f"tag {tag} points beyond the file")
            tags[tag] = struct.unpack_from(form, data, place)
        yield order, tags
        (at,) = struct.unpack_from(order + "I", data, at + 2 + 12 * n)


def read_pages(data: bytes) -> Iterator[Page]:
    for index, (order, tags) in enumerate(directories(data)):
        one = lambda tag, default, tags=tags: tags.get(tag, (default,))[0]
        width, height, samples, bits = one(WIDTH, 0), one(LENGTH, 0), one(SAMPLES, 1), one(BITS, 8)
        compression, predictor, planar = one(COMPRESSION, RAW), one(PREDICTOR, NO_PREDICTOR), one(PLANAR, 1) == 2
        if compression not in DECODERS or bits not in (8, 16, 32) or predictor not in (1, 2, 3):
            raise BadTiff(f"page {index}: compression {compression}, {bits} bits, predictor {predictor}")
        floats = one(SAMPLE_FORMAT, 1) == 3
        if floats and bits != 32 or predictor == FLOATING and not floats:
            raise BadTiff(f"page {index}: floating-point samples of {bits} bits, predictor {predictor}")
        dtype = np.dtype(order + ("f4" if floats else f"u{bits // 8}"))
        tiled = TILE_OFFSETS in tags
        if tiled:
            w, h = one(TILE_WIDTH, 0), one(TILE_LENGTH, 0)
            offsets, counts = tags[TILE_OFFSETS], tags[TILE_BYTES]
        else:
            w, h = width, min(height, one(STRIP_ROWS, height))
            offsets, counts = tags[STRIP_OFFSETS], tags[STRIP_BYTES]
        if min(width, height, samples, w, h) <= 0:
            raise BadTiff(f"page {index}: {width} x {height} pixels of {samples} samples in parts of {w} x {h}")
        depth = 1 if planar else samples
        across, down = -(-width // w), -(-height // h)
        if not len(offsets) == len(counts) == across * down * (samples if planar else 1):
            raise BadTiff(f"page {index}: {len(offsets)} parts with {len(counts)} lengths, not {across} x {down}")
        if any(start + count > len(data) for start, count in zip(offsets, counts, strict=True)):
            raise BadTiff(f"page {index}: a strip or tile lies beyond the file")
        if height * width * samples * dtype.itemsize > sum(counts) * EXPANSION[compression]:
            raise BadTiff(f"page {index}: {width} x {height} pixels are more than its data can hold")
        pixels = np.zeros((height, width, samples), dtype.newbyteorder("="))
        for k, (start, count) in enumerate(zip(offsets, counts, strict=True)):
            plane, cell = divmod(k, across * down)
            y, x = divmod(cell, across)
            rows = h if tiled else min(h, height - y * h)
            part = restore(DECODERS[compression](data[start : start + count], rows * w * depth * dtype.itemsize), (rows, w, depth), dtype, predictor)
            into = pixels[y * h : y * h + rows, x * w : x * w + w, plane : plane + 1] if planar else pixels[y * h : y * h + rows, x * w : x * w + w]
            into[...] = part[: into.shape[0], : into.shape[1]]
        yield Page(index, width, height, samples, bits, compression, predictor, tiled, pixels)


def write_tiff(pages: list[np.ndarray], compression: int = DEFLATE, predictor: int = NO_PREDICTOR, tile: tuple[int, int] | None = None, strip_rows: int = 64, order: str = "<", planar: bool = False) -> bytes:
    """A TIFF file of pages, each rows x columns x samples; ``tile`` is (rows, columns), multiples of 16."""
    out = bytearray((b"II" if order == "<" else b"MM") + struct.pack(order + "HI", 42, 0))
    link = 4
    for pixels in pages:
        height, width, samples = pixels.shape
        stored = pixels.dtype.newbyteorder(order)
        offsets, counts = [], []
        for plane in [pixels[:, :, k : k + 1] for k in range(samples)] if planar else [pixels]:
            h, w = tile or (strip_rows, width)
            for y in range(0, height, h):
                for x in range(0, width, w):
                    part = plane[y : y + h, x : x + w]
                    if tile:
                        full = np.zeros((h, w, plane.shape[2]), pixels.dtype)
                        full[: part.shape[0], : part.shape[1]] = part
                        part = full
                    part = predict(part, predictor)
                    data = ENCODERS[compression]((part if predictor == FLOATING else part.astype(stored)).tobytes())
                    offsets.append(len(out))
                    counts.append(len(data))
                    out += data
        fields = {WIDTH: [width], LENGTH: [height], BITS: [pixels.dtype.itemsize * 8] * samples, COMPRESSION: [compression], PHOTOMETRIC: [1], SAMPLES: [samples], PLANAR: [2 if planar else 1], PREDICTOR: [predictor], SAMPLE_FORMAT: [3 if pixels.dtype.kind == "f" else 1] * samples}
        fields |= {TILE_WIDTH: [tile[1]], TILE_LENGTH: [tile[0]], TILE_OFFSETS: offsets, TILE_BYTES: counts} if tile else {STRIP_OFFSETS: offsets, STRIP_ROWS: [strip_rows], STRIP_BYTES: counts}
        entries, wide = [], {STRIP_OFFSETS, STRIP_BYTES, TILE_OFFSETS, TILE_BYTES, WIDTH, LENGTH, STRIP_ROWS}
        for tag, values in sorted(fields.items()):
            kind = 4 if tag in wide else 3
            data = struct.pack(f"{order}{len(values)}{FIELD[kind]}", *values)
            if len(data) > 4:
                out += b"\0" * (len(out) & 1)
                place = struct.pack(order + "I", len(out))
                out += data
            else:
                place = data.ljust(4, b"\0")
            entries.append(struct.pack(order + "HHI", tag, kind, len(values)) + place)
        out += b"\0" * (len(out) & 1)
        struct.pack_into(order + "I", out, link, len(out))
        out += struct.pack(order + "H", len(entries)) + b"".join(entries)
        link = len(out)
        out += struct.pack(order + "I", 0)
    return bytes(out)


def tiff_pages(files: DataFrame, id_col: str = "doc_id", data_col: str = "media") -> DataFrame:
    """One row per page of each stored file, with its decoded samples and their shape.

    A null or empty file has no pages. A broken file gives one row that says so in ``error``, with page -1, after the
    pages that could be read: a page's geometry is held against the file's size before anything is allocated or decoded.
    Other columns are ignored.
    """
    from pyspark.sql import functions as F

    names = ["doc_id", "page", "width", "height", "samples", "bits", "compression", "predictor", "tiled", "pixels", "error"]
    types = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.bool_(), pa.binary(), pa.string()]

    def kernel(batches):
        for batch in steps(batches, "media"):
            rows, held = [], 0
            for key, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                try:
                    for p in read_pages(data) if data else ():
                        rows.append((key, p.index, p.width, p.height, p.samples, p.bits, p.compression, p.predictor, p.tiled, p.pixels.tobytes(), None))
                        held += p.pixels.nbytes
                        if held > 8 * STEP_BYTES:
                            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names)
                            rows, held = [], 0
                except BROKEN as e:
                    rows.append((key, -1, None, None, None, None, None, None, None, None, str(e)))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names)

    schema = "doc_id bigint, page int, width int, height int, samples int, bits int, compression int, predictor int, tiled boolean, pixels binary, error string"
    return files.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(data_col), F.lit(b"")).alias("media")).mapInArrow(kernel, schema)


def text_payload(text: bytes) -> bytes:
    return text + b"\xff" * (-len(text) % PAYLOAD_UNIT or PAYLOAD_UNIT * (not text))


def payload_tiff(payload: bytes) -> bytes:
    """A payload as pages of 8-bit samples. Its checksum picks the kind of file, so that all kinds are in use."""
    pixels = np.frombuffer(payload, np.uint8).reshape(-1, PAYLOAD_UNIT, 1)
    pages = [pixels[k : k + PAGE_ROWS] for k in range(0, len(pixels), PAGE_ROWS)]
    kind = zlib.crc32(payload) % 3
    if kind == 0:
        return write_tiff(pages, DEFLATE, HORIZONTAL)
    if kind == 1:
        return write_tiff(pages, PACKBITS, tile=(64, 192), order=">")
    return write_tiff(pages, LZW)


def page_features(pages: list[Page]) -> str:
    """Integer statistics of the decoded samples: equal pages, equal features."""
    flat = np.concatenate([p.pixels.reshape(-1) for p in pages])
    counts = np.bincount(flat, minlength=256)
    total = int((counts * np.arange(256)).sum())
    squares = int((counts * np.arange(256) ** 2).sum())
    edges = sum(int(np.abs(np.diff(p.pixels[:, :, 0].astype(np.int16), axis=1)).sum(dtype=np.int64)) for p in pages)
    return f"pages={len(pages)};rows={sum(p.height for p in pages)};sum={total};squares={squares};edges={edges};levels={int((counts > 0).sum())};quarters={','.join(str(int(q.sum())) for q in np.split(counts, 4))}"


def texts_as_tiff(docs: DataFrame) -> DataFrame:
    """doc_id, media: each text as a TIFF file. Null text counts as empty and becomes one row of padding."""

    def kernel(batches):
        for batch in steps(batches):
            files = [payload_tiff(text_payload(t.encode())) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(files, pa.binary())], ["doc_id", "media"])

    return texts_of(docs).mapInArrow(kernel, "doc_id bigint, media binary")


def media_round_trip(docs: DataFrame) -> DataFrame:
    """Each text stored as a TIFF file, read back page by page, and summed up in one row, where the pages are."""

    def kernel(batches):
        for batch in steps(batches):
            rows = []
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                raw = text.encode()
                media = payload_tiff(text_payload(raw))
                pages = list(read_pages(media))
                back = b"".join(p.pixels.tobytes() for p in pages)
                rows.append((key, len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(media), hashlib.sha256(media).hexdigest(), page_features(pages)))
            columns = list(zip(*rows, strict=True))
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    return texts_of(docs).mapInArrow(kernel, "doc_id bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string")
