"""TIFF media columns: walk the image directories, decode strips or tiles, undo predictors, one row per page.

Reads classic and big TIFF of either byte order, chunky or planar, with 8, 16, 32 or 64 bits a
sample, uncompressed or with PackBits, LZW or deflate, and the horizontal and floating-point
predictors. The writer makes what the reader reads, so that texts can be kept as images.

Cases: a null or empty file gives one row with page -1 and the error ``empty``; a file that is
no TIFF, or a page that cannot be decoded, gives a row with its error and null samples; a chain
of directories that returns to itself ends there. Equal files give equal rows. An empty table
gives an empty table.
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
from pyspark.sql import functions as F

from .common import arrow_map, rows_out

#: Tags, compression schemes and field types of the format.
WIDTH, LENGTH, BITS, COMPRESSION, PHOTOMETRIC, STRIP_OFFSETS, SAMPLES, ROWS, STRIP_BYTES = 256, 257, 258, 259, 262, 273, 277, 278, 279
PLANAR, PREDICTOR, TILE_WIDTH, TILE_LENGTH, TILE_OFFSETS, TILE_BYTES, SAMPLE_FORMAT = 284, 317, 322, 323, 324, 325, 339
NONE, LZW, DEFLATE, OLD_DEFLATE, PACKBITS = 1, 5, 8, 32946, 32773
FIELD = {1: "B", 2: "c", 3: "H", 4: "I", 5: "II", 6: "b", 7: "B", 8: "h", 9: "i", 10: "ii", 11: "f", 12: "d", 13: "I", 16: "Q", 17: "q", 18: "Q"}
CLEAR, STOP = 256, 257

#: Of texts kept as images: payload bytes a row, rows a strip and rows a page.
TEXT_WIDTH, TEXT_STRIP, TEXT_PAGE = 576, 64, 4096


@dataclass
class Page:
    number: int
    width: int
    height: int
    samples: int
    bits: int
    compression: int
    predictor: int
    data: bytes | None
    error: str | None = None


def unpack_bits(data: bytes) -> bytes:
    out, at = bytearray(), 0
    while at < len(data):
        head = data[at]
        at += 1
        if head < 128:
            out += data[at : at + head + 1]
            at += head + 1
        elif head > 128:
            out += data[at : at + 1] * (257 - head)
            at += 1
    return bytes(out)


def pack_bits(data: bytes) -> bytes:
    out, at, n = bytearray(), 0, len(data)
    while at < n:
        run = 1
        while run < 128 and at + run < n and data[at + run] == data[at]:
            run += 1
        if run > 2:
            out += bytes([257 - run, data[at]])
            at += run
            continue
        end = at + 1
        while end < n and end - at < 128 and not (end + 2 < n and data[end] == data[end + 1] == data[end + 2]):
            end += 1
        out += bytes([end - at - 1]) + data[at:end]
        at = end
    return bytes(out)


def lzw_decode(data: bytes) -> bytes:
    """Codes of 9 to 12 bits, most significant bit first, widened one entry early."""
    start = [bytes([i]) for i in range(256)] + [b"", b""]
    table, out = list(start), bytearray()
    width, held, bits, before = 9, 0, 0, b""
    for byte in data:
        held, bits = (held << 8 | byte) & 0xFFFFFF, bits + 8
        if bits < width:
            continue
        bits -= width
        code = held >> bits & ((1 << width) - 1)
        if code == STOP:
            break
        if code == CLEAR:
            table, width, before = list(start), 9, b""
            continue
        if code < len(table):
            entry = table[code]
        elif before and code == len(table):
            entry = before + before[:1]
        else:
            raise ValueError("an LZW code beyond its table")
        out += entry
        if before:
            table.append(before + entry[:1])
        before = entry
        width = min(12, max(9, (len(table) + 1).bit_length()))
    return bytes(out)


def lzw_encode(data: bytes) -> bytes:
    table = {bytes([i]): i for i in range(256)}
    count, width, held, bits, out = 258, 9, 0, 0, bytearray()

    def put(code: int) -> None:
        nonlocal held, bits
        held, bits = held << width | code, bits + width
        while bits >= 8:
            bits -= 8
            out.append(held >> bits & 255)
        held &= (1 << bits) - 1

    put(CLEAR)
    word = b""
    for i in range(len(data)):
        longer = word + data[i : i + 1]
        if longer in table:
            word = longer
            continue
        put(table[word])
        table[longer] = count
        count += 1
        if count == 4095:
            put(CLEAR)
            table, count, width = {bytes([i]): i for i in range(256)}, 258, 9
        else:
            width = max(9, count.bit_length())
        word = data[i : i + 1]
    if word:
        put(table[word])
        count += 1
        width = min(12, max(9, count.bit_length()))
    put(STOP)
    if bits:
        out.append(held << (8 - bits) & 255)
    return bytes(out)


def _decompress(data: bytes, scheme: int) -> bytes:
    if scheme == NONE:
        return data
    if scheme in (DEFLATE, OLD_DEFLATE):
        return zlib.decompress(data)
    if scheme == PACKBITS:
        return unpack_bits(data)
    if scheme == LZW:
        return lzw_decode(data)
    raise ValueError(f"compression {scheme} is not known")


def _compress(data: bytes, scheme: int) -> bytes:
    return {NONE: bytes, DEFLATE: lambda d: zlib.compress(d, 1), OLD_DEFLATE: lambda d: zlib.compress(d, 1), PACKBITS: pack_bits, LZW: lzw_encode}[scheme](data)


def _undo(block: np.ndarray, predictor: int, order: str) -> np.ndarray:
    """block: rows x columns x samples of unsigned integers, as stored."""
    if predictor == 1:
        return block
    if predictor == 2:
        return np.cumsum(block, axis=1, dtype=block.dtype)
    if predictor == 3:
        rows, columns, samples = block.shape
        size = block.dtype.itemsize
        planes = np.cumsum(block.reshape(rows, -1).view(np.uint8).reshape(rows, columns * size, samples), axis=1, dtype=np.uint8).reshape(rows, size, columns * samples)
        big = np.ascontiguousarray(planes.transpose(0, 2, 1)).view(f">u{size}").reshape(rows, columns, samples)
        return big.astype(f"{order}u{size}")
    raise ValueError(f"predictor {predictor} is not known")


def _directories(data: bytes) -> Iterator[tuple[str, dict[int, tuple]]]:
    order = {b"II": "<", b"MM": ">"}.get(data[:2])
    version = struct.unpack(order + "H", data[2:4])[0] if order else 0
    if version not in (42, 43):
        raise ValueError("this is no TIFF")
    big = version == 43
    at = struct.unpack_from(order + ("Q" if big else "I"), data, 8 if big else 4)[0]
    seen = set()
    count, entry, step, inline = ("Q", "HHQ", 20, 8) if big else ("H", "HHI", 12, 4)
    while at and at not in seen:
        seen.add(at)
        n = struct.unpack_from(order + count, data, at)[0]
        at += struct.calcsize(count)
        tags = {}
        for i in range(n):
            here = at + i * step
            tag, kind, values = struct.unpack_from(order + entry, data, here)
            form = FIELD.get(kind, "B")
            length = struct.calcsize("=" + form) * values
            where = here + step - inline
            if length > inline:
                where = struct.unpack_from(order + ("Q" if big else "I"), data, where)[0]
            tags[tag] = struct.unpack_from(order + form * values, data, where)
        yield order, tags
        at = struct.unpack_from(order + ("Q" if big else "I"), data, at + n * step)[0]


def _pixels(data: bytes, order: str, tags: dict[int, tuple]) -> bytes:
    width, height = tags[WIDTH][0], tags[LENGTH][0]
    samples, bits = tags.get(SAMPLES, (1,))[0], tags.get(BITS, (1,))
    if len(set(bits)) != 1 or bits[0] not in (8, 16, 32, 64):
        raise ValueError(f"{bits} bits a sample are not known")
    kind = np.dtype(f"{order}u{bits[0] // 8}")
    scheme, predictor = tags.get(COMPRESSION, (NONE,))[0], tags.get(PREDICTOR, (1,))[0]
    planes = samples if tags.get(PLANAR, (1,))[0] == 2 else 1
    inside = samples // planes
    if TILE_OFFSETS in tags:
        across, down, offsets, sizes = tags[TILE_WIDTH][0], tags[TILE_LENGTH][0], tags[TILE_OFFSETS], tags[TILE_BYTES]
    else:
        across, down, offsets, sizes = width, min(tags.get(ROWS, (height,))[0], height), tags[STRIP_OFFSETS], tags[STRIP_BYTES]
    per_row, per_column = -(-width // across), -(-height // down)
    if len(offsets) != per_row * per_column * planes:
        raise ValueError("blocks are missing")
    if min(width, height, samples) < 1 or width * height * samples * kind.itemsize > (sum(sizes) + 1) * MOST_RATIO:
        raise ValueError("the blocks cannot hold an image of this size")
    image = np.zeros((height, width, samples), kind)
    for k, (offset, size) in enumerate(zip(offsets, sizes, strict=True)):
        plane, k = divmod(k, per_row * per_column)
        top, left = k // per_row * down, k % per_row * across
        rows = down if TILE_OFFSETS in tags else min(down, height - top)
        raw = _decompress(data[offset : offset + size], scheme)
        block = np.frombuffer(raw, kind, count=rows * across * inside).reshape(rows, across, inside)
        block = _undo(block, predictor, order)[: height - top, : width - left]
        image[top : top + rows, left : left + across, plane if planes > 1 else slice(None)] = block[..., 0] if planes > 1 else block
    return image.tobytes()


#: What a malformed file may raise; the greatest ratio of any scheme, and the greatest number of a page.
MALFORMED = (ValueError, TypeError, LookupError, ArithmeticError, MemoryError, zlib.error, struct.error)
MOST_RATIO, MOST = 4096, (1 << 31) - 1


def read_pages(data: bytes | None) -> Iterator[Page]:
    if not data:
        yield Page(-1, 0, 0, 0, 0, 0, 0, None, "empty")
        return
    number = 0
    try:
        for order, tags in _directories(data):
            one = lambda tag, default, tags=tags: int(tags.get(tag, (default,))[0])
            if max(one(tag, 0) for tag in (WIDTH, LENGTH, SAMPLES, BITS, COMPRESSION, PREDICTOR)) > MOST:
                raise ValueError("a number of the directory is out of range")
            page = Page(number, one(WIDTH, 0), one(LENGTH, 0), one(SAMPLES, 1), one(BITS, 1), one(COMPRESSION, NONE), one(PREDICTOR, 1), None)
            try:
                page.data = _pixels(data, order, tags)
            except MALFORMED as wrong:
                page.error = f"{type(wrong).__name__}: {wrong}"
            yield page
            number += 1
    except MALFORMED as wrong:
        yield Page(number if number else -1, 0, 0, 0, 0, 0, 0, None, f"{type(wrong).__name__}: {wrong}")


def write_pages(images: list[np.ndarray], compression: int = DEFLATE, predictor: int = 1, rows: int = TEXT_STRIP, tile: tuple[int, int] | None = None, order: str = "<") -> bytes:
    """A classic TIFF of rows x columns x samples images of unsigned integers, in strips or tiles of (rows, columns)."""
    out = bytearray((b"II" if order == "<" else b"MM") + struct.pack(order + "HI", 42, 0))
    link = 4
    for image in images:
        height, width, samples = image.shape
        image = image.astype(image.dtype.newbyteorder(order))
        down, across = tile or (min(rows, height), width)
        offsets, sizes = [], []
        for top in range(0, height, down):
            for left in range(0, width, across):
                block = image[top : top + down, left : left + across]
                if tile:
                    block = np.pad(block, ((0, down - block.shape[0]), (0, across - block.shape[1]), (0, 0)))
                if predictor == 2:
                    block = np.concatenate([block[:, :1], block[:, 1:] - block[:, :-1]], axis=1).astype(block.dtype)
                stored = _compress(np.ascontiguousarray(block).tobytes(), compression)
                offsets.append(len(out))
                sizes.append(len(stored))
                out += stored
        size = image.dtype.itemsize * 8
        tags = [(WIDTH, "I", [width]), (LENGTH, "I", [height]), (BITS, "H", [size] * samples), (COMPRESSION, "H", [compression]), (PHOTOMETRIC, "H", [1]), (SAMPLES, "H", [samples]), (PREDICTOR, "H", [predictor])]
        tags += [(TILE_WIDTH, "I", [across]), (TILE_LENGTH, "I", [down]), (TILE_OFFSETS, "I", offsets), (TILE_BYTES, "I", sizes)] if tile else [(STRIP_OFFSETS, "I", offsets), (ROWS, "I", [down]), (STRIP_BYTES, "I", sizes)]
        entries = []
        for tag, form, values in sorted(tags):
            packed = struct.pack(order + form * len(values), *values)
            if len(packed) > 4:
                out += b"\0" * (len(out) % 2)
                packed, where = struct.pack(order + "I", len(out)), packed
                out += where
            entries.append(struct.pack(order + "HHI", tag, {"H": 3, "I": 4}[form], len(values)) + packed.ljust(4, b"\0"))
        out += b"\0" * (len(out) % 2)
        struct.pack_into(order + "I", out, link, len(out))
        out += struct.pack(order + "H", len(entries)) + b"".join(entries)
        link = len(out)
        out += b"\0\0\0\0"
    return bytes(out)


PAGES = "key {key}, page int, width int, height int, samples int, bits int, compression int, predictor int, data binary, error string, media_bytes long, media_sha256 string"


def tiff_pages(df: DataFrame, key: str = "doc_id", media: str = "media") -> DataFrame:
    """One row per page: its place, shape, how it was stored, its samples row by row, and the file's length and digest."""
    rows = df.select(F.col(key).alias("key"), F.col(media).alias("media"))
    schema = PAGES.format(key=rows.schema["key"].dataType.simpleString())
    fields = pa.schema([("page", pa.int32()), ("width", pa.int32()), ("height", pa.int32()), ("samples", pa.int32()), ("bits", pa.int32()), ("compression", pa.int32()), ("predictor", pa.int32()), ("data", pa.binary()), ("error", pa.string()), ("media_bytes", pa.int64()), ("media_sha256", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = pa.schema([("key", batch.schema.field(0).type), *fields])

            def pages(batch=batch):
                for k, media in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    held = media.as_py()
                    size, digest = len(held or b""), hashlib.sha256(held or b"").hexdigest()
                    for p in read_pages(held):
                        yield k, p.number, p.width, p.height, p.samples, p.bits, p.compression, p.predictor, p.data, p.error, size, digest

            yield from rows_out(pages(), out, weigh=lambda row: len(row[8] or b""))

    return arrow_map(rows, run, schema).withColumnRenamed("key", key)


def texts_as_tiff(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Texts as UTF-8, filled up with bytes 255 to whole rows, as pages of a deflated TIFF with the horizontal predictor.

    Columns: the key, n_bytes (before filling) and ``media``. A null text reads as the empty one.
    """
    rows = df.select(F.col(key).alias("key"), F.col(text).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = pa.schema([("key", batch.schema.field(0).type), ("n_bytes", pa.int64()), ("media", pa.binary())])

            def files(batch=batch):
                for k, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    payload = (t or "").encode("utf-8", "replace")
                    filled = np.frombuffer(payload.ljust(max(1, -(-len(payload) // TEXT_WIDTH)) * TEXT_WIDTH, b"\xff"), np.uint8).reshape(-1, TEXT_WIDTH, 1)
                    yield k, len(payload), write_pages([filled[i : i + TEXT_PAGE] for i in range(0, len(filled), TEXT_PAGE)], DEFLATE, 2)

            yield from rows_out(files(), out, weigh=lambda row: len(row[2]))

    return arrow_map(rows, run, f"key {rows.schema['key'].dataType.simpleString()}, n_bytes long, media binary").withColumnRenamed("key", key)


def page_digest(pages: DataFrame, key: str = "doc_id") -> DataFrame:
    """Per file, from its page rows, which stand together: payload_bytes, digests and features of all samples.

    The rows of a file follow each other from page 0, so pages are hashed as they come and no file is gathered.
    """
    names = ["page", "width", "height", "data", "media_bytes", "media_sha256"]
    rows = pages.select(F.col(key).alias("key"), *names)
    fields = [("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = None

        def digests():
            nonlocal kind
            held = None
            for batch in batches:
                kind = kind or batch.schema.field(0).type
                for k, page, width, height, data, size, digest in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    if page <= 0:
                        if held:
                            yield held.row()
                        held = _Held(k, size, digest)
                    held.add(width, height, data or b"")
            if held:
                yield held.row()

        source = digests()
        first = next(source, None)
        if first is None:
            return
        out = pa.schema([("key", kind), *fields])
        yield from rows_out(_chain(first, source), out)

    return arrow_map(rows, run, f"key {rows.schema['key'].dataType.simpleString()}, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string").withColumnRenamed("key", key)


def _chain(first: tuple, rest: Iterator[tuple]) -> Iterator[tuple]:
    yield first
    yield from rest


class _Held:
    """What is known so far of one file's samples."""

    def __init__(self, key, size: int, digest: str):
        self.key, self.size, self.media = key, size, digest
        self.sha, self.n, self.tail, self.pages, self.width, self.height = hashlib.sha256(), 0, b"", 0, 0, 0
        self.counts = np.zeros(256, np.int64)

    def add(self, width: int, height: int, data: bytes) -> None:
        self.sha.update(data)
        self.n += len(data)
        self.tail = (self.tail + data[-32:])[-32:]
        self.pages, self.width, self.height = self.pages + 1, max(self.width, width), self.height + height
        self.counts += np.bincount(np.frombuffer(data, np.uint8), minlength=256)

    def row(self) -> tuple:
        total = max(1, self.n)
        share = self.counts[self.counts > 0] / total
        mean = float(self.counts @ np.arange(256)) / total
        eighths = ",".join(map(str, self.counts.reshape(8, 32).sum(axis=1)))
        feature = f"pages={self.pages};width={self.width};height={self.height};mean={mean:.4f};entropy={-float(share @ np.log2(share)):.4f};eighths={eighths}"
        return self.key, self.n, self.sha.hexdigest(), zlib.crc32(self.tail), self.size, self.media, feature


def text_media_digest(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Texts to TIFF files, back to pages, and the digest of what was read back; n_bytes is the text's own length."""
    files = texts_as_tiff(df, key, text)
    digest = page_digest(tiff_pages(files.select(F.struct(F.col(key).alias("id"), "n_bytes").alias("key"), "media"), "key"), "key")
    return digest.select(F.col("key.id").alias(key), F.col("key.n_bytes").alias("n_bytes"), *[c for c in digest.columns if c != "key"])
