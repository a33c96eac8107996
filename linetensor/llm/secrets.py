"""Secret scans with a recursive decoding worklist.

Layer 0 is the text itself. Each layer is scanned for the kinds below, then unwrapped: percent
escapes, Unicode escapes, base64 (also over lines) and hexadecimal runs at every alignment, and
compressed data inside any of those; bytes that are not UTF-8 read as Latin-1. What comes
out is a new layer, unless the same characters were seen before from the same place (so a cycle
ends), and goes on the worklist until nothing new turns up. Raw deflate data, which nothing marks, is tried where a
base64 or hexadecimal run begins. Every character of a layer knows which stretch of
the original text it came from, so that a find in any layer is reported as a span of the text.

Cases: a null text reads as the empty one and has no spans. Repeated rows give repeated results;
extra columns are left alone; an empty table gives an empty table. Decompressed data beyond
``largest`` bytes in one text (a parameter, 256 MiB unless it is given) is not unwrapped further, as a
guard against bombs; the scan of the text itself has no limit. Very long texts are scanned whole, and
finds that tie in place are all reported, in the order of kinds.
"""

from __future__ import annotations

import binascii
import gzip
import hashlib
import re
import zlib
from array import array
from collections import deque
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, sha

#: The kinds in their order, their patterns and least lengths.
KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
HEX = re.compile(r"[0-9a-f]{24,}")
KEYWORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ASSIGN_LEAST = 6

#: What may be unwrapped.
PERCENT = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
UNICODE = re.compile(r"\\u[dD][89abAB][0-9A-Fa-f]{2}\\u[dD][c-fC-F][0-9A-Fa-f]{2}|\\u[0-9A-Fa-f]{4}|\\u\{[0-9A-Fa-f]{1,6}\}|\\U[0-9A-Fa-f]{8}|\\x[0-9A-Fa-f]{2}")
RUN = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}")
WRAPPED = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{16,}+(?:\r?\n[\x20\t]*[A-Za-z0-9+/_-]+)+={0,2}")
HEX_RUN = re.compile(r"[0-9A-Fa-f]{24,}")
#: Compressed bytes behind escapes: where they may begin, and what goes on with them.
PACKED = {
    "url": (re.compile(r"%1[fF]%8[bB]|(?:%78|x)%(?:01|5[eE]|9[cC]|[dD][aA])"), re.compile(r"%[0-9A-Fa-f]{2}|[!-~]")),
    "unicode": (re.compile(r"\\(?:x|u00)1[fF]\\(?:x|u00)8[bB]|(?:\\(?:x|u00)78|x)\\(?:x|u00)(?:01|5[eE]|9[cC]|[dD][aA])"), re.compile(r"\\(?:x|u00)[0-9A-Fa-f]{2}|\\[abfnrtv0\\'\"]|[\x20-~]")),
}
SHORT = dict(zip("abfnrtv0", b"\a\b\f\n\r\t\v\0", strict=True))
MAGIC = re.compile(rb"\x1f\x8b\x08|\x78[\x01\x5e\x9c\xda]")
#: The shortest find, or wrapping of one, has so many plain characters.
PLAIN = re.compile(r"[\x20-\x7e\t\r\n]{12,}")
#: Bytes of decompressed data in one text, unless the caller gives another bound.
LARGEST = 256 << 20

SPAN = "array<struct<kind:string,start:long,end:long,layer:string>>"


def scan(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the finds in one string, by start and kind."""
    found = []
    lower = text.lower()
    if any(word in lower for word in KEYWORDS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LEAST]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text)]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


class Layer:
    """A decoded text; starts[i] and ends[i] say where its character i lies in the original, or whole where all of it lies.

    Characters keep their order, so a stretch lies between its first start and its last end.
    """

    __slots__ = ("text", "starts", "ends", "how", "whole")

    def __init__(self, text: str, starts, ends, how: str, whole: tuple[int, int] | None = None):
        self.text, self.starts, self.ends, self.how, self.whole = text, starts, ends, how, whole

    def place(self, start: int, end: int) -> tuple[int, int]:
        if self.whole:
            return self.whole
        return (start, end) if self.starts is None else (self.starts[start], self.ends[end - 1])


def _escapes(layer: Layer, pattern: re.Pattern, decode, how: str) -> Layer | None:
    """The whole layer with each escape replaced, so that finds may begin and end outside of it."""
    pieces, starts, ends, at, changed = [], array("q"), array("q"), 0, False
    text = layer.text
    for found in pattern.finditer(text):
        parts = decode(found.group())
        if parts is None:
            continue
        changed = True
        for i in range(at, found.start()):
            a, b = layer.place(i, i + 1)
            starts.append(a)
            ends.append(b)
        pieces.append(text[at : found.start()])
        for char, begin, stop in parts:
            a, b = layer.place(found.start() + begin, found.start() + stop)
            pieces.append(char)
            starts.append(a)
            ends.append(b)
        at = found.end()
    if not changed:
        return None
    for i in range(at, len(text)):
        a, b = layer.place(i, i + 1)
        starts.append(a)
        ends.append(b)
    pieces.append(text[at:])
    return Layer("".join(pieces), starts, ends, f"{layer.how}>{how}")


def _percent(run: str) -> list[tuple[str, int, int]]:
    out, at = [], 0
    for char, size in _lossy(bytes.fromhex(run.replace("%", ""))):
        out.append((char, at, at + 3 * size))
        at += 3 * size
    return out


def _lossy(raw: bytes) -> Iterator[tuple[str, int]]:
    """Characters and their bytes: UTF-8, and Latin-1 for bytes that are not."""
    for char in raw.decode("utf-8", "surrogateescape"):
        code = ord(char)
        yield (chr(code - 0xDC00), 1) if 0xDC80 <= code <= 0xDCFF else (char, len(char.encode("utf-8")))


def _unicode(run: str) -> list[tuple[str, int, int]] | None:
    codes = [int(x, 16) for x in re.findall(r"[0-9A-Fa-f]{2,8}|(?<=\{)[0-9A-Fa-f]+", run.replace("\\x", "").replace("\\u", " ").replace("\\U", " ").replace("{", "").replace("}", ""))] or [0x110000]
    code = codes[0] if len(codes) == 1 else 0x10000 + ((codes[0] - 0xD800) << 10) + (codes[1] - 0xDC00)
    if code > 0x10FFFF or 0xD800 <= code < 0xE000:
        return None
    return [(chr(code), 0, len(run))]


def _inflate(raw: bytes, room: int) -> tuple[bytes, int] | None:
    """Decompressed bytes of gzip or zlib data, and how many it took; None if it is neither or has no room."""
    if raw[:2] == b"\x1f\x8b":
        window = 31
    elif len(raw) > 2 and raw[0] == 0x78 and (raw[0] * 256 + raw[1]) % 31 == 0:
        window = 15
    else:
        return None
    try:
        engine = zlib.decompressobj(window)
        out = engine.decompress(raw, room)
        return (out, len(raw) - len(engine.unused_data)) if engine.eof else None
    except zlib.error:
        return None


def _unpacked(raw: bytes, room: list[int]) -> tuple[str, str, int] | None:
    """The text in compressed bytes, however often compressed, its layers' names, and how many of the bytes it took."""
    packed, taken = "", 0
    while room[0] > 0 and (inflated := _inflate(raw, room[0])) is not None:
        raw, used = inflated
        room[0] -= len(raw)
        taken, packed = taken or used, packed + ">deflate"
    return ("".join(c for c, _ in _lossy(raw)), packed, taken) if packed and raw else None


def _raw_deflate(raw: bytes, room: list[int]) -> bytes | None:
    """What raw deflate data holds, if it is that: it must end in itself and give readable text."""
    if room[0] <= 0 or raw[:1] and raw[0] & 6 == 6:
        return None
    try:
        engine = zlib.decompressobj(-15)
        out = engine.decompress(raw, room[0])
    except zlib.error:
        return None
    if not engine.eof or not PLAIN.search(out.decode("latin-1")):
        return None
    room[0] -= len(out)
    return out


def _layers(layer: Layer, raw: bytes, how: str, place, room: list[int]) -> Iterator[Layer]:
    """What lies in decoded bytes: compressed data from any place on, and readable stretches; place(i, j) is where bytes lie."""
    for found in MAGIC.finditer(raw):
        if out := _unpacked(raw[found.start() :], room):
            yield Layer(out[0], None, None, f"{layer.how}>{how}{out[1]}", layer.place(*place(found.start(), found.start() + out[2])))
    if (out := _raw_deflate(raw, room)) is not None:
        yield Layer("".join(c for c, _ in _lossy(out)), None, None, f"{layer.how}>{how}>deflate", layer.place(*place(0, len(raw))))
    chars, starts, ends, byte = [], array("q"), array("q"), 0
    if not PLAIN.search(raw.decode("latin-1")):
        return
    for char, size in _lossy(raw):
        a, b = layer.place(*place(byte, byte + size))
        chars.append(char)
        starts.append(a)
        ends.append(b)
        byte += size
    yield Layer("".join(chars), starts, ends, f"{layer.how}>{how}")


def _runs(layer: Layer, room: list[int]) -> Iterator[Layer]:
    """Base64 and hexadecimal runs at every alignment, as what they are glued to may be letters of theirs; base64 also over lines."""
    for found in HEX_RUN.finditer(layer.text):
        for k in (0, 1):
            body = found.group()[k:]
            at = found.start() + k
            yield from _layers(layer, bytes.fromhex(body[: len(body) // 2 * 2]), "hex", lambda i, j, at=at: (at + 2 * i, at + 2 * j), room)
    for pattern in (RUN, WRAPPED):
        for found in pattern.finditer(layer.text):
            kept = [i for i in range(*found.span()) if layer.text[i] not in "=\r\n\t "]
            body = "".join([layer.text[i] for i in kept]).replace("-", "+").replace("_", "/")
            for k in range(4):
                own = body[k : len(body) - ((len(body) - k) % 4 == 1)]
                raw = binascii.a2b_base64(own + "=" * (-len(own) % 4))
                ends = [*[at + 1 for at in kept[:-1]], found.end()]  # padding belongs to the last letter
                yield from _layers(layer, raw, "base64", lambda i, j, k=k, kept=kept, ends=ends: (kept[k + i // 3 * 4], ends[min(len(kept), k + ((j - 1) // 3 + 1) * 4) - 1]), room)


def _packed_escapes(layer: Layer, how: str, room: list[int]) -> Iterator[Layer]:
    """Compressed bytes that are written as escapes, with or without plain characters between them."""
    first, unit = PACKED[how]
    for found in first.finditer(layer.text):
        raw, ends, at = bytearray(), array("q"), found.start()
        while piece := unit.match(layer.text, at):
            said, at = piece.group(), piece.end()
            ends.append(at)
            raw.append(ord(said) if len(said) == 1 else SHORT.get(said[1], ord(said[1])) if len(said) == 2 else int(said[-2:], 16))
        if out := _unpacked(bytes(raw), room):
            yield Layer(out[0], None, None, f"{layer.how}>{how}{out[1]}", layer.place(found.start(), ends[out[2] - 1]))


def unwrap(layer: Layer, room: list[int]) -> Iterator[Layer]:
    text = layer.text
    if "%" in text and (out := _escapes(layer, PERCENT, _percent, "url")):
        yield out
        yield from _packed_escapes(layer, "url", room)
    if "\\" in text and (out := _escapes(layer, UNICODE, _unicode, "unicode")):
        yield out
        yield from _packed_escapes(layer, "unicode", room)
    yield from _runs(layer, room)


def find_secrets(text: str | None, largest: int = LARGEST) -> list[tuple[str, int, int, str]]:
    """(kind, start, end, layer) of every distinct find, by start, kind and end; layer ``text`` is the text itself."""
    spans: dict[tuple[int, int, int], str] = {}
    room = [largest]
    work = deque([Layer(text or "", None, None, "text")])
    first = hashlib.sha256((text or "").encode("utf-8", "replace")).digest()
    seen: set[bytes] = set()
    while work:
        layer = work.popleft()
        for start, kind, end in scan(layer.text):
            a, b = layer.place(start, end)
            spans.setdefault((a, kind, b), layer.how)
        for inner in unwrap(layer, room):
            mark = hashlib.sha256(inner.text.encode("utf-8", "replace") + repr(inner.place(0, len(inner.text))).encode()).digest()
            plain = hashlib.sha256(inner.text.encode("utf-8", "replace")).digest()
            if mark not in seen and plain != first:
                seen.add(mark)
                work.append(inner)
    return [(KINDS[kind], a, b, how) for (a, kind, b), how in sorted(spans.items())]


def scan_documents(df: DataFrame, key: str = "doc_id", text: str = "text", largest: int = LARGEST) -> DataFrame:
    """One row per input row: the key and ``spans``, an array of (kind, start, end, layer) in code points."""
    rows = df.select(F.col(key).alias("key"), F.col(text).alias("text"))
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("layer", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ("kind", "start", "end", "layer")
        for batch in batches:
            spans = [[dict(zip(names, s, strict=True)) for s in find_secrets(t, largest)] for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(spans, kind)], names=["key", "spans"])

    return arrow_map(rows, run, f"key {rows.schema['key'].dataType.simpleString()}, spans {SPAN}").withColumnRenamed("key", key)


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def secret_digest(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Counts and digest of the finds in the text itself, and all spans."""
    found = scan_documents(df, key, text)
    base = F.filter("spans", lambda s: s["layer"] == "text")
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.withColumn("base", base).select(F.col(key), *[count(k) for k in KINDS], sha(_joined(F.col("base"))).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))


def wrapped(text: str, *layers: str) -> str:
    """The text wrapped layer by layer (url, unicode, base64, hex, gzip): for tests and examples."""
    for layer in layers:
        raw = text.encode("utf-8")
        text = {
            "url": lambda raw=raw: "".join(f"%{b:02X}" for b in raw),
            "unicode": lambda t=text: "".join(f"\\u{ord(c):04x}" for c in t),
            "base64": lambda raw=raw: binascii.b2a_base64(raw, newline=False).decode(),
            "hex": lambda raw=raw: raw.hex(),
            "gzip": lambda raw=raw: binascii.b2a_base64(gzip.compress(raw, mtime=0), newline=False).decode(),
        }[layer]()
    return text
