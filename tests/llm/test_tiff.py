import hashlib
import struct
import zlib

import numpy as np
import pytest

from linetensor.llm import tiff

RNG = np.random.default_rng(3)


@pytest.mark.parametrize("compression", [tiff.NONE, tiff.PACKBITS, tiff.LZW, tiff.DEFLATE, tiff.OLD_DEFLATE])
@pytest.mark.parametrize("predictor", [1, 2])
@pytest.mark.parametrize("tile", [None, (16, 32)])
@pytest.mark.parametrize("order", ["<", ">"])
@pytest.mark.parametrize(("kind", "samples"), [(np.uint8, 1), (np.uint8, 3), (np.uint16, 1)])
def test_round_trip(compression, predictor, tile, order, kind, samples):
    images = [RNG.integers(0, 9, (50, 70, samples)).astype(kind), np.full((5, 33, samples), 7, kind), RNG.integers(0, 256, (90, 80, samples)).astype(kind)]
    pages = list(tiff.read_pages(tiff.write_pages(images, compression, predictor, 7, tile, order)))
    assert [p.error for p in pages] == [None] * 3
    for page, image in zip(pages, images, strict=True):
        assert page.data == image.astype(image.dtype.newbyteorder(order)).tobytes()
        assert (page.height, page.width, page.samples) == image.shape


def test_long_lzw_tables_are_cleared():
    data = RNG.integers(0, 256, 60_000).astype(np.uint8).tobytes()
    assert tiff.lzw_decode(tiff.lzw_encode(data)) == data
    assert tiff.lzw_decode(tiff.lzw_encode(b"")) == b""


def test_float_predictor():
    values = RNG.normal(size=(3, 10)).astype(">f4")
    planes = values.view(np.uint8).reshape(3, 10, 4).transpose(0, 2, 1).reshape(3, 40)
    stored = np.concatenate([planes[:, :1], planes[:, 1:] - planes[:, :-1]], axis=1)
    block = np.frombuffer(stored.tobytes(), "<u4").reshape(3, 10, 1)
    assert (tiff._undo(block, 3, "<").tobytes()) == values.astype("<f4").tobytes()


def test_bad_files():
    assert [p.error for p in tiff.read_pages(None)] == ["empty"]
    assert next(tiff.read_pages(b"GIF89a....")).error.startswith("ValueError")
    good = bytearray(tiff.write_pages([np.zeros((4, 4, 1), np.uint8)]))
    at = struct.unpack_from("<I", good, 4)[0]
    n = struct.unpack_from("<H", good, at)[0]
    struct.pack_into("<I", good, at + 2 + 12 * n, at)  # the chain returns to itself
    assert len(list(tiff.read_pages(bytes(good)))) == 1
    assert list(tiff.read_pages(bytes(good[:12])))[0].error


def test_text_digest(spark):
    texts = ["", None, "abc", "é" * 400, "x" * 576, "long text " * 300_000, "abc"]
    df = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)], "doc_id long, text string, media int")
    rows = {r.doc_id: r for r in tiff.text_media_digest(df).collect()}
    for i, text in enumerate(texts):
        raw = (text or "").encode()
        payload = raw + b"\xff" * (max(576, -(-len(raw) // 576) * 576) - len(raw))
        r = rows[i]
        assert (r.n_bytes, r.payload_bytes, r.tail_crc32) == (len(raw), len(payload), zlib.crc32(payload[-32:]))
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest()
    assert rows[5].feature.startswith("pages=2;")
    assert rows[2][2:] == rows[6][2:]
    assert tiff.text_media_digest(df.limit(0)).count() == 0


def test_malformed_files_give_error_pages():
    good = tiff.write_pages([np.arange(24, dtype=np.uint8).reshape(4, 6, 1)])
    (first,) = struct.unpack_from("<I", good, 4)
    (entries,) = struct.unpack_from("<H", good, first)
    for k in range(entries):
        at = first + 2 + 12 * k
        for form, count, value in ((4, 1, 0), (4, 0, 0), (11, 1, 1), (4, 1, 0xFFFFFFFF), (3, 1, 7), (12, 9, 1 << 31), (2, 1, 65)):
            broken = bytearray(good)
            struct.pack_into("<HII", broken, at + 2, form, count, value)
            pages = list(tiff.read_pages(bytes(broken)))
            assert pages and all(abs(p.width) <= tiff.MOST for p in pages)
    for cut in range(0, len(good), 3):
        list(tiff.read_pages(good[:cut]))
    huge = bytearray(good)
    for k in range(entries):
        at = first + 2 + 12 * k
        if struct.unpack_from("<H", huge, at)[0] in (tiff.WIDTH, tiff.LENGTH):
            struct.pack_into("<I", huge, at + 8, 1 << 30)
    (page,) = tiff.read_pages(bytes(huge))
    assert page.data is None and page.error
