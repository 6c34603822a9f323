import hashlib
import struct
import zlib

import numpy as np
import pytest

from subweight.llm import tiff
from subweight.llm.entry import op5_tiff


def image(dtype, samples=1, shape=(37, 53)):
    rng = np.random.default_rng(3)
    a = rng.integers(0, 200, (*shape, samples)).cumsum(axis=1)
    return (a * 1.37).astype(dtype) if np.dtype(dtype).kind == "f" else a.astype(dtype)


@pytest.mark.parametrize("compression", [tiff.PLAIN, tiff.DEFLATE, tiff.LZW, tiff.PACKBITS])
@pytest.mark.parametrize("order", ["<", ">"])
@pytest.mark.parametrize("tile", [None, (16, 32)])
@pytest.mark.parametrize(("dtype", "predictor"), [("u1", 1), ("u1", 2), ("u2", 2), ("u4", 2), ("f4", 3), ("f8", 3), ("f4", 1)])
@pytest.mark.parametrize("samples", [1, 3])
def test_round_trip(compression, order, tile, dtype, predictor, samples):
    pictures = [image(dtype, samples), image(dtype, samples, (1, 1)), image(dtype, samples, (64, 64))]
    for planar in (False, True):
        pages = tiff.read_pages(tiff.write_pages(pictures, compression, predictor, tile, strip_rows=5, order=order, planar=planar))
        assert [p.pixels for p in pages] == [np.ascontiguousarray(x.astype(f"<{dtype}")).tobytes() for x in pictures]


def test_lzw_long():
    rng = np.random.default_rng(1)
    for data in (b"", b"a", b"a" * 100_000, rng.integers(0, 256, 50_000, dtype=np.uint8).tobytes(), rng.integers(0, 3, 50_000, dtype=np.uint8).tobytes(), *[rng.integers(0, 256, n, dtype=np.uint8).tobytes() for n in range(240, 270)], *[rng.integers(0, 256, n, dtype=np.uint8).tobytes() for n in range(3825, 3850)]):
        assert tiff.lzw_decode(tiff.lzw_encode(data)) == data
        assert tiff.unpack_bits(tiff.pack_bits(data)) == data


def test_two_bits_and_fill_order():
    rows = np.array([[0b00011011], [0b11100100]], np.uint8)
    flipped = np.packbits(np.unpackbits(rows, axis=1, bitorder="little"), axis=1)
    for data, order in ((rows, 1), (flipped, 2)):
        fields = [(256, 4), (257, 2), (258, 2), (259, 1), (266, order), (273, 8), (279, 2)]
        file = b"II" + struct.pack("<HI", 42, 10) + data.tobytes() + struct.pack("<H", len(fields)) + b"".join(struct.pack("<HHII", t, 3, 1, v) for t, v in fields) + struct.pack("<I", 0)
        assert tiff.read_pages(file)[0].pixels == bytes([0, 1, 2, 3, 3, 2, 1, 0])


def test_rows_and_damage(spark):
    good = tiff.write_pages([image("u1"), image("u2")], tiff.LZW, 2)
    ring = bytearray(tiff.write_pages([image("u1")]))
    (at,) = struct.unpack_from("<I", ring, 4)
    (n,) = struct.unpack_from("<H", ring, at)
    struct.pack_into("<I", ring, at + 2 + 12 * n, at)
    df = spark.createDataFrame([(1, good, "a"), (2, None, "b"), (3, b"", "c"), (4, b"nonsense", "d"), (5, bytes(ring), "e"), (6, good[:200], "f"), (1, good, "a")], "k long, media binary, width string")
    rows = tiff.tiff_pages(df).collect()
    assert sorted((r.k, r.page, r.error is None) for r in rows if r.page is not None) == [(1, 0, True), (1, 0, True), (1, 1, True), (1, 1, True)]
    assert {r.k for r in rows if r.error} == {2, 3, 4, 5, 6}
    assert tiff.tiff_pages(df.limit(0)).count() == 0


def entries(data):
    """Places of the values of the first directory's fields, by tag."""
    (at,) = struct.unpack_from("<I", data, 4)
    (n,) = struct.unpack_from("<H", data, at)
    return {struct.unpack_from("<H", data, at + 2 + 12 * i)[0]: at + 10 + 12 * i for i in range(n)}


@pytest.mark.parametrize("tile", [None, (16, 32)])
def test_no_field_value_is_a_crash(tile):
    """Zero, one, very large and odd values in each field, and bytes changed anywhere: pages or a ValueError."""
    good = tiff.write_pages([image("u1", 3, (20, 30))], tiff.LZW, 2, tile, strip_rows=5)
    for place in entries(good).values():
        for value in (0, 1, 7, 0xFFFF, 0x7FFFFFFF, 0xFFFFFFFF):
            bad = bytearray(good)
            struct.pack_into("<I", bad, place, value)
            try:
                tiff.read_pages(bytes(bad))
            except ValueError:
                pass
    rng = np.random.default_rng(9)
    for compression in (tiff.LZW, tiff.DEFLATE, tiff.PACKBITS, tiff.PLAIN):
        good = tiff.write_pages([image("u2", 1, (9, 11)), image("u1", 1, (4, 4))], compression, 2, tile)
        for _ in range(400):
            bad = bytearray(good)
            for at in rng.integers(0, len(bad), int(rng.integers(1, 6))):
                bad[int(at)] = int(rng.integers(0, 256))
            try:
                tiff.read_pages(bytes(bad[: int(rng.integers(1, len(bad) + 1))] if rng.random() < 0.2 else bad))
            except ValueError:
                pass


def test_inflation_is_bounded():
    """A strip that would expand far beyond its page is not expanded."""
    for compression, blob in ((tiff.DEFLATE, zlib.compress(bytes(50_000_000), 9)), (tiff.PACKBITS, bytes([129, 0]) * 400_000), (tiff.LZW, tiff.lzw_encode(bytes(5_000_000)))):
        assert len(tiff._inflate(blob, compression, 1000)) < 10_000


def slow_feature(page):
    data = page.pixels
    n = len(data)
    counts = [data.count(bytes([i])) for i in range(256)]
    mean = sum(i * c for i, c in enumerate(counts)) / n
    sd = max(0.0, sum(i * i * c for i, c in enumerate(counts)) / n - mean * mean) ** 0.5
    entropy = -sum(c / n * np.log2(c / n) for c in counts if c)
    edge = [i * n // 65 for i in range(66)]
    cell = [sum(data[a:b]) / max(1, b - a) for a, b in zip(edge, edge[1:], strict=False)]
    grade = "".join("1" if b > a else "0" for a, b in zip(cell, cell[1:], strict=False))
    return f"{page.width}x{page.height}x{page.samples};mean={mean:.3f};sd={sd:.3f};entropy={entropy:.3f};grade={int(grade, 2):016x}"


def test_feature_by_brute_force_and_all_layouts():
    seen = set()
    for i in range(150):
        text = (f"text {i} " * (i + 1)).encode()
        payload = text.ljust(-(-len(text) // 576) * 576, b"\xff")
        compression, predictor, tile, order = tiff.layout_of(payload)
        (page,) = tiff.read_pages(tiff.write_pages([np.frombuffer(payload, np.uint8).reshape(-1, 576, 1)], compression, predictor, tile, 57, order))
        assert page.pixels == payload and (page.compression, page.predictor) == (compression, predictor)
        assert tiff.feature(page) == slow_feature(page)
        seen.add((compression, predictor, tile, order))
    assert len(seen) > 24


def test_query(spark, tmp_path):
    long = "wörd " * 40_000
    df = spark.createDataFrame([(1, "abc"), (2, None), (3, ""), (4, long), (5, "abc"), (6, "x" * 576)], "doc_id long, text string")
    df.write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r for r in op5_tiff(spark, str(tmp_path)).collect()}
    for i, t in df.collect():
        raw = (t or "").encode()
        full = raw.ljust(max(1, -(-len(raw) // 576)) * 576, b"\xff")
        r = got[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-32:]))
    assert got[1].asDict() | {"doc_id": 5} == got[5].asDict()
    assert got[2].media_sha256 == got[3].media_sha256
