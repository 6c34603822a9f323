"""TIFF media columns: images to rows, one for each page.

The reader walks the chain of image directories in either byte order, decodes strips or tiles that
are stored plainly, by PackBits, LZW or deflate, undoes the horizontal and floating-point
predictors, and puts chunky or planar samples in pixel order.  The writer makes such files.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

# Fixed values of the TIFF format: tags, bytes in a field type, and compression schemes.
WIDTH, HEIGHT, BITS, COMPRESSION, PHOTOMETRIC, FILL_ORDER, STRIP_AT, SAMPLES, STRIP_ROWS, STRIP_SIZE, PLANAR = 256, 257, 258, 259, 262, 266, 273, 277, 278, 279, 284
PREDICTOR, TILE_WIDTH, TILE_HEIGHT, TILE_AT, TILE_SIZE, SAMPLE_FORMAT = 317, 322, 323, 324, 325, 339
TYPES = {1: "B", 2: "c", 3: "H", 4: "I", 6: "b", 8: "h", 9: "i", 16: "Q"}
PLAIN, LZW, DEFLATE, OLD_DEFLATE, PACKBITS = 1, 5, 8, 32946, 32773

#: Most bytes of pixels that the pages of one file may claim together.
MOST_PIXEL_BYTES = 1 << 30
#: What a damaged file may raise while it is read.
DAMAGE = (ValueError, KeyError, IndexError, ArithmeticError, MemoryError, TypeError, struct.error, zlib.error)


@dataclass
class Page:
    width: int
    height: int
    samples: int
    bits: int
    sample_format: int
    compression: int
    predictor: int
    pixels: bytes  # rows from the top, samples of a pixel together, little-endian, 1 to 4 bits unpacked to bytes


def unpack_bits(data: bytes, most: int | None = None) -> bytes:
    """PackBits undone, up to about ``most`` bytes."""
    out, i, n = bytearray(), 0, len(data)
    most = MOST_PIXEL_BYTES if most is None else most
    while i < n and len(out) < most:
        head = data[i]
        if head < 128:
            out += data[i + 1 : i + head + 2]
            i += head + 2
        else:
            if head > 128 and i + 1 < n:
                out += data[i + 1 : i + 2] * (257 - head)
            i += 1 if head == 128 else 2
    return bytes(out)


def pack_bits(data: bytes) -> bytes:
    """Runs of three or more as a count and a byte, all else as stretches of up to 128 bytes."""
    array = np.frombuffer(data, np.uint8)
    edge = np.flatnonzero(np.concatenate([[True], array[1:] != array[:-1], [True]])) if len(array) else np.zeros(1, np.int64)
    size = np.diff(edge)
    long = np.flatnonzero(size >= 3)
    out, at = bytearray(), 0

    def plain(end: int) -> None:
        nonlocal at
        while at < end:
            step = min(128, end - at)
            out.append(step - 1)
            out.extend(data[at : at + step])
            at += step

    for start, n in zip(edge[long].tolist(), size[long].tolist(), strict=True):
        plain(start)
        while n > 1:
            step = min(128, n)
            out += bytes([257 - step, data[start]])
            at, n = at + step, n - step
        plain(at + n)
    plain(len(data))
    return bytes(out)


def lzw_decode(data: bytes, most: int | None = None) -> bytes:
    """Codes of 9 to 12 bits, first bit highest; 256 clears the table, 257 ends; widths grow one code early.  Stops at about ``most`` bytes."""
    table: list[bytes] = []
    out, held, bits, width, last, made = [], 0, 0, 9, b"", 0
    most = MOST_PIXEL_BYTES if most is None else most
    clean = [bytes([i]) for i in range(256)] + [b"", b""]
    for byte in data:
        held = (held << 8 | byte) & 0xFFFFFF
        bits += 8
        if bits < width:
            continue
        bits -= width
        code = held >> bits & ((1 << width) - 1)
        if code == 257 or made > most:
            break
        if code == 256:
            table, width, last = clean.copy(), 9, b""
            continue
        if not table:
            raise ValueError("LZW data does not start with a clear code")
        if code < len(table):
            entry = table[code]
        elif code == len(table) and last:
            entry = last + last[:1]
        else:
            raise ValueError("LZW code out of range")
        out.append(entry)
        made += len(entry)
        if last and len(table) < 4096:
            table.append(last + entry[:1])
            if len(table) + 1 >= 1 << width and width < 12:
                width += 1
        last = entry
    return b"".join(out)


def lzw_encode(data: bytes) -> bytes:
    """What ``lzw_decode`` reads; strings of the table are numbers of a shorter string's code and one more byte."""
    codes, widths = [256], [9]
    table: dict[int, int] = {}
    at, next_code, width = -1, 258, 9
    get = table.get
    for byte in data:
        if at < 0:
            at = byte
            continue
        grown = at << 8 | byte
        code = get(grown)
        if code is not None:
            at = code
            continue
        codes.append(at)
        widths.append(width)
        table[grown] = next_code
        next_code += 1
        if next_code + 1 > 1 << width and width < 12:
            width += 1
        if next_code >= 4094:
            codes.append(256)
            widths.append(width)
            table.clear()
            next_code, width = 258, 9
        at = byte
    if at >= 0:
        codes.append(at)
        widths.append(width)
        if next_code + 2 > 1 << width and width < 12:  # the reader has added one more entry by then
            width += 1
    codes.append(257)
    widths.append(width)
    bits = []
    for a in range(0, len(codes), 1 << 16):  # the bits of each code, those above its width left out
        each = (np.array(codes[a : a + (1 << 16)], np.uint16)[:, None] >> np.arange(11, -1, -1, dtype=np.uint16)) & 1
        bits.append(each[np.arange(12)[None, :] >= 12 - np.array(widths[a : a + (1 << 16)])[:, None]].astype(np.uint8))
    return np.packbits(np.concatenate(bits)).tobytes()


def _inflate(data: bytes, compression: int, most: int) -> bytes:
    """A strip or tile, of which no more than about ``most`` bytes are wanted."""
    if compression == PLAIN:
        return data
    if compression in (DEFLATE, OLD_DEFLATE):
        return zlib.decompressobj().decompress(data, max(1, most))
    if compression == LZW:
        return lzw_decode(data, most)
    if compression == PACKBITS:
        return unpack_bits(data, most)
    raise ValueError(f"compression {compression} is not supported")


class _Fields:
    """The fields of one image directory."""

    def __init__(self, data: bytes, at: int, order: str):
        (n,) = struct.unpack_from(f"{order}H", data, at)
        self.values: dict[int, list[int]] = {}
        for i in range(n):
            tag, kind, count = struct.unpack_from(f"{order}HHI", data, at + 2 + 12 * i)
            form = TYPES.get(kind)
            if form is None or form == "c":
                continue
            size = struct.calcsize(form) * count
            where = at + 10 + 12 * i
            if size > 4:
                (where,) = struct.unpack_from(f"{order}I", data, where)
            self.values[tag] = list(struct.unpack_from(f"{order}{count}{form}", data, where))
        (self.next,) = struct.unpack_from(f"{order}I", data, at + 2 + 12 * n)

    def one(self, tag: int, default: int | None = None) -> int:
        got = self.values.get(tag)
        if got:
            return got[0]
        if default is None:
            raise ValueError(f"tag {tag} is missing")
        return default


def _page(data: bytes, f: _Fields, order: str, most: int) -> Page:
    """One page; ValueError if it claims more than ``most`` bytes or a field has no sensible value."""
    width, height, samples = f.one(WIDTH), f.one(HEIGHT), f.one(SAMPLES, 1)
    if min(width, height, samples) < 1:
        raise ValueError("a page without pixels")
    bits, compression, predictor, form = f.one(BITS, 1), f.one(COMPRESSION, PLAIN), f.one(PREDICTOR, 1), f.one(SAMPLE_FORMAT, 1)
    planar = f.one(PLANAR, 1) == 2
    if bits not in (1, 2, 4, 8, 16, 32, 64) or any(b != bits for b in f.values.get(BITS, [])):
        raise ValueError("sample sizes that are not supported")
    size = max(1, bits // 8)
    if width * height * samples * size > most:
        raise ValueError("the page claims too many pixels")
    tiled = TILE_AT in f.values
    across, down = (f.one(TILE_WIDTH), f.one(TILE_HEIGHT)) if tiled else (width, min(height, f.one(STRIP_ROWS, height)))
    if min(across, down) < 1 or across * down * samples * size > most:
        raise ValueError("strips or tiles of no sensible size")
    places, sizes = (f.values[TILE_AT], f.values[TILE_SIZE]) if tiled else (f.values[STRIP_AT], f.values[STRIP_SIZE])
    columns, lines, depth = -(-width // across), -(-height // down), 1 if planar else samples
    if min(len(places), len(sizes)) < columns * lines * (samples if planar else 1) or min(*places, *sizes, 0) < 0:
        raise ValueError("strips or tiles are missing")
    out = np.zeros((height, width, samples), f"<u{size}")
    for k in range(columns * lines * (samples if planar else 1)):
        plane, cell = divmod(k, columns * lines)
        top, left = cell // columns * down, cell % columns * across
        here = down if tiled else min(down, height - top)
        row_bytes = (across * depth * bits + 7) // 8
        piece = data[places[k] : places[k] + sizes[k]]
        if f.one(FILL_ORDER, 1) == 2:
            piece = np.packbits(np.unpackbits(np.frombuffer(piece, np.uint8), bitorder="little")).tobytes()
        raw = np.frombuffer(_inflate(piece, compression, here * row_bytes), np.uint8)[: here * row_bytes]
        if len(raw) < here * row_bytes:
            raise ValueError("a strip or tile is too short")
        raw = raw.reshape(here, row_bytes)
        if bits < 8:
            if predictor != 1:
                raise ValueError("a predictor needs samples of 8 bits or more")
            each = np.unpackbits(raw, axis=1).reshape(here, -1, bits)[:, : across * depth]
            block = (each * (1 << np.arange(bits - 1, -1, -1))).sum(axis=2).astype(np.uint8).reshape(here, across, depth)
        elif predictor == 3:  # bytes of a row by significance, differenced over the whole row by depth
            summed = np.cumsum(raw.reshape(here, -1, depth), axis=1, dtype=np.uint8).reshape(here, size, across * depth)
            block = np.ascontiguousarray(summed.transpose(0, 2, 1)[:, :, ::-1]).view(f"<u{size}").reshape(here, across, depth)
        else:
            block = np.ascontiguousarray(raw).view(f"{order}u{size}").reshape(here, across, depth).astype(f"<u{size}", copy=False)
            if predictor == 2:
                block = np.cumsum(block, axis=1, dtype=f"u{size}")
            elif predictor != 1:
                raise ValueError(f"predictor {predictor} is not supported")
        h, w = min(here, height - top), min(across, width - left)
        target = out[top : top + h, left : left + w]
        if planar:
            target[:, :, plane] = block[:h, :w, 0]
        else:
            target[:] = block[:h, :w]
    return Page(width, height, samples, bits, form, compression, predictor, out.tobytes())


def read_pages(data: bytes) -> list[Page]:
    """All pages of a file; ValueError if it is not a TIFF file or damaged."""
    try:
        order = {b"II": "<", b"MM": ">"}[data[:2]]
        magic, at = struct.unpack_from(f"{order}HI", data, 2)
        if magic != 42:
            raise ValueError("not a TIFF file")
        pages, seen, left = [], set(), MOST_PIXEL_BYTES
        while at:
            if at in seen:
                raise ValueError("the directories form a ring")
            seen.add(at)
            fields = _Fields(data, at, order)
            pages.append(_page(data, fields, order, left))
            left -= len(pages[-1].pixels)
            at = fields.next
        return pages
    except DAMAGE as e:
        raise ValueError(f"damaged or no TIFF file: {e!r}") from e


def write_pages(images: list[np.ndarray], compression: int = DEFLATE, predictor: int = 1, tile: tuple[int, int] | None = None, strip_rows: int = 0, order: str = "<", level: int = 6, planar: bool = False) -> bytes:
    """A file with a page for each (height, width, samples) array; unsigned or floating samples of 8 to 64 bits."""
    pack = {PLAIN: lambda b, n: b, DEFLATE: lambda b, n: zlib.compress(b, level), LZW: lambda b, n: lzw_encode(b), PACKBITS: lambda b, n: b"".join([pack_bits(b[i : i + n]) for i in range(0, len(b), n)])}[compression]  # PackBits: each row by itself
    out = bytearray((b"II" if order == "<" else b"MM") + struct.pack(f"{order}HI", 42, 0))
    link = 4
    for image in images:
        height, width, samples = image.shape
        size = image.dtype.itemsize
        across, down = tile or (width, min(height, strip_rows or max(1, 8192 // (width * samples * size))))
        places, sizes = [], []
        for plane in range(samples if planar else 1):
            source = image[:, :, plane : plane + 1] if planar else image
            for top in range(0, height, down):
                for left in range(0, width, across):
                    block = source[top : top + down, left : left + across]
                    if tile and block.shape[:2] != (down, across):
                        block = np.pad(block, ((0, down - block.shape[0]), (0, across - block.shape[1]), (0, 0)))
                    whole = np.ascontiguousarray(block).view(f"u{size}")
                    rows = whole.shape[0]
                    if predictor == 2:
                        whole = np.concatenate([whole[:, :1], whole[:, 1:] - whole[:, :-1]], axis=1)
                    raw = np.ascontiguousarray(whole.astype(f"{order}u{size}")).tobytes()
                    if predictor == 3:
                        split = np.ascontiguousarray(whole).reshape(rows, -1).astype(f">u{size}").view(np.uint8).reshape(rows, -1, size).transpose(0, 2, 1).reshape(rows, -1, whole.shape[2])
                        raw = np.concatenate([split[:, :1], split[:, 1:] - split[:, :-1]], axis=1).tobytes()
                    piece = pack(raw, len(raw) // rows)
                    places.append(len(out))
                    sizes.append(len(piece))
                    out += piece
        form = 3 if image.dtype.kind == "f" else 1
        fields = [(WIDTH, 4, [width]), (HEIGHT, 4, [height]), (BITS, 3, [size * 8] * samples), (COMPRESSION, 3, [compression]), (PHOTOMETRIC, 3, [2 if samples == 3 else 1]), (SAMPLES, 3, [samples]), (PLANAR, 3, [2 if planar else 1]), (PREDICTOR, 3, [predictor]), (SAMPLE_FORMAT, 3, [form] * samples)]
        fields += [(TILE_WIDTH, 4, [across]), (TILE_HEIGHT, 4, [down]), (TILE_AT, 4, places), (TILE_SIZE, 4, sizes)] if tile else [(STRIP_AT, 4, places), (STRIP_ROWS, 4, [down]), (STRIP_SIZE, 4, sizes)]
        entries = []
        for tag, kind, values in sorted(fields):
            blob = struct.pack(f"{order}{len(values)}{TYPES[kind]}", *values)
            if len(blob) > 4:
                out += b"\0" * (len(out) % 2)
                blob, value = struct.pack(f"{order}I", len(out)), blob
                out += value
            entries.append(struct.pack(f"{order}HHI", tag, kind, len(values)) + blob.ljust(4, b"\0"))
        out += b"\0" * (len(out) % 2)
        struct.pack_into(f"{order}I", out, link, len(out))
        out += struct.pack(f"{order}H", len(entries)) + b"".join(entries)
        link = len(out)
        out += struct.pack(f"{order}I", 0)
    return bytes(out)


def feature(page: Page) -> str:
    """Size, and mean, deviation and entropy of the bytes of the pixels (in thousandths), and a 64-bit gradient sign pattern of 8 x 8 cells."""
    array = np.frombuffer(page.pixels, np.uint8)
    counts = np.bincount(array, minlength=256)
    n = max(1, len(array))
    level = np.arange(256)
    total, square = int((counts * level).sum()), int((counts * level * level).sum())
    mean = total / n
    p = counts[counts > 0] / n
    entropy = float(-(p * np.log2(p)).sum()) if len(p) else 0.0
    cells = np.add.reduceat(array.astype(np.int64), np.arange(65) * len(array) // 65) if len(array) >= 65 else np.zeros(65, np.int64)
    width = np.diff(np.append(np.arange(65) * len(array) // 65, len(array)))
    grade = np.packbits(np.diff(cells / np.maximum(width, 1)) > 0).tobytes().hex()
    return f"{page.width}x{page.height}x{page.samples};mean={mean:.3f};sd={max(0.0, square / n - mean * mean) ** 0.5:.3f};entropy={entropy:.3f};grade={grade}"


PAGE_FIELDS = "page int, width int, height int, samples int, bits int, sample_format int, compression int, predictor int, pixels binary, feature string, error string"


def tiff_pages(df: DataFrame, media_column: str = "media") -> DataFrame:
    """A row for each page of each row's file: the other columns of ``df``, then the page's number from 0, shape, pixels and feature.

    A file that is null, empty, damaged or no TIFF gives one row with the reason as ``error`` and
    nulls; columns of ``df`` with the names of new ones are left out; no rows give no rows.
    """
    new = T._parse_datatype_string(PAGE_FIELDS)
    names = [c for c in df.columns if c != media_column and c not in new.fieldNames()]
    schema = T.StructType([*[df.schema[c] for c in names], *new.fields])
    columns = schema.fieldNames()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 512):
                part = batch.slice(a, 512)
                rows, index = [], []
                for i, data in enumerate(part.column(part.num_columns - 1).to_pylist()):
                    try:
                        if not data:
                            raise ValueError("no data")
                        found = [(k, p.width, p.height, p.samples, p.bits, p.sample_format, p.compression, p.predictor, p.pixels, feature(p), None) for k, p in enumerate(read_pages(data))]
                    except ValueError as e:
                        found = [(*[None] * 10, str(e))]
                    rows += found
                    index += [i] * len(found)
                kept = part.take(pa.array(index, pa.int64())).columns[:-1]
                types = [*[pa.int32()] * 8, pa.binary(), pa.string(), pa.string()]
                yield pa.RecordBatch.from_arrays([*kept, *[pa.array([r[j] for r in rows], t) for j, t in enumerate(types)]], names=columns)

    return df.select(*[F.col(f"`{c}`") for c in names], F.col(f"`{media_column}`").alias("__media")).mapInArrow(run, schema)


#: How a payload may be stored: compression, predictor, tile (None: strips), byte order.
LAYOUTS = [(c, p, t, o) for c in (DEFLATE, LZW, PACKBITS, PLAIN) for p in (1, 2) for t in (None, (192, 16)) for o in "<>"]


def layout_of(payload: bytes) -> tuple:
    """One of LAYOUTS, by the payload's CRC: equal payloads are stored alike."""
    return LAYOUTS[zlib.crc32(payload) % len(LAYOUTS)]


def store_text(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", row_bytes: int = 576) -> DataFrame:
    """(id, n_bytes, media): a text's UTF-8, filled with 255 to whole rows (one at least), as a one-page 8-bit file.

    All compressions, predictors, strips and tiles and both byte orders are used, one picked by a
    hash of the payload.  A null text is an empty one; repeated rows are stored as often as they come.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 512):
                part = batch.slice(a, 512)
                texts = [t or b"" for t in part.column(1).cast(pa.binary()).to_pylist()]
                files = []
                for t in texts:
                    rows = max(1, -(-len(t) // row_bytes))
                    payload = t.ljust(rows * row_bytes, b"\xff")
                    compression, predictor, tile, order = layout_of(payload)
                    files.append(write_pages([np.frombuffer(payload, np.uint8).reshape(rows, row_bytes, 1)], compression, predictor, tile, 57, order))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array(files, pa.binary())], names=["id", "n_bytes", "media"])

    kind = docs.schema[id_column].dataType.simpleString()
    return docs.select(F.col(f"`{id_column}`").alias("id"), F.col(f"`{text_column}`").cast("string").alias("text")).mapInArrow(run, f"id {kind}, n_bytes long, media binary")
