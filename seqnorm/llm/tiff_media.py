"""TIFF media columns: texts or pixels to TIFF files and back, one row for each page.

The reader walks the chain of image directories, decodes strips or tiles (none, PackBits, LZW or deflate),
undoes the horizontal predictor and gives one row per page.  The writer makes one page per payload.
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

from .common import ship

# Fixed values of the format: tags, and compression schemes.
WIDTH, HEIGHT, BITS, COMPRESSION, PHOTOMETRIC = 256, 257, 258, 259, 262
STRIP_OFFSETS, SAMPLES, ROWS_PER_STRIP, STRIP_COUNTS = 273, 277, 278, 279
PREDICTOR, TILE_WIDTH, TILE_HEIGHT, TILE_OFFSETS, TILE_COUNTS = 317, 322, 323, 324, 325
NONE, LZW, DEFLATE, PACKBITS, OLD_DEFLATE = 1, 5, 8, 32773, 32946
SIZES = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8, 6: 1, 7: 1, 8: 2, 9: 4, 10: 8, 11: 4, 12: 8}


class TiffError(ValueError):
    """The bytes are no TIFF file that this reader knows."""


def pack_bits(data: bytes) -> bytes:
    """PackBits: runs of three and more as (1 - n, byte), the rest as literals of up to 128 bytes."""
    samples, out, start = np.frombuffer(data, np.uint8), bytearray(), 0
    edges = np.concatenate([[0], np.flatnonzero(samples[1:] != samples[:-1]) + 1, [len(data)]]) if data else np.zeros(1, np.int64)
    long = np.flatnonzero(np.diff(edges) >= 3)

    def literal(upto: int) -> None:
        for at in range(start, upto, 128):
            piece = data[at : min(at + 128, upto)]
            out.append(len(piece) - 1)
            out.extend(piece)

    for begin, end in zip(edges[long].tolist(), edges[long + 1].tolist()):
        literal(begin)
        for at in range(begin, end, 128):
            n = min(128, end - at)
            out.append(257 - n if n > 1 else 0)
            out.append(data[at])
        start = end
    literal(len(data))
    return bytes(out)


def unpack_bits(data: bytes) -> bytes:
    out, i = bytearray(), 0
    while i < len(data):
        head = data[i]
        if head < 128:
            out += data[i + 1 : i + 2 + head]
            i += 2 + head
        elif head == 128:
            i += 1
        else:
            out += data[i + 1 : i + 2] * (257 - head)
            i += 2
    return bytes(out)


def lzw_pack(data: bytes) -> bytes:
    """LZW as TIFF has it: codes of 9 to 12 bits, most significant bit first, width raised one code early.

    A string in the table is known by the code of all but its last byte, and that byte."""
    out, held, bits = bytearray(), 256, 9
    width, code, table = 9, 258, {}
    word, top = -1, 1 << 9
    for b in data:
        if word < 0:
            word = b
            continue
        longer = table.get(word << 8 | b)
        if longer is not None:
            word = longer
            continue
        held, bits = held << width | word, bits + width
        table[word << 8 | b] = code
        code += 1
        if code == 4094:
            held, bits = held << width | 256, bits + width
            width, code, table, top = 9, 258, {}, 1 << 9
        elif code + 1 > top:
            width, top = width + 1, top << 1
        if bits >= 256:
            bits, rest = bits & 7, bits
            out += (held >> bits).to_bytes((rest - bits) // 8, "big")
            held &= (1 << bits) - 1
        word = b
    if word >= 0:
        held, bits = held << width | word, bits + width
        if code + 2 > top and width < 12:
            width += 1
    held, bits = held << width | 257, bits + width
    return bytes(out) + (held << -bits % 8).to_bytes(-(-bits // 8), "big")


def lzw_unpack(data: bytes) -> bytes:
    out: list[bytes] = []
    held = bits = at = 0
    width, first = 9, [bytes([b]) for b in range(256)] + [b"", b""]
    table, before = list(first), b""
    while True:
        while bits < width:
            if at >= len(data):
                return b"".join(out)
            held, bits, at = held << 8 | data[at], bits + 8, at + 1
        bits -= width
        code = held >> bits
        held &= (1 << bits) - 1
        if code == 257:
            return b"".join(out)
        if code == 256:
            width, table, before = 9, list(first), b""
            continue
        if not before:
            if code > 255:
                raise TiffError("LZW code before its entry")
            before = table[code]
            out.append(before)
            continue
        if code < len(table):
            word = table[code]
        elif code == len(table):
            word = before + before[:1]
        else:
            raise TiffError("LZW code before its entry")
        out.append(word)
        table.append(before + word[:1])
        if len(table) + 1 >= (1 << width) and width < 12:
            width += 1
        before = word


_PACK = {NONE: bytes, PACKBITS: pack_bits, LZW: lzw_pack, DEFLATE: lambda b: zlib.compress(b, 1)}
_UNPACK = {NONE: bytes, PACKBITS: unpack_bits, LZW: lzw_unpack, DEFLATE: zlib.decompress, OLD_DEFLATE: zlib.decompress}


def _differences(rows: np.ndarray, samples: int) -> np.ndarray:
    """rows (height, width * samples) of uint8: differences to the pixel on the left."""
    out = rows.copy()
    out[:, samples:] -= rows[:, :-samples]
    return out


def _sums(rows: np.ndarray, samples: int) -> np.ndarray:
    height, across = rows.shape
    return np.cumsum(rows.reshape(height, across // samples, samples), axis=1, dtype=np.uint8).reshape(height, across)


def write_tiff(
    pages: list[np.ndarray], compression: int = DEFLATE, predictor: bool = True, rows_per_strip: int = 256, tile: tuple[int, int] | None = None, order: str = "<"
) -> bytes:
    """A TIFF file of 8-bit pages (height, width) or (height, width, samples), in strips or in tiles (height, width)."""
    out = bytearray((b"II*\0" if order == "<" else b"MM\0*") + bytes(4))
    link = 4
    for page in pages:
        height, width, samples = (*page.shape, 1)[:3]
        flat = np.ascontiguousarray(page, dtype=np.uint8).reshape(height, width * samples)
        if tile:
            pieces = []
            for top in range(0, height, tile[0]):
                for left in range(0, width, tile[1]):
                    full = np.zeros((tile[0], tile[1] * samples), np.uint8)
                    part = flat[top : top + tile[0], left * samples : (left + tile[1]) * samples]
                    full[: part.shape[0], : part.shape[1]] = part
                    pieces.append(full)
        else:
            pieces = [flat[top : top + rows_per_strip] for top in range(0, height, rows_per_strip)]
        offsets, counts = [], []
        for piece in pieces:
            packed = _PACK[compression]((_differences(piece, samples) if predictor else piece).tobytes())
            offsets.append(len(out))
            counts.append(len(packed))
            out += packed
            if len(out) % 2:
                out.append(0)
        tags = {WIDTH: [width], HEIGHT: [height], BITS: [8] * samples, COMPRESSION: [compression], PHOTOMETRIC: [2 if samples >= 3 else 1], SAMPLES: [samples], PREDICTOR: [2 if predictor else 1]}
        tags |= {TILE_WIDTH: [tile[1]], TILE_HEIGHT: [tile[0]], TILE_OFFSETS: offsets, TILE_COUNTS: counts} if tile else {STRIP_OFFSETS: offsets, ROWS_PER_STRIP: [rows_per_strip], STRIP_COUNTS: counts}
        entries = []
        for tag, values in sorted(tags.items()):
            kind = "I" if tag in (WIDTH, HEIGHT, STRIP_OFFSETS, ROWS_PER_STRIP, STRIP_COUNTS, TILE_OFFSETS, TILE_COUNTS) else "H"
            raw = struct.pack(f"{order}{len(values)}{kind}", *values)
            if len(raw) > 4:
                place = struct.pack(f"{order}I", len(out))
                out += raw + bytes(len(raw) % 2)
            else:
                place = raw.ljust(4, b"\0")
            entries.append(struct.pack(f"{order}HHI", tag, 4 if kind == "I" else 3, len(values)) + place)
        struct.pack_into(f"{order}I", out, link, len(out))
        out += struct.pack(f"{order}H", len(entries)) + b"".join(entries)
        link = len(out)
        out += bytes(4)
    return bytes(out)


@dataclass
class Page:
    number: int
    width: int
    height: int
    samples: int
    compression: int
    pixels: bytes


def _directory(data: bytes, order: str, at: int) -> tuple[dict[int, tuple], int]:
    (count,) = struct.unpack_from(f"{order}H", data, at)
    tags: dict[int, tuple] = {}
    for k in range(count):
        tag, kind, n = struct.unpack_from(f"{order}HHI", data, at + 2 + 12 * k)
        place = at + 10 + 12 * k
        if SIZES.get(kind, 0) * n > 4:
            (place,) = struct.unpack_from(f"{order}I", data, place)
        if kind in (1, 3, 4):
            tags[tag] = struct.unpack_from(f"{order}{n}{ {1: 'B', 3: 'H', 4: 'I'}[kind] }", data, place)
    return tags, struct.unpack_from(f"{order}I", data, at + 2 + 12 * count)[0]


def read_tiff(data: bytes) -> Iterator[Page]:
    """The pages of a TIFF file of 8-bit samples in one plane."""
    order = {b"II*\0": "<", b"MM\0*": ">"}.get(data[:4])
    if order is None:
        raise TiffError("no TIFF header")
    try:
        (at,) = struct.unpack_from(f"{order}I", data, 4)
        seen: set[int] = set()
        while at and at not in seen:
            seen.add(at)
            tags, following = _directory(data, order, at)
            yield _page(data, tags, len(seen) - 1)
            at = following
    except (struct.error, KeyError, zlib.error, IndexError) as e:
        raise TiffError(str(e)) from e


def _page(data: bytes, tags: dict[int, tuple], number: int) -> Page:
    width, height, samples = tags[WIDTH][0], tags[HEIGHT][0], tags.get(SAMPLES, (1,))[0]
    compression, predictor = tags.get(COMPRESSION, (1,))[0], tags.get(PREDICTOR, (1,))[0]
    if set(tags.get(BITS, (1,))) != {8} or compression not in _UNPACK or predictor not in (1, 2):
        raise TiffError("only 8-bit samples and known compression")
    tiled = TILE_WIDTH in tags
    tall, wide = (tags[TILE_HEIGHT][0], tags[TILE_WIDTH][0]) if tiled else (tags.get(ROWS_PER_STRIP, (height,))[0], width)
    offsets, counts = (tags[TILE_OFFSETS], tags[TILE_COUNTS]) if tiled else (tags[STRIP_OFFSETS], tags[STRIP_COUNTS])
    across = -(-width // wide)
    out = np.zeros((height, width * samples), np.uint8)
    for k, (offset, count) in enumerate(zip(offsets, counts)):
        top, left = k // across * tall, k % across * wide
        rows = tall if tiled else min(tall, height - top)
        raw = np.frombuffer(_UNPACK[compression](data[offset : offset + count]), np.uint8)
        if raw.size < rows * wide * samples:
            raise TiffError("a strip or tile is short")
        piece = raw[: rows * wide * samples].reshape(rows, wide * samples)
        if predictor == 2:
            piece = _sums(piece, samples)
        into = out[top : top + rows, left * samples : (left + wide) * samples]
        into[:] = piece[: into.shape[0], : into.shape[1]]
    return Page(number, width, height, samples, compression, out.tobytes())


def read_pages(df: DataFrame, key: str = "doc_id", media: str = "media") -> DataFrame:
    """One row for each page of each TIFF file of a binary column: key, page, width, height, samples, compression, pixels, error.

    A null file gives no row; bytes that are no TIFF file, or a damaged one, give one row with page null and the
    reason in error, after the pages read before the damage.  Repeated rows are read each for itself."""
    ship(df.sparkSession)
    rows = df.select(F.col(key).cast("bigint").alias("key"), F.col(media).cast("binary").alias("media"))
    schema = pa.schema([("key", pa.int64()), ("page", pa.int64()), ("width", pa.int64()), ("height", pa.int64()), ("samples", pa.int64()), ("compression", pa.int64()), ("pixels", pa.binary()), ("error", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, data in zip(batch.column(0).to_pylist(), batch.column(1)):
                if not data.is_valid:
                    continue
                out = []
                try:
                    for p in read_tiff(data.as_py()):
                        out.append((k, p.number, p.width, p.height, p.samples, p.compression, p.pixels, None))
                except TiffError as e:
                    out.append((k, None, None, None, None, None, None, str(e)))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), schema.types)], schema=schema) if out else pa.RecordBatch.from_pylist([], schema)

    return rows.mapInArrow(run, "key bigint, page bigint, width bigint, height bigint, samples bigint, compression bigint, pixels binary, error string").withColumnRenamed("key", key)


ROW = 192


#: How payloads are stored.  The checksum of the bytes picks one, whatever their number.
SCHEMES = (
    {"compression": PACKBITS, "predictor": False, "rows_per_strip": 64},
    {"compression": LZW, "predictor": False},
    {"compression": DEFLATE, "predictor": True},
    {"compression": DEFLATE, "predictor": True, "tile": (256, 64)},
)


def scheme(payload: bytes) -> dict:
    """The scheme of a payload: equal bytes have equal schemes, and each scheme meets texts of every length."""
    return SCHEMES[zlib.crc32(payload) % len(SCHEMES)]


def store_text(text: str | None) -> tuple[int, bytes]:
    """(UTF-8 bytes, TIFF file): the bytes with spaces up to a positive multiple of 192, as a page 192 samples wide."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    payload = raw.ljust(max(ROW, -(-len(raw) // ROW) * ROW), b" ")
    return len(raw), write_tiff([np.frombuffer(payload, np.uint8).reshape(-1, ROW)], **scheme(payload))


def features(page: Page) -> str:
    """Size, mean, spread and the share of the commonest sample, in whole numbers."""
    counts = np.bincount(np.frombuffer(page.pixels, np.uint8), minlength=256)
    n, values = int(counts.sum()), np.arange(256)
    mean = int((counts * values).sum()) / n
    spread = (int((counts * values * values).sum()) / n - mean * mean) ** 0.5
    top = int(counts.argmax())
    return f"{page.width}x{page.height}x{page.samples} c{page.compression} mean {mean:.3f} sd {spread:.3f} top {top}:{counts[top] / n:.4f} used {int((counts > 0).sum())}"


DIGEST = "key bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string"


def text_media(df: DataFrame, key: str = "doc_id", text: str = "text", keep_media: bool = False) -> DataFrame:
    """Store each text as a one-page TIFF file, read the file back and describe what was read.

    Null and empty texts are one row of spaces.  Equal texts, repeated rows too, give equal values.  keep_media adds the
    files themselves as column media.  Other columns are not read, so their names may clash with the result's; an empty
    table gives an empty result; a very long text is one file of many strips or tiles.  One narrow pass: a batch of
    files at a time is in memory, nothing is shuffled."""
    ship(df.sparkSession)
    rows = df.select(F.col(key).cast("bigint").alias("key"), F.col(text).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1000):
                batch, out = whole.slice(at, 1000), []
                for k, t in zip(batch.column(0).to_pylist(), batch.column(1)):
                    n, media = store_text(t.as_py())
                    (page,) = read_tiff(media)
                    out.append((k, n, len(page.pixels), hashlib.sha256(page.pixels).hexdigest(), zlib.crc32(page.pixels[-16:]), len(media), hashlib.sha256(media).hexdigest(), features(page), media if keep_media else None))
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary()][: 8 + keep_media]
                names = ["key", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "media"][: 8 + keep_media]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names=names)

    return rows.mapInArrow(run, DIGEST + ", media binary" * keep_media).withColumnRenamed("key", key)
