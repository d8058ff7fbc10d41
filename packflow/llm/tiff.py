"""TIFF media columns: write byte payloads as grey 8-bit images, walk image directories, decode
PackBits, LZW and deflate strips or tiles, undo predictors, and emit one row per page.

Results for odd input: a null media value gives no page, and a digest row of nulls; bytes that are no TIFF
give one row with ``page`` -1 and the reason in ``error``; a page that cannot be decoded, whatever is damaged
in it, gives a row with its number and the reason. A page that declares more samples than its bytes could
hold in any of the compressions is refused before memory is taken for it.
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

from packflow.llm.common import sliced, text_bytes

# Fixed values of the TIFF 6.0 format: tag numbers, field sizes, compression codes.
WIDTH, LENGTH, BITS, COMPRESSION, PHOTOMETRIC = 256, 257, 258, 259, 262
STRIP_OFFSETS, SAMPLES, ROWS_PER_STRIP, STRIP_BYTES, PLANAR, PREDICTOR = 273, 277, 278, 279, 284, 317
TILE_WIDTH, TILE_LENGTH, TILE_OFFSETS, TILE_BYTES = 322, 323, 324, 325
FIELD_SIZE = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8, 6: 1, 7: 1, 8: 2, 9: 4, 10: 8, 11: 4, 12: 8, 13: 4}
FIELD_CODE = {1: "B", 3: "H", 4: "I", 6: "b", 8: "h", 9: "i", 13: "I"}
NONE, LZW, DEFLATE, PACKBITS, OLD_DEFLATE = 1, 5, 8, 32773, 32946
LZW_CLEAR, LZW_END, LZW_MAX_BITS = 256, 257, 12


#: No compression makes more samples of a byte (deflate's 1,032 is the most).
MOST_SAMPLES = 1100


class TiffError(ValueError):
    pass


#: What reading damaged bytes may raise.
DAMAGE = (ArithmeticError, LookupError, MemoryError, ValueError, zlib.error, struct.error)


def packbits_encode(data: bytes) -> bytes:
    """Runs of three or more equal bytes as repeats, the rest as literals of at most 128 bytes."""
    if not data:
        return b""
    a = np.frombuffer(data, np.uint8)
    cuts = np.flatnonzero(np.diff(a)) + 1
    starts = np.concatenate(([0], cuts)).tolist()
    ends = np.concatenate((cuts, [len(a)])).tolist()
    out, held = bytearray(), 0  # literal bytes from ``held`` on wait
    for start, end in zip(starts, ends, strict=True):
        if end - start < 3:
            continue
        for k in range(held, start, 128):
            piece = data[k : min(k + 128, start)]
            out += bytes((len(piece) - 1,)) + piece
        for k in range(start, end, 128):
            n = min(128, end - k)
            out += bytes(((257 - n) & 255 if n > 1 else 0, data[k]))
        held = end
    for k in range(held, len(data), 128):
        piece = data[k : k + 128]
        out += bytes((len(piece) - 1,)) + piece
    return bytes(out)


def packbits_decode(data: bytes, expected: int) -> bytes:
    out, at = bytearray(), 0
    while at < len(data) and len(out) < expected:
        head = data[at]
        if head < 128:
            out += data[at + 1 : at + 2 + head]
            at += head + 2
        elif head > 128:
            out += data[at + 1 : at + 2] * (257 - head)
            at += 2
        else:
            at += 1
    return bytes(out)


def lzw_encode(data: bytes) -> bytes:
    """Most significant bit first; the code width grows one code early, as TIFF has it."""
    total = bits = 0
    out, width, table = bytearray(), 9, {}

    def put(code: int) -> None:
        nonlocal total, bits
        total, bits = (total << width) | code, bits + width
        while bits >= 8:
            bits -= 8
            out.append(total >> bits & 255)
        total &= (1 << bits) - 1

    put(LZW_CLEAR)
    prefix, free = -1, 258
    for byte in data:
        if prefix < 0:
            prefix = byte
            continue
        key = prefix << 8 | byte
        if key in table:
            prefix = table[key]
            continue
        put(prefix)
        table[key] = free
        free += 1
        if free == 4095:
            put(LZW_CLEAR)
            table, free, width = {}, 258, 9
        elif free >= 1 << width and width < LZW_MAX_BITS:
            width += 1
        prefix = byte
    if prefix >= 0:
        put(prefix)
        if free + 1 >= 1 << width and width < LZW_MAX_BITS:
            width += 1
    put(LZW_END)
    if bits:
        out.append(total << (8 - bits) & 255)
    return bytes(out)


def lzw_decode(data: bytes) -> bytes:
    base = [bytes((i,)) for i in range(256)] + [b"", b""]
    table, width, total, bits, previous, out = list(base), 9, 0, 0, None, bytearray()
    for byte in data:
        total, bits = (total << 8) | byte, bits + 8
        if bits < width:
            continue
        bits -= width
        code = total >> bits
        total &= (1 << bits) - 1
        if code == LZW_END:
            break
        if code == LZW_CLEAR:
            table, width, previous = list(base), 9, None
            continue
        if previous is None:
            if code >= len(table):
                raise TiffError("LZW code out of range")
            entry = table[code]
        else:
            if code < len(table):
                entry = table[code]
            elif code == len(table):
                entry = previous + previous[:1]
            else:
                raise TiffError("LZW code out of range")
            table.append(previous + entry[:1])
            if len(table) >= (1 << width) - 1 and width < LZW_MAX_BITS:
                width += 1
        out += entry
        previous = entry
    return bytes(out)


def encode_segment(rows: np.ndarray, compression: int, predictor: int) -> bytes:
    if predictor == 2:
        rows = np.concatenate((rows[:, :1], np.diff(rows, axis=1)), axis=1)
    raw = rows.astype(np.uint8).tobytes()
    if compression == DEFLATE:
        return zlib.compress(raw, 1)
    if compression == LZW:
        return lzw_encode(raw)
    return packbits_encode(raw) if compression == PACKBITS else raw


def decode_segment(data: bytes, compression: int, expected: int) -> bytes:
    if compression in (DEFLATE, OLD_DEFLATE):
        return zlib.decompressobj().decompress(data, max(1, expected))
    if compression == LZW:
        return lzw_decode(data)
    if compression == PACKBITS:
        return packbits_decode(data, expected)
    if compression == NONE:
        return data
    raise TiffError(f"compression {compression} is not known")


def encode_tiff(
    payload: bytes, width: int = 64, compression: int | None = None, predictor: int | None = None,
    strip_rows: int = 512, page_rows: int = 1 << 16, tile: int = 0,
) -> bytes:
    """A little-endian TIFF whose pages hold the payload's bytes row by row.

    ``len(payload)`` must be a positive multiple of ``width``. Unless it is given, the compression
    is PackBits for pages that are one repeated byte and deflate else. ``tile`` > 0 writes square
    tiles of that size (padded, as the format asks) in place of strips.
    """
    if not payload or len(payload) % width:
        raise TiffError("the payload must be a positive multiple of the width")
    image = np.frombuffer(payload, np.uint8).reshape(-1, width)
    out, previous = bytearray(b"II*\0\0\0\0\0"), 4
    for top in range(0, len(image), page_rows):
        page = image[top : top + page_rows]
        flat = bool((page == page[0, 0]).all())
        how = compression if compression is not None else PACKBITS if flat else DEFLATE
        diff = predictor if predictor is not None else 2 if how in (LZW, DEFLATE) else 1
        if tile:
            high, wide = -(-len(page) // tile) * tile, -(-width // tile) * tile
            padded = np.zeros((high, wide), np.uint8)
            padded[: len(page), :width] = page
            parts = [padded[y : y + tile, x : x + tile] for y in range(0, high, tile) for x in range(0, wide, tile)]
        else:
            parts = [page[y : y + strip_rows] for y in range(0, len(page), strip_rows)]
        offsets, sizes = [], []
        for part in parts:
            data = encode_segment(part, how, diff)
            offsets.append(len(out))
            sizes.append(len(data))
            out += data + b"\0" * (len(data) & 1)
        lists = []
        for values in (offsets, sizes):
            lists.append(len(out) if len(values) > 1 else values[0])
            if len(values) > 1:
                out += struct.pack(f"<{len(values)}I", *values)
        n = len(parts)
        fields = {WIDTH: (4, 1, width), LENGTH: (4, 1, len(page)), BITS: (3, 1, 8), COMPRESSION: (3, 1, how), PHOTOMETRIC: (3, 1, 1), SAMPLES: (3, 1, 1), PREDICTOR: (3, 1, diff)}
        if tile:
            fields |= {TILE_WIDTH: (4, 1, tile), TILE_LENGTH: (4, 1, tile), TILE_OFFSETS: (4, n, lists[0]), TILE_BYTES: (4, n, lists[1])}
        else:
            fields |= {STRIP_OFFSETS: (4, n, lists[0]), ROWS_PER_STRIP: (4, 1, strip_rows), STRIP_BYTES: (4, n, lists[1])}
        struct.pack_into("<I", out, previous, len(out))
        out += struct.pack("<H", len(fields))
        for tag in sorted(fields):
            out += struct.pack("<HHII", tag, *fields[tag])
        previous = len(out)
        out += b"\0\0\0\0"
    return bytes(out)


@dataclass
class Page:
    number: int
    width: int
    height: int
    compression: int
    samples: np.ndarray  # height x width x samples per pixel


def directories(media: bytes) -> Iterator[dict[int, list[int]]]:
    """Tags of each image directory, in order; a loop in the chain ends the walk."""
    order = {b"II": "<", b"MM": ">"}.get(media[:2])
    if order is None or len(media) < 8 or struct.unpack(order + "H", media[2:4])[0] != 42:
        raise TiffError("no TIFF header")
    at, seen = struct.unpack(order + "I", media[4:8])[0], set()
    while at and at not in seen:
        seen.add(at)
        if at + 2 > len(media):
            raise TiffError("directory beyond the end")
        count, tags = struct.unpack_from(order + "H", media, at)[0], {}
        if at + 2 + 12 * count + 4 > len(media):
            raise TiffError("a directory reaches beyond the end")
        for k in range(count):
            tag, kind, n = struct.unpack_from(order + "HHI", media, at + 2 + 12 * k)
            if kind not in FIELD_CODE:
                continue
            where = at + 2 + 12 * k + 8
            if n * FIELD_SIZE[kind] > 4:
                where = struct.unpack_from(order + "I", media, where)[0]
            if where + n * FIELD_SIZE[kind] > len(media):
                raise TiffError("a field reaches beyond the end")
            tags[tag] = list(struct.unpack_from(f"{order}{n}{FIELD_CODE[kind]}", media, where))
        yield tags
        at = struct.unpack_from(order + "I", media, at + 2 + 12 * count)[0]


def read_page(media: bytes, tags: dict[int, list[int]], number: int) -> Page:
    one = lambda tag, default: tags.get(tag, [default])[0]
    width, height, depth = one(WIDTH, 0), one(LENGTH, 0), one(SAMPLES, 1)
    if set(tags.get(BITS, [8])) != {8} or one(PLANAR, 1) != 1:
        raise TiffError("only chunky 8-bit samples are read")
    if min(width, height, depth) < 1:
        raise TiffError("a page without samples")
    if width * height * depth > MOST_SAMPLES * len(media):
        raise TiffError("more samples are declared than the bytes can hold")
    tiled = TILE_OFFSETS in tags
    wide = one(TILE_WIDTH, width) if tiled else width
    high = one(TILE_LENGTH, height) if tiled else min(one(ROWS_PER_STRIP, height) or height, height)
    offsets, sizes = (tags[t] for t in ((TILE_OFFSETS, TILE_BYTES) if tiled else (STRIP_OFFSETS, STRIP_BYTES)))
    if min(wide, high) < 1 or wide > 1 << 16 and tiled or wide * high * depth > MOST_SAMPLES * max(len(media), 64):
        raise TiffError("impossible strips or tiles")
    across, down = -(-width // wide), -(-height // high)
    if len(offsets) != len(sizes) or len(offsets) < across * down:
        raise TiffError("strips or tiles are missing")
    image = np.zeros((height, width, depth), np.uint8)
    for k, (offset, n) in enumerate(zip(offsets[: across * down], sizes, strict=False)):
        y, x = k // across * high, k % across * wide
        rows = high if tiled else min(high, height - y)
        raw = decode_segment(media[offset : offset + n], one(COMPRESSION, 1), rows * wide * depth)
        if len(raw) < rows * wide * depth:
            raise TiffError("a strip or tile is too short")
        part = np.frombuffer(raw, np.uint8, rows * wide * depth).reshape(rows, wide, depth)
        if one(PREDICTOR, 1) == 2:
            part = np.cumsum(part, axis=1, dtype=np.uint8)
        image[y : y + rows, x : x + wide] = part[: height - y, : width - x]
    return Page(number, width, height, one(COMPRESSION, 1), image)


def read_pages(media: bytes) -> Iterator[Page]:
    for number, tags in enumerate(directories(media)):
        yield read_page(media, tags, number)


def average_hash(image: np.ndarray) -> str:
    """64 bits: an 8 x 8 grid of block means against their mean, row by row, as hex."""
    flat = image.reshape(image.shape[0], -1)
    rows = np.add.reduceat(flat, np.arange(8) * len(flat) // 8, axis=0, dtype=np.int64) if len(flat) >= 8 else np.repeat(flat, 8, axis=0)[: 8 * len(flat)].reshape(8, len(flat), -1).sum(1, dtype=np.int64)
    grid = np.add.reduceat(rows, np.arange(8) * rows.shape[1] // 8, axis=1) if rows.shape[1] >= 8 else rows[:, np.arange(8) * rows.shape[1] // 8]
    return np.packbits((grid * grid.size > grid.sum()).ravel()).tobytes().hex()


PAGE_SCHEMA = "page int, width int, height int, compression int, samples binary, feature string, error string"


def tiff_pages(df: DataFrame, id_col: str, media_col: str, with_samples: bool = True) -> DataFrame:
    """One row per page of each media value, with its samples, hash and any error."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches):
        for batch in sliced(batches, "__media", 32 << 20):
            rows = []
            for key, media in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if media is None:
                    continue
                try:
                    for number, tags in enumerate(directories(media)):
                        try:
                            p = read_page(media, tags, number)
                            rows.append((key, number, p.width, p.height, p.compression, p.samples.tobytes() if with_samples else None, average_hash(p.samples), None))
                        except DAMAGE as e:
                            rows.append((key, number, None, None, None, None, None, f"{type(e).__name__}: {e}"))
                except DAMAGE as e:
                    rows.append((key, -1, None, None, None, None, None, f"{type(e).__name__}: {e}"))
            types = [batch.schema.field(0).type, pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.string(), pa.string()]
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 8
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=names)

    names = [id_col, "page", "width", "height", "compression", "samples", "feature", "error"]
    narrow = df.selectExpr(f"`{id_col}`", f"`{media_col}` as __media")
    return narrow.mapInArrow(run, f"`{id_col}` {kind}, {PAGE_SCHEMA}")


def padded_payload(text: bytes, unit: int = 64) -> bytes:
    """The text with zero bytes up to a positive multiple of ``unit``."""
    return text + b"\0" * (-len(text) % unit or (0 if text else unit))


def texts_to_tiff(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, media): each text, null as empty, as the samples of a TIFF."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches):
        for batch in sliced(batches, "__text", 32 << 20):
            texts = text_bytes(batch.column(1))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array([encode_tiff(padded_payload(t)) for t in texts], pa.binary())],
                names=[id_col, "n_bytes", "media"],
            )

    return df.selectExpr(f"`{id_col}`", f"cast(`{text_col}` as string) as __text").mapInArrow(run, f"`{id_col}` {kind}, n_bytes long, media binary")


def media_digest(media: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Per media row: digests of the payload read back from all its pages and of the stored bytes."""
    kind = media.schema[id_col].dataType.simpleString()
    names = [id_col, "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "n_pages"]

    def run(batches):
        for batch in sliced(batches, "media", 32 << 20):
            rows = []
            for m in batch.column(2).to_pylist():
                if m is None:
                    rows.append((None,) * 7)
                    continue
                payload, hashes = [], []
                for page in read_pages(m):
                    payload.append(page.samples.tobytes())
                    hashes.append(average_hash(page.samples))
                p = b"".join(payload)
                rows.append((len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]), len(m), hashlib.sha256(m).hexdigest(), "-".join(hashes), len(hashes)))
            types = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True))], names=names)

    return media.select(id_col, "n_bytes", "media").mapInArrow(run, f"`{id_col}` {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_pages int")
