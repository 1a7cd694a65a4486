"""TIFF columns: a decoder that gives one row per image directory, and an encoder.

The decoder follows the chain of directories in files of either byte order,
gathers strips or tiles, undoes no compression, PackBits, LZW or deflate and the
horizontal or floating-point predictor, and returns the samples in order. Every
file is handled alone inside Arrow batches, so nothing is shuffled.

Edge cases: null bytes give one row with ``error`` set and no page; a damaged file
gives the pages before the damage and one row with ``error``; directories that
point back end the walk with an error; a null text is an empty text; repeated
rows give repeated rows; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.llm.common import slices

# Fixed values of the file format.
WIDTH, HEIGHT, BITS, COMPRESSION, PHOTOMETRIC = 256, 257, 258, 259, 262
STRIP_OFFSETS, SAMPLES, ROWS_PER_STRIP, STRIP_COUNTS = 273, 277, 278, 279
PLANAR, PREDICTOR, TILE_WIDTH, TILE_HEIGHT, TILE_OFFSETS, TILE_COUNTS, SAMPLE_FORMAT = 284, 317, 322, 323, 324, 325, 339
NONE, LZW, DEFLATE, OLD_DEFLATE, PACKBITS = 1, 5, 8, 32946, 32773
FIELD_SIZES = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8, 6: 1, 7: 1, 8: 2, 9: 4, 10: 8, 11: 4, 12: 8}
FIELD_CODES = {1: "B", 3: "H", 4: "I", 6: "b", 8: "h", 9: "i", 11: "f", 12: "d"}
LZW_CLEAR, LZW_END, LZW_MAX_BITS = 256, 257, 12

#: Directories followed in one file at most before the walk counts as endless.
MAX_PAGES = 1 << 16


def unpack_bits(data: bytes) -> bytes:
    out, at = bytearray(), 0
    while at < len(data):
        head, at = data[at], at + 1
        if head < 128:
            out += data[at : at + head + 1]
            at += head + 1
        elif head > 128:
            out += data[at : at + 1] * (257 - head)
            at += 1
    return bytes(out)


def pack_bits(data: bytes) -> bytes:
    out, at = bytearray(), 0
    while at < len(data):
        run = 1
        while run < 128 and at + run < len(data) and data[at + run] == data[at]:
            run += 1
        if run > 1:
            out += bytes([257 - run, data[at]])
            at += run
            continue
        start = at
        while at < len(data) and at - start < 128 and (at + 1 >= len(data) or data[at] != data[at + 1]):
            at += 1
        out += bytes([at - start - 1]) + data[start:at]
    return bytes(out)


def lzw_decode(data: bytes) -> bytes:
    singles = [bytes([i]) for i in range(256)] + [b"", b""]
    table, out, last, width, bits, held = singles[:], [], b"", 9, 0, 0
    for byte in data:
        held, bits = held << 8 | byte, bits + 8
        if bits < width:
            continue
        bits -= width
        code, held = held >> bits, held & ((1 << bits) - 1)
        if code == LZW_END:
            break
        if code == LZW_CLEAR:
            table, last, width = singles[:], b"", 9
            continue
        if code > len(table) or code == len(table) and not last:
            raise ValueError("LZW code out of range")
        entry = table[code] if code < len(table) else last + last[:1]
        out.append(entry)
        if last:
            table.append(last + entry[:1])
        last = entry
        if len(table) + 1 >= 1 << width and width < LZW_MAX_BITS:  # the width grows one code early
            width += 1
    return b"".join(out)


def lzw_encode(data: bytes) -> bytes:
    held = bits = 0
    out = bytearray()
    table: dict[bytes, int] = {}
    width, following = 9, LZW_END + 1

    def put(code: int) -> None:
        nonlocal held, bits
        held, bits = held << width | code, bits + width
        while bits >= 8:
            bits -= 8
            out.append(held >> bits & 255)
            held &= (1 << bits) - 1

    def code_of(s: bytes) -> int:
        return s[0] if len(s) == 1 else table[s]

    put(LZW_CLEAR)
    prefix = b""
    for i in range(len(data)):
        longer = prefix + data[i : i + 1]
        if len(longer) == 1 or longer in table:
            prefix = longer
            continue
        put(code_of(prefix))
        table[longer] = following
        following += 1
        if following == (1 << LZW_MAX_BITS) - 1:
            put(LZW_CLEAR)
            table, width, following = {}, 9, LZW_END + 1
        elif following + 1 > 1 << width:
            width += 1
        prefix = data[i : i + 1]
    if prefix:
        put(code_of(prefix))
        following += 1
        if following + 1 > 1 << width and width < LZW_MAX_BITS:
            width += 1
    put(LZW_END)
    if bits:
        out.append(held << (8 - bits) & 255)
    return bytes(out)


def _inflate(data: bytes, compression: int) -> bytes:
    if compression == NONE:
        return data
    if compression == PACKBITS:
        return unpack_bits(data)
    if compression == LZW:
        return lzw_decode(data)
    if compression in (DEFLATE, OLD_DEFLATE):
        return zlib.decompress(data)
    raise ValueError(f"compression {compression} is not supported")


def _undo_predictor(raw: bytes, rows: int, cols: int, depth: int, dtype: np.dtype, predictor: int) -> np.ndarray:
    """Samples (rows, cols, depth) of a decoded strip or tile."""
    if predictor == 3:  # bytes of each row lie by significance, each the difference to the one before
        size = dtype.itemsize
        planes = np.frombuffer(raw, np.uint8, rows * cols * depth * size).reshape(rows, cols * size, depth)
        planes = np.cumsum(planes, axis=1, dtype=np.uint8).reshape(rows, size, cols * depth)
        return np.ascontiguousarray(planes.transpose(0, 2, 1)).view(dtype.newbyteorder(">")).reshape(rows, cols, depth)
    samples = np.frombuffer(raw, dtype, rows * cols * depth).reshape(rows, cols, depth)
    if predictor == 2:
        whole = np.dtype(f"u{dtype.itemsize}")
        return np.cumsum(samples.view(dtype.newbyteorder("=")) if dtype.isnative else samples.astype(dtype.newbyteorder("=")), axis=1, dtype=whole).view(dtype.newbyteorder("="))
    if predictor != 1:
        raise ValueError(f"predictor {predictor} is not supported")
    return samples


def _directories(data: bytes) -> Iterator[dict[int, tuple]]:
    if data[:4] not in (b"II*\0", b"MM\0*"):
        raise ValueError("no TIFF header")
    order = "<" if data[:2] == b"II" else ">"
    (at,), seen = struct.unpack_from(order + "I", data, 4), set()
    while at:
        if at in seen or len(seen) >= MAX_PAGES:
            raise ValueError("the directories form a loop")
        seen.add(at)
        (n,), tags = struct.unpack_from(order + "H", data, at), {}
        for i in range(n):
            tag, kind, count = struct.unpack_from(order + "HHI", data, at + 2 + 12 * i)
            if kind not in FIELD_CODES:
                continue
            place = at + 10 + 12 * i
            if FIELD_SIZES[kind] * count > 4:
                (place,) = struct.unpack_from(order + "I", data, place)
            tags[tag] = struct.unpack_from(f"{order}{count}{FIELD_CODES[kind]}", data, place)
        yield {0: (order,)} | tags
        (at,) = struct.unpack_from(order + "I", data, at + 2 + 12 * n)


def _pixels(data: bytes, tags: dict[int, tuple]) -> np.ndarray:
    one = lambda tag, default: tags.get(tag, (default,))[0]
    width, height, depth = tags[WIDTH][0], tags[HEIGHT][0], one(SAMPLES, 1)
    bits, kind, predictor = one(BITS, 1), {1: "u", 2: "i", 3: "f", 4: "u"}[one(SAMPLE_FORMAT, 1)], one(PREDICTOR, 1)
    if len(set(tags.get(BITS, (1,)))) > 1:
        raise ValueError("samples of unlike width are not supported")
    separate = one(PLANAR, 1) == 2 and depth > 1
    tiled = TILE_OFFSETS in tags
    across, down = (tags[TILE_WIDTH][0], tags[TILE_HEIGHT][0]) if tiled else (width, min(one(ROWS_PER_STRIP, height), height))
    offsets, counts = (tags[TILE_OFFSETS], tags[TILE_COUNTS]) if tiled else (tags[STRIP_OFFSETS], tags[STRIP_COUNTS])
    if min(width, height, across, down) < 1:
        raise ValueError("empty image")
    per_row, per_col = -(-width // across), -(-height // down)
    planes, inner = (depth, 1) if separate else (1, depth)
    if len(offsets) < planes * per_row * per_col or len(counts) < len(offsets):
        raise ValueError("strips or tiles are missing")
    packed = bits < 8
    dtype = np.dtype("u1" if packed else f"{tags[0][0]}{kind}{bits // 8}")
    out = np.zeros((planes, height, width, inner), dtype.newbyteorder("="))
    for k in range(planes * per_row * per_col):
        plane, y, x = k // (per_row * per_col), k // per_row % per_col * down, k % per_row * across
        rows = down if tiled else min(down, height - y)
        raw = _inflate(data[offsets[k] : offsets[k] + counts[k]], one(COMPRESSION, 1))
        if packed:
            stride = -(-across * inner * bits // 8)
            unit = np.unpackbits(np.frombuffer(raw, np.uint8, rows * stride).reshape(rows, stride), axis=1)[:, : across * inner * bits]
            block = (unit.reshape(rows, across * inner, bits) @ (1 << np.arange(bits - 1, -1, -1))).astype(np.uint8).reshape(rows, across, inner)
        else:
            block = _undo_predictor(raw, rows, across, inner, dtype, predictor)
        out[plane, y : y + rows, x : x + across] = block[: height - y, : width - x]
    return np.concatenate(list(out), axis=2) if separate else out[0]


def decode(data: bytes) -> Iterator[tuple[dict[int, tuple], np.ndarray]]:
    """(tags, samples of shape height x width x depth) of each directory."""
    for tags in _directories(data):
        yield tags, _pixels(data, tags)


def _apply_predictor(block: np.ndarray, predictor: int) -> bytes:
    if predictor == 2:
        whole = block.view(f"u{block.dtype.itemsize}")
        return np.diff(whole, axis=1, prepend=np.zeros_like(whole[:, :1])).tobytes()
    if predictor == 3:
        rows, cols, depth = block.shape
        planes = block.astype(block.dtype.newbyteorder(">")).view(np.uint8).reshape(rows, cols * depth, block.dtype.itemsize).transpose(0, 2, 1).reshape(rows, -1, depth)
        return np.diff(planes, axis=1, prepend=np.zeros_like(planes[:, :1])).tobytes()
    return block.tobytes()


def encode(pages: list[np.ndarray], compression: int = DEFLATE, predictor: int = 2, rows_per_strip: int = 113, tile: tuple[int, int] | None = None) -> bytes:
    """A little-endian file with one directory for each (height, width, depth) array."""
    deflate = {NONE: bytes, PACKBITS: pack_bits, LZW: lzw_encode, DEFLATE: lambda b: zlib.compress(b, 1)}[compression]
    out, link = bytearray(b"II*\0\0\0\0\0"), 4
    for page in pages:
        height, width, depth = page.shape
        down, across = tile or (min(rows_per_strip, height), width)
        offsets, counts = [], []
        for y in range(0, height, down):
            for x in range(0, width, across):
                block = page[y : y + down, x : x + across]
                if tile:
                    block = np.pad(block, ((0, down - block.shape[0]), (0, across - block.shape[1]), (0, 0)))
                stored = deflate(_apply_predictor(np.ascontiguousarray(block), predictor))
                offsets.append(len(out))
                counts.append(len(stored))
                out += stored + b"\0" * (len(stored) & 1)
        kind = {"u": 1, "i": 2, "f": 3}[page.dtype.kind]
        tags = {WIDTH: (4, [width]), HEIGHT: (4, [height]), BITS: (3, [8 * page.dtype.itemsize] * depth), COMPRESSION: (3, [compression]), PHOTOMETRIC: (3, [2 if depth == 3 else 1]), SAMPLES: (3, [depth]), PREDICTOR: (3, [predictor]), SAMPLE_FORMAT: (3, [kind] * depth)}
        if tile:
            tags |= {TILE_WIDTH: (4, [across]), TILE_HEIGHT: (4, [down]), TILE_OFFSETS: (4, offsets), TILE_COUNTS: (4, counts)}
        else:
            tags |= {STRIP_OFFSETS: (4, offsets), ROWS_PER_STRIP: (4, [down]), STRIP_COUNTS: (4, counts)}
        entries = b""
        for tag, (field, values) in sorted(tags.items()):
            body = struct.pack(f"<{len(values)}{FIELD_CODES[field]}", *values)
            if len(body) > 4:
                place = struct.pack("<I", len(out))
                out += body + b"\0" * (len(body) & 1)
            else:
                place = body.ljust(4, b"\0")
            entries += struct.pack("<HHI", tag, field, len(values)) + place
        struct.pack_into("<I", out, link, len(out))
        out += struct.pack("<H", len(tags)) + entries
        link = len(out)
        out += b"\0\0\0\0"
    return bytes(out)


def pages(media: DataFrame, id_col: str, media_col: str = "media") -> DataFrame:
    """One row per page: id, page, width, height, depth, dtype, compression, predictor, pixels, error."""
    kind = media.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "media", 1 << 20):
            rows: list[tuple] = []
            for key, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                n = 0
                try:
                    if data is None:
                        raise ValueError("no bytes")
                    for tags, samples in decode(data):
                        rows.append((key, n, samples.shape[1], samples.shape[0], samples.shape[2], samples.dtype.str, tags.get(COMPRESSION, (1,))[0], tags.get(PREDICTOR, (1,))[0], samples.tobytes(), None))
                        n += 1
                except (ValueError, KeyError, IndexError, struct.error, zlib.error) as e:
                    rows.append((key, None, None, None, None, None, None, None, None, str(e)))
            fields = [batch.schema.field(0).type, *[pa.int32()] * 4, pa.string(), pa.int32(), pa.int32(), pa.binary(), pa.string()]
            names = ["id", "page", "width", "height", "depth", "dtype", "compression", "predictor", "pixels", "error"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 10, fields)], names=names)

    schema = f"id {kind}, page int, width int, height int, depth int, dtype string, compression int, predictor int, pixels binary, error string"
    return media.select(F.col(id_col).alias("id"), F.col(media_col).alias("media")).mapInArrow(run, schema).withColumnRenamed("id", id_col)


#: Payloads are padded to whole rows; a page holds at most so many of them.
ROW, PAGE_ROWS = 576, 4096


def text_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each text as a TIFF of 8-bit samples: (id, n_bytes, media)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            sizes, media = [], []
            for text in batch.column(1).to_pylist():
                payload = (text or "").encode("utf-8", "surrogatepass")
                sizes.append(len(payload))
                rows = max(1, -(-len(payload) // ROW))
                grid = np.frombuffer(payload.ljust(rows * ROW, b"\xff"), np.uint8).reshape(rows, ROW, 1)
                media.append(encode([grid[y : y + PAGE_ROWS] for y in range(0, rows, PAGE_ROWS)]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(media, pa.binary())], names=["id", "n_bytes", "media"])

    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return source.mapInArrow(run, f"id {source.schema['id'].dataType.simpleString()}, n_bytes long, media binary").withColumnRenamed("id", id_col)


def digests(media: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Decode every file and summarise its samples: the digest columns of op7."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "media"):
            rows = []
            for key, n, data in zip(*(batch.column(i).to_pylist() for i in range(3))):
                found = [samples for _, samples in decode(data)]
                payload = b"".join(x.tobytes() for x in found)
                counts = np.bincount(np.frombuffer(payload, np.uint8), minlength=256)
                parts = [len(found), sum(x.shape[0] for x in found), int(counts @ np.arange(256)), int((counts > 0).sum()), *counts.reshape(8, 32).sum(axis=1).tolist()]
                rows.append((key, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(data), hashlib.sha256(data).hexdigest(), ":".join(map(str, parts))))
            fields = [batch.schema.field(0).type, pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            names = ["id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 8, fields)], names=names)

    kind = media.schema[id_col].dataType.simpleString()
    return media.select(F.col(id_col).alias("id"), "n_bytes", "media").mapInArrow(run, f"id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string").withColumnRenamed("id", id_col)


def op7_tiff(spark, sf_dir: str) -> DataFrame:
    return digests(text_media(spark.read.parquet(f"{sf_dir}/documents.parquet")))
