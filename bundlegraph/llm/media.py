"""Media columns: TIFF images in a binary column, one row for each page.

The reader walks the chain of image directories in either byte order, takes strips or tiles,
decodes plain, PackBits, LZW or deflate data, undoes the horizontal predictor, and gives 8-bit
samples. The writer makes the same variants, so that each is tested by a round trip.

Nulls: a null image has no pages; a null text is an empty payload. Damaged images raise, unless
`keep_bad`, which gives one row with page -1 and no samples. Repeated rows give repeated rows,
empty tables none, other columns are ignored. The format's offsets have 32 bits, so an image of 4 GiB
or more raises; a text is held whole, with its pages, while its image is made or read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

# fixed values of the format: tags, compressions, type sizes
WIDTH, HEIGHT, BITS, COMPRESSION, PHOTOMETRIC, STRIP_AT, SAMPLES, STRIP_ROWS, STRIP_BYTES, PREDICTOR, TILE_W, TILE_H, TILE_AT, TILE_BYTES = 256, 257, 258, 259, 262, 273, 277, 278, 279, 317, 322, 323, 324, 325
PLAIN, LZW, DEFLATE, PACKBITS, OLD_DEFLATE = 1, 5, 8, 32773, 32946
TYPE_BYTES = {1: 1, 2: 1, 3: 2, 4: 4, 16: 8}
TYPE_CODE = {1: "B", 2: "B", 3: "H", 4: "I", 16: "Q"}


def packbits_encode(data: bytes) -> bytes:
    out, i, n = bytearray(), 0, len(data)
    lit = 0
    while i < n:
        run = 1
        while run < 128 and i + run < n and data[i + run] == data[i]:
            run += 1
        if run >= 3 or (run == 2 and lit == i):
            while lit < i:
                k = min(128, i - lit)
                out += bytes([k - 1]) + data[lit : lit + k]
                lit += k
            out += bytes([257 - run, data[i]])
            i += run
            lit = i
        else:
            i += run
    while lit < n:
        k = min(128, n - lit)
        out += bytes([k - 1]) + data[lit : lit + k]
        lit += k
    return bytes(out)


def packbits_decode(data: bytes, size: int) -> bytes:
    out, i = bytearray(), 0
    while len(out) < size and i < len(data):
        k = data[i]
        if k < 128:
            out += data[i + 1 : i + 2 + k]
            i += k + 2
        elif k > 128:
            out += data[i + 1 : i + 2] * (257 - k)
            i += 2
        else:
            i += 1
    return bytes(out)


def lzw_encode(data: bytes) -> bytes:
    """Codes of 9 to 12 bits, most significant bit first, one code early; 256 clears, 257 ends."""
    out, room, held = bytearray(), 0, 0
    width, known, nxt = 9, {}, 258

    def put(code: int) -> None:
        nonlocal room, held
        room, held = (room << width) | code, held + width
        while held >= 8:
            held -= 8
            out.append((room >> held) & 255)
            room &= (1 << held) - 1

    put(256)
    cur = -1
    for b in data:
        if cur < 0:
            cur = b
            continue
        key = (cur << 8) | b
        if key in known:
            cur = known[key]
            continue
        put(cur)
        known[key] = nxt
        nxt += 1
        cur = b
        if nxt == 4094:
            put(256)
            width, known, nxt = 9, {}, 258
        elif nxt + 1 > (1 << width):
            width += 1
    if cur >= 0:
        put(cur)
        nxt += 1
        if nxt + 1 > (1 << width) and width < 12:
            width += 1
    put(257)
    if held:
        out.append((room << (8 - held)) & 255)
    return bytes(out)


def lzw_decode(data: bytes, size: int) -> bytes:
    first = [bytes([i]) for i in range(256)] + [b"", b""]
    words, width, out, made, last = first[:], 9, [], 0, None
    room, held = 0, 0
    for b in data:
        room, held = (room << 8) | b, held + 8
        if held < width:
            continue
        held -= width
        code = room >> held
        room &= (1 << held) - 1
        if code == 257 or made >= size:
            break
        if code == 256:
            words, width, last = first[:], 9, None
            continue
        if last is None:
            word = words[code]
        else:
            word = words[code] if code < len(words) else last + last[:1]
            words.append(last + word[:1])
        out.append(word)
        made += len(word)
        last = word
        if len(words) + 1 >= (1 << width) and width < 12:
            width += 1
    return b"".join(out)


def squeeze(data: bytes, compression: int, level: int = 1) -> bytes:
    return {PLAIN: lambda: data, LZW: lambda: lzw_encode(data), DEFLATE: lambda: zlib.compress(data, level), OLD_DEFLATE: lambda: zlib.compress(data, level), PACKBITS: lambda: packbits_encode(data)}[compression]()


def expand(data: bytes, compression: int, size: int) -> bytes:
    if compression == PLAIN:
        return data
    if compression == LZW:
        return lzw_decode(data, size)
    if compression in (DEFLATE, OLD_DEFLATE):
        return zlib.decompressobj().decompress(data, size)
    if compression == PACKBITS:
        return packbits_decode(data, size)
    raise ValueError(f"TIFF compression {compression} is not supported")


def encode_tiff(pages: list[np.ndarray], compression: int = DEFLATE, predictor: bool = False, tile: tuple[int, int] | None = None, strip_rows: int = 512, order: str = "<") -> bytes:
    """Grey 8-bit pages (height x width); tile is (height, width), multiples of 16."""
    if sum(img.size for img in pages) >= 1 << 32:
        raise ValueError("an image of 4 GiB or more has no offsets in this format")
    out = bytearray((b"II" if order == "<" else b"MM") + struct.pack(order + "HI", 42, 0))
    link = 4
    for img in pages:
        h, w = img.shape
        if tile:
            th, tw = tile
            grid = np.zeros((-(-h // th) * th, -(-w // tw) * tw), dtype=np.uint8)
            grid[:h, :w] = img
            parts = [grid[y : y + th, x : x + tw] for y in range(0, h, th) for x in range(0, w, tw)]
        else:
            parts = [img[y : y + strip_rows] for y in range(0, h, strip_rows)]
        at, sizes = [], []
        for p in parts:
            if predictor:
                d = p.copy()
                d[:, 1:] -= p[:, :-1]
                p = d
            data = squeeze(p.tobytes(), compression)
            at.append(len(out))
            sizes.append(len(data))
            out += data
        tags = [(WIDTH, 4, [w]), (HEIGHT, 4, [h]), (BITS, 3, [8]), (COMPRESSION, 3, [compression]), (PHOTOMETRIC, 3, [1]), (SAMPLES, 3, [1]), (PREDICTOR, 3, [2 if predictor else 1])]
        tags += [(TILE_W, 4, [tile[1]]), (TILE_H, 4, [tile[0]]), (TILE_AT, 4, at), (TILE_BYTES, 4, sizes)] if tile else [(STRIP_AT, 4, at), (STRIP_ROWS, 4, [strip_rows]), (STRIP_BYTES, 4, sizes)]
        entries = []
        for tag, kind, values in sorted(tags):
            raw = struct.pack(order + str(len(values)) + TYPE_CODE[kind], *values)
            if len(raw) > 4:
                out += b"\0" * (len(out) % 2)
                raw, extra = struct.pack(order + "I", len(out)), raw
                out += extra
            entries.append(struct.pack(order + "HHI", tag, kind, len(values)) + raw.ljust(4, b"\0"))
        out += b"\0" * (len(out) % 2)
        out[link : link + 4] = struct.pack(order + "I", len(out))
        out += struct.pack(order + "H", len(entries)) + b"".join(entries)
        link = len(out)
        out += b"\0\0\0\0"
    return bytes(out)


def decode_tiff(data: bytes) -> Iterator[np.ndarray]:
    """The pages in the order of their directories, as height x width arrays of 8-bit samples."""
    order = {b"II": "<", b"MM": ">"}.get(bytes(data[:2]))
    if order is None or struct.unpack_from(order + "H", data, 2)[0] != 42:
        raise ValueError("not a TIFF image")
    at, seen = struct.unpack_from(order + "I", data, 4)[0], set()
    while at:
        if at in seen:
            raise ValueError("the image directories form a loop")
        seen.add(at)
        n = struct.unpack_from(order + "H", data, at)[0]
        tags = {}
        for i in range(n):
            tag, kind, count = struct.unpack_from(order + "HHI", data, at + 2 + 12 * i)
            if kind in TYPE_BYTES:
                where = at + 10 + 12 * i
                if count * TYPE_BYTES[kind] > 4:
                    where = struct.unpack_from(order + "I", data, where)[0]
                tags[tag] = struct.unpack_from(f"{order}{count}{TYPE_CODE[kind]}", data, where)
        at = struct.unpack_from(order + "I", data, at + 2 + 12 * n)[0]
        yield _page(data, tags)


def _page(data: bytes, tags: dict[int, tuple[int, ...]]) -> np.ndarray:
    one = lambda tag, default: tags.get(tag, (default,))[0]
    w, h, per = one(WIDTH, 0), one(HEIGHT, 0), one(SAMPLES, 1)
    if any(b != 8 for b in tags.get(BITS, (1,))) or one(284, 1) != 1:
        raise ValueError("only 8-bit samples, pixel by pixel, are supported")
    kind, predicted = one(COMPRESSION, PLAIN), one(PREDICTOR, 1) == 2
    tiled = TILE_AT in tags
    ph, pw = (one(TILE_H, h), one(TILE_W, w)) if tiled else (min(one(STRIP_ROWS, h), h) or 1, w)
    across = -(-w // pw) if w else 1
    img = np.zeros((h, w, per), dtype=np.uint8)
    for k, (off, size) in enumerate(zip(tags[TILE_AT if tiled else STRIP_AT], tags[TILE_BYTES if tiled else STRIP_BYTES])):
        y, x = k // across * ph, k % across * pw
        rows = ph if tiled else min(ph, h - y)
        need = rows * pw * per
        raw = expand(bytes(data[off : off + size]), kind, need)
        if len(raw) < need:
            raise ValueError("a strip or tile is too short")
        block = np.frombuffer(raw, dtype=np.uint8, count=need).reshape(rows, pw, per)
        if predicted:
            block = np.add.accumulate(block, axis=1, dtype=np.uint8)
        img[y : y + rows, x : x + pw] = block[: h - y, : w - x]
    return img[:, :, 0] if per == 1 else img.reshape(h, w * per)


def tiff_pages(df: DataFrame, key: str, image: str, keep_bad: bool = False) -> DataFrame:
    """key, page, width, height, samples: one row for each page of each image."""

    def read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k, data in zip(b.column(0).to_pylist(), b.column(1)):
                rows = []
                try:
                    for i, img in enumerate(decode_tiff(data.as_buffer().to_pybytes()) if data.is_valid else ()):
                        rows.append((k, i, img.shape[1], img.shape[0], img.tobytes()))
                except (ValueError, KeyError, struct.error, zlib.error):
                    if not keep_bad:
                        raise
                    rows = [(k, -1, None, None, None)]
                if rows:
                    c = list(zip(*rows))
                    yield pa.RecordBatch.from_arrays([pa.array(c[0], b.column(0).type), *(pa.array(x, pa.int32()) for x in c[1:4]), pa.array(c[4], pa.binary())], [key, "page", "width", "height", "samples"])

    kind = df.schema[key].dataType.simpleString()
    return df.select(key, image).mapInArrow(read, f"`{key}` {kind}, page int, width int, height int, samples binary")


PAGE_W, PAGE_H = 64, 2048


def text_to_tiff(payload: bytes) -> bytes:
    """A padded payload as pages of 64 samples a row. Its checksum, and nothing else, picks compression,
    layout, predictor and byte order, so equal payloads give equal images of whatever size; deflate is
    the commonest, the codecs that run in Python take one payload in sixteen each."""
    grid = np.frombuffer(payload, dtype=np.uint8).reshape(-1, PAGE_W)
    pages = [grid[y : y + PAGE_H] for y in range(0, len(grid), PAGE_H)]
    pick = zlib.crc32(payload)
    compression = {0: LZW, 1: PACKBITS, 2: PLAIN, 3: OLD_DEFLATE}.get(pick & 15, DEFLATE)
    tile = (16, PAGE_W) if pick >> 4 & 7 == 0 else None
    return encode_tiff(pages, compression, predictor=pick >> 7 & 3 == 0, tile=tile, order=">" if pick >> 9 & 1 else "<")


def texts_as_tiff(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media: each text, zero-padded to a positive multiple of 64 bytes, as a TIFF image."""

    def write(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                n_bytes, media = [], []
                for t in b.column(1).slice(lo, 256).to_pylist():
                    raw = (t or "").encode()
                    n_bytes.append(len(raw))
                    media.append(text_to_tiff(raw + b"\0" * (-len(raw) % 64 if raw else 64)))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, 256), pa.array(n_bytes, pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    return docs.select("doc_id", "text").mapInArrow(write, "doc_id long, n_bytes long, media binary")


def features(samples: np.ndarray, pages: int) -> str:
    """Pages, mean, deviation and entropy of the samples."""
    hist = np.bincount(samples, minlength=256)
    p = hist[hist > 0] / samples.size
    level = np.arange(256)
    mean = float(hist @ level) / samples.size
    var = float(hist @ (level * level)) / samples.size - mean * mean
    return f"pages={pages};mean={mean:.4f};std={max(var, 0.0) ** 0.5:.4f};entropy={abs(float(-(p * np.log2(p)).sum())):.4f}"


def stored_digest(stored: DataFrame) -> DataFrame:
    """What the stored images hold, read back page by page."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    names = [c.split()[0] for c in schema.split(", ")]

    def read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for d, n, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                data = data.as_buffer().to_pybytes()
                pages = [img.reshape(-1) for img in decode_tiff(data)]
                samples = np.concatenate(pages)
                back = samples.tobytes()
                rows.append((d, n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(data), hashlib.sha256(data).hexdigest(), features(samples, len(pages))))
            cols = list(zip(*rows)) or [[]] * 8
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.string() if k in (3, 6, 7) else pa.int64()) for k, c in enumerate(cols)], names)

    return stored.select("doc_id", "n_bytes", "media").mapInArrow(read, schema)


def text_media(docs: DataFrame) -> DataFrame:
    """Write the media column as a table in the shared folder, read it back and digest it."""
    return stored_digest(written(texts_as_tiff(docs), "media", codec="none"))
