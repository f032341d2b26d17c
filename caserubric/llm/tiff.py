"""TIFF: walk image directories, decode strips and tiles, undo predictors, one row per page.

Reads classic TIFF of either byte order, 8-bit chunky samples, compression none, PackBits, LZW or deflate, predictor
none or horizontal. The writer makes such files, a page at a time, so that memory is bounded by a page.
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

# Fixed values of the format: compression codes, and sizes of the field types BYTE, ASCII, SHORT, LONG, RATIONAL.
NONE, LZW, DEFLATE, OLD_DEFLATE, PACKBITS = 1, 5, 8, 32946, 32773
TYPE_SIZES = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8}
WIDTH, SAMPLES, UNIT = 64, 3, 192
PAGE_ROWS, STRIP_ROWS = 1024, 256


def packbits_decode(data: bytes) -> bytes:
    out, i, n = bytearray(), 0, len(data)
    while i < n:
        head = data[i]
        if head < 128:
            out += data[i + 1 : i + 2 + head]
            i += 2 + head
        else:
            if head > 128:
                out += data[i + 1 : i + 2] * (257 - head)
            i += 2 if head > 128 else 1
    return bytes(out)


def packbits_encode(data: bytes) -> bytes:
    out, i, n = bytearray(), 0, len(data)
    while i < n:
        j = i + 1
        while j < n and data[j] == data[i] and j - i < 128:
            j += 1
        if j - i > 1:
            out += bytes((257 - (j - i), data[i]))
        else:
            while j < n and j - i < 128 and not (j + 1 < n and data[j] == data[j + 1]):
                j += 1
            out += bytes((j - i - 1,)) + data[i:j]
        i = j
    return bytes(out)


def lzw_decode(data: bytes) -> bytes:
    """Codes of 9 to 12 bits, most significant bit first; the width grows one code early."""
    out, table, width, held, bits, last = bytearray(), [], 9, 0, 0, None
    for byte in data:
        held, bits = held << 8 | byte, bits + 8
        if bits < width:
            continue
        bits -= width
        code = held >> bits
        held &= (1 << bits) - 1
        if code == 257:
            break
        if code == 256:
            table, width, last = [bytes((k,)) for k in range(256)] + [b"", b""], 9, None
            continue
        if last is None:
            entry = table[code]
        else:
            entry = table[code] if code < len(table) else last + last[:1]
            table.append(last + entry[:1])
            if len(table) + 1 >= 1 << width and width < 12:
                width += 1
        out += entry
        last = entry
    return bytes(out)


def lzw_encode(data: bytes) -> bytes:
    out, held, bits, width = bytearray(), 0, 0, 9
    table: dict[bytes, int] = {}

    def put(code: int) -> None:
        nonlocal held, bits
        held, bits = held << width | code, bits + width
        while bits >= 8:
            bits -= 8
            out.append(held >> bits & 255)
        held &= (1 << bits) - 1

    def restart() -> None:
        nonlocal table, width
        put(256)
        table, width = {bytes((k,)): k for k in range(256)}, 9

    restart()
    run = b""
    for k in range(len(data)):
        more = run + data[k : k + 1]
        if more in table:
            run = more
            continue
        put(table[run])
        table[more] = len(table) + 2
        if len(table) + 2 >= 1 << width:
            width += 1
        if len(table) + 2 >= 4094:
            width = min(width, 12)
            restart()
        run = data[k : k + 1]
    if run:
        put(table[run])
        if len(table) + 3 >= 1 << width and width < 12:  # the reader adds an entry for this code too
            width += 1
    put(257)
    if bits:
        out.append(held << 8 - bits & 255)
    return bytes(out)


CODECS = {
    NONE: (bytes, bytes),
    PACKBITS: (packbits_encode, packbits_decode),
    LZW: (lzw_encode, lzw_decode),
    DEFLATE: (lambda b: zlib.compress(b, 1), zlib.decompress),
    OLD_DEFLATE: (lambda b: zlib.compress(b, 1), zlib.decompress),
}


def difference(rows: np.ndarray) -> np.ndarray:
    """Horizontal differencing of (row, pixel, sample) bytes."""
    out = rows.copy()
    out[:, 1:] -= rows[:, :-1]
    return out


def undo(rows: np.ndarray) -> np.ndarray:
    return np.cumsum(rows, axis=1, dtype=np.uint8)


def encode_tiff(payload: bytes, compression: int = DEFLATE, predictor: int = 2, tile: int = 0) -> bytes:
    """A TIFF of RGB pages, WIDTH pixels wide and up to PAGE_ROWS high, in strips, or in tiles of tile x tile."""
    squeeze = CODECS[compression][0]
    out = bytearray(b"II*\0\0\0\0\0")
    link = 4
    image = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH, SAMPLES)
    for top in range(0, len(image), PAGE_ROWS):
        page = image[top : top + PAGE_ROWS]
        parts = []
        if tile:
            full = np.zeros((-(-len(page) // tile) * tile, -(-WIDTH // tile) * tile, SAMPLES), np.uint8)
            full[: len(page), :WIDTH] = page
            parts = [full[y : y + tile, x : x + tile] for y in range(0, len(full), tile) for x in range(0, full.shape[1], tile)]
        else:
            parts = [page[y : y + STRIP_ROWS] for y in range(0, len(page), STRIP_ROWS)]
        offsets, counts = [], []
        for part in parts:
            data = squeeze((difference(part) if predictor == 2 else part).tobytes())
            offsets.append(len(out))
            counts.append(len(data))
            out += data + b"\0" * (len(data) & 1)

        def spare(kind: str, values: list[int]) -> tuple[int, int, bytes]:
            raw = struct.pack(f"<{len(values)}{kind}", *values)
            if len(raw) <= 4:
                return (3 if kind == "H" else 4), len(values), raw.ljust(4, b"\0")
            at = len(out)
            out.extend(raw + b"\0" * (len(raw) & 1))
            return (3 if kind == "H" else 4), len(values), struct.pack("<I", at)

        tags = {256: ("I", [WIDTH]), 257: ("I", [len(page)]), 258: ("H", [8] * SAMPLES), 259: ("H", [compression]), 262: ("H", [2]), 277: ("H", [SAMPLES]), 284: ("H", [1]), 317: ("H", [predictor])}
        tags |= {322: ("I", [tile]), 323: ("I", [tile]), 324: ("I", offsets), 325: ("I", counts)} if tile else {273: ("I", offsets), 278: ("I", [STRIP_ROWS]), 279: ("I", counts)}
        entries = [struct.pack("<HHI", t, *(x := spare(*tags[t]))[:2]) + x[2] for t in sorted(tags)]
        struct.pack_into("<I", out, link, len(out))
        out += struct.pack("<H", len(entries)) + b"".join(entries)
        link = len(out)
        out += b"\0\0\0\0"
    return bytes(out)


def tiff_images(data: bytes) -> Iterator[tuple[dict, np.ndarray]]:
    """(fields, samples as rows x pixels x samples) of each directory; ValueError for what isn't such a TIFF."""
    end = {b"II": "<", b"MM": ">"}.get(data[:2])
    if end is None or len(data) < 8 or struct.unpack_from(end + "H", data, 2)[0] != 42:
        raise ValueError("not a TIFF")
    at, seen = struct.unpack_from(end + "I", data, 4)[0], set()
    while at:
        if at in seen or at + 2 > len(data):
            raise ValueError("broken directory chain")
        seen.add(at)
        n = struct.unpack_from(end + "H", data, at)[0]
        if at + 6 + 12 * n > len(data):
            raise ValueError("directory is cut off")
        tags: dict[int, list[int]] = {}
        for k in range(n):
            tag, kind, count = struct.unpack_from(end + "HHI", data, at + 2 + 12 * k)
            size = TYPE_SIZES.get(kind, 0) * count
            where = at + 10 + 12 * k if size <= 4 else struct.unpack_from(end + "I", data, at + 10 + 12 * k)[0]
            if kind in (1, 3, 4) and where + size <= len(data):
                tags[tag] = list(struct.unpack_from(f"{end}{count}{'_B_HI'[kind]}", data, where))
        one = lambda t, default=None: tags.get(t, [default])[0]  # noqa: B023, E731
        width, height, samples, code, predictor = one(256), one(257), one(277, 1), one(259, 1), one(317, 1)
        if not width or not height or set(tags.get(258, [1])) != {8} or one(284, 1) != 1 or code not in CODECS or predictor not in (1, 2):
            raise ValueError(f"unsupported page: {width} x {height}, compression {code}, predictor {predictor}")
        if 324 in tags:
            tw, th, offsets, counts = one(322), one(323), tags[324], tags[325]
        else:
            tw, th, offsets, counts = width, min(one(278, height) or 0, height), tags.get(273, []), tags.get(279, [])
        if not tw or not th:
            raise ValueError("strips or tiles without a size")
        across, down = -(-width // tw), -(-height // th)
        if len(offsets) != across * down or len(counts) != len(offsets):
            raise ValueError("strips or tiles are missing")
        image = np.zeros((height, width, samples), np.uint8)
        for k, (o, c) in enumerate(zip(offsets, counts, strict=True)):
            y, x = k // across * th, k % across * tw
            rows = th if 324 in tags else min(th, height - y)
            raw = CODECS[code][1](data[o : o + c])
            if len(raw) < rows * tw * samples:
                raise ValueError("a strip or tile is too short")
            part = np.frombuffer(raw, np.uint8, rows * tw * samples).reshape(rows, tw, samples)
            part = undo(part) if predictor == 2 else part
            image[y : y + th, x : x + tw] = part[: height - y, : width - x]
        yield {"width": width, "height": height, "samples": samples, "compression": code, "predictor": predictor, "layout": "tiles" if 324 in tags else "strips"}, image
        at = struct.unpack_from(end + "I", data, at + 2 + 12 * n)[0]


def tiff_pages(media: DataFrame, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """One row per page: id, page, width, height, samples, compression, predictor, layout, pixels, error.

    A null or unreadable file gives one row with page null and error set; pages before the fault are kept. Ids may be
    null or repeated; other columns are ignored.
    """
    kind = media.select(id_col).schema[0].dataType.simpleString()
    names = ["id", "page", "width", "height", "samples", "compression", "predictor", "layout", "pixels", "error"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, data in enumerate(batch.column("media")):
                key, page = batch.column("id").slice(k, 1), 0
                row = lambda *x: pa.RecordBatch.from_arrays([key, *(pa.array([v], t) for v, t in zip(x, [pa.int32()] * 6 + [pa.string(), pa.binary(), pa.string()], strict=True))], names)  # noqa: B023, E731
                try:
                    for f, image in tiff_images(data.as_py() or b""):
                        yield row(page, f["width"], f["height"], f["samples"], f["compression"], f["predictor"], f["layout"], image.tobytes(), None)
                        page += 1
                except (ValueError, IndexError, zlib.error, struct.error) as fault:
                    yield row(None, None, None, None, None, None, None, None, str(fault))

    out = media.select(F.col(id_col).alias("id"), F.col(media_col).alias("media")).mapInArrow(run, f"id {kind}, page int, width int, height int, samples int, compression int, predictor int, layout string, pixels binary, error string")
    return out.withColumnRenamed("id", id_col)


def stored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "pages"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
    for batch in batches:
        rows = []
        for text in batch.column("text"):
            raw = (text.as_py() or "").encode("utf-8", "surrogatepass")
            media = encode_tiff(raw.ljust(max(UNIT, -(-len(raw) // UNIT) * UNIT), b" "))
            digest, size, tail, pages, height, sums, low, high = hashlib.sha256(), 0, b"", 0, 0, np.zeros(SAMPLES, np.int64), 255, 0
            for f, image in tiff_images(media):
                data = image.tobytes()
                digest.update(data)
                size, tail, pages, height = size + len(data), (tail + data[-16:])[-16:], pages + 1, height + f["height"]
                sums, low, high = sums + image.sum(axis=(0, 1), dtype=np.int64), min(low, int(image.min())), max(high, int(image.max()))
            feature = f"{WIDTH}x{height} pages={pages} sums={','.join(map(str, sums.tolist()))} range={low}-{high}"
            rows.append((len(raw), size, digest.hexdigest(), zlib.crc32(tail), len(media), hashlib.sha256(media).hexdigest(), feature, pages))
        cols = zip(*rows, strict=True) if rows else [()] * len(names)
        yield pa.RecordBatch.from_arrays([batch.column("id"), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], ["id", *names])


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store each whole text as a TIFF and return digests of what reading the file back gives, one row per document.

    The payload is the UTF-8 text, filled up with blanks to a positive multiple of 192 bytes: rows of 64 RGB pixels.
    A null text is empty. Files are made and read one at a time, so none crosses the network.
    """
    kind = docs.select(id_col).schema[0].dataType.simpleString()
    out = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(stored, f"id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, pages long")
    return out.withColumnRenamed("id", id_col)
