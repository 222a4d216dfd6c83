"""TIFF media: read image directories, strips and tiles into pages, and write payloads as multi-page files.

Reads both byte orders, classic files, 8 and 16 bits a sample, chunky and planar samples, compressions 1 (none), 5 (LZW),
8 and 32946 (deflate) and 32773 (PackBits), and predictor 2 (horizontal differences). Sizes in a file are checked against
the file before anything is made from them. Files that break these rules give one row with `error` set and no pixels.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: Fixed values of the format: bytes of each field type, and tag numbers.
TYPE_BYTES = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8, 6: 1, 7: 1, 8: 2, 9: 4, 10: 8}
WIDTH, HEIGHT, BITS, COMPRESSION, PHOTOMETRIC, STRIP_AT, SAMPLES, ROWS, STRIP_BYTES, PLANAR, PREDICTOR = 256, 257, 258, 259, 262, 273, 277, 278, 279, 284, 317
TILE_WIDTH, TILE_HEIGHT, TILE_AT, TILE_BYTES = 322, 323, 324, 325

#: Most samples of a page. A larger page is an error: it wouldn't fit a row.
MOST_SAMPLES = 1 << 29
#: Most bytes that one byte of a strip or tile can stand for, by compression (deflate and LZW: their theoretical limits, rounded up).
EXPANSION = {1: 1, 5: 4096, 8: 1100, 32946: 1100, 32773: 64}

PAGE = "page int, width int, height int, samples int, bits int, compression int, pixels binary, error string"


def unpackbits(data: bytes, size: int) -> bytes:
    out, k = bytearray(), 0
    while k < len(data) and len(out) < size:
        n = data[k]
        if n < 128:
            out += data[k + 1 : k + 2 + n]
            k += 2 + n
        else:
            if n > 128:
                out += data[k + 1 : k + 2] * (257 - n)
            k += 2 if n > 128 else 1
    return bytes(out)


def packbits(data: bytes) -> bytes:
    """Runs of two or more equal bytes, and what lies between them, in packets of 128 at most."""
    a = np.frombuffer(data, np.uint8)
    if not len(a):
        return b""
    edges = np.flatnonzero(a[1:] != a[:-1]) + 1
    starts, ends = np.concatenate([[0], edges]), np.concatenate([edges, [len(a)]])
    long = ends - starts > 1
    out, k = bytearray(), 0
    for start, end in zip(starts[long].tolist(), ends[long].tolist(), strict=True):
        _literal(out, data, k, start)
        for at in range(start, end, 128):
            n = min(128, end - at)
            out += bytes((257 - n, data[at])) if n > 1 else bytes((0, data[at]))
        k = end
    _literal(out, data, k, len(data))
    return bytes(out)


def _literal(out: bytearray, data: bytes, start: int, end: int) -> None:
    for at in range(start, end, 128):
        n = min(128, end - at)
        out.append(n - 1)
        out += data[at : at + n]


def unlzw(data: bytes, size: int) -> bytes:
    """Codes of 9 to 12 bits, high bits first, widening one code early; 256 clears, 257 ends."""
    out, table, prev = bytearray(), [], b""
    acc = bits = 0
    width, start = 9, [bytes([c]) for c in range(256)] + [b"", b""]
    for byte in data:
        acc, bits = (acc << 8) | byte, bits + 8
        while bits >= width:
            bits -= width
            code = acc >> bits
            acc &= (1 << bits) - 1
            if code == 257 or len(out) >= size:
                return bytes(out)
            if code == 256:
                table, width, prev = start.copy(), 9, b""
                continue
            if not table:
                table = start.copy()
            if code < len(table):
                entry = table[code]
            elif prev and code == len(table):
                entry = prev + prev[:1]
            else:
                raise ValueError("LZW code out of range")
            out += entry
            if prev:
                table.append(prev + entry[:1])
                width = 12 if len(table) >= 2047 else 11 if len(table) >= 1023 else 10 if len(table) >= 511 else 9
            prev = entry
    return bytes(out)


def lzw(data: bytes) -> bytes:
    out, acc, bits = bytearray(), 256, 9
    width, table, size, word = 9, {}, 258, b""

    def put(code: int) -> None:
        nonlocal acc, bits
        acc, bits = (acc << width) | code, bits + width
        while bits >= 8:
            bits -= 8
            out.append(acc >> bits & 255)
            acc &= (1 << bits) - 1

    out.append(acc >> 1)
    acc, bits = acc & 1, 1
    code = lambda w: w[0] if len(w) == 1 else table[w]
    for c in data:
        longer = word + bytes([c])
        if len(longer) == 1 or longer in table:
            word = longer
            continue
        put(code(word))
        table[longer] = size
        size += 1
        width = 12 if size >= 2048 else 11 if size >= 1024 else 10 if size >= 512 else 9
        if size >= 4094:
            put(256)
            width, table, size = 9, {}, 258
        word = bytes([c])
    if word:
        put(code(word))
        size += 1
        width = 12 if size >= 2048 else 11 if size >= 1024 else 10 if size >= 512 else 9
    put(257)
    if bits:
        out.append(acc << (8 - bits) & 255)
    return bytes(out)


def _inflate(data: bytes, size: int) -> bytes:
    return zlib.decompressobj().decompress(data, size)


DECODERS = {1: lambda d, n: d, 5: unlzw, 8: _inflate, 32946: _inflate, 32773: unpackbits}
ENCODERS = {1: bytes, 5: lzw, 8: lambda d: zlib.compress(d, 1), 32773: packbits}


def _entries(data: bytes, at: int, e: str) -> tuple[dict[int, tuple[int, ...]], int]:
    (n,) = struct.unpack_from(e + "H", data, at)
    if at + 2 + 12 * n + 4 > len(data):
        raise ValueError("a directory reaches beyond the file")
    tags = {}
    for k in range(n):
        tag, kind, count = struct.unpack_from(e + "HHI", data, at + 2 + 12 * k)
        size = TYPE_BYTES.get(kind, 1) * count
        where = at + 2 + 12 * k + 8
        if size > 4:
            (where,) = struct.unpack_from(e + "I", data, where)
            if where + size > len(data):
                raise ValueError("a tag's values reach beyond the file")
        if kind in (1, 3, 4):
            tags[tag] = struct.unpack_from(f"{e}{count}{ {1: 'B', 3: 'H', 4: 'I'}[kind] }", data, where)
    return tags, struct.unpack_from(e + "I", data, at + 2 + 12 * n)[0]


def _block(raw: bytes, tags: dict, rows: int, cols: int, samples: int, bits: int, e: str) -> np.ndarray:
    """One strip or tile as rows x cols x samples, with the predictor undone."""
    size = rows * cols * samples * bits // 8
    how = tags.get(COMPRESSION, (1,))[0]
    if how not in DECODERS:
        raise ValueError(f"compression {how}")
    data = DECODERS[how](raw, size)
    if len(data) < size:
        raise ValueError("a strip or tile is short")
    a = np.frombuffer(data[:size], dtype=np.uint8 if bits == 8 else np.dtype(e + "u2")).reshape(rows, cols, samples)
    if tags.get(PREDICTOR, (1,))[0] == 2:
        a = np.cumsum(a, axis=1, dtype=np.uint8 if bits == 8 else np.uint16)
    return a


def pages(data: bytes) -> Iterator[dict]:
    """The pages of a file, in the order of its directories. pixels: rows of chunky samples; 16 bits little-endian."""
    if data[:2] not in (b"II", b"MM"):
        raise ValueError("not a TIFF file")
    e = "<" if data[:2] == b"II" else ">"
    magic, at = struct.unpack_from(e + "HI", data, 2)
    if magic != 42:
        raise ValueError("not a classic TIFF file")
    seen: set[int] = set()
    number = 0
    while at and at not in seen:
        seen.add(at)
        tags, at = _entries(data, at, e)
        one = lambda tag, default=None: (tags.get(tag) or (default,))[0]  # noqa: B023, E731
        width, height, samples, bits = one(WIDTH), one(HEIGHT), one(SAMPLES, 1), one(BITS, 1)
        if bits not in (8, 16):
            raise ValueError(f"{bits} bits a sample")
        if not (width and height and samples) or width * height * samples > MOST_SAMPLES:
            raise ValueError(f"a page of {width} x {height} x {samples}")
        how = one(COMPRESSION, 1)
        if how not in DECODERS:
            raise ValueError(f"compression {how}")
        planes = samples if one(PLANAR, 1) == 2 and samples > 1 else 1
        deep = samples // planes
        tiled = TILE_AT in tags
        bw, bh = (one(TILE_WIDTH), one(TILE_HEIGHT)) if tiled else (width, min(one(ROWS, height), height))
        starts, sizes = (tags.get(TILE_AT, ()), tags.get(TILE_BYTES, ())) if tiled else (tags.get(STRIP_AT, ()), tags.get(STRIP_BYTES, ()))
        if not (bw and bh) or bw * bh * deep > MOST_SAMPLES:
            raise ValueError(f"strips or tiles of {bw} x {bh}")
        across, down = -(-width // bw), -(-height // bh)
        if len(starts) != len(sizes) or len(starts) != across * down * planes:
            raise ValueError("the wrong number of strips or tiles")
        if any(a + n > len(data) for a, n in zip(starts, sizes, strict=True)):
            raise ValueError("a strip or tile reaches beyond the file")
        if width * height * samples * bits // 8 > sum(sizes) * EXPANSION[how]:
            raise ValueError("strips or tiles are too short for the page")
        image = np.zeros((height, width, samples), dtype=np.uint8 if bits == 8 else np.uint16)
        for k, (start, size) in enumerate(zip(starts, sizes, strict=True)):
            plane, cell = divmod(k, across * down)
            y, x = cell // across * bh, cell % across * bw
            rows = bh if tiled else min(bh, height - y)
            block = _block(data[start : start + size], tags, rows, bw, deep, bits, e)
            image[y : y + bh, x : x + bw, plane * deep : (plane + 1) * deep] = block[: height - y, : width - x]
        yield {"page": number, "width": width, "height": height, "samples": samples, "bits": bits, "compression": how, "pixels": image.astype(image.dtype.newbyteorder("<")).tobytes(), "error": None}
        number += 1


def write(images: list[np.ndarray], compression: int = 8, predictor: int = 2, tile: int = 0, strip_rows: int = 64) -> bytes:
    """A little-endian file of 8-bit pages (rows x columns x samples). tile: edge in pixels, a multiple of 16; 0: strips."""
    out = bytearray(b"II" + struct.pack("<HI", 42, 0))
    link = 4
    for image in images:
        height, width, samples = image.shape
        bh, bw = (tile, tile) if tile else (strip_rows, width)
        starts, sizes = [], []
        for y in range(0, height, bh):
            for x in range(0, width, bw):
                block = image[y : y + bh, x : x + bw]
                if tile:
                    block = np.pad(block, ((0, bh - block.shape[0]), (0, bw - block.shape[1]), (0, 0)))
                if predictor == 2:
                    block = np.diff(block, axis=1, prepend=np.zeros_like(block[:, :1]))
                data = ENCODERS[compression](block.tobytes())
                starts.append(len(out))
                sizes.append(len(data))
                out += data + b"\0" * (len(data) % 2)
        places = {WIDTH: (4, [width]), HEIGHT: (4, [height]), BITS: (3, [8] * samples), COMPRESSION: (3, [compression]), PHOTOMETRIC: (3, [2 if samples == 3 else 1]), SAMPLES: (3, [samples]), PLANAR: (3, [1]), PREDICTOR: (3, [predictor])}
        places |= {TILE_WIDTH: (4, [bw]), TILE_HEIGHT: (4, [bh]), TILE_AT: (4, starts), TILE_BYTES: (4, sizes)} if tile else {STRIP_AT: (4, starts), ROWS: (4, [bh]), STRIP_BYTES: (4, sizes)}
        entries = b""
        for tag, (kind, values) in sorted(places.items()):
            raw = struct.pack(f"<{len(values)}{'H' if kind == 3 else 'I'}", *values)
            if len(raw) > 4:
                where = len(out)
                out += raw + b"\0" * (len(raw) % 2)
                raw = struct.pack("<I", where)
            entries += struct.pack("<HHI", tag, kind, len(values)) + raw.ljust(4, b"\0")
        struct.pack_into("<I", out, link, len(out))
        out += struct.pack("<H", len(places)) + entries
        link = len(out)
        out += b"\0\0\0\0"
    return bytes(out)


#: Pixels in a row of a stored payload (three samples each: 192 bytes), and rows in a page.
ROW_PIXELS, PAGE_ROWS = 64, 1024


#: Forms in which store() writes payloads, by a checksum of the payload: (compression, tile edge or 0 for strips).
FORMS = ((8, 0), (8, 64), (32773, 0), (5, 0), (1, 0), (32773, 64), (5, 64), (1, 64))


def store(payload: bytes) -> bytes:
    """A payload (a positive multiple of 192 bytes) as a file of RGB pages 64 pixels wide, in one of the FORMS."""
    compression, tile = FORMS[zlib.crc32(payload) % len(FORMS)]
    rows = np.frombuffer(payload, dtype=np.uint8).reshape(-1, ROW_PIXELS, 3)
    return write([rows[k : k + PAGE_ROWS] for k in range(0, len(rows), PAGE_ROWS)], compression, 2 if compression in (5, 8) else 1, tile)


def pad(text: str | None) -> tuple[int, bytes]:
    data = (text or "").encode()
    return len(data), data.ljust(max(1, -(-len(data) // 192)) * 192, b" ")


def feature(parts: list[np.ndarray]) -> str:
    """Mean and deviation of each of the three sample planes over all pages, and the share of equal neighbours in a row."""
    n = sum(len(p) * ROW_PIXELS for p in parts)
    total, square, same = np.zeros(3), np.zeros(3), 0
    for p in parts:
        counts = [np.bincount(p[:, :, c].ravel(), minlength=256) for c in range(3)]
        total += [c @ np.arange(256) for c in counts]
        square += [c @ np.arange(256) ** 2 for c in counts]
        same += int((p[:, 1:] == p[:, :-1]).all(axis=2).sum())
    mean = total / n
    spread = np.sqrt(np.maximum(square / n - mean**2, 0))
    return ";".join(f"{a:.4f},{b:.4f}" for a, b in zip(mean, spread, strict=True)) + f";{same / n:.6f}"


def read_pages(df: DataFrame, media: str = "media") -> DataFrame:
    """One row a page: the other columns (but those named as a page's), then the page. Null media: no rows.

    A file that can't be read gives one row whose `error` says why. Narrow: each file is read where it is.
    """
    made = [c.split()[0] for c in PAGE.split(", ")]
    keep = [c for c in df.columns if c != media and c not in made]
    schema = ", ".join([*(f"`{n}` {t}" for n, t in df.select(*keep).dtypes), PAGE])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, data in enumerate(batch.column(media).to_pylist()):
                if data is None:
                    continue
                rows = []
                try:
                    rows = list(pages(data))
                except (ValueError, KeyError, IndexError, TypeError, OverflowError, MemoryError, struct.error, zlib.error) as x:
                    rows = [dict.fromkeys(made) | {"page": 0, "error": str(x)[:200] or type(x).__name__}]
                for row in rows:
                    one = batch.slice(k, 1)
                    made_columns = [pa.array([row[n]], t) for n, t in zip(made, (*[pa.int32()] * 6, pa.binary(), pa.string()), strict=True)]
                    yield pa.RecordBatch.from_arrays([*(one.column(c) for c in keep), *made_columns], [*keep, *made])

    return df.select(*keep, media).mapInArrow(run, schema)


def store_texts(df: DataFrame, text: str = "text", out: str = "media") -> DataFrame:
    """Add each text's payload as a TIFF file in column `out`. A null text counts as empty: one row of spaces."""
    keep = [c for c in df.columns if c != out]
    schema = ", ".join([*(f"`{n}` {t}" for n, t in df.select(*keep).dtypes), f"`{out}` binary"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data = [store(pad(t)[1]) for t in batch.column(text).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(data, pa.binary())], [*keep, out])

    return df.mapInArrow(run, schema)


def round_trip(df: DataFrame) -> DataFrame:
    """Store each row's text, read the file's pages back, and describe both. One pass; files don't leave their task."""
    kind = dict(df.dtypes)["doc_id"]
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "n_pages"]
    types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for t in batch.column("text").to_pylist():
                n, payload = pad(t)
                media = store(payload)
                back = [p["pixels"] for p in pages(media)]
                read = b"".join(back)
                shown = feature([np.frombuffer(b, np.uint8).reshape(-1, ROW_PIXELS, 3) for b in back])
                rows.append((n, len(read), hashlib.sha256(read).hexdigest(), zlib.crc32(read[-16:]), len(media), hashlib.sha256(media).hexdigest(), shown, len(back)))
            columns = zip(*rows, strict=True) if rows else [()] * len(types)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, t) for c, t in zip(columns, types, strict=True))], names)

    schema = f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_pages int"
    return df.select("doc_id", df["text"].cast("string").alias("text")).mapInArrow(run, schema)
