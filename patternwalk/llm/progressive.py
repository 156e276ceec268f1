"""Operator 6: progressive JPEG columns.

:func:`decode` reads the scans of a progressive JPEG one after another into one
array of quantised coefficients per component: first scans of a spectral band set
the high bits, refining scans add one bit each. The coefficients are then
dequantised and inverse-transformed by matrix products in numpy, chroma is repeated
to full resolution, and the picture becomes an RGB tensor.

Scans are decoded symbol by symbol, but for three kinds of run that are read at once
with the same result: direct-current differences of zero under a one-bit code, band
coefficients that all have the same one-byte form, and the correction bits of an
end-of-band run.

:func:`store` keeps any bytes as the quantised coefficients of such a picture: a byte
becomes a coefficient of magnitude 128 to 255 whose eight additional bits are the
byte, in zigzag places 1 to 63, sent in two spectral bands with the low bit in
refining scans. :func:`restore` reads the bytes back from the decoded coefficients.

Defined results: a null text is empty; its payload is one block of spaces. Texts of any
length are stored whole in one picture, up to 6 GB. Equal texts give equal values. Rows
are handled one by one; an empty table gives an empty result; extra columns are not
read. Null media decodes to a null tensor; media that is no progressive JPEG of one
or three components raises an error.
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

UNIT = 192


def _zigzag() -> np.ndarray:
    """Row-major place of each zigzag index."""
    cells = sorted(((r, c) for r in range(8) for c in range(8)), key=lambda x: (x[0] + x[1], x[0] if (x[0] + x[1]) % 2 else x[1]))
    return np.array([8 * r + c for r, c in cells])


ZIGZAG = _zigzag()
_K = np.arange(8)
#: The inverse transform's matrix: samples = _IDCT @ coefficients @ _IDCT.T
_IDCT = (np.cos((2 * _K[:, None] + 1) * _K[None, :] * np.pi / 16) * np.where(_K == 0, np.sqrt(0.125), 0.5)[None, :]).astype(np.float32)


class Huffman:
    """Canonical codes as a table over the next 16 bits: code length and symbol."""

    def __init__(self, counts: bytes, symbols: bytes) -> None:
        self.symbol, self.length = [0] * 65536, [0] * 65536
        self.one_bit = symbols[0] if counts[0] else None
        code = at = 0
        for bits, n in enumerate(counts, 1):
            for _ in range(n):
                a, b = code << (16 - bits), (code + 1) << (16 - bits)
                self.symbol[a:b] = [symbols[at]] * (b - a)
                self.length[a:b] = [bits] * (b - a)
                code += 1
                at += 1
            code <<= 1


_TABLES: dict[bytes, Huffman] = {}


def _huffman(counts: bytes, symbols: bytes) -> Huffman:
    key = counts + symbols
    if key not in _TABLES:
        if len(_TABLES) > 64:
            _TABLES.clear()
        _TABLES[key] = Huffman(counts, symbols)
    return _TABLES[key]


class _Bits:
    """Entropy-coded bytes without their stuffing."""

    def __init__(self, data: bytes) -> None:
        self.data, self.at, self.end = data + b"\0\0\0\0", 0, 8 * len(data)

    def take(self, n: int) -> int:
        if not n:
            return 0
        a, b = self.at >> 3, self.at + n
        self.at = b
        if b > self.end + 7:
            raise ValueError("scan data ends early")
        return int.from_bytes(self.data[a : (b + 7) >> 3], "big") >> (-b & 7) & ((1 << n) - 1)

    def symbol(self, table: Huffman) -> int:
        a = self.at >> 3
        d = self.data
        if a + 3 > len(d):
            raise ValueError("scan data ends early")
        peek = (d[a] << 16 | d[a + 1] << 8 | d[a + 2]) >> (8 - (self.at & 7)) & 0xFFFF
        n = table.length[peek]
        if not n:
            raise ValueError("no such code")
        self.at += n
        return table.symbol[peek]

    def many(self, n: int) -> np.ndarray:
        """The next ``n`` bits, one in each place."""
        a, b = self.at >> 3, self.at + n
        if b > self.end + 7:
            raise ValueError("scan data ends early")
        skip = self.at & 7
        self.at = b
        return np.unpackbits(np.frombuffer(self.data, np.uint8, (b + 7 >> 3) - a, a), count=n + skip)[skip:]


def _extend(bits: int, n: int) -> int:
    return bits if not n or bits >> (n - 1) else bits - (1 << n) + 1


class Component:
    """One component's sampling factors, table and coefficients, ``[block row, block column, zigzag]``."""

    def __init__(self, name: int, h: int, v: int, table: int) -> None:
        self.name, self.h, self.v, self.table = name, h, v, table

    def size(self, width: int, height: int, most_h: int, most_v: int) -> None:
        up = lambda a, b: -(-a // b)
        self.across, self.down = up(up(width * self.h, most_h), 8), up(up(height * self.v, most_v), 8)
        self.coefficients = np.zeros((up(height, 8 * most_v) * self.v, up(width, 8 * most_h) * self.h, 64), np.int16)


class Picture:
    def __init__(self) -> None:
        self.width = self.height = self.interval = 0
        self.components: list[Component] = []
        self.quant: dict[int, np.ndarray] = {}
        self.comments: list[bytes] = []

    def rgb(self) -> np.ndarray:
        """The full-resolution tensor, ``[row, column, channel]``."""
        planes, most_h, most_v = [], max(c.h for c in self.components), max(c.v for c in self.components)
        for c in self.components:
            rows, columns, _ = c.coefficients.shape
            natural = np.empty((rows * columns, 64), np.float32)
            natural[:, ZIGZAG] = c.coefficients.reshape(-1, 64) * self.quant[c.table].astype(np.float32)
            cells = (natural.reshape(-1, 8) @ _IDCT.T).reshape(-1, 8, 8)
            cells = np.matmul(_IDCT, cells).reshape(rows, columns, 8, 8)
            plane = cells.transpose(0, 2, 1, 3).reshape(8 * rows, 8 * columns) + np.float32(128)
            np.clip(plane, 0, 255, out=plane)
            if most_v > c.v:
                plane = plane[np.arange(self.height) * c.v // most_v]
            if most_h > c.h:
                plane = plane[:, np.arange(self.width) * c.h // most_h]
            planes.append(plane[: self.height, : self.width])
        out = np.empty((self.height, self.width, 3), np.uint8)
        if len(planes) == 1:
            out[:] = np.rint(planes[0])[:, :, None]
            return out
        y, cb, cr = planes
        cb, cr = cb - np.float32(128), cr - np.float32(128)
        # The file format's conversion from luma and chroma.
        for k, x in enumerate((y + np.float32(1.402) * cr, y - np.float32(0.344136) * cb - np.float32(0.714136) * cr, y + np.float32(1.772) * cb)):
            out[:, :, k] = np.clip(np.rint(x), 0, 255)
        return out


def _scan(picture: Picture, chosen: list[tuple[Component, Huffman | None, Huffman | None]], ss: int, se: int, ah: int, al: int, segments: list[bytes]) -> None:
    at, interval = 0, picture.interval
    if len(chosen) > 1 or ss == 0:
        most_h, most_v = max(c.h for c in picture.components), max(c.v for c in picture.components)
        if len(chosen) > 1:
            units = [(i, c, [(r, q) for r in range(c.v) for q in range(c.h)]) for i, (c, _, _) in enumerate(chosen)]
            columns, total = -(-picture.width // (8 * most_h)), -(-picture.width // (8 * most_h)) * -(-picture.height // (8 * most_v))
        else:
            c = chosen[0][0]
            units, columns, total = [(0, c, [(0, 0)])], c.across, c.across * c.down
        for segment in segments:
            n = min(interval or total, total - at)
            _dc_segment(chosen, units, columns, at, n, _Bits(segment), ah, al, len(chosen) > 1)
            at += n
        if at < total:
            raise ValueError("scan data ends early")
        return
    c, _, table = chosen[0]
    band = np.ascontiguousarray(c.coefficients[: c.down, : c.across, ss : se + 1]).reshape(-1, se - ss + 1)
    for segment in segments:
        n = min(interval or len(band), len(band) - at)
        (_ac_refine if ah else _ac_first)(band[at : at + n], table, _Bits(segment), al)
        at += n
    if at < len(band):
        raise ValueError("scan data ends early")
    c.coefficients[: c.down, : c.across, ss : se + 1] = band.reshape(c.down, c.across, -1)


def _dc_segment(chosen: list, units: list, columns: int, first: int, n: int, bits: _Bits, ah: int, al: int, joined: bool) -> None:
    per = sum(len(cells) for _, _, cells in units)
    if ah:
        values = bits.many(n * per).astype(np.int16) << al
    else:
        tables, previous, values, owner = [], [0] * len(units), [], [i for i, _, cells in units for _ in cells]
        tables = [chosen[i][1] for i in owner]
        if all(t.one_bit == 0 for t in tables) and n * per <= bits.end and not bits.many(n * per).any():
            values = np.zeros(n * per, np.int16)
        else:
            bits.at = 0
            for k in range(n * per):
                i = owner[k % per]
                size = bits.symbol(tables[k % per])
                previous[i] += _extend(bits.take(size), size)
                values.append(previous[i])
            values = (np.array(values, np.int32) << al).astype(np.int16)
    values = values.reshape(n, per)
    unit = np.arange(first, first + n)
    rows, across, k = unit // columns, unit % columns, 0
    for _, c, cells in units:
        for r, q in cells:
            target = c.coefficients[:, :, 0]
            place = (rows * c.v + r, across * c.h + q) if joined else (rows, across)
            if ah:
                target[place] |= values[:, k]
            else:
                target[place] = values[:, k]
            k += 1


def _ac_first(band: np.ndarray, table: Huffman, bits: _Bits, al: int) -> None:
    blocks, width = band.shape
    n = blocks * width
    one = table.one_bit
    if one is not None and one == 7 and bits.end >= 8 * n:  # a zero bit and seven more, a byte each
        data = np.frombuffer(bits.data, np.uint8, n)
        if data.max(initial=0) < 128:
            x = data.astype(np.int16)
            x -= np.where(x < 64, 127, 0).astype(np.int16)
            band[:] = (x << al).reshape(band.shape)
            return
    run = 0
    for b in range(blocks):
        if run:
            run -= 1
            continue
        k, row = 0, band[b]
        while k < width:
            s = bits.symbol(table)
            zeros, size = s >> 4, s & 15
            if size:
                k += zeros
                if k >= width:
                    raise ValueError("run beyond the band")
                row[k] = _extend(bits.take(size), size) << al
                k += 1
            elif zeros == 15:
                k += 16
            else:
                run = (1 << zeros) - 1 + bits.take(zeros)
                break


def _ac_refine(band: np.ndarray, table: Huffman, bits: _Bits, al: int) -> None:
    blocks, width = band.shape
    step = 1 << al

    def correct(part: np.ndarray) -> None:
        """One bit for each coefficient of ``part`` that is not zero."""
        held = part != 0
        own = bits.many(int(held.sum())).astype(np.int16) << al
        part[held] += np.where(part[held] > 0, own, -own)

    b = 0
    while b < blocks:
        row, k = band[b], 0
        while k < width:
            s = bits.symbol(table)
            zeros, size = s >> 4, s & 15
            if not size and zeros < 15:
                run = (1 << zeros) + bits.take(zeros)
                correct(row[k:])
                more = band[b + 1 : b + run]
                correct(more)
                b += len(more)
                break
            if size > 1:
                raise ValueError("a refining scan adds one bit")
            new = (step if bits.take(1) else -step) if size else 0
            start = k
            while k < width and (row[k] != 0 or zeros > 0):
                zeros -= int(row[k] == 0)
                k += 1
            if not size and k < width:
                k += 1  # the sixteenth zero
            correct(row[start : min(k, width)])
            if size:
                if k >= width:
                    raise ValueError("run beyond the band")
                row[k] = new
                k += 1
        b += 1


def decode(data: bytes) -> Picture:
    """All scans of a progressive JPEG."""
    if data[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG")
    picture, at = Picture(), 2
    dc: dict[int, Huffman] = {}
    ac: dict[int, Huffman] = {}
    while True:
        if at + 2 > len(data) or data[at] != 0xFF:
            raise ValueError("a marker was due")
        marker = data[at + 1]
        if marker == 0xFF:
            at += 1
            continue
        if marker == 0xD9:
            return picture
        size = struct.unpack_from(">H", data, at + 2)[0]
        body, at = data[at + 4 : at + 2 + size], at + 2 + size
        if marker == 0xC2:
            depth, picture.height, picture.width, n = struct.unpack_from(">BHHB", body)
            if depth != 8:
                raise ValueError("samples of 8 bits are needed")
            if n not in (1, 3) or not picture.height or not picture.width:
                raise ValueError("one or three components and a size are needed")
            picture.components = [Component(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(n)]
            if n == 1:
                picture.components[0].h = picture.components[0].v = 1
            for c in picture.components:
                c.size(picture.width, picture.height, max(x.h for x in picture.components), max(x.v for x in picture.components))
        elif 0xC0 <= marker <= 0xCF and marker not in (0xC4, 0xC8, 0xCC):
            raise ValueError("not a progressive JPEG")
        elif marker == 0xC4:
            k = 0
            while k < len(body):
                n = sum(body[k + 1 : k + 17])
                (ac if body[k] >> 4 else dc)[body[k] & 15] = _huffman(body[k + 1 : k + 17], body[k + 17 : k + 17 + n])
                k += 17 + n
        elif marker == 0xDB:
            k = 0
            while k < len(body):
                wide = body[k] >> 4
                picture.quant[body[k] & 15] = np.frombuffer(body, ">u2" if wide else np.uint8, 64, k + 1).astype(np.int32)
                k += 1 + 64 * (1 + wide)
        elif marker == 0xDD:
            picture.interval = struct.unpack(">H", body)[0]
        elif marker == 0xFE:
            picture.comments.append(body)
        elif marker == 0xDA:
            n, by_name = body[0], {c.name: c for c in picture.components}
            chosen = [(by_name[body[1 + 2 * i]], dc.get(body[2 + 2 * i] >> 4), ac.get(body[2 + 2 * i] & 15)) for i in range(n)]
            ss, se, a = body[1 + 2 * n], body[2 + 2 * n], body[3 + 2 * n]
            segments, start = [], at
            while True:
                at = data.find(b"\xff", at)
                if at < 0 or at + 1 >= len(data):
                    raise ValueError("scan data ends early")
                follow = data[at + 1]
                if follow == 0:
                    at += 2
                elif 0xD0 <= follow <= 0xD7:
                    segments.append(data[start:at].replace(b"\xff\0", b"\xff"))
                    at += 2
                    start = at
                elif follow == 0xFF:
                    at += 1
                else:
                    break
            segments.append(data[start:at].replace(b"\xff\0", b"\xff"))
            _scan(picture, chosen, ss, se, a >> 4, a & 15, segments)


def _segment(marker: int, body: bytes) -> bytes:
    return bytes((0xFF, marker)) + struct.pack(">H", len(body) + 2) + body


def _codes(kind: int, symbols_by_length: dict[int, list[int]]) -> bytes:
    return bytes([kind]) + bytes(len(symbols_by_length.get(n, [])) for n in range(1, 17)) + bytes(s for n in range(1, 17) for s in symbols_by_length.get(n, []))


#: Band coefficients of seven more bits have the one-bit code; ends of bands, in runs of 2**n blocks, have five bits.
_AC_LENGTHS = {1: [0x07], 5: [n << 4 for n in range(15)]}
_HEAD = _segment(0xDB, b"\0" + bytes([1] * 64)) + _segment(0xC4, _codes(0x00, {1: [0], 4: list(range(1, 8))}) + _codes(0x10, _AC_LENGTHS))
_BANDS = ((1, 5), (6, 63))


def store(payload: bytes, n_bytes: int) -> bytes:
    """A progressive picture, chroma at half resolution, whose coefficients are the payload."""
    blocks = -(-len(payload) // 63)
    units = max(1, -(-blocks // 6))
    down = -(-units // 64) if units <= 64 * 4095 else 4095
    across = -(-units // down)
    if across > 4095:
        raise ValueError("more bytes than one picture holds")
    m = across * down
    cells = np.full(m * 6 * 63, 32, np.uint8)
    cells[: len(payload)] = np.frombuffer(payload, np.uint8)
    cells = cells.reshape(-1, 63)
    parts = (cells[: 4 * m], cells[4 * m : 5 * m], cells[5 * m :])
    out = [b"\xff\xd8", _segment(0xFE, struct.pack(">QQ", len(payload), n_bytes)), _HEAD]
    out.append(_segment(0xC2, struct.pack(">BHHB", 8, 16 * down, 16 * across, 3) + bytes([1, 0x22, 0, 2, 0x11, 0, 3, 0x11, 0])))
    out.append(_segment(0xDA, bytes([3, 1, 0, 2, 0, 3, 0, 0, 0, 0x01])))
    flat = bytes(-(-6 * m // 8))
    out.append(flat if 6 * m % 8 == 0 else flat[:-1] + bytes([(1 << (-6 * m % 8)) - 1]))
    for name, part in enumerate(parts, 1):
        half = part >> 1
        for a, b in _BANDS:
            out += [_segment(0xDA, bytes([1, name, 0, a, b, 0x01])), half[:, a - 1 : b].tobytes()]
    for name, part in enumerate(parts, 1):
        low = (part & 1) ^ (part < 128)
        bits = []
        for s in range(0, len(part), 32767):
            some = low[s : s + 32767]
            n = len(some).bit_length() - 1
            head = (0b10000 + n) << n | len(some) - (1 << n)
            bits += [np.array([head >> k & 1 for k in range(4 + n, -1, -1)], np.uint8), some.ravel()]
        bits.append(np.ones(-sum(map(len, bits)) % 8, np.uint8))
        out += [_segment(0xDA, bytes([1, name, 0, 1, 63, 0x10])), np.packbits(np.concatenate(bits)).tobytes().replace(b"\xff", b"\xff\0")]
    out.append(b"\xff\xd9")
    return b"".join(out)


def restore(picture: Picture) -> bytes:
    """The payload of a stored picture."""
    n, _ = struct.unpack(">QQ", picture.comments[0])
    x = np.concatenate([c.coefficients.reshape(-1, 64)[:, 1:] for c in picture.components])
    return np.where(x < 0, x + 255, x).astype(np.uint8).tobytes()[:n]


def summary(tensor: np.ndarray) -> str:
    """Size, mean and spread by channel of an RGB tensor."""
    flat = tensor.reshape(-1, 3)
    n = len(flat)
    means, spreads = [], []
    for k in range(3):
        seen = np.bincount(flat[:, k], minlength=256)
        level = np.arange(256)
        mean = float((seen * level).sum()) / n
        means.append(f"{mean:.3f}")
        spreads.append(f"{max(0.0, float((seen * level * level).sum()) / n - mean * mean) ** 0.5:.3f}")
    return f"{tensor.shape[1]}x{tensor.shape[0]};mean={','.join(means)};sd={','.join(spreads)}"


def decode_column(media: DataFrame, media_col: str = "media", keep: list[str] | None = None) -> DataFrame:
    """``height, width, rgb`` (row-major bytes) of each progressive JPEG, beside the columns to keep."""
    kept = media.select(*(keep or []), F.col(media_col).alias("_media"))
    names = kept.columns[:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(whole.num_rows):  # a picture at a time: tensors are large
                b = whole.slice(at, 1)
                raw = b.column(len(names))[0].as_py()
                t = None if raw is None else decode(raw).rgb()
                yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(names))), pa.array([None if t is None else t.shape[0]], pa.int32()), pa.array([None if t is None else t.shape[1]], pa.int32()), pa.array([None if t is None else t.tobytes()], pa.binary())], names=[*names, "height", "width", "rgb"])

    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in kept.schema.fields[:-1])
    return kept.mapInArrow(run, f"{fields}height int, width int, rgb binary")


_DIGEST = [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())]


def digest(text: str | None) -> tuple:
    """Store a text as a picture, read the stored bytes back, and describe both."""
    raw = (text or "").encode("utf-8", "replace")
    n = len(raw)
    raw += b" " * ((-n % UNIT) if n else UNIT)
    media = store(raw, n)
    picture = decode(media)
    payload = restore(picture)
    return n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest(), summary(picture.rgb())


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: what was stored, read back and computed."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                b = whole.slice(at, 256)
                rows = [digest(t.as_py()) for t in b.column(1)]
                yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(x, kind) for x, (_, kind) in zip(zip(*rows), _DIGEST[1:]))], schema=pa.schema(_DIGEST))

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    return store_texts(table(spark, sf_dir, "documents"))
