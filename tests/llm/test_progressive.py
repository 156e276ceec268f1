import hashlib
import random
import struct
import zlib

import numpy as np
import pytest
from pyspark.sql import types as T

from patternwalk.llm import progressive as P

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("feature", T.StringType()), T.StructField("n_bytes", T.StringType())])


class Writer:
    """A plain encoder: eight-bit codes for all symbols, any scan script."""

    def __init__(self):
        self.bits = []

    def put(self, value, n):
        self.bits += [value >> k & 1 for k in range(n - 1, -1, -1)]

    def symbol(self, s):
        self.put(s + 1 if s < 255 else 0, 9)

    def data(self):
        bits = self.bits + [1] * (-len(self.bits) % 8)
        return np.packbits(np.array(bits, np.uint8)).tobytes().replace(b"\xff", b"\xff\0")


TABLE = [0] * 16
TABLE[8] = 255
CODES = bytes(TABLE) + bytes([255, *range(254)])  # nine bits: 255 is code 0, s is code s + 1


def size_of(v):
    return abs(v).bit_length()


def put_value(w, v):
    n = size_of(v)
    w.put(v if v >= 0 else v + (1 << n) - 1, n)


def shifted(v, al):
    return (abs(v) >> al) * (1 if v >= 0 else -1)


def ac_first(w, rows, al):
    run = 0

    def flush():
        nonlocal run
        while run:
            n = min(run, 32767).bit_length() - 1
            w.symbol(n << 4)
            w.put(min(run, 32767) - (1 << n), n)
            run -= min(run, 32767)

    for row in rows:
        zeros = 0
        for v in (shifted(int(x), al) for x in row):
            if not v:
                zeros += 1
                continue
            flush()
            while zeros > 15:
                w.symbol(0xF0)
                zeros -= 16
            w.symbol(zeros << 4 | size_of(v))
            put_value(w, v)
            zeros = 0
        run += zeros > 0
    flush()


def ac_refine(w, rows, al):
    pending, run = [], 0

    def flush():
        nonlocal run
        if run:
            n = run.bit_length() - 1
            w.symbol(n << 4)
            w.put(run - (1 << n), n)
            w.bits += pending
            pending.clear()
            run = 0

    for row in rows:
        mags = [abs(int(x)) >> al for x in row]
        last = max((k for k, m in enumerate(mags) if m == 1), default=-1)
        zeros, own = 0, []
        for k, m in enumerate(mags):
            if m == 0:
                zeros += 1
                continue
            while zeros > 15 and k <= last:
                flush()
                w.symbol(0xF0)
                w.bits += own
                own, zeros = [], zeros - 16
            if m > 1:
                own.append(m & 1)
                continue
            flush()
            w.symbol(zeros << 4 | 1)
            w.put(int(row[k] > 0), 1)
            w.bits += own
            own, zeros = [], 0
        if zeros or own:
            run += 1
            pending += own
    flush()


def encode(parts, factors, width, height, script, interval=0):
    """``parts``: padded coefficient arrays; ``script``: (component numbers, ss, se, ah, al)."""
    out = [b"\xff\xd8", P._segment(0xE0, b"other"), P._segment(0xDB, b"\0" + bytes(range(1, 65))), P._segment(0xC4, b"\0" + CODES + b"\x10" + CODES)]
    out.append(P._segment(0xC2, struct.pack(">BHHB", 8, height, width, len(parts)) + b"".join(bytes([i + 1, h << 4 | v, 0]) for i, (h, v) in enumerate(factors))))
    if interval:
        out.append(P._segment(0xDD, struct.pack(">H", interval)))
    mh, mv = max(h for h, _ in factors), max(v for _, v in factors)
    up = lambda a, b: -(-a // b)
    for chosen, ss, se, ah, al in script:
        out.append(P._segment(0xDA, bytes([len(chosen), *(x for i in chosen for x in (i + 1, 0)), ss, se, ah << 4 | al])))
        if len(chosen) > 1:
            units = [[(i, r * factors[i][1] + a, q * factors[i][0] + b) for i in chosen for a in range(factors[i][1]) for b in range(factors[i][0])] for r in range(up(height, 8 * mv)) for q in range(up(width, 8 * mh))]
        else:
            i = chosen[0]
            units = [[(i, r, q)] for r in range(up(up(height * factors[i][1], mv), 8)) for q in range(up(up(width * factors[i][0], mh), 8))]
        for n, s in enumerate(range(0, len(units), interval or len(units))):
            w, some = Writer(), units[s : s + (interval or len(units))]
            if ss:
                (ac_refine if ah else ac_first)(w, [parts[i][r, q, ss : se + 1] for u in some for i, r, q in u], al)
            else:
                before = [0] * len(parts)
                for i, r, q in (x for u in some for x in u):
                    v = int(parts[i][r, q, 0]) >> al
                    if ah:
                        w.put(v & 1, 1)
                    else:
                        w.symbol(size_of(v - before[i]))
                        put_value(w, v - before[i])
                        before[i] = v
            if n:
                out.append(bytes([0xFF, 0xD0 + (n - 1) % 8]))
            out.append(w.data())
    return b"".join([*out, b"\xff\xd9"])


def picture(rng, factors, width, height, density):
    mh, mv = max(h for h, _ in factors), max(v for _, v in factors)
    out = []
    for h, v in factors:
        a = np.zeros((-(-height // (8 * mv)) * v, -(-width // (8 * mh)) * h, 64), np.int16)
        a[:] = np.where(rng.random(a.shape) < density, rng.integers(-60, 61, a.shape), 0)
        # places beyond the picture are sent in joined scans only
        rows, columns = -(-(-(-height * v // mv)) // 8), -(-(-(-width * h // mh)) // 8)
        a[rows:, :, 1:] = 0
        a[:, columns:, 1:] = 0
        out.append(a)
    return out


@pytest.mark.parametrize("seed", range(8))
def test_any_scan_script_gives_the_coefficients_back(seed):
    rng = np.random.default_rng(seed)
    factors = [[(1, 1)], [(2, 2), (1, 1), (1, 1)], [(2, 1), (1, 1), (1, 1)], [(1, 1)] * 3][seed % 4]
    width, height = int(rng.integers(1, 70)), int(rng.integers(1, 70))
    parts = picture(rng, factors, width, height, [0.02, 0.2, 0.9][seed % 3])
    n = len(parts)
    script = [(list(range(n)), 0, 0, 0, 1)]
    for i in range(n):
        script += [([i], 1, 5, 0, 2), ([i], 6, 63, 0, 2)]
    script += [([i], 1, 63, 2, 1) for i in range(n)]
    script += [(list(range(n)), 0, 0, 1, 0)] + [([i], 1, 63, 1, 0) for i in range(n)]
    got = P.decode(encode(parts, factors, width, height, script, interval=[0, 3][seed // 4]))
    for c, a in zip(got.components, parts):
        if n == 1:
            a, c.coefficients = a[: c.down, : c.across], c.coefficients[: c.down, : c.across]
        assert np.array_equal(c.coefficients, a)
    assert got.rgb().shape == (height, width, 3)


def test_tensor_against_the_cosine_sum():
    rng = np.random.default_rng(1)
    factors = [(2, 2), (1, 1), (1, 1)]
    parts = picture(rng, factors, 16, 16, 0.05)
    got = P.decode(encode(parts, factors, 16, 16, [([0, 1, 2], 0, 0, 0, 0), *[([i], 1, 63, 0, 0) for i in range(3)]])).rgb()
    planes = []
    for a in parts:
        plane = np.zeros((8 * a.shape[0], 8 * a.shape[1]))
        for r in range(a.shape[0]):
            for q in range(a.shape[1]):
                f = np.zeros(64)
                f[P.ZIGZAG] = a[r, q] * np.arange(1, 65)
                f = f.reshape(8, 8)
                for y in range(8):
                    for x in range(8):
                        plane[8 * r + y, 8 * q + x] = sum((0.5**0.5 if u == 0 else 1) * (0.5**0.5 if v == 0 else 1) * f[v, u] * np.cos((2 * x + 1) * u * np.pi / 16) * np.cos((2 * y + 1) * v * np.pi / 16) for u in range(8) for v in range(8)) / 4
        planes.append(np.clip(plane + 128, 0, 255))
    y, cb, cr = planes[0], planes[1].repeat(2, 0).repeat(2, 1) - 128, planes[2].repeat(2, 0).repeat(2, 1) - 128
    want = np.stack([y + 1.402 * cr, y - 0.344136 * cb - 0.714136 * cr, y + 1.772 * cb], axis=2).clip(0, 255)
    assert np.abs(got - want).max() <= 0.51


@pytest.mark.parametrize("n", [1, 2, 3, 100, 40_000])
def test_payloads_round_trip(n):
    raw = random.Random(n).randbytes(192 * n)
    assert P.restore(P.decode(P.store(raw, len(raw)))) == raw


def test_broken_files_are_refused():
    good = P.store(b"x" * 192, 1)
    for bad in (b"", b"\xff\xd8", good[:200], good[:-2], good.replace(b"\xff\xc2", b"\xff\xc0")):
        with pytest.raises(ValueError):
            P.decode(bad)


def test_texts(spark):
    texts = [None, "", "a", "é" * 96, "x" * 192, "long text " * 30_000, "a"]
    rows = [(i, t, "clash", "clash") for i, t in enumerate(texts)]
    got = {r.doc_id: r for r in P.store_texts(spark.createDataFrame(rows, SCHEMA)).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        padded = raw + b" " * (max(192, -(-len(raw) // 192) * 192) - len(raw))
        r = got[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-16:]))
        media = P.store(padded, len(raw))
        assert (r.media_bytes, r.media_sha256, r.feature) == (len(media), hashlib.sha256(media).hexdigest(), P.summary(P.decode(media).rgb()))
    assert got[0][1:] == got[1][1:] and got[2][1:] == got[6][1:]
    assert P.store_texts(spark.createDataFrame([], SCHEMA)).count() == 0
    media = spark.createDataFrame([(1, bytearray(P.store(b"x" * 192, 1)), 5), (2, None, 5)], "id long, media binary, width long").select("id", "media")
    assert sorted((r.id, r.height, None if r.rgb is None else len(r.rgb)) for r in P.decode_column(media, keep=["id"]).collect()) == [(1, 16, 768), (2, None, None)]
