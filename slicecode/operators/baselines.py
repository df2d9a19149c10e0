"""Classical compressors as baselines: gzip, PNG and FLAC written from their public specifications, with decoders."""

from __future__ import annotations

import gzip
import struct
import zlib
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

# --- gzip -------------------------------------------------------------------------------------------------------


def gzip_bytes(data: bytes, level: int = 9) -> bytes:
    return gzip.compress(data, level, mtime=0)


def zlib_segment(data: bytes, before: bytes = b"", level: int = 9) -> bytes:
    """Raw deflate of a segment whose window is primed with the end of the segment before: long streams in bounded memory."""
    c = zlib.compressobj(level, zlib.DEFLATED, -15, 9, zlib.Z_DEFAULT_STRATEGY, before[-32768:]) if before else zlib.compressobj(level, zlib.DEFLATED, -15)
    return c.compress(data) + c.flush()


# --- PNG: one 8-bit gray channel ----------------------------------------------------------------------------------

SIGNATURE = bytes([137, 80, 78, 71, 13, 10, 26, 10])


def _paeth(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> np.ndarray:
    p = a + b - c
    pa_, pb, pc = abs(p - a), abs(p - b), abs(p - c)
    return np.where((pa_ <= pb) & (pa_ <= pc), a, np.where(pb <= pc, b, c))


def filtered_rows(rows: np.ndarray) -> np.ndarray:
    """Residuals of all rows under the kinds 0 to 4 (none, left, above, mean of both, nearest of three), modulo 256. The guesses
    come from the raw rows, so all rows are filtered at once."""
    x = rows.astype(np.int16)
    b = np.concatenate((np.zeros((1, x.shape[1]), np.int16), x[:-1]))
    left = lambda v: np.concatenate((np.zeros((len(v), 1), np.int16), v[:, :-1]), axis=1)
    a, c = left(x), left(b)
    return np.stack([((x - guess) & 255).astype(np.uint8) for guess in (np.zeros_like(x), a, b, (a + b) // 2, _paeth(a, b, c))])


def png_bytes(data: bytes, width: int = 128, adaptive: bool = True) -> bytes:
    """A gray image of rows of ``width`` bytes (the last one padded with zeros). The row's filter is the one with the least
    sum of absolute signed residuals, the lower number at ties; without ``adaptive`` none is used."""

    def chunk(kind: bytes, body: bytes) -> bytes:
        return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))

    width = max(1, min(width, len(data) or 1))
    rows = np.frombuffer(data + bytes(-len(data) % width), np.uint8).reshape(-1, width)
    packer, body, above = zlib.compressobj(9), [], np.zeros((1, width), np.uint8)
    for at in range(0, len(rows), 8192):  # bounded memory for large images
        part = np.concatenate((above, rows[at : at + 8192]))
        options = filtered_rows(part)[:, 1:] if adaptive else part[None, 1:]
        kind = np.abs(options.view(np.int8).astype(np.int32)).sum(axis=2).argmin(axis=0)
        chosen = options[kind, np.arange(len(kind))]
        body.append(packer.compress(np.concatenate((kind[:, None].astype(np.uint8), chosen), axis=1).tobytes()))
        above = part[-1:]
    body.append(packer.flush())
    head = struct.pack(">IIBBBBB", width, max(1, len(rows)), 8, 0, 0, 0, 0)
    return SIGNATURE + chunk(b"IHDR", head) + chunk(b"IDAT", b"".join(body)) + chunk(b"IEND", b"")


def png_pixels(image: bytes) -> bytes:
    """The rows of an image that ``png_bytes`` wrote, checksums verified."""
    at, body, width = 8, b"", 0
    while at < len(image):
        (size,) = struct.unpack(">I", image[at : at + 4])
        kind, data = image[at + 4 : at + 8], image[at + 8 : at + 8 + size]
        if struct.unpack(">I", image[at + 8 + size : at + 12 + size])[0] != zlib.crc32(kind + data):
            raise ValueError("checksum")
        if kind == b"IHDR":
            (width,) = struct.unpack(">I", data[:4])
        elif kind == b"IDAT":
            body += data
        at += 12 + size
    lines, up, out = zlib.decompress(body), [0] * width, []
    for y in range(0, len(lines), width + 1):
        kind, row = lines[y], []
        for x, r in enumerate(lines[y + 1 : y + 1 + width]):
            a, b, c = row[x - 1] if x else 0, up[x], up[x - 1] if x else 0
            p = a + b - c
            near = a if abs(p - a) <= abs(p - b) and abs(p - a) <= abs(p - c) else b if abs(p - b) <= abs(p - c) else c
            row.append((r + (0, a, b, (a + b) // 2, near)[kind]) & 255)
        out.append(bytes(row))
        up = row
    return b"".join(out)


# --- FLAC: one channel, fixed predictors, partitioned Rice -------------------------------------------------------------


class _Bits:
    def __init__(self) -> None:
        self.parts: list[str] = []

    def put(self, value: int, n: int) -> None:
        if n:
            self.parts.append(format(value & (1 << n) - 1, f"0{n}b"))

    def bytes(self) -> bytes:
        s = "".join(self.parts)
        s += "0" * (-len(s) % 8)
        return int(s, 2).to_bytes(len(s) // 8, "big") if s else b""


def _crc(data: bytes, poly: int, width: int) -> int:
    r, top = 0, 1 << width - 1
    for byte in data:
        r ^= byte << width - 8
        for _ in range(8):
            r = (r << 1 ^ poly if r & top else r << 1) & (1 << width) - 1
    return r


def zigzag(r: np.ndarray) -> np.ndarray:
    return np.where(r >= 0, 2 * r, -2 * r - 1)


def rice_choice(residual: np.ndarray) -> tuple[int, int]:
    """(k, bits) of the cheapest Rice code of the residuals, k in 0 to 14."""
    u = zigzag(residual.astype(np.int64))
    costs = [int((u >> k).sum()) + len(u) * (1 + k) for k in range(15)]
    k = int(np.argmin(costs))
    return k, costs[k]


def predictor_choice(block: np.ndarray) -> tuple[int, np.ndarray]:
    """(order, residuals) of the fixed predictor whose Rice cost, warm-up samples included, is least."""
    best = None
    for order in range(min(4, len(block) - 1) + 1):
        r = np.diff(block, order) if order else block
        cost = rice_choice(r)[1] + order * 16
        if best is None or cost < best[0]:
            best = (cost, order, r)
    return best[1], best[2]


def flac_bytes(samples: np.ndarray, bits: int = 16, rate: int = 16000, block: int = 4096) -> bytes:
    """A one-channel stream of signed samples: constant or fixed-predictor subframes, one Rice partition."""
    samples = np.asarray(samples, np.int64)
    info = _Bits()
    for value, n in ((block, 16), (block, 16), (0, 24), (0, 24), (rate, 20), (0, 3), (bits - 1, 5), (len(samples), 36), (0, 128)):
        info.put(value, n)
    out = [b"fLaC", bytes([0x80, 0, 0, 34]), info.bytes()]
    for number, at in enumerate(range(0, len(samples), block)):
        x = samples[at : at + block]
        head = _Bits()
        for value, n in ((0x3FFE, 14), (0, 1), (0, 1), (7, 4), (0, 4), (0, 4), ({8: 1, 16: 4}[bits], 3), (0, 1)):
            head.put(value, n)
        raw = head.bytes() + _utf8_number(number) + struct.pack(">H", len(x) - 1)
        raw += bytes([_crc(raw, 0x07, 8)])
        body = _Bits()
        if (x == x[0]).all():
            body.put(0, 8)
            body.put(int(x[0]), bits)
        else:
            order, residual = predictor_choice(x)
            k, _ = rice_choice(residual)
            body.put(8 + order << 1, 8)
            for s in x[:order]:
                body.put(int(s), bits)
            body.put(0, 2)
            body.put(0, 4)
            body.put(k, 4)
            for u in zigzag(residual).tolist():
                body.parts.append("0" * (u >> k) + "1")
                body.put(u, k)
        raw += body.bytes()
        out.append(raw + struct.pack(">H", _crc(raw, 0x8005, 16)))
    return b"".join(out)


def flac_length(samples: np.ndarray, bits: int = 16, block: int = 4096) -> int:
    """The length of ``flac_bytes`` without writing the bits: a Rice code's cost is its length."""
    samples, total = np.asarray(samples, np.int64), 42
    for number, at in enumerate(range(0, len(samples), block)):
        x = samples[at : at + block]
        body = 8 + bits
        if not (x == x[0]).all():
            order, residual = predictor_choice(x)
            body = 18 + order * bits + rice_choice(residual)[1]
        total += 4 + len(_utf8_number(number)) + 3 + (body + 7) // 8 + 2
    return total


def _utf8_number(n: int) -> bytes:
    """Frame numbers are written as UTF-8 writes code points."""
    if n < 0x80:
        return bytes([n])
    tail = []
    while n >= 1 << 6 - len(tail) - 0 or not tail:
        tail.insert(0, 0x80 | n & 63)
        n >>= 6
        if n < 1 << 6 - len(tail):
            break
    return bytes([(0xFF << 7 - len(tail) & 0xFF) | n, *tail])


def flac_samples(stream: bytes) -> np.ndarray:
    """The samples of a stream that ``flac_bytes`` wrote, checksums verified."""
    if stream[:4] != b"fLaC":
        raise ValueError("signature")
    info = int.from_bytes(stream[8:42], "big")
    bits, total = (info >> 164 & 31) + 1, info >> 128 & (1 << 36) - 1
    at, out = 42, []
    while sum(map(len, out)) < total:
        start = at
        at += 4
        lead = stream[at]
        at += 1 if lead < 0x80 else 8 - (lead ^ 0xFF).bit_length()
        size = struct.unpack(">H", stream[at : at + 2])[0] + 1
        if _crc(stream[start : at + 2], 0x07, 8) != stream[at + 2]:
            raise ValueError("header checksum")
        at += 3
        text, pos = "".join(format(b, "08b") for b in stream[at : at + size * 8 + 64]), 0

        def take(n: int) -> int:
            nonlocal pos
            pos += n
            return int(text[pos - n : pos], 2) if n else 0

        def signed(n: int) -> int:
            v = take(n)
            return v - (1 << n) if v >> n - 1 else v

        kind = take(8) >> 1
        if kind == 0:
            x = [signed(bits)] * size
        else:
            order = kind - 8
            x = [signed(bits) for _ in range(order)]
            take(6)
            k = take(4)
            for _ in range(size - order):
                stop = text.index("1", pos)
                u, pos = stop - pos, stop + 1
                u = u << k | take(k)
                r = u >> 1 if not u & 1 else -(u + 1 >> 1)
                y = x
                x.append(r + (0, y and y[-1], len(y) > 1 and 2 * y[-1] - y[-2], len(y) > 2 and 3 * y[-1] - 3 * y[-2] + y[-3], len(y) > 3 and 4 * y[-1] - 6 * y[-2] + 4 * y[-3] - y[-4])[order])
        at += (pos + 7) // 8
        if _crc(stream[start:at], 0x8005, 16) != struct.unpack(">H", stream[at : at + 2])[0]:
            raise ValueError("frame checksum")
        at += 2
        out.append(np.array(x, np.int64))
    return np.concatenate(out) if out else np.zeros(0, np.int64)


# --- as columns ---------------------------------------------------------------------------------------------------


def _measured(length: Callable[[bytes], int]):
    @F.pandas_udf("long")
    def size(values: pd.Series) -> pd.Series:
        return values.map(lambda v: None if v is None else length(bytes(v)))

    return size


def _size_of(compress: Callable[[bytes], bytes]):
    return _measured(lambda b: len(compress(b)))


def gzip_size(data: Column, level: int = 9) -> Column:
    return _size_of(lambda b: gzip_bytes(b, level))(data)


def png_size(data: Column, width: int = 128, adaptive: bool = True) -> Column:
    return _size_of(lambda b: png_bytes(b, width, adaptive))(data)


def _flac_of(data: bytes, bits: int, block: int = 4096) -> int:
    """16 bits: little-endian signed pairs; 8 bits: unsigned bytes, shifted by 128."""
    return flac_length(np.frombuffer(data[: len(data) // 2 * 2], "<i2") if bits == 16 else np.frombuffer(data, np.uint8).astype(np.int64) - 128, bits, block=block)


def flac_size(data: Column, bits: int = 16, block: int = 4096) -> Column:
    return _measured(lambda b: _flac_of(b, bits, block))(data)


def source_sizes(data: Column, source: Column) -> Column:
    """A struct of gzip, png and flac sizes: tiles have rows of 64 bytes, all else of 128; the sampled source has 16-bit samples,
    all else 8-bit ones. One pass over the bytes."""

    @F.pandas_udf("gzip long, png long, flac long")
    def sizes(values: pd.Series, sources: pd.Series) -> pd.DataFrame:
        rows = [(bytes(v), s) for v, s in zip(values, sources, strict=True)]
        return pd.DataFrame({"gzip": [len(gzip_bytes(v)) for v, _ in rows], "png": [len(png_bytes(v, 64 if s == "gray_patches" else 128)) for v, s in rows], "flac": [_flac_of(v, 16 if s == "sample_series" else 8) for v, s in rows]}, dtype="int64")

    return sizes(data, source)
