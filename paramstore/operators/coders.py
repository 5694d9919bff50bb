"""The baselines as coders of blocks: encode(payload, dtype) and decode(data, dtype) for each, so that their round trip and speed can be taken.

A block is coded alone. Lossless coders give every bit back; lossy ones keep the bound of unit packing (half keeps its own, pruning and
uniform quantization theirs). Fields of single bits go through put() and take(), which work on whole arrays; only the two coders whose
next field's width hangs on the last one's (the XOR coders) are decoded value by value.
"""

from __future__ import annotations

import struct
import zlib
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa

from paramstore.functions.bits import BOUND, STORED, VIEW, WIDTH
from paramstore.operators import distance, unitpack
from paramstore.operators.codecs import ROUNDED
from paramstore.operators.kernels import bit_width

UNSIGNED = {"float16": np.uint16, "float32": np.uint32, "float64": np.uint64}


def put(values: np.ndarray, widths: np.ndarray) -> bytes:
    """The lowest widths[i] bits of each value, highest first, one after the other."""
    values, ends = values.astype(np.uint64), np.cumsum(widths.astype(np.int64))
    stream = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    for k in range(int(widths.max(initial=0))):
        own = np.flatnonzero(widths > k)
        stream[ends[own] - 1 - k] = values[own] >> np.uint64(k) & np.uint64(1)
    return np.packbits(stream).tobytes()


def take(data: bytes, widths: np.ndarray) -> np.ndarray:
    """The values that put() was given, as unsigned numbers."""
    widths = widths.astype(np.int64)
    ends, out = np.cumsum(widths), np.zeros(len(widths), np.uint64)
    stream = np.unpackbits(np.frombuffer(data, np.uint8))
    for k in range(int(widths.max(initial=0))):
        own = np.flatnonzero(widths > k)
        out[own] |= stream[ends[own] - 1 - k].astype(np.uint64) << np.uint64(k)
    return out


def parts(*data: bytes) -> bytes:
    return struct.pack(f"<B{len(data)}I", len(data), *map(len, data)) + b"".join(data)


def split(data: bytes) -> list[bytes]:
    n = data[0]
    at, out = 1 + 4 * n, []
    for size in struct.unpack_from(f"<{n}I", data, 1):
        out.append(data[at : at + size])
        at += size
    return out


def zigzag(x: np.ndarray) -> np.ndarray:
    return ((x << 1) ^ (x >> 63)).view(np.uint64)


def unzigzag(z: np.ndarray) -> np.ndarray:
    return (z >> np.uint64(1)).view(np.int64) ^ -(z & np.uint64(1)).view(np.int64)


def gzip_encode(p: bytes, dtype: str) -> bytes:
    return zlib.compress(p, 6, 31)


def gzip_decode(data: bytes, dtype: str) -> bytes:
    return zlib.decompress(data, 31)


def pgzip_encode(p: bytes, dtype: str, threads: int = 4, part: int = 1 << 14) -> bytes:
    """Independent members, compressed by threads."""
    with ThreadPoolExecutor(threads) as pool:
        return b"".join(pool.map(lambda at: zlib.compress(p[at : at + part], 6, 31), range(0, max(len(p), 1), part)))


def pgzip_decode(data: bytes, dtype: str) -> bytes:
    out = []
    while data:
        member = zlib.decompressobj(31)
        out.append(member.decompress(data))
        data = member.unused_data
    return b"".join(out)


def zstd_encode(p: bytes, dtype: str, level: int = 3) -> bytes:
    return len(p).to_bytes(8, "little") + pa.Codec("zstd", compression_level=level).compress(p, asbytes=True)


def zstd_decode(data: bytes, dtype: str) -> bytes:
    n = int.from_bytes(data[:8], "little")
    return pa.Codec("zstd").decompress(data[8:], n, asbytes=True) if n else b""


def zstd_threads_encode(p: bytes, dtype: str, threads: int = 4) -> bytes:
    import zstandard

    return len(p).to_bytes(8, "little") + zstandard.ZstdCompressor(level=3, threads=threads).compress(p)


def unit_encode(p: bytes, dtype: str) -> bytes:
    return unitpack.pack(np.frombuffer(p, VIEW[dtype][1]), dtype)


def unit_decode(data: bytes, dtype: str) -> bytes:
    return unitpack.unpack(data, dtype).astype(VIEW[dtype][1]).tobytes()


def de_encode(p: bytes, dtype: str) -> bytes:
    return distance.encode(np.frombuffer(p, STORED[dtype]).astype(np.int64), dtype)


def de_decode(data: bytes, dtype: str) -> bytes:
    return distance.decode(data, dtype).astype(STORED[dtype]).tobytes()


def half_encode(p: bytes, dtype: str) -> bytes:
    with np.errstate(over="ignore"):
        return np.frombuffer(p, VIEW[dtype][0]).astype(np.float16).tobytes()


def half_decode(data: bytes, dtype: str) -> bytes:
    return np.frombuffer(data, np.float16).astype(VIEW[dtype][0]).tobytes()


def mp_encode(p: bytes, dtype: str, times: float = 1.0) -> bytes:
    """A mask, and the values that are not below the bound."""
    v = np.frombuffer(p, VIEW[dtype][0])
    kept = ~(np.abs(v) < BOUND[dtype] * times)
    return parts(struct.pack("<I", len(v)), np.packbits(kept).tobytes(), v[kept].tobytes())


def mp_decode(data: bytes, dtype: str) -> bytes:
    n, mask, values = split(data)
    kept = np.unpackbits(np.frombuffer(mask, np.uint8))[: struct.unpack("<I", n)[0]].astype(bool)
    out = np.zeros(len(kept), VIEW[dtype][0])
    out[kept] = np.frombuffer(values, VIEW[dtype][0])
    return out.tobytes()


def gouq_encode(p: bytes, dtype: str, times: float = 1.0) -> bytes:
    """Values within three standard deviations as steps of twice the bound from the least one; a mask, and the others raw."""
    v = np.frombuffer(p, VIEW[dtype][0])
    x = v.astype(np.float64)
    fine = np.isfinite(x)
    mean, spread = (x[fine].mean(), x[fine].std()) if fine.any() else (0.0, 0.0)
    step = 2 * BOUND[dtype] * times
    with np.errstate(invalid="ignore", over="ignore"):
        near = fine & (np.abs(x - mean) <= 3 * spread)
        low = x[near].min(initial=np.inf) if near.any() else 0.0
        index = np.floor((x - low) / step + 0.5)
        near &= index < 2.0**52
    index = np.where(near, index, 0).astype(np.uint64)[near]
    width = int(index.max(initial=0)).bit_length()
    return parts(struct.pack("<IBdd", len(v), width, low, step), np.packbits(near).tobytes(), put(index, np.full(len(index), width)), v[~near].tobytes())


def gouq_decode(data: bytes, dtype: str) -> bytes:
    head, mask, index, rest = split(data)
    n, width, low, step = struct.unpack("<IBdd", head)
    near = np.unpackbits(np.frombuffer(mask, np.uint8))[:n].astype(bool)
    out = np.zeros(n, VIEW[dtype][0])
    out[near] = low + take(index, np.full(int(near.sum()), width)).astype(np.float64) * step
    out[~near] = np.frombuffer(rest, VIEW[dtype][0])
    return out.tobytes()


def predquant_encode(p: bytes, dtype: str) -> bytes:
    """Multiples of twice the bound, predicted by the one before; residuals of 16 bits through zstd, farther ones and odd values apart."""
    v = np.frombuffer(p, VIEW[dtype][0])
    x = v.astype(np.float64)
    with np.errstate(invalid="ignore", over="ignore"):
        scaled = x / (2 * BOUND[dtype])
        fits = np.isfinite(scaled) & (np.abs(scaled) < 2.0**52)
    q = np.where(fits, np.floor(np.where(fits, scaled, 0) + 0.5), 0).astype(np.int64)
    z = zigzag(np.diff(q, prepend=0))
    far = z >= 0xFFFF
    codes = np.where(far, 0xFFFF, z).astype("<u2")
    width = int(z.max(initial=0)).bit_length()
    return parts(struct.pack("<IB", len(v), width), zstd_encode(codes.tobytes(), dtype), put(z[far], np.full(int(far.sum()), width)), np.packbits(fits).tobytes(), v[~fits].tobytes())


def predquant_decode(data: bytes, dtype: str) -> bytes:
    head, codes, far, mask, rest = split(data)
    n, width = struct.unpack("<IB", head)
    z = np.frombuffer(zstd_decode(codes, dtype), "<u2").astype(np.uint64)
    outside = z == 0xFFFF
    z[outside] = take(far, np.full(int(outside.sum()), width))
    with np.errstate(over="ignore"):
        out = (np.cumsum(unzigzag(z)).astype(np.float64) * (2 * BOUND[dtype])).astype(VIEW[dtype][0])
    fits = np.unpackbits(np.frombuffer(mask, np.uint8))[:n].astype(bool)
    out[~fits] = np.frombuffer(rest, VIEW[dtype][0])
    return out.tobytes()


def sprintz_encode(p: bytes, dtype: str) -> bytes:
    """Differences of patterns, in blocks of eight at the width of the widest; a byte a block for the width."""
    w = WIDTH[dtype]
    x = np.frombuffer(p, UNSIGNED[dtype])
    with np.errstate(over="ignore"):
        d = np.diff(x, prepend=x.dtype.type(0)).view(VIEW[dtype][1]).astype(np.int64)
    z = zigzag(d) if w < 64 else ((d << 1) ^ (d >> 63)).view(np.uint64)
    padded = np.zeros(-(-len(z) // 8) * 8, np.uint64)
    padded[: len(z)] = z
    widths = bit_width(padded).reshape(-1, 8).max(axis=1) if len(padded) else np.zeros(0, np.int64)
    return parts(struct.pack("<I", len(x)), widths.astype(np.uint8).tobytes(), put(padded, np.repeat(widths, 8)))


def sprintz_decode(data: bytes, dtype: str) -> bytes:
    n, widths, body = split(data)
    n = struct.unpack("<I", n)[0]
    z = take(body, np.repeat(np.frombuffer(widths, np.uint8).astype(np.int64), 8))[:n]
    with np.errstate(over="ignore"):
        return np.cumsum(unzigzag(z).astype(VIEW[dtype][1]).view(UNSIGNED[dtype]), dtype=UNSIGNED[dtype]).tobytes()


def buff_encode(p: bytes, dtype: str) -> bytes:
    """Fixed-point numbers above the least whole one, in byte columns; blocks with odd or too wide values stay raw."""
    v = np.frombuffer(p, VIEW[dtype][0])
    x = v.astype(np.float64)
    f = {"float16": 11, "float32": 24, "float64": 52}[dtype]
    low = np.floor(x.min()) if len(x) and np.isfinite(x).all() else np.nan
    if not len(x) or not np.isfinite(low) or np.abs(x).max() >= 2.0 ** (62 - f) or (x.max() - low) * 2.0**f >= 2.0**62:
        return parts(b"raw", p)
    whole = np.floor(x)
    fixed = ((whole - low).astype(np.int64) << f) + np.floor((x - whole) * 2.0**f + 0.5).astype(np.int64)
    size = max(1, -(-int(fixed.max()).bit_length() // 8))
    columns = fixed.astype(">i8").view(np.uint8).reshape(-1, 8)[:, 8 - size :].T
    return parts(struct.pack("<IBd", len(v), size, low), np.ascontiguousarray(columns).tobytes())


def buff_decode(data: bytes, dtype: str) -> bytes:
    head, body = split(data)
    if head == b"raw":
        return body
    n, size, low = struct.unpack("<IBd", head)
    f = {"float16": 11, "float32": 24, "float64": 52}[dtype]
    wide = np.zeros((n, 8), np.uint8)
    wide[:, 8 - size :] = np.frombuffer(body, np.uint8).reshape(size, n).T
    fixed = wide.view(">i8").ravel().astype(np.int64)
    return (low + (fixed >> f) + (fixed & ((1 << f) - 1)) / 2.0**f).astype(VIEW[dtype][0]).tobytes()


def szx_encode(p: bytes, dtype: str, block: int = 128) -> bytes:
    """Blocks that are constant within the bound as their middle; in others patterns without the bits that the bound allows to drop."""
    v = np.frombuffer(p, VIEW[dtype][0])
    w, eb, n = WIDTH[dtype], BOUND[dtype], len(v)
    m = {"float16": 10, "float32": 23, "float64": 52}[dtype]
    starts = np.arange(0, n, block)
    sizes = np.diff(np.append(starts, n))
    x = v.astype(np.float64)
    odd = np.logical_or.reduceat(~np.isfinite(x), starts) if n else np.zeros(0, bool)
    with np.errstate(invalid="ignore"):
        high, low = (np.maximum.reduceat(x, starts), np.minimum.reduceat(x, starts)) if n else (np.zeros(0), np.zeros(0))
        top = np.maximum(np.abs(high), np.abs(low))
    middle = ((high + low) / 2).astype(VIEW[dtype][0])
    with np.errstate(invalid="ignore"):
        constant = ~odd & (np.maximum(high - middle.astype(np.float64), middle.astype(np.float64) - low) <= eb)
    least = int(np.log2(eb))
    drop = np.where(odd | constant, 0, np.clip(m + least - np.frexp(np.where(np.isfinite(top), top, 1.0))[1] + 1, 0, m))
    each = np.repeat(np.where(constant, 0, w - drop), sizes)
    bits = v.view(UNSIGNED[dtype]).astype(np.uint64) >> np.repeat(drop, sizes).astype(np.uint64)
    return parts(struct.pack("<I", n), np.where(constant, 255, drop).astype(np.uint8).tobytes(), middle[constant].tobytes(), put(bits, each))


def szx_decode(data: bytes, dtype: str, block: int = 128) -> bytes:
    n, drop, middle, body = split(data)
    n, w = struct.unpack("<I", n)[0], WIDTH[dtype]
    drop = np.frombuffer(drop, np.uint8).astype(np.int64)
    sizes = np.diff(np.append(np.arange(0, n, block), n))
    constant = drop == 255
    each = np.repeat(np.where(constant, 0, w - drop), sizes)
    bits = take(body, each) << np.repeat(np.where(constant, 0, drop), sizes).astype(np.uint64)
    out = bits.astype(UNSIGNED[dtype]).view(VIEW[dtype][0]).copy()
    out[np.repeat(constant, sizes)] = np.repeat(np.frombuffer(middle, VIEW[dtype][0]), sizes[constant])
    return out.tobytes()


def pseudodecimal_encode(p: bytes, dtype: str, most: int = 22) -> bytes:
    """Digits of 31 bits with a sign and a power of ten for each value that has them; the others raw."""
    v = np.frombuffer(p, VIEW[dtype][0])
    x = v.astype(np.float64)
    exponent, digits = np.full(len(x), 31, np.uint8), np.zeros(len(x), np.int64)
    left = np.flatnonzero(np.isfinite(x) & ~((x == 0) & np.signbit(x)))
    for e in range(most + 1):
        scaled = x[left] * 10.0**e
        d = np.floor(scaled + 0.5)
        fits = (np.abs(scaled) < 2.0**31) & (np.abs(d) < 2.0**31) & (d / 10.0**e == x[left])
        exponent[left[fits]], digits[left[fits]] = e, d[fits].astype(np.int64)
        left = left[~fits]
        if not len(left):
            break
    there = exponent < 31
    z = zigzag(digits[there])
    width = int(z.max(initial=0)).bit_length()
    return parts(struct.pack("<IB", len(v), width), put(exponent, np.full(len(v), 5)), put(z, np.full(len(z), width)), v[~there].tobytes())


def pseudodecimal_decode(data: bytes, dtype: str) -> bytes:
    head, exponents, digits, rest = split(data)
    n, width = struct.unpack("<IB", head)
    exponent = take(exponents, np.full(n, 5)).astype(np.int64)
    there = exponent < 31
    out = np.zeros(n, VIEW[dtype][0])
    out[there] = unzigzag(take(digits, np.full(int(there.sum()), width))).astype(np.float64) / np.power(10.0, exponent[there])
    out[~there] = np.frombuffer(rest, VIEW[dtype][0])
    return out.tobytes()


def xors(p: bytes, dtype: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Patterns, XORs with the one before, and their leading and trailing zeros (of the width for zero)."""
    w, bits = WIDTH[dtype], np.frombuffer(p, UNSIGNED[dtype])
    x = (bits[1:] ^ bits[:-1]).astype(np.uint64)
    return bits, x, w - bit_width(x), np.where(x > 0, bit_width(x & (~x + np.uint64(1))) - 1, w)


def gorilla_encode(p: bytes, dtype: str) -> bytes:
    """XORs in a window of meaningful bits; only changes of the window are met one by one."""
    w = WIDTH[dtype]
    bits, x, leading, trail = xors(p, dtype)
    leading = np.minimum(leading, 31)
    n = len(x)
    lead, size, fresh = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, bool)
    some = np.flatnonzero(x)
    at = 0
    while at < len(some):
        i = some[at]
        window = int(leading[i]), int(w - leading[i] - trail[i])
        fresh[i] = True
        end, step = at + 1, 16
        while end < len(some):  # the next XOR that leaves the window
            ahead = some[end : end + step]
            out = np.flatnonzero((leading[ahead] < window[0]) | (trail[ahead] < w - window[0] - window[1]))
            if len(out):
                end += int(out[0])
                break
            end += len(ahead)
            step *= 2
        lead[some[at:end]], size[some[at:end]] = window
        at = end
    head_width = np.where(x == 0, 1, np.where(fresh, 13, 2))
    head = np.where(x == 0, 0, np.where(fresh, 3 << 11 | lead << 6 | size - 1, 2))
    body = np.where(x > 0, x >> (w - lead - size).astype(np.uint64), np.uint64(0))
    values, widths = np.empty(2 * n, np.uint64), np.empty(2 * n, np.int64)
    values[::2], values[1::2], widths[::2], widths[1::2] = head.astype(np.uint64), body, head_width, np.where(x > 0, size, 0)
    return parts(struct.pack("<I", len(bits)), bits[:1].tobytes(), put(values, widths))


class Reader:
    """Bits of a string of bytes, one field after the other."""

    def __init__(self, data: bytes):
        self.data, self.at = data, 0

    def __call__(self, width: int) -> int:
        first, end = self.at >> 3, (self.at + width + 7) >> 3
        chunk = int.from_bytes(self.data[first:end], "big")
        self.at += width
        return chunk >> (8 * end - self.at) & ((1 << width) - 1)


def gorilla_decode(data: bytes, dtype: str) -> bytes:
    n, first, body = split(data)
    n, w, read = struct.unpack("<I", n)[0], WIDTH[dtype], Reader(body)
    out = np.zeros(n, UNSIGNED[dtype])
    if n:
        last = int(np.frombuffer(first, UNSIGNED[dtype])[0])
        out[0], lead, size = last, 0, 0
        for i in range(1, n):
            if read(1):
                if read(1):
                    lead, size = read(5), read(6) + 1
                last ^= read(size) << (w - lead - size)
            out[i] = last
    return out.tobytes()


def chimp_encode(p: bytes, dtype: str) -> bytes:
    """XORs with leading zeros rounded down; four kinds, told by two bits."""
    w = WIDTH[dtype]
    bits, x, leading, trail = xors(p, dtype)
    code = np.searchsorted(ROUNDED, np.minimum(leading, w - 1), side="right") - 1
    lead, n, c = np.array(ROUNDED)[code], len(x), 6 if w == 64 else 5
    kept = np.where((x > 0) & (trail <= 6), code, -1)
    stored = np.append(-1, kept[:-1]) if n else kept
    size = w - lead - np.where(trail > 6, trail, 0)
    kind = np.where(x == 0, 0, np.where(trail > 6, 1, np.where(code == stored, 2, 3)))
    head = np.where(kind == 1, (1 << 3 | code) << c | size - 1, np.where(kind == 3, 3 << 3 | code, kind))
    head_width = np.where(kind == 1, 5 + c, np.where(kind == 3, 5, 2))
    body = np.where(kind == 1, x >> np.where(trail < 64, trail, 0).astype(np.uint64), x)
    values, widths = np.empty(2 * n, np.uint64), np.empty(2 * n, np.int64)
    values[::2], values[1::2], widths[::2], widths[1::2] = head.astype(np.uint64), body, head_width, np.where(kind > 0, size, 0)
    return parts(struct.pack("<I", len(bits)), bits[:1].tobytes(), put(values, widths))


def chimp_decode(data: bytes, dtype: str) -> bytes:
    n, first, body = split(data)
    n, w, read = struct.unpack("<I", n)[0], WIDTH[dtype], Reader(body)
    out, c = np.zeros(n, UNSIGNED[dtype]), 6 if w == 64 else 5
    if n:
        last = int(np.frombuffer(first, UNSIGNED[dtype])[0])
        out[0], stored = last, 0
        for i in range(1, n):
            kind = read(2)
            if kind == 1:
                lead = ROUNDED[read(3)]
                size = read(c) + 1
                last ^= read(size) << (w - lead - size)
            elif kind:
                stored = read(3) if kind == 3 else stored
                last ^= read(w - ROUNDED[stored])
            out[i] = last
    return out.tobytes()


#: Lossless ones, and those that keep the bound of unit packing within its interval; half, mp2e and gouq2e keep other bounds.
LOSSLESS = ("gzip", "pgzip", "zstd", "zstd_threads", "sprintz", "gorilla", "chimp", "pseudodecimal", "de")
CODERS = {
    "unit": (unit_encode, unit_decode),
    "de": (de_encode, de_decode),
    "gzip": (gzip_encode, gzip_decode),
    "pgzip": (pgzip_encode, pgzip_decode),
    "zstd": (zstd_encode, zstd_decode),
    "zstd_threads": (zstd_threads_encode, zstd_decode),
    "sprintz": (sprintz_encode, sprintz_decode),
    "gorilla": (gorilla_encode, gorilla_decode),
    "chimp": (chimp_encode, chimp_decode),
    "buff": (buff_encode, buff_decode),
    "pseudodecimal": (pseudodecimal_encode, pseudodecimal_decode),
    "szx": (szx_encode, szx_decode),
    "predquant": (predquant_encode, predquant_decode),
    "mp": (mp_encode, mp_decode),
    "gouq": (gouq_encode, gouq_decode),
    "half": (half_encode, half_decode),
}


def round_trips(blocks, names=tuple(CODERS)):
    """(coder, dtype, blocks, original, compressed, exact, max_error) over blocks (dtype, payload): bits, whether all bits came back, the largest error of finite values."""
    from pyspark.sql import functions as F

    def run(batches):
        for batch in batches:
            rows = []
            for dtype, p in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                v = np.frombuffer(p, VIEW[dtype][0]).astype(np.float64)
                for name in names:
                    encode, decode = CODERS[name]
                    data = encode(p, dtype)
                    back = decode(data, dtype)
                    b = np.frombuffer(back, VIEW[dtype][0]).astype(np.float64)
                    inside = np.abs(v) < 1
                    rows.append((name, dtype, 8 * len(p), 8 * len(data), back == p, float(np.abs(b - v)[inside].max(initial=0.0))))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64()), pa.array(cols[4], pa.bool_()), pa.array(cols[5], pa.float64())], ["coder", "dtype", "original", "compressed", "exact", "error"])

    rows = blocks.select("dtype", "payload").mapInArrow(run, "coder string, dtype string, original long, compressed long, exact boolean, error double")
    return rows.groupBy("coder", "dtype").agg(F.count("*").alias("blocks"), F.sum("original").alias("original"), F.sum("compressed").alias("compressed"), F.every("exact").alias("exact"), F.max("error").alias("max_error"))
