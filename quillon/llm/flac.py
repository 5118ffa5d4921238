"""FLAC streams of 8-bit samples: a vectorised encoder, a lockstep decoder, and Spark media columns.

All frames of many streams are coded at once. The encoder writes mono frames of 576 samples with a
constant, verbatim, fixed or linear predictor and one Rice partition, and a seek table with each frame.
The decoder starts at all seek points together (without any, at the first frame) and takes one sample
of every frame in a step; it also reads other block sizes, Rice partitions, escapes and 5-bit parameters.
It checks every frame's CRC-8 and CRC-16 and the stream's MD5.
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

from .common import map_batches, slices, utf8

BLOCK = 576
RATE = 8000
#: Text bytes that are coded together; each takes some 100 bytes of memory meanwhile.
CODE_BYTES = 1 << 18
#: Frames that are coded together, of one stream or of many.
FRAMES = 512

# Fixed values of the format: polynomials of the two checksums, block sizes by code.
CRC8, CRC16 = 0x07, 0x8005
BLOCK_SIZES = {1: 192, 2: 576, 3: 1152, 4: 2304, 5: 4608, 8: 256, 9: 512, 10: 1024, 11: 2048, 12: 4096, 13: 8192, 14: 16384, 15: 32768}


class FlacError(ValueError):
    pass


def _crc_bytes(width: int, polynomial: int) -> np.ndarray:
    """The checksum of each single byte."""
    top, mask = 1 << (width - 1), (1 << width) - 1
    crc = np.arange(256) << (width - 8)
    for _ in range(8):
        crc = np.where(crc & top, (crc << 1) ^ polynomial, crc << 1) & mask
    return crc


def _crc_places(width: int, polynomial: int, n: int, start: np.ndarray | None = None) -> np.ndarray:
    """[distance to the end, byte] -> what the byte adds to the checksum; checksums add up by xor."""
    one, mask = _crc_bytes(width, polynomial), (1 << width) - 1
    out = np.empty((n, 256), np.uint16)
    out[0] = one
    for k in range(1, n):
        last = out[k - 1].astype(np.int64)
        out[k] = ((last << 8) & mask) ^ one[last >> (width - 8)]
    return out


_places: dict[int, np.ndarray] = {}


def checksums(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, width: int) -> np.ndarray:
    """CRC-8 or CRC-16 of many non-empty ranges of `data`."""
    lengths = ends - starts
    need = int(lengths.max())
    if len(_places.get(width, ())) < need:
        _places[width] = _crc_places(width, CRC8 if width == 8 else CRC16, max(1024, 1 << (need - 1).bit_length()))
    first = np.cumsum(lengths) - lengths
    k = np.arange(int(lengths.sum()))
    own = np.repeat(np.arange(len(starts)), lengths)
    inside = k - first[own]
    parts = _places[width][lengths[own] - 1 - inside, data[starts[own] + inside]]
    return np.bitwise_xor.reduceat(parts, first)


def _numbers(n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Frame numbers in the format's UTF-8-like form: [frame, 7] bytes, and their lengths."""
    limits = np.array([1 << 7, 1 << 11, 1 << 16, 1 << 21, 1 << 26, 1 << 31, 1 << 36])
    length = np.searchsorted(limits, n, side="right") + 1
    out = np.zeros((len(n), 7), np.uint8)
    for size in np.unique(length).tolist():
        at, v = length == size, n[length == size]
        if size == 1:
            out[at, 0] = v
            continue
        lead = (0xFF << (8 - size)) & 0xFF
        out[at, 0] = lead | (v >> (6 * (size - 1)) if size < 7 else 0)
        for k in range(1, size):
            out[at, k] = 0x80 | ((v >> (6 * (size - 1 - k))) & 0x3F)
    return out, length


def _linear(x: np.ndarray, order: int, precision: int = 12) -> tuple[np.ndarray, np.ndarray]:
    """Quantised predictor coefficients [frame, order] and shifts, by Levinson-Durbin on each frame."""
    y = x.astype(np.float64)
    r = np.stack([(y[:, k:] * y[:, : y.shape[1] - k]).sum(axis=1) for k in range(order + 1)], axis=1)
    r[:, 0] = r[:, 0] * (1 + 1e-9) + 1e-9
    a, err = np.zeros((len(x), order)), r[:, 0].copy()
    for i in range(order):
        reflect = (r[:, i + 1] - (a[:, :i] * r[:, i:0:-1]).sum(axis=1)) / err
        a[:, :i], a[:, i] = a[:, :i] - reflect[:, None] * a[:, i - 1 :: -1][:, :i] if i else a[:, :0], reflect
        err = np.maximum(err * (1 - reflect**2), 1e-12)
    top = np.maximum(np.abs(a).max(axis=1), 1e-6)
    shift = np.clip(precision - 2 - np.floor(np.log2(top)).astype(np.int64), 0, 15)
    limit = 1 << (precision - 1)
    return np.clip(np.rint(a * (1 << shift)[:, None]), -limit, limit - 1).astype(np.int64), shift


def _rice(res: np.ndarray, skip: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Zigzag residuals, best parameter and bits of the codes; the first `skip` of a frame don't count."""
    u = np.where(np.arange(res.shape[1])[None, :] >= skip[:, None], (res << 1) ^ (res >> 31), 0)
    n = res.shape[1] - skip
    total = u.sum(axis=1, dtype=np.int64)
    guess = np.clip(np.floor(np.log2(np.maximum(total / n, 1))).astype(np.int32), 0, 13)
    best, bits = guess, None
    for d in (-1, 0, 1):
        k = np.clip(guess + d, 0, 14)
        size = (u >> k[:, None]).sum(axis=1, dtype=np.int64) + n * (k + 1)
        if bits is None:
            best, bits = k, size
        else:
            better = size < bits
            best, bits = np.where(better, k, best), np.where(better, size, bits)
    return u, best, bits


def encode_frames(payload: np.ndarray, numbers: np.ndarray, order: int = 2, precision: int = 12) -> tuple[np.ndarray, np.ndarray]:
    """The frames of blocks [frame, BLOCK] of bytes (sample + 128), one after another, and their n + 1 offsets."""
    x = payload.astype(np.int32) - 128
    frames = len(x)
    costs, residuals = [], []
    res = x
    for k in range(5):
        full = np.zeros_like(x)
        full[:, k:] = res
        residuals.append(full)
        costs.append(np.abs(full).sum(axis=1))
        res = np.diff(res, axis=1)
    kind = np.argmin(np.stack(costs), axis=0)
    chosen = np.stack(residuals)[kind, np.arange(frames)]
    skip = kind.copy()
    if order:
        coefficients, shift = _linear(x, order, precision)
        guess = np.zeros((frames, BLOCK - order), np.int64)
        for j in range(order):
            guess += coefficients[:, j : j + 1] * x[:, order - 1 - j : BLOCK - 1 - j]
        full = np.zeros_like(x)
        full[:, order:] = x[:, order:] - (guess >> shift[:, None])
        gain = np.abs(full).sum(axis=1) * 1.01 + 4 * order < costs_min(costs)
        chosen[gain], kind, skip = full[gain], np.where(gain, 5, kind), np.where(gain, order, skip)
    u, k, bits = _rice(chosen, skip)
    linear = kind == 5
    side = np.where(linear, 9 + (order * precision if order else 0), 0)
    body = 8 * skip + side + 10 + bits
    flat = (x == x[:, :1]).all(axis=1)
    verbatim = ~flat & (body >= 8 * BLOCK)
    coded = ~flat & ~verbatim
    body = np.where(flat, 8, np.where(verbatim, 8 * BLOCK, body))
    names, width = _numbers(numbers)
    head = 4 + width + 1
    size = head + 1 + (body + 7) // 8 + 2
    at = np.concatenate(([0], np.cumsum(size)))
    rice_bits = (at[:-1] + head + 1) * 8 + 8 * skip + side + 10  # of coded frames: where their codes begin
    stream = np.zeros(int(at[-1]) * 8, np.uint8)
    for p in np.unique(k[coded]).tolist():
        rows = np.flatnonzero(coded & (k == p))
        live = np.arange(BLOCK)[None, :] >= skip[rows, None]
        v = u[rows]
        lengths = np.where(live, (v >> p) + (p + 1), 0)
        stops = rice_bits[rows, None] + np.cumsum(lengths, axis=1) - (p + 1)
        stops, v = stops[live], v[live]
        stream[stops] = 1
        for j in range(p):
            stream[stops + 1 + j] = (v >> (p - 1 - j)) & 1
    for rows, values, where, n in _fields(coded, linear, k, skip, order, precision, *((coefficients, shift) if order else (None, None)), at, head, side):
        for j in range(n):
            stream[where + j] = (values >> (n - 1 - j)) & 1
    out = np.packbits(stream)
    start = at[:-1]
    out[start], out[start + 1], out[start + 2], out[start + 3] = 0xFF, 0xF8, 0x20, 0x02
    for size_ in np.unique(width).tolist():
        for j in range(size_):
            rows = width == size_
            out[start[rows] + 4 + j] = names[rows, j]
    out[start + head - 1] = checksums(out, start, start + head - 1, 8)
    out[start + head] = np.where(flat, 0, np.where(verbatim, 2, np.where(linear, 0x40 | ((order - 1) << 1), 0x10 | (kind << 1))))
    raw = x.astype(np.int8).view(np.uint8)
    out[(start + head + 1)[flat]] = raw[flat, 0]
    rows = np.flatnonzero(verbatim)
    out[(start + head + 1)[rows, None] + np.arange(BLOCK)] = raw[rows]
    for j in range(int(skip.max(initial=0))):
        rows = coded & (skip > j)
        out[(start + head + 1)[rows] + j] = raw[rows, j]
    crc = checksums(out, start, at[1:] - 2, 16)
    out[at[1:] - 2], out[at[1:] - 1] = crc >> 8, crc & 0xFF
    return out, at


def costs_min(costs: list[np.ndarray]) -> np.ndarray:
    return np.min(np.stack(costs), axis=0)


def _fields(coded, linear, k, skip, order, precision, coefficients, shift, at, head, side) -> Iterator[tuple]:
    """Bit fields of the coded frames besides warm-up samples and codes: (rows, values, bit positions, width)."""
    after = (at[:-1] + head + 1) * 8 + 8 * skip
    rows = np.flatnonzero(coded & linear)
    if len(rows):
        yield rows, np.full(len(rows), precision - 1), after[rows], 4
        yield rows, shift[rows], after[rows] + 4, 5
        for j in range(order):
            yield rows, coefficients[rows, j] & ((1 << precision) - 1), after[rows] + 9 + j * precision, precision
    rows = np.flatnonzero(coded)
    yield rows, k[rows], after[rows] + side[rows] + 6, 4  # method 0 and partition order 0 are zero bits


def encode(payloads: list[np.ndarray], order: int = 2) -> list[bytes]:
    """A FLAC stream for each payload; its length is a positive multiple of BLOCK."""
    counts = np.array([len(p) // BLOCK for p in payloads])
    if any(len(p) % BLOCK or not len(p) for p in payloads):
        raise FlacError(f"a payload must be a positive multiple of {BLOCK} bytes")
    blocks = np.concatenate(payloads).reshape(-1, BLOCK)
    ends = np.cumsum(counts)
    numbers = np.arange(len(blocks)) - np.repeat(ends - counts, counts)
    coded, lengths = [], []
    for k in range(0, len(blocks), FRAMES):
        data, at = encode_frames(blocks[k : k + FRAMES], numbers[k : k + FRAMES], order)
        coded.append(data.tobytes())
        lengths.append(np.diff(at))
    raw, out, at = b"".join(coded), [], np.concatenate(([0], np.cumsum(np.concatenate(lengths))))
    coded.clear()
    for p, a, b in zip(payloads, (ends - counts).tolist(), ends.tolist(), strict=True):
        sizes = np.diff(at[a : b + 1])
        samples = len(p)
        md5 = hashlib.md5(p ^ 0x80).digest()
        info = struct.pack(">HH", BLOCK, BLOCK) + int(sizes.min()).to_bytes(3, "big") + int(sizes.max()).to_bytes(3, "big") + ((RATE << 44) | (7 << 36) | samples).to_bytes(8, "big") + md5
        points = np.zeros(b - a, np.dtype([("sample", ">u8"), ("offset", ">u8"), ("n", ">u2")]))
        points["sample"], points["offset"], points["n"] = np.arange(b - a) * BLOCK, at[a:b] - at[a], BLOCK
        table = points.tobytes()
        parts = [b"fLaC", b"\x00", len(info).to_bytes(3, "big"), info]
        chunks = [table[k : k + 18 * 900_000] for k in range(0, len(table), 18 * 900_000)]  # a block's length has 24 bits
        for n, chunk in enumerate(chunks):
            parts += [bytes([3 | (0x80 if n == len(chunks) - 1 else 0)]), len(chunk).to_bytes(3, "big"), chunk]
        out.append(b"".join([*parts, raw[int(at[a]) : int(at[b])]]))
    return out


class _Bits:
    """Big-endian bit reads at many positions of one buffer."""

    def __init__(self, data: np.ndarray):
        padded = np.concatenate((data, np.zeros(16, np.uint8))).astype(np.uint64)
        n = len(data) + 8
        self.words = np.zeros(n, np.uint64)
        for k in range(8):
            self.words |= padded[k : k + n] << np.uint64(56 - 8 * k)

    def window(self, at: np.ndarray) -> np.ndarray:
        """57 bits or more from each position on, at the top of 64."""
        return self.words[np.minimum(at >> 3, len(self.words) - 1)] << (at & 7).astype(np.uint64)

    def read(self, at: np.ndarray, n: np.ndarray | int) -> np.ndarray:
        n = np.asarray(n, np.int64)
        value = self.window(at) >> np.where(n > 0, 64 - n, 0).astype(np.uint64)
        return np.where(n > 0, value.astype(np.int64), 0)

    def signed(self, at: np.ndarray, n: np.ndarray | int) -> np.ndarray:
        n = np.asarray(n, np.int64)
        value = self.read(at, n)
        return value - ((value >> np.maximum(n - 1, 0) & 1) << n) * (n > 0)

    def zeros(self, at: np.ndarray) -> np.ndarray:
        """How many zero bits there are before the next one bit."""
        out, rest, most = np.zeros(len(at), np.int64), np.arange(len(at)), len(self.words) * 8
        while True:
            top = (self.window(at[rest] + out[rest]) >> np.uint64(32)).astype(np.int64)
            some = top > 0
            if some.all():
                out[rest] += 31 - ((top.astype(np.float64).view(np.int64) >> 52) - 1023)
                return out
            done = rest[some]
            out[done] += 31 - ((top[some].astype(np.float64).view(np.int64) >> 52) - 1023)
            rest = rest[~some]
            out[rest] += 32
            if (at[rest] + out[rest] > most).any():
                raise FlacError("the stream ends within a code")


def _metadata(stream: bytes) -> tuple[int, int, int, bytes, np.ndarray, np.ndarray, int]:
    """(samples, bits a sample, default block size, md5, seek points' samples and offsets, first frame's place)."""
    if stream[:4] != b"fLaC":
        raise FlacError("no FLAC stream")
    at, last, info, samples, offsets = 4, False, None, [], []
    while not last:
        if at + 4 > len(stream):
            raise FlacError("the stream ends within its metadata")
        kind, size = stream[at] & 0x7F, int.from_bytes(stream[at + 1 : at + 4], "big")
        last, body = bool(stream[at] & 0x80), stream[at + 4 : at + 4 + size]
        if kind == 0:
            packed = int.from_bytes(body[10:18], "big")
            info = (packed & ((1 << 36) - 1), ((packed >> 36) & 31) + 1, int.from_bytes(body[2:4], "big"), body[18:34], (packed >> 41) & 7)
        elif kind == 3:
            points = np.frombuffer(body, np.dtype([("sample", ">u8"), ("offset", ">u8"), ("n", ">u2")]))
            points = points[points["sample"] != 0xFFFFFFFFFFFFFFFF]
            samples.append(points["sample"].astype(np.int64))
            offsets.append(points["offset"].astype(np.int64))
        at += 4 + size
    if info is None or info[4] or not 4 <= info[1] <= 16:
        raise FlacError("only mono streams of 4 to 16 bits are read")
    join = lambda p: np.concatenate(p) if p else np.zeros(1, np.int64)
    return *info[:4], join(samples), join(offsets), at


def _decode_frames(data: np.ndarray, bits: _Bits, at: np.ndarray, depth: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One frame from each byte position: samples [frame, largest block], block sizes, ends."""
    lanes = len(at)
    if (at + 6 > len(data)).any() or (data[at] != 0xFF).any() or (data[at + 1] & 0xFE != 0xF8).any():
        raise FlacError("no frame where one should be")
    code, width = data[at + 2] >> 4, np.ones(lanes, np.int64)
    lead = data[at + 4]
    for k in range(2, 8):
        width[lead >= ((0xFF << (8 - k)) & 0xFF)] = k
    p = at + 4 + width
    sizes = np.zeros(lanes, np.int64)
    for c in np.unique(code).tolist():
        rows = code == c
        if c == 6:
            sizes[rows] = data[p[rows]].astype(np.int64) + 1
        elif c == 7:
            sizes[rows] = data[p[rows]].astype(np.int64) * 256 + data[p[rows] + 1] + 1
        elif c in BLOCK_SIZES:
            sizes[rows] = BLOCK_SIZES[c]
        else:
            raise FlacError("reserved block size")
    rate = data[at + 2] & 15
    p = p + np.where(code == 6, 1, np.where(code == 7, 2, 0)) + np.where(rate == 12, 1, np.where((rate == 13) | (rate == 14), 2, 0))
    if (checksums(data, at, p, 8) != data[p]).any():
        raise FlacError("a frame header's checksum differs")
    kind = (data[p + 1] >> 1).astype(np.int64)
    if (data[p + 1] & 0x81).any():
        raise FlacError("wasted bits or padding in a subframe header")
    pos = (p + 2) * 8
    fixed, linear = (kind >= 8) & (kind <= 12), kind >= 32
    order = np.where(fixed, kind - 8, np.where(linear, kind - 31, 0))
    if (~fixed & ~linear & (kind > 1)).any():
        raise FlacError("reserved subframe type")
    most = int(sizes.max())
    x = np.zeros((most, lanes), np.int64)  # a row a sample
    rows = np.flatnonzero(kind == 0)
    x[:, rows] = bits.signed(pos[rows], depth[rows])
    pos[rows] += depth[rows]
    rows = np.flatnonzero(kind == 1)
    for i in range(int(sizes[rows].max(initial=0))):
        own = rows[sizes[rows] > i]
        x[i, own] = bits.signed(pos[own], depth[own])
        pos[own] += depth[own]
    for i in range(int(order.max())):
        own = order > i
        x[i, own] = bits.signed(pos[own], depth[own])
        pos[own] += depth[own]
    rows = np.flatnonzero(linear)
    coefficients, shift = np.zeros((32, lanes), np.int64), np.zeros(lanes, np.int64)
    if len(rows):
        precision = bits.read(pos[rows], 4) + 1
        shift[rows] = bits.signed(pos[rows] + 4, 5)
        pos[rows] += 9
        for j in range(int(order[rows].max())):
            own = order[rows] > j
            coefficients[j, rows[own]] = bits.signed(pos[rows[own]], precision[own])
            pos[rows[own]] += precision[own]
    rows = np.flatnonzero(fixed | linear)
    if len(rows):
        pos[rows] = _residuals(bits, x, rows, pos[rows], order[rows], sizes[rows])
        _predict(x, np.where(fixed, order, -1), np.where(linear, order, -1), coefficients, shift)
    ends = (pos + 7) // 8 + 2
    if (ends > len(data)).any():
        raise FlacError("the stream ends within a frame")
    if (checksums(data, at, ends - 2, 16) != data[ends - 2].astype(np.uint16) * 256 + data[ends - 1]).any():
        raise FlacError("a frame's checksum differs")
    return x.T, sizes, ends


def _residuals(bits: _Bits, x: np.ndarray, rows: np.ndarray, pos: np.ndarray, order: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Reads the Rice codes of the frames `rows` into x, all frames in step; gives the positions after them."""
    method, splits = bits.read(pos, 2), bits.read(pos + 2, 4)
    if (method > 1).any():
        raise FlacError("reserved residual coding")
    pos = pos + 6
    wide, part = 4 + method, sizes >> splits
    k, raw = np.zeros(len(rows), np.int64), np.full(len(rows), -1)
    fresh, steady = np.ones(len(rows), bool), bool((sizes == sizes[0]).all())
    single = bool((splits == 0).all())
    for i in range(int(order.min()), int(sizes.max())):
        every = steady and i >= int(order.max())
        live = np.ones(len(rows), bool) if every else (i >= order) & (i < sizes)
        new = live & (fresh if single else fresh | (i % part == 0))
        if new.any():
            own = np.flatnonzero(new)
            k[own] = bits.read(pos[own], wide[own])
            pos[own] += wide[own]
            escape = k[own] == (1 << wide[own]) - 1
            raw[own] = np.where(escape, bits.read(pos[own], 5), -1)
            pos[own] += 5 * escape
            fresh[own] = False
        if every and not (raw >= 0).any():
            q = bits.zeros(pos)
            pos = pos + q + 1
            u = (q << k) | bits.read(pos, k)
            pos = pos + k
            x[i, rows] = (u >> 1) ^ -(u & 1)
            continue
        own = np.flatnonzero(live & (raw < 0))
        if len(own):
            q = bits.zeros(pos[own])
            pos[own] += q + 1
            u = (q << k[own]) | bits.read(pos[own], k[own])
            pos[own] += k[own]
            x[i, rows[own]] = (u >> 1) ^ -(u & 1)
        own = np.flatnonzero(live & (raw >= 0))
        if len(own):
            x[i, rows[own]] = bits.signed(pos[own], raw[own])
            pos[own] += raw[own]
    return pos


def _predict(x: np.ndarray, fixed: np.ndarray, linear: np.ndarray, coefficients: np.ndarray, shift: np.ndarray) -> None:
    """Turns residuals after the warm-up samples into samples, in place."""
    for order in range(1, 5):
        rows = np.flatnonzero(fixed == order)
        if len(rows):
            own = x[:, rows]
            warm = own[:order].copy()
            for level in range(order, 0, -1):
                own[level - 1] = np.diff(warm, n=level - 1, axis=0)[0]
                own[level - 1 :] = np.cumsum(own[level - 1 :], axis=0)
            x[:, rows] = own
            x[:order, rows] = warm
    for order in np.unique(linear[linear > 0]).tolist():
        rows = np.flatnonzero(linear == order)
        own, c, s = x[:, rows], coefficients[:order, rows], shift[rows]
        for i in range(order, len(own)):
            own[i] += (c * own[i - order : i][::-1]).sum(axis=0) >> s
        x[:, rows] = own


def decode_blocks(streams: list[bytes]) -> Iterator[tuple[int, int, np.ndarray]]:
    """(stream, sample offset, samples) of successive runs of frames, all checksums verified.

    A group of FRAMES seek points is decoded at a time, of one stream or of several together, so that a long
    stream never is in memory as samples. Seek points must be frame starts; without any a stream is one run.
    """
    heads = [_metadata(s) for s in streams]
    points = [(n, h[6] + o, end, int(sample), int(stop)) for n, (h, s) in enumerate(zip(heads, streams, strict=True)) for o, end, sample, stop in zip(h[5].tolist(), [*(h[5][1:] + h[6]).tolist(), len(s)], h[4], [*h[4][1:], h[0]], strict=True)]
    sums = [hashlib.md5() for _ in streams]
    for k in range(0, len(points), FRAMES):
        group = points[k : k + FRAMES]
        owner = np.array([p[0] for p in group])
        lo, hi, base = {}, {}, {}
        for n, at, end, sample, stop in group:
            lo[n], hi[n] = min(lo.get(n, at), at), max(hi.get(n, end), end)
            base.setdefault(n, [sample, stop])
            base[n] = [min(base[n][0], sample), max(base[n][1], stop)]
        place, where = 0, {}
        for n in lo:
            where[n] = place - lo[n]
            place += hi[n] - lo[n]
        data = np.frombuffer(b"".join(streams[n][lo[n] : hi[n]] for n in lo), np.uint8)
        at, limit = np.array([where[n] + x for n, x, _, _, _ in group]), np.array([where[n] + x for n, _, x, _, _ in group])
        sample, starts, total = np.array([p[3] for p in group]), {}, 0
        for n, (x, y) in base.items():
            starts[n] = total - x
            total += y - x
        shift, last = np.array([starts[n] for n in owner.tolist()]), np.array([base[n][1] for n in owner.tolist()])
        flat, depth, bits = np.zeros(total, np.int16), np.array([heads[n][1] for n in owner.tolist()]), _Bits(data)
        while len(at):
            x, sizes, ends = _decode_frames(data, bits, at, depth)
            if (sample + sizes > last).any() or (ends > limit).any():
                raise FlacError("frames go beyond the stream")
            to = shift + sample
            if (sizes == sizes[0]).all():
                flat[to[:, None] + np.arange(int(sizes[0]))] = x
            else:
                for row, a, n in zip(x, to.tolist(), sizes.tolist(), strict=True):
                    flat[a : a + n] = row[:n]
            more = ends < limit
            at, sample, limit, shift, last, depth = ends[more], (sample + sizes)[more], limit[more], shift[more], last[more], depth[more]
        for n, (x, y) in base.items():
            own = flat[starts[n] + x : starts[n] + y]
            if heads[n][1] == 8:
                sums[n].update(own.astype(np.int8))
                if y == heads[n][0] and any(heads[n][3]) and sums[n].digest() != heads[n][3]:
                    raise FlacError("the stream's MD5 differs")
            yield n, x, own


def decode(streams: list[bytes]) -> list[np.ndarray]:
    """The samples of each stream."""
    parts: list[list[np.ndarray]] = [[] for _ in streams]
    for n, _, x in decode_blocks(streams):
        parts[n].append(x)
    return [np.concatenate(p) if p else np.zeros(0, np.int16) for p in parts]


def payloads(data: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
    """Each text's bytes, filled with 255 up to a positive multiple of BLOCK."""
    out = []
    for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        p = np.full(max(1, -(-(b - a) // BLOCK)) * BLOCK, 255, np.uint8)
        p[: b - a] = data[a:b]
        out.append(p)
    return out


class Digests:
    """What the query tells of a stream's samples, taken from one block of them after another."""

    def __init__(self) -> None:
        self.size = self.energy = self.crossings = self.peak = self.steps = 0
        self.sha, self.tail, self.last = hashlib.sha256(), b"", None

    def update(self, x: np.ndarray) -> None:
        for a in range(0, len(x), 1 << 16):
            wide = x[a : a + (1 << 16)].astype(np.int64)
            raw = (wide + 128).astype(np.uint8).tobytes()
            self.sha.update(raw)
            self.tail = (self.tail + raw)[-32:]
            self.size += len(raw)
            joined = wide if self.last is None else np.concatenate(([self.last], wide))
            self.energy += int((wide * wide).sum())
            self.crossings += int(((joined[1:] < 0) != (joined[:-1] < 0)).sum())
            self.peak = max(self.peak, int(np.abs(wide).max()))
            self.steps += int(np.abs(np.diff(joined)).sum())
            self.last = int(wide[-1])

    @property
    def feature(self) -> str:
        """Energy, sign changes, peak and sum of steps of the samples, as integers."""
        return f"energy={self.energy};crossings={self.crossings};peak={self.peak};steps={self.steps}"


def _small(batches: Iterable[pa.RecordBatch], column: int, most: int) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    for batch in batches:
        data, at = utf8(batch.column(column))
        for a, b in slices(at, most):
            for c in range(a, b, 512):  # short texts take a whole block each
                d = min(b, c + 512)
                yield batch.slice(c, d - c), data[at[c] : at[d]], at[c : d + 1] - at[c]


def media_digests(docs: DataFrame, key: str = "doc_id", text: str = "text", order: int = 2, with_media: bool = False) -> DataFrame:
    """Each text's UTF-8 bytes as a FLAC stream, read back: key, n_bytes, payload_bytes, payload_sha256,
    tail_crc32, media_bytes, media_sha256, feature; `with_media` adds the stream itself.

    All digests but n_bytes are of the PCM blocks that the decoder gives at the stream's seek points, the media's
    of the stream. Null and empty texts are one block of 255. Equal texts give equal values. Texts are stored
    whole, long ones in bounded memory besides their own bytes; repeated rows are treated alike; an empty table
    gives an empty result; other columns, whatever their names, are ignored.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, data, at in _small(batches, 1, CODE_BYTES):
            media = encode(payloads(data, at), order)
            back = [Digests() for _ in media]
            for n, _, samples in decode_blocks(media):
                back[n].update(samples)
            columns = [
                pa.array(np.diff(at)), pa.array([b.size for b in back], pa.int64()), pa.array([b.sha.hexdigest() for b in back], pa.string()),
                pa.array([zlib.crc32(b.tail) for b in back], pa.int64()), pa.array([len(m) for m in media], pa.int64()),
                pa.array([hashlib.sha256(m).hexdigest() for m in media], pa.string()), pa.array([b.feature for b in back], pa.string()),
            ]
            columns += [pa.array(media, pa.binary())] if with_media else []
            yield pa.RecordBatch.from_arrays([rows.column(0), *columns], names=["id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "media"][: len(columns) + 1])

    source = docs.select(F.col(key).alias("id"), F.col(text).alias("text"))
    schema = f"id {source.schema['id'].dataType.simpleString()}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string" + ", media binary" * with_media
    return map_batches(source, run, schema).withColumnRenamed("id", key)


def pcm_blocks(media: DataFrame, key: str = "doc_id", column: str = "media", block_samples: int = BLOCK * 64) -> DataFrame:
    """Decodes FLAC streams into seekable blocks: key, block, sample_offset, n_samples, pcm (16-bit little-endian).

    A row whose stream is null gives no blocks; a damaged stream fails the job. Repeated rows give repeated
    blocks; an empty table gives none; other columns are ignored.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            for k in range(rows.num_rows):
                stream = rows.column(1)[k].as_py()
                held, offset, size = [], 0, 0

                def block() -> pa.RecordBatch:
                    x = np.concatenate(held)
                    cut = x[:block_samples]
                    held[:] = [x[block_samples:]]
                    columns = [[offset // block_samples], [offset], [len(cut)], [cut.astype("<i2").tobytes()]]
                    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary())
                    return pa.RecordBatch.from_arrays([rows.column(0).slice(k, 1), *(pa.array(c, t) for c, t in zip(columns, kinds, strict=True))], names=["id", "block", "sample_offset", "n_samples", "pcm"])

                for _, _, x in decode_blocks([stream]) if stream is not None else ():
                    held.append(x)
                    size += len(x)
                    while size >= block_samples:
                        yield block()
                        offset, size = offset + block_samples, size - block_samples
                if size:
                    yield block()

    source = media.select(F.col(key).alias("id"), F.col(column).alias("media"))
    return map_batches(source, run, f"id {source.schema['id'].dataType.simpleString()}, block long, sample_offset long, n_samples long, pcm binary").withColumnRenamed("id", key)
