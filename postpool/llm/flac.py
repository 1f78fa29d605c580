"""Media columns: FLAC. Any bytes are stored losslessly as mono 8-bit samples and read back block by block.

The decoder reads constant, verbatim, fixed and LPC subframes, Rice partitions of any order with escapes, verifies the
header CRC-8, the frame CRC-16 and the MD5 of the samples, and gives PCM blocks with their sample offsets; the seek
table leads to any block without the ones before it. The encoder writes the smallest of constant, verbatim, the fixed
linear predictors of order 0 to 4 and LPC of a given order. A sample of an LPC frame needs the ones before it, so the
decoder walks many frames side by side, one sample of each a step.

`stored` writes media to the shared folder and gives the table read back; `write_pcm` decodes media to a table of PCM
blocks that any block is found in by document and sample offset.

Edge cases: a null text is empty; a payload is never empty (padding to a positive multiple of 64); equal payloads give
equal media; very long texts are worked on block by block; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property, lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..runtime import materialise
from .common import batches, pick

BLOCK, PAD, RATE, LPC_ORDER = 4096, 64, 8000, 8
#: Samples that are decoded together: frames of several streams up to so many.
TOGETHER = 1 << 21
STREAM_HEAD = b"fLaC"
#: Coefficients of the fixed predictors by order (fixed values of the format).
FIXED = ((), (1,), (2, -1), (3, -3, 1), (4, -6, 4, -1))


def _table(poly: int, bits: int) -> list[int]:
    top, mask = 1 << (bits - 1), (1 << bits) - 1
    out = []
    for byte in range(256):
        crc = byte << (bits - 8)
        for _ in range(8):
            crc = ((crc << 1) ^ poly if crc & top else crc << 1) & mask
        out.append(crc)
    return out


CRC8, CRC16 = _table(0x07, 8), _table(0x8005, 16)
#: Bytes whose CRC-16 is summed at once.
SPAN = 256


def crc8(data: bytes) -> int:
    crc = 0
    for b in data:
        crc = CRC8[crc ^ b]
    return crc


@lru_cache(maxsize=1)
def _spread() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What a byte adds to the CRC-16 by its distance from the end of a span; a span's shift of the high and low CRC byte."""
    table = np.array(CRC16, np.uint16)
    step = lambda x: ((x << 8) & 0xFFFF).astype(np.uint16) ^ table[x >> 8]
    by = np.empty((SPAN, 256), np.uint16)
    by[SPAN - 1] = table
    for i in range(SPAN - 2, -1, -1):
        by[i] = step(by[i + 1].astype(np.uint32).astype(np.uint16))
    high, low = np.arange(256, dtype=np.uint16) << 8, np.arange(256, dtype=np.uint16)
    for _ in range(SPAN):
        high, low = step(high), step(low)
    return by.reshape(-1), high, low


def crc16(data: bytes) -> int:
    """The CRC is linear: whole spans are looked up and XORed, and the spans' sums are shifted and joined."""
    by, high, low = _spread()
    lead = -len(data) % SPAN  # leading zeros change nothing, as the CRC starts from zero
    padded = np.zeros(lead + len(data), np.uint8)
    padded[lead:] = np.frombuffer(data, np.uint8)
    sums = np.bitwise_xor.reduce(by[padded.reshape(-1, SPAN) + (np.arange(SPAN) * 256)], axis=1)
    crc = 0
    for s in sums.tolist():
        crc = int(high[crc >> 8]) ^ int(low[crc & 255]) ^ s
    return crc


def _coded(n: int) -> bytes:
    """A frame number in the format's extended UTF-8."""
    if n < 0x80:
        return bytes([n])
    out, room = [], 6
    while n >= 1 << room:
        out.append(0x80 | (n & 0x3F))
        n >>= 6
        room -= 1
    return bytes([(0xFF << (room + 1)) & 0xFF | n, *reversed(out)])


def _uncoded(data: bytes, at: int) -> tuple[int, int]:
    b = data[at]
    if b < 0x80:
        return b, at + 1
    more = 8 - (b ^ 0xFF).bit_length() - 1
    n = b & ((1 << (6 - more)) - 1)
    for i in range(more):
        n = (n << 6) | (data[at + 1 + i] & 0x3F)
    return n, at + 1 + more


# ---------------------------------------------------------------- encoder


def _rice_bits(z: np.ndarray) -> tuple[int, int]:
    """(parameter, bits) of the cheapest Rice code of these folded residuals."""
    n = len(z)
    guess = max(0, (int(z.sum()) // max(n, 1)).bit_length() - 1)
    costs = [(n * (1 + k) + int((z >> k).sum()), k) for k in range(max(0, guess - 1), min(14, guess + 1) + 1)]
    bits, k = min(costs)
    return k, bits


def _put(value: int, bits: int) -> np.ndarray:
    return np.array([(value >> i) & 1 for i in range(bits - 1, -1, -1)], np.uint8)


def _rice(z: np.ndarray, k: int) -> np.ndarray:
    ends = np.cumsum((z >> k) + (1 + k))
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    out[ends - k - 1] = 1
    for j in range(k):
        out[ends - k + j] = (z >> (k - 1 - j)) & 1
    return out


def _lpc(x: np.ndarray, order: int) -> tuple[np.ndarray, int, np.ndarray] | None:
    """(quantised coefficients, shift, residual) by autocorrelation and normal equations."""
    f = x.astype(float)
    r = np.array([f[: len(f) - i] @ f[i:] for i in range(order + 1)])
    if not r[0]:
        return None
    m = r[np.abs(np.subtract.outer(np.arange(order), np.arange(order)))] + np.eye(order) * r[0] * 1e-9
    c = np.linalg.solve(m, r[1:])
    shift = max(0, min(15, 13 - int(np.frexp(np.abs(c).max())[1])))
    q = np.clip(np.rint(c * (1 << shift)), -(1 << 13), (1 << 13) - 1).astype(np.int64)
    guess = np.correlate(f[:-1], q[::-1].astype(float)).astype(np.int32) >> shift  # whole numbers below 2**53
    return q, shift, x[order:] - guess


def _subframe(x: np.ndarray, lpc_order: int = LPC_ORDER) -> np.ndarray:
    """Bits of the smallest subframe of these samples."""
    n = len(x)
    raw = lambda v: np.unpackbits(v.astype(np.int8).view(np.uint8))
    if (x == x[0]).all():
        return np.concatenate([_put(0, 8), raw(x[:1])])
    best, bits = ("verbatim", None), 8 + 8 * n
    residual, found = x, []
    for order in range(min(5, n)):
        if order:
            residual = np.diff(residual)
        found.append((int(np.abs(residual).sum()), order, residual))
    _, order, residual = min(found, key=lambda f: f[:2])
    z = (residual << 1) ^ (residual >> 31)
    k, cost = _rice_bits(z)
    if 8 + 8 * order + 10 + cost < bits:
        best, bits = ("fixed", (order, z, k)), 8 + 8 * order + 10 + cost
    if 0 < lpc_order < n and (fit := _lpc(x, lpc_order)):
        q, shift, residual = fit
        zl = (residual << 1) ^ (residual >> 31)
        kl, cost = _rice_bits(zl)
        if 8 + 8 * lpc_order + 9 + 15 * lpc_order + 10 + cost < bits:
            best = ("lpc", (q, shift, zl, kl))
    kind, fit = best
    if kind == "verbatim":
        return np.concatenate([_put(1 << 1, 8), raw(x)])
    if kind == "fixed":
        order, z, k = fit
        return np.concatenate([_put((8 | order) << 1, 8), raw(x[:order]), _put(k, 10), _rice(z, k)])
    q, shift, z, k = fit
    order = len(q)
    head = [_put((32 | (order - 1)) << 1, 8), raw(x[:order]), _put(14, 4), _put(shift, 5), *(_put(int(c) & 0x7FFF, 15) for c in q)]
    return np.concatenate([*head, _put(k, 10), _rice(z, k)])


def encode(payload: bytes, block: int = BLOCK, lpc_order: int = LPC_ORDER) -> bytes:
    """The payload as a FLAC stream of mono 8-bit samples (byte less 128), with a seek point for each frame."""
    data = np.frombuffer(payload, np.uint8).astype(np.int32) - 128
    frames = []
    for number, start in enumerate(range(0, len(data), block)):
        x = data[start : start + block]
        head = struct.pack(">BBBB", 0xFF, 0xF8, 0x74, 0x02) + _coded(number) + struct.pack(">H", len(x) - 1)
        body = head + bytes([crc8(head)]) + np.packbits(_subframe(x, lpc_order)).tobytes()
        frames.append(body + struct.pack(">H", crc16(body)))
    sizes = [len(f) for f in frames] or [0]
    info = struct.pack(">HH", block, block) + min(sizes).to_bytes(3, "big") + max(sizes).to_bytes(3, "big")
    info += ((RATE << 44) | (0 << 41) | (7 << 36) | len(data)).to_bytes(8, "big") + hashlib.md5((data.astype(np.int8)).tobytes()).digest()
    points, at = [], 0
    for i, f in enumerate(frames):
        points.append(struct.pack(">QQH", i * block, at, min(block, len(data) - i * block)))
        at += len(f)
    seek = b"".join(points[: (1 << 24) // 18 - 1])
    return STREAM_HEAD + b"\x00" + len(info).to_bytes(3, "big") + info + b"\x83" + len(seek).to_bytes(3, "big") + seek + b"".join(frames)


# ---------------------------------------------------------------- decoder


def read_head(stream: bytes) -> dict:
    """Stream information, seek points (sample, byte offset, samples) and where the first frame starts."""
    if stream[:4] != STREAM_HEAD:
        raise ValueError("not a FLAC stream")
    at, last, out = 4, False, {"points": []}
    while not last:
        last, kind, size = bool(stream[at] & 0x80), stream[at] & 0x7F, int.from_bytes(stream[at + 1 : at + 4], "big")
        body = stream[at + 4 : at + 4 + size]
        if kind == 0:
            packed = int.from_bytes(body[10:18], "big")
            out |= {"block": int.from_bytes(body[2:4], "big"), "rate": packed >> 44, "channels": (packed >> 41 & 7) + 1, "bits": (packed >> 36 & 31) + 1, "samples": packed & ((1 << 36) - 1), "md5": body[18:34]}
        elif kind == 3:
            out["points"] = [struct.unpack_from(">QQH", body, i) for i in range(0, size, 18)]
        at += 4 + size
    return out | {"start": at}


class Bits:
    """The bits of one frame, and the place of the next one bit from any bit."""

    def __init__(self, data: bytes, at: int):
        self.data, self.at = data, at * 8
        self.ones = self.before = None

    @cached_property
    def bits(self) -> np.ndarray:
        return np.unpackbits(np.frombuffer(self.data, np.uint8))

    def take(self, n: int) -> int:
        first, self.at = self.at >> 3, self.at + n
        last = (self.at + 7) >> 3
        return int.from_bytes(self.data[first:last], "big") >> (8 * last - self.at) & ((1 << n) - 1)

    def signed(self, n: int) -> int:
        v = self.take(n)
        return v - (1 << n) if n and v >> (n - 1) else v

    def raw(self, n: int, width: int) -> np.ndarray:
        """n values of `width` bits each, signed."""
        if n <= 32:
            return np.array([self.signed(width) for _ in range(n)], np.int64)
        b = self.bits[self.at : self.at + n * width].reshape(n, width).astype(np.int64)
        self.at += n * width
        v = b @ (1 << np.arange(width - 1, -1, -1, dtype=np.int64)) if width else np.zeros(n, np.int64)
        return np.where(v >> max(width - 1, 0) & 1, v - (1 << width), v) if width else v

    def rice(self, n: int, k: int) -> np.ndarray:
        """n Rice codes. Each ends k bits after a one bit, so the one bits form chains; every 32nd link is followed by
        steps that are composed five times over all one bits, the links between are looked up together."""
        if not n:
            return np.zeros(0, np.int64)
        if self.ones is None:
            self.ones = np.flatnonzero(self.bits)
            self.before = np.concatenate([[0], np.cumsum(self.bits, dtype=np.int32)])
        ones, before = self.ones, self.before
        first = int(before[self.at])
        follow = before[np.minimum(ones[first:] + (1 + k), len(self.bits))] - first
        follow = np.append(np.minimum(follow, len(ones) - first), len(ones) - first)
        if n > 64:
            far = follow
            for _ in range(5):
                far = far[far]
            stops, j = [], 0
            for _ in range(-(-n // 32)):
                stops.append(j)
                j = int(far[j])
            grid = np.empty((32, len(stops)), np.int64)
            grid[0] = stops
            for i in range(1, 32):
                grid[i] = follow[grid[i - 1]]
            links = grid.T.reshape(-1)[:n]
        else:
            links, j = [], 0
            for _ in range(n):
                links.append(j)
                j = int(follow[j])
            links = np.array(links)
        if links[-1] >= len(ones) - first:
            raise ValueError("a Rice code runs past the frame")
        at = ones[first:][links]
        begins = np.empty(n, np.int64)
        begins[0] = self.at
        begins[1:] = at[:-1] + (1 + k)
        z = at - begins
        for j in range(k):
            z = (z << 1) | self.bits[at + 1 + j]
        self.at = int(at[-1]) + 1 + k
        return (z >> 1) ^ -(z & 1)

    def residual(self, block: int, order: int) -> np.ndarray:
        method, parts = self.take(2), 1 << self.take(4)
        wide = 5 if method else 4
        out = []
        for i in range(parts):
            n, k = block // parts - (0 if i else order), self.take(wide)
            if k == (1 << wide) - 1:
                out.append(self.raw(n, self.take(5)))
            else:
                out.append(self.rice(n, k))
        return np.concatenate(out)


def _restore(warm: np.ndarray, residual: np.ndarray, order: int) -> np.ndarray:
    """Undo a fixed predictor: each difference of the warm-up samples is the start of one running sum."""
    starts, row = [], warm
    for _ in range(order):
        starts.append(int(row[-1]))
        row = np.diff(row)
    for start in reversed(starts):
        residual = np.cumsum(residual) + start
    return np.concatenate([warm, residual])


def _rice_together(frames: list[tuple[bytes, int, int, int]]) -> list[np.ndarray]:
    """Residuals of frames (bytes, bit where the codes begin, how many, parameter) with one Rice code each. A code ends
    so many bits after its first one bit; all frames go from code to code together, longest first."""
    if not frames:
        return []
    order = sorted(range(len(frames)), key=lambda i: -frames[i][2])
    counts = np.array([frames[i][2] for i in order])
    sizes = np.array([8 * len(frames[i][0]) for i in order])
    base = np.cumsum(sizes) - sizes
    k = np.array([frames[i][3] for i in order], np.int32)
    start = (base + [frames[i][1] for i in order]).astype(np.int32)
    packed = np.frombuffer(b"".join([*(frames[i][0] for i in order), bytes(4)]), np.uint8)
    bits = np.unpackbits(packed[:-4])
    ones = np.append(np.flatnonzero(bits.view(bool)).astype(np.int32), np.int32(len(bits)))
    before = np.full(len(bits) + int(k.max()) + 2, len(ones) - 1, np.int32)  # one bits before a place
    before[0] = 0
    np.cumsum(bits, dtype=np.int32, out=before[1 : len(bits) + 1])
    steps = int(counts[0])
    at = np.zeros((steps, len(frames)), np.int32)
    live = np.searchsorted(-counts, -np.arange(steps), "left").tolist()
    j, skip = before[start], k + 1
    for t, n in enumerate(live):
        found = ones[j[:n]]
        at[t, :n] = found
        j = before[found + skip[:n]]
    if (at[counts - 1, np.arange(len(frames))] + k >= base + sizes).any():
        raise ValueError("a Rice code runs past the frame")
    z = at.copy()
    z[1:] -= at[:-1] + skip
    z[0] -= start
    wide = packed.astype(np.int32)
    wide = wide[:-2] << 16 | wide[1:-1] << 8 | wide[2:]  # a place's low bits lie within three bytes
    at += 1
    low = wide[at >> 3]
    low >>= (24 - k) - (at & 7)
    low &= (1 << k) - 1
    z <<= k
    z |= low
    columns = np.ascontiguousarray(((z >> 1) ^ -(z & 1)).T)
    out: list = [None] * len(frames)
    for column, i in enumerate(order):
        out[i] = columns[column, : counts[column]]
    return out


def _predict(frames: list[tuple[np.ndarray, np.ndarray, list[int], int]]) -> list[np.ndarray]:
    """Undo the predictors of LPC frames (warm-up, residual, coefficients, shift), longest first so that frames that
    have ended leave the right side of the matrix."""
    if not frames:
        return []
    order = sorted(range(len(frames)), key=lambda i: -len(frames[i][1]))
    deep = max(len(f[2]) for f in frames)
    lengths = np.array([len(frames[i][1]) for i in order])
    steps = int(lengths[0])
    wide = np.int32 if max(int(np.abs(f[2]).sum()) for f in frames) << 7 < 1 << 31 else np.int64  # of 8-bit samples
    samples, rest = np.zeros((deep + steps, len(frames)), wide), np.zeros((steps, len(frames)), wide)
    by, shift = np.zeros((deep, len(frames)), wide), np.zeros(len(frames), wide)
    for column, i in enumerate(order):
        warm, residual, q, down = frames[i]
        samples[deep - len(q) : deep, column], rest[: len(residual), column] = warm, residual
        by[deep - len(q) :, column], shift[column] = q[::-1], down
    live = np.searchsorted(-lengths, -np.arange(steps), "left")  # frames longer than so many steps
    for t, n in enumerate(live.tolist()):
        guess = np.einsum("ij,ij->j", samples[t : t + deep, :n], by[:, :n])
        samples[t + deep, :n] = rest[t, :n] + (guess >> shift[:n])
    out: list = [None] * len(frames)
    for column, i in enumerate(order):
        out[i] = samples[deep - len(frames[i][2]) : deep + lengths[column], column]
    return out


@dataclass
class Coded:
    """A frame's predictor and its residual, or where its one Rice code lies (first bit, codes, parameter)."""

    order: int
    warm: np.ndarray
    data: bytes
    code: tuple[int, int, int] | None
    residual: np.ndarray | None
    taps: tuple[list[int], int] | None


def read_frame(stream: bytes, at: int, end: int) -> tuple[int, np.ndarray | Coded]:
    """(frame number, samples or what they are coded by) of the frame in stream[at:end]; both checksums are verified."""
    data = stream[at:end]
    if data[0] != 0xFF or data[1] != 0xF8 or data[3] >> 4:
        raise ValueError("not a mono frame of fixed block size")
    number, pos = _uncoded(data, 4)
    code = data[2] >> 4
    if code == 6:
        n, pos = data[pos] + 1, pos + 1
    elif code == 7:
        n, pos = int.from_bytes(data[pos : pos + 2], "big") + 1, pos + 2
    else:
        n = 192 if code == 1 else 576 << (code - 2) if code < 6 else 256 << (code - 8)
    pos += {12: 1, 13: 2, 14: 2}.get(data[2] & 15, 0)
    if crc8(data[:pos]) != data[pos]:
        raise ValueError("header checksum differs")
    if crc16(data[:-2]) != int.from_bytes(data[-2:], "big"):
        raise ValueError("frame checksum differs")
    kind, wasted, pos = data[pos + 1] >> 1, data[pos + 1] & 1, pos + 2
    if wasted:
        raise ValueError("wasted bits are not stored in 8-bit media")
    if kind == 0:
        return number, np.full(n, np.frombuffer(data, np.int8, 1, pos)[0], np.int64)
    if kind == 1:
        return number, np.frombuffer(data, np.int8, n, pos).astype(np.int64)
    order = kind & 7 if kind < 32 else (kind & 31) + 1
    warm = np.frombuffer(data, np.int8, order, pos).astype(np.int64)
    bits, taps = Bits(data[:-2], pos + order), None
    if kind >= 32:
        precision = bits.take(4) + 1
        shift = bits.signed(5)
        taps = bits.raw(order, precision).tolist(), shift
    begin, wide = bits.at, 5 if bits.take(2) else 4
    parts, k = bits.take(4), bits.take(wide)
    if not parts and k < (1 << wide) - 1:
        return number, Coded(order, warm, bits.data, (bits.at, n - order, k), None, taps)
    bits.at = begin
    return number, Coded(order, warm, bits.data, None, bits.residual(n, order), taps)


def _samples(read: list[tuple[int, np.ndarray | Coded]]) -> Iterator[tuple[int, np.ndarray]]:
    """(frame number, samples) of frames read, in their order."""
    coded = [x for _, x in read if isinstance(x, Coded)]
    codes = iter(_rice_together([(x.data, *x.code) for x in coded if x.code]))
    for x in coded:
        if x.code:
            x.residual = next(codes)
    undone = iter(_predict([(x.warm, x.residual, *x.taps) for x in coded if x.taps]))
    for number, x in read:
        yield number, x if not isinstance(x, Coded) else next(undone) if x.taps else _restore(x.warm, x.residual, x.order)


def decode_all(streams: list[bytes], together: int = TOGETHER) -> Iterator[tuple[int, int, bytes]]:
    """(stream's place in the list, sample offset, PCM bytes) of each block of each stream in turn; after a stream's last
    block the MD5 of its samples is verified. At most `together` samples, or one frame, are held at once."""
    read: list[tuple[int, int, np.ndarray | Coded]] = []
    held, whole, open_ = 0, hashlib.md5(), -1
    heads = {}

    def close(i: int) -> None:
        if i >= 0 and whole.digest() != heads.pop(i)["md5"]:
            raise ValueError("MD5 of the samples differs")

    def blocks() -> Iterator[tuple[int, int, bytes]]:
        nonlocal whole, open_
        for (i, _, _), (number, x) in zip(read, _samples([(n, x) for _, n, x in read])):
            if i != open_:
                close(open_)
                whole, open_ = hashlib.md5(), i
            pcm = x.astype(np.int8)
            whole.update(pcm.tobytes())
            yield i, number * heads[i]["block"], (pcm.view(np.uint8) ^ 0x80).tobytes()

    for i, stream in enumerate(streams):
        heads[i] = head = read_head(stream)
        starts = [head["start"] + p[1] for p in head["points"]]
        for at, end in zip(starts, [*starts[1:], len(stream)]):
            read.append((i, *read_frame(stream, at, end)))
            held += min(head["block"], head["samples"])
            if held >= together:
                yield from blocks()
                read, held = [], 0
    yield from blocks()
    close(open_)


def decode_blocks(stream: bytes) -> Iterator[tuple[int, bytes]]:
    """(sample offset, PCM bytes) of each block; after the last the MD5 of all samples is verified."""
    for _, at, pcm in decode_all([stream]):
        yield at, pcm


def seek(stream: bytes, sample: int) -> tuple[int, bytes]:
    """The block that holds a sample, through the seek table: (its first sample, its bytes)."""
    head = read_head(stream)
    points = head["points"]
    i = int(np.searchsorted([p[0] for p in points], sample, "right")) - 1
    at = head["start"] + points[i][1]
    end = head["start"] + points[i + 1][1] if i + 1 < len(points) else len(stream)
    number, x = next(_samples([read_frame(stream, at, end)]))
    return number * head["block"], (x.astype(np.int8).view(np.uint8) ^ 0x80).tobytes()


# ---------------------------------------------------------------- columns


def pad(text: str | None) -> bytes:
    data = (text or "").encode()
    return data + bytes(-len(data) % PAD if data else PAD)


def store(docs: DataFrame, block: int = BLOCK, lpc_order: int = LPC_ORDER) -> DataFrame:
    """(doc_id, n_bytes, media): each whole text as a FLAC stream."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = batch.column(1).to_pylist()
        media = pa.array([encode(pad(t), block, lpc_order) for t in texts], pa.binary())
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([len((t or "").encode()) for t in texts], pa.int64()), media], names=["doc_id", "n_bytes", "media"])

    return pick(docs, doc_id="long", text="string").mapInArrow(batches(kernel), "doc_id long, n_bytes long, media binary")


def stored(docs: DataFrame, block: int = BLOCK, lpc_order: int = LPC_ORDER) -> DataFrame:
    """`store` written to the shared folder and read back. Zstandard finds streams of equal texts, which Rice codes can't."""
    return materialise(store(docs, block, lpc_order), "media", compression="zstd")


PCM = "doc_id long, sample_offset long, n_samples long, pcm binary"


def pcm_blocks(media: DataFrame) -> DataFrame:
    """PCM rows: decoded blocks, each addressed by its document and first sample."""

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            docs, rows, size = batch.column(0).to_pylist(), [], 0
            make = lambda: pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.binary()))], names=["doc_id", "sample_offset", "n_samples", "pcm"])  # noqa: E731,B023
            for i, at, pcm in decode_all(batch.column(1).to_pylist()):
                rows.append((docs[i], at, len(pcm), pcm))
                size += len(pcm)
                if size >= TOGETHER:
                    yield make()
                    rows, size = [], 0
            if rows:
                yield make()

    return media.select("doc_id", "media").mapInArrow(kernel, PCM)


def write_pcm(media: DataFrame, path: str) -> DataFrame:
    """Write PCM rows under `path` in order of document and offset within each file, so that a reader's filter on both
    skips all row groups but one; gives the table read back. Nothing is shuffled."""
    pcm_blocks(media).sortWithinPartitions("doc_id", "sample_offset").write.option("compression", "zstd").parquet(path)
    return media.sparkSession.read.schema(PCM).parquet(path)


def block_at(pcm: DataFrame, doc_id: int, sample: int) -> DataFrame:
    """PCM row of the block that holds a sample of a document."""
    return pcm.where((F.col("doc_id") == doc_id) & (F.col("sample_offset") <= sample) & (F.col("sample_offset") + F.col("n_samples") > sample))


FEATURES = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_blocks long"


class Summary:
    """Digests of one stream's payload and sums over its blocks."""

    def __init__(self, media: bytes):
        self.media, self.whole, self.tail = media, hashlib.sha256(), b""
        self.n = self.total = self.energy = self.crossings = self.blocks = 0

    def add(self, pcm: bytes) -> None:
        x = np.frombuffer(pcm, np.uint8).astype(np.int32) - 128
        self.whole.update(pcm)
        self.n, self.total, self.energy, self.blocks = self.n + len(pcm), self.total + int(x.sum()), self.energy + int((x * x).sum()), self.blocks + 1
        self.crossings += int(np.count_nonzero(np.signbit(x[1:]) != np.signbit(x[:-1])))
        self.tail = (self.tail + pcm)[-PAD:]

    def row(self) -> tuple:
        feature = f"sum={self.total};energy={self.energy};crossings={self.crossings};blocks={self.blocks}"
        return self.n, self.whole.hexdigest(), zlib.crc32(self.tail), len(self.media), hashlib.sha256(self.media).hexdigest(), feature, self.blocks


def features(media: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, FEATURES) from the stored bytes alone: digests, and sums over the decoded blocks as text."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        names = [c.split()[0] for c in FEATURES.split(", ")]
        kinds = [pa.string() if c.endswith("string") else pa.int64() for c in FEATURES.split(", ")]
        streams = batch.column(2).to_pylist()
        found = [Summary(s) for s in streams]
        for i, _, pcm in decode_all(streams):
            found[i].add(pcm)
        rows = list(zip(*(f.row() for f in found)))
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(r, k) for r, k in zip(rows, kinds))], names=["doc_id", "n_bytes", *names])

    return media.select("doc_id", "n_bytes", "media").mapInArrow(batches(kernel), f"doc_id long, n_bytes long, {FEATURES}")
