"""Block codecs: patched frame-of-reference blocks in numpy, their sizes as expressions, variable bytes and Rice codes.

A block: header (values as 2 bytes, width, exceptions), the low bits of all values, slots of exceptions (1 byte each),
exceptions whole (4 bytes each); every part is padded to 4 bytes. The width is the least that leaves at most a tenth of
the values as exceptions.
"""

from __future__ import annotations

import struct

import numpy as np
from pyspark.sql import Column, functions as F


def bit_lengths(v: np.ndarray) -> np.ndarray:
    return np.ceil(np.log2(v.astype(np.float64) + 1)).astype(np.int64)


def pfor_encode(values: np.ndarray) -> bytes:
    v = np.asarray(values, np.uint32)
    n = len(v)
    if not 0 < n <= 256:
        raise ValueError("a block holds 1 to 256 values")
    lengths = bit_lengths(v)
    width = int(np.sort(lengths)[::-1][n // 10])
    odd = np.flatnonzero(lengths > width)
    low = (v & np.uint32((1 << width) - 1)).astype(np.uint64)
    bits = ((low[:, None] >> np.arange(width, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8).reshape(-1)
    packed = np.packbits(bits, bitorder="little").tobytes()
    pad = lambda b: b + bytes(-len(b) % 4)
    return struct.pack("<HBB", n, width, len(odd)) + pad(packed) + pad(odd.astype(np.uint8).tobytes()) + v[odd].astype("<u4").tobytes()


def pfor_decode(block: bytes) -> np.ndarray:
    n, width, odd = struct.unpack_from("<HBB", block)
    size = 4 * (-(-n * width // 32))
    if width:
        bits = np.unpackbits(np.frombuffer(block, np.uint8, size, 4), bitorder="little")[: n * width].reshape(n, width)
        out = bits.astype(np.int64) @ (np.int64(1) << np.arange(width, dtype=np.int64))
    else:
        out = np.zeros(n, np.int64)
    if odd:
        at = 4 + size
        slots = np.frombuffer(block, np.uint8, odd, at)
        out[slots] = np.frombuffer(block, "<u4", odd, at + 4 * (-(-odd // 4)))
    return out


def _starts(sizes: np.ndarray) -> np.ndarray:
    return np.cumsum(sizes) - sizes


def pfor_shapes(values: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, ...]:
    """Of many blocks at once, whose values lie one after the other: (width, exceptions, bytes) of each block, and the
    block and whether it is an exception of each value."""
    owner = np.repeat(np.arange(len(sizes)), sizes)
    lengths = bit_lengths(values)
    ranked = lengths[np.lexsort((-lengths, owner))]
    width = ranked[_starts(sizes) + sizes // 10]
    far = lengths > width[owner]
    odd = np.bincount(owner[far], minlength=len(sizes))
    return width, odd, 4 + 4 * -(-sizes * width // 32) + 4 * -(-odd // 4) + 4 * odd, owner, far


def pfor_encode_many(values: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of many blocks, the same bytes as `pfor_encode` gives for each."""
    v, n = np.asarray(values, np.uint32), np.asarray(sizes, np.int64)
    if not len(n):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if n.min() < 1 or n.max() > 256:
        raise ValueError("a block holds 1 to 256 values")
    width, odd, size, owner, far = pfor_shapes(v, n)
    offsets = np.concatenate([[0], np.cumsum(size)])
    at, place = offsets[:-1], np.arange(len(v)) - _starts(n)[owner]
    bits = np.zeros(int(offsets[-1]) * 8, np.uint8)
    first, wide = (at[owner] + 4) * 8 + place * width[owner], width[owner]
    for j in range(int(width.max())):
        there = np.flatnonzero(wide > j)
        bits[first[there] + j] = (v[there] >> np.uint32(j)) & np.uint32(1)
    out = np.packbits(bits, bitorder="little")
    out[at], out[at + 1], out[at + 2], out[at + 3] = n & 255, n >> 8, width, odd
    odds = np.flatnonzero(far)
    block = owner[odds]
    k = np.arange(len(odds)) - _starts(odd)[block]
    slots = at[block] + 4 + 4 * -(-n[block] * width[block] // 32)
    out[slots + k] = place[odds]
    whole = slots + 4 * -(-odd[block] // 4) + 4 * k
    for j in range(4):
        out[whole + j] = (v[odds] >> np.uint32(8 * j)) & np.uint32(255)
    return out, offsets


def pfor_decode_many(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(values, sizes) of the blocks of `pfor_encode` that begin at these places of a byte array."""
    at = np.asarray(at, np.int64)
    if not len(at):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    head = data[at[:, None] + np.arange(4)].astype(np.int64)
    n, width, odd = head[:, 0] | head[:, 1] << 8, head[:, 2], head[:, 3]
    owner = np.repeat(np.arange(len(n)), n)
    first = (at[owner] + 4) * 8 + (np.arange(len(owner)) - _starts(n)[owner]) * width[owner]
    place, out, end = first >> 3, np.zeros(len(owner), np.int64), len(data) - 1
    for j in range((int(width.max()) + 14) // 8):  # the bytes that a value can lie in
        out |= data[np.minimum(place + j, end)].astype(np.int64) << 8 * j
    out = (out >> (first & 7)) & ((np.int64(1) << width) - 1)[owner]
    block = np.repeat(np.arange(len(n)), odd)
    k = np.arange(len(block)) - _starts(odd)[block]
    slots = at[block] + 4 + 4 * -(-n[block] * width[block] // 32)
    whole = slots + 4 * -(-odd[block] // 4) + 4 * k
    out[_starts(n)[block] + data[slots + k]] = sum(data[whole + j].astype(np.int64) << 8 * j for j in range(4))
    return out, n


def vbyte_encode(values: np.ndarray) -> bytes:
    """Seven bits a byte, the lowest first; the last byte of a value has its top bit set."""
    v = np.asarray(values, np.int64)
    n = np.ones(len(v), np.int64)
    for bits in range(7, 63, 7):
        longer = v >= 1 << bits
        if not longer.any():
            break
        n += longer
    last = np.cumsum(n) - 1
    out = np.zeros(int(n.sum()), np.uint8)
    for j in range(int(n.max()) if len(n) else 0):
        there = slice(None) if j == 0 else np.flatnonzero(n > j)
        out[(last - n + 1)[there] + j] = (v[there] >> 7 * j) & 127
    out[last] |= 128
    return out.tobytes()


def vbyte_decode(data: bytes) -> np.ndarray:
    b = np.frombuffer(data, np.uint8)
    last = np.flatnonzero(b & 128)
    if not len(last):
        return np.zeros(0, np.int64)
    first = np.concatenate([[0], last[:-1] + 1])
    out, n = (b[first] & 127).astype(np.int64), last - first
    for j in range(1, int(n.max()) + 1):
        there = np.flatnonzero(n >= j)
        out[there] |= (b[first[there] + j] & 127).astype(np.int64) << 7 * j
    return out


def rice_parameter(values: np.ndarray) -> int:
    return max(0, int(np.sum(values)) // max(1, len(values))).bit_length() - 1 if np.sum(values) >= len(values) else 0


def rice_encode(values: np.ndarray, k: int) -> bytes:
    bits = []
    for v in np.asarray(values, np.int64).tolist():
        bits += [1] * (v >> k) + [0] + [(v >> i) & 1 for i in range(k)]
    return np.packbits(np.array(bits, np.uint8)).tobytes()


def rice_decode(data: bytes, n: int, k: int) -> np.ndarray:
    bits, at, out = np.unpackbits(np.frombuffer(data, np.uint8)).tolist(), 0, []
    for _ in range(n):
        q = 0
        while bits[at]:
            q, at = q + 1, at + 1
        at += 1
        out.append((q << k) | sum(bits[at + i] << i for i in range(k)))
        at += k
    return np.array(out, np.int64)


# ---------------------------------------------------------------- sizes as expressions


def bit_length(v: Column) -> Column:
    return F.when(v > 0, F.length(F.bin(v))).otherwise(0)


def block_shape(values: Column) -> Column:
    """(n_values, width, exceptions, n_bytes) of an array's block."""
    lengths = F.sort_array(F.transform(values, bit_length), asc=False)
    n = F.size(values)
    width = F.get(lengths, F.floor(n / F.lit(10)).cast("int"))
    odd = F.size(F.filter(lengths, lambda x: x > width))
    size = 4 + 4 * F.ceil(n * width / F.lit(32)) + 4 * F.ceil(odd / F.lit(4)) + 4 * odd
    return F.struct(n.cast("long").alias("n_values"), width.cast("long").alias("width"), odd.cast("long").alias("exceptions"), size.cast("long").alias("n_bytes"))


def pfor_size(values: Column) -> Column:
    return block_shape(values)["n_bytes"]


def vbyte_size(v: Column) -> Column:
    """Bytes of one value, 7 bits each."""
    return F.greatest(F.lit(1), F.ceil(bit_length(v) / F.lit(7))).cast("long")


def in_blocks(values: Column, block: int) -> Column:
    """The array cut into blocks; none for an empty array."""
    count = F.ceil(F.size(values) / F.lit(block)).cast("int")
    return F.transform(F.filter(F.sequence(F.lit(0), F.greatest(count, F.lit(1)) - 1), lambda i: i < count), lambda i: F.slice(values, i * block + 1, F.lit(block)))
