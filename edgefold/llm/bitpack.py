"""Fixed-width bit packing of non-negative integers, vectorised; eight values fill exactly `bits` bytes."""

from __future__ import annotations

import numpy as np


def width(size: int) -> int:
    """Bits that every id below `size` fits into."""
    return max(1, (size - 1).bit_length())


def pack(values: np.ndarray, bits: int) -> bytes:
    """Little-endian bit stream of `values`; the last group of eight is filled with zeros."""
    n = len(values)
    lanes = np.zeros((-(-n // 8), 8), dtype=np.uint64)
    lanes.reshape(-1)[:n] = values
    out = np.zeros((len(lanes), bits), dtype=np.uint8)
    for lane in range(8):
        first = lane * bits
        for byte in range(first // 8, (first + bits - 1) // 8 + 1):
            shift = byte * 8 - first
            part = lanes[:, lane] >> np.uint64(shift) if shift >= 0 else lanes[:, lane] << np.uint64(-shift)
            out[:, byte] |= part.astype(np.uint8)
    return out.tobytes()


def unpack(packed: bytes, bits: int, start: int, count: int) -> np.ndarray:
    """`count` values from the one at `start` on, without reading what lies outside their groups."""
    low, high = start // 8, -(-(start + count) // 8)
    raw = np.frombuffer(packed, dtype=np.uint8, count=(high - low) * bits, offset=low * bits).reshape(-1, bits)
    out = np.zeros((high - low, 8), dtype=np.uint64)
    for lane in range(8):
        first = lane * bits
        for byte in range(first // 8, (first + bits - 1) // 8 + 1):
            shift = byte * 8 - first
            part = raw[:, byte].astype(np.uint64)
            out[:, lane] |= part << np.uint64(shift) if shift >= 0 else part >> np.uint64(-shift)
    out &= np.uint64((1 << bits) - 1)
    return out.reshape(-1)[start - low * 8 : start - low * 8 + count].astype(np.uint32)
