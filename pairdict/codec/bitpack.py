"""Entry numbers of any width as one stream of bits, lowest bit first."""

from __future__ import annotations

import numpy as np


def pack_bits(ids: np.ndarray, bits: int) -> bytes:
    if not 1 <= bits <= 32:
        raise ValueError("1 to 32 bits")
    raw = np.ascontiguousarray(ids, dtype="<u4")
    if len(raw) and int(raw.max()) >> bits:
        raise ValueError("a number needs more bits")
    spread = np.unpackbits(raw.view(np.uint8).reshape(-1, 4), axis=1, bitorder="little")[:, :bits]
    return np.packbits(spread.ravel(), bitorder="little").tobytes()


def unpack_bits(raw: bytes, bits: int, n: int) -> np.ndarray:
    flat = np.unpackbits(np.frombuffer(raw, np.uint8), count=n * bits, bitorder="little").reshape(n, bits)
    wide = np.zeros((n, 32), np.uint8)
    wide[:, :bits] = flat
    return np.packbits(wide, axis=1, bitorder="little").view("<u4").ravel()
