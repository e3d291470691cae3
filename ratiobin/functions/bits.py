"""Bit packing of index arrays of 1 to 16 bits, most significant bit first, blocks padded with zero bits to a byte."""

from __future__ import annotations

import numpy as np


def pack_bits(idx: np.ndarray, bits: int) -> bytes:
    """The low `bits` bits of each index, one after the other."""
    if not len(idx):
        return b""
    wide = np.asarray(idx, dtype=">u2").view(np.uint8).reshape(-1, 2)
    return np.packbits(np.unpackbits(wide, axis=1)[:, 16 - bits :].ravel()).tobytes()


def unpack_bits(data: bytes, bits: int, n: int) -> np.ndarray:
    flat = np.unpackbits(np.frombuffer(data, dtype=np.uint8))[: n * bits].reshape(n, bits)
    wide = np.zeros((n, 16), dtype=np.uint8)
    wide[:, 16 - bits :] = flat
    return np.packbits(wide, axis=1).view(">u2").ravel().astype(np.int64)


def indices_per_block(block_bytes: int, bits: int, round_block: bool = False) -> int:
    """Indices that fit a block; rounded down to 8192 where blocks must not depend on the index length's parity."""
    n = block_bytes * 8 // bits
    return max(n // 8192 * 8192, 8192) if round_block else n
