"""Bit packing in NumPy and the block arithmetic shared by Spark and SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F


def block_size(n: int, p: int) -> int:
    return -(-n // p) if n else 1


def block_of(vid, size: int):
    return F.floor(F.col(vid) / F.lit(size)).cast("long") if isinstance(vid, str) else F.floor(vid / F.lit(size)).cast("long")


def slot_of(vid, size: int):
    return F.pmod(F.col(vid) if isinstance(vid, str) else vid, F.lit(size)).cast("long")


def bits_of_block(n: int, size: int, block):
    """Slots of a block; the last one may be short."""
    return F.least(F.lit(size).cast("long"), F.lit(n).cast("long") - block * size)


def to_bits(slots: np.ndarray, n_bits: int) -> np.ndarray:
    out = np.zeros(n_bits, dtype=bool)
    out[slots] = True
    return out


def pack_bitmap(slots: np.ndarray, n_bits: int) -> bytes:
    """Slot 0 is the most significant bit of byte 0."""
    return np.packbits(to_bits(slots, n_bits)).tobytes()


def unpack_bitmap(payload: bytes, n_bits: int) -> np.ndarray:
    return np.flatnonzero(np.unpackbits(np.frombuffer(payload, dtype=np.uint8), count=n_bits))
