"""Bit packing of codes and refinement bits: one binary value per vector."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def pack(codes: np.ndarray, bits: int) -> np.ndarray:
    """n x d codes to n x ceil(d * bits / 8) bytes, high bit first."""
    n, d = codes.shape
    each = (codes[:, :, None].astype(np.uint8) >> np.arange(bits - 1, -1, -1, dtype=np.uint8)) & 1
    return np.packbits(each.reshape(n, d * bits), axis=1)


def unpack(packed: np.ndarray, bits: int, d: int) -> np.ndarray:
    each = np.unpackbits(packed, axis=1, count=d * bits).reshape(len(packed), d, bits)
    return (each << np.arange(bits - 1, -1, -1, dtype=np.uint8)).sum(axis=2, dtype=np.uint8)


def to_binary(m: np.ndarray) -> pa.Array:
    """Rows of bytes as a binary column, without a Python object per row."""
    n, w = m.shape
    data = np.ascontiguousarray(m)
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(np.arange(0, n * w + 1, max(w, 1), dtype=np.int32)[: n + 1].tobytes()), pa.py_buffer(data.tobytes())])


def from_binary(column: pa.Array | pa.ChunkedArray, width: int) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(len(column), width)


def half_bits(x: np.ndarray) -> np.ndarray:
    """Half-precision floats as 16-bit integers, for Spark's SHORT."""
    return x.astype(np.float16).view(np.int16)


def from_half(x: np.ndarray) -> np.ndarray:
    return x.astype(np.int16).view(np.float16).astype(np.float64)
