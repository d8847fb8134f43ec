"""Arrow columns as numpy arrays and back."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa


def matrix(column: pa.Array, dtype=np.float64) -> np.ndarray:
    """A list column of equal lengths as rows x J; no copy where the type is the same."""
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    if n == 0:
        return np.zeros((0, 0), dtype)
    if flat.size % n or (pa.compute.list_value_length(column).to_numpy(zero_copy_only=False) != flat.size // n).any():
        raise ValueError("vectors differ in length; load them through sources.vectors.load")
    return flat.reshape(n, -1).astype(dtype, copy=False)


def stacked(column: pa.ChunkedArray, order: np.ndarray, dtype=np.float64) -> np.ndarray:
    """A list column of equal lengths as rows x J in the given order, chunk by chunk: no second copy is made."""
    parts = [matrix(part, dtype) for part in column.chunks if len(part)]
    if len({part.shape[1] for part in parts}) > 1:
        raise ValueError("vectors differ in length; load them through sources.vectors.load")
    out = np.empty((len(order), parts[0].shape[1] if parts else 0), dtype)
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    at = 0
    for part in parts:
        out[place[at : at + len(part)]] = part
        at += len(part)
    return out


def lists(x: np.ndarray) -> pa.ListArray:
    x = np.ascontiguousarray(x)
    return pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1] or 1, dtype=np.int32)[: len(x) + 1]), pa.array(x.reshape(-1)))


def binary(x: np.ndarray) -> pa.Array:
    """Rows of bytes as a binary column."""
    x = np.ascontiguousarray(x, np.uint8)
    offsets = np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)
    return pa.BinaryArray.from_buffers(pa.binary(), len(x), [None, pa.py_buffer(offsets), pa.py_buffer(x)])


def bytes_of(column: pa.Array) -> np.ndarray:
    """A binary column of equal lengths as rows x bytes, without a copy."""
    n = len(column)
    if n == 0:
        return np.zeros((0, 0), np.uint8)
    offsets = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + n + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8)[offsets[0] : offsets[-1]]
    return data.reshape(n, -1)


def squeezed(x: np.ndarray) -> tuple[tuple[int, ...], str, bytes]:
    """Rows x J for the way, without loss: column by column, as many entries of a column are often equal."""
    return x.shape, x.dtype.str, zlib.compress(np.ascontiguousarray(x.T), 1)


def restored(sent: tuple[tuple[int, ...], str, bytes]) -> np.ndarray:
    """What `squeezed` was given."""
    shape, kind, data = sent
    return np.ascontiguousarray(np.frombuffer(zlib.decompress(data), kind).reshape(shape[::-1]).T)
