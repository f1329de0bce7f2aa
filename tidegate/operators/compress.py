"""Half-precision packing of parameters and pushes. Spark has no half type: two bytes a value, little-endian."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column
from pyspark.sql import functions as F


def to_half(x: np.ndarray) -> bytes:
    """Values beyond the format's range become its largest."""
    return np.clip(x, -65504, 65504).astype("<f2").tobytes()


def from_half(b: bytes) -> np.ndarray:
    return np.frombuffer(b, "<f2").astype(np.float32)


def _cuts(lengths: pa.Array) -> np.ndarray:
    return np.concatenate(([0], np.cumsum(pc.fill_null(lengths, 0).to_numpy(zero_copy_only=False).astype(np.int64))))


def pack_half(c: Column) -> Column:
    """binary of an array of numbers; null stays null."""

    @F.arrow_udf("binary")
    def run(column: pa.Array) -> pa.Array:
        flat = column.flatten().cast(pa.float64()).to_numpy(zero_copy_only=False)
        cuts = (2 * _cuts(pc.list_value_length(column))).astype(np.int32)
        packed = pa.Array.from_buffers(pa.binary(), len(column), [None, pa.py_buffer(cuts.tobytes()), pa.py_buffer(to_half(flat))])
        return pc.if_else(pc.is_valid(column), packed, pa.scalar(None, pa.binary()))

    return run(c)


def unpack_half(c: Column) -> Column:
    """array of numbers of a binary; null stays null."""

    @F.arrow_udf("array<float>")
    def run(column: pa.Array) -> pa.Array:
        flat = from_half(b"".join(x for x in column.to_pylist() if x))
        cuts = _cuts(pc.binary_length(column)) // 2
        ends = pa.array([None if not ok else int(a) for ok, a in zip(column.is_valid().to_pylist(), cuts, strict=False)] + [int(cuts[-1])], pa.int32()) if column.null_count else pa.array(cuts.astype(np.int32))
        return pa.ListArray.from_arrays(ends, pa.array(flat, pa.float32()))

    return run(c)


EXPONENT, LEAST, LARGEST = np.int64(0x7FF << 52), np.int64(1009 << 52), np.int64(1038 << 52)  # bits of a double's exponent, of 2**-14 and of 2**15


def halved(x: np.ndarray) -> np.ndarray:
    """from_half(to_half(x)) of doubles, to the bit but for a zero's sign: a number 2**42 times as large, of which x is a few last places, is
    added and taken off. That takes a fraction of the time of numpy's own conversion."""
    large = x.view(np.int64) & EXPONENT
    if large.size and large.max() >= LARGEST:
        x = np.clip(x, -65504.0, 65504.0)
        large = x.view(np.int64) & EXPONENT
    large = np.maximum(large, LEAST, out=large).view(np.float64)  # what is less than LEAST has its last place
    large *= 1.5 * 2.0**42
    near = x + large
    near -= large
    return near


def carried(x: np.ndarray, precision: str) -> np.ndarray:
    """What arrives when a vector, or several, are sent in this precision."""
    if precision == "fp32":
        return x
    return halved(x) if x.dtype == np.float64 else from_half(to_half(x)).astype(x.dtype).reshape(x.shape)
