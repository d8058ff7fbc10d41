"""Matrices as Arrow columns without copying, and the naive way for comparison."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def vectors_to_arrow(matrix: np.ndarray, layout: str = "list") -> pa.Array:
    """One column over the matrix's own buffer. ``list`` is what the JVM takes; ``fixed`` is for files;
    ``binary`` holds each row's bytes."""
    matrix = np.ascontiguousarray(matrix, np.float32)
    n, dim = matrix.shape
    if layout == "binary":
        return pa.FixedSizeBinaryArray.from_buffers(pa.binary(4 * dim), n, [None, pa.py_buffer(matrix)])
    flat = pa.Array.from_buffers(pa.float32(), n * dim, [None, pa.py_buffer(matrix)])
    if layout == "fixed":
        return pa.FixedSizeListArray.from_arrays(flat, dim)
    if n * dim >= 2**31:
        raise ValueError("too many values for 32-bit offsets; slice the matrix")
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * dim + 1, dim, dtype=np.int32) if n else np.zeros(1, np.int32)), flat)


def vectors_to_arrow_naive(matrix: np.ndarray) -> pa.Array:
    """Through Python floats: the ablation."""
    return pa.array(matrix.tolist(), pa.list_(pa.float32()))


def naive_bytes(n: int, dim: int) -> int:
    """Python objects that the naive way makes: a float and a pointer to it for each value."""
    return n * dim * 32
