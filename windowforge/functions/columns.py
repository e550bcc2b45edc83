"""Arrow columns of vectors as matrices and back, without a Python object for each number."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def matrix(column: pa.Array) -> np.ndarray:
    """A column of lists of one length as a matrix of its own type; a missing number is NaN."""
    if not len(column):
        return np.zeros((0, 0))
    sizes = column.value_lengths().to_numpy(zero_copy_only=False)
    if column.null_count or (sizes != sizes[0]).any():
        raise ValueError("a vector is null or has another length than the others")
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def lists(x: np.ndarray) -> pa.Array:
    """The rows of a matrix as a column of lists."""
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * (x.shape[1] if x.ndim == 2 else 0), pa.int32()), pa.array(np.ascontiguousarray(x).ravel()))


def batch(**columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in columns.values()], names=list(columns))
