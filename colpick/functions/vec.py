"""Vector expressions over array columns, and the same over Arrow batches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm_sq(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x)


def hadamard(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def axpy(s: Column, a: Column, b: Column) -> Column:
    """s * a + b."""
    return F.zip_with(a, b, lambda x, y: s * x + y)


def stack(column: pa.Array) -> np.ndarray:
    """n x m matrix of a list column whose lists are equally long."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def unstack(x: np.ndarray) -> pa.Array:
    """List column of the rows of a matrix."""
    x = np.ascontiguousarray(x, dtype=np.float64)
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * (x.shape[1] if x.ndim > 1 else 1)), pa.array(x.ravel()))
