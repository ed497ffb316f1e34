"""Vectors as arrays of doubles: what takes part, and exact cosines."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def usable(v: Column) -> Column:
    """Not null, no null or non-finite component, not all zero."""
    x = lambda c: c.cast("double")
    ok = lambda c: c.isNotNull() & ~F.isnan(x(c)) & (F.abs(x(c)) < float("inf"))
    return F.coalesce(v.isNotNull() & F.forall(v, ok) & F.exists(v, lambda c: F.coalesce(x(c) != 0, F.lit(False))), F.lit(False))


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    """Rows of a list column whose lists all have ``dim`` numbers."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def cosines(x: np.ndarray, norms: np.ndarray, q: np.ndarray, qn: float) -> np.ndarray:
    """Cosines of the rows of x with q; equal rows give equal results wherever they stand."""
    return (x * q).sum(axis=1) / (norms * qn)


def scaled(x: np.ndarray) -> np.ndarray:
    """Rows divided by a power of two near their largest component, so that no square over- or underflows. That changes no digit of a
    component, so cosines are those of the rows as given."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, keepdims=True))[1])
