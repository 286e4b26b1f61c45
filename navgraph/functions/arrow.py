"""Functions over Arrow batches, for what Column expressions do element by element."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def _rows(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


@F.arrow_udf(DoubleType())
def l2_batch(a: pa.Array, b: pa.Array) -> pa.Array:
    """Distance of two vectors of one length, a batch at a time; null if either is null."""
    good = np.asarray(a.is_valid()) & np.asarray(b.is_valid())
    out = np.full(len(a), np.nan)
    if good.any():
        x, y = (_rows(c.filter(pa.array(good))) for c in (a, b))
        out[good] = np.sqrt(((x - y) ** 2).sum(1))
    return pa.array(out, mask=~good)


@F.arrow_udf(DoubleType())
def recall_at_k(true: pa.Array, found: pa.Array) -> float:
    """Aggregate: the mean share of the true neighbours (arrays) that are among those found (arrays; null: none)."""
    shares = [len(set(t) & set(f or ())) / len(set(t)) for t, f in zip(true.to_pylist(), found.to_pylist(), strict=True) if t]
    return float(np.mean(shares)) if shares else 0.0
